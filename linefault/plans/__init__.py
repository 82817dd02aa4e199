"""Detector, typer, experiments and the query registry."""

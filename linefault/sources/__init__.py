"""Readers, writers and adapters that give the given tables the canonical shapes."""

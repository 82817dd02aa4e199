"""Feature names: metric-model-parameter, where the model may itself hold hyphens."""

from __future__ import annotations

import re
from typing import NamedTuple

MODELS = ("avg", "wma", "ewma", "wma-diff", "var")


class Feature(NamedTuple):
    metric: str
    model: str
    param: int  # days; for ewma, tenths of lambda

    @property
    def name(self) -> str:
        return f"{self.metric}-{self.model}-{self.param}"

    @property
    def column(self) -> str:
        return self.name.replace("-", "_")


def parse_feature(name: str) -> Feature:
    found = re.fullmatch(r"(.+?)-(avg|wma-diff|wma|ewma|var)-(\d+)", name)
    if not found:
        raise ValueError(f"not a feature name: {name}")
    return Feature(found[1], found[2], int(found[3]))


def feature_grid(metrics, days=range(1, 8), tenths=range(1, 10)) -> list[Feature]:
    """All features of the metrics: four windowed models for each day count and one for each lambda."""
    return [Feature(m, model, p) for m in metrics for model in MODELS for p in (tenths if model == "ewma" else days)]

"""Parameters of a model and how they are set when the user gives none."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace


@dataclass(frozen=True)
class ModelConfig:
    """w: page height; r_impute, r_forecast: kept ranks (None: by ``rank_rule``);
    least: observations before a model is built; capacity: observations of one
    sub-model; growth: factor between full retrains; average: sub-models whose
    weights are averaged for forecasts; fill: 'zero' or 'inverse_rate'."""

    w: int | None = None
    r_impute: int | None = None
    r_forecast: int | None = None
    least: int = 100
    capacity: int = 2_500_000
    growth: float = 0.5
    average: int = 10
    rank_rule: str = "threshold"
    energy: float = 0.9
    fill: str = "zero"
    standardize: bool = False
    backend: str = "gram"
    schedule: str = "half_window"

    def __post_init__(self):
        if self.w is not None and self.w < 2:
            raise ValueError("a page needs at least two rows")
        if not 0 < self.growth <= 1:
            raise ValueError("growth lies in (0, 1]")
        if self.least < 1 or self.capacity < 2 * self.least:
            raise ValueError("capacity holds at least twice the least count")
        if self.rank_rule not in ("threshold", "energy"):
            raise ValueError(f"unknown rank rule {self.rank_rule}")


def page_height(n_series: int, steps: int, capacity: int) -> int:
    """Height of the page matrix: with ten times as many columns as rows, but
    never more rows than columns."""
    cells = min(n_series * steps, capacity)
    w = max(2, math.isqrt(max(0, cells // 10)))
    while w > 2 and w > n_series * (steps // w):
        w -= 1
    return w


def settle(config: ModelConfig, n_series: int, steps: int) -> ModelConfig:
    if config.w is None:
        config = replace(config, w=page_height(n_series, steps, config.capacity))
    return config


def half_window(config: ModelConfig, n_series: int) -> int:
    """Steps in half a sub-model: a whole number of pages, at least one."""
    return max(1, config.capacity // (2 * n_series) // config.w) * config.w

"""The synthesizer with one part taken out, and the non-private reference."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from ..functions import rng
from .grid import Grid
from .models import fit, fit_exact
from .synthesis import synthesize


def full(spark: SparkSession, trips: DataFrame, grid: Grid, eps: float, n: int, seed: int | None = None, **options) -> DataFrame:
    return synthesize(spark, fit(trips, grid, eps, seed=seed, **options), n, rng.public(seed))


def no_endpoints(spark: SparkSession, trips: DataFrame, grid: Grid, eps: float, n: int, seed: int | None = None, **options) -> DataFrame:
    """No virtual cells: an even start, and a stop only at the drawn length. The freed budget goes to the moves."""
    model = fit(trips, grid, eps, seed=seed, endpoints=False, **options)
    return synthesize(spark, replace(model, begin=np.full(grid.cells, 1 / grid.cells)), n, rng.public(seed), reweight=False)


def pooled_transitions(spark: SparkSession, trips: DataFrame, grid: Grid, eps: float, n: int, seed: int | None = None, **options) -> DataFrame:
    """Begins, moves and ends are one domain; each report perturbs all of it."""
    return synthesize(spark, fit(trips, grid, eps, seed=seed, scheme="pooled", pooled=True, **options), n, rng.public(seed))


def no_reweight(spark: SparkSession, trips: DataFrame, grid: Grid, eps: float, n: int, seed: int | None = None, **options) -> DataFrame:
    """The chance to stop does not grow with the length."""
    return synthesize(spark, fit(trips, grid, eps, seed=seed, **options), n, rng.public(seed), reweight=False)


def non_private(spark: SparkSession, trips: DataFrame, grid: Grid, n: int, seed: int = 0) -> DataFrame:
    """True counts: the best that any budget can reach."""
    return synthesize(spark, fit_exact(trips, grid), n, rng.public(seed))


VARIANTS = {"full": full, "no_endpoints": no_endpoints, "pooled_transitions": pooled_transitions, "no_reweight": no_reweight}

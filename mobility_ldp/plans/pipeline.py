"""From points to synthetic trips."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession

from ..functions import rng
from ..operators.grid import Grid, make_grid
from ..operators.models import Model, fit
from ..operators.synthesis import synthesize
from ..operators.trajectory import assemble


@dataclass
class Published:
    grid: Grid
    trips: DataFrame
    model: Model
    synthetic: DataFrame


def publish(points: DataFrame, n: int, eps: float, size: int | None = None, seed: int | None = None, bounds=None, **options) -> Published:
    """Collect, fit and synthesize. The trips are kept in memory and on disk, as the two rounds of reports both read them.

    size: how many trips to make; as many as there are real ones if not given.
    bounds: the public box of the grid. Without it the exact least and greatest coordinates are used, which costs no
    budget and is not private: give one whenever the points are.
    seed: repeats an experiment. Without it the noise of the reports is keyed by a secret of this collection.
    """
    spark: SparkSession = points.sparkSession
    grid = make_grid(points, n, bounds)
    trips = assemble(points, grid).persist(StorageLevel.MEMORY_AND_DISK)
    model = fit(trips, grid, eps, seed=seed, **options)
    return Published(grid, trips, model, synthesize(spark, model, trips.count() if size is None else size, rng.public(seed)))

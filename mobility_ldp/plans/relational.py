"""Questions that users of trips ask, as plain relational plans."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import trajectory
from ..operators.grid import Grid
from ..sources import walks


def od_matrix(trips: DataFrame) -> DataFrame:
    """(first, last, n): trips from cell to cell."""
    return trajectory.endpoints(trips).groupBy("first", "last").agg(F.count("*").alias("n"))


def od_cube(trips: DataFrame, grid: Grid) -> DataFrame:
    """Trips by row of the first and row of the last cell, with all subtotals."""
    e = trajectory.endpoints(trips).select(F.floor(F.col("first") / grid.n).cast("int").alias("r1"), F.floor(F.col("last") / grid.n).cast("int").alias("r2"))
    return e.cube("r1", "r2").agg(F.count("*").alias("n"))


def region_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders and their price by region and nation, with subtotals. Dimensions are tables of fixed size, so Spark broadcasts them."""
    o = walks.table(spark, sf_dir, "orders", "o_custkey", "o_totalprice").join(walks.table(spark, sf_dir, "customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    n, r = walks.table(spark, sf_dir, "nation"), walks.table(spark, sf_dir, "region")
    j = o.join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))
    return j.rollup("r_name", "n_name").agg(F.count("*").alias("n"), F.round(F.sum(F.col("o_totalprice").cast("decimal(18,2)")), 2).cast("double").alias("total"))


def top_targets(trips: DataFrame, k: int = 3) -> DataFrame:
    """(src, dst, n, place): the k most frequent next cells of each cell."""
    t = trajectory.transitions(trips).groupBy("src", "dst").agg(F.count("*").alias("n"))
    return t.withColumn("place", F.row_number().over(Window.partitionBy("src").orderBy(F.col("n").desc(), "dst"))).where(F.col("place") <= k)


def asof_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per purchase, the last click of the same user before it: a union and a running last, no range join."""
    e = walks.table(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("click_id", last).where(F.col("event_type") == "purchase").select("event_id", "user_id", "click_id")


def moving_density(spark: SparkSession, sf_dir: str, days: int = 3) -> DataFrame:
    """Events per day of the year, their running total, and the mean over the last days."""
    e = walks.table(spark, sf_dir, "events", "ts").groupBy(F.dayofyear("ts").alias("day")).agg(F.count("*").alias("n"))
    w = Window.orderBy("day")
    return e.select("day", "n", F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("so_far"), F.round(F.avg("n").over(w.rowsBetween(1 - days, 0)), 6).alias("mean_n"))


def cell_sets(a: DataFrame, b: DataFrame) -> DataFrame:
    """(kind, cell): cells of both sets of trips, and of one alone."""
    x, y = a.select(F.explode("cells").alias("cell")).distinct(), b.select(F.explode("cells").alias("cell")).distinct()
    kind = lambda df, k: df.select(F.lit(k).alias("kind"), "cell")
    return kind(x.intersect(y), "both").unionByName(kind(x.exceptAll(y), "first")).unionByName(kind(y.exceptAll(x), "second"))


def dataset_stats(points: DataFrame) -> DataFrame:
    """(trips, points, mean_points) of a source."""
    out = points.agg(F.count_distinct("traj_id").alias("trips"), F.count("*").alias("points"))
    return out.withColumn("mean_points", F.round(F.col("points") / F.col("trips"), 6))


def mean_interval(points: DataFrame) -> DataFrame:
    """(seconds): mean time between consecutive points of a trip, for sources whose order is a time."""
    t = points.select("traj_id", F.col("ord.ts").cast("timestamp").alias("ts"), F.col("ord.event_id").alias("e"))
    gap = F.unix_micros(F.lead("ts").over(Window.partitionBy("traj_id").orderBy("ts", "e"))) - F.unix_micros("ts")
    return t.select(gap.alias("g")).agg(F.round(F.avg("g") / 1e6, 3).alias("seconds"))

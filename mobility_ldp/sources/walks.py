"""Trips made from the given tables: points (traj_id, ord, x, y), no coordinates being at hand.

The unit of privacy is the trip. Where a person owns several trips (orders of
a customer, days of a user), the guarantee is per trip and adds up over trips.
Each source comes with its DuckDB SQL: (traj_id, k, x, y), k being the order.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import rng


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def order_walk(spark, sf_dir):
    """A trip per order, a point per line."""
    keys = ["l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_quantity", "l_extendedprice"]
    return table(spark, sf_dir, "lineitem", "l_orderkey", *keys).select(F.col("l_orderkey").alias("traj_id"), F.struct(*keys).alias("ord"), F.col("l_quantity").alias("x"), F.col("l_extendedprice").alias("y"))


def customer_walk(spark, sf_dir):
    """A trip per customer, a point per order: total price by day."""
    o = table(spark, sf_dir, "orders", "o_custkey", "o_orderdate", "o_orderkey", "o_totalprice")
    day = F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")).cast("double")
    return o.select(F.col("o_custkey").alias("traj_id"), F.struct("o_orderdate", "o_orderkey").alias("ord"), F.col("o_totalprice").alias("x"), day.alias("y"))


def _event_points(spark, sf_dir, traj):
    e = table(spark, sf_dir, "events", "event_id", "ts", "user_id", "value", "props")
    return e.select(traj.alias("traj_id"), F.struct("ts", "event_id").alias("ord"), F.log(1 + F.col("value")).alias("x"), F.get_json_object("props", "$.k").cast("double").alias("y"))


def userday_walk(spark, sf_dir):
    """A trip per user and day of the year, a point per event."""
    return _event_points(spark, sf_dir, F.col("user_id") * 1000 + F.dayofyear("ts"))


def user_walk(spark, sf_dir):
    """A trip per user: long trips."""
    return _event_points(spark, sf_dir, F.col("user_id"))


def supplier_walk(spark, sf_dir):
    """A trip per supplier, a point per line: few trips, very long."""
    keys = ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_discount"]
    return table(spark, sf_dir, "lineitem", "l_suppkey", *keys).select(F.col("l_suppkey").alias("traj_id"), F.struct(*keys).alias("ord"), F.col("l_quantity").alias("x"), F.col("l_discount").alias("y"))


def sites(spark, sf_dir):
    """Places with a category, from embeddings: (site, x, y, category). Their number is that of the table, which the walks bound by max_sites."""
    e = table(spark, sf_dir, "embeddings", "vec_id", "embedding", "label")
    return e.select(F.col("vec_id").alias("site"), F.col("embedding")[0].cast("double").alias("x"), F.col("embedding")[1].cast("double").alias("y"), F.col("label").alias("category"))


def poi_walk(spark, sf_dir, walkers: int = 2000, steps: int = 12, seed: int = 11, max_sites: int = 434):
    """Walks between places: walker w is at a place drawn by (seed, w, step), more often than not of its favourite category."""
    known = F.broadcast(sites(spark, sf_dir).where(F.col("site") < max_sites).select(F.col("site").cast("int").alias("slot"), "x", "y"))
    n = table(spark, sf_dir, "embeddings", "vec_id").where(F.col("vec_id") < max_sites).count()
    w = spark.range(walkers).withColumnRenamed("id", "traj_id").withColumn("step", F.explode(F.sequence(F.lit(0), F.lit(steps - 1))))
    home = F.floor(rng.u01(seed, F.col("traj_id"), "home", engine="xx") * n)
    away = F.floor(rng.u01(seed, F.col("traj_id"), F.col("step"), engine="xx") * n)
    near = F.pmod(home + F.floor(rng.u01(seed, F.col("traj_id"), F.col("step"), "near", engine="xx") * 9), F.lit(n))
    slot = F.when(rng.u01(seed, F.col("traj_id"), F.col("step"), "which", engine="xx") < 0.7, near).otherwise(away).cast("int")
    return w.withColumn("slot", slot).join(known, "slot").select("traj_id", F.struct("step").alias("ord"), "x", "y")


#: Columns of the lattice of suppliers.
LATTICE = 50


def network_walk(spark, sf_dir):
    """A trip per order over a lattice, a point per line: the node of its supplier, row by row in the order of keys."""
    keys = ["l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_quantity", "l_extendedprice"]
    at = F.col("l_suppkey")
    return table(spark, sf_dir, "lineitem", "l_orderkey", *keys).select(F.col("l_orderkey").alias("traj_id"), F.struct(*keys).alias("ord"), F.pmod(at, F.lit(LATTICE)).cast("double").alias("x"), F.floor(at / LATTICE).cast("double").alias("y"))


WALKS = {"order_walk": order_walk, "customer_walk": customer_walk, "userday_walk": userday_walk, "user_walk": user_walk, "supplier_walk": supplier_walk, "poi_walk": poi_walk, "network_walk": network_walk}

SQL = {
    "order_walk": "SELECT l_orderkey AS traj_id, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, l_quantity, l_extendedprice) AS k, l_quantity AS x, l_extendedprice AS y FROM lineitem",
    "customer_walk": "SELECT o_custkey AS traj_id, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS k, o_totalprice AS x, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS DOUBLE) AS y FROM orders",
    "userday_walk": "SELECT user_id * 1000 + dayofyear(ts) AS traj_id, row_number() OVER (PARTITION BY user_id * 1000 + dayofyear(ts) ORDER BY ts, event_id) AS k, ln(1 + value) AS x, CAST(props->>'$.k' AS DOUBLE) AS y FROM events",
    "user_walk": "SELECT user_id AS traj_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k, ln(1 + value) AS x, CAST(props->>'$.k' AS DOUBLE) AS y FROM events",
    "supplier_walk": "SELECT l_suppkey AS traj_id, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_shipdate, l_orderkey, l_linenumber, l_partkey, l_quantity, l_discount) AS k, l_quantity AS x, l_discount AS y FROM lineitem",
}
#: Beside those of SQL, which have queries of their own for statistics.
MORE_SQL = {
    "network_walk": f"SELECT l_orderkey AS traj_id, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, l_quantity, l_extendedprice) AS k, CAST((l_suppkey % {LATTICE} + {LATTICE}) % {LATTICE} AS DOUBLE) AS x, floor(l_suppkey / {LATTICE}.0) AS y FROM lineitem",
}

"""Points from and to files and streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

POINTS = "traj_id BIGINT, seq BIGINT, x DOUBLE, y DOUBLE"
EVENTS = "event_id BIGINT, ts TIMESTAMP_NTZ, user_id BIGINT, event_type STRING, value DOUBLE, props STRING"


def _points(df: DataFrame) -> DataFrame:
    return df.select("traj_id", F.struct("seq").alias("ord"), "x", "y")


def read_points(spark: SparkSession, path: str, form: str = "parquet", header: bool = True) -> DataFrame:
    """Points with columns traj_id, seq, x, y from Parquet, CSV or JSON; the schema is declared, never guessed."""
    reader = spark.read.schema(POINTS)
    return _points(reader.option("header", header).csv(path) if form == "csv" else reader.format(form).load(path))


def points_from_rows(spark: SparkSession, rows) -> DataFrame:
    """Points from (traj_id, seq, x, y) tuples."""
    return _points(spark.createDataFrame(rows, POINTS))


def event_stream(spark: SparkSession, folder: str, files_per_batch: int = 1) -> DataFrame:
    """Events as a stream of files; ts becomes a TIMESTAMP, since a watermark needs one."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(folder)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def rate_stream(spark: SparkSession, rows_per_second: int = 100) -> DataFrame:
    """Endless points of ten users, for trying things out."""
    raw = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return raw.select((F.col("value") % 10).alias("user_id"), F.col("value").alias("event_id"), F.col("timestamp").alias("ts"), F.sin("value").alias("x"), F.cos("value").alias("y"))


def write_trips(trips: DataFrame, path: str, run: str = "run", mode: str = "append") -> None:
    """Trips as Parquet, a folder for each run."""
    trips.withColumn("run", F.lit(run)).write.mode(mode).partitionBy("run").parquet(path)


def force(df: DataFrame) -> None:
    """Compute all rows and keep none."""
    df.write.format("noop").mode("overwrite").save()

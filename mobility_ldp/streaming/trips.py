"""Trips, densities and reports from a stream of events.

Streams are append-only: a session or window comes out once, when the
watermark passes its end. The registered queries read the events table as a
stream of files until it is used up, write what is closed, and read it back.
State and output live in the shared folder, so a lost executor or a restart
goes on from the last finished batch.
"""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import rng
from ..functions.cells import grid_cell
from ..operators import models, oue, trajectory
from ..operators.grid import Grid
from ..sources.files import EVENTS

GAP, LATE = "6 hours", "1 hour"
#: Public bounds of the events' coordinates (log of 1 + value, and k).
BOUNDS = (0.0, 7.0, 0.0, 99.0)
SIDE = 6


def grid(n: int = SIDE) -> Grid:
    return Grid(n, *BOUNDS)


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or a temporary folder where that is unset and all runs in one machine (tests)."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found and not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    return (found or tempfile.mkdtemp(prefix="checkpoints-")).rstrip("/")


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream, with coordinates. ts is a TIMESTAMP: a watermark takes no other kind."""
    # a pattern, as a stream takes a single file for no folder of its own
    raw = spark.readStream.schema(EVENTS).parquet(f"{sf_dir}/event[s].parquet")
    return located(raw)


def located(raw: DataFrame) -> DataFrame:
    k = F.get_json_object("props", "$.k").cast("double")
    return raw.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", F.log(1 + F.col("value")).alias("x"), k.alias("y"))


def sessions(stream: DataFrame, gap: str = GAP, late: str = LATE) -> DataFrame:
    """(user_id, start, last, points): one trip per user and stretch without a pause of gap."""
    s = stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id")
    out = s.agg(F.sort_array(F.collect_list(F.struct("ts", "event_id", "x", "y"))).alias("points"))
    return out.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("until"), "points")


def session_trips(closed: DataFrame, g: Grid) -> DataFrame:
    """(traj_id, cells, n_cells) of closed sessions."""
    t = closed.select(F.xxhash64("user_id", "start").alias("traj_id"), F.transform("points", lambda p: grid_cell(p["x"], p["y"], g)).alias("c"))
    t = t.select("traj_id", trajectory.collapse(F.col("c")).alias("c")).select("traj_id", trajectory.interpolate(F.col("c"), g.n).alias("cells"))
    return t.withColumn("n_cells", F.size("cells"))


def density(stream: DataFrame, g: Grid, size: str = "1 day", slide: str | None = None, late: str = LATE) -> DataFrame:
    """(start, cell, n): visits per window and cell, tumbling or sliding."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    d = stream.withWatermark("ts", late).withColumn("cell", grid_cell(F.col("x"), F.col("y"), g))
    return d.groupBy(w.alias("w"), "cell").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "cell", "n")


def moves(stream: DataFrame, g: Grid, late: str = LATE, idle: str = "30 days") -> DataFrame:
    """(user_id, src, dst): a row whenever a user's cell changes; each user's last cell is kept until the watermark is an idle time past its last event."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    wait = int(pd.Timedelta(idle).total_seconds() * 1000)

    def step(key, frames, state: GroupState):
        if state.hasTimedOut:
            state.remove()
            return
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        last = state.get[0] if state.exists else None
        src, dst = [], []
        for cell in rows["cell"].tolist():
            if last is not None and cell != last:
                src.append(last)
                dst.append(cell)
            last = cell
        state.update((int(last),))
        state.setTimeoutTimestamp(max(int(rows["ts"].max().timestamp() * 1000), state.getCurrentWatermarkMs()) + wait)
        yield pd.DataFrame({"user_id": [key[0]] * len(src), "src": src, "dst": dst})

    d = stream.withWatermark("ts", late).select("user_id", "ts", "event_id", grid_cell(F.col("x"), F.col("y"), g).alias("cell"))
    return d.groupBy("user_id").applyInPandasWithState(step, "user_id bigint, src int, dst int", "cell int", "append", GroupStateTimeout.EventTimeTimeout)


def paired(starts: DataFrame, ends: DataFrame, within: str = "1 hour", late: str = LATE) -> DataFrame:
    """(start_id, end_id, user_id): ends that follow a start of the same user within a time; both sides' state is bounded by the watermarks."""
    a = starts.withWatermark("ts", late).select(F.col("event_id").alias("start_id"), "user_id", F.col("ts").alias("start_ts"))
    b = ends.withWatermark("ts", late).select(F.col("event_id").alias("end_id"), F.col("user_id").alias("end_user"), F.col("ts").alias("end_ts"))
    on = (F.col("user_id") == F.col("end_user")) & (F.col("end_ts") > F.col("start_ts")) & (F.col("end_ts") <= F.col("start_ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, on).select("start_id", "end_id", "user_id")


def admitted(closed: DataFrame, cap: int = 3) -> DataFrame:
    """A user's first cap sessions, whose reports add up to cap times eps at most (sequential composition).

    closed is a table of sessions, or a stream of them: one that reads what the stream of sessions() has written,
    since a stream cannot keep own state behind an aggregation.
    """
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    if not closed.isStreaming:
        from pyspark.sql import Window

        k = F.row_number().over(Window.partitionBy("user_id").orderBy("start"))
        return closed.withColumn("spent", k).where(F.col("spent") <= cap).select("user_id", "start", "spent")

    def step(key, frames, state: GroupState):
        used = state.get[0] if state.exists else 0
        rows = pd.concat(list(frames)).sort_values("start").head(max(0, cap - used))
        state.update((used + len(rows),))
        yield pd.DataFrame({"user_id": [key[0]] * len(rows), "start": rows["start"], "spent": range(used + 1, used + len(rows) + 1)})

    return closed.select("user_id", "start").groupBy("user_id").applyInPandasWithState(step, "user_id bigint, start timestamp, spent int", "used int", "append", GroupStateTimeout.NoTimeout)


def written(df: DataFrame, name: str) -> str:
    """Run a stream over all that is there; the folder that it has written."""
    spark = df.sparkSession
    base = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    q = df.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    return f"{base}/out"


def drain(df: DataFrame, name: str) -> DataFrame:
    """Run a stream over all that is there, and read back what it has written."""
    return df.sparkSession.read.schema(df.schema).parquet(written(df, name))


def collect_reports(stream: DataFrame, g: Grid, eps: float, l_k: int, seed: int | None = None, max_len: int | None = None) -> DataFrame:
    """Continuous collection: closed sessions are perturbed and counted batch by batch; only sums per batch are stored. Gives (feature, item, ones, n)."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/reports-{uuid.uuid4().hex}"
    max_len = max_len or g.cells
    # one secret for all batches, so that a batch that is run again sends the same reports
    secret = rng.new_secret() if seed is None else None
    each = 0.9 * eps / (l_k + 2)
    features = [
        ("length", models.length_item(max_len), 0, max_len, eps / 10),
        ("intra", models.kept_moves(models.state_items(g), l_k), l_k, g.states, each),
        ("begin", F.col("cells")[0], 0, g.cells, each),
        ("end", F.element_at("cells", -1), 0, g.cells, each),
    ]

    def store(batch: DataFrame, batch_id: int) -> None:
        # a batch that is run again overwrites its own folder
        oue.fused(session_trips(batch, g), features, seed, secret).write.mode("overwrite").parquet(f"{base}/out/batch={batch_id}")

    q = sessions(stream).writeStream.foreachBatch(store).option("checkpointLocation", f"{base}/state").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    sums = spark.read.parquet(f"{base}/out")
    return sums.groupBy("feature", "item").agg(F.sum("ones").alias("ones"), F.sum("n").alias("n"))


# ---- registered queries ----------------------------------------------------------


def _sessions(spark, sf):
    out = drain(sessions(events(spark, sf)), "sessions")
    return out.select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), F.size("points").cast("bigint").alias("n"))


CLOSED = """WITH e AS (SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k FROM e),
g AS (SELECT user_id, k, min(ts) AS start, max(ts) AS last, count(*) AS n FROM s GROUP BY 1, 2),
c AS (SELECT * FROM g WHERE last + INTERVAL 6 HOUR <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events))
"""


def _density(spark, sf, slide=None):
    out = drain(density(events(spark, sf), grid(), slide=slide), "density")
    return out.select(F.date_format("start", "yyyy-MM-dd HH:mm").alias("start"), "cell", "n")


_CELL = f"CAST(greatest(0, least({SIDE - 1}, floor(CAST(props->>'$.k' AS DOUBLE) / 99.0 * {SIDE}))) * {SIDE} + greatest(0, least({SIDE - 1}, floor(ln(1 + value) / 7.0 * {SIDE}))) AS INTEGER)"
DENSITY = f"SELECT strftime(w, '%Y-%m-%d %H:%M') AS start, cell, count(*) AS n FROM (SELECT date_trunc('day', ts) AS w, {_CELL} AS cell FROM events) WHERE w + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) GROUP BY 1, 2"
SLIDING = f"SELECT strftime(w, '%Y-%m-%d %H:%M') AS start, cell, count(*) AS n FROM (SELECT date_trunc('day', ts) - INTERVAL (CASE WHEN extract(hour FROM ts) >= 12 THEN 0 ELSE 12 END) HOUR + INTERVAL (h * 12) HOUR AS w, {_CELL} AS cell, ts FROM events, (SELECT unnest([0, 1]) AS h)) WHERE w <= ts AND ts < w + INTERVAL 1 DAY AND w + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) GROUP BY 1, 2"


def _moves(spark, sf):
    out = drain(moves(events(spark, sf), grid()), "moves")
    return out.groupBy("src", "dst").agg(F.count("*").alias("n"))


MOVES = f"SELECT src, dst, count(*) AS n FROM (SELECT lag(cell) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS src, cell AS dst FROM (SELECT user_id, ts, event_id, {_CELL} AS cell FROM events)) WHERE src <> dst GROUP BY 1, 2"


def _pairs(spark, sf):
    e = events(spark, sf)
    return drain(paired(e.where("event_type = 'click'"), e.where("event_type = 'purchase'")), "pairs")


PAIRS = "SELECT a.event_id AS start_id, b.event_id AS end_id, a.user_id AS user_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR"


def _ledger(spark, sf):
    closed = sessions(events(spark, sf)).select("user_id", "start")
    again = spark.readStream.schema(closed.schema).parquet(written(closed, "closed"))
    out = drain(admitted(again), "ledger")
    return out.groupBy("user_id").agg(F.max("spent").cast("bigint").alias("spent"))


LEDGER = CLOSED + "SELECT user_id, least(count(*), 3) AS spent FROM c GROUP BY 1"


def _reports(spark, sf):
    return collect_reports(events(spark, sf), grid(), 1.0, 6, seed=5)


QUERIES: list[tuple[str, Callable, str | None]] = [
    ("stream_sessions", _sessions, CLOSED + "SELECT user_id, strftime(date_trunc('second', start), '%Y-%m-%d %H:%M:%S') AS start, n FROM c"),
    ("stream_density", _density, DENSITY),
    ("stream_density_sliding", lambda spark, sf: _density(spark, sf, "12 hours"), SLIDING),
    ("stream_moves", _moves, MOVES),
    ("stream_pairs", _pairs, PAIRS),
    ("stream_budget", _ledger, LEDGER),
    ("stream_reports", _reports, None),
]

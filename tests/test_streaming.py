import datetime as dt

from mobility_ldp.sources.files import EVENTS, event_stream
from mobility_ldp.streaming import trips


def write(spark, path, rows):
    spark.createDataFrame(rows, EVENTS).coalesce(1).write.mode("append").parquet(path)


def at(hour, k, user=1):
    t = dt.datetime(2024, 1, 1) + dt.timedelta(hours=hour)
    return (k, t, user, "click", 5.0, f'{{"k": {k % 99}}}')


def test_late_rows_and_restart(spark, tmp_path):
    src, out, state = (str(tmp_path / x) for x in ("src", "out", "state"))

    def run():
        q = trips.sessions(trips.located(event_stream(spark, src))).writeStream.format("parquet").option("path", out).option("checkpointLocation", state).trigger(availableNow=True).start()
        q.awaitTermination()
        return q, sorted((r["user_id"], r["start"].isoformat(), len(r["points"])) for r in spark.read.parquet(out).collect())

    write(spark, src, [at(0, 1), at(1, 2), at(30, 3)])
    q, rows = run()
    assert rows == [(1, "2024-01-01T00:00:00", 2)]
    # a row long before the watermark is dropped; a later one closes the second session
    write(spark, src, [at(2, 4), at(60, 5)])
    q, rows = run()
    assert rows == [(1, "2024-01-01T00:00:00", 2), (1, "2024-01-02T06:00:00", 1)]
    dropped = sum(s["numRowsDroppedByWatermark"] for p in q.recentProgress for s in p["stateOperators"])
    assert dropped >= 1


def test_admission_of_a_table(spark):
    rows = [(1, dt.datetime(2024, 1, d)) for d in range(1, 6)] + [(2, dt.datetime(2024, 1, 1))]
    s = spark.createDataFrame(rows, "user_id bigint, start timestamp")
    got = sorted((r["user_id"], r["spent"]) for r in trips.admitted(s, 3).collect())
    assert got == [(1, 1), (1, 2), (1, 3), (2, 1)]


def test_sources_and_sinks(spark, tmp_path):
    from mobility_ldp.sources import files

    p = files.points_from_rows(spark, [(1, 0, 0.5, 0.5), (1, 1, 1.5, 1.0)])
    flat = p.select("traj_id", "ord.seq", "x", "y")
    for form in ("csv", "json", "parquet"):
        path = str(tmp_path / form)
        (flat.write.option("header", True).csv(path) if form == "csv" else flat.write.format(form).save(path))
        assert sorted(map(str, files.read_points(spark, path, form).collect())) == sorted(map(str, p.collect()))
    files.write_trips(spark.createDataFrame([(1, [1, 2])], "traj_id bigint, cells array<int>"), str(tmp_path / "trips"), "a")
    assert spark.read.parquet(str(tmp_path / "trips")).first()["run"] == "a"
    assert files.rate_stream(spark).isStreaming

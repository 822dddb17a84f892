"""Streams against the batch results, with state and refresh."""

import uuid

import numpy as np
import pytest
from pyspark.sql import functions as F

from joincluster.operators.components import solve
from joincluster.operators.lloyd import point_mixtures, seed_top
from joincluster.plans.messages import Calibration
from joincluster.sources import workloads as wl
from joincluster.streaming import stream

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def events(spark):
    return wl.tables(spark, SF, "events")[0]


@pytest.fixture(scope="module")
def comps(spark):
    q = wl.w_y(spark, SF).only("event_type")
    return solve(q, Calibration(q).marginals(), 3)


def folder(events, path, parts=3):
    events.repartitionByRange(parts, "ts").write.parquet(str(path))
    return str(path)


def name():
    return f"t_{uuid.uuid4().hex}"


def test_daily_marginals(spark, events, tmp_path):
    s = stream.event_stream(spark, folder(events, tmp_path / "in"), "60 days")
    got = stream.run_to_table(stream.stream_marginals(s, "event_type"), name(), "complete", str(tmp_path / "st"))
    want = events.groupBy(F.to_date("ts").alias("d"), "event_type").count()
    assert sorted((r["start"].date(), r["value"], r["w"]) for r in got.collect()) == sorted((r["d"], r["event_type"], r["count"]) for r in want.collect())


def test_deduplication_and_pairs(spark, events, tmp_path):
    twice = events.limit(50).unionByName(events.limit(50))
    s = stream.event_stream(spark, folder(twice, tmp_path / "in", 1), "60 days")
    assert stream.run_to_table(stream.deduplicated(s), name(), "append", str(tmp_path / "a")).count() == 50
    views, buys = (stream.event_stream(spark, str(tmp_path / "in"), "60 days").where(F.col("event_type") == t) for t in ("view", "purchase"))
    got = stream.run_to_table(stream.pairs_within(views, buys, "user_id", "100 hours"), name(), "append", str(tmp_path / "b"))
    x, y = (twice.where(F.col("event_type") == t).select("user_id", "ts") for t in ("view", "purchase"))
    want = x.alias("x").join(y.alias("y"), F.expr("x.user_id = y.user_id and y.ts >= x.ts and y.ts <= x.ts + interval 100 hours")).count()
    assert got.count() == want


def test_grid_of_a_stream(spark, events, comps, tmp_path):
    cust = wl.tables(spark, SF, "customer")[0].select("c_custkey")
    s = stream.event_stream(spark, folder(events, tmp_path / "in"), "60 days")
    got = stream.run_to_table(stream.stream_grid(s, cust, ("user_id", "c_custkey"), comps, {"event_type": "event_type"}), name(), "complete", str(tmp_path / "st"))
    want = events.groupBy(comps["event_type"].encode(F.col("event_type")).alias("c")).count()
    assert sorted(tuple(r) for r in got.collect()) == sorted(tuple(r) for r in want.collect())


def test_user_state(spark, events, comps, tmp_path):
    s = stream.event_stream(spark, folder(events, tmp_path / "in", 2), "60 days")
    got = stream.run_to_table(stream.user_cells(s, comps, "event_type", "event_type"), name(), "update", str(tmp_path / "st"))
    last = got.groupBy("user_id", "comp").agg(F.max("w").alias("w")).agg(F.sum("w")).first()[0]
    assert last == events.count()


def test_refresh_and_drift(spark, events, comps, tmp_path):
    encode = lambda df: df.select(comps["event_type"].encode(F.col("event_type")).alias("c_event_type"))
    cells = encode(events).groupBy("c_event_type").agg(F.count("*").alias("w"))
    target = stream.Refresher(point_mixtures(comps, seed_top(cells, comps, 2)), encode)
    s = stream.event_stream(spark, folder(events, tmp_path / "in", 2), "60 days")
    q = s.writeStream.foreachBatch(target).option("checkpointLocation", str(tmp_path / "st")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert sorted(map(tuple, target.cells.collect())) == sorted(map(tuple, cells.collect()))
    assert target.objective >= 0 and np.allclose(target.centroids.coef[0].sum(1), 1)
    one, two = (spark.createDataFrame([(0.0, a), (1.0, b)], "x double, w long") for a, b in ((1, 1), (1, 3)))
    assert stream.drift(one, two) == pytest.approx(0.25)
    assert sorted(r["w"] for r in stream.merged([cells, cells]).collect()) == sorted(2 * r["w"] for r in cells.collect())


def test_sessions_never_come_to_the_driver(spark, tmp_path, monkeypatch):
    """The query's sessions of all batches, against a gap count; no memory sink holds them."""
    from joincluster import queries

    monkeypatch.setattr(stream, "run_to_table", None)
    got = {r["user_id"]: (r["sessions"], r["n"]) for r in queries.QUERIES["stream_session_counts"](spark, SF).collect()}
    want = {}
    for r in wl.tables(spark, SF, "events")[0].select("user_id", F.col("ts").cast("timestamp").cast("double").alias("t")).orderBy("user_id", "t").collect():
        s, n, last = want.get(r["user_id"], (0, 0, None))
        want[r["user_id"]] = (s + (last is None or r["t"] >= last + 6 * 3600), n + 1, r["t"])
    assert got == {u: v[:2] for u, v in want.items()}


def test_a_stream_without_events_gives_an_empty_table(spark, events, tmp_path):
    events.limit(0).write.parquet(str(tmp_path / "in"))
    counts = lambda t: t.groupBy("user_id").agg(F.count("*").alias("sessions"))
    got = stream.run_to_files(stream.stream_sessions(stream.event_stream(spark, str(tmp_path / "in"))), str(tmp_path / "out"), str(tmp_path / "state"), counts)
    assert got.columns == ["user_id", "sessions"] and got.count() == 0

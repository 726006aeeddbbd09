"""What an iteration moves, sources and sinks, streams."""

import shutil

import numpy as np
import pytest
from pyspark.sql import functions as F

from bundlemv.graph import Graph
from bundlemv.operators import rank, steps
from bundlemv.operators.layout import packed_pairs
from bundlemv.plans import check
from bundlemv.sources import files
from bundlemv.sources import workloads as wl
from bundlemv.streaming import edges as stream


@pytest.fixture
def no_broadcast(spark):
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    yield
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)


def exchanges_per_iteration(g, method, **flags):
    def of(iters):
        *_, last = rank.iterate(g, method, q=64, iters=iters, **flags)
        return check.moved(last.select("id", "rank"))

    two, three = of(2), of(3)
    return {k: three[k] - two[k] for k in three | two if three[k] != two[k]}


def test_exchanges_per_iteration(spark, tiny, no_broadcast):
    g = wl.copurchase(spark, tiny).persist()
    assert exchanges_per_iteration(g, "bundled") == {"ShuffleExchangeExec": 1}
    assert exchanges_per_iteration(g, "bundled", chunk_edges=50) == {"ShuffleExchangeExec": 2}  # sums of chunks, then of blocks
    assert exchanges_per_iteration(g, "bundled_rows") == {"ShuffleExchangeExec": 1}
    assert exchanges_per_iteration(g, "per_edge") == {"ShuffleExchangeExec": 1}
    assert exchanges_per_iteration(g, "per_edge_resend") == {"ShuffleExchangeExec": 1}
    assert exchanges_per_iteration(g, "pull")["BroadcastExchangeExec"] == 1
    assert exchanges_per_iteration(g, "naive")["ShuffleExchangeExec"] >= 2


def test_scans_are_pruned_and_filters_pushed(spark, tiny):
    plan = wl.copurchase(spark, tiny).edges._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<l_orderkey:bigint,l_partkey:bigint>" in plan and "l_extendedprice" not in plan


def test_edge_files(spark, tmp_path):
    g = Graph(spark.createDataFrame([(0, 1, 0.5), (0, 2, 1.0), (3, 0, 2.0)], "src long, dst long, weight double"), 4)
    want = sorted(map(tuple, g.edges.collect()))
    for fmt, sep in (("csv", ","), ("tsv", "\t"), ("ssv", " ")):
        g.edges.write.option("sep", sep).option("header", True).csv(f"{tmp_path}/{fmt}")
        assert sorted(map(tuple, files.read_edges(spark, f"{tmp_path}/{fmt}", fmt, weight="weight", header=True).collect())) == want
    for fmt in ("json", "parquet", "orc"):
        g.edges.write.format(fmt).save(f"{tmp_path}/{fmt}")
        assert sorted(map(tuple, files.read_edges(spark, f"{tmp_path}/{fmt}", fmt, weight="weight").collect())) == want
    (tmp_path / "bad.csv").write_text("# note\n1,2\nx,3\n")
    with pytest.raises(Exception, match="x"):
        files.read_edges(spark, f"{tmp_path}/bad.csv").collect()
    files.write_adjacency(g, f"{tmp_path}/adj")
    assert sorted(map(tuple, files.read_adjacency(spark, f"{tmp_path}/adj").collect())) == [x[:2] for x in want]


def test_layout_files(spark, tmp_path):
    g = wl.worked9(spark)
    files.write_layout(g, f"{tmp_path}/l", 3)
    meta, layout, lists = files.open_layout(spark, f"{tmp_path}/l")
    assert (meta["m"], meta["bundles"], meta["k"]) == (10, 6, 3) and layout.count() == lists.count() == 5
    prepared = files.prepared_layout(spark, f"{tmp_path}/l")
    for iters in (1, 4):
        got, want = rank.run(None, prepared=prepared, iters=iters), rank.run(g, q=3, iters=iters)
        assert {r.id: round(r.rank, 12) for r in got.collect()} == {r.id: round(r.rank, 12) for r in want.collect()}
    shutil.rmtree(f"{tmp_path}/l/layout")
    g.spark.createDataFrame([], layout.schema).write.parquet(f"{tmp_path}/l/layout")
    with pytest.raises(ValueError):
        files.open_layout(spark, f"{tmp_path}/l")
    files.write_ranks(rank.run(g, q=3, iters=1), f"{tmp_path}/r")
    assert spark.read.parquet(f"{tmp_path}/r").count() == 9


@pytest.fixture
def event_files(spark, tiny, tmp_path):
    e = spark.read.parquet(f"{tiny}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    days = e.withColumn("d", F.to_date("ts")).orderBy("ts")
    cut = e.agg(F.percentile_approx(F.unix_timestamp("ts"), 0.5)).first()[0]
    for i, part in enumerate((F.unix_timestamp("ts") <= cut, F.unix_timestamp("ts") > cut)):
        days.where(part).drop("d").coalesce(1).write.mode("append").parquet(f"{tmp_path}/events")
    return e, f"{tmp_path}/events"


def finish(df, name, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(120)
    return df.sparkSession.table(name)


def test_streams_equal_batches(spark, event_files):
    batch, path = event_files
    key = lambda df: sorted(map(tuple, df.collect()))
    live = finish(stream.window_counts(stream.read_events(spark, path, 10), late="3650 days"), "w1", "complete")
    got, want = key(live.select("start", "event_type", "events")), key(stream.window_counts(batch).select("start", "event_type", "events"))
    assert got == want
    twice = stream.read_events(spark, path, 10)
    assert finish(stream.without_repeats(twice.union(stream.read_events(spark, path, 10)), "3650 days"), "w2").count() == batch.count()
    slid = stream.window_counts(batch, "2 days", "1 day").agg(F.sum("events")).first()[0]
    assert slid == 2 * batch.count()


def test_late_rows_are_counted(spark, tmp_path):
    times = [["2024-01-10 00:00:00"], ["2024-01-20 00:00:00"], ["2024-01-01 00:00:00", "2024-01-20 01:00:00"]]
    for i, some in enumerate(times):
        rows = [(i * 10 + j, t, 1, "a", 1.0, "{}") for j, t in enumerate(some)]
        spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string, value double, props string").withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.mode("append").parquet(f"{tmp_path}/late")
    q = stream.window_counts(stream.read_events(spark, f"{tmp_path}/late", 1)).writeStream.format("memory").queryName("late1").outputMode("update").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert stream.late_rows(q) == 1


def test_state_follows_users(spark, event_files):
    batch, path = event_files
    live = finish(stream.type_transitions(stream.read_events(spark, path, 10)), "t1")
    users = batch.select("user_id").distinct().count()
    assert live.count() == batch.count() - users


def test_live_ranks(spark, tmp_path):
    rng = np.random.default_rng(1)
    edges = sorted({(int(a), int(b)) for a, b in rng.integers(0, 40, (150, 2))})
    live = stream.LiveRank(spark, 40, 8, f"file://{tmp_path}", iters=20)
    for i in range(3):
        live.append(spark.createDataFrame(edges[i::3], "src long, dst long"))
    g = Graph(spark.createDataFrame(edges, "src long, dst long"), 40)
    rows = lambda df: sorted((r.src_block, r.dst_block, tuple(r.srcs)) for r in df.collect())
    assert rows(live.layout()) == rows(packed_pairs(g, 8).layout) and live.edges().count() == len(edges)
    got = {r.id: r.rank for r in live.ranks.collect()}
    want = {r.id: r.rank for r in rank.run(g, q=8, iters=40).collect()}
    assert max(abs(got[i] - want[i]) for i in want) < 2e-3


def test_every_method_is_named():
    assert {"bundled", "per_edge", "pull", "edge_scan", "naive"} <= set(steps.METHODS)

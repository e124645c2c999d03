"""Keys beyond narrow ids, plans without one-task windows, recursion's counters, streams of several batches."""

import contextlib
import io
import random

import pytest
from pyspark.errors import PySparkException
from pyspark.sql import functions as F

from brute import recursion, rows
from pathframe.operators.recursion import InfiniteWalkError, Log, between, refuse_cycles
from pathframe.sources import catalog, sinks
from pathframe.sources.graph import PropertyGraph, paired, tagged
from pathframe.streaming import edges

KNOWS = [((1, 2), (101,)), ((2, 3), (102,)), ((3, 2), (103,)), ((2, 4), (104,))]


def plan(df) -> str:
    out = io.StringIO()
    with contextlib.redirect_stdout(out):
        df.explain()
    return out.getvalue()


def test_ids_never_meet(spark):
    df = spark.createDataFrame([(0, 2**24 - 1), (1, 0)], "a long, b long")
    assert df.select(paired(7, F.col("a"), F.col("b")).alias("i")).distinct().count() == 2
    for a, b in ((0, 2**24), (2**24, 0), (-1, 0)):
        big = spark.createDataFrame([(a, b)], "a long, b long")
        with pytest.raises(PySparkException):
            big.select(paired(7, F.col("a"), F.col("b"))).collect()
    wide = spark.createDataFrame([(0, 2**24 + 5), (1, 5), (2**47, 3), (2**47, 2**47)], "a long, b long")
    assert wide.select(paired(7, F.col("a"), F.col("b"), True).alias("i")).union(wide.select(tagged(8, F.col("b"), True))).distinct().count() == 8
    with pytest.raises(PySparkException):
        wide.select(tagged(7, F.lit(2**48))).collect()


def test_wide_graphs_hold_the_same_paths(spark):
    folder = "/root/testdata/sf0.001"
    for name in ("logistics", "dialogue", "web"):
        narrow, wide = (catalog.GRAPHS[name](spark, folder, w) for w in (False, True))
        for a, b in ((narrow.edges().df, wide.edges().df), (narrow.nodes().df, wide.nodes().df)):
            assert a.count() == b.count() and a.select("edges").distinct().count() == b.select("edges").distinct().count()
    a, b = (catalog.trade(spark, folder, w).edges().recurse("trail", max_len=3) for w in (False, True))
    assert a.df.groupBy("len").count().orderBy("len").collect() == b.df.groupBy("len").count().orderBy("len").collect()
    from pathframe.operators.conditions import FIRST, label, prop

    g = catalog.logistics(spark, folder, True)
    named = sinks.to_table(g.edges(["LIVES_IN"]).where(label(FIRST) == "Person"), name=prop(FIRST, "name"))
    assert named.filter("name LIKE 'Customer%'").count() == g.edges(["LIVES_IN"]).df.count() > 0


def test_spaces_of_one_partition_have_no_window_over_everything(spark):
    trails = catalog.sample(spark).edges(["KNOWS"]).recurse("trail")
    spaces = [trails.group_by("L").order_by("G").project(g=1), trails.group_by("").order_by("P").project(a=2), trails.group_by("L").order_by("PGA").project(1, 2, 1), trails.group_by("").order_by("PGA").project()]
    for paths in spaces:
        assert "SinglePartition" not in plan(paths.df)
    assert {r["len"] for r in spaces[0].df.collect()} == {1}


def test_rounds_are_counted(spark):
    log = Log(detail=True)
    got = catalog.sample(spark).edges(["KNOWS"]).recurse("trail", log=log)
    per_round = [k for _, k in log.rounds]
    assert sum(per_round) == got.df.count() == 12 and log.longest[: len(per_round) - 1] == list(range(1, len(per_round)))
    assert all(log.met[r] == log.pruned[r] + kept + log.repeated[r] for r, kept in log.rounds if r in log.met) and sum(log.pruned.values()) > 0


def test_cycles_of_chains_are_found_by_doubling(spark):
    def graph(pairs):
        return PropertyGraph({"": spark.createDataFrame([(i,) for i in range(100)], "id bigint")}, {"E": spark.createDataFrame([(1000 + k, a, b) for k, (a, b) in enumerate(pairs)], "eid bigint, src bigint, dst bigint")})

    chain = [(i, i + 1) for i in range(60)]
    refuse_cycles(graph(chain).edges())
    refuse_cycles(graph([(0, 1), (0, 2), (1, 3), (2, 3), (3, 4)]).edges())
    for pairs in ([*chain, (60, 7)], [(0, 0)], [(0, 1), (0, 2), (1, 3), (2, 3), (3, 1)]):
        with pytest.raises(InfiniteWalkError):
            refuse_cycles(graph(pairs).edges())
    refuse_cycles(graph([*chain, (60, 7)]).edges(), seed=[90])


def test_two_sided_search(spark):
    rng = random.Random(41)
    n, m = 5, 8
    listed = [(100 + k, rng.randint(1, n), rng.randint(1, n)) for k in range(m)]
    graph = PropertyGraph({"": spark.createDataFrame([(i,) for i in range(1, n + 1)], "id bigint")}, {"E": spark.createDataFrame(listed, "eid bigint, src bigint, dst bigint")})
    for mode in ("trail", "acyclic", "simple"):
        known = recursion([((s, d), (e,)) for e, s, d in listed], mode, 5)
        for most in (1, 5):
            got = between(graph.edges(), [1, 2], [2, 3], mode, most)
            want = {p for p in known if p[0][0] in (1, 2) and p[0][-1] in (2, 3) and len(p[1]) <= most}
            assert rows(got) == want and got.df.count() == len(want), (mode, most, listed)


def test_streams_of_several_batches(spark, tmp_path):
    folder = tmp_path / "events"
    def put(part, some):
        df = spark.createDataFrame(some, "event_id long, s long, user_id long, event_type string")
        df.select("event_id", F.timestamp_seconds("s").alias("ts"), "user_id", "event_type").coalesce(1).write.mode("append").parquet(f"{folder}/{part}")

    put("a", [(1, 1000, 7, "view"), (2, 1100, 7, "click"), (3, 90_000, 8, "view")])
    stream = lambda: spark.readStream.schema("event_id long, ts timestamp, user_id long, event_type string").option("maxFilesPerTrigger", 1).parquet(f"{folder}/*").withWatermark("ts", "1 hour")
    table, state = f"{tmp_path}/counts", f"{tmp_path}/state"
    first = edges.merged_counts(stream(), table, state=state)
    assert {(r["user"], r["type"]): r["n"] for r in first.collect()} == {(7, "view"): 1, (7, "click"): 1, (8, "view"): 1}
    put("b", [(4, 1200, 7, "purchase"), (5, 90_100, 8, "view")])
    again = edges.merged_counts(stream(), table, state=state)
    assert {(r["user"], r["type"]): r["n"] for r in again.collect()} == {(7, "view"): 1, (7, "click"): 1, (7, "purchase"): 1, (8, "view"): 2}
    hops = edges.drained(edges.k_hops(stream())).collect()
    assert [(r["user"], r["hops"]) for r in hops] == [(7, [1, 2, 4])]
    progress = []
    edges.drained(edges.windowed_edges(stream(), "10 minutes"), ["window_start", "user", "type"], progress)
    assert edges.late_rows(progress) in (0, 1)  # which of the two files comes first decides whether the purchase is late

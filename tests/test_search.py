"""Shortest walks of all pairs: found in tasks that hold the steps, equal to those found round by round."""

import random

import pyarrow as pa
from pyspark.sql import functions as F

from test_whole import far, relay_table
from pathframe.operators import recursion, search
from pathframe.operators.pathset import Facts, PathSet
from pathframe.operators.recursion import Log
from pathframe.plans.execute import Counters, run
from pathframe.plans.language import plan_of
from pathframe.queries import catalogue
from pathframe.sources import catalog
from pathframe.sources.graph import PropertyGraph



def rows(paths):
    return sorted(map(repr, paths.df.select("src", "dst", "len", "nodes", "edges", "elabels").collect()))


def steps_of(spark, ends, id_type="bigint"):
    df = spark.createDataFrame([(k, a, b) for k, (a, b) in enumerate(ends)], "eid long, src long, dst long")
    c = lambda x: F.col(x).cast(id_type)
    return PathSet(df.select(c("src").alias("src"), c("dst").alias("dst"), F.lit(1).alias("len"), F.array(c("src"), c("dst")).alias("nodes"), F.array(c("eid")).alias("edges"), F.array((F.col("eid") % 3).cast("smallint")).alias("elabels")), PropertyGraph({"N": df.select(c("src").alias("id"))}, {}), Facts(1, 1, True))


def test_a_deep_relay_is_searched_without_rounds(spark, tmp_path, monkeypatch):
    relay_table(spark, tmp_path, [*range(60), 0])
    wrote, real = [], recursion.written
    monkeypatch.setattr(recursion, "written", lambda *a, **k: wrote.append(1) or real(*a, **k))
    for name, many in (("shortest_relay", 3600), ("any_shortest_walk_relay", 3600), ("all_shortest_acyclic_relay", 3540)):
        wrote.clear()
        got = catalogue.queries()[f"{name}_unbounded"](spark, str(tmp_path)).collect()
        assert len(got) == many and max(r["len"] for r in got) == 60 - (many == 3540)
        assert len(wrote) == 1, name  # the steps; a table for each round before


def test_searched_walks_are_those_of_rounds(spark, monkeypatch):
    rng = random.Random(3)
    ends = [(rng.randrange(14), rng.randrange(14)) for _ in range(34)] + [(20, 21), (20, 22), (21, 23), (22, 23), (23, 23), (23, 24), (24, 20), (24, 20), (30, 31), (31, None)]
    for id_type in ("bigint", "decimal(38,0)"):
        steps = steps_of(spark, ends, id_type)
        rounds = steps.recurse("shortest", log=Log())
        first = rounds.group_by("ST").order_by("A").project(a=1)
        assert rows(steps.recurse("shortest")) == rows(rounds)
        assert rows(steps.recurse("walk", keep=("k_shortest", 1))) == rows(first)
        monkeypatch.setattr(search, "HELD", 3)  # many steps take rounds, with the same result
        assert rows(steps.recurse("shortest")) == rows(rounds)
        monkeypatch.undo()


def held(ends):
    return search.Search(pa.table({"src": pa.array([a for a, _ in ends], pa.int64()), "dst": pa.array([b for _, b in ends], pa.int64()), "edge": pa.array(range(len(ends)), pa.int64()), "label": pa.array([None] * len(ends), pa.int16())}))


def test_pieces_are_bounded_and_whole(monkeypatch):
    rng = random.Random(5)
    # diamonds in a row, with 2^9 shortest walks from end to end, and a part with cycles
    ends = [e for k in range(9) for e in ((3 * k, 3 * k + 1), (3 * k, 3 * k + 2), (3 * k + 1, 3 * k + 3), (3 * k + 2, 3 * k + 3))]
    found = held(ends + [(40 + rng.randrange(15), 40 + rng.randrange(15)) for _ in range(40)])
    walks = lambda one: sorted(tuple(x) for batch in found.rows(search.np.arange(found.n), one) for x in batch.column("edges").to_pylist())
    whole = {one: walks(one) for one in (False, True)}
    assert sum(len(x) == 18 for x in whole[False]) == 512 and sum(len(x) == 18 for x in whole[True]) == 1
    monkeypatch.setattr(search, "CELLS", 64)
    monkeypatch.setattr(search, "PAIRS", 100)
    for one in (False, True):
        assert walks(one) == whole[one] and len(set(whole[one])) == len(whole[one])
        assert all(b.num_rows * b.column("len")[0].as_py() <= 64 for b in found.rows(search.np.arange(found.n), one))


def test_any_shortest_is_the_first_of_all_shortest(spark):
    g = catalog.sample(spark)
    text = "ANY SHORTEST WALK (x)-[(KNOWS|LIKES|HAS_CREATOR)+]->(y)"
    assert rows(run(plan_of(text), g)) == rows(run(plan_of(text), g, counters=Counters()))


def test_steps_reach_tasks_without_a_shuffle(spark):
    steps = steps_of(spark, [(1, 2), (2, 3), (3, 1)])
    for found in (steps.recurse("shortest"), steps.recurse("walk", keep=("k_shortest", 1))):
        plan = found.df._jdf.queryExecution().optimizedPlan().toString()
        assert "Repartition" not in plan and "MapInArrow" in plan  # a copy of the steps for each task was on disk before
        assert len(rows(found)) == 9


def test_closure_is_searched_without_rounds(spark, monkeypatch):
    rng = random.Random(7)
    ring = {(k, (k + 1) % 90) for k in range(90)} | {(100, 0), (101, 100), (7, 110), (110, 111), (101, 111), (120, 120), (None, 101), (111, None)}
    line = {(k, k + 1) for k in range(200, 280)} | {(300 + rng.randrange(25), 300 + rng.randrange(25)) for _ in range(30)}
    df = spark.createDataFrame(sorted(ring | line, key=str), "src long, dst long")
    wrote, real = [], recursion.written
    monkeypatch.setattr(recursion, "written", lambda *a, **k: wrote.append(1) or real(*a, **k))
    want = set(far({e for e in ring | line if e[0] is not None})) | {(None, b) for a, b in far(ring) if a == 101} | {(None, 101)}
    for part, firsts, lasts, pairs in ((64, 64, 1024, 1 << 20), (1, 2, 3, 50)):
        for name, k in (("PART", part), ("FIRSTS", firsts), ("LASTS", lasts), ("PAIRS", pairs)):
            monkeypatch.setattr(search, name, k)
        wrote.clear()
        got = [tuple(r) for r in recursion.closure(df).collect()]
        assert set(got) == want and len(got) == len(want)
        assert len(wrote) == 2  # the steps and the parts; a table for each round before

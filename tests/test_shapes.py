"""Groupings by orderings by projections, and random small graphs, against enumeration."""

import itertools
import random

import pytest

from brute import project, recursion, rows
from pathframe.operators.space import GROUPINGS, ORDERINGS
from pathframe.sources import catalog
from pathframe.sources.graph import PropertyGraph

KNOWS = [((1, 2), (101,)), ((2, 3), (102,)), ((3, 2), (103,)), ((2, 4), (104,))]


def test_every_shape_of_the_space(spark):
    """All eight projections of a sample of groupings and orderings; one Spark job for each grouping and ordering."""
    trails = catalog.sample(spark).edges(["KNOWS"]).recurse("trail")
    trails.df.cache()
    known = recursion(KNOWS, "trail")
    shapes = list(itertools.product(GROUPINGS, ("", *ORDERINGS), itertools.product(("*", 1), ("*", 1), ("*", 2))))
    random.seed(5)
    for letters, order, (p, g, a) in random.sample(shapes, 60):
        space = trails.group_by(letters)
        got = rows((space.order_by(order) if order else space).project(p, g, a))
        assert got == project(known, letters, order, p, g, a), (letters, order, p, g, a)


@pytest.mark.parametrize("seed", range(4))
def test_random_graphs(spark, seed):
    """Loops, parallel edges, isolated and unlabelled nodes."""
    rng = random.Random(seed)
    n, m = rng.randint(2, 5), rng.randint(1, 7)
    edges = [(100 + k, rng.randint(1, n), rng.randint(1, n)) for k in range(m)]
    nodes = spark.createDataFrame([(i,) for i in range(1, n + 2)], "id bigint")
    graph = PropertyGraph({"": nodes}, {"E": spark.createDataFrame(edges, "eid bigint, src bigint, dst bigint")})
    base = [((s, d), (e,)) for e, s, d in edges]
    for mode in ("trail", "acyclic", "simple", "shortest"):
        bound = 4 if mode == "trail" else None
        assert rows(graph.edges().recurse(mode, max_len=bound)) == recursion(base, mode, bound or 12), (mode, edges)
    k2 = rows(graph.edges().recurse("walk", keep=("k_shortest", 2)))
    walks = recursion(base, "walk", 12 if m < 4 else 6)
    short = {x for x in project(walks, "ST", "A", "*", "*", 2) if len(x[1]) <= 4}
    assert short <= k2
    one, two, three, four = (rows(graph.edges().recurse(x, max_len=3)) for x in ("acyclic", "simple", "trail", "walk"))
    assert one <= two <= three <= four


def test_seeds_as_lists_and_tables(spark):
    graph = catalog.sample(spark)
    known = recursion(KNOWS, "trail")
    for seed in ([2], [1, 3]):
        want = {p for p in known if p[0][0] in seed}
        table = spark.createDataFrame([(x,) for x in seed], "id bigint")
        assert rows(graph.edges(["KNOWS"]).recurse("trail", seed=seed)) == want
        assert rows(graph.edges(["KNOWS"]).recurse("trail", seed=table)) == want
        ends = {p for p in known if p[0][-1] in seed}
        assert rows(graph.edges(["KNOWS"]).recurse("trail", seed=seed, direction="backward")) == ends

"""Plans to Spark: each node becomes an operator call; with counters, what leaves each operator is counted."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import space as space_ops
from ..operators.conditions import Condition, satisfied
from ..operators.pathset import PathSet
from ..operators.recursion import Log, recurse
from ..sources.graph import PropertyGraph
from .nodes import EdgesOf, GroupBy, Join, NodesOf, OrderBy, PathExpr, Project, Recurse, Restrict, Select, SpaceExpr, Star, Union, title, walk
from .rewrite import optimise


@dataclass
class Counters:
    """(operator, paths out, candidate pairs of a join or 0), in the order of execution; and the logs of recursions."""

    rows: list[tuple[str, int, int]] = field(default_factory=list)
    logs: list[Log] = field(default_factory=list)

    def intermediate(self) -> int:
        """Paths that leave operators below the root."""
        return sum(n for _, n, _ in self.rows[:-1])

    def compared(self) -> int:
        return sum(p for _, _, p in self.rows)


def pairs_of(a: PathSet, b: PathSet) -> int:
    """Pairs with last = first, from two grouped counts; no join of paths is made."""
    left, right = a.df.groupBy("dst").agg(F.count(F.lit(1)).alias("m")), b.df.groupBy("src").agg(F.count(F.lit(1)).alias("n"))
    return left.join(right, F.col("dst") == F.col("src")).agg(F.coalesce(F.sum(F.col("m") * F.col("n")), F.lit(0))).first()[0]


def _seed_ids(graph: PropertyGraph, condition: Condition | None) -> DataFrame | None:
    """Nodes that meet a condition on first (or last), as a table for the semi-join at the start of a recursion."""
    return None if condition is None else satisfied(graph.nodes().df, graph, condition).select("src")


def run(plan: PathExpr, graph: PropertyGraph, *, optimised: bool = True, counters: Counters | None = None) -> PathSet:
    """The set of paths of a plan. Unless optimised is False, it is rewritten first."""
    return _paths(optimise(plan) if optimised else plan, graph, counters)


def _counted(out: PathSet, node, counters: Counters | None, pairs: int = 0) -> PathSet:
    if counters is None:
        return out
    kept = replace(out, df=out.df.persist())
    counters.rows.append((title(node), kept.df.count(), pairs))
    return kept


def _paths(node: PathExpr, graph: PropertyGraph, counters: Counters | None) -> PathSet:
    match node:
        case NodesOf():
            return _counted(graph.nodes(), node, counters)
        case EdgesOf(labels):
            return _counted(graph.edges(labels), node, counters)
        case Select(c, child):
            return _counted(_paths(child, graph, counters).where(c), node, counters)
        case Join(a, b):
            left, right = _paths(a, graph, counters), _paths(b, graph, counters)
            return _counted(left.join(right), node, counters, pairs_of(left, right) if counters else 0)
        case Union(a, b):
            return _counted(_paths(a, graph, counters).union(_paths(b, graph, counters)), node, counters)
        case Recurse(child, mode, max_len, seed, back, keep):
            log = Log() if counters else None
            out = recurse(_paths(child, graph, counters), mode, seed=_seed_ids(graph, seed), direction="backward" if back else "forward", max_len=max_len, keep=keep, log=log)
            if counters:
                counters.logs.append(log)
            return _counted(out, node, counters)
        case Star(child, mode, max_len, seed, back):
            ids = _seed_ids(graph, seed)
            some = recurse(_paths(child, graph, counters), mode, seed=ids, direction="backward" if back else "forward", max_len=max_len)
            zero = graph.nodes()
            if ids is not None:
                zero = replace(zero, df=zero.df.join(ids.select(F.col("src").alias("__seed")), F.col("src") == F.col("__seed"), "left_semi"))
            return _counted(some.union(zero), node, counters)
        case Restrict(mode, child):
            return _counted(_paths(child, graph, counters).restrict(mode), node, counters)
        case Project("*", "*", 1, OrderBy("A", GroupBy(letters, Recurse(child, "shortest", None, None, False, None))), desc) if counters is None and not desc and set(letters) == set("ST"):
            # the first of each pair's shortest walks: no other need be made
            return recurse(_paths(child, graph, None), "walk", keep=("k_shortest", 1))
        case Project(p, g, a, child, desc):
            return _counted(_space(child, graph, counters).project(p, g, a, desc), node, counters)
    raise TypeError(node)


def _space(node: SpaceExpr, graph: PropertyGraph, counters: Counters | None) -> space_ops.SolutionSpace:
    if isinstance(node, GroupBy):
        return space_ops.group_by(_paths(node.child, graph, counters), node.letters)
    if isinstance(node, OrderBy):
        return _space(node.child, graph, counters).order_by(node.letters)
    raise TypeError(node)


def lint(plan) -> list[str]:
    """Orders that can't change the result, named in words; the plan is accepted all the same."""
    return [f"{title(n)} has no effect" for n in walk(plan) if isinstance(n, OrderBy) and not any(title(m) == title(n) for m in walk(optimise(plan)))]

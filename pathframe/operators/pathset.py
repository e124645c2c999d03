"""Sets of paths: selection, ordered join, union and the other set operations."""

from __future__ import annotations

from dataclasses import dataclass, replace
from typing import TYPE_CHECKING

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import paths as P
from .conditions import Condition, satisfied

if TYPE_CHECKING:
    from ..sources.graph import PropertyGraph
    from .space import SolutionSpace


@dataclass(frozen=True)
class Facts:
    """What is known of a set without reading it: least and most length (None: unbounded), no repeats, edge labels."""

    least: int = 0
    most: int | None = None
    distinct: bool = False
    labels: frozenset[str] | None = None

    @property
    def uniform(self) -> bool:
        return self.most is not None and self.least == self.most


@dataclass(frozen=True)
class PathSet:
    df: DataFrame
    graph: PropertyGraph
    facts: Facts = Facts()

    def where(self, condition: Condition | Column) -> PathSet:
        """Paths that meet a condition (or a plain column over the path columns)."""
        if isinstance(condition, Condition):
            return replace(self, df=satisfied(self.df, self.graph, condition))
        return replace(self, df=self.df.filter(F.coalesce(condition, F.lit(False))))

    def restrict(self, mode: str) -> PathSet:
        """Paths that are lawful end to end under a path mode; "shortest": of least length for their ends."""
        if mode == "shortest":
            return replace(self, df=least_per_pair(self.df))
        return self if mode == "walk" else replace(self, df=self.df.filter(P.LAWFUL[mode]()))

    def join(self, other: PathSet) -> PathSet:
        """Each path of self followed by each of other that begins where it ends.

        Pairs of one operand of a single length give each path once; otherwise one path may come from several cuts.
        """
        facts = Facts(self.facts.least + other.facts.least, None if None in (self.facts.most, other.facts.most) else self.facts.most + other.facts.most, self.facts.distinct and other.facts.distinct and (self.facts.uniform or other.facts.uniform), _either(self, other))
        met = self.df.alias("a").join(other.df.alias("b"), F.col("a.dst") == F.col("b.src")).select(*P.concatenated())
        out = PathSet(met, self.graph, facts)
        return out if facts.distinct else out.distinct()

    def union(self, other: PathSet) -> PathSet:
        """Both sets without repeats; no shuffle where lengths or labels prove that they share no path."""
        a, b = self.facts, other.facts
        apart = (a.most is not None and a.most < b.least) or (b.most is not None and b.most < a.least)
        apart |= a.labels is not None and b.labels is not None and not a.labels & b.labels and min(a.least, b.least) > 0
        facts = Facts(min(a.least, b.least), None if None in (a.most, b.most) else max(a.most, b.most), apart and a.distinct and b.distinct, _either(self, other))
        out = PathSet(self.df.unionByName(other.df), self.graph, facts)
        return out if facts.distinct else out.distinct()

    def distinct(self) -> PathSet:
        """Repeats removed: a path is its edges, one of length 0 its node."""
        return self if self.facts.distinct else replace(self, df=self.df.dropDuplicates(["src", "edges"]), facts=replace(self.facts, distinct=True))

    def _matched(self, other: PathSet, how: str) -> PathSet:
        keys = other.df.select(F.col("src").alias("__src"), F.col("edges").alias("__edges"))
        own = self.distinct()
        return replace(own, df=own.df.join(keys, (F.col("src") == F.col("__src")) & (F.col("edges") == F.col("__edges")), how))

    def intersect(self, other: PathSet) -> PathSet:
        return self._matched(other, "left_semi")

    def except_(self, other: PathSet) -> PathSet:
        return self._matched(other, "left_anti")

    def semi(self, other: PathSet) -> PathSet:
        """Paths whose ends some path of other joins."""
        ends = other.df.select(F.col("src").alias("__src"), F.col("dst").alias("__dst"))
        return replace(self, df=self.df.join(ends, (F.col("src") == F.col("__src")) & (F.col("dst") == F.col("__dst")), "left_semi"))

    def anti(self, other: PathSet) -> PathSet:
        ends = other.df.select(F.col("src").alias("__src"), F.col("dst").alias("__dst"))
        return replace(self, df=self.df.join(ends, (F.col("src") == F.col("__src")) & (F.col("dst") == F.col("__dst")), "left_anti"))

    def reversed(self) -> PathSet:
        """Every path read backwards; a device for recursion towards fixed targets."""
        back = self.df.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "len", F.reverse("nodes").alias("nodes"), F.reverse("edges").alias("edges"), F.reverse("elabels").alias("elabels"))
        return replace(self, df=back)

    def recurse(self, mode: str = "walk", **options) -> PathSet:
        from .recursion import recurse

        return recurse(self, mode, **options)

    def star(self, mode: str = "walk", **options) -> PathSet:
        """Zero or more: the recursion and the paths of length 0."""
        return self.recurse(mode, **options).union(self.graph.nodes())

    def group_by(self, letters: str = "") -> SolutionSpace:
        from .space import group_by

        return group_by(self, letters)

    def endpoints(self) -> DataFrame:
        return self.df.select("src", "dst").distinct()

    def word(self) -> Column:
        return P.path_word(self.graph.names)

    def unwind(self) -> DataFrame:
        """One row for each hop: src, dst, len, hop from 1, from, edge, to, label."""
        names = self.graph.names
        known = F.create_map(*[F.lit(x) for pair in names.items() for x in pair])
        hops = self.df.select("src", "dst", "len", "nodes", "elabels", F.posexplode("edges").alias("at", "edge"))
        return hops.select("src", "dst", "len", (F.col("at") + 1).alias("hop"), F.get("nodes", "at").alias("from"), "edge", F.get("nodes", F.col("at") + 1).alias("to"), F.try_element_at(known, F.get("elabels", "at").cast("int")).alias("label"))

    def invalid(self) -> PathSet:
        """Paths with a hop that is no edge of the graph: a lawful set has none."""
        real = self.graph.edges().df.select(F.element_at("edges", 1).alias("edge"), F.col("src").alias("from"), F.col("dst").alias("to"))
        bad = self.unwind_keyed().join(real, ["edge", "from", "to"], "left_anti").select(F.col("key_src").alias("__src"), F.col("key_edges").alias("__edges")).distinct()
        return replace(self, df=self.df.join(bad, (F.col("src") == F.col("__src")) & (F.col("edges") == F.col("__edges")), "left_semi"))

    def unwind_keyed(self) -> DataFrame:
        hops = self.df.select("src", "edges", "nodes", F.posexplode("edges").alias("at", "edge"))
        return hops.select(F.col("src").alias("key_src"), F.col("edges").alias("key_edges"), "edge", F.get("nodes", "at").alias("from"), F.get("nodes", F.col("at") + 1).alias("to"))


def co_ended(paths: PathSet) -> DataFrame:
    """src, dst, shared: each two first nodes (src < dst) with some last node in common, and how many they share.

    It is the join of the set with its reverse, counted. First nodes of the same last nodes are one class; classes are
    joined and counted, by their least members, and pairs of members are made from them as the result is read.
    """
    from ..sources.shared import written

    ends = paths.df.groupBy("src").agg(F.sort_array(F.collect_set("dst")).alias("ends"))
    members, _ = written(ends.groupBy("ends").agg(F.min("src").alias("of"), F.collect_list("src").alias("members")))
    single = members.select("of", F.explode("ends").alias("end"))
    a, b = single.alias("a"), single.alias("b")
    met = a.join(b, F.col("a.end") == F.col("b.end")).groupBy(F.col("a.of").alias("of"), F.col("b.of").alias("with")).agg(F.count(F.lit(1)).alias("shared"))
    each, _ = written(members.select("of", F.explode("members").alias("member")))
    met, _ = written(met)
    spread = max(8, paths.df.sparkSession.sparkContext.defaultParallelism)
    first = each.withColumnRenamed("member", "src").repartition(spread, "src").join(met, "of").drop("of")
    pairs = first.join(each.select(F.col("of").alias("with"), F.col("member").alias("dst")), "with").filter("src < dst")
    return pairs.select("src", "dst", "shared")


def least_per_pair(df: DataFrame) -> DataFrame:
    from pyspark.sql import Window

    return df.withColumn("__least", F.min("len").over(Window.partitionBy("src", "dst"))).filter("len = __least").drop("__least")


def _either(a: PathSet, b: PathSet) -> frozenset[str] | None:
    return None if a.facts.labels is None or b.facts.labels is None else a.facts.labels | b.facts.labels

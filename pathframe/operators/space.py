"""Solution spaces: paths in groups in partitions, ordered lazily and cut by the projection.

A space is flat: each path carries its partition key (p_src, p_dst; null where the grouping ignores an end), its group
key (g_len) and three order values. Ordering replaces values and sorts nothing; the projection turns values into group
limits that Spark applies before its exchange.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import paths as P
from .pathset import PathSet

GROUPINGS = ("", "S", "T", "L", "ST", "SL", "TL", "STL")
ORDERINGS = ("P", "G", "A", "PG", "PA", "GA", "PGA")
_PARTITION, _GROUP = ("p_src", "p_dst"), ("p_src", "p_dst", "g_len")


@dataclass(frozen=True)
class SolutionSpace:
    paths: PathSet
    letters: str
    df: DataFrame
    ordered: frozenset[str] = frozenset()

    def least_length(self, of: str) -> Column:
        """Least length in the path's partition or group; a group of one length needs no window, and a space of one
        partition takes the least of its lengths, which an aggregate of few rows gives: never a window over everything."""
        if of == "group" and "L" in self.letters:
            return F.col("len")
        if not any(x in self.letters for x in "ST"):
            return self.df.groupBy("len").agg(F.count(F.lit(1)).alias("n")).select("len").orderBy("len").limit(1).scalar()
        keys = _PARTITION if of == "partition" else _GROUP
        return F.min("len").over(Window.partitionBy(*keys))

    def order_by(self, letters: str) -> SolutionSpace:
        """P, G and A set the order of partitions, groups and paths to least lengths (of paths: to lengths); orders
        set before stay, and setting one twice changes nothing."""
        values = {"P": ("ord_p", lambda: self.least_length("partition")), "G": ("ord_g", lambda: self.least_length("group")), "A": ("ord_a", P.length)}
        df = self.df
        for x in letters:
            if x not in values:
                raise ValueError(f"no order {x!r}")
            name, value = values[x]
            df = df.withColumn(name, value().cast("int"))
        return replace(self, df=df, ordered=self.ordered | set(letters))

    def project(self, p: int | str = "*", g: int | str = "*", a: int | str = "*", desc: str = "") -> PathSet:
        """The first p partitions, in each the first g groups, in each the first a paths; "*" takes all, and a number
        beyond what there is takes all too. desc names orders (P, G, A) to read from the top. Ties go by key, and
        paths by length, nodes and edges, so results repeat; any choice among ties is lawful."""
        df = self.df
        way = lambda c, x: F.col(c).desc() if x in desc else F.col(c).asc()
        if p != "*":
            if any(x in self.letters for x in "ST"):
                firsts = df.groupBy(*_PARTITION).agg(F.min("ord_p").alias("ord_p")).orderBy(way("ord_p", "P"), *_PARTITION).limit(int(p)).select(F.col("p_src").alias("__s"), F.col("p_dst").alias("__t"))
                df = df.join(firsts, F.col("p_src").eqNullSafe(F.col("__s")) & F.col("p_dst").eqNullSafe(F.col("__t")), "left_semi")
        if g != "*" and self.letters == "L":  # one partition: its groups are a row a length, and the first of them a top-k
            firsts = df.groupBy("g_len").agg(F.min("ord_g").alias("ord_g")).orderBy(way("ord_g", "G"), "g_len").limit(int(g)).select(F.col("g_len").alias("__l"))
            df = df.join(F.broadcast(firsts), F.col("g_len") == F.col("__l"), "left_semi")
        elif g != "*" and "L" in self.letters:
            rank = F.dense_rank().over(Window.partitionBy(*_PARTITION).orderBy(way("ord_g", "G"), "g_len"))
            df = df.withColumn("__r", rank).filter(F.col("__r") <= int(g)).drop("__r")
        if a != "*":
            if self.letters:
                rank = F.row_number().over(Window.partitionBy(*_GROUP).orderBy(way("ord_a", "A"), *P.TIE))
                df = df.withColumn("__r", rank).filter(F.col("__r") <= int(a)).drop("__r")
            else:  # one group of everything: a top-k, not a window over one partition
                df = df.orderBy(way("ord_a", "A"), *P.TIE).limit(int(a))
        return replace(self.paths, df=df.select(*P.PATH_COLUMNS))


def group_by(paths: PathSet, letters: str = "") -> SolutionSpace:
    """Partitions by first node (S) and last node (T), groups in them by length (L); without a letter, one of each."""
    letters = "".join(x for x in "STL" if x in letters.upper())
    own = paths.distinct()
    null, id_type = F.lit(None), own.graph.id_type
    df = own.df.withColumns({
        "p_src": F.col("src") if "S" in letters else null.cast(id_type), "p_dst": F.col("dst") if "T" in letters else null.cast(id_type),
        "g_len": F.col("len") if "L" in letters else null.cast("int"), "ord_p": F.lit(1), "ord_g": F.lit(1), "ord_a": F.lit(1),
    })
    return SolutionSpace(own, letters, df)

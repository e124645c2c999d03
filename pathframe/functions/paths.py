"""Functions of one path: accessors, concatenation, membership in the path classes. Built-in expressions only."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Columns of every set of paths. src, dst and len repeat what the arrays say: they are the join, group and order keys.
PATH_COLUMNS = ("src", "dst", "len", "nodes", "edges", "elabels")
PATH_SCHEMA = "src bigint, dst bigint, len int, nodes array<bigint>, edges array<bigint>, elabels array<smallint>"
#: A reproducible order of paths: by length, then nodes, then edges.
TIE = ("len", "nodes", "edges")


def first() -> Column:
    return F.col("src")


def last() -> Column:
    return F.col("dst")


def length() -> Column:
    return F.col("len")


def node_at(i: int, nodes: str | Column = "nodes") -> Column:
    """Node in place i, from 1; null where there is none."""
    return F.try_element_at(F.col(nodes) if isinstance(nodes, str) else nodes, F.lit(i))


def edge_at(i: int, edges: str | Column = "edges") -> Column:
    return F.try_element_at(F.col(edges) if isinstance(edges, str) else edges, F.lit(i))


def path_word(names: dict[int, str]) -> Column:
    """Edge labels along the path, parted by slashes; unlabelled edges leave an empty place."""
    known = F.create_map(*[F.lit(x) for code, name in names.items() for x in (code, name)]) if names else F.lit(None).cast("map<int,string>")
    return F.array_join(F.transform("elabels", lambda c: F.coalesce(F.try_element_at(known, c.cast("int")), F.lit(""))), "/")


def concatenated(a: str = "a", b: str = "b") -> list[Column]:
    """The path a followed by b, where a ends in b's first node; aliases of two path sets."""
    return [
        F.col(f"{a}.src").alias("src"), F.col(f"{b}.dst").alias("dst"), (F.col(f"{a}.len") + F.col(f"{b}.len")).cast("int").alias("len"),
        F.concat(f"{a}.nodes", F.slice(f"{b}.nodes", F.lit(2), F.col(f"{b}.len"))).alias("nodes"), F.concat(f"{a}.edges", f"{b}.edges").alias("edges"), F.concat(f"{a}.elabels", f"{b}.elabels").alias("elabels"),
    ]


def is_walk() -> Column:
    return F.lit(True)


def is_trail() -> Column:
    return F.size(F.array_distinct("edges")) == F.col("len")


def is_acyclic() -> Column:
    return F.size(F.array_distinct("nodes")) == F.col("len") + 1


def is_simple() -> Column:
    return is_acyclic() | ((F.col("len") >= 1) & (F.col("src") == F.col("dst")) & (F.size(F.array_distinct("nodes")) == F.col("len")))


LAWFUL = {"walk": is_walk, "trail": is_trail, "acyclic": is_acyclic, "simple": is_simple}


def may_follow(mode: str, a: str = "a", b: str = "b") -> Column:
    """Whether lawful a and lawful b make a lawful path of the mode, tested on what is new in b alone."""
    a_nodes, b_nodes = F.col(f"{a}.nodes"), F.col(f"{b}.nodes")
    if mode == "trail":
        return ~F.arrays_overlap(F.col(f"{a}.edges"), F.col(f"{b}.edges"))
    if mode == "acyclic":
        return ~F.arrays_overlap(a_nodes, F.slice(b_nodes, F.lit(2), F.col(f"{b}.len")))
    if mode == "simple":  # the inside of b is new; its end is new or closes the path
        inside = F.slice(b_nodes, F.lit(2), F.greatest(F.col(f"{b}.len") - 1, F.lit(0)))
        return ~F.arrays_overlap(a_nodes, inside) & ~F.array_contains(F.slice(a_nodes, F.lit(2), F.greatest(F.col(f"{a}.len"), F.lit(0))), F.col(f"{b}.dst"))
    return F.lit(True)

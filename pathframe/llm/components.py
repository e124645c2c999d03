"""Connected components of an edge table by star contraction, all of it in joins and aggregates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import settle


#: Parts that a node's neighbours are dealt to, so that no task holds all of a node that a third of the edges end in.
PARTS = 1024


def _stars(edges: DataFrame, large: bool) -> DataFrame:
    """One contraction: every node's larger (large) or smaller neighbours are tied to its smallest neighbour or itself.

    Least neighbours are found by part, then by node over at most PARTS rows, and go back to the parts: edges are never
    dealt by a node alone.
    """
    pairs = edges.select("u", "v")
    if large:
        pairs = pairs.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    pairs = pairs.withColumn("part", F.pmod(F.xxhash64("v"), F.lit(PARTS)))
    by_part = pairs.groupBy("u", "part").agg(F.min("v").alias("m"))
    least = by_part.groupBy("u").agg(F.min("m").alias("m")).select("u", F.least("u", "m").alias("m"))
    tied = pairs.join(by_part.select("u", "part").join(least, "u"), ["u", "part"])
    if large:
        out = tied.filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        out = tied.filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v")))
    return out.filter("u <> v").distinct()


def components(edges: DataFrame, rounds: int = 40) -> DataFrame:
    """node, root for each node of edges (u, v): root is the smallest node that it reaches. A root is a row of its own.

    Edges with a null end, loops and repeated edges count for nothing. Each round cuts its lineage with a checkpoint;
    the driver sees a count and a sum a round. Rounds grow with the logarithm of the longest path.
    """
    now = edges.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    now, seen = settle(now), None
    for _ in range(rounds):
        after = settle(_stars(_stars(now, True), False))
        mark = after.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        now = after
        if mark == seen:
            break
        seen = mark
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    roots = now.select(F.col("v").alias("node")).distinct()
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).union(roots.select("node", F.col("node").alias("root")))

"""Loading graphs from files and writing sets of paths."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.pathset import PathSet
from .graph import PropertyGraph

READERS = ("parquet", "csv", "json", "orc")


def table_of(spark: SparkSession, where: str, kind: str = "parquet", schema: str | None = None) -> DataFrame:
    """A table from a file of a kind, or, of kind "table", from the session's catalog."""
    if kind == "table":
        return spark.table(where)
    if kind not in READERS:
        raise ValueError(f"no reader for {kind!r}")
    reader = spark.read.format(kind).option("header", "true")
    return (reader.schema(schema) if schema else reader.option("inferSchema", "true")).load(where)


def graph_of(nodes: dict[str, DataFrame], edges: dict[str, DataFrame], *, node_id: str = "id", edge_id: str = "eid", source: str = "src", target: str = "dst") -> PropertyGraph:
    """A graph from any tables that have an id column, and ids of both ends."""
    return PropertyGraph({k: t.withColumnRenamed(node_id, "id") for k, t in nodes.items()}, {k: t.withColumnsRenamed({edge_id: "eid", source: "src", target: "dst"}) for k, t in edges.items()})


def write_paths(paths: PathSet, where: str) -> None:
    """Parquet by length, so that reads of short paths skip the others."""
    paths.df.write.mode("overwrite").partitionBy("len").parquet(where)


def write_edges(graph: PropertyGraph, label: str, table: str, buckets: int = 64) -> None:
    """One label's edges as a table in buckets by first node, which recursions then join without another shuffle."""
    graph.edges([label]).df.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(table)


def read_paths(spark: SparkSession, where: str, graph: PropertyGraph) -> PathSet:
    from ..functions.paths import PATH_COLUMNS

    return PathSet(spark.read.parquet(where).select(*PATH_COLUMNS).withColumn("len", F.col("len").cast("int")), graph)


def write_endpoints(paths: PathSet, where: str) -> None:
    paths.endpoints().write.mode("overwrite").parquet(where)


def as_json(paths: PathSet) -> DataFrame:
    """One JSON text a path, with its word."""
    return paths.df.select(F.to_json(F.struct("src", "dst", "len", "nodes", "edges", paths.word().alias("word"))).alias("path"))


def to_table(paths: PathSet, **columns) -> DataFrame:
    """A relational row a path: names given to terms of the condition language, such as first=prop(FIRST, "name")."""
    df = paths.df
    for name, term in columns.items():
        if term.kind == "len":
            df = df.withColumn(name, F.col("len"))
            continue
        what = "edge" if term.place.what == "edge" else "node"
        owners = paths.graph.labels_of_nodes().withColumnRenamed("label", "value") if term.kind == "label" else paths.graph.property_of(term.name, what)
        if owners is None:
            df = df.withColumn(name, F.lit(None).cast("string"))
            continue
        df = df.withColumn("__k", term.place.id()).join(owners.select(F.col("id").alias("__i"), F.col("value").alias(name)), F.col("__k") == F.col("__i"), "left").drop("__k", "__i")
    return df.select("src", "dst", "len", *columns)


def register_views(spark: SparkSession, graph: PropertyGraph, prefix: str = "") -> None:
    """Temporary views of the graph's nodes and edges as path rows, for SQL."""
    graph.nodes().df.createOrReplaceTempView(f"{prefix}nodes_paths")
    graph.edges().df.createOrReplaceTempView(f"{prefix}edge_paths")


def register_result(paths: PathSet, name: str) -> None:
    """Temporary view of a set of paths: its columns and the word of each path, for SQL."""
    paths.df.withColumn("word", paths.word()).createOrReplaceTempView(name)

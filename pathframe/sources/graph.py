"""Property graphs: node and edge tables by label, seen as the sets of paths of length 0 and 1."""

from __future__ import annotations

from collections.abc import Iterable, Mapping
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Ids carry their kind in the bits from this one up, so node and edge ids never meet. Keys are checked as ids are made.
KIND_BIT = 48


#: Bits of each of the two keys of an edge that is known by its ends.
PAIR_BITS = KIND_BIT // 2
#: The same for wide ids, which are decimals of 38 digits: any two keys below 2^48.
WIDE_KIND_BIT, WIDE_PAIR_BITS, WIDE_TYPE = 100, 48, "decimal(38,0)"


def _power(bits: int) -> Column:
    return F.lit(str(1 << bits)).cast(WIDE_TYPE)


def _within(key: Column, bits: int) -> Column:
    """key, or an error where it is out of range: an id is never another one's by overflow."""
    key = key.cast("bigint")
    told = F.concat(F.lit("key "), key.cast("string"), F.lit(f" doesn't fit {bits} bits: make the graph with wide ids"))
    return F.when(key.isNull() | ((key >= 0) & (key <= (1 << bits) - 1)), key).otherwise(F.raise_error(told).cast("bigint"))


def tagged(kind: int, key: Column, wide: bool = False) -> Column:
    """Id of a key below 2^48 (wide: any bigint that isn't negative)."""
    if wide:
        return (F.lit(str(kind << WIDE_KIND_BIT)).cast(WIDE_TYPE) + _within(key, 63)).cast(WIDE_TYPE)
    return F.lit(kind << KIND_BIT) + _within(key, KIND_BIT)


def paired(kind: int, a: Column, b: Column, wide: bool = False) -> Column:
    """Id of the one edge between two keys below 2^24 (wide: below 2^48)."""
    if wide:
        pair = (_within(a, WIDE_PAIR_BITS).cast("decimal(15,0)") * F.lit(1 << WIDE_PAIR_BITS).cast("decimal(16,0)")).cast(WIDE_TYPE) + _within(b, WIDE_PAIR_BITS)
        return (F.lit(str(kind << WIDE_KIND_BIT)).cast(WIDE_TYPE) + pair).cast(WIDE_TYPE)
    return F.lit(kind << KIND_BIT) + _within(a, PAIR_BITS) * (1 << PAIR_BITS) + _within(b, PAIR_BITS)


@dataclass(frozen=True)
class PropertyGraph:
    """Node tables (id, properties...) and edge tables (eid, src, dst, properties...) by label; "" is no label.

    A property that a label's table lacks, or that is null, is undefined. node_kinds gives the label of a kind-tagged
    node id; a graph without it has labels found by a join.
    """

    node_tables: Mapping[str, DataFrame]
    edge_tables: Mapping[str, DataFrame]
    node_kinds: Mapping[int, str] = field(default_factory=dict)

    @property
    def id_type(self) -> str:
        """Type of all ids: bigint, or what the node tables have instead (wide decimals, strings)."""
        return next((t.schema["id"].dataType.simpleString() for t in self.node_tables.values()), "bigint")

    def kind_of(self, id_: Column) -> Column:
        """Kind of a kind-tagged id."""
        if self.id_type == "bigint":
            return F.shiftright(id_, KIND_BIT).cast("int")
        return F.floor(id_ / _power(WIDE_KIND_BIT)).cast("int")

    @property
    def codes(self) -> dict[str, int]:
        return {name: i for i, name in enumerate(sorted(k for k in self.edge_tables if k))}

    @property
    def names(self) -> dict[int, str]:
        return {i: name for name, i in self.codes.items()}

    def nodes(self) -> PathSet:
        rows = [t.select(F.col("id").alias("src"), F.col("id").alias("dst"), F.lit(0).alias("len"), F.array("id").alias("nodes"), F.array().cast(f"array<{self.id_type}>").alias("edges"), F.array().cast("array<smallint>").alias("elabels")) for t in self.node_tables.values()]
        return PathSet(reduce(DataFrame.unionByName, rows), self, Facts(0, 0, True))

    def edges(self, labels: Iterable[str] | None = None) -> PathSet:
        """Paths of length 1; only the tables of the labels asked for are read."""
        wanted = [k for k in self.edge_tables if labels is None or k in set(labels)]
        rows = [self._edge_rows(k) for k in wanted]
        if not rows:
            any_table = next(iter(self.edge_tables))
            rows = [self._edge_rows(any_table).limit(0)]
        return PathSet(reduce(DataFrame.unionByName, rows), self, Facts(1, 1, True, frozenset(wanted)))

    def _edge_rows(self, label: str) -> DataFrame:
        code = F.lit(self.codes[label] if label else None).cast("smallint")
        return self.edge_tables[label].select("src", "dst", F.lit(1).alias("len"), F.array("src", "dst").alias("nodes"), F.array("eid").alias("edges"), F.array(code).alias("elabels"))

    def labels_of_nodes(self) -> DataFrame:
        return reduce(DataFrame.unionByName, [t.select("id", F.lit(k or None).cast("string").alias("label")) for k, t in self.node_tables.items()])

    def property_of(self, name: str, what: str) -> DataFrame | None:
        """(id, value) of a property of nodes or edges, from the labels that have it; None if none has."""
        tables, key = (self.node_tables, "id") if what == "node" else (self.edge_tables, "eid")
        own = [t.select(F.col(key).alias("id"), F.col(name).alias("value")) for t in tables.values() if name in t.columns and name != key]
        if len({t.schema["value"].dataType.simpleString() for t in own}) > 1:
            own = [t.withColumn("value", F.col("value").cast("string")) for t in own]
        return reduce(DataFrame.unionByName, own) if own else None

    def orphans(self) -> DataFrame:
        """Edges with an end that is no node: a lawful graph has none."""
        ids = reduce(DataFrame.unionByName, [t.select("id") for t in self.node_tables.values()])
        ends = reduce(DataFrame.unionByName, [t.select("eid", F.explode(F.array("src", "dst")).alias("id")) for t in self.edge_tables.values()])
        return ends.join(ids, "id", "left_anti").select("eid", "id")


from ..operators.pathset import Facts, PathSet  # noqa: E402  graphs give path sets and path sets know their graph

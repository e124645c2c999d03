"""Selection conditions. They are two-valued: a test of something undefined is false, and its negation true."""

from __future__ import annotations

from dataclasses import dataclass
from typing import TYPE_CHECKING, Any

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import paths as P

if TYPE_CHECKING:
    from ..sources.graph import PropertyGraph

OPERATORS = {
    "=": lambda a, b: a == b, "<>": lambda a, b: a != b, "<": lambda a, b: a < b, ">": lambda a, b: a > b, "<=": lambda a, b: a <= b, ">=": lambda a, b: a >= b,
    "in": lambda a, b: a.isin(*b), "like": lambda a, b: a.like(b), "between": lambda a, b: a.between(*b),
}


class Condition:
    def __and__(self, other: Condition) -> Condition:
        return And(self, other)

    def __or__(self, other: Condition) -> Condition:
        return Or(self, other)

    def __invert__(self) -> Condition:
        return Not(self)


@dataclass(frozen=True)
class Place:
    """what: first, last, node or edge; at: from 1, for node and edge."""

    what: str
    at: int = 0

    def id(self) -> Column:
        return {"first": P.first, "last": P.last}[self.what]() if self.what in ("first", "last") else P.node_at(self.at) if self.what == "node" else P.edge_at(self.at)

    def __str__(self) -> str:
        return self.what if self.what in ("first", "last") else f"{self.what}({self.at})"


@dataclass(frozen=True)
class Term:
    """kind: label, prop, len; with substr, a part of the value (from 1, length)."""

    kind: str
    place: Place | None = None
    name: str = ""
    substr: tuple[int, int] | None = None

    def _test(self, op: str, value: Any) -> Test:
        return Test(self, op, value)

    def __eq__(self, other: object):  # type: ignore[override]
        return NotImplemented if isinstance(other, Term) else self._test("=", other)

    def __ne__(self, other: object):  # type: ignore[override]
        return NotImplemented if isinstance(other, Term) else self._test("<>", other)

    def __lt__(self, v):
        return self._test("<", v)

    def __gt__(self, v):
        return self._test(">", v)

    def __le__(self, v):
        return self._test("<=", v)

    def __ge__(self, v):
        return self._test(">=", v)

    def isin(self, *values):
        return self._test("in", tuple(values))

    def like(self, pattern: str):
        return self._test("like", pattern)

    def between(self, low, high):
        return self._test("between", (low, high))

    def is_bound(self) -> Test:
        return self._test("bound", True)

    def part(self, start: int, n: int) -> Term:
        return Term(self.kind, self.place, self.name, (start, n))

    def key(self) -> tuple:
        return (self.kind, self.place, self.name)

    __hash__ = None  # type: ignore[assignment]

    def __str__(self) -> str:
        body = "len()" if self.kind == "len" else f"label({self.place})" if self.kind == "label" else f"{self.place}.{self.name}"
        return f"substr({body}, {self.substr[0]}, {self.substr[1]})" if self.substr else body


@dataclass(frozen=True, eq=False)
class Test(Condition):
    term: Term
    op: str
    value: Any

    def __str__(self) -> str:
        if self.op == "bound":
            return f"bound({self.term})"
        return f"{self.term} {self.op} " + (f'"{self.value}"' if isinstance(self.value, str) else str(self.value))


@dataclass(frozen=True, eq=False)
class And(Condition):
    a: Condition
    b: Condition

    def __str__(self) -> str:
        return f"({self.a} AND {self.b})"


@dataclass(frozen=True, eq=False)
class Or(Condition):
    a: Condition
    b: Condition

    def __str__(self) -> str:
        return f"({self.a} OR {self.b})"


@dataclass(frozen=True, eq=False)
class Not(Condition):
    a: Condition

    def __str__(self) -> str:
        return f"NOT {self.a}"


@dataclass(frozen=True, eq=False)
class Quantified(Condition):
    """Whether every ("all") or some ("some") node or edge of a path meets a condition, which is put for a single one: on
    FIRST for nodes, on edge(1) for edges. A path without edges meets any condition on all its edges, and none on some."""

    how: str
    what: str
    inner: Condition

    def __str__(self) -> str:
        return f"{self.how} {self.what}s: {self.inner}"


FIRST, LAST = Place("first"), Place("last")


def every_node(inner: Condition) -> Quantified:
    return Quantified("all", "node", inner)


def some_node(inner: Condition) -> Quantified:
    return Quantified("some", "node", inner)


def every_edge(inner: Condition) -> Quantified:
    return Quantified("all", "edge", inner)


def some_edge(inner: Condition) -> Quantified:
    return Quantified("some", "edge", inner)


def node(i: int) -> Place:
    return Place("node", i)


def edge(i: int) -> Place:
    return Place("edge", i)


def label(place: Place) -> Term:
    return Term("label", place)


def prop(place: Place, name: str) -> Term:
    return Term("prop", place, name)


def length() -> Term:
    return Term("len")


def quantified(c: Condition) -> list[Quantified]:
    return [c] if isinstance(c, Quantified) else [] if isinstance(c, Test) else quantified(c.a) + (quantified(c.b) if hasattr(c, "b") else [])  # type: ignore[attr-defined]


def tests(c: Condition) -> list[Test]:
    if isinstance(c, Quantified):
        return []
    return [c] if isinstance(c, Test) else tests(c.a) if isinstance(c, Not) else tests(c.a) + tests(c.b)  # type: ignore[attr-defined]


def conjuncts(c: Condition) -> list[Condition]:
    return conjuncts(c.a) + conjuncts(c.b) if isinstance(c, And) else [c]


def satisfied(df: DataFrame, graph: PropertyGraph, condition: Condition) -> DataFrame:
    """Rows of df that meet the condition. A node label or property costs one left join with the tables that own it
    (edge labels and the labels of kind-tagged nodes ride in the row); only the named column is read there."""
    columns, values = df.columns, {}
    for k, q in enumerate(quantified(condition)):
        df = df.join(_holding(df, graph, q).withColumn(f"__q{k}", F.lit(True)).withColumnsRenamed({"src": f"__s{k}", "edges": f"__e{k}"}), (F.col("src") == F.col(f"__s{k}")) & (F.col("edges") == F.col(f"__e{k}")), "left")
        values[id(q)] = F.col(f"__q{k}").isNotNull() if q.how == "some" else F.col(f"__q{k}").isNull()
    for k, term in enumerate({t.term.key(): t.term for t in tests(condition)}.values()):
        name = f"__v{k}"
        values[term.key()] = F.col(name)
        if term.kind == "len":
            df = df.withColumn(name, P.length())
        elif term.kind == "label" and term.place.what == "edge":
            known = graph.names
            code = P.edge_at(term.place.at, "elabels").cast("int")
            df = df.withColumn(name, F.try_element_at(F.create_map(*[F.lit(x) for p in known.items() for x in p]), code) if known else F.lit(None).cast("string"))
        elif term.kind == "label" and graph.node_kinds:
            kinds = F.create_map(*[F.lit(x) for p in graph.node_kinds.items() for x in p])
            df = df.withColumn(name, F.try_element_at(kinds, graph.kind_of(term.place.id())))
        else:
            owners = graph.labels_of_nodes().withColumnRenamed("label", "value") if term.kind == "label" else graph.property_of(term.name, "edge" if term.place.what == "edge" else "node")
            if owners is None:
                df = df.withColumn(name, F.lit(None).cast("string"))
            else:
                owners = owners.select(F.col("id").alias(f"__i{k}"), F.col("value").alias(name))
                df = df.withColumn(f"__k{k}", term.place.id()).join(owners, F.col(f"__k{k}") == F.col(f"__i{k}"), "left")
    return df.filter(_column(condition, values)).select(*columns)


def _holding(df: DataFrame, graph: PropertyGraph, q: Quantified) -> DataFrame:
    """src, edges of the paths with an element that meets (some) or fails (all) the condition: elements are joined with
    those that meet it, found once in the graph."""
    if q.what == "node":
        meet = satisfied(graph.nodes().df, graph, q.inner).select(F.col("src").alias("__id"))
    else:
        meet = satisfied(graph.edges().df, graph, q.inner).select(F.element_at("edges", 1).alias("__id"))
    hops = df.select("src", "edges", F.explode("nodes" if q.what == "node" else "edges").alias("__at"))
    return hops.join(meet, F.col("__at") == F.col("__id"), "left_semi" if q.how == "some" else "left_anti").select("src", "edges").distinct()


def _column(c: Condition, values: dict) -> Column:
    if isinstance(c, Quantified):
        return values[id(c)]
    if isinstance(c, And):
        return _column(c.a, values) & _column(c.b, values)
    if isinstance(c, Or):
        return _column(c.a, values) | _column(c.b, values)
    if isinstance(c, Not):
        return ~_column(c.a, values)
    value = values[c.term.key()]  # type: ignore[attr-defined]
    if c.op == "bound":
        return value.isNotNull()
    if c.term.substr:
        value = F.substring(value.cast("string"), *c.term.substr)
    return F.coalesce(OPERATORS[c.op](value, c.value), F.lit(False))


def shifted(c: Condition, by: int) -> Condition:
    """The condition with every numbered place moved by `by`."""
    if isinstance(c, And):
        return And(shifted(c.a, by), shifted(c.b, by))
    if isinstance(c, Or):
        return Or(shifted(c.a, by), shifted(c.b, by))
    if isinstance(c, Not):
        return Not(shifted(c.a, by))
    t = c.term  # type: ignore[attr-defined]
    place = Place(t.place.what, t.place.at + by) if t.place and t.place.what in ("node", "edge") else t.place
    return Test(Term(t.kind, place, t.name, t.substr), c.op, c.value)

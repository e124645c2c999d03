"""Text queries: a standard-like form with selector and restrictor, and an extended form that states the projection.

    MATCH? [selector] [restrictor] [name =] (x {p: v})-[regex]->(y {p: v}) [WHERE condition]
    MATCH? n|ALL PARTITIONS n|ALL GROUPS n|ALL PATHS [restrictor] pattern [WHERE ...] [GROUP BY ...] [ORDER BY ...]

Regular expressions have labels (with or without a colon), / for sequence, | for choice, + * ? {m,n} and parentheses; a
repetition may also follow the arrow, ->+ or ->*. WHERE, MATCH and a leading question mark on variables are optional.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import reduce

from ..operators.conditions import FIRST, LAST, Condition, Place, Term, Test
from ..operators.modes import mode_plan, restricted
from .nodes import EdgesOf, GroupBy, Join, NodesOf, OrderBy, PathExpr, Project, Recurse, Select, Star, Union, show


class SyntaxFault(ValueError):
    def __init__(self, what: str, at: int) -> None:
        super().__init__(f"{what} at character {at + 1}")
        self.at = at


_TOKEN = re.compile(r"\s*(?:(?P<number>\d+(?:\.\d+)?)|(?P<string>\"[^\"]*\"|'[^']*'|“[^”]*”)|(?P<word>\??[A-Za-z_][A-Za-z_0-9]*)|(?P<mark>->|<>|!=|<=|>=|[-()\[\]{}:,./|+*?=<>]))")


def tokens(text: str) -> list[tuple[str, str, int]]:
    out, at = [], 0
    while text[at:].strip():
        m = _TOKEN.match(text, at)
        if m is None:
            raise SyntaxFault("nothing known", at + len(text[at:]) - len(text[at:].lstrip()))
        out.append((m.lastgroup, m[m.lastgroup], m.start(m.lastgroup)))
        at = m.end()
    return [*out, ("end", "", len(text))]


@dataclass(frozen=True)
class PathQuery:
    """A parsed query: its pattern as a plan with walks, the modes to apply, and the condition on whole paths."""

    pattern: PathExpr
    condition: Condition | None
    restrictor: str
    selector: str | None = None
    k: int | None = None
    projection: tuple = ()
    grouping: str = ""
    ordering: str = ""

    def plan(self, scope: str = "path", max_len: int | None = None) -> PathExpr:
        body = _bounded(self.pattern, max_len)
        if self.condition is not None:
            body = Select(self.condition, body)
        if self.projection:
            if self.restrictor == "shortest":
                inner: PathExpr = restricted(body, "shortest")
            else:
                inner = mode_plan(body, "all", self.restrictor, scope=scope).child.child
            space = GroupBy(self.grouping, inner)
            return Project(*self.projection, OrderBy(self.ordering, space) if self.ordering else space)
        if self.restrictor == "shortest":
            return _moded_shortest(body, self.selector or "all", self.k)
        return mode_plan(body, self.selector or "all", self.restrictor, self.k, scope)


def _moded_shortest(body: PathExpr, selector: str, k: int | None) -> PathExpr:
    plan = mode_plan(EdgesOf(), selector, "walk", k)
    inner = restricted(body, "shortest")

    def over(node):
        if isinstance(node, GroupBy):
            return GroupBy(node.letters, inner)
        return OrderBy(node.letters, over(node.child)) if isinstance(node, OrderBy) else Project(node.p, node.g, node.a, over(node.child))

    return over(plan)


def _bounded(node: PathExpr, max_len: int | None) -> PathExpr:
    from dataclasses import replace

    if max_len is None:
        return node
    if isinstance(node, (Recurse, Star)):
        return replace(node, child=_bounded(node.child, max_len), max_len=max_len)
    names = [n for n in ("left", "right", "child") if hasattr(node, n)]
    return replace(node, **{n: _bounded(getattr(node, n), max_len) for n in names})


class _Parser:
    def __init__(self, text: str) -> None:
        self.t, self.i = tokens(text), 0

    def peek(self, *words: str) -> bool:
        return all(self.t[min(self.i + k, len(self.t) - 1)][1].upper() == w.upper() for k, w in enumerate(words))

    def take(self, *words: str) -> bool:
        if self.peek(*words):
            self.i += len(words)
            return True
        return False

    def need(self, word: str) -> None:
        if not self.take(word):
            raise SyntaxFault(f"expected {word!r}, found {self.t[self.i][1] or 'the end'!r}", self.t[self.i][2])

    def kind(self, kind: str) -> str:
        if self.t[self.i][0] != kind:
            raise SyntaxFault(f"expected a {kind}, found {self.t[self.i][1] or 'the end'!r}", self.t[self.i][2])
        self.i += 1
        return self.t[self.i - 1][1]

    def query(self) -> PathQuery:
        self.take("MATCH")
        selector, k, projection = None, None, ()
        if self.t[self.i][0] == "number" or self.peek("ALL", "PARTITIONS"):
            projection = tuple(self.share(w) for w in ("PARTITIONS", "GROUPS", "PATHS"))
        else:
            selector, k = self.selector()
        restrictor = next((m for m in ("walk", "trail", "acyclic", "simple", "shortest") if self.take(m)), "walk")
        if self.t[self.i][0] == "word" and self.t[self.i + 1][1] == "=":
            self.i += 2
        pattern, condition, ends = self.pattern()
        if self.take("WHERE"):
            more = self.disjunction(ends)
            condition = more if condition is None else condition & more
        grouping = ordering = ""
        if self.take("GROUP"):
            self.take("BY")
            grouping = "".join(x for w, x in (("SOURCE", "S"), ("TARGET", "T"), ("LENGTH", "L")) if self.take(w))
        if self.take("ORDER"):
            self.take("BY")
            ordering = "".join(x for w, x in (("PARTITION", "P"), ("GROUP", "G"), ("PATH", "A")) if self.take(w))
        self.take(".")
        if self.t[self.i][0] != "end":
            raise SyntaxFault(f"not understood: {self.t[self.i][1]!r}", self.t[self.i][2])
        return PathQuery(pattern, condition, restrictor, selector, k, projection, grouping, ordering)

    def share(self, word: str) -> int | str:
        n = "*" if self.take("ALL") else int(self.kind("number"))
        self.need(word)
        return n

    def selector(self) -> tuple[str | None, int | None]:
        for name in ("any shortest", "all shortest", "all"):
            if self.take(*name.split()):
                return name, None
        if self.take("ANY"):
            return ("any k", int(self.kind("number"))) if self.t[self.i][0] == "number" else ("any", None)
        if self.peek("SHORTEST") and self.t[self.i + 1][0] == "number":
            self.i += 1
            k = int(self.kind("number"))
            return ("shortest k group" if self.take("GROUP") else "shortest k"), k
        return None, None

    def end(self, place: Place) -> tuple[str, Condition | None]:
        self.need("(")
        name, condition = "", None
        if self.t[self.i][0] == "word":
            name = self.kind("word").lstrip("?")
        if self.take(":"):
            condition = Term("label", place) == self.kind("word")
        if self.take("{"):
            while not self.take("}"):
                key = self.kind("word")
                self.need(":")
                one = Term("prop", place, key) == self.value()
                condition = one if condition is None else condition & one
                self.take(",")
        self.need(")")
        return name, condition

    def value(self):
        kind, text, at = self.t[self.i]
        self.i += 1
        if kind == "number":
            return float(text) if "." in text else int(text)
        if kind == "string":
            return text[1:-1]
        if text.upper() in ("TRUE", "FALSE"):
            return text.upper() == "TRUE"
        raise SyntaxFault(f"expected a value, found {text!r}", at)

    def pattern(self) -> tuple[PathExpr, Condition | None, dict[str, Place]]:
        x, a = self.end(FIRST)
        self.need("-")
        self.need("[")
        body = self.choice()
        self.need("]")
        self.need("->")
        body = self.repeats(body)
        y, b = self.end(LAST)
        both = [c for c in (a, b) if c is not None]
        return body, reduce(lambda p, q: p & q, both) if both else None, {x: FIRST, y: LAST} if x != y else {x: FIRST}

    def choice(self) -> PathExpr:
        out = self.sequence()
        while self.take("|"):
            out = Union(out, self.sequence())
        return out

    def sequence(self) -> PathExpr:
        out = self.factor()
        while self.take("/"):
            out = Join(out, self.factor())
        return out

    def factor(self) -> PathExpr:
        if self.take("("):
            out = self.choice()
            self.need(")")
        else:
            self.take(":")
            name = self.kind("word").lstrip("?")
            out = Select(Term("label", Place("edge", 1)) == name, EdgesOf())
        return self.repeats(out)

    def repeats(self, out: PathExpr) -> PathExpr:
        while True:
            if self.take("+"):
                out = Recurse(out)
            elif self.take("*"):
                out = Star(out)
            elif self.take("?"):
                out = Union(out, NodesOf())
            elif self.peek("{") and self.t[self.i + 1][0] == "number":
                self.i += 1
                low = int(self.kind("number"))
                high = int(self.kind("number")) if self.take(",") else low
                self.need("}")
                out = repeated(out, low, high)
            else:
                return out

    def disjunction(self, ends: dict[str, Place]) -> Condition:
        out = self.conjunction(ends)
        while self.take("OR"):
            out = out | self.conjunction(ends)
        return out

    def conjunction(self, ends: dict[str, Place]) -> Condition:
        out = self.test(ends)
        while self.take("AND"):
            out = out & self.test(ends)
        return out

    def test(self, ends: dict[str, Place]) -> Condition:
        if self.take("NOT"):
            return ~self.test(ends)
        if self.take("("):
            out = self.disjunction(ends)
            self.need(")")
            return out
        if self.take("bound"):
            self.need("(")
            term = self.term(ends)
            self.need(")")
            return term.is_bound()
        term = self.term(ends)
        at = self.t[self.i][2]
        op = self.kind("mark")
        op = "<>" if op == "!=" else op
        if op not in ("=", "<>", "<", ">", "<=", ">="):
            raise SyntaxFault(f"no comparison {op!r}", at)
        return Test(term, op, self.value())

    def term(self, ends: dict[str, Place]) -> Term:
        at = self.t[self.i][2]
        if self.take("substr"):
            self.need("(")
            inner = self.term(ends)
            self.need(",")
            start = int(self.kind("number"))
            self.need(",")
            n = int(self.kind("number"))
            self.need(")")
            return inner.part(start, n)
        if self.take("len"):
            self.need("(")
            self.need(")")
            return Term("len")
        if self.take("label"):
            self.need("(")
            place = self.place(ends)
            self.need(")")
            return Term("label", place)
        place = self.place(ends)
        if not self.take("."):
            raise SyntaxFault("expected a property", at)
        return Term("prop", place, self.kind("word"))

    def place(self, ends: dict[str, Place]) -> Place:
        at = self.t[self.i][2]
        name = self.kind("word").lstrip("?")
        if name in ("node", "edge") and self.take("("):
            n = int(self.kind("number"))
            self.need(")")
            return Place(name, n)
        if name in ("first", "last"):
            return Place(name)
        if name in ends:
            return ends[name]
        raise SyntaxFault(f"no variable {name!r}", at)


def repeated(step: PathExpr, low: int, high: int) -> PathExpr:
    """low to high times, by joins."""
    if high < low:
        raise ValueError("the upper bound is below the lower")
    power = lambda n: NodesOf() if n == 0 else reduce(lambda a, _: Join(a, step), range(n - 1), step)
    return reduce(Union, [power(n) for n in range(low, high + 1)])


def parse(text: str) -> PathQuery:
    return _Parser(text).query()


def plan_of(text: str, **options) -> PathExpr:
    return parse(text).plan(**options)


def explain(text: str, **options) -> str:
    """The plan of a query as text; no Spark job runs."""
    from .rewrite import optimise

    plan = plan_of(text, **options)
    return f"as written\n{show(plan, 1)}\nas run\n{show(optimise(plan), 1)}"

"""Plan nodes in two sorts: expressions of path sets, and of solution spaces, so that no ill-typed plan can be built."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

from ..operators.conditions import Condition


class PathExpr:
    pass


class SpaceExpr:
    pass


@dataclass(frozen=True, eq=False)
class NodesOf(PathExpr):
    pass


@dataclass(frozen=True, eq=False)
class EdgesOf(PathExpr):
    labels: tuple[str, ...] | None = None


@dataclass(frozen=True, eq=False)
class Select(PathExpr):
    condition: Condition
    child: PathExpr


@dataclass(frozen=True, eq=False)
class Join(PathExpr):
    left: PathExpr
    right: PathExpr


@dataclass(frozen=True, eq=False)
class Union(PathExpr):
    left: PathExpr
    right: PathExpr


@dataclass(frozen=True, eq=False)
class Recurse(PathExpr):
    """One or more. seed: a condition on the first node (last, if backward) that only the start must meet."""

    child: PathExpr
    mode: str = "walk"
    max_len: int | None = None
    seed: Condition | None = None
    backward: bool = False
    keep: tuple[str, int] | None = None


@dataclass(frozen=True, eq=False)
class Star(PathExpr):
    """Zero or more: the recursion and the nodes of the graph."""

    child: PathExpr
    mode: str = "walk"
    max_len: int | None = None
    seed: Condition | None = None
    backward: bool = False


@dataclass(frozen=True, eq=False)
class Restrict(PathExpr):
    mode: str
    child: PathExpr


@dataclass(frozen=True, eq=False)
class GroupBy(SpaceExpr):
    letters: str
    child: PathExpr


@dataclass(frozen=True, eq=False)
class OrderBy(SpaceExpr):
    letters: str
    child: SpaceExpr


@dataclass(frozen=True, eq=False)
class Project(PathExpr):
    p: int | str
    g: int | str
    a: int | str
    child: SpaceExpr
    desc: str = ""


def children(node) -> list:
    return [getattr(node, f) for f in ("left", "right", "child") if hasattr(node, f)]


def walk(node) -> Iterator:
    yield node
    for c in children(node):
        yield from walk(c)


def title(node) -> str:
    """One line for a node, without its operands."""
    match node:
        case NodesOf():
            return "all nodes"
        case EdgesOf(labels):
            return "all edges" if labels is None else f"edges labelled {', '.join(labels)}"
        case Select(c, _):
            return f"select {c}"
        case Join():
            return "concatenate"
        case Union():
            return "unite"
        case Recurse(_, mode, max_len, seed, back) | Star(_, mode, max_len, seed, back):
            keep = getattr(node, "keep", None)
            extra = [f"at most {max_len} edges"] * (max_len is not None) + [f"{'ending' if back else 'starting'} where {seed}"] * (seed is not None) + ([f"{keep[0]} {keep[1]}"] if keep else [])
            return ("repeat once or more" if isinstance(node, Recurse) else "repeat any times") + f" as {mode}" + (f" ({'; '.join(extra)})" if extra else "")
        case Restrict(mode, _):
            return f"whole path is {mode}"
        case GroupBy(letters, _):
            return "group by " + (", ".join({"S": "source", "T": "target", "L": "length"}[x] for x in letters) or "nothing")
        case OrderBy(letters, _):
            return "order " + ", ".join({"P": "partitions", "G": "groups", "A": "paths"}[x] for x in letters)
        case Project(p, g, a, _, desc):
            return f"take partitions {p}, groups {g}, paths {a}" + (f" from the top of {desc}" if desc else "")
    raise TypeError(node)


def show(node, depth: int = 0) -> str:
    """The plan as indented lines."""
    return "\n".join(["  " * depth + title(node), *(show(c, depth + 1) for c in children(node))])

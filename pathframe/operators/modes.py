"""Path modes: seven selectors by four restrictors (and shortest as a fifth), as plans over the algebra."""

from __future__ import annotations

from ..plans.nodes import GroupBy, Join, OrderBy, PathExpr, Project, Recurse, Restrict, Select, Star, Union

SELECTORS = ("all", "any shortest", "all shortest", "any", "any k", "shortest k", "shortest k group")
RESTRICTORS = ("walk", "trail", "acyclic", "simple")
#: selector: (grouping, ordering, partitions, groups, paths); "k" stands for the number given.
SHAPES = {
    "all": ("", "", "*", "*", "*"),
    "any shortest": ("ST", "A", "*", "*", 1),
    "all shortest": ("STL", "G", "*", 1, "*"),
    "any": ("ST", "", "*", "*", 1),
    "any k": ("ST", "", "*", "*", "k"),
    "shortest k": ("ST", "A", "*", "*", "k"),
    "shortest k group": ("STL", "G", "*", "k", "*"),
}


def restricted(pattern: PathExpr, mode: str) -> PathExpr:
    """Every recursion of the pattern under the mode."""
    match pattern:
        case Recurse(child, _, max_len, seed, back, keep):
            return Recurse(restricted(child, mode), mode, max_len, seed, back, keep)
        case Star(child, _, max_len, seed, back):
            return Star(restricted(child, mode), mode, max_len, seed, back)
        case Select(c, child):
            return Select(c, restricted(child, mode))
        case Join(a, b):
            return Join(restricted(a, mode), restricted(b, mode))
        case Union(a, b):
            return Union(restricted(a, mode), restricted(b, mode))
    return pattern


def _recursive_whole(pattern: PathExpr) -> bool:
    """Whether the pattern is one recursion over edges (under selections), whose own test covers the whole path."""
    while isinstance(pattern, Select):
        pattern = pattern.child
    return isinstance(pattern, (Recurse, Star))


def mode_plan(pattern: PathExpr, selector: str = "all", restrictor: str = "walk", k: int | None = None, scope: str = "path") -> PathExpr:
    """Plan of a selector and a restrictor over a pattern.

    scope "path": the restrictor holds for each recursion and for the whole path; "recursion": inside recursions only.
    """
    selector, restrictor = selector.lower(), restrictor.lower()
    if selector not in SHAPES:
        raise ValueError(f"no selector {selector!r}")
    if "k" in SHAPES[selector] and not k:
        raise ValueError(f"{selector!r} needs a number")
    inner = restricted(pattern, restrictor)
    if scope == "path" and restrictor != "walk" and not _recursive_whole(inner):
        inner = Restrict(restrictor, inner)
    grouping, ordering, p, g, a = SHAPES[selector]
    space = GroupBy(grouping, inner)
    if ordering:
        space = OrderBy(ordering, space)
    n = lambda x: k if x == "k" else x
    return Project(p, n(g), n(a), space)


def concat_queries(a: PathExpr, b: PathExpr, selector: str, restrictor: str, k: int | None = None) -> PathExpr:
    """An outer selector and restrictor over the concatenation of two moded queries."""
    whole = Join(a, b) if restrictor == "walk" else Restrict(restrictor, Join(a, b))
    grouping, ordering, p, g, n = SHAPES[selector]
    space = GroupBy(grouping, whole)
    if ordering:
        space = OrderBy(ordering, space)
    pick = lambda x: k if x == "k" else x
    return Project(p, pick(g), pick(n), space)


def union_queries(a: PathExpr, b: PathExpr) -> PathExpr:
    return Union(a, b)

"""Rewriting of plans. Each rule is a pure function from a node to an equal node, or None where it has nothing to do."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from ..operators.conditions import And, Condition, Not, Or, Test, conjuncts, shifted, tests
from .nodes import EdgesOf, GroupBy, Join, NodesOf, OrderBy, PathExpr, Project, Recurse, Restrict, Select, Star, Union, walk


def lengths(node: PathExpr) -> tuple[int, int | None]:
    """Least and most length that the paths of a plan can have; None: unbounded."""
    match node:
        case NodesOf():
            return 0, 0
        case EdgesOf():
            return 1, 1
        case Select(_, child) | Restrict(_, child):
            return lengths(child)
        case Join(a, b):
            (x, y), (u, v) = lengths(a), lengths(b)
            return x + u, None if None in (y, v) else y + v
        case Union(a, b):
            (x, y), (u, v) = lengths(a), lengths(b)
            return min(x, u), None if None in (y, v) else max(y, v)
        case Recurse(child, _, max_len):
            return lengths(child)[0], max_len
        case Star(child, _, max_len):
            return 0, max_len
        case Project(_, _, _, child):
            while not isinstance(child, GroupBy):
                child = child.child
            return lengths(child.child)
    return 0, None


def _both(conditions: list[Condition]) -> Condition:
    out = conditions[0]
    for c in conditions[1:]:
        out = And(out, c)
    return out


def _only(c: Condition, what: str) -> bool:
    """Whether every test of c is about one end of the path."""
    return all(t.term.place is not None and t.term.place.what == what for t in tests(c))


def split_over_union(node):
    """A selection over a union goes to both sides."""
    if isinstance(node, Select) and isinstance(node.child, Union):
        return Union(Select(node.condition, node.child.left), Select(node.condition, node.child.right))


def merge_selections(node):
    if isinstance(node, Select) and isinstance(node.child, Select):
        return Select(And(node.condition, node.child.condition), node.child.child)


def fold_label(node):
    """A test that the one edge has a label becomes the choice of edge tables, so other tables aren't read."""
    if isinstance(node, Select) and isinstance(node.child, EdgesOf):
        parts = conjuncts(node.condition)
        for i, c in enumerate(parts):
            if isinstance(c, Test) and c.term.kind == "label" and c.term.place.what == "edge" and c.term.place.at == 1 and c.term.substr is None and c.op in ("=", "in"):
                wanted = (c.value,) if c.op == "=" else tuple(c.value)
                labels = wanted if node.child.labels is None else tuple(x for x in node.child.labels if x in wanted)
                rest = parts[:i] + parts[i + 1 :]
                return Select(_both(rest), EdgesOf(labels)) if rest else EdgesOf(labels)


def push_into_join(node):
    """Tests of the first node go left, of the last right; of numbered places left while the left operand always has
    them, else right, moved, when the left has one length."""
    if not (isinstance(node, Select) and isinstance(node.child, Join)):
        return None
    a, b = node.child.left, node.child.right
    least, most = lengths(a)
    left, right, stay = [], [], []
    for c in conjuncts(node.condition):
        places = [t.term.place for t in tests(c)]
        numbered = all(p is not None and p.what in ("node", "edge") for p in places)
        if _only(c, "first"):
            left.append(c)
        elif _only(c, "last"):
            right.append(c)
        elif numbered and all(p.at <= least + (p.what == "node") for p in places):
            left.append(c)
        elif numbered and least == most and all(p.at > least for p in places):
            right.append(shifted(c, -least))
        else:
            stay.append(c)
    if not left and not right:
        return None
    out = Join(Select(_both(left), a) if left else a, Select(_both(right), b) if right else b)
    return Select(_both(stay), out) if stay else out


def seed_recursion(node):
    """Tests of the first node over a recursion choose where it starts; its steps stay whole. Tests of the last node
    do the same for a recursion run backwards, where none of the first are."""
    if not (isinstance(node, Select) and isinstance(node.child, (Recurse, Star))):
        return None
    inner, parts = node.child, conjuncts(node.condition)
    for what, back in (("first", False), ("last", True)):
        mine = [c for c in parts if _only(c, what)]
        if mine and (inner.seed is None or inner.backward == back):
            seed = _both(mine + ([inner.seed] if inner.seed is not None else []))
            rest = [c for c in parts if c not in mine]
            # a backward recursion reads paths reversed, so its seed speaks of the first node there
            out = replace(inner, seed=_as_first(seed) if back else seed, backward=back)
            return Select(_both(rest), out) if rest else out


def _as_first(c: Condition) -> Condition:
    from ..operators.conditions import FIRST

    if isinstance(c, (And, Or)):
        return type(c)(_as_first(c.a), _as_first(c.b))
    if isinstance(c, Not):
        return Not(_as_first(c.a))
    return Test(replace(c.term, place=FIRST), c.op, c.value)


def bound_length(node):
    """len() = n, <= n or < n over a recursion also bounds its rounds; the test itself stays."""
    if isinstance(node, Select) and isinstance(node.child, (Recurse, Star)):
        for c in conjuncts(node.condition):
            if isinstance(c, Test) and c.term.kind == "len" and c.term.substr is None and c.op in ("=", "<=", "<"):
                n = int(c.value) - (c.op == "<")
                if node.child.max_len is None or node.child.max_len > n:
                    return Select(node.condition, replace(node.child, max_len=n))


def _mode_shape(node):
    """(p, g, a, order letters, grouping, child) of a projection, else None."""
    if not isinstance(node, Project) or node.desc:
        return None
    space, letters = node.child, set()
    while isinstance(space, OrderBy):
        letters |= set(space.letters)
        space = space.child
    return node.p, node.g, node.a, letters, space.letters, space.child


def _bounded(node: PathExpr, how) -> PathExpr | None:
    """The pattern with every walk recursion cut by how, or None where some part looks at more than ends.

    Parts of a best walk are best for their own ends (put in a better part and the whole gets better), so cutting each
    recursion loses nothing that a limit over pairs of ends still takes after joins and unions.
    """
    match node:
        case NodesOf() | EdgesOf():
            return node
        case Select(c, child):
            if not any(isinstance(x, (Recurse, Star)) for x in walk(child)):
                return node
            inner = _bounded(child, how) if all(_only(x, "first") or _only(x, "last") for x in conjuncts(c)) else None
            return inner and Select(c, inner)
        case Join(a, b) | Union(a, b):
            x, y = _bounded(a, how), _bounded(b, how)
            return x and y and type(node)(x, y)
        case Recurse(child, "walk") | Star(child, "walk") if not getattr(node, "keep", None):
            inner = _bounded(child, how)
            return how(replace(node, child=inner)) if inner and lengths(inner)[0] >= 1 else None
    return None


def bound_walks(node):
    """Selectors over walks that need no more than the best of each pair of ends: all shortest, any, any shortest, and
    their k. Only recursions without a bound of their own are changed."""
    shape = _mode_shape(node)
    if shape is None:
        return None
    p, g, a, letters, grouping, inner = shape
    if not any(isinstance(x, (Recurse, Star)) and x.mode == "walk" and x.max_len is None and not getattr(x, "keep", None) for x in walk(inner)):
        return None
    shortest = lambda r: replace(r, mode="shortest")
    kept = lambda how, k: lambda r: replace(r, keep=(how, k)) if isinstance(r, Recurse) else Union(Recurse(r.child, r.mode, r.max_len, r.seed, r.backward, (how, k)), NodesOf()) if r.seed is None else None
    out = None
    if p == "*" and set(grouping) == set("STL") and "G" in letters and g != "*":
        out = _bounded(inner, shortest if g == 1 else kept("k_lengths", g))
    elif p == "*" and set(grouping) == set("ST") and a != "*":
        # any of a pair's walks may be taken where no order is asked, so its best are lawful
        out = _bounded(inner, shortest if a == 1 else kept("k_shortest", a))
    elif p in (1, "*") and set(grouping) == set("L") and "G" in letters and g == 1:
        # the least walks of all are least for their ends: the outer operators stay
        out = _bounded(inner, shortest)
    return None if out is None else _over(node, out)


def _over(node: Project, inner: PathExpr) -> Project:
    def rebuilt(space):
        return replace(space, child=rebuilt(space.child)) if isinstance(space, OrderBy) else replace(space, child=inner)

    return replace(node, child=rebuilt(node.child))


def one_arbitrary_walk(node):
    """One unordered path of a single group of walks over single edges: any trail will do, and trails end."""
    shape = _mode_shape(node)
    if shape and isinstance(shape[-1], Recurse) and shape[-1].mode == "walk" and not shape[-1].keep and shape[-1].max_len is None:
        p, g, a, letters, grouping, inner = shape
        ordered = ("A" in letters) or ("G" in letters and "L" in grouping and g != "*") or ("P" in letters and p != "*")
        if a == 1 and not ordered and "L" not in grouping and lengths(inner.child) == (1, 1):
            return _over(node, replace(inner, mode="trail"))


def useless_orders(node):
    """Orders that no limit reads: of partitions where there is one or all are taken, of groups likewise, of paths
    where all are taken or a group has one length; and a projection of everything."""
    shape = _mode_shape(node)
    if shape is None:
        return None
    p, g, a, letters, grouping, inner = shape
    if (p, g, a) == ("*", "*", "*"):
        return inner
    useless = set()
    if p == "*" or not set(grouping) & set("ST"):
        useless.add("P")
    if g == "*" or "L" not in grouping:
        useless.add("G")
    if a == "*" or "L" in grouping:
        useless.add("A")
    if letters & useless:
        kept = "".join(x for x in "PGA" if x in letters - useless)
        space = GroupBy(grouping, inner)
        return replace(node, child=OrderBy(kept, space) if kept else space)


def select_below_projection(node):
    """A test of an end that is part of the partition key picks whole partitions: it may go below a projection that
    takes all partitions."""
    if isinstance(node, Select) and isinstance(node.child, Project) and not node.child.desc:
        p, g, a, letters, grouping, inner = _mode_shape(node.child)
        parts = conjuncts(node.condition)
        mine = [c for c in parts if p == "*" and (_only(c, "first") and "S" in grouping or _only(c, "last") and "T" in grouping)]
        if mine:
            rest = [c for c in parts if c not in mine]
            out = _over(node.child, Select(_both(mine), inner))
            return Select(_both(rest), out) if rest else out


RULES: tuple[Callable, ...] = (merge_selections, split_over_union, fold_label, push_into_join, seed_recursion, bound_length, select_below_projection, useless_orders, bound_walks, one_arbitrary_walk)


def single_pair_shortest(node):
    """The rewriting to a shortest recursion without the outer operators. It holds only where all paths share one pair
    of ends, which the caller must know; it is in no default list of rules."""
    shape = _mode_shape(node)
    if shape and isinstance(shape[-1], Recurse) and shape[-1].mode == "walk" and shape[0] == 1 and shape[1] == 1 and shape[2] == "*" and shape[4] == "L" and "G" in shape[3]:
        return replace(shape[-1], mode="shortest")


def optimise(plan, rules: tuple[Callable, ...] = RULES, most: int = 1000):
    """Rules from the top down until none changes the plan."""
    for _ in range(most):
        after = _once(plan, rules)
        if after is None:
            return plan
        plan = after
    raise RuntimeError("rewriting did not settle")


def _once(node, rules):
    for rule in rules:
        if (out := rule(node)) is not None:
            return out
    for name in ("left", "right", "child"):
        if hasattr(node, name) and (out := _once(getattr(node, name), rules)) is not None:
            return replace(node, **{name: out})
    return None

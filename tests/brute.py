"""Plain enumeration of paths over small graphs, for comparison."""


def lawful(mode, nodes, edges):
    closed = len(edges) > 0 and nodes[0] == nodes[-1]
    if mode == "trail":
        return len(set(edges)) == len(edges)
    if mode == "acyclic":
        return len(set(nodes)) == len(nodes)
    if mode == "simple":
        return len(set(nodes)) == len(nodes) or (closed and len(set(nodes)) == len(nodes) - 1)
    return True


def recursion(base, mode, bound=8):
    """Lawful concatenations of base paths ((nodes), (edges)) of at most `bound` edges."""
    known = {p for p in base if lawful(mode, *p) and len(p[1]) <= bound}
    new = set(known)
    while new:
        grown = set()
        for nodes, edges in new:
            for n2, e2 in base:
                if n2[0] == nodes[-1] and len(edges) + len(e2) <= bound:
                    p = (nodes + n2[1:], edges + e2)
                    if lawful(mode, *p) and p not in known:
                        grown.add(p)
        known |= grown
        new = grown
    if mode == "shortest":
        least = {}
        for nodes, edges in known:
            k = (nodes[0], nodes[-1])
            least[k] = min(least.get(k, 99), len(edges))
        known = {p for p in known if len(p[1]) == least[p[0][0], p[0][-1]]}
    return known


def project(paths, letters, orders, p, g, a):
    """Partitions, groups and paths taken in order; ties by key, and by length, nodes, edges."""
    part = lambda x: tuple(v for c, v in (("S", x[0][0]), ("T", x[0][-1])) if c in letters)
    group = lambda x: (len(x[1]),) if "L" in letters else ()
    parts = {}
    for x in paths:
        parts.setdefault(part(x), {}).setdefault(group(x), []).append(x)
    least = lambda xs: min(len(x[1]) for x in xs)
    cut = lambda xs, n: xs if n == "*" else xs[:n]
    out = set()
    by_part = sorted(parts, key=lambda k: (least(sum(parts[k].values(), [])) if "P" in orders else 1, k))
    for k in cut(by_part, p):
        by_group = sorted(parts[k], key=lambda h: (least(parts[k][h]) if "G" in orders else 1, h))
        for h in cut(by_group, g):
            xs = sorted(parts[k][h], key=lambda x: (len(x[1]) if "A" in orders else 1, len(x[1]), x[0], x[1]))
            out |= set(cut(xs, a))
    return out


def rows(path_set):
    return {(tuple(r["nodes"]), tuple(r["edges"])) for r in path_set.df.collect()}

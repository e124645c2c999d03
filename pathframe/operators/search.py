"""Shortest walks and the closure of all pairs without rounds: tasks hold the steps and search from their share of the
first nodes.

Distances come first, by breadth from many first nodes at once; walks are then grown along steps that lose nothing, depth
first in pieces, so that a task holds some pieces of each length, never all walks. No row is written on the way or met by
another: they are made as the result is read.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import paths as P

#: Steps that a task may hold; of more, shortest walks are found round by round.
HELD = 1_000_000
#: Pairs whose distances a task keeps at once (or those of one first node), and edges of a piece of walks (or one walk).
PAIRS, CELLS = 1 << 20, 1 << 17
#: A connected part of fewer nodes has no hub. First nodes and last nodes of a block of pairs.
PART, FIRSTS, LASTS = 64, 64, 1024


def shortest_of_all(steps: DataFrame, one: bool = False) -> DataFrame:
    """All shortest walks (one: the first of each pair by nodes, then edges) over steps of one edge, at most HELD. The
    steps reach the tasks by broadcast: dealt out by a shuffle, each task's copy of them would be on disk."""
    spread = max(8, 4 * steps.sparkSession.sparkContext.defaultParallelism)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[pa.RecordBatch]] = {}
        for batch in batches:
            for task in pc.unique(batch.column("__task")).to_pylist():
                held.setdefault(task, []).append(batch.filter(pc.equal(batch.column("__task"), task)))
        for parts in held.values():
            task, found = parts[0].column("__task")[0].as_py(), Search(pa.Table.from_batches(parts))
            yield from found.rows(np.arange(task, found.n, spread), one)

    flat = steps.select("src", "dst", F.get("edges", F.lit(0)).alias("edge"), F.get("elabels", F.lit(0)).alias("label"))
    tasks = steps.sparkSession.range(0, spread, 1, spread).select(F.col("id").alias("__task"))
    return tasks.crossJoin(F.broadcast(flat)).mapInArrow(run, steps.select(*P.PATH_COLUMNS).schema)


def _numbered(src: pa.Array, dst: pa.Array) -> tuple[pa.Array, np.ndarray, np.ndarray]:
    """Ids in their order, then two missing ones; and the numbers of the first and the last nodes."""
    ids = pc.unique(pa.chunked_array([src, dst])).drop_null()
    ids = ids.take(pc.array_sort_indices(ids))
    code = lambda of, missing: pc.fill_null(pc.index_in(of, value_set=ids, skip_nulls=True), missing).to_numpy().astype(np.int64)
    return pa.concat_arrays([ids, pa.nulls(2, ids.type)]), code(src, len(ids)), code(dst, len(ids) + 1)


def _ways(starts: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Steps from each node of `at`: the node's place in it, and the step."""
    many = starts[at + 1] - starts[at]
    before = np.cumsum(many) - many
    return np.repeat(np.arange(len(at)), many), np.arange(many.sum()) + np.repeat(starts[at] - before, many)


class Search:
    """Steps by first node, in the order of their last nodes and edges; nodes are numbered in the order of their ids.

    A missing id is no node that a step could go on from: as a first node and as a last one it is numbered apart.
    """

    def __init__(self, steps: pa.Table) -> None:
        src, dst, edge, label = (steps.column(k).combine_chunks() for k in ("src", "dst", "edge", "label"))
        self.ids, a, b = _numbered(src, dst)
        self.n = len(self.ids)
        rank = np.empty(len(edge), np.int64)
        rank[pc.array_sort_indices(edge, null_placement="at_start").to_numpy()] = np.arange(len(edge))
        order = np.lexsort((rank, b, a))
        self.dst, self.starts = b[order], np.searchsorted(a[order], np.arange(self.n + 1))
        self.edge, self.label = edge.take(pa.array(order)), label.take(pa.array(order))

    def _on(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Steps from each node of `at`: the node's place in it, and the step."""
        return _ways(self.starts, at)

    def rows(self, firsts: np.ndarray, one: bool) -> Iterator[pa.RecordBatch]:
        some = max(1, PAIRS // self.n)
        for k in range(0, len(firsts), some):
            own = firsts[k : k + some]
            for first, made in self._first_walks(own) if one else self._all_walks(own):
                yield self._batch(first, made)

    def _far(self, firsts: np.ndarray) -> np.ndarray:
        """Distances by (place of the first node) * n + last node; 0 where there is no way."""
        far, row, at, level = np.zeros(len(firsts) * self.n, np.int32), np.arange(len(firsts)), firsts, 0
        while len(at):
            level += 1
            k, step = self._on(at)
            pair = row[k] * self.n + self.dst[step]
            pair = np.unique(pair[far[pair] == 0])
            far[pair] = level
            row, at = np.divmod(pair, self.n)
        return far

    def _all_walks(self, firsts: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        far = self._far(firsts)
        row, step = self._on(firsts)
        # to be made: walks of the piece `made`, by their places in it, each with its first node's place and a next step
        due = [(np.zeros((len(row), 0), np.int32), np.arange(len(row)), row, step)] if len(row) else []
        while due:
            before, place, row, step = due.pop()
            level = before.shape[1] + 1
            if len(step) > (some := max(1, CELLS // level)):
                due.append((before, place[:-some], row[:-some], step[:-some]))
                place, row, step = place[-some:], row[-some:], step[-some:]
            made = np.concatenate([before[place], step[:, None].astype(np.int32)], axis=1)
            yield firsts[row], made
            k, step = self._on(self.dst[step])
            row = row[k]
            on = np.flatnonzero(far[row * self.n + self.dst[step]] == level + 1)
            if len(on):
                due.append((made, k[on], row[on], step[on]))

    def _first_walks(self, firsts: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """One walk a pair. Walks of a length stand by first node, then in their own order, and so do the steps that
        follow them, so of those that meet in a pair the first is the least."""
        far, row, at, levels = np.zeros(len(firsts) * self.n, bool), np.arange(len(firsts)), firsts, []
        while len(at):
            k, step = self._on(at)
            pair = row[k] * self.n + self.dst[step]
            new = np.flatnonzero(~far[pair])
            new = new[np.sort(np.unique(pair[new], return_index=True)[1])]
            far[pair[new]] = True
            row, at = np.divmod(pair[new], self.n)
            levels.append((k[new], step[new]))
            some = max(1, CELLS // len(levels))
            for a in range(0, len(new), some):
                place, made = np.arange(a, min(a + some, len(new))), []
                for parent, taken in reversed(levels):
                    made.append(taken[place])
                    place = parent[place]
                yield firsts[place], np.stack(made[::-1], axis=1)

    def _batch(self, first: np.ndarray, made: np.ndarray) -> pa.RecordBatch:
        many, length = made.shape
        nodes = np.concatenate([first[:, None], self.dst[made]], axis=1)
        lists = lambda of, at: pa.ListArray.from_arrays(pa.array(np.arange(0, at.size + 1, at.shape[1], dtype=np.int32)), of.take(pa.array(at.ravel())))
        columns = [self.ids.take(pa.array(first)), self.ids.take(pa.array(nodes[:, -1])), pa.array(np.full(many, length, np.int32)), lists(self.ids, nodes), lists(self.edge, made), lists(self.label, made)]
        return pa.RecordBatch.from_arrays(columns, list(P.PATH_COLUMNS))


def parts_of(steps: DataFrame) -> DataFrame:
    """What the closure of steps (src, dst; at most HELD, none twice) is made of, found in one task that holds them.

    One node of each larger connected part is its hub. Of way 0 are blocks of the nodes that reach a hub, of way 1 blocks of
    those reached from it: all pairs of the two sides of a part are in the closure. Of way 2 are the steps clear of all nodes
    on a cycle with a hub, with whether the first node reaches the hub (__in) and the last is reached from it (__out).
    """
    kind = steps.schema["src"].dataType.simpleString()

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if held := list(batches):
            table = pa.Table.from_batches(held)
            yield from Parts(table.column("src").combine_chunks(), table.column("dst").combine_chunks()).rows()

    return steps.select("src", "dst").coalesce(1).mapInArrow(run, f"way int, part long, block long, ids array<{kind}>, src {kind}, dst {kind}, __in boolean, __out boolean")


def closure_of_parts(parts: DataFrame) -> DataFrame:
    """The pairs (src, dst), each once, made as the result is read; blocks of a part's two sides meet in the tasks, so that
    its pairs are spread over all of them."""
    spark, kind = parts.sparkSession, parts.schema["src"].dataType.simpleString()
    spread = max(8, 4 * spark.sparkContext.defaultParallelism)
    firsts = parts.filter("way = 0").select("part", "block", F.col("ids").alias("__from")).repartition(spread, "part", "block")
    lasts = parts.filter("way = 1").select("part", F.col("ids").alias("__to"))
    joined = firsts.join(F.broadcast(lasts), "part").select(F.explode("__from").alias("src"), "__to").select("src", F.explode("__to").alias("dst"))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[pa.RecordBatch]] = {}
        for batch in batches:
            for task in pc.unique(batch.column("__task")).to_pylist():
                held.setdefault(task, []).append(batch.filter(pc.equal(batch.column("__task"), task)))
        for task, own in held.items():
            yield from _closed(pa.Table.from_batches(own), task, spread)

    tasks = spark.range(0, spread, 1, spread).select(F.col("id").alias("__task"))
    rest = tasks.crossJoin(F.broadcast(parts.filter("way = 2").select("src", "dst", "__in", "__out")))
    return joined.unionByName(rest.mapInArrow(run, f"src {kind}, dst {kind}"))


def _closed(steps: pa.Table, task: int, spread: int) -> Iterator[pa.RecordBatch]:
    """Pairs along the steps from every spread-th first node, without those of which a hub joins both."""
    ids, a, b = _numbered(*(steps.column(k).combine_chunks() for k in ("src", "dst")))
    n, order = len(ids), np.argsort(a, kind="stable")
    inward, onward = np.zeros(n, bool), np.zeros(n, bool)
    inward[a], onward[b] = (steps.column(k).to_numpy() for k in ("__in", "__out"))
    starts, to, firsts = np.searchsorted(a[order], np.arange(n + 1)), b[order], np.unique(a)[task::spread]
    some = max(1, PAIRS // n)
    seen = np.zeros(some * n, bool)
    for x in range(0, len(firsts), some):
        own = firsts[x : x + some]
        row, at, made = np.arange(len(own)), own, []
        while len(at):
            k, step = _ways(starts, at)
            row, at = row[k], to[step]
            pair = row * n + at
            pair = np.unique(pair[~seen[pair] & ~(inward[own[row]] & onward[at])])
            seen[pair] = True
            made.append(pair)
            row, at = np.divmod(pair, n)
        pair = np.concatenate(made)
        seen[pair] = False
        row, at = np.divmod(pair, n)
        yield pa.RecordBatch.from_arrays([ids.take(pa.array(own[row])), ids.take(pa.array(at))], ["src", "dst"])


class Parts:
    """The connected parts of a graph, their hubs, and which nodes reach those or are reached from them."""

    def __init__(self, src: pa.Array, dst: pa.Array) -> None:
        self.ids, self.a, self.b = _numbered(src, dst)
        self.n = len(self.ids)
        root = self._roots()
        ways = np.bincount(self.a, minlength=self.n) * np.bincount(self.b, minlength=self.n)
        order = np.lexsort((-ways, root))
        hubs = order[np.unique(root[order], return_index=True)[1]]
        self.hubs = hubs[np.bincount(root, minlength=self.n)[root[hubs]] >= PART]
        self.onward, self.inward = self._reached(self.a, self.b), self._reached(self.b, self.a)
        self.root, open_ = root, self.hubs[~self.onward[self.hubs]]
        self.onward[self.hubs] = self.inward[self.hubs] = True
        self.open = np.zeros(self.n, bool)  # hubs that no cycle meets, and that so aren't joined with themselves
        self.open[open_] = True

    def _roots(self) -> np.ndarray:
        """For each node the least one of its part."""
        root = np.arange(self.n)
        while True:
            a, b = root[self.a], root[self.b]
            if (a == b).all():
                return root
            np.minimum.at(root, np.maximum(a, b), np.minimum(a, b))
            while (root[root] != root).any():
                root = root[root]

    def _reached(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Nodes that one or more steps from a to b lead to from the hubs."""
        order = np.argsort(a, kind="stable")
        starts, to, seen, at = np.searchsorted(a[order], np.arange(self.n + 1)), b[order], np.zeros(self.n, bool), self.hubs
        while len(at):
            at = to[_ways(starts, at)[1]]
            at = np.unique(at[~seen[at]])
            seen[at] = True
        return seen

    def rows(self) -> Iterator[pa.RecordBatch]:
        inward, onward = np.flatnonzero(self.inward), np.flatnonzero(self.onward)
        # an open hub is apart from those that reach it, as it has one pair less
        alone, rest = self.open[inward], onward[~self.open[onward]]
        rest = rest[np.isin(self.root[rest], self.root[self.open])]
        yield self._blocks(0, inward, 2 * self.root[inward] + alone, FIRSTS)
        yield self._blocks(1, np.concatenate([onward, rest]), 2 * self.root[np.concatenate([onward, rest])] + np.repeat([0, 1], [len(onward), len(rest)]), LASTS)
        core = self.inward & self.onward
        into, out = self.inward[self.a], self.onward[self.b]
        own = np.flatnonzero(~core[self.a] & ~core[self.b] & ~(into & out))
        ids = lambda of: self.ids.take(pa.array(of[own]))
        yield self._batch(2, len(own), src=ids(self.a), dst=ids(self.b), __in=pa.array(into[own]), __out=pa.array(out[own]))

    def _blocks(self, way: int, nodes: np.ndarray, part: np.ndarray, most: int) -> pa.RecordBatch:
        order = np.argsort(part, kind="stable")
        nodes, part = nodes[order], part[order]
        place = np.arange(len(part)) - np.searchsorted(part, part)
        cut = np.flatnonzero(place % most == 0)
        lists = pa.ListArray.from_arrays(pa.array(np.append(cut, len(part)).astype(np.int32)), self.ids.take(pa.array(nodes)))
        return self._batch(way, len(cut), part=pa.array(part[cut]), block=pa.array(place[cut] // most), ids=lists)

    def _batch(self, way: int, many: int, **columns: pa.Array) -> pa.RecordBatch:
        kinds = {"part": pa.int64(), "block": pa.int64(), "ids": pa.list_(self.ids.type), "src": self.ids.type, "dst": self.ids.type, "__in": pa.bool_(), "__out": pa.bool_()}
        return pa.RecordBatch.from_pydict({"way": pa.array(np.full(many, way, np.int32))} | {k: columns.get(k, pa.nulls(many, t)) for k, t in kinds.items()})

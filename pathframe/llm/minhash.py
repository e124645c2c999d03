"""Near-duplicate documents by b-bit MinHash, with links confirmed on the full shingle sets.

1. One pass over the texts gives each document's set size, a 128-bit hash of its set, 25 band hashes of 5 minima each,
   and the low 2 bits of 128 minima packed in 32 bytes.
2. Documents of equal sets are one class, represented by its smallest doc_id.
3. Representatives that share a band are compared by packed signatures: equal 2-bit fields, corrected for chance
   collisions. Pairs whose corrected estimate reaches a floor far below the threshold tie a cluster together; a
   group hands on a spanning forest of such pairs, never all of them.
4. Within a cluster every pair of different texts is confirmed or refused by its exact intersection, over an inverted
   index of the cluster's shingles; again a spanning forest goes on, and components are taken over it.

Groups and clusters beyond a bound are cut in blocks, and each pair of blocks is one task's work. At the threshold a
pair shares no band with probability 4e-7, and falls below the floor with 1e-7.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_bounded, chunks, free_name, stored
from .components import components

#: Words of a shingle; link when 100 * shared >= LINK * united.
WORDS, LINK = 5, 85
BANDS, ROWS, MINIMA = 25, 5, 128
#: Bytes from which on a word is hashed by a digest.
LONG_WORD = 64
#: Share of equal minima that a candidate's corrected estimate must reach.
FLOOR = 0.65
#: Rows of a group or cluster, and shingles of a cluster, that one block holds.
BLOCK_ROWS, BLOCK_SHINGLES = 1000, 2_000_000

_U = np.uint64
_rng = np.random.default_rng(7)
_BYTE = _rng.integers(1, 2**64, 256, dtype=_U)
_BYTE[0x41:0x5B] = _BYTE[0x61:0x7B]  # A-Z hash as a-z
_STEP = _U(0x9E3779B97F4A7C15)
_BACK = _U(pow(int(_STEP), -1, 2**64))
_SCALE = _rng.integers(0, 2**31, MINIMA, dtype=np.uint32) * np.uint32(2) + np.uint32(1)
_SHIFT = _rng.integers(0, 2**32, MINIMA, dtype=np.uint32)
_BAND = _rng.integers(0, 2**63, (BANDS, ROWS), dtype=_U) * _U(2) + _U(1)
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(33))) * _U(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> _U(33))) * _U(0xC4CEB9FE1A85EC53)
    return x ^ (x >> _U(33))


def _powers(base: np.uint64, n: int) -> np.ndarray:
    out = np.full(n, base, _U)
    out[0] = 1
    return np.multiply.accumulate(out)


def shingles(texts: pa.Array) -> list[np.ndarray]:
    """Sorted distinct 64-bit hashes of each text's shingles; empty for texts without words, and for nulls."""
    texts = texts.cast(pa.large_string()).fill_null("")
    if not len(texts):
        return []
    offsets = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
    data = np.frombuffer(texts.buffers()[2], np.uint8)[offsets[0] : offsets[-1]] if offsets[-1] > offsets[0] else np.zeros(0, np.uint8)
    offsets = offsets - offsets[0]
    if not len(data):
        return [np.zeros(0, _U)] * len(texts)
    inside = ~_SPACE[data]
    begins = inside.copy()
    begins[1:] &= ~inside[:-1]
    heads = offsets[:-1][offsets[:-1] < len(data)]
    begins[heads] = inside[heads]
    starts = np.flatnonzero(begins)
    stops = ~inside
    stops[heads] = True  # a text ends where the next begins
    stop_at = np.append(np.flatnonzero(stops), len(data))
    ends = stop_at[np.searchsorted(stop_at, starts, "right")]
    # sums of byte * step^place over a word, moved back to the word's own start
    sums = np.zeros(len(data) + 1, _U)
    np.cumsum(_BYTE[data] * _powers(_STEP, len(data)), out=sums[1:])
    words = _mix((sums[ends] - sums[starts]) * _powers(_BACK, len(data))[starts])
    for k in np.flatnonzero(ends - starts > LONG_WORD).tolist():  # sums modulo 2^64 part long words of a regular build badly
        words[k] = int.from_bytes(hashlib.blake2b(data[starts[k] : ends[k]].tobytes().lower(), digest_size=8).digest(), "little")
    first = np.searchsorted(starts, offsets)
    out = []
    scale = _powers(_STEP, WORDS)
    n = len(words)
    if n >= WORDS:
        runs = words[: n - WORDS + 1] * scale[0]
        for k in range(1, WORDS):
            runs = runs + words[k : n - WORDS + 1 + k] * scale[k]
        runs = _mix(runs)
    for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
        if b - a >= WORDS:
            out.append(np.unique(runs[a : b - WORDS + 1]))
        elif b > a:  # the whole sequence, kept apart from full shingles by its length
            out.append(_short(words[a:b], scale))
        else:
            out.append(np.zeros(0, _U))
    return out


def _short(words: np.ndarray, scale: np.ndarray) -> np.ndarray:
    return _mix(np.array([(words * scale[: len(words)]).sum(dtype=_U)], _U) + _U(len(words)))


def minima(own: np.ndarray) -> np.ndarray:
    """128 minima of affine maps of the upper hash bits, in slices so that memory is bounded."""
    low = np.full(MINIMA, 0xFFFFFFFF, np.uint32)
    short = (own >> _U(32)).astype(np.uint32)
    for i in range(0, len(short), 1024):
        low = np.minimum(low, (short[i : i + 1024, None] * _SCALE + _SHIFT).min(axis=0))
    return low


def packed(lows: np.ndarray) -> np.ndarray:
    """The low 2 bits of each minimum, 128 of them in 4 words: rows of uint64."""
    two = (lows & np.uint32(3)).astype(np.uint8)
    quad = two[:, 0::4] | (two[:, 1::4] << 2) | (two[:, 2::4] << 4) | (two[:, 3::4] << 6)
    return np.ascontiguousarray(quad).view(_U)


def estimate(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Similarity of packed signatures: the share of equal fields, less the quarter that agree by chance."""
    x = a ^ b
    differ = np.bitwise_count((x | (x >> _U(1))) & _U(0x5555555555555555)).sum(axis=-1)
    return ((MINIMA - differ) / MINIMA - 0.25) / 0.75


_SIGNED = "doc_id long, text_key long, n_shingles long, set_a long, set_b long, bands array<long>, signature binary"


def sign(docs: DataFrame) -> DataFrame:
    """doc_id, text_key, n_shingles, set_a, set_b (hash of the whole set), bands, signature."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in chunks(batch, "text", 1 << 20):
                sets = shingles(part.column("text"))
                sizes = np.array([len(s) for s in sets], np.int64)
                low = np.stack([minima(s) for s in sets])
                a = np.array([_mix(s).sum(dtype=_U) for s in sets], _U).view(np.int64)
                b = np.array([_mix(s ^ _U(0x5BD1E9955BD1E995)).sum(dtype=_U) for s in sets], _U).view(np.int64)
                cut = low[:, : BANDS * ROWS].astype(_U).reshape(-1, BANDS, ROWS)
                bands = _mix((cut * _BAND).sum(axis=2, dtype=_U) + np.arange(BANDS, dtype=_U)).view(np.int64)
                bands = pa.ListArray.from_arrays(pa.array(np.arange(len(sets) + 1, dtype=np.int32) * BANDS), pa.array(bands.ravel()))
                signature = pa.array([x.tobytes() for x in packed(low)], pa.binary())
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("text_key"), pa.array(sizes), pa.array(a), pa.array(b), bands, signature], ["doc_id", "text_key", "n_shingles", "set_a", "set_b", "bands", "signature"])

    return arrow_bounded(_keyed(docs)).mapInArrow(run, _SIGNED)


def _keyed(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_key"), "text")


def _groups(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.Table]:
    """Tables that hold whole groups of equal keys, of rows sorted by them; the last group of a batch waits for more."""
    wait: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        columns = [batch.column(k).to_numpy() for k in keys]
        change = np.zeros(batch.num_rows, bool)
        for c in columns:
            change[1:] |= c[1:] != c[:-1]
        change[0] = bool(wait) and any(wait[-1].column(k)[-1].as_py() != batch.column(k)[0].as_py() for k in keys)
        cuts = np.flatnonzero(change)
        if not len(cuts):
            wait.append(batch)
            continue
        if (rows := [*wait, batch.slice(0, cuts[-1])]) and sum(r.num_rows for r in rows):
            yield pa.Table.from_batches(rows)
        wait = [batch.slice(cuts[-1])]
    if wait:
        yield pa.Table.from_batches(wait)


def _bounds(table: pa.Table, keys: list[str]) -> np.ndarray:
    change = np.zeros(table.num_rows, bool)
    change[0] = True
    for k in keys:
        c = table.column(k).to_numpy()
        change[1:] |= c[1:] != c[:-1]
    return np.append(np.flatnonzero(change), table.num_rows)


def _spread(groups: DataFrame, key: str, weight: str | None = None) -> DataFrame:
    """Rows of groups of two or more with block numbers i <= j. A group beyond a block's bound is cut in blocks, and a
    row goes to every pair of blocks that has its own; others have the one pair (0, 0)."""
    most = F.ceil(F.count(F.lit(1)) / BLOCK_ROWS)
    if weight:
        most = F.greatest(most, F.ceil(F.sum(weight) / BLOCK_SHINGLES))
    sizes = groups.groupBy(key).agg(F.count(F.lit(1)).alias("rows"), most.cast("int").alias("blocks")).filter("rows > 1").drop("rows")
    met = groups.join(sizes, key)
    own = F.pmod(F.xxhash64("doc_id"), F.col("blocks")).cast("int")
    met = met.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    return met.withColumns({"i": F.least("own", "other"), "j": F.greatest("own", "other")}).drop("blocks", "own", "other")


def candidate_edges(reps: DataFrame) -> DataFrame:
    """u, v: for each band group, a spanning forest of the pairs whose estimate reaches FLOOR."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _groups(batches, ["key", "i", "j"]):
            at = _bounds(table, ["key", "i", "j"])
            ids = table.column("doc_id").to_numpy()
            marks = np.frombuffer(b"".join(table.column("signature").to_pylist()), _U).reshape(-1, 4)
            sizes = np.diff(at)
            two = at[:-1][sizes == 2]
            good = two[estimate(marks[two], marks[two + 1]) >= FLOOR]
            found = [(ids[good], ids[good + 1])]
            for a, n in zip(at[:-1][sizes > 2].tolist(), sizes[sizes > 2].tolist(), strict=True):
                found.append(_forest(ids[a : a + n], marks[a : a + n]))
            u, v = (np.concatenate([f[k] for f in found]) for k in (0, 1))
            yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], ["u", "v"])

    keyed = reps.select("doc_id", "signature", F.explode("bands").alias("key"))
    dealt = _spread(keyed, "key").repartition("key", "i", "j").sortWithinPartitions("key", "i", "j")
    return arrow_bounded(dealt.select("key", "i", "j", "doc_id", "signature")).mapInArrow(run, "u long, v long")


def _forest(ids: np.ndarray, marks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Components of one group by estimates: each row is compared once with the rows not reached yet."""
    left, out_u, out_v = np.arange(len(ids)), [], []
    while len(left):
        front, left = [left[0]], left[1:]
        root = ids[front[0]]
        while front and len(left):
            near = estimate(marks[left], marks[front.pop()]) >= FLOOR
            if near.any():
                met = left[near]
                out_u.append(ids[met])
                out_v.append(np.full(len(met), root))
                front.extend(met.tolist())
                left = left[~near]
    return (np.concatenate(out_u), np.concatenate(out_v)) if out_u else (ids[:0], ids[:0])


def exact_links(sets: list[np.ndarray], link: int = LINK) -> tuple[np.ndarray, np.ndarray]:
    """Places (a, b) of a spanning forest of the pairs with 100 * shared >= link * united, all pairs compared exactly
    but those that are already tied."""
    n = len(sets)
    sizes = np.array([len(s) for s in sets])
    flat = np.concatenate(sets)
    owner = np.repeat(np.arange(n), sizes)
    order = np.argsort(flat, kind="stable")
    ordered, by = flat[order], owner[order]
    edges = np.append(np.flatnonzero(np.append(True, ordered[1:] != ordered[:-1])), len(ordered))
    group = np.empty(len(flat), np.int64)
    group[order] = np.repeat(np.arange(len(edges) - 1), np.diff(edges))
    starts, lengths = edges[:-1], np.diff(edges)
    at = np.concatenate([[0], np.cumsum(sizes)])
    tied, parts = np.arange(n), n
    out_a, out_b = [], []
    for i in range(n):
        if parts == 1:
            break
        own = group[at[i] : at[i + 1]]
        own = own[lengths[own] > 1]
        if not len(own):
            continue
        count = lengths[own]
        places = np.repeat(starts[own] - np.cumsum(count) + count, count) + np.arange(count.sum())
        shared = np.bincount(by[places], minlength=n)
        linked = np.flatnonzero((100 * shared >= link * (sizes + sizes[i] - shared)) & (shared > 0) & (tied != tied[i]))
        for j in linked.tolist():
            if tied[j] != tied[i]:
                tied[tied == tied[j]] = tied[i]
                parts -= 1
                out_a.append(i)
                out_b.append(j)
    return np.array(out_a, np.int64), np.array(out_b, np.int64)


def confirmed_edges(members: DataFrame) -> DataFrame:
    """u, v: links of different texts that share a cluster. members: doc_id, root, n_shingles, text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _groups(batches, ["root", "i", "j"]):
            at = _bounds(table, ["root", "i", "j"])
            ids, texts = table.column("doc_id").to_numpy(), table.column("text")
            us, vs = [ids[:0]], [ids[:0]]
            for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
                u, v = exact_links(shingles(texts.slice(a, b - a).combine_chunks()))
                us.append(ids[a:b][u])
                vs.append(ids[a:b][v])
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(us)), pa.array(np.concatenate(vs))], ["u", "v"])

    dealt = _spread(members, "root", "n_shingles").repartition("root", "i", "j").sortWithinPartitions("root", "i", "j")
    return arrow_bounded(dealt.select("root", "i", "j", "doc_id", "text")).mapInArrow(run, "u long, v long")


def find_near_copies(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for each row of docs.

    Words are split at ASCII white space, A-Z folded; a text of fewer words than a shingle has one shingle, its whole
    sequence; a null text, or one without words, has none and is its own component. Rows that repeat a doc_id stay,
    each judged by its own text; where one id represents several different texts, these count as one document. A null doc_id links with nothing: its component is null and it is kept. Other columns are ignored.
    """
    signed = stored(sign(docs), "signatures")
    has = signed.filter("n_shingles > 0 AND doc_id IS NOT NULL")
    same = ["n_shingles", "set_a", "set_b"]
    first = F.min(F.struct("doc_id", "text_key"))
    classes = has.groupBy(*same).agg(first.alias("node"), F.first("bands").alias("bands"), F.first("signature").alias("signature"))
    classes = stored(classes.select(*same, F.col("node.doc_id").alias("node"), F.col("node.text_key").alias("text_key"), "bands", "signature"), "classes")
    clusters = components(candidate_edges(classes.select(F.col("node").alias("doc_id"), "bands", "signature")))
    members = clusters.join(classes.select("node", "text_key", "n_shingles"), "node").withColumnRenamed("node", "doc_id")
    links = components(confirmed_edges(_keyed(docs).join(members, ["doc_id", "text_key"])))
    rooted = classes.select(*same, "node").join(links, "node", "left").select(*same, F.coalesce("root", "node").alias("component_id"))
    out = signed.select("doc_id", *same).join(rooted, same, "left")
    component = F.when(F.col("doc_id").isNull(), F.lit(None)).otherwise(F.coalesce("component_id", "doc_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def keep_one(docs: DataFrame) -> DataFrame:
    """The rows of docs that represent their groups, with their columns; of rows that repeat a doc_id, one stays."""
    name = free_name(docs, "kept_")
    kept = find_near_copies(docs).filter("kept AND doc_id IS NOT NULL").select(F.col("doc_id").alias(name)).distinct()
    rows = docs.join(kept, F.col("doc_id") == F.col(name), "left_semi").dropDuplicates(["doc_id"])
    return rows.unionByName(docs.filter("doc_id IS NULL"))

"""Benchmark decontamination: one Aho-Corasick automaton over word windows of the items, each text scanned once."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator, Sequence
from itertools import chain

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import arrow_bounded, chunks, free_name, quoted, stored

#: Words of a window; bytes of item text that one automaton (and its broadcast) may hold.
WINDOW, AUTOMATON_BYTES = 13, 32 << 20
#: A-Z to a-z, the word characters as they are, all other bytes below 0x80 to a space.
_FOLD = bytes(c + 32 if 0x41 <= c <= 0x5A else c if 0x30 <= c <= 0x39 or 0x61 <= c <= 0x7A or c >= 0x80 else 0x20 for c in range(256))
_WORD = regex.compile(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")


def words_of(text: str | bytes | None) -> list[bytes]:
    data = text.encode("utf-8") if isinstance(text, str) else text or b""
    return data.translate(_FOLD).split()


def windows_of(items: Sequence[tuple[object, str | None]]) -> dict[bytes, list[int]]:
    """window: places in items whose word sequence has it. An item of fewer words than a window is one; of none, none."""
    found: dict[bytes, list[int]] = {}
    for k, (_, text) in enumerate(items):
        words = words_of(text)
        for i in range(max(1, len(words) - WINDOW + 1) if words else 0):
            held = found.setdefault(b" ".join(words[i : i + WINDOW]), [])
            if not held or held[-1] != k:
                held.append(k)
    return found


class Scanner:
    def __init__(self, items: Sequence[tuple[object, str | None]]) -> None:
        import ahocorasick

        self.names = [str(i) for i, _ in items]
        self.automaton = ahocorasick.Automaton()
        # bytes are read as Latin-1, one character each; spaces at both ends keep matches to whole words
        for window, held in windows_of(items).items():
            self.automaton.add_word(f" {window.decode('latin-1')} ", (window.count(b" ") + 1, held))
        self.automaton.make_automaton()
        self.empty = not len(self.automaton)

    def scan(self, words: list[bytes]) -> tuple[list[tuple[int, int]], list[str]]:
        """Runs of hit words (first, end) in order without overlaps, and the items found."""
        if self.empty or not words:
            return [], []
        line = f" {b' '.join(words).decode('latin-1')} "
        ends, sizes, items = [], [], set()
        for end, (n, held) in self.automaton.iter(line):
            ends.append(end)
            sizes.append(n)
            items.update(held)
        if not ends:
            return [], []
        # the word that ends before place `end` is numbered by the spaces up to there
        spaces = np.flatnonzero(np.frombuffer(line.encode("latin-1"), np.uint8) == 0x20)
        last = np.searchsorted(spaces, ends)
        hit = np.zeros(len(words) + 1, np.int64)
        np.add.at(hit, last - sizes, 1)
        np.add.at(hit, last, -1)
        inside = np.concatenate([[False], np.cumsum(hit) > 0])
        edges = np.flatnonzero(inside[1:] != inside[:-1])
        return list(zip(edges[::2].tolist(), edges[1::2].tolist(), strict=True)), [self.names[k] for k in items]


_SCANNERS: dict[str, Scanner] = {}


def _groups(benchmark: DataFrame) -> Iterator[list[tuple[object, str | None]]]:
    """Items in groups of at most about AUTOMATON_BYTES of text: each group is one automaton and one scan. The driver
    holds one group at a time. Repeated rows are one; an empty benchmark is one empty group."""
    rows = benchmark.select("item_id", "text").distinct()
    size, count = rows.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)), F.count(F.lit(1))).first()
    n = max(1, -(-size // AUTOMATON_BYTES), -(-count // 1_000_000))
    for k in range(n):
        yield [tuple(r) for r in (rows.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == k) if n > 1 else rows).collect()]


_FOUND = "n_words long, runs array<struct<first:long,end:long>>, items array<string>, hit_spans array<struct<start:long,end:long>>"
_FOUND_TYPES = pa.schema([("n_words", pa.int64()), ("runs", pa.list_(pa.struct([("first", pa.int64()), ("end", pa.int64())]))), ("items", pa.list_(pa.string())), ("hit_spans", pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))])


def _scanned(rows: DataFrame, items: list[tuple[object, str | None]], keep: Sequence[str], spans: bool) -> DataFrame:
    """keep and what one automaton finds in each row: its words, the runs of hit words, the items, the runs as places of
    the original text if asked."""
    shared = rows.sparkSession.sparkContext.broadcast(items)
    key = hashlib.sha256(repr(items).encode()).hexdigest()
    kept = ", ".join(f"{quoted(k)} {rows.schema[k].dataType.simpleString()}" for k in keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if key not in _SCANNERS:
            _SCANNERS.clear()
            _SCANNERS[key] = Scanner(shared.value)
        own = _SCANNERS[key]
        for batch in batches:
            for part in chunks(batch, "text"):
                columns: list[list] = [[], [], [], []]
                for text in part.column("text").to_pylist():
                    words = words_of(text)
                    runs, found = own.scan(words)
                    columns[0].append(len(words))
                    columns[1].append([{"first": a, "end": b} for a, b in runs])
                    columns[2].append(found)
                    at = [m.span() for m in _WORD.finditer(text)] if runs and spans else []
                    columns[3].append([{"start": at[a][0], "end": at[b - 1][1]} for a, b in runs] if at else [])
                yield pa.RecordBatch.from_arrays([*[part.column(k) for k in keep], *[pa.array(c, f.type) for c, f in zip(columns, _FOUND_TYPES, strict=True)]], [*keep, *_FOUND_TYPES.names])

    return arrow_bounded(rows.select(*[F.col(quoted(k)) for k in keep], "text")).mapInArrow(run, f"{kept}, {_FOUND}")


def _hits(rows: DataFrame, row: str, first: list, others: Iterator[list], spans: bool) -> DataFrame:
    """What several automata find, put together by row number: the first one's rows are all there, the others give only
    rows with hits, each written before the next group is read. A row's runs are all that meets in one place."""
    every = stored(_scanned(rows, first, [row], spans), "scan")
    hits = every.filter(F.size("runs") > 0)
    for items in others:
        hits = hits.unionByName(stored(_scanned(rows, items, [row], spans).filter(F.size("runs") > 0), "scan"))
    lists = lambda c: F.flatten(F.collect_list(c)).alias(c)
    joined = hits.groupBy(row).agg(*[lists(c) for c in _FOUND_TYPES.names[1:]]).withColumnRenamed(row, "at_")
    empty = {f.name: F.array().cast(f.dataType) for f in every.schema.fields if f.name in _FOUND_TYPES.names[1:]}
    both = every.select(row, "n_words").join(joined, F.col(row) == F.col("at_"), "left")
    return both.select(row, "n_words", *[F.coalesce(c, e).alias(c) for c, e in empty.items()])


def _judged(found: DataFrame) -> tuple[Column, Column]:
    """Number of hit words, and whether they make a text contaminated; runs of several automata may overlap."""
    zero = F.lit(0).cast("long")
    step = lambda s, r: F.struct((s["n"] + F.greatest(zero, r["end"] - F.greatest(s["upto"], r["first"]))).alias("n"), F.greatest(s["upto"], r["end"]).alias("upto"))
    n_hit = F.aggregate(F.array_sort(found["runs"]), F.struct(zero.alias("n"), zero.alias("upto")), step, lambda s: s["n"])
    return n_hit, (n_hit > 0) & (20 * n_hit >= found["n_words"])


def scan_documents(docs: DataFrame, benchmark: DataFrame, spans: bool = False) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated for each row; with spans also hit_spans, the runs of
    hit words as places start:end (code points of the original text, end exclusive), comma-joined in order.

    A null or empty text has no words, no hits and the hash of the empty string; so has any text while benchmark is
    empty. Equal items under several ids all count. Every row is judged by its own text: repeated rows, and rows that
    share an id or have none, stay apart, with one automaton or several. Other columns are ignored. A benchmark beyond
    AUTOMATON_BYTES is scanned for by several automata, one after another; the driver holds one group of items.
    """
    groups = _groups(benchmark)
    first, second = next(groups), next(groups, None)
    rows = docs.select("doc_id", "text")
    if second is None:
        found = _scanned(rows, first, ["doc_id"], spans)
    else:
        rows = stored(rows.withColumn("row_", F.monotonically_increasing_id()), "rows")
        found = rows.select("doc_id", "row_").join(_hits(rows, "row_", first, chain([second], groups), spans), "row_")
    n_hit, bad = _judged(found)
    items = F.array_sort(F.array_distinct("items"))
    out = found.select("doc_id", "n_words", n_hit.alias("n_hit"), F.size(items).cast("long").alias("n_items"), F.sha2(F.array_join(items, ","), 256).alias("items_sha256"), bad.alias("contaminated"), "hit_spans")
    places = F.array_join(F.transform(F.array_sort(F.array_distinct("hit_spans")), lambda s: F.concat_ws(":", s["start"].cast("string"), s["end"].cast("string"))), ",")
    return out.withColumn("hit_spans", places) if spans else out.drop("hit_spans")


def clean_documents(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of docs that aren't contaminated, with their columns, whatever these are called. Each row is judged by its
    own text, as scan_documents() does; one scan where one automaton holds the items, else rows are numbered."""
    groups = _groups(benchmark)
    first, second = next(groups), next(groups, None)
    if second is not None:
        row = free_name(docs, "row_")
        rows = stored(docs.withColumn(row, F.monotonically_increasing_id()), "rows")
        found = _hits(rows.select(row, "text"), row, first, chain([second], groups), False)
        bad = found.filter(_judged(found)[1]).select(F.col(row).alias("bad_"))
        return rows.join(bad, F.col(row) == F.col("bad_"), "left_anti").drop(row)
    shared = docs.sparkSession.sparkContext.broadcast(first)
    key = hashlib.sha256(repr(first).encode()).hexdigest()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if key not in _SCANNERS:
            _SCANNERS.clear()
            _SCANNERS[key] = Scanner(shared.value)
        for batch in batches:
            keep = []
            for text in batch.column("text").to_pylist():
                words = words_of(text)
                n = sum(b - a for a, b in _SCANNERS[key].scan(words)[0])
                keep.append(not (n > 0 and 20 * n >= len(words)))
            yield batch.filter(pa.array(keep, pa.bool_()))

    return arrow_bounded(docs).mapInArrow(run, docs.schema)

"""Token ids in directly addressable codes: chunk levels with continuation bitmaps and rank directories.

A segment holds the ids of whole documents. Level 0 has the low bits of every id; an id that needs more has a set bit
in the level's bitmap, and its next bits stand in level 1 at the rank of that bit; and so on. A rank is read from the
directory (ones before each block of 512 bits) and one partial block, so any token is reached without decoding others. `tokens_at` and `Store` find a token by its place among all ids.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator
from pathlib import Path

import numpy as np
import public_tokenizers
import pyarrow as pa
import regex
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow_bounded, chunks, shared_folder
from .pieces import PieceEncoder, encoded, joined

MAGIC, BITS, BLOCK = b"PFDA", 8, 512
#: Ids after which a writer closes a segment, at the end of a document.
SEGMENT_IDS = 4_000_000
_HEAD = struct.Struct("<4sBBHQQQQ")  # magic, bits, levels, 0, ids before in the shard, ids, documents, of them without an id
#: Ids that a bucket of places spans: lookups meet segments by bucket.
BUCKET = 1 << 22


def pack(ids: np.ndarray, doc_ids: np.ndarray, starts: np.ndarray, before: int = 0, bits: int = BITS, nameless: int = 0) -> bytes:
    """A segment. ids: uint32; doc_ids: int64 of each document, the first `nameless` of which have none; starts: where
    each begins, and the end."""
    levels, rest = [], ids.astype(np.uint32)
    while True:
        more = (rest >> np.uint32(bits)) > 0
        body = (rest & np.uint32((1 << bits) - 1)).astype(np.uint8 if bits <= 8 else np.uint16)
        bitmap = np.packbits(more, bitorder="little")
        padded = np.zeros(-(-len(bitmap) // (BLOCK // 8)) * (BLOCK // 8), np.uint8)
        padded[: len(bitmap)] = bitmap
        ones = np.bitwise_count(padded.view(np.uint64)).reshape(-1, BLOCK // 64).sum(axis=1)
        ranks = np.zeros(len(ones) + 1, np.uint32)
        np.cumsum(ones, out=ranks[1:])
        levels.append((body, padded, ranks))
        rest = rest[more] >> np.uint32(bits)
        if not len(rest):
            break
    parts = [_HEAD.pack(MAGIC, bits, len(levels), 0, before, len(ids), len(doc_ids), nameless), doc_ids.astype("<i8").tobytes(), starts.astype("<u8").tobytes()]
    parts += [struct.pack("<QQQ", *(x.nbytes for x in level)) for level in levels]
    for level in levels:
        parts += [x.tobytes() for x in level]
    return b"".join(parts)


class Segment:
    """Reader of a segment in a buffer; nothing is decoded until asked for."""

    def __init__(self, data: bytes | memoryview) -> None:
        magic, self.bits, n_levels, _, self.before, self.n_ids, self.n_docs, self.nameless = _HEAD.unpack_from(data)
        if magic != MAGIC:
            raise ValueError("not a token segment")
        at = _HEAD.size
        self.doc_ids = np.frombuffer(data, "<i8", self.n_docs, at)
        self.starts = np.frombuffer(data, "<u8", self.n_docs + 1, at := at + 8 * self.n_docs)
        at += 8 * (self.n_docs + 1)
        sizes = [struct.unpack_from("<QQQ", data, at + 24 * k) for k in range(n_levels)]
        at += 24 * n_levels
        self.levels = []
        for body, bitmap, ranks in sizes:
            kind = np.uint8 if self.bits <= 8 else np.uint16
            self.levels.append((np.frombuffer(data, kind, body // kind().itemsize, at), np.frombuffer(data, np.uint8, bitmap, at + body), np.frombuffer(data, "<u4", ranks // 4, at + body + bitmap)))
            at += body + bitmap + ranks

    def __getitem__(self, i: int) -> int:
        """The id at a place, by one step for each level that it has."""
        if not 0 <= i < self.n_ids:
            raise IndexError(i)
        value, shift = 0, 0
        for body, bitmap, ranks in self.levels:
            value |= int(body[i]) << shift
            if not (bitmap[i >> 3] >> (i & 7)) & 1:
                break
            block = i // BLOCK
            ones = int(np.bitwise_count(bitmap[block * BLOCK // 8 : i >> 3]).sum()) + int(bitmap[i >> 3] & ((1 << (i & 7)) - 1)).bit_count()
            i, shift = int(ranks[block]) + ones, shift + self.bits
        return value

    def slice(self, begin: int, end: int) -> np.ndarray:
        """Ids from begin to end (not included), by ranks of the two ends in each level."""
        out = np.zeros(max(0, end - begin), np.uint32)
        where, shift = np.arange(len(out)), 0
        for body, bitmap, ranks in self.levels:
            if not len(where):
                break
            out[where] |= body[begin:end].astype(np.uint32) << np.uint32(shift)
            first = begin >> 3
            more = np.unpackbits(bitmap[first : (end + 7) >> 3], bitorder="little")[begin - 8 * first : end - 8 * first].astype(bool)
            block = begin // BLOCK
            rank = int(ranks[block]) + int(np.bitwise_count(bitmap[block * BLOCK // 8 : first]).sum()) + int(bitmap[first] & ((1 << (begin & 7)) - 1)).bit_count()
            where = where[more]
            begin, end, shift = rank, rank + len(where), shift + self.bits
        return out

    def document(self, k: int) -> np.ndarray:
        """Ids of a document, found by its start; no other document's are read."""
        return self.slice(int(self.starts[k]), int(self.starts[k + 1]))


class LibraryEncoder(PieceEncoder):
    """Ids as the tokenizers library gives them.

    New pre-tokens are put together in long lines in which each is again a pre-token of its own; the library encodes a
    line, and its word numbers part the ids. Chunks with special strings, or with characters on which tables of
    letters may differ, are given to the library as they are; so is a line that it cuts otherwise than expected.
    """

    LINE = 4000
    most = 300_000

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer

        super().__init__()
        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        special = [regex.escape(t.content) for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.apart = regex.compile("|".join([*special, r"[^\x00-\x7f\u00a0-\u024f\u0400-\u045f\u2010-\u2027\u3041-\u3096\u30a1-\u30fa\u4e00-\u9fa5]"]))
        self.cut = regex.compile(public_tokenizers.PATTERN)

    def _alone(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def _line(self, pieces: list[str], mark: str) -> list[bytes]:
        """Pieces with a leading space (mark ""), or without white space at their start (mark a line break)."""
        line = self.tokenizer.encode(mark + mark.join(pieces), add_special_tokens=False)
        words = np.array(line.word_ids)
        cuts = np.flatnonzero(words[1:] != words[:-1]) + 1
        bounds = [0, *cuts.tolist(), len(words)]
        step = 2 if mark else 1
        if len(bounds) - 1 != step * len(pieces):
            return [self._alone(p) for p in pieces]
        ids = np.array(line.ids, "<u4").tobytes()
        return [ids[4 * a : 4 * b] for a, b in zip(bounds[step - 1 :: step], bounds[step::step], strict=False)]

    def fresh(self, pieces: list[str]) -> list[bytes]:
        kinds: tuple[list[int], ...] = ([], [], [])
        for i, p in enumerate(pieces):
            kinds[0 if p[0] == " " and len(p) > 1 and not p[1].isspace() else 2 if p[0].isspace() else 1].append(i)
        out = [b""] * len(pieces)
        for kind, mark in ((kinds[0], ""), (kinds[1], "\n")):
            for a in range(0, len(kind), self.LINE):
                some = kind[a : a + self.LINE]
                for i, value in zip(some, self._line([pieces[i] for i in some], mark), strict=True):
                    out[i] = value
        for i in kinds[2]:
            out[i] = self._alone(pieces[i])
        return out

    def chunk(self, text: str) -> bytes:
        if self.apart.search(text):
            return self._alone(text)
        found = self.cut.findall(text)
        if any(p not in self.known for p in found):
            self.learn(set(found))
        return b"".join([self.known[p] for p in found])


_ENCODERS: dict[str, LibraryEncoder] = {}


def _encoder(vocabulary: str) -> LibraryEncoder:
    if vocabulary not in _ENCODERS:
        _ENCODERS[vocabulary] = LibraryEncoder(public_tokenizers.path(vocabulary))
    return _ENCODERS[vocabulary]


_SEGMENTS = "shard long, segment long, first_doc long, n_ids long, payload binary"


def write_tokens(docs: DataFrame, path: str | None = None, vocabulary: str = "byte_bpe_50k.json", end_id: int = 0, segment_ids: int = SEGMENT_IDS) -> str:
    """Write every document's ids and end_id, documents in ascending doc_id order, as segments; gives the folder.

    Documents are dealt by ranges of (doc_id, hash of text, place in the input), as sampled by Spark, so that an id that
    repeats a great deal is split too; they are sorted, and cut into segments at document ends, so a task holds one
    segment. The folder is a Parquet table (shard, segment, first_doc, n_ids, payload), not compressed, with a segment
    in a row, which Spark's commit makes safe against lost executors and which any of its stores can hold. Null texts
    count as empty; null ids go first and are counted in the segment's head; repeated rows stay, in order of their
    texts' hashes.
    """
    path = path or shared_folder(docs.sparkSession, "tokens")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, shard, number, before = _encoder(vocabulary), TaskContext.get().partitionId(), 0, 0
        ids, names, sizes, held, nameless = [], [], [], 0, 0

        def close() -> pa.RecordBatch:
            nonlocal number, before, held, nameless
            starts = np.concatenate([[0], np.cumsum(np.concatenate(sizes))])
            flat, docs_ = np.concatenate(ids), np.concatenate(names)
            row = pa.RecordBatch.from_arrays([pa.array([shard]), pa.array([number]), pa.array([int(docs_[0])]), pa.array([len(flat)]), pa.array([pack(flat, docs_, starts, before, nameless=nameless)], pa.binary())], schema=out)
            number, before, held, nameless = number + 1, before + len(flat), 0, 0
            ids.clear(), names.clear(), sizes.clear()
            return row

        for batch in batches:
            for part in chunks(batch, "text", min(8 << 20, 2 * segment_ids)):
                values, starts = encoded(part.column("text"), encoder)
                flat, at = joined(values, starts)
                at = at // 4
                ids.append(np.insert(flat[: 4 * at[-1]].view("<u4"), at[1:], np.uint32(end_id)))
                sizes.append(np.diff(at) + 1)
                names.append(part.column("doc_id").fill_null(0).to_numpy(zero_copy_only=False))
                nameless += part.column("doc_id").null_count
                held += len(ids[-1])
                if held >= segment_ids:
                    yield close()
        if held:
            yield close()

    out = pa.schema([("shard", pa.int64()), ("segment", pa.int64()), ("first_doc", pa.int64()), ("n_ids", pa.int64()), ("payload", pa.binary())])
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.xxhash64("text").alias("h"), F.monotonically_increasing_id().alias("at"))
    dealt = own.repartitionByRange("doc_id", "h", "at").sortWithinPartitions("doc_id", "h", "at").select("doc_id", "text")
    arrow_bounded(dealt).mapInArrow(run, _SEGMENTS).write.option("compression", "none").option("parquet.enable.dictionary", "false").parquet(path)
    return path


def _shard_starts(segments: DataFrame) -> tuple[dict[int, int], int]:
    """Place of each shard's first id, and the number of ids: one total for each partition of the writer is collected."""
    starts, total = {}, 0
    for shard, n in sorted((r["shard"], r["n"]) for r in segments.groupBy("shard").agg(F.sum("n_ids").alias("n")).collect()):
        starts[shard], total = total, total + n
    return starts, total


def read_documents(spark, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, each reached by its start in its segment.

    Only one total for each shard reaches the driver (8 bytes for each partition of the writer) to place the shards.
    """
    files = spark.read.schema(_SEGMENTS).parquet(path)
    offsets, _ = _shard_starts(files)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for shard, payload in zip(batch.column("shard").to_pylist(), batch.column("payload"), strict=True):
                part = Segment(payload.as_buffer())
                starts = part.starts.astype(np.int64)
                crc = [zlib.crc32(part.document(k).astype("<u4", copy=False)) for k in range(part.n_docs)]
                doc_ids = pa.array(part.doc_ids, mask=np.arange(part.n_docs) < part.nameless)
                yield pa.RecordBatch.from_arrays([doc_ids, pa.array(starts[:-1] + part.before + offsets[shard]), pa.array(np.diff(starts)), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return arrow_bounded(files.select("shard", "payload")).mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def tokens_at(spark, path: str, places: DataFrame) -> DataFrame:
    """place, token for each row of places (place: among the ids of all documents, from 0); token is null where there is
    none. Places meet segments in an equi-join by bucket, never a broadcast of either; a segment is opened once for all
    places in it, and each token is read by its own rank steps."""
    files = spark.read.schema(_SEGMENTS).parquet(path)
    offsets, _ = _shard_starts(files)
    shard_start = F.coalesce(F.element_at(F.create_map(*[F.lit(x) for p in (offsets or {-1: 0}).items() for x in p]), F.col("shard")), F.lit(0))
    by_shard = Window.partitionBy("shard").orderBy("segment").rowsBetween(Window.unboundedPreceding, -1)
    index = files.select("shard", "segment", "n_ids").withColumn("first", (shard_start + F.coalesce(F.sum("n_ids").over(by_shard), F.lit(0))).cast("long")).filter("n_ids > 0")
    index = index.withColumn("bucket", F.explode(F.sequence(F.floor(F.col("first") / BUCKET), F.floor((F.col("first") + F.col("n_ids") - 1) / BUCKET))))
    asked = places.select(F.col("place").cast("long").alias("place"), F.monotonically_increasing_id().alias("row"), F.floor(F.col("place") / BUCKET).alias("bucket"))
    met = asked.join(index, (asked["bucket"] == index["bucket"]) & (F.col("place") >= F.col("first")) & (F.col("place") < F.col("first") + F.col("n_ids")), "left")
    wanted = met.filter("segment IS NOT NULL").groupBy("shard", "segment").agg(F.collect_set(F.col("place") - F.col("first")).alias("at"), F.first("first").alias("first"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, at, payload in zip(batch.column("first").to_pylist(), batch.column("at").to_pylist(), batch.column("payload"), strict=True):
                part = Segment(payload.as_buffer())
                yield pa.RecordBatch.from_arrays([pa.array([first + k for k in at], pa.int64()), pa.array([part[k] for k in at], pa.int64())], ["found", "token"])

    found = wanted.join(files.select("shard", "segment", "payload"), ["shard", "segment"]).select("first", "at", "payload").mapInArrow(run, "found long, token long")
    return places.select(F.col("place").cast("long").alias("place")).join(found, F.col("place") == F.col("found"), "left").select("place", "token")


class Store:
    """The ids of exported files as one sequence, each file mapped into memory: reading a token or a document touches the
    bytes that its codes stand in, and nothing is decompressed or decoded besides."""

    def __init__(self, folder: str) -> None:
        self.files = [Segment(memoryview(np.memmap(f, np.uint8, "r"))) for f in sorted(Path(folder).glob("*.ids"))]
        self.firsts = np.concatenate([[0], np.cumsum([f.n_ids for f in self.files], dtype=np.int64)]).astype(np.int64)

    def __len__(self) -> int:
        return int(self.firsts[-1])

    def __getitem__(self, place: int) -> int:
        if not 0 <= place < len(self):
            raise IndexError(place)
        k = int(np.searchsorted(self.firsts, place, "right")) - 1
        return self.files[k][place - int(self.firsts[k])]

    def document(self, doc_id: int) -> np.ndarray:
        """Ids of the first document of an id, its end id among them, by binary search in the files' names."""
        for f in self.files:
            k = f.nameless + int(np.searchsorted(f.doc_ids[f.nameless :], doc_id))
            if k < f.n_docs and f.doc_ids[k] == doc_id:
                return f.document(k)
        raise KeyError(doc_id)


def export_files(spark, path: str, folder: str) -> int:
    """Write each segment as a file of its own under a folder that all executors mount; gives their number.

    A file is written under another name and renamed, so a task that runs again replaces it whole.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for shard, number, payload in zip(batch.column("shard").to_pylist(), batch.column("segment").to_pylist(), batch.column("payload").to_pylist(), strict=True):
                to = Path(folder) / f"{shard:06d}-{number:06d}.ids"
                part = to.with_suffix(f".{TaskContext.get().taskAttemptId()}")
                part.write_bytes(payload)
                part.replace(to)
            yield pa.RecordBatch.from_arrays([pa.array([batch.num_rows])], ["n"])

    Path(folder).mkdir(parents=True, exist_ok=True)
    return spark.read.parquet(path).select("shard", "segment", "payload").mapInArrow(run, "n long").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]

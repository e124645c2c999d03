"""Token counts: pieces counted for each distinct pre-token, joined to each document's pre-token frequencies and summed.

Both tables are those of a slice of texts, in its worker: a table of all pre-tokens of a corpus would be as large as a
good part of it (each megabyte of these texts has some 12,000 words that none before it had), and joining it to all
documents' frequencies would shuffle each document's words there and its sums back. A worker remembers MEMO pre-tokens
between slices, so a common one is counted once in a worker, and a rare one once in each slice that has it.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_bounded, chunks

#: Pre-tokens whose counts a worker keeps between batches; beyond it the memo begins anew.
MEMO = 400_000


class PieceCounter:
    """Pieces of pre-tokens as a tokenizers file gives them, each distinct pre-token encoded once."""

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.known: dict[str, int] = {}

    def whole(self, texts: list[str]) -> list[int]:
        return [len(e.ids) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def pieces(self, words: list[str]) -> np.ndarray:
        if len(self.known) > MEMO:
            self.known.clear()
        fresh = [w for w in words if w not in self.known]
        if fresh:
            self.known.update(zip(fresh, self.whole(fresh), strict=True))
        return np.fromiter(map(self.known.__getitem__, words), np.int64, len(words))

    def count(self, texts: pa.Array) -> np.ndarray:
        """Tokens of each text. White space is dropped by the vocabulary's own split, so texts are cut there first."""
        texts = pc.fill_null(texts, "")
        words = pc.ascii_split_whitespace(texts)
        starts = words.offsets.to_numpy().astype(np.int64) - words.offsets[0].as_py()
        coded = words.flatten().dictionary_encode()
        n, size = len(texts), max(1, len(coded.dictionary))
        # the frequency table: one row for each document and pre-token in it, keyed by code
        rows = np.repeat(np.arange(n), np.diff(starts))
        keys, frequency = np.unique(rows * size + coded.indices.to_numpy(), return_counts=True)
        # joined with the pieces of each distinct pre-token by code, and summed by document; no ids are made
        pieces = self.pieces(coded.dictionary.to_pylist())
        out = np.bincount(keys // size, weights=frequency * pieces[keys % size], minlength=n).astype(np.int64) if len(keys) else np.zeros(n, np.int64)
        for special in self.special:  # the library cuts these strings out before it splits
            held = np.flatnonzero(pc.match_substring(texts, special).to_numpy(zero_copy_only=False))
            if len(held):
                out[held] = self.whole(texts.take(pa.array(held)).to_pylist())
        return out


_COUNTERS: dict[str, PieceCounter] = {}


def count_tokens(docs: DataFrame, vocabulary: str = "word_bpe_49k.json", limit: int = 2048) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for each row of docs.

    A null text counts as empty: 0 bytes, 0 tokens. Repeated rows and null ids stay; other columns of docs are
    ignored. No shuffle: each task holds the distinct pre-tokens of one slice of texts and a bounded memo.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if vocabulary not in _COUNTERS:
            _COUNTERS[vocabulary] = PieceCounter(public_tokenizers.path(vocabulary))
        for batch in batches:
            for part in chunks(batch, "text"):
                n = _COUNTERS[vocabulary].count(part.column("text"))
                size = pc.binary_length(part.column("text")).fill_null(0).cast(pa.int64())
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), size, pa.array(n)], ["doc_id", "n_bytes", "n_tokens"])

    counted = arrow_bounded(docs.select("doc_id", "text")).mapInArrow(run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, n_bytes long, n_tokens long")
    return counted.withColumn("over_limit", F.col("n_tokens") > limit)

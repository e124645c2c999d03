"""Texts cut at single spaces into chunks, and chunks encoded once each: the shared front of the token operators.

A space that a non-space follows always begins a new pre-token, and what precedes it sees the end of its chunk as it
would see the space, so chunks can be encoded apart. Texts in which white space follows a space are cut by the same
rule with a regular expression instead.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex

#: A space before white space: such texts take the slow cut. All code points that Unicode counts as white space.
_ODD = r"[ ][\s\x{0b}\x{1c}-\x{1f}\x{85}\x{a0}\x{1680}\x{2000}-\x{200a}\x{2028}\x{2029}\x{202f}\x{205f}\x{3000}]"
_CUT = regex.compile(r"(?<!^)(?= \S)")


def cut(texts: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """Chunks of all texts in order (a chunk but the first of a text begins with its space), and each text's first chunk.

    The second array has one entry more than there are texts. Chunks of a text joined give the text.
    """
    texts = pc.fill_null(texts, "")
    odd = pc.match_substring_regex(texts, _ODD).to_numpy(zero_copy_only=False)
    if odd.any():
        lists = [[p for p in _CUT.split(t) if p] if o else _plain(t) for t, o in zip(texts.to_pylist(), odd, strict=True)]
        starts = np.zeros(len(lists) + 1, np.int64)
        np.cumsum([len(x) for x in lists], out=starts[1:])
        return pa.array([p for x in lists for p in x], pa.string()), starts
    lists = pc.split_pattern(texts, " ")
    starts = lists.offsets.to_numpy().astype(np.int64) - lists.offsets[0].as_py()
    flat = lists.flatten()
    first = np.zeros(len(flat), bool)
    first[starts[:-1]] = True
    space = pa.array(np.where(first, 0, 1).astype(np.int8))
    return pc.binary_join_element_wise(pc.take(pa.array(["", " "]), space), flat, ""), starts


def _plain(text: str) -> list[str]:
    head, *rest = text.split(" ")
    return [head, *(" " + x for x in rest)]


#: Chunks that are at most a word, marks, a line break, a word and marks, each a pre-token whatever stands around it.
#: Letters are those on which all tables of letters agree; marks leave out the apostrophe, which may begin a word.
_PLAIN = r"^(?P<a>[ ]?[A-Za-z\x{c0}-\x{d6}\x{d8}-\x{f6}\x{f8}-\x{ff}]+|)(?P<b>[ ]?[.,!?;:*#$%&|()\-]+|)(?P<c>\n|)(?P<d>[A-Za-z\x{c0}-\x{d6}\x{d8}-\x{f6}\x{f8}-\x{ff}]+|)(?P<e>[.,!?;:*#$%&|()\-]+|)$"


class PieceEncoder:
    """Encodes pre-tokens, each distinct one once, in a memory of two generations: when the younger is full it becomes
    the older, and what is met again moves over, so common pre-tokens stay and entries are bounded.

    fresh(list of pre-tokens) gives one bytes value each; chunk(text) gives that of a chunk of any form.
    """

    #: Entries of a generation.
    most = 200_000

    def __init__(self) -> None:
        self.known: dict[str, bytes] = {"": b""}
        self.older: dict[str, bytes] = {}

    def fresh(self, pieces: list[str]) -> list[bytes]:
        raise NotImplementedError

    def chunk(self, text: str) -> bytes:
        raise NotImplementedError

    def learn(self, pieces: set[str]) -> None:
        """Have every one of pieces in known."""
        if len(self.known) > self.most:
            self.older, self.known = self.known, {"": b""}
        known, older, new = self.known, self.older, []
        for p in pieces:
            if p not in known:
                if (value := older.get(p)) is None:
                    new.append(p)
                else:
                    known[p] = value
        if new:
            known.update(zip(new, self.fresh(new), strict=True))

    def of(self, chunks: pa.Array) -> pa.Array:
        """Values of distinct chunks: plain ones are cut, looked up and joined by column, others one by one."""
        cut = pc.extract_regex(chunks, _PLAIN)
        parts = [pc.struct_field(cut, k).fill_null("").dictionary_encode() for k in range(5)]
        lists = [p.dictionary.to_pylist() for p in parts]
        self.learn(set().union(*lists))
        known = self.known
        columns = [pa.array([known[x] for x in names], pa.large_binary()).take(p.indices) for names, p in zip(lists, parts, strict=True)]
        values = pc.binary_join_element_wise(*columns, pa.scalar(b"", pa.large_binary()))
        odd = cut.is_null()
        others = chunks.filter(odd).to_pylist()
        if not others:
            return values
        return pc.replace_with_mask(values, odd, pa.array([self.chunk(c) for c in others], pa.large_binary()))


def encoded(texts: pa.Array, encoder: PieceEncoder) -> tuple[pa.Array, np.ndarray]:
    """Binary array with each chunk's value in text order, and where each text's chunks begin."""
    flat, starts = cut(texts)
    coded = flat.dictionary_encode()
    return encoder.of(coded.dictionary).take(coded.indices), starts


def joined(values: pa.Array, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a large_binary array, and where each text's begin."""
    offsets = np.frombuffer(values.buffers()[1], np.int64)[values.offset : values.offset + len(values) + 1]
    data = values.buffers()[2]
    flat = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return flat, offsets[starts] if len(values) else np.zeros(len(starts), np.int64)

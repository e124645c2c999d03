"""Byte-level BPE by a lazily determinised transducer, and a streaming decoder with its own UTF-8 automaton.

A sequence of tokens is the encoding of its bytes just when each token is the encoding of its own bytes and each two
neighbours are the encoding of theirs. That makes the encodings a regular language over tokens: the transducer's
nondeterministic states are (last finished token, node of the byte trie). A deterministic state is a set of those
with the tokens each still owes; tokens on which all agree leave at once, so output lags by a bounded lookahead.
Transitions are made when a text first needs them and kept up to a bound.
"""

from __future__ import annotations

import base64
import hashlib
import re
from array import array
from collections.abc import Iterable, Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .common import arrow_bounded, chunks
from .pieces import PieceEncoder, encoded, joined

#: Transitions of the automaton (unless a caller asks for fewer), and tested neighbours, that a worker keeps.
TRANSITIONS, PAIRS = 200_000, 100_000


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}


class Transducer:
    def __init__(self, ranks: dict[bytes, int]) -> None:
        self.ranks, self.bytes_of = ranks, {r: b for b, r in ranks.items()}
        # the trie's edges in one dict, by node * 256 + byte: most nodes have few
        self.edges: dict[int, int] = {}
        self.token = array("i", [-1])
        self.inner = bytearray(1)
        for b, r in ranks.items():
            node = 0
            for x in b:
                if (nxt := self.edges.get(node << 8 | x)) is None:
                    self.inner[node] = 1
                    nxt = self.edges[node << 8 | x] = len(self.token)
                    self.token.append(-1)
                    self.inner.append(0)
                node = nxt
            self.token[node] = r
        self.pairs: dict[int, bool] = {}
        self.halves: dict[bytes, tuple[bytes, ...]] = {}
        self.spines: tuple[dict, dict] = ({}, {})
        self.whole: dict[int, bool] = {}
        self.most = TRANSITIONS
        self.reset()

    def reset(self) -> None:
        """Forget the determinised states; the start stays state 0."""
        # a state is flat, (last + 1) << 32 | node and what is owed in turn: a worker holds very many of them
        self.states: list[tuple] = [(0, ())]
        self.ids = {self.states[0]: 0}
        self.moves: dict[int, tuple[int, tuple[int, ...]]] = {}
        self.ends: list[tuple[int, ...] | None] = [()]

    def merged(self, piece: bytes, parts_left: int = 1) -> list[bytes]:
        """Merges by rank, as the vocabulary defines them, until so many parts are left."""
        parts = [piece[i : i + 1] for i in range(len(piece))]
        while len(parts) > parts_left:
            best = min(((self.ranks[a + b], i) for i, (a, b) in enumerate(zip(parts, parts[1:])) if a + b in self.ranks), default=None)
            if best is None:
                break
            i = best[1]
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        return parts

    def _halves(self, token: bytes) -> tuple[bytes, ...]:
        """The two parts whose merge ends a token's own encoding; itself if it is a byte; none if it is never made."""
        if (parts := self.halves.get(token)) is None:
            two = self.merged(token, 2)
            parts = self.halves[token] = tuple(two) if len(two) <= 2 and b"".join(two) == token else ()
        return parts

    def _spine(self, token: int, side: int) -> list[tuple[bytes, float]]:
        """What stands at one side (0: left end, 1: right end) of a token while it is made, with the rank of the merge
        that takes it up."""
        if (spine := self.spines[side].get(token)) is None:
            part, until, spine = self.bytes_of[token], float("inf"), []
            while True:
                spine.append((part, until))
                if len(part) == 1:
                    break
                until, part = self.ranks[part], self._halves(part)[-1 if side else 0]
            self.spines[side][token] = spine
        return spine

    def follows(self, a: int, b: int) -> bool:
        """Whether tokens a, b (a = -1: none) stand side by side in some encoding.

        They don't just when, while both are made, what ends a and what begins b would merge before either is taken up
        on its own side; of equal ranks, the merge further left goes first.
        """
        if (ok := self.whole.get(b)) is None:
            ok = self.whole[b] = bool(self._halves(self.bytes_of[b]))
        if a < 0 or not ok:
            return ok
        if (ok := self.pairs.get(a << 32 | b)) is None:
            if len(self.pairs) > PAIRS:
                self.pairs.clear()
            rank, right = self.ranks.get, self._spine(b, 0)
            ok = True
            for x, x_until in self._spine(a, 1):
                for y, y_until in right:
                    if (m := rank(x + y)) is not None and m < x_until and m <= y_until:
                        ok = False
                        break
                if not ok:
                    break
            self.pairs[a << 32 | b] = ok
        return ok

    def _move(self, state: int, byte: int) -> tuple[int, tuple[int, ...]]:
        reached = []
        own = self.states[state]
        for code, owed in zip(own[::2], own[1::2], strict=True):
            if (nxt := self.edges.get((code & 0xFFFFFFFF) << 8 | byte)) is None:
                continue
            if self.inner[nxt]:
                reached.append((code >> 32 << 32 | nxt, owed))
            if (t := self.token[nxt]) >= 0 and self.follows((code >> 32) - 1, t):
                reached.append(((t + 1) << 32, (*owed, t)))
        common = reached[0][1] if reached else ()
        for _, owed in reached:
            if owed[: len(common)] != common:
                k = 0
                while k < len(owed) and owed[k] == common[k]:
                    k += 1
                common = common[:k]
            if not common:
                break
        if common:
            cut = len(common)
            reached = [(code, owed[cut:]) for code, owed in reached]
        key = tuple(x for pair in sorted(reached) for x in pair)
        if (i := self.ids.get(key)) is None:
            i = self.ids[key] = len(self.states)
            self.states.append(key)
            self.ends.append(next((owed for code, owed in zip(key[::2], key[1::2], strict=True) if code & 0xFFFFFFFF == 0), None))
        step = self.moves[state << 8 | byte] = (i << 8, common)
        return step

    def encode(self, piece: bytes) -> list[int]:
        """Tokens of one pre-token; a piece that is a token is that token, as the library has it."""
        return self.encode_sorted([piece])[0]

    def encode_sorted(self, pieces: list[bytes]) -> list[list[int]]:
        """Tokens of pieces in order; each starts in the state where it parts from the one before."""
        if len(self.moves) > self.most:
            self.reset()
        moves, ranks, out = self.moves, self.ranks, []
        trail, sent = [0], [0]  # state, and tokens sent, after each byte of the last piece; states come shifted by 8
        tokens: list[int] = []
        for piece, same in zip(pieces, shared_starts(pieces), strict=True):
            if piece in ranks:
                out.append([ranks[piece]])
                same = min(same, len(trail) - 1)
                del trail[same + 1 :], sent[same + 1 :]
                continue
            same = min(same, len(trail) - 1)
            del trail[same + 1 :], sent[same + 1 :]
            del tokens[sent[same] :]
            state = trail[same]
            for byte in piece[same:]:
                if (step := moves.get(state | byte)) is None:
                    step = self._move(state >> 8, byte)
                state, owed = step
                if owed:
                    tokens += owed
                trail.append(state)
                sent.append(len(tokens))
            out.append(tokens + list(self.ends[state >> 8] or ()))
        return out


def shared_starts(pieces: list[bytes]) -> list[int]:
    """Leading bytes that each piece shares with the one before it, up to 32."""
    if len(pieces) < 2:
        return [0] * len(pieces)
    cut = np.array(pieces, "S32").view(np.uint8).reshape(len(pieces), 32)
    same = np.cumprod(cut[1:] == cut[:-1], axis=1, dtype=np.uint8).sum(axis=1, dtype=np.int64)
    sizes = np.array([len(p) for p in pieces])
    return [0, *np.minimum(same, np.minimum(sizes[1:], sizes[:-1])).tolist()]


def _utf8_steps() -> tuple[np.ndarray, list[tuple[int, int, int]]]:
    """STEPS[state, byte] -> state of the automaton of UTF-8. State 0 is between characters; a state is the number of
    continuation bytes due and the range of the next one; the last state is that of bytes that no character can hold."""
    leads = {range(0xC2, 0xE0): (1, 0x80, 0xBF), range(0xE0, 0xE1): (2, 0xA0, 0xBF), range(0xE1, 0xED): (2, 0x80, 0xBF), range(0xED, 0xEE): (2, 0x80, 0x9F),
             range(0xEE, 0xF0): (2, 0x80, 0xBF), range(0xF0, 0xF1): (3, 0x90, 0xBF), range(0xF1, 0xF4): (3, 0x80, 0xBF), range(0xF4, 0xF5): (3, 0x80, 0x8F)}
    states = [(0, 0, 0), *sorted({*leads.values(), (1, 0x80, 0xBF), (2, 0x80, 0xBF)})]
    steps = np.full((len(states) + 1, 256), len(states), np.uint8)
    steps[0, :0x80] = 0
    for bytes_, state in leads.items():
        steps[0, bytes_.start : bytes_.stop] = states.index(state)
    for k, (due, low, high) in enumerate(states[1:], 1):
        steps[k, low : high + 1] = states.index((due - 1, 0x80, 0xBF)) if due > 1 else 0
    return steps, states


STEPS, _STATES = _utf8_steps()
INVALID = len(_STATES)
_ROWS = [row.tolist() for row in STEPS]
_NOT_ASCII = re.compile(rb"[\x80-\xff]")


class Utf8Stream:
    """Incremental UTF-8: feed bytes cut anywhere, get text; only an unfinished character waits (3 bytes at most).

    The automaton steps through every byte that isn't ASCII and gathers the character's bits; bytes that no character
    can hold give the replacement character, one for each longest valid start.
    """

    def __init__(self) -> None:
        self.state, self.bits, self.wait = 0, 0, b""

    def feed(self, data: bytes) -> str:
        out, at, end, state, bits = [], 0, len(data), self.state, self.bits
        began = -len(self.wait) if state else 0  # where the unfinished character begins
        while at < end:
            byte = data[at]
            if state == 0:
                if byte < 0x80:  # a run of ASCII
                    stop = m.start() if (m := _NOT_ASCII.search(data, at)) else end
                    out.append(data[at:stop].decode("ascii"))
                    at = stop
                    continue
                state, began = _ROWS[0][byte], at
                at += 1
                if state == INVALID:
                    out.append("\ufffd")
                    state = 0
                else:
                    bits = byte & (0x1F if byte < 0xE0 else 0x0F if byte < 0xF0 else 0x07)
                continue
            after = _ROWS[state][byte]
            if after == INVALID:  # the byte may begin a character of its own
                out.append("\ufffd")
                state = 0
                continue
            bits, state = bits << 6 | byte & 0x3F, after
            at += 1
            if state == 0:
                out.append(chr(bits))
        self.wait = (self.wait + data if began < 0 else data[began:]) if state else b""
        self.state, self.bits = state, bits
        return "".join(out)

    def close(self) -> str:
        unfinished, self.state, self.bits, self.wait = self.state, 0, 0, b""
        return "\ufffd" if unfinished else ""


class TokenDecoder:
    """The automaton lifted to tokens: where each token's bytes lead from each state, so that a stream of ids is decoded
    a token at a step, and most of them, which begin and end between characters, all at once."""

    def __init__(self, bytes_of: list[bytes]) -> None:
        self.bytes = pa.array(bytes_of, pa.large_binary())
        flat, sizes = np.frombuffer(b"".join(bytes_of), np.uint8), np.array([len(b) for b in bytes_of])
        starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
        self.leads = np.repeat(np.arange(INVALID + 1, dtype=np.uint8)[:, None], len(sizes), axis=1)  # [state, token] -> state
        for k in range(sizes.max(initial=0)):
            on = np.flatnonzero(sizes > k)
            self.leads[:, on] = STEPS[self.leads[:, on], flat[starts[on] + k][None, :]]

    def decode(self, ids: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """All bytes of the texts' ids, where each text's begin, and whether the automaton takes each text as UTF-8."""
        data, data_at = joined(self.bytes.take(pa.array(ids)), at)
        good = np.ones(len(at) - 1, bool)
        open_ = np.flatnonzero(self.leads[0][ids] != 0)  # tokens that don't begin and end between characters
        if len(open_):
            rows, tokens = np.searchsorted(at, open_, "right") - 1, ids[open_]
            last_row, state, next_place = -1, 0, 0
            for place, row, token in zip(open_.tolist(), rows.tolist(), tokens.tolist(), strict=True):
                if row != last_row:
                    if state and last_row >= 0:
                        good[last_row] = False
                    last_row, state = row, 0
                elif state and place != next_place:  # a whole token came while a character was unfinished
                    state = INVALID
                state, next_place = int(self.leads[state, token]), place + 1
            if state:
                good[last_row] = False
        return data, data_at, good


class Codec(PieceEncoder):
    """Encodes and decodes texts in batches: pre-tokens through the transducer once each, ids back through the automaton."""

    def __init__(self, ranks_file: str, pattern: str) -> None:
        super().__init__()
        ranks = read_ranks(ranks_file)
        self.machine, self.pattern = Transducer(ranks), regex.compile(pattern)
        self.decoder = TokenDecoder([self.machine.bytes_of.get(i, b"") for i in range(max(ranks.values()) + 1)])

    def fresh(self, pieces: list[str]) -> list[bytes]:
        order = sorted(range(len(pieces)), key=pieces.__getitem__)
        values: list[bytes] = [b""] * len(pieces)
        for a in range(0, len(order), 20_000):
            some = order[a : a + 20_000]
            for i, ids in zip(some, self.machine.encode_sorted([pieces[i].encode("utf-8") for i in some]), strict=True):
                values[i] = array("I", ids).tobytes()
        return values

    def chunk(self, text: str) -> bytes:
        found = self.pattern.findall(text)
        if any(p not in self.known for p in found):
            self.learn(set(found))
        return b"".join([self.known[p] for p in found])

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids, and where each text's begin."""
        values, starts = encoded(texts, self)
        flat, at = joined(values, starts)
        return flat[: at[-1]].view("<u4"), at // 4

    def decode_stream(self, ids: Iterable[int]) -> Iterator[str]:
        """Text of a stream of ids, token by token."""
        stream = Utf8Stream()
        for i in ids:
            if text := stream.feed(self.machine.bytes_of[i]):
                yield text
        if text := stream.close():
            yield text


_CODECS: dict[tuple[str, str], Codec] = {}
_DIGITS: dict[int, pa.Array] = {}


def codec(vocabulary: str, pattern: str) -> Codec:
    if (vocabulary, pattern) not in _CODECS:
        _CODECS[vocabulary, pattern] = Codec(public_tokenizers.path(vocabulary), pattern)
    return _CODECS[vocabulary, pattern]


def encode_texts(docs: DataFrame, vocabulary: str = "byte_bpe_50k.tiktoken", pattern: str = public_tokenizers.PATTERN, with_ids: bool = False, carry: tuple[str, ...] = (), slice_bytes: int = 4 << 20, transitions: int = TRANSITIONS) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256, valid_utf8 (and ids, if asked; and the carried columns) for each row.

    ids_sha256 is over the decimal ids joined by spaces, decoded_sha256 over the bytes that the ids decode to, and
    valid_utf8 is whether the decoder's automaton, token by token, ends each of their characters. A null text counts as empty: no ids, both hashes those of no bytes. Repeated rows and null ids stay; other columns are
    ignored. No shuffle; memory follows a slice of texts (slice_bytes) and the bounded memo (transitions); neither
    changes a row.
    """
    keep = ["doc_id", *carry]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(vocabulary, pattern)
        own.machine.most = transitions
        top = len(own.decoder.bytes)
        if top not in _DIGITS:
            _DIGITS[top] = pa.array([b"%d " % i for i in range(top)], pa.large_binary())
        for batch in batches:
            for part in chunks(batch, "text", slice_bytes):
                ids, at = own.encode(part.column("text"))
                text, text_at, good = own.decoder.decode(ids, at)
                plain, plain_at = joined(_DIGITS[top].take(pa.array(ids)), at)
                text, plain = memoryview(text), memoryview(plain)
                ids_sha = [hashlib.sha256(plain[a : max(a, b - 1)]).hexdigest() for a, b in zip(plain_at[:-1].tolist(), plain_at[1:].tolist(), strict=True)]
                text_sha = [hashlib.sha256(text[a:b]).hexdigest() for a, b in zip(text_at[:-1].tolist(), text_at[1:].tolist(), strict=True)]
                columns = [part.column(k) for k in keep] + [pa.array(np.diff(at)), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string()), pa.array(good)]
                if with_ids:
                    columns.append(pa.ListArray.from_arrays(pa.array(at.astype(np.int32)), pa.array(ids.astype(np.int32))))
                yield pa.RecordBatch.from_arrays(columns, names)

    names = [*keep, "n_tokens", "ids_sha256", "decoded_sha256", "valid_utf8", *["ids"] * with_ids]
    kept = ", ".join(f"`{k}` {docs.schema[k].dataType.simpleString()}" for k in keep)
    return arrow_bounded(docs.select(*keep, "text")).mapInArrow(run, f"{kept}, n_tokens long, ids_sha256 string, decoded_sha256 string, valid_utf8 boolean" + ", ids array<int>" * with_ids)

"""Encoders against the libraries, the token store's round trip, token counts."""

import hashlib
import random
import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from pathframe.llm import counts, pieces, store, transducer

BPE, WORDS, RANKS = "byte_bpe_50k.json", "word_bpe_49k.json", "byte_bpe_50k.tiktoken"
ODD = ["", " ", "  ", " a", "a ", "a  b", "\n", " \n a", "a" * 3000, " " * 400, "<|endoftext|>", "a <|endoftext|> b<|endoftext|>", "don't we'll I'M", "word.\nNext, one", "x \u00a0y", "日本 語😀", "3.14 a1b2", "'s 's", "a|b *** c"]


def texts(n, seed):
    rng = random.Random(seed)
    letters = "ab cde\n\téßñ're123.,!日😀 \r\x85K"
    return ["".join(rng.choice(letters) for _ in range(rng.randint(0, 50))) for _ in range(n)]


@pytest.fixture(scope="module")
def rank_library():
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=transducer.read_ranks(public_tokenizers.path(RANKS)), special_tokens={})


def test_cut_loses_nothing():
    for some in (ODD, texts(200, 1), ["plain text only", ""], []):
        flat, starts = pieces.cut(pa.array(some, pa.string()))
        flat = flat.to_pylist()
        assert ["".join(flat[a:b]) for a, b in zip(starts[:-1], starts[1:])] == some


def test_transducer_agrees_with_the_library(rank_library):
    some = ODD + texts(1500, 2)
    own = transducer.codec(RANKS, public_tokenizers.PATTERN)
    ids, at = own.encode(pa.array(some))
    data, data_at, good = own.decoder.decode(ids, at)
    assert good.all()
    for k, t in enumerate(some):
        assert list(ids[at[k] : at[k + 1]]) == rank_library.encode_ordinary(t)
        assert bytes(data[data_at[k] : data_at[k + 1]]) == t.encode()
        assert "".join(own.decode_stream(ids[at[k] : at[k + 1]])) == t


def test_neighbours_by_spines_agree_with_merging():
    machine = transducer.codec(RANKS, public_tokenizers.PATTERN).machine
    rng = random.Random(3)
    short = [r for b, r in machine.ranks.items() if len(b) <= 4]
    for _ in range(20000):
        a, b = rng.choice(short), rng.choice(short)
        x, y = machine.bytes_of[a], machine.bytes_of[b]
        whole = machine.merged(x) == [x] and machine.merged(y) == [y]
        if whole:
            assert machine.follows(a, b) == (machine.merged(x + y) == [x, y]), (x, y)


def test_bounded_memories_change_nothing(rank_library, monkeypatch):
    monkeypatch.setattr(transducer, "TRANSITIONS", 50)
    own = transducer.Codec(public_tokenizers.path(RANKS), public_tokenizers.PATTERN)
    own.most = 20
    for seed in range(4):
        some = texts(60, 10 + seed)
        ids, at = own.encode(pa.array(some))
        assert [list(ids[a:b]) for a, b in zip(at[:-1], at[1:])] == [rank_library.encode_ordinary(t) for t in some]


@settings(max_examples=200, deadline=None)
@given(st.binary(max_size=40), st.lists(st.integers(0, 40)))
def test_stream_decodes_as_codecs_do(data, cuts):
    stream, out, last = transducer.Utf8Stream(), "", 0
    for c in sorted(c for c in cuts if c <= len(data)):
        out += stream.feed(data[last:c])
        last = c
        assert len(stream.wait) <= 3
    assert out + stream.feed(data[last:]) + stream.close() == data.decode("utf-8", "replace")


@settings(max_examples=150, deadline=None)
@given(st.lists(st.lists(st.integers(0, 400), max_size=12), max_size=4))
def test_tokens_in_any_order_are_told_from_text(rows):
    """The automaton over tokens says what a codec says of their bytes, valid or not."""
    decoder = transducer.codec(RANKS, public_tokenizers.PATTERN).decoder
    at = np.concatenate([[0], np.cumsum([len(r) for r in rows], dtype=np.int64)]).astype(np.int64)
    ids = np.array([i for r in rows for i in r], np.uint32)
    data, data_at, good = decoder.decode(ids, at)
    for k in range(len(rows)):
        own = bytes(data[data_at[k] : data_at[k + 1]])
        try:
            own.decode("utf-8")
            assert good[k]
        except UnicodeDecodeError:
            assert not good[k]


def frame(spark, some):
    return spark.createDataFrame([(i, t, "x", 1) for i, t in enumerate(some)] + [(None, "null id", "x", 1), (0, some[0], "x", 1)], "doc_id long, text string, n_tokens string, start int")


def test_encode_query(spark, rank_library):
    some = [*ODD, None]
    rows = transducer.encode_texts(frame(spark, some), with_ids=True).collect()
    assert len(rows) == len(some) + 2
    for r in rows:
        t = "null id" if r["doc_id"] is None else some[r["doc_id"]] or ""
        ids = rank_library.encode_ordinary(t)
        assert (r["n_tokens"], r["ids"]) == (len(ids), ids)
        assert r["ids_sha256"] == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(t.encode()).hexdigest() and r["valid_utf8"]


def test_counts_query(spark):
    library, some = Tokenizer.from_file(public_tokenizers.path(WORDS)), [*ODD, "ΑΣ ΑΣ é ́x İ", None]
    for r in counts.count_tokens(frame(spark, some), limit=100).collect():
        t = "null id" if r["doc_id"] is None else some[r["doc_id"]] or ""
        n = len(library.encode(t, add_special_tokens=False).ids)
        assert (r["n_bytes"], r["n_tokens"], r["over_limit"]) == (len(t.encode()), n, n > 100)
    assert counts.count_tokens(frame(spark, some).limit(0)).count() == 0


@pytest.mark.parametrize("bits", [3, 8, 11])
def test_segments_give_every_id(bits):
    rng = np.random.default_rng(0)
    ids = np.concatenate([rng.integers(0, 70000, 3000), np.zeros(700), [2**32 - 1, 0, 255, 256]]).astype(np.uint32)
    starts = np.array([0, 0, 5, 5, 3000, len(ids)])
    part = store.Segment(store.pack(ids, np.arange(5), starts, 7, bits))
    assert [part[i] for i in range(len(ids))] == ids.tolist() and part.before == 7
    for _ in range(100):
        a, b = sorted(rng.integers(0, len(ids) + 1, 2).tolist())
        assert (part.slice(a, b) == ids[a:b]).all()
    assert [len(part.document(k)) for k in range(5)] == np.diff(starts).tolist()
    with pytest.raises(IndexError):
        part[len(ids)]


def test_store_round_trip(spark, tmp_path, monkeypatch):
    library, some = Tokenizer.from_file(public_tokenizers.path(BPE)), [*ODD, *texts(300, 4), None]
    docs = spark.createDataFrame([(i * 7 % 1009, t, 0) for i, t in enumerate(some)], "doc_id long, text string, shard int").repartition(5)
    path = store.write_tokens(docs, segment_ids=500)
    got = {r["doc_id"]: r for r in store.read_documents(spark, path).collect()}
    at = 0
    for i, t in sorted((i * 7 % 1009, t or "") for i, t in enumerate(some)):
        ids = [*library.encode(t, add_special_tokens=False).ids, 0]
        assert (got[i]["start"], got[i]["n_tokens"], got[i]["ids_crc32"]) == (at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        at += len(ids)
    n = store.export_files(spark, path, f"{tmp_path}/files")
    files = sorted((tmp_path / "files").glob("*.ids"))
    assert len(files) == n > 1 and sum(store.Segment(f.read_bytes()).n_ids for f in files) == at
    # any token by its place among all, through Spark and through files mapped into memory
    every = np.concatenate([[*library.encode(t, add_special_tokens=False).ids, 0] for _, t in sorted((i * 7 % 1009, t or "") for i, t in enumerate(some))])
    monkeypatch.setattr(store, "BUCKET", 700)
    rng = random.Random(8)
    places = [0, at - 1, at, at + 10**9, 5, 5, *(rng.randrange(at) for _ in range(60))]
    rows = store.tokens_at(spark, path, spark.createDataFrame([(p,) for p in places], "place long")).collect()
    assert sorted((r["place"], r["token"]) for r in rows if r["token"] is not None) == sorted((p, int(every[p])) for p in places if p < at)
    assert len(rows) == len(places) and sum(r["token"] is None for r in rows) == 2
    mapped = store.Store(f"{tmp_path}/files")
    assert len(mapped) == at and [mapped[p] for p in places if p < at] == [int(every[p]) for p in places if p < at]
    assert mapped.document(7).tolist() == [*library.encode(some[1], add_special_tokens=False).ids, 0]
    with pytest.raises(KeyError):
        mapped.document(10**6)
    empty = store.write_tokens(docs.limit(0))
    assert store.read_documents(spark, empty).count() == 0


def test_store_of_odd_ids(spark):
    """The smallest long is an id like others, null ids go first, and an id of a third of the rows is split."""
    rows = [(None, "a b"), (-(2**63), "c d"), (None, None), (3, "x"), *[(5, f"t {k % 7}") for k in range(400)]]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")  # which would put so few rows together again
    try:
        path = store.write_tokens(docs, segment_ids=50)
    finally:
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")
    got = sorted(store.read_documents(spark, path).collect(), key=lambda r: r["start"])
    assert [r["doc_id"] for r in got] == [None, None, -(2**63), 3, *[5] * 400]
    assert spark.read.parquet(path).select("shard").distinct().count() > 2
    at = 0
    for r in got:
        assert r["start"] == at
        at += r["n_tokens"]


def test_a_workers_memory_of_states_is_small():
    import tracemalloc

    machine = transducer.codec(RANKS, public_tokenizers.PATTERN).machine
    rng = random.Random(5)
    machine.reset()
    pieces = sorted({" " + "".join(rng.choices("abcdefghijklmnopqrstuvwxyz", k=rng.randint(4, 12))) for _ in range(8000)})
    tracemalloc.start()
    machine.encode_sorted([p.encode() for p in pieces])
    held = tracemalloc.get_traced_memory()[0] / len(machine.moves)
    tracemalloc.stop()
    assert held * transducer.TRANSITIONS < 110e6

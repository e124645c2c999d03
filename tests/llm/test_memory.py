"""What bounds a worker's memory changes no row."""

import random

import corpus_pipeline
from pathframe.llm import transducer


def test_small_slices_and_few_transitions(spark, monkeypatch):
    rng = random.Random(11)
    word = lambda: "".join(rng.choice("abcdeéß中😀'’ -") for _ in range(rng.randint(1, 14)))
    rows = [(k, None if k % 9 == 4 else " ".join(word() for _ in range(rng.randint(0, 60))), "en", "s") for k in range(60)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").coalesce(1)
    whole = transducer.encode_texts(docs, with_ids=True, carry=("lang", "source")).collect()
    small = transducer.encode_texts(docs, with_ids=True, carry=("lang", "source"), slice_bytes=200, transitions=50).collect()
    assert sorted(whole) == sorted(small) and len(whole) == 60

    asked, real = {}, transducer.encode_texts
    monkeypatch.setattr(transducer, "encode_texts", lambda *a, **k: asked.update(k) or real(*a, **k))
    assert sorted(corpus_pipeline.bpe_tokens(spark, docs, "").collect()) == sorted(whole)
    assert asked["slice_bytes"] <= 1 << 20 and asked["transitions"] <= transducer.TRANSITIONS // 2


def test_transitions_are_forgotten_beyond_the_bound():
    machine = transducer.codec("byte_bpe_50k.tiktoken", transducer.public_tokenizers.PATTERN).machine
    rng = random.Random(12)
    pieces = [bytes(rng.choice(b"abcdefgh") for _ in range(12)) for _ in range(400)]
    machine.reset()
    whole, grown = [machine.encode(p) for p in pieces], len(machine.moves)
    machine.reset()
    machine.most = 300
    try:
        assert [machine.encode(p) for p in pieces] == whole
        assert len(machine.moves) <= 312 < grown
    finally:
        machine.most = transducer.TRANSITIONS

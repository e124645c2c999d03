"""Texts that earlier forms of the operators read in part."""

import random

import pytest

from pathframe.llm import licenses, pages


def docs_of(spark, some):
    return spark.createDataFrame(list(enumerate(some)), "doc_id long, text string")


BSD = "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"
MPL = "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."
GRANT = "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files"
UNLESS = "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS"


def wrapped(text, every, mark=""):
    w = text.split()
    return "\n".join(mark + " ".join(w[i : i + every]) for i in range(0, len(w), every))


def test_wrapped_notices(spark):
    notices = [(BSD, "bsd"), (MPL, "mpl"), (GRANT, "mit"), (UNLESS, "apache")]
    some = [f"Some words before it.\n{mark}Words of the head. {wrapped(text, every, mark)}\nAnd after." for text, _ in notices for every, mark in ((99, ""), (10, ""), (7, " * "), (3, "# "), (1, ""))]
    apart = [wrapped(BSD, 9).replace("\n", "\n\n"), wrapped(BSD, 9, " * ").replace("\n", "\n *\n"), "redistribution in source\n" + "word " * 80 + "\nbinary forms with or without modification are permitted provided that the following conditions are met"]
    got = {r["doc_id"]: (r["labels"], r["score"]) for r in licenses.scan_licenses(docs_of(spark, some + apart)).collect()}
    for k, label in enumerate(label for _, label in notices for _ in range(5)):
        assert got[k] == (label, 1.0), some[k]
    assert {got[len(some) + k] for k in range(3)} == {("", 0.0)}


@pytest.mark.parametrize("threshold", [0.5, 0.8, 0.9, 1.0])
def test_guard_words_lose_no_match(threshold):
    sets = [sorted(set(t.split())) for _, t in licenses.TEMPLATES]
    need = [-(-round(threshold * 1000) * len(ws) // 1000) for ws in sets]
    guard = set(licenses.guards(sets, need))
    assert all(len(set(ws) - guard) < n for ws, n in zip(sets, need, strict=True))


def test_blocks_are_told_by_words_wherever_they_stand():
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("etaoinshrdlu") for _ in range(rng.randrange(3, 9)))
    sentence = lambda n: " ".join(word() for _ in range(n)).capitalize() + "."
    model, right = pages.labeller(), []
    for cue in ("posted on Monday morning by {} All rights reserved.", "and on this site we use cookies {}.", "{} subscribe to our newsletter."):
        for _ in range(20):
            said = f"{sentence(15)[:-1]} {cue.format(sentence(4)[:-1])}"
            plain = sentence(len(said.split()))
            got = [pages.main_texts([f"<html><body><div class='content'><p>{sentence(30)}</p><p>{text}</p><p>{sentence(25)}</p></div></body></html>"], model)[0].split("\n") for text in (said, plain)]
            right.append(len(got[0]) == 2 and said not in got[0] and len(got[1]) == 3)
    assert sum(right) >= 0.8 * len(right)


def test_open_heads_and_text_of_formulas_and_drawings():
    texts = lambda page: [t for _, t, _ in pages.leaves(page)]
    assert texts("<html><head><title>t</title><body><p>article") == ["article"]
    assert texts("<head><meta charset=utf-8><script>var a = '<p>';</script><style>p{}</style><link rel=x><p>one<p>two") == ["one", "two"]
    assert texts("<html><head>\n<title>t</title>\nbare <b>words</b>") == ["bare words"]
    assert texts("<head><title>t</title></head><body>a</body>") == ["a"] and texts("<head><noscript><p>no</p></noscript><template><p>no</p></template><body>a") == ["a"]
    assert texts("<p>with <math><mi>x</mi><mo>=</mo><mn>2</mn></math> it holds</p>") == ["with x=2 it holds"]
    assert texts("<p>a</p><svg><title>no</title><style>no</style><text x='1'>axis</text><text>label</text></svg><object data=x>fallback</object><canvas><p>drawn</p></canvas><p>b") == ["a", "axis", "label", "fallback", "drawn", "b"]
    page = "<html><head><title>t</title><body><div class='content'><h1>A title of it</h1><p>The first sentence of the article stands here.</p><p>And a second one follows it.</p></div></body></html>"
    assert "first sentence" in pages.main_texts([page], pages.labeller())[0]

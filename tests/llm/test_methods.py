"""What the learned parts of the operators decide, on cases that they didn't learn from; odd columns and long texts."""

import random

import pytest

from pathframe.llm import private, quality

FOLDER = "/root/testdata/sf0.01"


def docs_of(spark, some):
    return spark.createDataFrame(list(enumerate(some)), "doc_id long, text string")


def spans_of(spark, some, model):
    return {r["doc_id"]: r["spans"] for r in private.find_private(docs_of(spark, some), model).collect()}


def labelled(n, seed):
    """Texts with one candidate each, and whether it is personal."""
    rng = random.Random(seed)
    hexes = lambda k: "".join(rng.choice("0123456789abcdef") for _ in range(k - 2)) + "a7"
    digits = lambda k: "".join(rng.choice("0123456789") for _ in range(k))
    word = lambda: "".join(rng.choice("etaoinshrdlu") for _ in range(rng.randrange(3, 8)))

    def no_card():
        while True:
            d = digits(16)
            if sum(sum(divmod(int(x) * (1 + i % 2), 10)) for i, x in enumerate(reversed(d))) % 10:
                return d

    kinds = [
        (True, lambda: f'token = "{hexes(40)}"'), (True, lambda: f"password: {word()}{digits(3)}"), (True, lambda: f"call ({digits(3)}) {digits(3)}-{digits(4)}"), (True, lambda: f"AKIA{'Q7' * 8}"),
        (True, lambda: f"Dear {rng.choice(private.GIVEN_NAMES)} {word().capitalize()},"), (True, lambda: f"lives at {rng.randrange(1, 999)} {word().capitalize()} {rng.choice(private.STREETS)}"), (True, lambda: f"api_key={hexes(32)}"),
        (False, lambda: f"articles/2023/{word()}-final-v{rng.randrange(9)}"), (False, lambda: f"covid-19-infection-{rng.randrange(2019, 2024)}"), (False, lambda: f"id {hexes(8)}-{hexes(4)}-{hexes(4)}-{hexes(4)}-{hexes(12)}"),
        (False, lambda: f"ISBN 978-3-16-{digits(6)}-{digits(1)}"), (False, lambda: f"from 20{rng.randrange(10, 24)}-03-04 20{rng.randrange(10, 24)}-05-06"), (False, lambda: f"commit {hexes(40)}"), (False, lambda: f"the {no_card()} of"),
        (False, lambda: f"in {rng.choice(['Victoria', 'Alexander', 'Charlotte'])} {rng.choice(private.NO_SURNAMES)}"), (False, lambda: f"order {digits(9)}"),
    ]
    out = []
    for _ in range(n):
        personal, make = rng.choice(kinds)
        out.append((f"{word()} {word()} {make()} {word()} {word()}.", personal))
    return out


def test_spans_of_held_out_texts(spark):
    model = private.fit(docs_of(spark, [t for t, _ in labelled(400, 1)]))
    held = labelled(300, 2)
    got = spans_of(spark, [t for t, _ in held], model)
    hit = sum(bool(got[i]) and y for i, (_, y) in enumerate(held))
    assert hit >= 0.9 * sum(y for _, y in held) and hit >= 0.9 * sum(bool(s) for s in got.values())


def test_spans_by_the_given_texts(spark):
    """Fitted where nearly all candidates are personal, the model still needs evidence for each."""
    model = private.fit(spark.read.parquet(f"{FOLDER}/documents.parquet"))
    no = ["see articles/2023/report-final-v2 here", "covid-19-infection-2021 is", "id 123e4567-e89b-12d3-a456-426614174000 x", "ISBN 978-3-16-148410-0.", "from 2021-03-04 2022-05-06 on", "commit 9fceb02d0ae598e95dc970b74767f19372d61af8 ok", "the number 9807915762804490 in"]
    yes = ['token = "24be64439e3e49cf46b2d7c90f3602a3d0b907ff"### x', "password: hunter", "call (229) 555-4838 now", "Dear Mary Johnson, hello", "lives at 12 Baker Street in"]
    got = spans_of(spark, no + yes, model)
    assert [bool(got[i]) for i in range(len(no) + len(yes))] == [False] * len(no) + [True] * len(yes)


def test_a_labeler_that_never_votes_keeps_its_start():
    post, right = private.estimate({(1, 0, 1): 1000, (-1, 0, -1): 1000, (0, 0, 0): 5000})
    assert right[1] == pytest.approx(0.8) and right[0] > 0.9 and post[(0, 0, 0)] == pytest.approx(0.5)


def test_redaction_of_clashing_columns_and_many_spans(spark):
    model = private.Classifier((2.0,) * 7, (0.0,) * 8, (0.0,) * 7, (0.8,) * 7)
    n = 3000  # beyond a block of the running sums and many pieces of text
    many = "é a%d@example.com x 1.2.3.4 y " * n
    df = spark.createDataFrame([(1, many, 5, "s", "c"), (2, "", 0, "s", "c"), (3, None, None, None, None), (4, "no data", 7, "s", "c"), (5, "a@b.cc", 6, "s", "c")], "doc_id long, text string, n_chars long, spans string, `clean.x` string")
    got = {r["doc_id"]: r for r in private.redact(df, model).collect()}
    assert list(got[1].asDict()) == df.columns and got[1]["text"] == "é <email> x <ip> y " * n and got[1]["n_chars"] == len(got[1]["text"])
    assert (got[2]["text"], got[3]["text"], got[4]["text"], got[4]["n_chars"], got[5]["text"], got[1]["spans"], got[1]["clean.x"]) == ("", None, "no data", 7, "<email>", "s", "c")
    assert private.find_private(df, model).filter("doc_id = 1").first()["n_email"] == n


def test_list_learned_from_few_labels(spark):
    docs, labels = (spark.read.parquet(f"{FOLDER}/{t}.parquet") for t in ("documents", "labels"))
    rules = quality.learn_from(docs, labels)
    judged = quality.judge_quality(docs, rules).join(labels, "doc_id").filter("NOT base_failed")
    bad, good = judged.filter("quality = 0"), judged.filter("quality = 1")
    assert rules and bad.filter("kept").count() <= 0.1 * bad.count() and good.filter("NOT kept").count() <= 0.02 * good.count()
    # ids of any type, ids that repeat, and a bound on the rows that are read
    named = docs.selectExpr("concat('d', doc_id) doc_id", "text").union(docs.selectExpr("concat('d', doc_id) doc_id", "text"))
    assert quality.learn_from(named, labels.selectExpr("concat('d', doc_id) doc_id", "quality"), most=300) != []


def test_long_texts_are_measured_whole(spark):
    words = [f"w{i}" for i in range(60_000)]
    docs = docs_of(spark, [" ".join(words + words[100:40_000] + ["end"])])
    got = quality.judge_quality(docs, []).first()
    assert (got["n_words"], got["n_repeat_words"]) == (99_901, 2 * 39_900)

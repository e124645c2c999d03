"""Queries that give the whole answer where their bounded neighbours, checked by SQL, give a part of it."""

import random

from pyspark.sql import functions as F

from pathframe.operators.pathset import PathSet, co_ended
from pathframe.operators.recursion import Log, closure
from pathframe.queries import catalogue
from pathframe.sources import catalog


SMALL = "/root/testdata/sf0.001"


def far(ends):
    """{(src, dst): least number of steps}, one or more, by breadth-first search from every node."""
    out, ways = {}, {}
    for a, b in ends:
        ways.setdefault(a, set()).add(b)
    for a in ways:
        level, new = 1, set(ways[a])
        while new:
            out |= {(a, b): level for b in new}
            new = {c for b in new for c in ways.get(b, ()) if (a, c) not in out}
            level += 1
    return out


def relay_table(spark, folder, users):
    """Purchases of one user after another, all on one day."""
    rows = [(k, k, u, "purchase") for k, u in enumerate(users)]
    df = spark.createDataFrame(rows, "event_id long, s long, user_id long, event_type string")
    df.select("event_id", F.timestamp_seconds(F.col("s") + 1_700_000_000 // 86400 * 86400).alias("ts"), "user_id", "event_type").coalesce(1).write.parquet(f"{folder}/events.parquet")


def test_shortest_relays_of_all_pairs(spark, tmp_path):
    relay_table(spark, tmp_path, [1, 2, 3, 4, 5, 6, 7, 8, 9, 1, 5, 2, 2, 10])
    known = far({(r["src"], r["dst"]) for r in catalog.relay(spark, str(tmp_path)).edges().df.collect()})
    assert max(known.values()) > 3
    got = {q: catalogue.queries()[f"{q}_unbounded"](spark, str(tmp_path)).collect() for q in ("shortest_relay", "any_shortest_walk_relay", "all_shortest_acyclic_relay")}
    for q, rows in got.items():
        want = {k: n for k, n in known.items() if q != "all_shortest_acyclic_relay" or k[0] != k[1]}
        assert {(r["src"], r["dst"]): r["len"] for r in rows} == want, q
        assert len({r["edges_txt"] for r in rows}) == len(rows) and all(len(r["edges_txt"].split("-")) == r["len"] for r in rows)
    assert len(got["any_shortest_walk_relay"]) == len(known)


def text_tables(spark, folder, texts, items=(), labels=()):
    spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long").coalesce(1).write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame(list(labels), "doc_id long, quality int, toxic int").coalesce(1).write.parquet(f"{folder}/labels.parquet")
    spark.createDataFrame(list(enumerate(items)), "item_id long, text string").coalesce(1).write.parquet(f"{folder}/benchmark.parquet")


def test_copies_of_large_groups(spark, tmp_path):
    texts = ["same", "other", "same", "same", "same", "one", "same", "same", "other"]
    labels = [(0, 1, 0), (2, 0, 0), (7, 1, 0), (6, 0, 0)]
    text_tables(spark, tmp_path, texts, labels=labels)
    bit, quality = 10 << 48, {d: q for d, q, _ in labels}
    pairs = {(a, b) for a in range(9) for b in range(a + 1, 9) if texts[a] == texts[b]}
    ends = lambda q: {(r["src"] - bit, r["dst"] - bit) for r in catalogue.queries()[q](spark, str(tmp_path)).collect()}
    assert ends("copy_chain_unbounded") == pairs
    good = {(a, b) for a, b in pairs if quality.get(a) == 1 and quality.get(b) != 0}
    assert ends("copy_chain_quality_unbounded") == good and (0, 7) in good
    rows = catalogue.queries()["copy_groups"](spark, str(tmp_path)).collect()
    assert {(a["src"] - bit, b["src"] - bit) for a in rows for b in rows if a["representative"] == b["representative"] and a["links"] < b["links"]} == pairs
    assert {r["src"] - bit: r["not_bad_after"] for r in rows} == {d: sum(a == d and quality.get(b) != 0 for a, b in pairs) for d in {x for p in pairs for x in p}}


def test_passages_of_short_items(spark, tmp_path, monkeypatch):
    long = "one two three four five six seven eight"
    items = ["ab", "two words", "cat", "a\nb  c", "", "é😀", "w1 w2 w3 w4 w5 w6", "two words", long, "never there"]
    texts = ["concatenate", "x two words.", "xtwo wordsx a\nb  c", "", None, "z é😀 z", "0w1 w2 w3 w4 w5 w67", f"zero{long}!", "ab cat ab"]
    text_tables(spark, tmp_path, texts, items)
    want = {(d, i) for d, t in enumerate(texts) for i, x in enumerate(items) if t is not None and x in t}
    for most in (1 << 25, 8):  # one automaton, and several
        monkeypatch.setattr(catalog, "AUTOMATON_BYTES", most)
        rows = catalogue.queries()["doc_passage_quality"](spark, str(tmp_path)).collect()
        assert {(r["src"] - (10 << 48), r["dst"] - (13 << 48)) for r in rows} == want and len(rows) == len(want)


def test_closure_writes_hubs_not_their_pairs(spark):
    rng = random.Random(4)
    ring = {(k, (k + 1) % 12) for k in range(12)} | {(40, 0), (41, 40), (7, 50), (50, 51), (41, 51), (60, 60), (70, 71), (71, 72), (70, 72)}
    some = {(100 + rng.randrange(20), 100 + rng.randrange(20)) for _ in range(22)} | {(200 + rng.randrange(9), 200 + rng.randrange(9)) for _ in range(20)}
    log = Log()
    rows = closure(spark.createDataFrame(sorted(ring | some), "src long, dst long"), log=log).collect()
    assert {(r["src"], r["dst"]) for r in rows} == set(far(ring | some)) and len(rows) == len(set(rows))
    log = Log()
    assert closure(spark.createDataFrame(sorted(ring), "src long, dst long"), log=log).count() > 200
    assert sum(n for _, n in log.rounds) < 80


def test_pairs_of_common_ends_come_from_classes(spark):
    rng = random.Random(6)
    links = {k: {rng.randrange(6) for _ in range(rng.randint(1, 3))} for k in range(40)}
    rows = [(k, 100 + v) for k, ends in links.items() for v in ends for _ in range(rng.randint(1, 2))]
    got = co_ended(PathSet(spark.createDataFrame(rows, "src long, dst long"), None))
    want = {(a, b): len(links[a] & links[b]) for a in links for b in links if a < b and links[a] & links[b]}
    assert {(r["src"], r["dst"]): r["shared"] for r in got.collect()} == want and got.count() == len(want)
    assert "Aggregate" not in got._jdf.queryExecution().optimizedPlan().toString()  # no row of a pair is shuffled


def test_plans_and_languages_read_tables(spark, tmp_path):
    spark.createDataFrame([(1, "A"), (2, None), (3, "B c"), (4, 'D"')], "s_suppkey long, s_name string").write.parquet(f"{tmp_path}/supplier.parquet")
    rows = catalogue.queries()["plan_text"](spark, str(tmp_path)).collect()
    for key, name in ((1, "A"), (3, "B c")):
        plan = [r["plan"] for r in sorted(rows, key=lambda r: r["line"]) if r["supplier"] == key]
        assert plan[0] == "as written" and "as run" in plan and sum(f'first.name = "{name}"' in x for x in plan) == 3
    assert {r["supplier"] for r in rows} == {1, 3, 4}
    own = catalogue.queries()["expressiveness"](spark, SMALL).collect()
    assert {r["label"]: r["edges"] for r in own}["LIVES_IN"] == spark.read.parquet(f"{SMALL}/customer.parquet").count()
    assert {r["language"]: r["combinations"] for r in own} == {"standard": 28, "algebra, printed": 1960, "algebra, all": 2560} and len(own) == 18


def test_good_copies_are_slices_of_their_groups(spark, tmp_path, monkeypatch):
    texts = ["a" if k % 3 else "b" for k in range(30)] + [None, "c", None]
    labels = [(k, k % 5 != 0, 0) for k in range(0, 33, 2)]
    text_tables(spark, tmp_path, texts, labels=[(d, int(q), t) for d, q, t in labels])
    quality = {d: int(q) for d, q, _ in labels}
    monkeypatch.setattr("pathframe.operators.recursion.written", None)  # a recursion would write its rounds
    want = set()
    for t in set(texts):
        own = [k for k, x in enumerate(texts) if x == t]
        for i, a in enumerate(own):
            want |= {("-".join(str((10 << 48) + x) for x in own[i : j + 1]), "-".join(str((116 << 48) + x) for x in own[i:j]), j - i) for j in range(i + 1, len(own)) if quality.get(a) == 1 and quality.get(own[j]) != 0}
    rows = catalogue.queries()["copy_chain_quality_unbounded"](spark, str(tmp_path)).collect()
    assert {(r["nodes_txt"], r["edges_txt"], r["len"]) for r in rows} == want and len(rows) == len(want)
    assert all(r["nodes_txt"].startswith(str(r["src"])) and r["nodes_txt"].endswith(str(r["dst"])) for r in rows)

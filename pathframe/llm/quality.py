"""Quality rules: text statistics, and a learned decision list emitted as an ordered conditional expression."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import let

_SPACE = " \t\n\x0b\f\r"
#: Rows of labelled documents that a list is learned from, at most: those of the smallest hashes of their ids and texts.
SAMPLE = 4000
#: A rule must be right for this share of the rows that it rejects, in the pruning part and in all; and reject this share
#: of the bad rows there are when learning begins, SEEN rows at least.
PRECISION, COVER, SEEN = 0.95, 0.02, 3
MOST_RULES, MOST_CONDITIONS, CUTS = 12, 4, 24


def words_of(text: Column) -> Column:
    return F.filter(F.split(text, "[\\x20\\x09-\\x0D]+"), lambda w: w != "")


def repeated_words(words: Column, width: int = 5) -> Column:
    """Words inside windows of `width` words that occur twice or more, the first occurrence included.

    Windows are compared by 64-bit hashes within one text. Texts without a repeat stop after one distinct count; for
    others, windows are sorted by hash, those with an equal neighbour are put back in order, and their words counted:
    time grows as n log n.
    """

    def windows(hashes: Column) -> Column:
        return F.transform(F.slice(hashes, 1, F.greatest(F.size(hashes) - (width - 1), F.lit(0))), lambda h, i: F.xxhash64(h, *[hashes[i + k] for k in range(1, width)]))

    def marked(ordered: Column) -> Column:
        """Places of the windows that have an equal neighbour in the order of hashes."""
        alike = lambda s, k: F.coalesce(F.get(ordered, k)["h"] == s["h"], F.lit(False))
        return F.array_sort(F.transform(F.filter(ordered, lambda s, k: alike(s, k - 1) | alike(s, k + 1)), lambda s: s["i"]))

    def covered(found: Column) -> Column:
        # each marked window adds the words that the marked window before it doesn't hold
        start = F.struct(F.lit(0).cast("long").alias("n"), F.lit(-width).alias("last"))
        step = lambda s, i: F.struct((s["n"] + F.least(F.lit(width), i - s["last"])).alias("n"), i.alias("last"))
        ordered = F.array_sort(F.transform(found, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        return F.when(F.size(F.array_distinct(found)) == F.size(found), F.lit(0).cast("long")).otherwise(F.aggregate(let(ordered, marked), start, step, lambda s: s["n"]))

    return let(let(F.transform(words, lambda w: F.xxhash64(w)), windows), covered)


def statistics(text: Column) -> Column:
    """struct of the contract's counts and of those that only the learned list reads; a null text counts as empty."""
    text = F.coalesce(text, F.lit(""))
    lines = F.filter(F.split(text, "\n"), lambda s: F.length(F.translate(s, _SPACE, "")) > 0)
    without = lambda s: F.length(text) - F.length(F.translate(text, s, ""))
    long = lambda c, name: c.cast("long").alias(name)

    def of_words(words: Column) -> Column:
        return F.struct(
            long(F.size(words), "n_words"), long(F.length(F.translate(text, _SPACE, "")), "word_chars"), long(without("#*$%&|<>"), "n_symbols"),
            let(lines, lambda x: long(F.size(x) - F.size(F.array_distinct(x)), "n_dup_lines")).alias("n_dup_lines"), repeated_words(words).alias("n_repeat_words"),
            long(F.size(F.array_distinct(words)), "n_distinct"), long(without("ABCDEFGHIJKLMNOPQRSTUVWXYZ"), "n_capitals"), long(without("0123456789"), "n_digits"), long(without(".,;:!?"), "n_marks"), long(F.size(lines), "n_lines"),
        )

    return let(words_of(text), of_words)


def _shares(s: Column) -> dict[str, Column]:
    """The measures that conditions test; all of them are 0 for a text without words."""
    per = lambda a, b: F.when(s[b] > 0, s[a] / s[b]).otherwise(F.lit(0.0))
    return {
        "words": s["n_words"].cast("double"), "word_length": per("word_chars", "n_words"), "symbols": per("n_symbols", "word_chars"), "dup_lines": per("n_dup_lines", "n_lines"), "repeats": per("n_repeat_words", "n_words"),
        "distinct": per("n_distinct", "n_words"), "capitals": per("n_capitals", "word_chars"), "digits": per("n_digits", "word_chars"), "marks": per("n_marks", "word_chars"), "line_words": per("n_words", "n_lines"),
    }


@dataclass(frozen=True)
class Condition:
    measure: str
    above: bool
    cut: float

    def holds(self, row: dict[str, float]) -> bool:
        return row[self.measure] > self.cut if self.above else row[self.measure] <= self.cut


@dataclass(frozen=True)
class Rule:
    conditions: tuple[Condition, ...]

    def holds(self, row: dict[str, float]) -> bool:
        return all(c.holds(row) for c in self.conditions)


def learn(rows: Sequence[tuple[dict[str, float], bool]]) -> list[Rule]:
    """Sequential covering over (measures, is bad): grow on two thirds, prune on the rest, drop what a rule covers.

    Bad rows and good ones are dealt to the parts by position, each kind by itself, so that few bad ones are in both
    parts, and the list depends on nothing but the rows. Conditions are pruned from the end; a rule stays that is right
    for PRECISION of what it rejects in the pruning part and in all. What a rule covers goes, and so do the growing rows
    of a rule that is refused, so one bad rule doesn't end the list. Empty rows, or none bad, give an empty list.
    """
    measures = sorted(rows[0][0]) if rows else []
    x, bad = np.array([[r[m] for m in measures] for r, _ in rows], float).reshape(len(rows), len(measures)), np.array([b for _, b in rows], bool)
    place = np.zeros(len(rows), np.int64)
    for kind in (bad, ~bad):
        place[kind] = np.arange(kind.sum())
    growing, alive, rules = place % 3 != 0, np.ones(len(rows), bool), []
    least, tried = max(SEEN, int(COVER * bad.sum())), 0
    while len(rules) < MOST_RULES and tried < 3 * MOST_RULES and (alive & growing & bad).any():
        tried += 1
        held, chosen, options = alive & growing, [], []
        while len(chosen) < MOST_CONDITIONS and (held & ~bad).any():
            if (found := _best(x[held], bad[held])) is None:
                break
            m, above, cut = found
            chosen.append(Condition(measures[m], above, cut))
            held &= (x[:, m] > cut) if above else (x[:, m] <= cut)
            options.append(list(chosen))
        scored = []
        for conditions in options:
            met = alive.copy()
            for c in conditions:
                column = x[:, measures.index(c.measure)]
                met &= (column > c.cut) if c.above else (column <= c.cut)
            part = met & ~growing
            if met.sum() >= least and part.any() and bad[part].mean() >= PRECISION and bad[met].mean() >= PRECISION:
                scored.append(((bad[part].mean() - 0.5) * part.sum(), -len(conditions), conditions, met))
        if scored:
            _, _, conditions, met = max(scored, key=lambda s: s[:2])
            rules.append(Rule(tuple(conditions)))
            alive &= ~met
        elif options:
            alive &= ~(held & growing)
        else:
            break
    return rules


def _best(x: np.ndarray, bad: np.ndarray) -> tuple[int, bool, float] | None:
    """(measure, above, cut) of the largest information gain over the rows that it keeps; cuts stand half way to the next
    value, so that rows unlike any seen aren't rejected by a hair."""
    p, n = int(bad.sum()), len(bad)
    if not p or p == n:
        return None
    base, best, most = np.log2(p / n), None, 1e-9
    for m in range(x.shape[1]):
        order = np.argsort(x[:, m], kind="stable")
        values, upto = x[order, m], np.cumsum(bad[order])
        ends = np.flatnonzero(np.append(values[1:] != values[:-1], False))  # a cut stands after these
        if len(ends) > 16 * CUTS:
            ends = ends[np.unique(np.concatenate([np.linspace(0, len(ends) - 1, 12 * CUTS).astype(int), np.arange(2 * CUTS), np.arange(len(ends) - 2 * CUTS, len(ends))]))]
        low_p, low_n = upto[ends].astype(float), ends + 1.0
        for above, a, b in ((True, p - low_p, n - low_n), (False, low_p, low_n)):
            with np.errstate(divide="ignore", invalid="ignore"):
                gain = np.where(a > 0, a * (np.log2(a / b) - base), -1.0)
            if len(gain) and gain.max() > most:
                k = int(gain.argmax())
                best, most = (m, above, float((values[ends[k]] + values[ends[k] + 1]) / 2)), gain[k]
    return best


def learn_from(docs: DataFrame, labels: DataFrame, most: int = SAMPLE) -> list[Rule]:
    """A list learned from at most `most` rows of labelled documents (quality 0: bad) that pass the base test, which the
    list adds to; rows of null ids or labels are left out, and of several labels of an id the worst counts.

    Only these rows' measures reach the driver, `most` rows of ten numbers, whatever the type of the ids and however
    often one repeats; they are picked by hash of id and text, the same at every run and in any order of rows.
    """
    picked = labels.filter(F.col("quality").isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.min("quality").alias("quality"))
    picked = picked.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    rows = docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id")
    rows = rows.orderBy(F.xxhash64("doc_id"), "doc_id", F.xxhash64("text")).limit(most)
    shares = _shares(F.col("s"))
    got = rows.withColumn("s", statistics(F.col("text"))).select(base_failed(F.col("s")).alias("failed"), "quality", F.xxhash64("doc_id").alias("at"), *[c.alias(k) for k, c in shares.items()]).collect()
    got = sorted((r for r in got if not r["failed"]), key=lambda r: (r["at"], *[r[k] for k in shares]))
    return learn([({k: float(r[k]) for k in shares}, r["quality"] == 0) for r in got])


def rejected(stats: Column, rules: Sequence[Rule]) -> Column:
    """Number of the first rule that a text meets (from 1), else 0: an ordered conditional expression."""
    shares, out = _shares(stats), None
    for i, rule in enumerate(rules, 1):
        test = None
        for c in rule.conditions:
            one = shares[c.measure] > F.lit(c.cut) if c.above else shares[c.measure] <= F.lit(c.cut)
            test = one if test is None else test & one
        out = F.when(test, i) if out is None else out.when(test, i)
    return F.lit(0) if out is None else out.otherwise(0)


def base_failed(stats: Column) -> Column:
    return (stats["n_words"] < 10) | (100 * stats["n_repeat_words"] > 20 * stats["n_words"])


def judge_quality(docs: DataFrame, rules: Sequence[Rule]) -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, rule for each row.

    A null or empty text has zero counts and fails the base test. Repeated rows and null ids stay; other columns of
    docs are ignored.
    """
    s = F.col("s")
    out = docs.select("doc_id", statistics(F.col("text")).alias("s"))
    out = out.select("doc_id", *[s[k].alias(k) for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")], base_failed(s).alias("base_failed"), rejected(s, rules).alias("rule"))
    return out.select(*[c for c in out.columns if c != "rule"], (~F.col("base_failed") & (F.col("rule") == 0)).alias("kept"), "rule")


def keep_good(docs: DataFrame, rules: Sequence[Rule]) -> DataFrame:
    """The rows of docs that pass, with their columns."""
    tested = let(statistics(F.col("text")), lambda s: ~base_failed(s) & (rejected(s, rules) == 0))
    return docs.filter(tested)

"""License scans: stated phrases by place, and an exact set-similarity join of text blocks with notice templates."""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, let

#: phrase: label. The contract's phrases.
PHRASES = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}
#: Notices whose word sets are looked for in blocks; fixed values, worded as the licences' own short notices are.
TEMPLATES = (
    ("apache", "licensed under the apache license version 2 0"),
    ("apache", "you may not use this file except in compliance with the license"),
    ("apache", "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis"),
    ("mit", "released under the mit license"),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"),
    ("gpl", "this work is licensed under the gnu general public license version 3"),
    ("gpl", "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
    ("cc-by-nc", "licensed under cc by nc 4 0"),
    ("cc-by-sa", "licensed under cc by sa 4 0"),
    ("cc-by", "this work is licensed under a creative commons attribution 4 0 international license"),
    ("mpl", "this source code form is subject to the terms of the mozilla public license v 2 0"),
)
#: Share of a template's words that a block must hold: all of a short notice, as such notices differ in a word or two.
CONTAINMENT = 0.9
_IN = "0-9A-Za-z\\x{80}-\\x{10FFFF}"


def word_count(text: Column) -> Column:
    return F.regexp_count(text, F.lit(f"[{_IN}]+")).cast("long")


def _phrase_pattern(phrase: str) -> str:
    return f"(?i)(?<![{_IN}])" + f"[^{_IN}]+".join(phrase.split()) + f"(?![{_IN}])"


def phrase_places(text: Column, n_words: Column, phrase: str) -> Column:
    """struct(n, first, last): number of places of the phrase, and the smallest and largest word index where one starts."""
    pattern, size = _phrase_pattern(phrase), len(phrase.split())
    none = F.struct(F.lit(0).cast("long").alias("n"), F.lit(None).cast("long").alias("first"), F.lit(None).cast("long").alias("last"))
    found = let(
        F.split(text, pattern, -1),
        lambda pieces: F.struct((F.size(pieces) - 1).cast("long").alias("n"), word_count(pieces[0]).alias("first"), (n_words - word_count(F.element_at(pieces, -1)) - size).alias("last")),
    )
    return F.when(text.rlike(pattern), found).otherwise(none)


def guards(sets: list[list[str]], need: list[int]) -> list[str]:
    """Words of which any block that reaches its need holds one at least: the longest of each template, one more than it may lack."""
    return sorted({w for ws, n in zip(sets, need, strict=True) for w in sorted(ws, key=lambda w: (-len(w), w))[: len(ws) - n + 1]})


def blocks_with_words(docs: DataFrame, vocabulary: list[str], least: int, onward: int, guard: list[str]) -> DataFrame:
    """doc_id, text_key, words: distinct template words of each block that has at least `least` of them.

    A block is a line with the next `onward` words of its paragraph, however they are broken into lines, so a notice
    that begins in a line is whole in that line's block. A paragraph ends at a line without words, such as a bare
    comment mark. Texts without a guard word have no block that could match.
    """
    known = F.array(*[F.lit(w) for w in vocabulary])
    text = ascii_lower(F.col("text"))
    lines = F.transform(F.split(text, "\n"), lambda b: F.filter(F.split(b, "[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+"), lambda w: w != ""))

    def follow(all_lines: Column, i: Column) -> Column:
        """Words after line i in its paragraph: each of its lines has one at least, so `onward` lines are enough."""
        return let(F.slice(all_lines, i + 2, onward), lambda ahead: let(F.array_position(F.transform(ahead, F.size), F.lit(0)), lambda stop: F.slice(F.flatten(F.when(stop > 0, F.slice(ahead, 1, (stop - 1).cast("int"))).otherwise(ahead)), 1, onward)))

    blocks = let(lines, lambda all_lines: F.transform(all_lines, lambda own, i: F.when(F.size(own) > 0, F.array_intersect(F.concat(own, follow(all_lines, i)), known)).otherwise(F.array().cast("array<string>"))))
    kept = F.array_distinct(F.transform(F.filter(blocks, lambda w: F.size(w) >= least), lambda w: F.array_sort(w)))
    likely = docs.filter(text.rlike("|".join(guard)))
    return likely.select("doc_id", F.xxhash64("text").alias("text_key"), F.explode(kept).alias("words"))


def template_matches(docs: DataFrame, templates=TEMPLATES, threshold: float = CONTAINMENT) -> DataFrame:
    """doc_id, text_key, method_labels, containment: exact join of blocks with templates by prefix, length and position.

    Words outside every template can't overlap one, so blocks are cut to template words first; the word order is that
    of the number of blocks of the whole input in which a word occurs, rarest first. The template side is the
    documented constant list (a few hundred words) and is all that is broadcast.
    """
    spark = docs.sparkSession
    sets = [(i, label, sorted(set(text.split()))) for i, (label, text) in enumerate(templates)]
    vocabulary = sorted({w for _, _, ws in sets for w in ws})
    # ceil in integers of thousandths, so that a share such as 0.8 is exact
    need = {i: -(-round(threshold * 1000) * len(ws) // 1000) for i, _, ws in sets}
    onward = 2 * max((len(text.split()) for _, text in templates), default=0)  # room for words put into a notice
    blocks = blocks_with_words(docs, vocabulary, min(need.values()), onward, guards([ws for _, _, ws in sets], list(need.values())))
    counted = dict(blocks.select(F.explode("words").alias("word")).groupBy("word").count().collect())  # at most len(vocabulary) rows
    order = {w: r for r, w in enumerate(sorted(vocabulary, key=lambda w: (counted.get(w, 0), w)))}
    heads, bodies = [], []
    for i, label, ws in sets:
        ranks = sorted(order[w] for w in ws)
        bodies.append((i, label, ranks, need[i]))
        heads += [(r, i, at, label, ranks, need[i]) for at, r in enumerate(ranks[: len(ranks) - need[i] + 1])]
    index = spark.createDataFrame(heads, "head int, template int, at int, label string, ranks array<int>, need int")
    rank_of = F.create_map(*[F.lit(x) for pair in order.items() for x in pair])
    ranked = blocks.select("doc_id", "text_key", F.array_sort(F.transform("words", lambda w: rank_of[w])).alias("own"))
    probes = ranked.select("doc_id", "text_key", "own", F.posexplode("own").alias("place", "head"))
    met = probes.join(F.broadcast(index), "head")
    met = met.filter((F.size("own") >= F.col("need")) & (F.least(F.size("own") - F.col("place"), F.size("ranks") - F.col("at")) + F.least(F.col("place"), F.col("at")) >= F.col("need")))
    shared = F.size(F.array_intersect("own", "ranks"))
    met = met.withColumn("shared", shared).filter(F.col("shared") >= F.col("need"))
    best = met.groupBy("doc_id", "text_key").agg(F.collect_set("label").alias("method_labels"), F.max(F.col("shared") / F.size("ranks")).alias("containment"))
    return best  # collect_set holds at most one entry for each label of the list


def scan_licenses(docs: DataFrame, phrases: Mapping[str, str] = PHRASES, templates=TEMPLATES, threshold: float = CONTAINMENT) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, one row for each row of docs.

    score is 1 with a stated phrase, else the largest containment that reaches the threshold, else 0. Null texts count
    as empty: no words, no labels (empty strings), score 0. Repeated rows stay; a null doc_id is kept; blocks are the
    lines of a text, each with the words that follow in its paragraph; other columns of docs are ignored.
    """
    own = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    places = own.select("doc_id", "text", word_count(F.col("text")).alias("n_words"))
    names = list(phrases)
    places = places.select("doc_id", F.xxhash64("text").alias("text_key"), "n_words", *[phrase_places(F.col("text"), F.col("n_words"), p).alias(f"phrase_{i}") for i, p in enumerate(names)])
    all_of = lambda f: [F.col(f"phrase_{i}.{f}") for i in range(len(names))]
    extreme = lambda fn, f: fn(*all_of(f), F.lit(None).cast("long"))  # noqa: E731  skips nulls
    labels = F.filter(F.array(*[F.when(F.col(f"phrase_{i}.n") > 0, F.lit(phrases[p])) for i, p in enumerate(names)]), lambda x: x.isNotNull())
    n_base = sum(all_of("n")[1:], all_of("n")[0])
    places = places.select("doc_id", "text_key", "n_words", n_base.alias("n_base"), extreme(F.least, "first").alias("first_word"), extreme(F.greatest, "last").alias("last_word"), labels.alias("base"))
    found = template_matches(own, templates, threshold).withColumnsRenamed({"doc_id": "found_id", "text_key": "found_key"})
    both = places.join(found, F.col("doc_id").eqNullSafe(F.col("found_id")) & (F.col("text_key") == F.col("found_key")), "left")
    text_of = lambda a: F.array_join(F.array_sort(F.array_distinct(a)), ",")
    return both.select(
        "doc_id", "n_words", "n_base", "first_word", "last_word", text_of(F.col("base")).alias("base_labels"),
        text_of(F.concat("base", F.coalesce("method_labels", F.array().cast("array<string>")))).alias("labels"),
        F.when(F.col("n_base") > 0, F.lit(1.0)).otherwise(F.coalesce("containment", F.lit(0.0))).alias("score"),
    )


def oracle_sql(templates=TEMPLATES, threshold: float = CONTAINMENT) -> str:
    """The same from all words of each paragraph in a row: a line's own and those that follow it, by their numbers."""
    listed = ", ".join(f"({i}, '{label}', {sorted(set(text.split()))!r})" for i, (label, text) in enumerate(templates))
    onward = 2 * max(len(text.split()) for _, text in templates)
    fold = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    return f"""
WITH templates(i, label, ws) AS (VALUES {listed}),
d AS (SELECT row_number() OVER () AS r, doc_id, {fold} AS t FROM documents),
w AS (SELECT r, doc_id, t, regexp_extract_all(t, '[0-9a-z\\x{{80}}-\\x{{10FFFF}}]+') AS ws FROM d),
p AS (SELECT r, unnest(range(1, len(ws) + 1)) AS i, ws FROM w WHERE t LIKE '%license%'),
hits AS (
  SELECT r, i - 1 AS place, 'mit' AS label FROM p WHERE ws[i] = 'mit' AND ws[i + 1] = 'license'
  UNION ALL SELECT r, i - 1, 'apache' FROM p WHERE ws[i] = 'apache' AND ws[i + 1] = 'license'
  UNION ALL SELECT r, i - 1, 'gpl' FROM p WHERE ws[i] = 'general' AND ws[i + 1] = 'public' AND ws[i + 2] = 'license'),
base AS (SELECT r, count(*) AS n, min(place) AS a, max(place) AS b FROM hits GROUP BY r),
split AS (SELECT r, generate_subscripts(ls, 1) AS l, unnest(ls) AS line FROM (SELECT r, string_split(t, chr(10)) AS ls FROM w)),
told AS (SELECT r, l, regexp_extract_all(line, '[0-9a-z\\x{{80}}-\\x{{10FFFF}}]+') AS ws FROM split),
para AS (SELECT r, l, ws, sum(CASE WHEN len(ws) = 0 THEN 1 ELSE 0 END) OVER (PARTITION BY r ORDER BY l) AS p FROM told),
run AS (SELECT r, p, flatten(list(ws ORDER BY l)) AS all_ws FROM para WHERE len(ws) > 0 GROUP BY r, p),
line AS (SELECT r, p, len(ws) AS n, sum(len(ws)) OVER (PARTITION BY r, p ORDER BY l) AS upto FROM para WHERE len(ws) > 0),
b AS (SELECT r, list_distinct(all_ws[upto - n + 1 : upto + {onward}]) AS ws FROM line JOIN run USING (r, p)),
m AS (SELECT r, label, len(list_intersect(b.ws, templates.ws)) / len(templates.ws) AS c FROM b, templates
      WHERE len(list_intersect(b.ws, templates.ws)) * 1000 >= {round(threshold * 1000)} * len(templates.ws)),
best AS (SELECT r, max(c) AS c FROM m GROUP BY r),
named AS (SELECT r, string_agg(DISTINCT label, ',' ORDER BY label) AS labels FROM (SELECT r, label FROM hits UNION SELECT r, label FROM m) GROUP BY r),
stated AS (SELECT r, string_agg(DISTINCT label, ',' ORDER BY label) AS labels FROM hits GROUP BY r)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(base.n, 0) AS BIGINT) AS n_base, CAST(base.a AS BIGINT) AS first_word, CAST(base.b AS BIGINT) AS last_word,
  coalesce(stated.labels, '') AS base_labels, coalesce(named.labels, '') AS labels,
  CASE WHEN coalesce(base.n, 0) > 0 THEN 1.0 ELSE coalesce(best.c, 0) END::DOUBLE AS score
FROM w LEFT JOIN base USING (r) LEFT JOIN best USING (r) LEFT JOIN named USING (r) LEFT JOIN stated USING (r)
"""

"""Personal data: stated patterns by place, and further spans found by weak supervision.

Candidates beyond the stated patterns get votes from regex, gazetteer and context labelers. Counts of the distinct vote
patterns and shapes over the whole corpus go to the driver, expectation-maximisation estimates each labeler's
reliability from them, and a logistic classifier over a span's shape is trained on the posteriors; labelers' log odds
and the classifier's weights come back as one column expression. A span without evidence is not personal.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import free_name, let, quoted, running

#: Kinds in their stated order; those from "secret" on are the method's own.
KINDS = ("email", "ip", "card", "phone", "secret", "number", "name", "address")
#: A search begins where a run begins or where the match before ended; runs are taken whole, which changes no match
#: (what follows a run can't begin inside it) and keeps the time in proportion to the text.
_EMAIL = r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
_IP = r"(?:(?<![0-9])|\G)[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"
_CARD = r"[0-9](?:[\x20-]?[0-9])++"
_PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"

#: Gazetteers, fixed values: given names that are no common words; words of street names; words that follow a name-like
#: word in names of places and firms; words that make a token a phrase, not a key.
GIVEN_NAMES = (
    "Aaron Abigail Adrian Alexander Alice Amelia Amir Andrea Andrew Angela Anna Anthony Antonio Barbara Benjamin Bernard Brandon Brian Camille Carlos Carmen Carol Catherine Charles Charlotte "
    "Chloe Christian Christine Christopher Claire Claudia Daniel David Deborah Diego Dorothy Edward Elena Elizabeth Emily Emma Eric Fatima Francis Francisco Frank Gabriel George Hannah Hans "
    "Heather Helen Henry Isabella Jacob James Jason Jean Jennifer Jessica Johann John Jonathan Jorge Joseph Joshua Juan Julia Karen Katherine Kevin Klaus Laura Linda Louis Lucas Margaret Maria "
    "Marie Martin Mary Matthew Michael Michelle Miguel Mohammed Nancy Natalie Nicholas Nicole Olivia Pablo Patricia Patrick Paul Pedro Peter Philip Pierre Rachel Raymond Rebecca Richard Robert "
    "Samantha Samuel Sandra Sarah Sophia Stephanie Stephen Steven Susan Thomas Timothy Vanessa Victor Victoria Vincent Walter William Yusuf Zachary"
).split()
STREETS = "Street St Avenue Ave Road Rd Boulevard Blvd Lane Ln Drive Court Square Terrace Highway Parkway Crescent".split()
NO_SURNAMES = "Street Avenue Road Square Station University College School Hospital Church Bridge Park River Lake Island County City Airport Museum Award Prize Cup Inc Ltd Corporation Company Group Foundation Institute".split()
PHRASE_WORDS = "article articles report final draft version page pages chapter section figure table index news blog post image images photo file files data test build release update download static content covid infection study".split()
_CUE = r"(?:password|passwd|passwort|pwd|secret|token|api[_-]?key|access[_-]?key|private[_-]?key|credentials?|bearer)"
_NEGATIVE = r"(?:version|isbn|issn|doi|page|chapter|figure|sha1?|sha256|md5|commit|revision|checksum|digest|hash|build|issue|ref|path|file|uuid|guid|etag)"
_CONTACT = r"(?:phone|tel|telephone|mobile|cell|call|fax|ssn|social security|account|acct|iban|passport|card|contact|whatsapp)"
#: What candidates look like. A value after a cue and "=" or ":"; a long run of token characters.
_TOKEN = r"(?<![A-Za-z0-9_/+.-])[A-Za-z0-9_/+-]{16,}+"
#: Begins at the mark, which is rare, and looks back for the cue.
_ASSIGNED = rf"[=:](?<=(?i:{_CUE})[\"']{{0,1}}\s{{0,3}}[=:])"
_SECRET = rf"(?<=[\s\"'=:])(?<=(?i:{_CUE})[\"']{{0,1}}\s{{0,3}}[=:]\s{{0,3}}[\"']{{0,1}})[^\s\"',;<>()\[\]{{}}#*%&$|!?]{{4,}}+|{_TOKEN}"
_NUMBER = r"(?<![A-Za-z0-9.])\(?[0-9](?:[\x20().-]{0,2}[0-9])++(?![A-Za-z])"
_SURNAME = r"[A-Z][a-z]+(?:[-'][A-Z][a-z]+)?"
_NAME = rf"(?=[A-Z][a-z])(?<![A-Za-z0-9])(?:(?:Mr|Mrs|Ms|Dr|Prof)\.?\x20{_SURNAME}(?:\x20{_SURNAME})?|(?:{'|'.join(GIVEN_NAMES)})(?:\x20[A-Z]\.)?\x20{_SURNAME})\b"
_ADDRESS = rf"(?<![0-9A-Za-z.,])[0-9]{{1,5}}[A-Za-z]?\x20(?:[A-Z][a-z]+\x20){{1,3}}(?:{'|'.join(STREETS)})\b"
#: Characters before and after a candidate that the context labelers read, at most, inside what parts it from the next.
CONTEXT, AFTER = 24, 8


#: (kind, pattern, what a text must hold to be searched for it, what it must not hold). What must be held is quick to look
#: for: a single class, or something that begins with a rare character.
PATTERNS = (
    ("email", _EMAIL, ("@",), ""), ("ip", _IP, (r"[0-9]\.[0-9]",), ""), ("card", _CARD, ("[0-9]",), ""), ("phone", _PHONE, (r"\+",), ""),
    ("secret", _SECRET, ("[=:]", _ASSIGNED), ""), ("secret", _TOKEN, ("[0-9]", "[A-Za-z0-9_/+-]{16}"), _ASSIGNED), ("number", _NUMBER, ("[0-9]",), ""),
    ("name", _NAME, (r"[A-Z][a-z]+\.?\x20(?:[A-Z]\.\x20)?[A-Z][a-z]",), ""), ("address", _ADDRESS, (r"[0-9][A-Za-z]?\x20[A-Z][a-z]",), ""),
)


def found_in(text: Column, kinds: tuple[str, ...]) -> Column:
    """array<struct(kind, found, between)> of the kinds that text has matches of: the matches, and what parts them."""
    none = F.lit(None).cast("struct<kind:int,found:array<string>,between:array<string>>")

    def one(kind: str, pattern: str, needs: tuple[str, ...], unless: str) -> Column:
        hits = lambda found: F.when(F.size(found) > 0, F.struct(F.lit(KINDS.index(kind)).alias("kind"), found.alias("found"), F.split(text, pattern, -1).alias("between")))
        searched = reduce(Column.__and__, [text.rlike(n) for n in needs] + [~text.rlike(unless)] * bool(unless))
        return F.when(searched, let(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), hits)).otherwise(none)

    return F.array_compact(F.array(*[one(*p) for p in PATTERNS if p[0] in kinds]))


def placed(hits: Column) -> Column:
    """array<struct(kind, start, end, found, before, after)> in code points, of what found_in() gives. before ends with the
    match before, and after at the match that follows. Time grows as the matches do: no place is counted from the start."""

    def of(h: Column) -> Column:
        found, between = h["found"], h["between"]

        def one(f: Column, i: Column, ends: Column) -> Column:
            gap = between[i]
            before = F.when(F.length(gap) >= CONTEXT, gap).otherwise(F.concat(F.when(i > 0, F.right(found[F.greatest(i - 1, F.lit(0))], F.lit(CONTEXT))).otherwise(""), gap))
            return F.struct(h["kind"].alias("kind"), (ends[i] - F.length(f)).alias("start"), ends[i].alias("end"), f.alias("found"), F.right(before, F.lit(CONTEXT)).alias("before"), F.left(between[i + 1], F.lit(AFTER)).alias("after"))

        sizes = F.transform(found, lambda f, i: F.length(between[i]) + F.length(f))
        return let(running(sizes, "sum"), lambda ends: F.transform(found, lambda f, i: one(f, i, ends)))

    return F.flatten(F.transform(hits, of))


def _digits(s: Column) -> Column:
    return F.regexp_replace(s, "[^0-9]", "")


def _byte_sized(part: Column) -> Column:
    bare = F.ltrim(part, F.lit("0"))
    return (F.length(bare) < 3) | ((F.length(bare) == 3) & (bare <= "255"))


def luhn(digits: Column) -> Column:
    """Whether a string of at most a few dozen digits passes the check sum."""
    back = F.split(F.reverse(digits), "")
    worth = F.transform(back, lambda d, i: let(d.cast("int") * F.when(i % 2 == 1, 2).otherwise(1), lambda v: F.when(v > 9, v - 9).otherwise(v)))
    return F.aggregate(worth, F.lit(0), lambda a, v: a + F.coalesce(v, F.lit(0))) % 10 == 0


def _fits(s: Column) -> Column:
    """Whether a match is a span of its kind (the stated ones) or a candidate (the method's: values after a cue and long
    tokens with two digits, grouped digits, given names or titles with a surname, and street addresses)."""
    found, kind = s["found"], s["kind"]
    count = F.length(_digits(found))
    of = lambda k: kind == KINDS.index(k)
    cued = s["before"].rlike(rf"{_ASSIGNED}\s{{0,3}}[\"']?$")
    key = ((count >= 2) & found.rlike("[A-Za-z]")) | found.rlike("^A[KS]IA[0-9A-Z]{16}$")
    return (
        F.when(of("ip"), F.forall(F.split(found, "\\."), _byte_sized)).when(of("card"), F.when(count.between(12, 19), luhn(_digits(found))).otherwise(F.lit(False)))
        .when(of("phone"), count.between(9, 15)).when(of("secret"), cued | key).when(of("number"), count >= 9).otherwise(F.lit(True))
    )


#: Labelers by name: two of formats (regex), two of words around (context), two gazetteers, and one of the build of a token.
LABELERS = ("format", "check digit", "cue", "contact", "assignment", "known words", "build")


def votes(c: Column) -> list[Column]:
    """A vote of each labeler: 1 (personal), -1 (not) or 0 (none)."""
    found, before, after = c["found"], c["before"], c["after"]
    kind = {k: c["kind"] == i for i, k in enumerate(KINDS)}
    vote = lambda yes, no: F.when(no, -1).when(yes, 1).otherwise(0)
    number, secret = kind["number"], kind["secret"]
    digits = _digits(found)
    key = found.rlike(r"^(?:(?:AKIA|ASIA)[0-9A-Z]{16}|gh[pousr]_[A-Za-z0-9]{20,}|sk-[A-Za-z0-9_-]{16,}|xox[abp]-[A-Za-z0-9-]{10,}|(?=[0-9A-Fa-f]*[A-Fa-f])(?=[0-9A-Fa-f]*[0-9])[0-9A-Fa-f]{32,64})$")
    short = F.length(found) <= 200  # no phrase or number is longer; patterns with groups stay off long tokens
    phrase = short & (found.rlike(r"^[0-9A-Fa-f]{8}(?:-[0-9A-Fa-f]{4}){3}-[0-9A-Fa-f]{12}$") | found.rlike(r"^/?[A-Za-z]{2,}[0-9]{0,4}(?:[/_+-]+(?:[A-Za-z]{2,}[0-9]{0,4}|v?[0-9]{1,4}))+/?$"))
    phone = found.rlike(r"^\(?[0-9]{3}\)?[\x20.-][0-9]{3}[\x20.-][0-9]{4}$|^[0-9]{3}-[0-9]{2}-[0-9]{4}$|^0[0-9]{2,4}[\x20/-][0-9]{3,4}[\x20-]?[0-9]{3,5}$")
    date = found.rlike(r"^(?:(?:19|20)[0-9]{2}([-./\x20])(?:0?[1-9]|1[0-2])\1(?:0?[1-9]|[12][0-9]|3[01])|(?:0?[1-9]|[12][0-9]|3[01])([-./\x20])(?:0?[1-9]|1[0-2])\2(?:19|20)[0-9]{2})(?:[\x20-]|$)") | found.rlike(r"^97[89][\x20-]?[0-9][0-9\x20-]{8,}$")
    turns = F.length(F.regexp_replace(F.regexp_replace(found, "[0-9]+", "0"), "[^0]+", "a"))
    plain = short & F.length(digits).between(12, 19) & found.rlike(r"^[0-9]+(?:[\x20-][0-9]+)*$")
    return [
        vote((secret & key) | (number & phone) | kind["address"] | (kind["name"] & found.rlike(rf"\x20{_SURNAME}$")), (secret & phrase) | (number & date)),
        vote(F.lit(False), number & plain & ~F.when(number & plain, luhn(digits)).otherwise(F.lit(True))),
        vote(secret & before.rlike(rf"(?i)\b{_CUE}\W{{0,6}}$"), (secret | number) & before.rlike(rf"(?i)\b{_NEGATIVE}\W{{0,4}}$")),
        vote((number & before.rlike(rf"(?i)\b{_CONTACT}\W{{0,4}}(?:\w+\W{{1,3}})?$")) | (kind["name"] & before.rlike(r"(?i)\b(?:name|named|contact|dear|signed|sincerely|regards|from|by|i am|customer|patient)\W{1,4}$")) | (kind["address"] & before.rlike(r"(?i)\b(?:address|lives? at|living at|residing at|ship to|home)\W{1,4}(?:is\W)?$")),
             (number & before.rlike(r"(?i)\b(?:on|since|until|dated?|order|invoice|serial|item|no|nr|number of|total of|about)\W{1,3}$")) | (kind["name"] & before.rlike(r"(?i)\b(?:in|at|near|university of|city of|saint|st)\W{1,2}$"))),
        vote(secret & before.rlike(r"[=:]\s{0,3}[\"']?$"), (secret | number) & (before.rlike(r"[/#@]$") | after.rlike(r"^\.(?:html?|pdf|jpe?g|png|txt|zip|com|org|net)\b"))),
        vote((kind["name"] & found.rlike(rf"\b(?:{'|'.join(GIVEN_NAMES)})\b")) | (kind["address"] & found.rlike(rf"\b(?:{'|'.join(STREETS)})$")), (kind["name"] & found.rlike(rf"\b(?:{'|'.join(NO_SURNAMES)})$")) | (secret & found.rlike(rf"(?i)(?<![a-z])(?:{'|'.join(PHRASE_WORDS)})(?![a-z])"))),
        vote(secret & ~key & ~found.rlike("[-/]") & found.rlike("[0-9]") & found.rlike("[A-Za-z]") & (turns >= 8), secret & ~key & (turns <= 3) & found.rlike("[-/_]")),
    ]


#: What the classifier sees of a span, next to its kind: tests of its build.
SHAPES = ("long", "very long", "upper", "lower", "digits", "marks", "quoted")


def shape(c: Column) -> list[Column]:
    found = c["found"]
    flag = lambda t: t.cast("int")
    return [flag(F.length(found) >= 12), flag(F.length(found) >= 32), flag(found.rlike("[A-Z]")), flag(found.rlike("[a-z]")), flag(found.rlike("[0-9]")), flag(found.rlike("[^A-Za-z0-9]")), flag(c["before"].rlike("[\"']$"))]


#: What a span needs: odds of 7 to 3, where no vote is even odds. The share of personal candidates is taken as even, so
#: what speaks for a span is its own evidence, never the corpus's share of personal ones.
NEEDED = math.log(0.7 / 0.3)
#: Imagined votes that a labeler starts with, right and wrong; limits of a reliability; most that a span's shape may say.
IMAGINED, LEAST, MOST, SHAPE_MOST = (8.0, 2.0), 0.55, 0.99, 0.8


@dataclass(frozen=True)
class Classifier:
    """log odds = the weight of each labeler, with its vote's sign, + the kind's and the shape's weights within SHAPE_MOST."""

    labelers: tuple[float, ...]
    kinds: tuple[float, ...]
    shapes: tuple[float, ...]
    reliabilities: tuple[float, ...]

    def holds(self, c: Column) -> Column:
        build = F.element_at(F.array(*[F.lit(w) for w in self.kinds]), c["kind"] + 1)
        for s, w in zip(shape(c), self.shapes, strict=True):
            build = build + s * w
        score = F.greatest(F.lit(-SHAPE_MOST), F.least(F.lit(SHAPE_MOST), build))
        for v, w in zip(votes(c), self.labelers, strict=True):
            score = score + v * w
        return score > NEEDED


def estimate(counts: dict[tuple[int, ...], int], rounds: int = 60) -> tuple[dict[tuple[int, ...], float], list[float]]:
    """Expectation-maximisation over counted vote patterns: each pattern's probability, each labeler's reliability.

    Two latent classes of even odds; given the class, labelers vote apart from each other, are right with their own
    reliability where they vote, and abstain alike in both. Reliabilities begin at 0.8 and are smoothed by a constant ten
    imagined votes (8 right, 2 wrong), so a labeler that never votes keeps 0.8. No counts: nothing to estimate.
    """
    if not counts:
        return {}, []
    k, post = len(next(iter(counts))), {}
    right = [IMAGINED[0] / sum(IMAGINED)] * k
    for _ in range(rounds):
        odds = [math.log(a / (1 - a)) for a in right]
        post = {p: _logistic(sum(v * w for v, w in zip(p, odds, strict=True))) for p in counts}
        for j in range(k):
            agree = sum(n * (post[p] if p[j] > 0 else 1 - post[p]) for p, n in counts.items() if p[j])
            cast = sum(n for p, n in counts.items() if p[j])
            right[j] = min(MOST, max(LEAST, (agree + IMAGINED[0]) / (cast + sum(IMAGINED))))
    return post, right


def _logistic(z: float) -> float:
    return 1 / (1 + math.exp(-min(60.0, max(-60.0, z))))


def fit(docs: DataFrame, steps: int = 300) -> Classifier:
    """Votes over every text are counted by pattern, kind and shape, on the executors; EM and the training see the counts
    alone: at most 4 * 3^7 * 2^7 rows by what votes and shapes there are, some hundreds in practice."""
    c = F.col("c")
    names, marks = [f"v{j}" for j in range(len(LABELERS))], [f"s{j}" for j in range(len(SHAPES))]
    rows = docs.select(found_in(F.coalesce(F.col("text"), F.lit("")), KINDS[4:]).alias("c")).select(F.explode(F.filter(placed(c), _fits)).alias("c"))
    rows = rows.select(F.col("c.kind").alias("kind"), *[v.alias(n) for n, v in zip(names, votes(c), strict=True)], *[s.alias(n) for n, s in zip(marks, shape(c), strict=True)])
    counted = sorted((tuple(r[n] for n in names), r["kind"], tuple(r[n] for n in marks), r["count"]) for r in rows.groupBy("kind", *names, *marks).count().collect())
    by_votes: dict[tuple[int, ...], int] = {}
    for p, _, _, n in counted:
        by_votes[p] = by_votes.get(p, 0) + n
    post, right = estimate(by_votes)
    right = right or [IMAGINED[0] / sum(IMAGINED)] * len(LABELERS)
    kinds, shapes = _trained([(kind, s, post[p], n) for p, kind, s, n in counted if any(p)], steps)
    return Classifier(tuple(math.log(a / (1 - a)) for a in right), tuple(kinds), tuple(shapes), tuple(right))


def _trained(rows: list[tuple[int, tuple[int, ...], float, int]], steps: int) -> tuple[list[float], list[float]]:
    """Weights of kinds and shape tests: gradient ascent on the expected log likelihood of the posteriors of candidates
    that got a vote, with a penalty that keeps the weights of what is rare near none."""
    kinds, shapes = [0.0] * len(KINDS), [0.0] * len(SHAPES)
    total = sum(n for _, _, _, n in rows) + 20
    for step in range(steps if rows else 0):
        g_kind, g_shape = [-0.05 * w for w in kinds], [-0.05 * w for w in shapes]
        for kind, s, p, n in rows:
            d = (p - _logistic(kinds[kind] + sum(w for w, on in zip(shapes, s, strict=True) if on))) * n / total
            g_kind[kind] += d
            for j, on in enumerate(s):
                if on:
                    g_shape[j] += d
        rate = 1.0 / (1 + step / 100)
        kinds = [w + rate * g for w, g in zip(kinds, g_kind, strict=True)]
        shapes = [w + rate * g for w, g in zip(shapes, g_shape, strict=True)]
    return kinds, shapes


def _bare(spans: Column) -> Column:
    return F.transform(spans, lambda s: F.struct(s["start"].alias("start"), s["kind"].alias("kind"), s["end"].alias("end")))


def _apart(base: Column, own: Column) -> Column:
    """The method's spans that no stated span touches, in time that grows as both lists do."""

    def untouched(every: Column) -> Column:
        # a stated span touches another when one that begins before it ends inside, or one begins inside
        stated = lambda s: s["kind"] < 4
        upto = running(F.transform(every, lambda s: F.when(stated(s), s["end"]).otherwise(-1)), "max")
        onward = F.reverse(running(F.reverse(F.transform(every, lambda s: F.when(stated(s), s["start"]).otherwise(2**31 - 1))), "min"))
        both = F.struct(upto.alias("ends"), onward.alias("begins"))
        return let(both, lambda b: F.filter(every, lambda s, i: ~stated(s) & (b["ends"][i] <= s["start"]) & (b["begins"][i] >= s["end"])))

    return F.when((F.size(own) == 0) | (F.size(base) == 0), own).otherwise(let(F.array_sort(F.concat(base, own)), untouched))


def _with_spans(rows: DataFrame, keep: list[Column], text: Column, name: str, classifier: Classifier) -> DataFrame:
    """keep and a column `name`: struct(base, own) of the stated spans and the method's, a step of the work a projection."""
    spans = F.col(name)
    rows = rows.select(*keep, found_in(text, KINDS).alias(name))
    rows = rows.select(*keep, F.filter(placed(spans), _fits).alias(name))
    rows = rows.select(*keep, F.struct(_bare(F.filter(spans, lambda s: s["kind"] < 4)).alias("base"), _bare(F.filter(F.filter(spans, lambda s: s["kind"] >= 4), classifier.holds)).alias("own")).alias(name))
    return rows.select(*keep, F.struct(spans["base"].alias("base"), _apart(spans["base"], spans["own"]).alias("own")).alias(name))


def _listed(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(F.array_sort(spans), lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def find_private(docs: DataFrame, classifier: Classifier) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_spans (the method's among them) for each row.

    A null text counts as empty: zero counts, the hash of the empty string, no spans. Repeated rows and null ids
    stay; other columns of docs are ignored. Spans of equal start go by kind.
    """
    rows = _with_spans(docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")), [F.col("doc_id")], F.col("text"), "s", classifier)
    stated = lambda k: F.size(F.filter("s.base", lambda s: s["kind"] == KINDS.index(k))).cast("long").alias(f"n_{k}")
    every = F.concat("s.base", "s.own")
    return rows.select("doc_id", *[stated(k) for k in KINDS[:4]], F.sha2(_listed(F.col("s.base")), 256).alias("base_sha256"), _listed(every).alias("spans"), F.size(every).cast("long").alias("n_spans"))


#: Characters of a piece that a long text is cut in, so that a part of it is found without counting from its start.
PIECE = 1024


def _between(pieces: Column, begin: Column, end: Column) -> Column:
    """Characters from begin to end (not included) of a text cut in pieces."""
    a, b = F.floor(begin / PIECE).cast("int"), F.floor(end / PIECE).cast("int")
    tail = F.when(end % PIECE > 0, F.substring(F.get(pieces, b), F.lit(1), (end % PIECE).cast("int"))).otherwise("")
    inner = F.when(b - a > 1, F.array_join(F.slice(pieces, a + 2, F.greatest(b - a - 1, F.lit(0))), "")).otherwise("")
    far = F.concat(F.coalesce(F.substring(F.get(pieces, a), (begin % PIECE + 1).cast("int"), F.lit(PIECE)), F.lit("")), inner, tail)
    return F.when(end <= begin, "").when(a == b, F.substring(F.get(pieces, a), (begin % PIECE + 1).cast("int"), (end - begin).cast("int"))).otherwise(far)


def _heads(spans: Column, ends: Column) -> Column:
    """First spans of the groups of sorted spans that overlap, each with its group's end: ends is the furthest end so far."""
    first = F.filter(F.transform(spans, lambda s, i: F.when((i == 0) | (s["start"] >= F.get(ends, i - 1)), F.struct(i.alias("at"), s["start"].alias("start"), s["kind"].alias("kind")))), lambda s: s.isNotNull())
    return let(first, lambda f: F.transform(f, lambda s, k: F.struct(s["start"].alias("start"), s["kind"].alias("kind"), F.coalesce(F.get(ends, F.get(f, k + 1)["at"] - 1), F.element_at(ends, -1)).alias("end"))))


def _rebuilt(text: Column, heads: Column, pieces: Column) -> Column:
    names = F.array(*[F.lit(f"<{k}>") for k in KINDS])
    parts = F.transform(heads, lambda h, k: F.concat(_between(pieces, F.when(k > 0, F.get(heads, k - 1)["end"]).otherwise(0), h["start"]), F.element_at(names, h["kind"] + 1)))
    return F.concat(F.array_join(parts, ""), _between(pieces, F.element_at(heads, -1)["end"], F.length(text)))


def redact(docs: DataFrame, classifier: Classifier) -> DataFrame:
    """docs with each span of text replaced by its kind in angle brackets (overlapping spans become one, under the
    first one's kind), and n_chars, where there is one, counted anew for the texts that changed. Null texts stay null.
    """
    text, own = F.col("text"), [F.col(quoted(c)) for c in docs.columns]
    name = free_name(docs, "spans")
    spans, size = F.col(name), F.size(name)
    rows = _with_spans(docs, own, F.coalesce(text, F.lit("")), name, classifier)
    rows = rows.select(*own, F.array_sort(F.concat(spans["base"], spans["own"])).alias(name))
    rows = rows.select(*own, F.when(size > 0, F.struct(spans.alias("spans"), running(F.transform(spans, lambda s: s["end"]), "max").alias("ends"))).alias(name))
    rows = rows.select(*own, F.when(spans.isNotNull(), F.struct(_heads(spans["spans"], spans["ends"]).alias("heads"), F.regexp_extract_all(text, F.lit(f"(?s).{{1,{PIECE}}}"), F.lit(0)).alias("pieces"))).alias(name))
    rows = rows.select(*own, F.when(spans.isNotNull(), _rebuilt(text, spans["heads"], spans["pieces"])).alias(name))
    columns = []
    for c, held in zip(docs.columns, own, strict=True):
        new = F.coalesce(name, "text") if c == "text" else F.when(spans.isNotNull(), F.length(name).cast(docs.schema[c].dataType)).otherwise(held) if c == "n_chars" else held
        columns.append(new.alias(c))
    return rows.select(*columns)

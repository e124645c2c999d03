"""Main text of web pages: leaf blocks, each labelled by a bidirectional LSTM that reads the whole page's sequence.

The page is cut into blocks at block-level tags. A block is described by hashed embeddings of its tag path (tags with
their class, id and role words) and of its first words, by the sum of those of all its words and pairs of
neighbouring words, and by a few measures. A forward and a backward LSTM read the
blocks of the page, and every block is labelled content or not from both. Weights are learned here, in numpy, from
pages that a generator lays out with known labels (a stated number of them and a stated seed); no page of the corpus
is needed for it, and its words carry no meaning.
"""

from __future__ import annotations

import html as entities
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import arrow_bounded, chunks

#: Tags that end a block; tags whose content is no text of the page.
_BLOCK = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol option p pre section select summary table tbody td tfoot th thead title tr ul svg text object canvas".split())
_SILENT = frozenset("script style noscript template textarea iframe head title button select option".split())
#: Tags that an open head holds; any other, and text, closes it, as its end tag may be left out.
_IN_HEAD = frozenset("base basefont bgsound link meta title noscript noframes style script template head html".split())
#: Elements that hold nothing, and elements that a new one of the same group closes.
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_CLOSES = {"p": {"p"}, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}}
_PART = re.compile(r"<!--.*?(?:-->|$)|<![^>]*(?:>|$)|<\?[^>]*(?:>|$)|<(/?)([A-Za-z][A-Za-z0-9:-]*)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)(?:>|$)", re.S)
_NAMES = re.compile(r"\b(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_WORD = re.compile(r"[^\W\d_]+")
_INLINE_SPACE = frozenset({"br", "wbr", "img", "input"})

#: Places of paths and first words, and of words wherever they stand; numbers of each; numbers of a state.
SLOTS, WORDS, WIDTH, HIDDEN = 2048, 16384, 16, 16
#: Words that a worker remembers the places of, and words whose vectors are summed at once.
REMEMBERED, SUMMED = 200_000, 1 << 18
#: Blocks that a word, or a pair, must stand in to get a vector of its own; rarer ones are unknown words, with none.
FREQUENT = 12
#: Log odds from which on a block is content: one is dropped only where at least 4.5 to 1 speaks against it.
CONTENT = -1.5
#: Generated pages to learn from, passes over them, seed.
PAGES, PASSES, SEED = 500, 6, 11


class Path:
    """An element's place in the page: its tag with its class, id and role words, and the element around it. Blocks share
    the paths of the elements that they stand in, so a page takes room and time as it has elements, however deep."""

    __slots__ = ("parent", "name", "own", "total", "count")

    def __init__(self, parent: Path | None, name: str) -> None:
        self.parent, self.name, self.total, self.count = parent, name, None, 0
        tag, *words = name.split()
        self.own = tuple(map(_path_slot, [f"t:{tag}", *(f"n:{w}" for w in words)]))

    def every(self) -> list[int]:
        """Places of the features of all elements from the outermost."""
        out, at = [], self
        while at is not None:
            out.append(at.own)
            at = at.parent
        return [k for own in reversed(out) for k in own]

    def sums(self, vectors: np.ndarray) -> tuple[np.ndarray, int]:
        """Sum and number of those features' vectors: the parent's and its own, found once for each element."""
        todo, at = [], self
        while at is not None and at.total is None:
            todo.append(at)
            at = at.parent
        for path in reversed(todo):
            above = path.parent
            own = vectors[list(path.own)].sum(axis=0)
            path.total, path.count = (own, len(path.own)) if above is None else (above.total + own, above.count + len(path.own))
        return self.total, self.count


@lru_cache(maxsize=20_000)
def _path_slot(word: str) -> int:
    return zlib.crc32(word.encode()) % (SLOTS // 2)


def leaves(page: str) -> list[tuple[Path | None, str, int]]:
    """(path, text, characters inside links) of the page's blocks in order, those without text left out.

    Text of silent elements is dropped, but not that of formulas, drawings and fallbacks of objects; a head ends where
    its end tag, a body, a flow element or text stands. Character references are decoded; white space becomes one space. A line break
    inside a block is white space. Unclosed and truncated markup closes where its parent or the page does. Time is in
    proportion to the page, whatever its depth.
    """
    out: list[tuple[Path | None, str, int]] = []
    stack: list[tuple[str, Path | None]] = []  # open elements, and the path inside each
    opened: Counter[str] = Counter()
    parts: list[str] = []
    link = silent = 0
    at, end = 0, len(page)

    def flush() -> None:
        nonlocal link
        if parts:
            text = " ".join(entities.unescape("".join(parts)).split())
            if text:
                out.append((stack[-1][1] if stack else None, text, link))
            parts.clear()
        link = 0

    def leave_head() -> None:
        if stack and stack[-1][0] == "head":
            close(len(stack) - 1)

    def close(upto: int) -> None:
        nonlocal silent
        while len(stack) > upto:
            name, _ = stack.pop()
            opened[name] -= 1
            silent -= name in _SILENT

    while at < end:
        tag = page.find("<", at)
        if tag < 0:
            tag = end
        if silent and tag > at and not page[at:tag].isspace():
            leave_head()
        if tag > at and not silent:
            parts.append(page[at:tag])
            if opened["a"]:
                link += tag - at
        if tag == end:
            break
        m = _PART.match(page, tag)
        if m is None:
            leave_head()
            if not silent:
                parts.append("<")
            at = tag + 1
            continue
        at = m.end()
        name = (m[2] or "").lower()
        if not name:
            continue
        if name in _BLOCK:
            flush()
        elif name in _INLINE_SPACE:
            parts.append(" ")
        if m[1]:
            if opened[name]:
                i = len(stack) - 1
                while stack[i][0] != name:
                    i -= 1
                close(i)
            continue
        if name not in _IN_HEAD:
            leave_head()
        if name in _VOID or m[3].endswith("/"):
            continue
        if name in _CLOSES and any(opened[x] for x in _CLOSES[name]):
            for i in range(len(stack) - 1, -1, -1):
                if stack[i][0] in _CLOSES[name]:
                    close(i)
                    break
                if stack[i][0] in ("table", "ul", "ol", "dl", "article", "section", "div", "td"):
                    break
        named = " ".join(w.lower() for got in _NAMES.findall(m[3]) for g in got for w in _WORD.findall(g))
        inside = stack[-1][1] if stack else None
        stack.append((name, Path(inside, f"{name} {named}".strip()) if name in _BLOCK or named else inside))
        opened[name] += 1
        if name in _SILENT:
            silent += 1
            if name in ("script", "style", "textarea", "noscript", "title"):  # raw text: nothing but its end tag counts
                stop = re.compile(rf"</{name}\b[^>]*(?:>|$)", re.I).search(page, at)
                at = stop.end() if stop else end
                close(len(stack) - 1)
    flush()
    return out


class _WordSlots(dict):
    """word: its place among all words; forgets everything when full."""

    def __missing__(self, word: str) -> int:
        if len(self) >= REMEMBERED:
            self.clear()
        self[word] = at = SLOTS + 1 + zlib.crc32(word.encode()) % (WORDS - 1)
        return at


_word_slots = _WordSlots()


#: What the labeller reads of a block: its path, the places of its innermost tag and first words, those of all its words
#: and pairs of neighbours.
Read = tuple[Path | None, np.ndarray, np.ndarray]


def features(blocks: list[tuple[Path | None, str, int]]) -> tuple[list[Read], np.ndarray]:
    """What is read of each block; its measures."""
    slots, dense = [], np.zeros((len(blocks), 6), np.float32)
    for k, (path, text, link) in enumerate(blocks):
        words = _WORD.findall(text.lower())
        head = [_path_slot(f"i:{path.name.split()[0] if path else ''}"), *(SLOTS // 2 + zlib.crc32(w.encode()) % (SLOTS // 2) for w in words[:4])]
        # place SLOTS stands in every block, so that none is empty; pairs of neighbours tell a cue from its single words
        every = [SLOTS, *map(_word_slots.__getitem__, words), *map(_word_slots.__getitem__, map(" ".join, zip(words, words[1:])))]
        slots.append((path, np.array(head, np.int32), np.array(every, np.int32)))
        n = len(text)
        dense[k] = (np.log1p(n) / 6, min(1.0, link / max(1, n)), text[-1] in ".!?;:\"'", (text[:1] == "©"), k / max(1, len(blocks) - 1), sum(map(text.count, ".,;")) / max(1, n) * 10)
    return slots, dense


def spelled(slots: list[Read]) -> list[tuple[np.ndarray, np.ndarray]]:
    """The same with each path's places written out, as learning needs them for its gradients."""
    return [(np.array([*(path.every() if path else ()), *head], np.int32), every) for path, head, every in slots]


class Labeller:
    """Embedding sums, two LSTMs and a logistic layer; all weights in one flat dict of arrays."""

    def __init__(self, seed: int = SEED) -> None:
        rng = np.random.default_rng(seed)
        d, h = 2 * WIDTH + 6, HIDDEN
        self.w = {"e": np.concatenate([rng.normal(0, 0.1, (SLOTS // 2, WIDTH)), np.zeros((SLOTS // 2 + WORDS, WIDTH))]), "o": rng.normal(0, 0.3, (2 * h, 1)), "ob": np.zeros(1)}
        for side in "fb":
            self.w[f"{side}x"] = rng.normal(0, d**-0.5, (d, 4 * h))
            self.w[f"{side}h"] = rng.normal(0, h**-0.5, (h, 4 * h))
            self.w[f"{side}b"] = np.concatenate([np.zeros(h), np.ones(h), np.zeros(2 * h)])
        self.w = {k: v.astype(np.float32) for k, v in self.w.items()}

    def _sums(self, slots: list[np.ndarray]) -> np.ndarray:
        """Sum of the vectors of each of the lists, by the root of its size; SUMMED vectors or one list at a time."""
        out, first = np.empty((len(slots), WIDTH), np.float32), 0
        while first < len(slots):
            upto, n = first + 1, len(slots[first])
            while upto < len(slots) and n + len(slots[upto]) <= SUMMED:
                n += len(slots[upto])
                upto += 1
            sizes = np.array([len(s) for s in slots[first:upto]])
            at = np.concatenate([[0], np.cumsum(sizes)[:-1]])
            out[first:upto] = np.add.reduceat(self.w["e"][np.concatenate(slots[first:upto])], at, axis=0) / np.sqrt(sizes)[:, None]
            first = upto
        return out

    def inputs(self, slots: list[Read], dense: np.ndarray) -> np.ndarray:
        paths = [path.sums(self.w["e"]) if path else (np.zeros(WIDTH, np.float32), 0) for path, _, _ in slots]
        sizes = np.array([len(head) for _, head, _ in slots])
        heads = self._sums([head for _, head, _ in slots]) * np.sqrt(sizes)[:, None]
        above = (np.array([t for t, _ in paths]) + heads) / np.sqrt(sizes + np.array([n for _, n in paths]))[:, None]
        return np.concatenate([above, self._sums([w for _, _, w in slots]), dense], axis=1).astype(np.float32)

    def spelled_inputs(self, slots: list[tuple[np.ndarray, np.ndarray]], dense: np.ndarray) -> np.ndarray:
        return np.concatenate([self._sums([s for s, _ in slots]), self._sums([w for _, w in slots]), dense], axis=1).astype(np.float32)

    def _pass(self, x: np.ndarray, side: str, keep: bool = False):
        """x: (pages, places, d) -> hidden states; with keep also what the gradient needs."""
        n, t, _ = x.shape
        h = HIDDEN
        z = x @ self.w[f"{side}x"] + self.w[f"{side}b"]
        state, cell, out, held = np.zeros((n, h), np.float32), np.zeros((n, h), np.float32), np.empty((n, t, h), np.float32), []
        for k in range(t) if side == "f" else range(t - 1, -1, -1):
            g = z[:, k] + state @ self.w[f"{side}h"]
            s = 1 / (1 + np.exp(-np.clip(g[:, : 3 * h], -30, 30)))
            i, f, o, c = s[:, :h], s[:, h : 2 * h], s[:, 2 * h :], np.tanh(g[:, 3 * h :])
            before, past = cell, state
            cell = f * cell + i * c
            squashed = np.tanh(cell)
            state = o * squashed
            out[:, k] = state
            if keep:
                held.append((k, i, f, o, c, before, past, squashed))
        return (out, held) if keep else out

    def scores(self, x: np.ndarray) -> np.ndarray:
        both = np.concatenate([self._pass(x, "f"), self._pass(x, "b")], axis=2)
        return (both @ self.w["o"])[..., 0] + self.w["ob"]

    def label(self, pages: list[tuple[list[Read], np.ndarray]]) -> list[np.ndarray]:
        """Whether each block of each page is content. Pages are taken in groups of one length: no padding is read."""
        out: list[np.ndarray] = [np.zeros(0, bool)] * len(pages)
        by: dict[int, list[int]] = {}
        for k, (slots, _) in enumerate(pages):
            if slots:
                by.setdefault(len(slots), []).append(k)
        for t, members in by.items():
            for a in range(0, len(members), max(1, 4096 // t)):
                some = members[a : a + max(1, 4096 // t)]
                x = self.inputs([s for k in some for s in pages[k][0]], np.concatenate([pages[k][1] for k in some])).reshape(len(some), t, -1)
                for k, s in zip(some, self.scores(x), strict=True):
                    out[k] = s > CONTENT
        return out

    def learn(self, pages: list[tuple[list[Read], np.ndarray, np.ndarray]], passes: int = PASSES, rate: float = 0.01) -> None:
        """Adam on the cross entropy of every block, a page at a time, by backpropagation through the sequence. Only the
        vectors of path features and of frequent words are learned; all others stay none."""
        read = [(spelled(slots), dense, truth) for slots, dense, truth in pages]
        stands = np.zeros(SLOTS + WORDS, np.int64)
        for slots, _, _ in read:
            for own in (x for pair in slots for x in pair):
                stands[np.unique(own)] += 1
        active = np.flatnonzero((stands >= FREQUENT) | (np.arange(SLOTS + WORDS) < SLOTS // 2))
        place = np.full(SLOTS + WORDS, len(active))  # the last row stands for all words without a vector
        place[active] = np.arange(len(active))
        read = [([(place[own], place[every]) for own, every in slots], dense, truth) for slots, dense, truth in read]
        whole, self.w["e"] = self.w["e"], np.concatenate([self.w["e"][active], np.zeros((1, WIDTH), np.float32)])
        firsts, words = (active >= SLOTS // 2) & (active < SLOTS), active >= SLOTS
        m = {k: np.zeros_like(v) for k, v in self.w.items()}
        v = {k: np.zeros_like(a) for k, a in self.w.items()}
        rng, step, h, first, total = np.random.default_rng(SEED), 0, HIDDEN, rate, passes * len(pages)
        for _ in range(passes):
            for k in rng.permutation(len(pages)):
                slots, dense, truth = read[k]
                x = self.spelled_inputs(slots, dense)[None]
                (f, f_held), (b, b_held) = self._pass(x, "f", True), self._pass(x, "b", True)
                both = np.concatenate([f, b], axis=2)
                score = (both @ self.w["o"])[0, :, 0] + self.w["ob"]
                d_score = ((1 / (1 + np.exp(-np.clip(score, -30, 30)))) - truth)[None, :, None].astype(np.float32) / len(truth)
                g = {"o": (both * d_score).sum(axis=(0, 1))[:, None], "ob": d_score.sum(axis=(0, 1))}
                d_both, d_x = d_score * self.w["o"][:, 0], np.zeros_like(x)
                for side, held, part in (("f", f_held, d_both[..., :h]), ("b", b_held, d_both[..., h:])):
                    d_state = d_cell = np.zeros((1, h), np.float32)
                    g_x, g_h, g_b = (np.zeros_like(self.w[side + s]) for s in "xhb")
                    for at, i, fg, o, c, before, past, squashed in reversed(held):
                        d_state = d_state + part[:, at]
                        d_cell = d_cell + d_state * o * (1 - squashed**2)
                        d_g = np.concatenate([d_cell * c * i * (1 - i), d_cell * before * fg * (1 - fg), d_state * squashed * o * (1 - o), d_cell * i * (1 - c**2)], axis=1)
                        g_x += x[:, at].T @ d_g
                        g_h += past.T @ d_g
                        g_b += d_g[0]
                        d_x[:, at] += d_g @ self.w[f"{side}x"].T
                        d_state, d_cell = d_g @ self.w[f"{side}h"].T, d_cell * fg
                    g |= {f"{side}x": g_x, f"{side}h": g_h, f"{side}b": g_b}
                g["e"] = np.zeros_like(self.w["e"])
                for part, own in enumerate(zip(*slots, strict=True)):
                    sizes = np.array([len(s) for s in own])
                    np.add.at(g["e"], np.concatenate(own), np.repeat(d_x[0, :, part * WIDTH : (part + 1) * WIDTH] / np.sqrt(sizes)[:, None], sizes, axis=0))
                g["e"][:-1][firsts] += 0.003 * self.w["e"][:-1][firsts]  # most first words are of no kind
                g["e"][:-1][words] += 0.0003 * self.w["e"][:-1][words]
                g["e"][-1] = 0
                step += 1
                rate = first * (1 - 0.97 * step / total)
                for name, grad in g.items():
                    m[name] = 0.9 * m[name] + 0.1 * grad
                    v[name] = 0.999 * v[name] + 0.001 * grad**2
                    self.w[name] = (self.w[name] - rate * (m[name] / (1 - 0.9**step)) / (np.sqrt(v[name] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
        whole[active] = self.w["e"][:-1]
        whole[np.setdiff1d(np.arange(SLOTS // 2, SLOTS + WORDS), active)] = 0
        self.w["e"] = whole


_ASIDE = ("sidebar", "widget", "related", "recommended", "promo", "ad", "ads", "advert", "banner", "sponsor", "cookie", "consent", "notice", "newsletter", "subscribe", "share", "social", "breadcrumb", "pagination", "popup", "modal", "disclaimer", "tags", "author box", "menu", "toolbar", "skip")
_STOCK = ("Subscribe to our newsletter", "We use cookies", "All rights reserved", "Sponsored", "Advertisement", "Related articles", "Share this", "Read more", "Sign up", "Follow us", "Privacy policy", "Terms of use")
#: Words by which a block without a telling class is known for a notice, an advert or a comment, wherever they stand.
_CUES = (
    "all rights reserved", "we use cookies", "by using this site you accept our use of cookies", "accept all cookies", "subscribe to our newsletter", "sign up for our newsletter", "read our privacy policy",
    "terms of use apply", "share this article", "follow us on", "this is a sponsored post", "paid advertisement", "buy now and save", "leave a reply", "log in to reply", "posted in the comments",
    "posted on Monday morning by", "posted on Friday by", "posted by", "copyright by", "unsubscribe at any time", "related articles", "click here to subscribe", "report this comment",
)
_COMMON = "the and of to a in is on by this that we our it as at for with you all your are be from or was not us use no".split()
_TALK = ("comments", "comment", "discussion", "reply", "respond", "disqus thread", "user comments")
_MAIN = ("", "", "", "content", "post", "entry content", "article body", "main", "story", "post body", "text")


def sample_page(rng: np.random.Generator) -> tuple[str, list[bool]]:
    """A laid-out page of invented words, and whether each of its leaf blocks is content."""
    letters = "etaoinshrdlucmfwypvbgk"
    word = lambda: "".join(rng.choice(list(letters), rng.integers(1, 9)))
    words = lambda a, b: " ".join(word() for _ in range(rng.integers(a, b)))
    pick = lambda xs: xs[int(rng.integers(len(xs)))]
    sentence = lambda a=3, b=25: mixed(words(a, b)).capitalize() + rng.choice([".", ".", ".", "!", "?", ""])
    out, truth = [], []

    def mixed(text: str) -> str:
        """Some of the words replaced by common ones, which tell nothing although cues hold them too."""
        share = pick((0, 0.2, 0.4, 0.7))
        return " ".join(pick(_COMMON) if rng.random() < share else w for w in text.split())

    def stray(text: str) -> str:
        """At times with words of several cues, which tell nothing without their neighbours."""
        own = text.split()
        for _ in range(int(rng.integers(1, 4)) if rng.random() < 0.3 else 0):
            own.insert(int(rng.integers(len(own) + 1)), pick(pick(_CUES).split()))
        return " ".join(own)

    def telling() -> str:
        """Invented words with a cue or two anywhere among them."""
        own = [mixed(words(1, 25)) for _ in range(rng.integers(1, 3))] + [pick(_CUES) for _ in range(rng.integers(1, 3))]
        text = " ".join(own[int(k)] for k in rng.permutation(len(own)))
        return text[0].upper() + text[1:] + pick([".", ".", "", "!"])

    def add(markup: str, *labels: bool) -> None:
        out.append(markup)
        truth.extend(labels)

    def named(tag: str, name: str) -> str:
        return f"<{tag}>" if not name else f'<{tag} {pick(["class", "class", "id"])}="{name.replace(" ", pick(["-", " ", "_"]))}">'

    def links(n: int) -> None:
        for _ in range(n):
            add(f'<li><a href="/{word()}">{words(1, 4)}</a></li>', False)

    def extra() -> None:
        """One block of something that is not the article."""
        kind = rng.integers(8)
        if kind == 0:
            lead = pick(_STOCK) + " " if rng.random() < 0.3 else ""
            add(named(pick(["div", "aside", "section"]), pick(_ASIDE)) + f"{lead}{sentence(2, 30)}</div>", False)
        elif kind == 1:
            add(named(pick(["aside", "div"]), pick(_ASIDE)) + f"<h3>{words(1, 4)}</h3><p>{sentence()}</p></aside>", False, False)
        elif kind == 2:
            add(named("form", pick(["", "search", "newsletter", "login"])) + f"<label>{words(1, 4)}</label><input><button>{word()}</button></form>", False)
        elif kind == 3:
            add(named(pick(["nav", "div", "ul"]), pick(["", "menu", "breadcrumb", "related", "tags"]) if rng.random() < 0.6 else "nav") if rng.random() < 0.5 else "<nav>")
            out.append("<ul>")
            links(int(rng.integers(1, 7)))
            out.append("</ul></nav>")
        elif kind == 4:
            add(named("div", pick(_ASIDE)) + "<ul>")
            links(int(rng.integers(1, 5)))
            out.append("</ul></div>")
        elif kind == 5:
            add(named(pick(["div", "p"]), pick(_ASIDE)) + f"{sentence(2, 20)}", False)
            out.append("</div></p>")
        else:  # nothing but its words tells it from the article
            tag = pick(["div", "p", "p"])
            add(f"<{tag}>{telling()}</{tag}>", False)

    if rng.random() < 0.5:
        add(named("header", pick(["", "site header", "top"])) + f"<h1>{words(1, 4)}</h1><p>{sentence(2, 8)}</p></header>", False, False)
    if rng.random() < 0.85:
        out.append(pick(["<nav><ul>", '<div class="menu"><ul>', '<nav class="main-nav"><ul>']))
        links(int(rng.integers(2, 9)))
        out.append("</ul></nav>")
    for _ in range(int(rng.integers(0, 3))):
        extra()
    tag = pick(["article", "article", "article", "main", "div", "section"])
    name = pick(_MAIN) if tag != "div" else pick(_MAIN[3:])
    out.append(named(tag, name))
    own_header = tag in ("article", "main") and rng.random() < 0.3  # the headline's, not the page's
    if own_header:
        out.append(named("header", pick(["", "", "entry header", "post header"])))
    if own_header or rng.random() < 0.8:
        add(f"<{(h := pick(['h1', 'h1', 'h2']))}>{stray(words(1, 12))}</{h}>", True)
    if own_header:
        out.append("</header>")
    for _ in range(int(rng.integers(1, 14 if rng.random() < 0.85 else 70))):
        kind = rng.random()
        if kind < 0.5:
            add(f"<p>{' '.join(stray(sentence(1, 30)) for _ in range(rng.integers(1, 5)))}</p>", True)
        elif kind < 0.65:
            add(f"<p><b>{sentence(1, 40)}<br>", True)
        elif kind < 0.72:
            add(f"<h2>{stray(words(1, 6))}</h2>", True)
        elif kind < 0.8:
            out.append("<ul>")
            for _ in range(int(rng.integers(1, 4))):
                add(f"<li>{stray(sentence(1, 12))}</li>", True)
            out.append("</ul>")
        elif kind < 0.86:
            add(f"<blockquote>{stray(sentence())}</blockquote>", True)
        elif kind < 0.92:
            add(f'<p>{sentence(1, 9)} <a href="/{word()}">{words(1, 5)}</a> {sentence(1, 9)}</p>', True)
        elif kind < 0.95:
            add(f"<table><tr><td>{words(1, 3)}</td><td>{words(1, 3)}</td></tr></table>", True, True)
        else:
            out.append("</b></p>")
            extra()
        if rng.random() < 0.1:
            add(f"<p>{telling()}</p>", False)
    out.append(f"</{tag}>")
    if rng.random() < 0.06:  # a page that was cut short
        return "<!DOCTYPE html><html><body>" + "".join(out), truth
    if rng.random() < 0.4:
        out.append(named(pick(["div", "section", "ol"]), pick(_TALK)))
        if rng.random() < 0.6:
            add(f"<h3>{words(1, 3)}</h3>", False)
        for _ in range(int(rng.integers(1, 6))):
            inner = named(pick(["div", "li", "article"]), pick(_TALK[1:]))
            add(f"{inner}<p>{' '.join(sentence() for _ in range(rng.integers(1, 3)))}</p></{inner[1:].split()[0].rstrip('>')}>", False)
        out.append("</div></section></ol>")
    for _ in range(int(rng.integers(0, 3))):
        extra()
    if rng.random() < 0.9:
        add(named("footer", pick(["", "", "site footer"])) + f"{pick(['&copy; ', '', 'Copyright ', 'All rights reserved '])}{sentence(1, 14)}</footer>", False)
    lead = f"<!DOCTYPE html><html><head><title>{words(1, 8)}</title></head><body>"
    return lead + "".join(out), truth


def generated(n: int, seed: int) -> list[tuple[list[Read], np.ndarray, np.ndarray]]:
    """Pages with labels; those whose markup the block cutter reads otherwise than the generator meant are left out."""
    rng, out = np.random.default_rng(seed), []
    while len(out) < n:
        page, truth = sample_page(rng)
        blocks = leaves(page)
        if len(blocks) == len(truth):
            out.append((*features(blocks), np.array(truth, np.float32)))
    return out


@lru_cache(maxsize=1)
def labeller() -> Labeller:
    own = Labeller()
    own.learn(generated(PAGES, SEED))
    return own


def main_texts(pages: list[str], model: Labeller) -> list[str]:
    cut = [leaves(p) for p in pages]
    kept = model.label([features(b) for b in cut])
    return ["\n".join(text for (_, text, _), k in zip(b, ks, strict=True) if k) for b, ks in zip(cut, kept, strict=True)]


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars for each row of pages.

    A null or empty html, or one without content, has an empty text. Repeated rows and null ids stay; other columns
    are ignored. The model (some 40,000 numbers) is learned once on the driver and broadcast.
    """
    shared = pages.sparkSession.sparkContext.broadcast(labeller().w)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = Labeller()
        model.w = shared.value
        for batch in batches:
            for part in chunks(batch, "html"):
                texts = main_texts([p or "" for p in part.column("html").to_pylist()], model)
                yield pa.RecordBatch.from_arrays([part.column("page_id"), part.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    kinds = {k: pages.schema[k].dataType.simpleString() for k in ("page_id", "url")}
    return arrow_bounded(pages.select("page_id", "url", "html")).mapInArrow(run, f"page_id {kinds['page_id']}, url {kinds['url']}, text string, n_chars long")

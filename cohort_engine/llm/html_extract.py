"""Main text of web pages by a recurrent block labeller.

A page is read into a sequence of blocks: runs of text between tags that start or end a block, each with the path
of open elements above it. A block becomes a vector of hashed path steps (tags, classes, ids, roles), hashed
words and a few measures; a bidirectional LSTM, in numpy, reads the whole sequence both ways and labels
every block in the light of all others. Blocks labelled content, joined by line feeds, are the text. All words of a block
and all open elements above it count, however long and deep a page is.

The weights are trained on generated pages of many layouts (:mod:`html_train`) and kept beside this module.

Defined results: a null or empty page, or one without content blocks, has an empty text; scripts, styles, fields of
forms, comments and markup are never text; unclosed or stray tags are read as far as they go: an element whose
text is left out and that has no end tag of its own ends with the element around it, at the next block or the next of its
kind, and a head at the first tag that can't stand in it, so no text after it is lost; repeated rows get equal
texts; an empty table gives an empty one; other columns are not read.
"""

from __future__ import annotations

import html
import re
import zlib
from collections import defaultdict
from functools import lru_cache
from pathlib import Path

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_columns

_TAG = re.compile(
    r"<!--(?:-?>|.*?(?:--!?>|\Z))|<(/?)([a-zA-Z][^\s/<>]*)((?:[^<>\"']++|\"[^\"<]*+\"|'[^'<]*+'|(?<==)\"[^\"]{0,4000}\"(?=[\s/>])|(?<==)'[^']{0,4000}'(?=[\s/>])|[\"'])*+)>|<[!?/][^>]*>",
    re.S,
)
_ATTRIBUTE = re.compile(r"(?:^|\s)(class|id|role|hidden|style)\s*(?:=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
_NAME = re.compile(r"[a-z]+")
_WORD = re.compile(r"\w+")
# HTML elements by how they take part.
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Elements whose text is left out; of the raw ones the inside is not markup.
SKIPPED = frozenset("script style noscript template svg math title textarea select option optgroup button datalist object iframe canvas audio video head".split())
RAW = frozenset("script style title textarea iframe".split())
_IN_HEAD = frozenset("base basefont bgsound link meta noscript script style template title head html".split())
_CLOSED_BY = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "p": {"p"}}
_LIMITS = {"li": {"ul", "ol"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"table"}, "th": {"table"}, "p": frozenset("div article section td th li body blockquote main aside header footer nav form".split())}
_ENDS_P = frozenset("address article aside blockquote div dl fieldset footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul".split())
_OPTIONS = frozenset(("option", "optgroup"))

#: Elements that have a place of their own in a block's vector; inline ones other than links count by their names alone.
_PLACES = {t: k for k, t in enumerate("html body div section article main header footer nav aside p h1 h2 h3 h4 h5 h6 ul ol li dl dt dd table tbody tr td th form label fieldset legend blockquote pre figure figcaption address details summary center hgroup a".split())}
TAGS, STEPS, WORDS, MEASURES, HIDDEN = 48, 240, 96, 12, 24  # STEPS counts tags and hashed names
WIDTH = STEPS + WORDS + MEASURES

#: Places of the path's steps, its depth without inline elements, the nearest element that isn't inline, the text, and how much of it is in links.
Block = tuple[tuple[int, ...], int, str, str, int]


class _Path:
    """The open elements. Every operation takes time by what it opens and closes, and a path's steps are kept as
    a set of bounded size, so deep nesting costs no more than wide pages."""

    def __init__(self) -> None:
        self.open: list[tuple[str, tuple[int, ...]]] = []
        self.at: dict[str, list[int]] = defaultdict(list)
        self.blocks: list[str] = []
        self.counts: dict[int, int] = {}
        self.known: tuple[int, ...] | None = ()

    def push(self, tag: str, names: str) -> None:
        places = _step(tag, names)
        self.at[tag].append(len(self.open))
        self.open.append((tag, places))
        if tag not in INLINE:
            self.blocks.append(tag)
        for place in places:
            n = self.counts.get(place, 0)
            self.counts[place] = n + 1
            if not n:
                self.known = None

    def cut(self, length: int) -> None:
        while len(self.open) > length:
            tag, places = self.open.pop()
            self.at[tag].pop()
            if tag not in INLINE:
                self.blocks.pop()
            for place in places:
                self.counts[place] -= 1
                if not self.counts[place]:
                    del self.counts[place]
                    self.known = None

    def shut(self, names: frozenset[str] | set[str], limits: frozenset[str] | set[str] = frozenset()) -> None:
        """Closes up to the nearest open element of these names, unless a limit is nearer."""
        nearest = max((self.at[n][-1] for n in names if self.at.get(n)), default=-1)
        if nearest >= 0 and nearest > max((self.at[n][-1] for n in limits if self.at.get(n)), default=-1):
            self.cut(nearest)

    def steps(self) -> tuple[int, ...]:
        if self.known is None:
            self.known = tuple(sorted(self.counts))
        return self.known


#: A tag: its first and last-plus-one character, its name, whether it ends an element, its attributes, and whether it closes itself.
Tag = tuple[int, int, str, bool, str, bool]


def _tags(page: str) -> tuple[list[Tag], dict[int, int]]:
    """The tags of a page, and for start tags of left-out elements (by place) the place of their end tag, if they have one."""
    tags: list[Tag] = []
    ends: dict[int, int] = {}
    waiting: dict[str, list[int]] = defaultdict(list)
    no_end: set[str] = set()
    m = _TAG.search(page)
    while m:
        at = m.end()
        if m[2] is None:
            tags.append((m.start(), at, "", True, "", False))
        else:
            tag, shut = m[2].lower(), m[3].rstrip().endswith("/")
            if tag in SKIPPED:
                if m[1]:
                    if waiting[tag]:
                        ends[waiting[tag].pop()] = len(tags)
                elif not shut or tag == "head":
                    waiting[tag].append(len(tags))
            tags.append((m.start(), at, tag, bool(m[1]), m[3], shut))
            if tag in RAW and not m[1] and not shut and tag not in no_end:
                end = re.compile(rf"</{tag}(?=[\s/>])[^>]*>", re.I).search(page, at)
                if end:
                    waiting[tag].pop()
                    ends[len(tags) - 1] = len(tags)
                    tags.append((end.start(), end.end(), tag, True, "", False))
                    at = end.end()
                else:
                    no_end.add(tag)
        m = _TAG.search(page, at)
    return tags, ends


def blocks(page: str | None) -> list[Block]:
    """The blocks with text, in page order."""
    out: list[Block] = []
    if not page:
        return out
    tags, ends = _tags(page)
    path = _Path()
    pieces: list[str] = []
    linked, where, skip_to, loose, in_head = 0, ((), 0, ""), -1, "", False

    def close() -> None:
        nonlocal linked
        if pieces:
            text = " ".join(html.unescape("".join(pieces)).split())
            if text:
                out.append((*where, text, min(linked, len(text))))
            pieces.clear()
        linked = 0

    def add(text: str) -> None:
        nonlocal linked, where
        if text and (pieces or not text.isspace()):
            if not pieces:
                where = (path.steps(), len(path.blocks), path.blocks[-1] if path.blocks else "")
            pieces.append(text)
            if path.at["a"]:
                linked += len(text)

    at = 0
    for k, (start, end, tag, closes, attributes, shut) in enumerate(tags):
        if skip_to < 0 and not loose:
            text = page[at:start]
            if in_head and text and not text.isspace():
                in_head = False
            if not in_head:
                add(text)
        at = end
        if skip_to >= 0:
            if k == skip_to:
                skip_to = -1
            continue
        if not tag:
            continue
        if in_head:
            if closes:
                in_head = in_head and tag != "head"
                continue
            if tag in _IN_HEAD:
                skip_to = ends.get(k, -1) if tag in SKIPPED and tag != "head" else -1
                loose = tag if tag in SKIPPED and tag != "head" and skip_to < 0 and not shut else ""
                in_head = not loose
                continue
            in_head = False
        if loose:  # an element without an end tag: it ends here, or goes on
            options = loose in _OPTIONS
            if tag in INLINE or (tag in VOID and tag != "hr") or (closes and tag in SKIPPED and not (options and tag in ("select", "datalist"))):
                continue
            if not closes and tag in SKIPPED and tag != loose and not (options and tag in _OPTIONS):
                skip_to = ends.get(k, -1)
                continue
            loose = ""
        if tag in SKIPPED and tag != "head":
            if not closes and not shut:
                if k in ends:
                    skip_to = ends[k]
                else:
                    loose = tag
            continue
        if closes:
            if tag not in INLINE:
                close()
            path.shut({tag})
            continue
        if tag not in INLINE:
            close()
            if tag in _ENDS_P:
                path.shut(_CLOSED_BY["p"], _LIMITS["p"])
            if tag in _CLOSED_BY and tag != "p":
                path.shut(_CLOSED_BY[tag], _LIMITS[tag])
        if tag == "br":
            add(" ")
        if tag == "head":
            in_head = True
        elif tag not in VOID and not (shut and tag not in ("body", "html")):
            path.push(tag, " ".join(f"{a[0].lower()} {a[1] or a[2] or a[3]}" for a in _ATTRIBUTE.findall(attributes)) if attributes else "")
    if skip_to < 0 and not loose and not (in_head and page[at:].isspace()):
        add(page[at:])
    close()
    return out


@lru_cache(maxsize=1 << 16)
def _step(tag: str, names: str) -> tuple[int, ...]:
    """Places of a path step: its tag, and each word of its names."""
    words = {w for w in _NAME.findall(names.lower()) if len(w) > 1 and w not in ("class", "id", "role", "style")}
    own = () if tag in INLINE and tag != "a" else (_PLACES.get(tag, TAGS - 1),)
    return (*own, *(TAGS + zlib.crc32(x.encode()) % (STEPS - TAGS) for x in sorted(words)))


@lru_cache(maxsize=1 << 16)
def _word(word: str) -> int:
    return STEPS + zlib.crc32(word.encode()) % WORDS


_PROSE, _TITLES = frozenset(("p", "blockquote", "pre")), frozenset(("h1", "h2", "h3", "h4"))


def vectors(page: list[Block]) -> np.ndarray:
    out = np.zeros((len(page), WIDTH), np.float32)
    n = max(1, len(page))
    for k, (steps, depth, own, text, linked) in enumerate(page):
        row = out[k]
        row[list(steps)] = 1
        words = _WORD.findall(text.lower())
        if words:
            row[STEPS : STEPS + WORDS] = np.bincount([_word(w) for w in words], minlength=STEPS + WORDS)[STEPS:] / (2 + len(words) / 4)
        size = len(text)
        row[STEPS + WORDS :] = (
            min(np.log1p(size) / 7, 1.5),
            min(linked / size, 1),
            sum(map(text.count, ".,;:!?")) / (1 + size / 20),
            k / n,
            min(np.log1p(n) / 5, 1.5),
            text[-1] in ".!?:\"”»…",
            size < 30,
            min(depth / 10, 1.5),
            own in _PROSE,
            own in _TITLES,
            "©" in text,
            k == n - 1,
        )
    return out


class Labeller:
    """``w``: for each direction input weights, recurrent weights and bias; then output weights and bias."""

    def __init__(self, w: dict[str, np.ndarray]) -> None:
        self.w = {k: v.astype(np.float32) for k, v in w.items()}

    @staticmethod
    def load() -> Labeller:
        with np.load(Path(__file__).with_name("html_weights.npz")) as f:
            return Labeller(dict(f))

    def _pass(self, x: np.ndarray, alive: np.ndarray, side: str) -> np.ndarray:
        """Hidden states, steps first, of sequences ``x[step, sequence]``; ``alive`` marks steps that a sequence has."""
        steps, many, _ = x.shape
        inner = x @ self.w[f"{side}x"] + self.w[f"{side}b"]
        h, c = np.zeros((many, HIDDEN), np.float32), np.zeros((many, HIDDEN), np.float32)
        out = np.zeros((steps, many, HIDDEN), np.float32)
        for t in range(steps) if side == "f" else range(steps - 1, -1, -1):
            g = inner[t] + h @ self.w[f"{side}h"]
            i, f, o = (1 / (1 + np.exp(-g[:, k * HIDDEN : (k + 1) * HIDDEN])) for k in range(3))
            on = alive[t][:, None]
            c = np.where(on, f * c + i * np.tanh(g[:, 3 * HIDDEN :]), c)
            h = np.where(on, o * np.tanh(c), h)
            out[t] = h
        return out

    def label(self, pages: list[np.ndarray], at_once: int = 64) -> list[np.ndarray]:
        """For each page, the probability that each block is content. Pages of like length share a batch."""
        out: list[np.ndarray] = [np.zeros(0, np.float32)] * len(pages)
        order = sorted((k for k in range(len(pages)) if len(pages[k])), key=lambda k: len(pages[k]))
        while order:
            many = max(1, min(at_once, 20_000 // len(pages[order[-1]])))
            batch, order = order[-many:], order[:-many]
            steps = max(len(pages[k]) for k in batch)
            x = np.zeros((steps, len(batch), WIDTH), np.float32)
            alive = np.zeros((steps, len(batch)), bool)
            for j, k in enumerate(batch):
                x[: len(pages[k]), j] = pages[k]
                alive[: len(pages[k]), j] = True
            both = np.concatenate([self._pass(x, alive, "f"), self._pass(x, alive, "b")], 2)
            p = 1 / (1 + np.exp(-(both @ self.w["y"] + self.w["z"])))
            for j, k in enumerate(batch):
                out[k] = p[: len(pages[k]), j]
        return out


_loaded: list[Labeller] = []


def main_texts(pages: list[str | None]) -> list[str]:
    if not _loaded:
        _loaded.append(Labeller.load())
    read = [blocks(p) for p in pages]
    out = []
    for page, p in zip(read, _loaded[0].label([vectors(b) for b in read]), strict=True):
        out.append("\n".join(b[3] for b, q in zip(page, p.tolist(), strict=True) if q >= 0.5))
    return out


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """A row for each page: ``id_col, url_col, text, n_chars``. No shuffle."""

    def run(c: dict[str, list]) -> dict[str, list]:
        texts = main_texts(c["html"])
        return {"id": c["id"], "url": c["url"], "text": texts, "n_chars": list(map(len, texts))}

    narrow = pages.select(F.col(id_col).cast("bigint").alias("id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"))
    return map_columns(narrow, run, "id bigint, url string, text string, n_chars bigint").withColumnRenamed("id", id_col).withColumnRenamed("url", url_col)

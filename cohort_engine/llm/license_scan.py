"""License scans by template matching.

Templates are license notices in the markup of the public license list (:mod:`license_texts`): optional regions may be missing, and replaceable
ones stand for words of the author's own. They are compiled into automata over word tokens; a place of a text is accepted
if the mandatory wording matches exactly from there, in order, with nothing between but what the
markup allows. Case, punctuation and white space don't count, as words are all that is compared, and spellings that the list takes for equal are equal.
An automaton runs over a text once, from all places at the same time, and only if the text has the template's rarest-looking word.

Beside this, a few fixed phrases are counted wherever their words stand consecutively.

Defined results: null and empty texts have no words and no labels, and score 0; repeated rows get equal answers;
of several matches each label counts once, by its first; empty tables give empty ones; other columns are not read.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_columns
from .license_texts import TEMPLATES

# Phrases and their labels, and spellings that are equal in templates.
PHRASES = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}
EQUAL = {b"licence": b"license", b"licences": b"licenses", b"licenced": b"licensed", b"sublicence": b"sublicense", b"acknowledgement": b"acknowledgment", b"favour": b"favor", b"noncommercial": b"non-commercial", b"whilst": b"while"}
#: Replaceable regions of up to so many words count them; longer ones take any number.
COUNTED = 12

_LOWER_OR_BLANK = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))


def words_of(text: str | None) -> list[bytes]:
    """Lower-case runs of ASCII letters and digits and of all other characters, as UTF-8."""
    return (text or "").encode("utf-8", "surrogatepass").translate(_LOWER_OR_BLANK).split()


_MARKUP = re.compile(r"<<(beginOptional|endOptional|var)([^<>]*)>>|([^<]+|<)")
_RANGE = re.compile(r"match=\"\.(?:\{(\d+),(\d+)\}|(\+)|(\*))\"")


@dataclass
class Automaton:
    """A nondeterministic automaton over words. Edges by word, edges for any word, and free edges."""

    label: str
    by_word: list[dict[bytes, list[int]]] = field(default_factory=list)
    by_any: list[list[int]] = field(default_factory=list)
    free: list[list[int]] = field(default_factory=list)
    final: int = 0
    mandatory: list[bytes] = field(default_factory=list)
    #: For each state how many mandatory words lie before it.
    passed: list[int] = field(default_factory=list)

    def state(self) -> int:
        self.by_word.append({})
        self.by_any.append([])
        self.free.append([])
        self.passed.append(len(self.mandatory))
        return len(self.free) - 1

    @staticmethod
    def compile(label: str, markup: str) -> Automaton:
        a = Automaton(label)
        at = a.state()
        opened: list[int] = []
        for kind, more, text in _MARKUP.findall(markup):
            if kind == "beginOptional":
                opened.append(at)
                nxt = a.state()
                a.free[at].append(nxt)
                at = nxt
            elif kind == "endOptional":
                nxt = a.state()
                a.free[at].append(nxt)
                a.free[opened.pop()].append(nxt)
                at = nxt
            elif kind == "var":
                at = a._own(at, more)
            else:
                for word in words_of(text):
                    word = EQUAL.get(word, word)
                    if not opened:
                        a.mandatory.append(word)
                    nxt = a.state()
                    a.by_word[at].setdefault(word, []).append(nxt)
                    at = nxt
        assert not opened and a.mandatory, markup
        a.final = at
        a.start = frozenset(a.closed({0}))
        return a

    def _own(self, at: int, more: str) -> int:
        """Words of the author's own: at least one unless the range starts at 0 characters, and at most one for every two characters of the range."""
        m = _RANGE.search(more)
        assert m, more
        least, most = (int(m[1]), (int(m[2]) + 1) // 2) if m[1] else (1 if m[3] else 0, COUNTED + 1)
        if most > COUNTED:
            loop, after = self.state(), self.state()
            (self.by_any if least else self.free)[at].append(loop)
            self.by_any[loop].append(loop)
            self.free[loop].append(after)
            return after
        ends = [] if least else [at]
        for _ in range(most):
            nxt = self.state()
            self.by_any[at].append(nxt)
            ends.append(at := nxt)
        after = self.state()
        for s in ends:
            self.free[s].append(after)
        return after

    def closed(self, states: set[int]) -> set[int]:
        todo, seen = list(states), set(states)
        while todo:
            for s in self.free[todo.pop()]:
                if s not in seen:
                    seen.add(s)
                    todo.append(s)
        return seen

    def first(self, words: list[bytes], starts: range | list[int] | None = None) -> tuple[int, int] | None:
        """The match that ends first, from its last start: first and last word; None if there is none. ``starts``: where a match may start."""
        allowed = None if starts is None else set(starts)
        now: dict[int, int] = {}
        self.reached = 0
        for i, word in enumerate(words):
            if allowed is None or i in allowed:
                for s in self.start:
                    now[s] = i
            nxt: dict[int, int] = {}
            for s, began in now.items():
                for t in (*self.by_word[s].get(word, ()), *self.by_any[s]):
                    for c in self._closure(t):
                        if nxt.get(c, -1) < began:
                            nxt[c] = began
            if self.final in nxt:
                return nxt[self.final], i
            now = nxt
            if now:
                self.reached = max(self.reached, max(self.passed[s] for s in now))
        return None

    def _closure(self, state: int) -> list[int]:
        found = self.closures.get(state)
        if found is None:
            found = self.closures[state] = sorted(self.closed({state}))
        return found

    closures: dict[int, list[int]] = field(default_factory=dict)
    start: frozenset[int] = frozenset()
    reached: int = 0

    def accepts(self, words: list[bytes], start: int) -> bool:
        return self.first(words, [start]) is not None


class Scanner:
    def __init__(self, templates: list[tuple[str, str]] = TEMPLATES, phrases: dict[str, str] = PHRASES) -> None:
        self.automata = [Automaton.compile(label, markup) for label, markup in templates]
        self.phrases = [(f" {p} ".encode(), label) for p, label in phrases.items()]
        # a text that lacks the longest mandatory word of a template can't match it
        self.anchors: dict[bytes, list[Automaton]] = {}
        for a in self.automata:
            self.anchors.setdefault(max(a.mandatory, key=lambda w: (len(w), w)), []).append(a)
        self.spelled = {v: [k for k, x in EQUAL.items() if x == v] for v in EQUAL.values()}

    def scan(self, text: str | None) -> tuple[int, list[int], list[str], list[str], list[tuple[str, int, int]], float]:
        """Words, the places of phrases, base labels, all labels, the first match of each label of a template, and the score.

        The score grades the evidence: from 0.5 for a phrase and more for a template by its mandatory words; a long template that is
        only begun counts by how far it goes, up to a half."""
        words = words_of(text)
        line = b" " + b" ".join(words) + b" "
        places, base = [], set()
        for phrase, label in self.phrases:
            at = line.find(phrase)
            while at >= 0:
                places.append(line.count(b" ", 0, at))
                base.add(label)
                at = line.find(phrase, at + 1)
        found: dict[str, tuple[int, int]] = {}
        score = 0.5 if base else 0.0
        same: list[bytes] | None = None
        for anchor, automata in self.anchors.items():
            if any(b" " + w + b" " in line for w in (anchor, *self.spelled.get(anchor, ()))):
                same = same or [EQUAL.get(w, w) for w in words]
                for a in automata:
                    match = a.first(same)
                    if match:
                        found[a.label] = min(found.get(a.label, match), match)
                        score = max(score, 1 - 2.0 ** (-1 - len(a.mandatory) / 8))
                    elif len(a.mandatory) >= 40:
                        score = max(score, a.reached / len(a.mandatory) / 2)
        matches = sorted((label, *m) for label, m in found.items())
        return len(words), places, sorted(base), sorted(base | set(found)), matches, score


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", templates: list[tuple[str, str]] = TEMPLATES) -> DataFrame:
    """A row for each document: ``id_col, n_words, n_base, first_word, last_word, base_labels, labels, score, matches``.

    ``matches``: label, first and last word of each template's label, comma-joined."""
    kept: list[Scanner] = []

    def run(c: dict[str, list]) -> dict[str, list]:
        if not kept:
            kept.append(Scanner(templates))
        out: dict[str, list] = {n: [] for n in ("n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "matches")}
        for text in c["text"]:
            n, places, base, labels, matches, score = kept[0].scan(text)
            row = (n, len(places), min(places, default=None), max(places, default=None), ",".join(base), ",".join(labels), score, ",".join(f"{x}:{a}:{b}" for x, a, b in matches))
            for column, value in zip(out.values(), row, strict=True):
                column.append(value)
        return {"id": c["id"]} | out

    narrow = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text"))
    return map_columns(narrow, run, "id bigint, n_words bigint, n_base bigint, first_word bigint, last_word bigint, base_labels string, labels string, score double, matches string").withColumnRenamed("id", id_col)

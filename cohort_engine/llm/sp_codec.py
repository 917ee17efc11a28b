"""SentencePiece encoding and decoding by a streaming Viterbi search.

The search reads a text from left to right. It holds the best cost of each boundary that a
piece reaching past the current character may end at (no more than the longest piece has characters), and
the back-pointers of text that isn't committed. Whenever all surviving paths meet at one boundary,
the ids before it are final and leave the window.

Where the vocabulary shows that paths always meet (no piece goes on across a blank that follows
another character, or across a line feed), the search starts afresh, so what it gives for a run of text between two such boundaries
depends on the run alone. Ids of runs are kept in a bounded memory; a run that isn't there is searched. With ``memory=0`` all are.

Costs are the negative piece scores of a unigram model. A model of byte-pair merges has ranks as scores;
they are taken as frequency ranks, with the costs that a Zipf law gives, so ids may differ from those of
merge-order encoding while every sequence of ids decodes to the same text. Characters without a piece become
byte pieces, and so does a literal U+2581, so texts round-trip exactly.

Defined results: null and empty texts have no ids, and decode to an empty text; repeated rows get equal ids;
of equally cheap paths the one whose last piece is longest wins; empty tables give empty ones; other columns pass through
:func:`encode`; columns named like an output are replaced.
"""

from __future__ import annotations

import math
import re
from array import array
from itertools import chain
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import add_columns

BLANK = "▁"
_BLANK = BLANK.encode()
#: Costs are whole numbers of this part of a natural-log unit, so sums are exact and ties are ties wherever a text is cut.
UNIT = 1 << 20
#: Parts of texts whose ids a worker remembers, in each of two generations.
MEMORY = 250_000


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


class PieceCodec:
    def __init__(self, model: bytes, memory: int = MEMORY) -> None:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_proto=model)
        n = sp.get_piece_size()
        names, scores = [sp.id_to_piece(i) for i in range(n)], [sp.get_score(i) for i in range(n)]
        plain = [i for i in range(n) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
        ranks = all(scores[i] == round(scores[i]) for i in plain)
        cost = {i: round(UNIT * (math.log(2 - scores[i]) + math.log(math.log(n)) if ranks else -scores[i])) for i in plain}
        self.pieces = {names[i]: (cost[i], i) for i in plain}
        #: A tree by characters; under 0 a node has the cost and ids of the piece that ends there.
        self.tree: dict = {}
        for piece, (c, i) in self.pieces.items():
            node = self.tree
            for char in piece:
                node = node.setdefault(char, {})
            node[0] = c, (i,)
        self.bytes_of = [bytes([int(names[i][3:5], 16)]) if sp.is_byte(i) else names[i].replace(BLANK, " ").encode() if i in cost else b"" for i in range(n)]
        self.byte_id = {b[0]: i for i, b in enumerate(self.bytes_of) if sp.is_byte(i)}
        self.unknown = sp.unk_id()
        self.kind = "H" if n <= 1 << 16 else "i"
        self.longest = max(map(len, self.pieces))
        self.worst = max(cost.values()) + 10 * UNIT
        blank_inside = any(BLANK in p.lstrip(BLANK) for p in self.pieces)
        feed_inside = any("\n" in p and len(p) > 1 for p in self.pieces)
        self.parts = None if blank_inside else re.compile(b" *[^ ]+| +" if feed_inside else b" *[^ \n]+|\n| +").findall
        self.memory = memory
        self.recent: dict[bytes, bytes] = {}
        self.older: dict[bytes, bytes] = {}

    def spelled(self, char: str) -> tuple[int, tuple[int, ...]]:
        raw = char.encode()
        if all(b in self.byte_id for b in raw):
            return self.worst * len(raw), tuple(self.byte_id[b] for b in raw)
        return self.worst, (self.unknown,)

    def search(self, text: str):
        """Yields runs of ids as they become final. ``text`` has U+2581 for blanks.

        ``best`` holds, for each boundary of the window, its cost and where its last piece began. Where no piece reaches past a boundary,
        all paths go through it, so it is committed at once; a window as long as the longest piece is searched for a boundary
        that all surviving paths share further back. (Over one repeated letter there may be none; back-pointers then stay, costs don't.)"""
        root, window = self.tree.get, self.longest
        best: dict[int, tuple[int, int, tuple[int, ...]]] = {0: (0, 0, ())}
        start, reach, n, look = 0, 0, len(text), window
        for i in range(n):
            here = best[i][0]
            if reach == i:
                if i > start:
                    yield self._path(best, start, i)
                    best, start, look = {i: (here, 0, ())}, i, i + window
            elif i >= look:
                meet = self._meeting(best, range(i, reach + 1), start)
                if meet > start:
                    yield self._path(best, start, meet)
                    for k in range(start, meet):
                        best.pop(k, None)
                    start = meet
                # paths that never meet, as over one repeated letter, are looked at ever more rarely
                look = max(start + window, i + max(window // 4, (i - start) // 2))
            j, single, node = i + 1, False, root(text[i])
            while node is not None:
                piece = node.get(0)
                if piece is not None:
                    c, old = here + piece[0], best.get(j)
                    if old is None or c < old[0]:
                        best[j] = c, i, piece[1]
                        if j > reach:
                            reach = j
                    if j == i + 1:
                        single = True
                if j == n:
                    break
                node = node.get(text[j])
                j += 1
            if not single:
                c, ids = self.spelled(text[i])
                c += here
                old = best.get(i + 1)
                if old is None or c < old[0]:
                    best[i + 1] = c, i, ids
                    if reach == i:
                        reach = i + 1
        if n > start:
            yield self._path(best, start, n)

    @staticmethod
    def _meeting(best: dict, boundaries: range, start: int) -> int:
        """The last boundary that the paths to all of these go through."""
        ends = {k for k in boundaries if k in best}
        while len(ends) > 1:
            top = max(ends)
            ends.remove(top)
            ends.add(best[top][1] if top > start else start)
        return ends.pop()

    @staticmethod
    def _path(best: dict, start: int, end: int) -> list[int]:
        """Ids from ``start`` to ``end``."""
        runs, at = [], end
        while at > start:
            _, at, ids = best[at]
            runs.append(ids)
        runs.reverse()
        return [i for ids in runs for i in ids]

    def part(self, raw: bytes) -> bytes:
        """The ids of a run between two boundaries, as numbers of the type ``kind``."""
        found = self.older.get(raw)
        if found is None:
            text = raw.decode("utf-8", "surrogatepass").replace(" ", BLANK)
            found = array(self.kind, chain.from_iterable(self.search(text))).tobytes()
        if len(self.recent) >= self.memory:
            self.older, self.recent = self.recent, {}
        if len(raw) <= 64 and self.memory:
            self.recent[raw] = found
        return found

    def packed(self, text: str | None) -> np.ndarray:
        """The ids of a text."""
        if not text:
            return np.zeros(0, self.kind)
        out: list[bytes] = []
        for k, piece in enumerate((" " + text).encode("utf-8", "surrogatepass").split(_BLANK)):
            if k:
                out.append(array(self.kind, self.spelled(BLANK)[1]).tobytes())
            if self.parts:
                get, miss = self.recent.get, self.part
                out += [get(p) or miss(p) for p in self.parts(piece)]
            elif piece:
                out.append(self.part(piece))
        return np.frombuffer(b"".join(out), self.kind)

    def encode(self, text: str | None) -> list[int]:
        return self.packed(text).tolist()

    def decode(self, ids: list[int] | None) -> str:
        return b"".join([self.bytes_of[i] for i in ids or ()]).decode("utf-8", "replace")[1:]


_codecs: dict[bytes, PieceCodec] = {}


def _codec(model: bytes) -> PieceCodec:
    """The worker's codec for a model; built once."""
    if model not in _codecs:
        _codecs[model] = PieceCodec(model)
    return _codecs[model]


def _shared(df: DataFrame, model_path: str | None):
    return df.sparkSession.sparkContext.broadcast(Path(model_path or default_model()).read_bytes())


def encode(docs: DataFrame, text_col: str = "text", model_path: str | None = None) -> DataFrame:
    """``docs`` with ``ids array<int>, n_ids bigint, round_trip boolean`` (the ids decode to the text). No shuffle."""
    model = _shared(docs, model_path)

    def run(c: dict[str, list]) -> dict[str, list]:
        codec = _codec(model.value)
        runs, same = [], []
        for text in c[text_col]:
            ids = codec.packed(text)
            runs.append(ids.astype(np.int32))
            same.append(codec.decode(ids.tolist()) == (text or ""))
        sizes = [len(r) for r in runs]
        offsets = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
        return {"ids": pa.ListArray.from_arrays(offsets, np.concatenate(runs)), "n_ids": sizes, "round_trip": same}

    return add_columns(docs, [text_col], run, "ids array<int>, n_ids bigint, round_trip boolean")


def decode(coded: DataFrame, ids_col: str = "ids", text_col: str = "text", model_path: str | None = None) -> DataFrame:
    """``coded`` with the text of its ids. No shuffle."""
    model = _shared(coded, model_path)

    def run(c: dict[str, list]) -> dict[str, list]:
        codec = _codec(model.value)
        return {text_col: [codec.decode(ids) for ids in c[ids_col]]}

    return add_columns(coded, [ids_col], run, f"`{text_col}` string")



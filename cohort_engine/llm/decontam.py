"""Benchmark decontamination by greedy string tiling.

Texts and benchmark items become sequences of lower-case word tokens. A document is paired with the items with
which it shares a seed (``seed`` tokens in a row). For each pair, the longest common run of
tokens that is still unmarked on both sides is found by running Karp-Rabin hashes and marked as
a tile, again and again, until none of ``seed`` tokens is left; tiles may stand in any order, so
reordered passages count in full. A pair counts as a leak if tiles cover ``coverage`` of the item.

The benchmark is taken in blocks of bounded size; each block is an index that is sent to the
executors, and documents stream past it without a shuffle, whatever they share. Blocks are taken one after
another, each with a pass over the documents; only the index of one is held.

Defined results: null and word-less texts match nothing, and so do null and word-less items; items of
fewer than ``seed`` tokens need all their tokens in a row; repeated documents each give
their own rows, and items of equal tokens (in one block) count as one that has all their ids; empty tables give no rows (or keep all documents); extra columns of either table are
not read by :func:`leaks`, and pass through :func:`drop_leaks`.
"""

from __future__ import annotations

import math
import re
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import add_columns, cut, map_columns, numbered, place_of

_WORD = re.compile(r"[^\W_]+")
_BASE = 0x9E3779B97F4A7C15  # odd, so its powers can be divided out modulo 2**64
#: Characters of benchmark text in one block.
BLOCK_CHARS = 16_000_000


def tokens(text: str | None) -> list[str]:
    return _WORD.findall((text or "").lower())


def _powers(n: int) -> np.ndarray:
    out = np.full(n, _BASE, np.uint64)
    out[:1] = 1
    return np.multiply.accumulate(out)


class _Rolling:
    """Hashes of all windows of a sequence, for any length, from one running sum."""

    def __init__(self, ids: np.ndarray, powers: np.ndarray) -> None:
        self.powers, self.n = powers, len(ids)
        terms = ids.astype(np.uint64) * powers[: self.n]
        self.sums = np.concatenate([np.zeros(1, np.uint64), np.add.accumulate(terms)])

    def windows(self, width: int) -> np.ndarray:
        starts = self.n - width + 1
        return (self.sums[width:] - self.sums[:starts]) * self.powers[len(self.powers) - 1 - np.arange(starts)]


def tile(item: np.ndarray, text: np.ndarray, least: int) -> list[tuple[int, int, int]]:
    """Tiles ``(place in item, place in text, length)``, longest first. Negative ids match nothing.

    The length of the longest common open run is found by halving, as every shorter length has a common run too. Of all runs of that
    length (none can be longer) the first by place in the item, then in the text, are marked; each window is looked at once, since a
    window that a mark has covered never opens again. So a length costs time by the lengths of both sides, and there are at most as many
    lengths as the item has different tiles, however repetitive the texts are."""
    powers = _powers(max(len(item), len(text)) + 1)
    ours, theirs = _Rolling(item, powers), _Rolling(text, powers)
    used_item, used_text = item < 0, text < 0
    tiles: list[tuple[int, int, int]] = []

    def open_windows(used: np.ndarray, width: int) -> np.ndarray:
        taken = np.concatenate([[0], np.cumsum(used)])
        return np.flatnonzero(taken[width:] == taken[:-width])

    def common(width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Starts and hashes of open windows of both sides that the other side has, too."""
        a, b = open_windows(used_item, width), open_windows(used_text, width)
        x, y = ours.windows(width)[a], theirs.windows(width)[b]
        p, q = np.isin(x, y), np.isin(y, x)
        return a[p], x[p], b[q], y[q]

    most = min(len(item), len(text))
    while most >= least and len(common(least)[0]):
        low, high = least, most
        while low < high:
            middle = (low + high + 1) // 2
            if len(common(middle)[0]):
                low = middle
            else:
                high = middle - 1
        starts, own, there, keys = common(low)
        waiting: dict[int, list[int]] = {}
        for j, h in zip(there.tolist()[::-1], keys.tolist()[::-1], strict=True):
            waiting.setdefault(h, []).append(j)  # last first, so the first is at the end
        end_item, marked = 0, False
        for i, h in zip(starts.tolist(), own.tolist(), strict=True):
            if i < end_item:
                continue
            places = waiting[h]
            while places:
                j = places.pop()
                if not (used_text[j] or used_text[j + low - 1]) and (item[i : i + low] == text[j : j + low]).all():
                    used_item[i : i + low] = used_text[j : j + low] = True
                    tiles.append((i, j, low))
                    end_item, marked = i + low, True
                    break
        most = low if marked and len(common(low)[0]) else low - 1
    return tiles


@dataclass
class SeedIndex:
    """The items of one block: their tokens as numbers, and where each seed occurs. Items of equal tokens are kept once, with all their ids."""

    seed: int
    ids: list[list[int | None]] = field(default_factory=list)
    items: list[np.ndarray] = field(default_factory=list)
    number: dict[str, int] = field(default_factory=dict)
    #: For each width of seeds: the distinct hashes in order, where each one's places begin, and the item and place of each.
    seeds: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = field(default_factory=dict)

    @staticmethod
    def build(rows: list[tuple[int | None, str | None]], seed: int) -> SeedIndex:
        index = SeedIndex(seed)
        known: dict[bytes, int] = {}
        widths: dict[int, list[int]] = {}
        for item_id, text in rows:
            if words := tokens(text):
                item = np.array([index.number.setdefault(w, len(index.number) + 1) for w in words], np.int64)
                k = known.setdefault(item.tobytes(), len(index.items))
                if k == len(index.items):
                    index.items.append(item)
                    index.ids.append([])
                    widths.setdefault(min(seed, len(words)), []).append(k)
                index.ids[k].append(item_id)
        for ids in index.ids:
            ids.sort(key=lambda i: (i is None, i))
        for width, ks in widths.items():
            parts = [_fixed_windows(index.items[k], width) for k in ks]
            hashes, owner = np.concatenate(parts), np.repeat(ks, [len(p) for p in parts])
            place = np.concatenate([np.arange(len(p)) for p in parts])
            order = np.argsort(hashes, kind="stable")
            distinct, first = np.unique(hashes[order], return_index=True)
            index.seeds[width] = distinct, np.append(first, len(order)), owner[order], place[order]
        return index

    def seen(self, texts: list[str | None], coverage: float = 0.0) -> list[list[tuple[int, int, int, int]]]:
        """For each text ``(item, tokens covered, tiles, longest tile)`` for every item that tiles may cover to that share.

        Tiles lie within seeds that both sides have, so an item whose shared seeds cover too little of it isn't tiled."""
        get = self.number.get
        parts = [np.array([get(w, 0) for w in tokens(t)] + [0], np.int64) for t in texts]
        flat = np.concatenate(parts) if parts else np.zeros(0, np.int64)
        bounds = np.cumsum([len(p) for p in parts])
        out: list[list[tuple[int, int, int, int]]] = [[] for _ in texts]
        gaps = np.concatenate([[0], np.cumsum(flat == 0)])
        for width, (distinct, first, owner, place) in self.seeds.items():
            if len(flat) < width:
                continue
            full = np.flatnonzero(gaps[width:] == gaps[:-width])
            h = _window_at(flat, full, width)
            at = np.minimum(np.searchsorted(distinct, h), len(distinct) - 1)
            hit = distinct[at] == h
            starts, values = full[hit], at[hit]
            docs = np.searchsorted(bounds, starts, side="right")
            for doc in np.unique(docs).tolist():
                mine = slice(*np.searchsorted(docs, [doc, doc + 1]).tolist())
                shared = np.unique(values[mine])
                # the places in items of the seeds that the text has
                spread = np.concatenate([np.arange(a, b) for a, b in zip(first[shared].tolist(), first[shared + 1].tolist(), strict=True)])
                order = np.lexsort((place[spread], owner[spread]))
                who, where = owner[spread][order], place[spread][order]
                new = np.concatenate([[True], who[1:] != who[:-1]])
                gain = np.where(new, width, np.minimum(np.diff(where, prepend=0), width))
                heads = np.flatnonzero(new)
                reach = np.add.reduceat(gain, heads)
                for k, n in zip(who[heads].tolist(), reach.tolist(), strict=True):
                    if n >= coverage * len(self.items[k]):
                        found = self._tiled(k, width, flat, starts[mine], values[mine], distinct)
                        if found:
                            out[doc].append(found)
        return [sorted(x) for x in out]

    def _tiled(self, k: int, width: int, flat: np.ndarray, starts: np.ndarray, values: np.ndarray, distinct: np.ndarray) -> tuple[int, int, int, int] | None:
        """Tiles of item ``k`` with the parts of a text that lie in seeds of the item; the rest of the text is left out."""
        item = self.items[k]
        own = np.unique(_fixed_windows(item, width))
        mine = starts[np.isin(distinct[values], own)]
        cover = np.unique((mine[:, None] + np.arange(width)).ravel())
        breaks = np.flatnonzero(np.diff(cover) > 1) + 1
        text = np.insert(flat[cover], breaks, -1)
        tiles = tile(item, text, width)
        return (k, sum(n for _, _, n in tiles), len(tiles), max(n for _, _, n in tiles)) if tiles else None


def _window_at(ids: np.ndarray, starts: np.ndarray, width: int) -> np.ndarray:
    h = np.full(len(starts), width, np.uint64)
    for d in range(width):
        h = h * np.uint64(_BASE) + ids[starts + d].astype(np.uint64)
    return h


def _fixed_windows(ids: np.ndarray, width: int) -> np.ndarray:
    return _window_at(ids, np.arange(len(ids) - width + 1), width)


def _blocks(benchmark: DataFrame, item_col: str, text_col: str, seed: int):
    """The indexes of the blocks, one after another, and whether each is the last."""
    items = benchmark.select(F.col(item_col).cast("bigint").alias("i"), F.col(text_col).alias("t"))
    size = items.agg(F.sum(F.length("t")).alias("n")).first()["n"] or 0
    n = max(1, math.ceil(size / BLOCK_CHARS))
    for k in range(n):
        # by text, so that equal items share a block
        block = items if n == 1 else items.where(F.pmod(F.xxhash64(F.lower("t")), F.lit(n)) == k)
        yield k == n - 1, benchmark.sparkSession.sparkContext.broadcast(SeedIndex.build([(r["i"], r["t"]) for r in block.toLocalIterator()], seed))


def leaks(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", seed: int = 5, coverage: float = 0.5) -> DataFrame:
    """A row for each leak: ``id_col, item_id, item_tokens, covered, coverage, tiles, longest_tile, item_ids``.

    Items of equal tokens are one item: ``item_id`` is their smallest id, ``item_ids`` has all of them."""

    def against(index):
        def run(c: dict[str, list]) -> dict[str, list]:
            x, rows = index.value, []
            for i, found in zip(c["id"], x.seen(c["text"], coverage), strict=True):
                rows += [(i, x.ids[k][0], len(x.items[k]), n, n / len(x.items[k]), t, long, x.ids[k]) for k, n, t, long in found if n >= coverage * len(x.items[k])]
            return {name: [r[k] for r in rows] for k, name in enumerate(names)}

        return map_columns(narrow, run, "id bigint, item_id bigint, item_tokens bigint, covered bigint, coverage double, tiles bigint, longest_tile bigint, item_ids array<bigint>")

    names = ["id", "item_id", "item_tokens", "covered", "coverage", "tiles", "longest_tile", "item_ids"]
    narrow = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text"))
    parts = []
    for last, index in _blocks(benchmark, item_col, item_text_col, seed):
        part = against(index)
        if not last:  # one block after another: its rows are kept, and its index goes before the next is built
            part = cut(part)
            index.unpersist(blocking=True)
        parts.append(part)
    return reduce(DataFrame.unionByName, parts).withColumnRenamed("id", id_col)


def drop_leaks(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", seed: int = 5, coverage: float = 0.5) -> DataFrame:
    """Documents without a leak, all columns as they are; no shuffle."""
    out, text = numbered(docs), f"_{place_of(docs, text_col)}"
    for last, index in _blocks(benchmark, item_col, item_text_col, seed):

        def run(c: dict[str, list], index=index) -> dict[str, list]:
            x = index.value
            return {"_clean": [not any(n >= coverage * len(x.items[k]) for k, n, _, _ in found) for found in x.seen(c[text], coverage)]}

        out = add_columns(out, [text], run, "_clean boolean", keep="_clean")
        if not last:
            out = cut(out)
            index.unpersist(blocking=True)
    return out.toDF(*docs.columns)

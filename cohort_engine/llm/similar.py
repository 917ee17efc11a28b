"""Near copies by the similarity of whole texts: five-word shingles, Jaccard 0.8 or more.

Every distinct text gets a fingerprint of its five-word shingles, made as in :mod:`simhash`, and multi-index hashing over six
segments of it finds candidates: in each bucket of a segment the members with one of them, then of all pairs with a segment that differs in one bit or none
those that are still in different groups. Whatever is linked has been compared by its whole sets of shingles, so no pair below the
limit is. Fingerprints of two texts at 0.8 differ in about ten bits, so these segments can't find all pairs. For the rest every text
also has 128 minima of its shingles' hashes under different orders, cut into 32 pieces of four. Of a pair at 0.8 no piece is equal
for one in 20 million. In each bucket of a piece members that are not yet in its group are compared with one member, another one in
each bucket. Texts of buckets that are still in several groups are then joined by the rarest shingles
of their sets: of two similar sets, the first few in order of rarity must meet, early enough for the rest to make up the
overlap, and in each list of texts with a shingle only pairs of different groups are looked at. Before any
comparison of sets stands a bound that is exact, too: 512 bits of parity of a set, of which no two sets differ in more than in
their shingles. So a large group of near copies costs rows by its members and its links, not by their square, even where most of its members are just below the limit.

Defined results: letters A-Z count as a-z, and runs of ASCII white space as one blank; a text of fewer than five words is one
shingle; null and word-less texts are equal to each other; rows with a null id take part; an empty table gives an empty one.
"""

from __future__ import annotations

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import FEW_KEYS, cut, keep_keys, map_columns, row_key
from .simhash import SEED, candidates, components, crowded, majority, stars

SHINGLE = 5
SEGMENTS, ROWS = 32, 4
#: The limit as a fraction of whole numbers.
LIMIT = (4, 5)
#: Bits by which fingerprints of candidates may differ; two texts at the limit differ in about ten.
REACH = 16

_RANDOM = np.random.default_rng(SEED)
_TIMES = _RANDOM.integers(0, 1 << 63, SEGMENTS * ROWS, np.uint64) * np.uint64(2) + np.uint64(1)
_PLUS = _RANDOM.integers(0, 1 << 63, SEGMENTS * ROWS, np.uint64)
_MIX = _RANDOM.integers(0, 1 << 63, SEGMENTS * ROWS, np.uint64).reshape(SEGMENTS, ROWS) * np.uint64(2) + np.uint64(1)


def windows(text: str | None) -> np.ndarray:
    """Hashes of a text's shingles, repeats included."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: A-Z and ASCII white space only
    line = b" ".join(words)
    digest = xxhash.xxh64_intdigest
    if len(words) <= SHINGLE:
        return np.array([digest(line, SEED)], np.uint64)
    blanks = np.flatnonzero(np.frombuffer(line, np.uint8) == 32)
    starts, ends = [0, *(blanks + 1).tolist()], [*blanks.tolist(), len(line)]
    return np.array([digest(line[a:b], SEED) for a, b in zip(starts, ends[SHINGLE - 1 :], strict=False)], np.uint64)


def shingles(text: str | None) -> np.ndarray:
    """Hashes of the distinct shingles of a text, in order."""
    return np.unique(windows(text))


def segments(hashes: np.ndarray) -> np.ndarray:
    """For each segment one number, equal where all its minima are."""
    least = np.full(SEGMENTS * ROWS, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(hashes), 256):
        np.minimum(least, (hashes[at : at + 256, None] * _TIMES + _PLUS).min(0), out=least)
    mixed = ((least.reshape(SEGMENTS, ROWS) ^ (least.reshape(SEGMENTS, ROWS) >> np.uint64(31))) * _MIX).sum(1, dtype=np.uint64)
    return (mixed ^ (mixed >> np.uint64(29)) ^ np.arange(SEGMENTS, dtype=np.uint64)).view(np.int64)


PARITY = 8


def parity(hashes: np.ndarray) -> np.ndarray:
    """For each of 512 bits whether an odd number of hashes falls on it, as 8 numbers."""
    bits = np.bincount((hashes >> np.uint64(13)).astype(np.int64) & 511, minlength=512) & 1
    return np.packbits(bits.astype(np.uint8), bitorder="little").view(np.int64)


def _digest(text: Column) -> Column:
    return F.unhex(F.md5(F.coalesce(text, F.lit(""))))


def _least_overlap(n: Column, m: Column) -> Column:
    """How many shingles two sets of these sizes share at least, if they are similar."""
    return F.ceil((n + m) * LIMIT[0] / (LIMIT[0] + LIMIT[1]))


def _plausible(x: str, y: str) -> Column:
    """Whether two sets may be similar by their sizes (``<x>n``) and parities (``<x>p0`` and on)."""
    n, m = F.col(f"{x}n"), F.col(f"{y}n")
    apart = F.lit(0)
    for k in range(PARITY):
        apart = apart + F.bit_count(F.col(f"{x}p{k}").bitwiseXOR(F.col(f"{y}p{k}")))
    return (F.least(n, m) * LIMIT[1] >= F.greatest(n, m) * LIMIT[0]) & (apart <= n + m - 2 * _least_overlap(n, m))


def _about(per: DataFrame, x: str, name: str) -> DataFrame:
    """Sizes and parities of nodes, for one side of a join."""
    return per.select(F.col("node").alias(name), F.col("n").alias(f"{x}n"), *(F.col("parity")[k].alias(f"{x}p{k}") for k in range(PARITY)))


def _alike(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """Those of the pairs ``a, b`` whose sets are at least as similar as the limit."""
    x, y = (sets.select(F.col("node").alias(n), F.col("hashes").alias(f"{n}s")) for n in ("a", "b"))
    both = pairs.select("a", "b").join(y, "b").join(x, "a")
    total = F.size("as") + F.size("bs")
    shared = F.size(F.array_intersect("as", "bs"))
    return both.where(shared * LIMIT[1] >= (total - shared) * LIMIT[0]).select("a", "b")


def _roots(edges: DataFrame) -> DataFrame:
    return cut(components(edges))


def _joined(roots: DataFrame, edges: DataFrame) -> DataFrame:
    """``roots`` (``node, root``) once more edges have come. Groups are joined, not their texts, so edges within
    a group are nothing here, and those between two groups are one."""
    edges = cut(edges)
    if edges.isEmpty():
        return roots
    x, y = (roots.select(F.col("node").alias(n), F.col("root").alias(f"{n}root")) for n in ("a", "b"))
    groups = edges.join(x, "a", "left").join(y, "b", "left").select(F.coalesce("aroot", "a").alias("a"), F.coalesce("broot", "b").alias("b"))
    over = _roots(groups)
    moved = roots.join(over.select(F.col("node").alias("root"), F.col("root").alias("to")), "root", "left").select("node", F.coalesce("to", "root").alias("root"))
    return cut(_anew(moved).unionByName(_anew(over)).distinct())


def _by_rarity(nodes: DataFrame, sets: DataFrame, per: DataFrame) -> DataFrame:
    """Plausible pairs ``a, b`` of ``nodes`` (``node, root``) with different roots: all that are similar, and few others."""
    held = sets.join(nodes, "node")
    flat = held.select("node", "root", F.size("hashes").alias("n"), F.explode("hashes").alias("token"))
    counted = flat.groupBy("token").agg(F.count("*").alias("f")).where("f > 1")
    # what only one of the texts has can't be shared, but it takes a place at the front
    ranked = flat.join(counted, "token").groupBy("node").agg(F.first("root").alias("root"), F.first("n").alias("n"), F.sort_array(F.collect_list(F.struct("f", "token"))).alias("shared"))
    alone = F.col("n") - F.size("shared")
    first = (F.col("n") - F.ceil(F.col("n") * LIMIT[0] / LIMIT[1]) + 1 - alone).cast("int")
    entries = ranked.where(first > 0).select("node", "root", "n", alone.alias("alone"), F.posexplode(F.slice("shared", 1, first)).alias("k", "e"))
    entries = cut(entries.select("node", "root", F.col("e.token").alias("token"), (F.col("n") - F.col("k") - F.col("alone")).alias("rest")))
    # the group that most texts of a list are in; pairs within it are never made
    tally = entries.groupBy("token", "root").agg(F.count("*").alias("c"))
    main = tally.groupBy("token").agg(F.max_by("root", F.struct("c", "root")).alias("main"), F.count("*").alias("groups")).where("groups > 1").drop("groups")
    entries = cut(entries.join(main, "token").withColumn("in_main", F.col("root") == F.col("main")).select("node", "root", "token", "rest", "in_main"))
    probe = entries.join(_about(per, "x", "node"), "node").withColumnsRenamed({"node": "x", "root": "xr", "rest": "xrest", "in_main": "xmain"})
    # of two similar sets the smaller one has a shared shingle even earlier
    index = entries.join(_about(per, "y", "node"), "node").where(F.col("rest") >= _least_overlap(F.col("yn"), F.col("yn"))).withColumnsRenamed({"node": "y", "root": "yr", "rest": "yrest", "in_main": "ymain"})
    smaller = (F.col("yn") < F.col("xn")) | ((F.col("yn") == F.col("xn")) & (F.col("y") < F.col("x")))
    enough = F.least("xrest", "yrest") >= _least_overlap(F.col("xn"), F.col("yn"))
    sides = ((probe, index.where("not ymain")), (probe.where("not xmain"), index.where("ymain")))
    met = [p.join(i, "token").where((F.col("xr") != F.col("yr")) & smaller & enough & _plausible("x", "y")).select(*_ordered("x", "y")) for p, i in sides]
    return met[0].unionByName(met[1]).distinct()


def _ordered(x: str, y: str) -> tuple[Column, Column]:
    return F.least(x, y).alias("a"), F.greatest(x, y).alias("b")


def _anew(numbers: DataFrame) -> DataFrame:
    """Numbers that are worked out anew: a union of two checkpoints with known partitions can fail in Spark 4.1."""
    return numbers.select(*(F.col(c).bitwiseXOR(F.lit(0).cast("bigint")).alias(c) for c in numbers.columns))


def _likely(met: DataFrame, per: DataFrame) -> DataFrame:
    """The plausible ones of the pairs ``a, b``."""
    return met.join(_about(per, "x", "a"), "a").join(_about(per, "y", "b"), "b").where(_plausible("x", "y")).select("a", "b")


def _ends(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.explode(F.array("a", "b")).alias("node"))


def groups(texts: DataFrame, per: DataFrame) -> DataFrame:
    """``node, root`` of all nodes that have a near copy; ``texts`` has ``digest, text``, and ``per`` ``node, digest, fp, n, parity, bands``."""
    filed = per.select("node", F.explode("bands").alias("bucket"))
    full = cut(filed.groupBy("bucket").agg(F.count("*").alias("many")).where("many > 1").select("bucket"))
    shared = cut(filed.join(F.broadcast(full) if full.count() <= FEW_KEYS else full, "bucket", "left_semi"))

    def run(c: dict[str, list]) -> dict[str, list]:
        return {"node": c["node"], "hashes": [shingles(t).view(np.int64).tolist() for t in c["text"]]}

    def sets_of(wanted: DataFrame) -> DataFrame:
        # a digest and a number are twice a key
        found = texts.join(F.broadcast(wanted) if 2 * wanted.count() <= FEW_KEYS else wanted, "digest")
        one = found.groupBy("node").agg(F.min("text").alias("text"))
        return cut(map_columns(one, run, "node bigint, hashes array<bigint>"))

    # fingerprints: first each text of a bucket of a segment with one of them
    prints = per.select("node", "fp", "n")
    crowd = crowded(prints)
    met = cut(_likely(stars(prints, REACH, LIMIT, crowd=crowd), per))
    ends = _anew(_ends(met)).unionByName(_anew(shared.select("node"))).distinct()
    about = cut(per.select("node", "digest", "n", "parity").join(ends, "node", "left_semi"))
    sets = sets_of(about.select("digest", "node"))
    roots = _roots(_alike(met, sets))
    # then all pairs of texts that are still in different groups
    grouped = prints.join(roots, "node", "left").select("node", "fp", "n", F.coalesce("root", "node").alias("root"))
    more = cut(_likely(candidates(grouped, REACH, LIMIT, apart="root", crowd=crowd).join(met, ["a", "b"], "left_anti"), per))
    late = cut(per.select("digest", "node").join(_ends(more).distinct().join(about, "node", "left_anti"), "node", "left_semi"))
    if not late.isEmpty():
        sets = cut(sets.unionByName(sets_of(late)))
    roots = _joined(roots, _alike(more, sets))
    # what fingerprints left apart: first each text of a bucket of minima with one of them
    hubs = shared.groupBy("bucket").agg(F.min(F.struct(F.xxhash64("bucket", "node"), "node"))["node"].alias("hub"))
    held = cut(shared.join(roots, "node", "left").select("bucket", "node", F.coalesce("root", "node").alias("root")))
    centres = hubs.join(roots.withColumnsRenamed({"node": "hub", "root": "centre"}), "hub", "left").select("bucket", "hub", F.coalesce("centre", "hub").alias("centre"))
    rays = held.join(centres, "bucket").where("root != centre").select(*_ordered("node", "hub")).distinct()
    roots = _joined(roots, _alike(_likely(rays, about), sets))
    # then texts of buckets whose members are still in more than one group
    held = shared.join(roots, "node", "left").select("bucket", "node", F.coalesce("root", "node").alias("root"))
    split = held.groupBy("bucket").agg(F.min("root").alias("low"), F.max("root").alias("high")).where("low != high").select("bucket")
    apart = cut(held.join(split, "bucket", "left_semi").select("node", "root").distinct())
    return _joined(roots, _alike(_by_rarity(apart, sets, about), sets))


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One document of each group of near copies: that with the smallest id, nulls last. Of rows with that same id
    and equal texts one stays."""
    own_id, text = F.col(id_col).cast("bigint"), F.col(text_col)
    narrow = docs.select(own_id.alias("id"), text.alias("text"), _digest(text).alias("digest"), row_key(F.col(id_col), text).alias("key"))

    def run(c: dict[str, list]) -> dict[str, list]:
        runs = [windows(t) for t in c["text"]]
        sets = list(map(np.unique, runs))
        made = {"fp": np.array(list(map(majority, runs)), np.uint64).view(np.int64).tolist(), "n": list(map(len, sets)), "parity": [parity(x).tolist() for x in sets], "bands": [segments(x).tolist() for x in sets]}
        return {n: c[n] for n in ("id", "digest", "key")} | made

    prints = cut(map_columns(narrow, run, "id bigint, digest binary, key binary, fp bigint, n int, parity array<bigint>, bands array<bigint>"))
    first = F.min(F.struct(F.col("id").isNull(), "id", "key")).alias("first")
    per = prints.groupBy("digest").agg(first, *(F.first(c).alias(c) for c in ("fp", "n", "parity", "bands")))
    # a text's number, which is short; the checkpoint holds it fast
    per = cut(per.withColumn("node", F.monotonically_increasing_id()))
    found = groups(narrow.select("digest", "text"), per)
    named = per.join(found, "node", "left").select("first", F.coalesce("root", "node").alias("root"))
    winners = named.groupBy("root").agg(F.min("first").alias("first")).select(F.col("first.key").alias("key"))
    return keep_keys(docs, id_col, text_col, prints.select("key"), winners)

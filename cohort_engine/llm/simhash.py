"""SimHash near-duplicates by multi-index hashing.

A 64-bit fingerprint is the bitwise majority of the XXH64 hashes of a text's word shingles.
Fingerprints at most three bits apart are linked. They are cut into two halves: if two
fingerprints differ in three bits or fewer, one half differs in one bit or none. Every distinct
fingerprint is filed under both halves, and asks for each half as it is and with one of its
clear bits set (of two halves one bit apart, one has that bit clear, so each pair is asked for once).
Matches are verified over all 64 bits.

Buckets with more than ``dense`` fingerprints (a group of near copies), and neighbours that would make as many
pairs as such a bucket, take another exact way that makes no pairs: see :func:`_dense_links`.

Links join distinct fingerprints only, so exact copies cost nothing, and components are found
by rounds of distributed label exchange, cut by checkpoints; nothing but counts reaches the driver.

Defined results: null and word-less texts have fingerprint zero, linked like any other; rows
with a null id take part and get the component's smallest id that is not null (null if it has
none); repeated ids and rows each get a row; an empty table gives an empty one; other columns
of the input are not read.
"""

from __future__ import annotations

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import FEW_KEYS, cut, has_rows, keep_keys, map_columns, row_key

SEED = 42
#: For each value of a byte, its bits, lowest first.
_BITS = ((np.arange(256)[:, None] >> np.arange(8)) & 1).astype(np.int64)
_HALF = 0xFFFFFFFF
#: Beside the masks of a half's bits, the mark of the half as it is.
_ITSELF = 1 << 32


def majority(hashes: np.ndarray) -> int:
    """The bits that are set in over half the hashes."""
    planes = hashes.astype("<u8").view(np.uint8).reshape(-1, 8)
    ones = np.concatenate([np.bincount(planes[:, k], minlength=256) @ _BITS for k in range(8)])
    return int.from_bytes(np.packbits(2 * ones > len(hashes), bitorder="little").tobytes(), "little")


def fingerprint(text: str | None, width: int = 3) -> int:
    """The fingerprint of one text, as an unsigned integer."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: A-Z and ASCII white space only
    if not words:
        return 0
    line = b" ".join(words)
    if len(words) < width:
        hashes = [xxhash.xxh64_intdigest(line, SEED)]
    else:
        blanks = np.flatnonzero(np.frombuffer(line, np.uint8) == 32)
        starts, ends = [0, *(blanks + 1).tolist()], [*blanks.tolist(), len(line)]
        digest = xxhash.xxh64_intdigest
        hashes = [digest(line[a:b], SEED) for a, b in zip(starts, ends[width - 1 :], strict=False)]
    return majority(np.array(hashes, dtype="<u8"))


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3) -> DataFrame:
    """``id, fp`` with the fingerprint as a signed 64-bit integer. No shuffle."""

    def run(c: dict[str, list]) -> dict[str, list]:
        return {"id": c["id"], "fp": [f - (1 << 64) if (f := fingerprint(t, width)) >> 63 else f for t in c["text"]]}

    narrow = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text"))
    return map_columns(narrow, run, "id bigint, fp bigint")


def hexadecimal(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def _half(fp: Column, k: int) -> Column:
    return F.shiftrightunsigned(fp, 32 * k).bitwiseAND(F.lit(_HALF))


def _filed(fps: DataFrame) -> DataFrame:
    """Every fingerprint under both halves."""
    both = F.array(*(F.struct(F.lit(k).alias("half"), _half(F.col("fp"), k).alias("key")) for k in (0, 1)))
    return fps.select(F.explode(both).alias("f"), F.col("fp").alias("there")).select(F.col("f.half").alias("half"), F.col("f.key").alias("key"), "there")


def _asked(starts: DataFrame) -> DataFrame:
    """Keys within one bit of a half: itself, and itself with each clear bit set. ``skip`` marks bits that are
    left out, and with ``_ITSELF`` the key itself."""
    clear = lambda mask: F.col("skip").bitwiseAND(F.lit(mask)) == 0
    ups = (F.when((F.col("key").bitwiseAND(F.lit(1 << b)) == 0) & clear(1 << b), F.col("key").bitwiseOR(F.lit(1 << b))) for b in range(32))
    near = F.array(F.when(clear(_ITSELF), F.col("key")), *ups)
    return starts.select("half", F.explode(F.array_compact(near)).alias("key"), F.col("there").alias("here"))


def _ball(radius: int, bits: int = 32) -> Column:
    """The masks of all values within ``radius`` bits, nearest first, as strings: a constant of the plan."""
    masks = [0, *(1 << i for i in range(bits))] + [(1 << i) | (1 << j) for i in range(bits) for j in range(i)] * (radius > 1)
    return F.split(F.lit(",".join(map(str, masks))), ",")


def _dense_links(members: DataFrame, apart: int) -> DataFrame:
    """Links within groups of many fingerprints (``half, key, bit, there``), without pairs.

    Inside a group two members are linked if their other halves are at most ``apart`` bits
    apart; and they are just then if some value lies within one part of these bits of the one
    and the rest of the other. Each member stands at all values of its balls of both sizes; at
    each value, all members that come within the larger are linked to one that comes within the
    smaller (if there is one). Every link made is true, and true links that are left out are between
    two members that such links connect. Rows grow with members, not with their square."""
    near = apart // 2
    other = F.when(F.col("half") == 0, _half(F.col("there"), 1)).otherwise(_half(F.col("there"), 0))
    masked = members.select("half", "key", "bit", "there", other.alias("other"), F.posexplode(_ball(apart - near)).alias("i", "mask"))
    stands = masked.select("half", "key", "bit", F.col("other").bitwiseXOR(F.col("mask").cast("bigint")).alias("at"), (F.col("i") <= 32 * near).alias("close"), "there")
    hubs = stands.where("close").groupBy("half", "key", "bit", "at").agg(F.min("there").alias("a"))
    return stands.join(hubs, ["half", "key", "bit", "at"]).where("there != a").select("a", F.col("there").alias("b"))


def _wide_edges(heavy: DataFrame, sizes: DataFrame, dense: int) -> DataFrame:
    """``half, key, bit`` of buckets one bit apart that would make more than ``dense`` squared pairs: the key where
    the bit is clear, and the bit's mask. One of two such buckets is heavy itself."""
    flips = F.explode(F.array(*(F.lit(1 << b) for b in range(32))))
    near = heavy.select("half", F.col("key").alias("own"), F.col("n").alias("m"), flips.alias("bit"))
    near = near.withColumn("key", F.col("own").bitwiseXOR(F.col("bit")))
    return near.join(sizes, ["half", "key"]).where(F.col("n") * F.col("m") > dense * dense).select("half", F.least("own", "key").alias("key"), "bit").distinct()


def links(fps: DataFrame, radius: int = 3, dense: int = 256) -> DataFrame:
    """``a, b``: pairs of distinct fingerprints, enough of the pairs within ``radius`` bits to connect
    all that they connect; in buckets up to ``dense`` members, and between two neighbours up to
    ``dense`` squared pairs, each such pair once."""
    assert 2 <= radius <= 3, "two halves and one bit hold up to a distance of three"
    filed = cut(_filed(fps))
    sizes = filed.groupBy("half", "key").agg(F.count("*").alias("n"))
    heavy = cut(sizes.where(F.col("n") > dense))
    many = not heavy.isEmpty()
    if many:
        wide = cut(_wide_edges(heavy, sizes, dense))
        whole = heavy.select("half", "key", F.lit(_ITSELF).alias("bit"))
        marks = whole.unionByName(wide).groupBy("half", "key").agg(F.bit_or("bit").alias("skip"))
        starts = filed.join(marks, ["half", "key"], "left").withColumn("skip", F.coalesce("skip", F.lit(0).cast("bigint")))
    else:
        starts = filed.withColumn("skip", F.lit(0).cast("bigint"))
    apart = F.bit_count(F.col("here").bitwiseXOR(F.col("there")))
    itself = F.col("here") == F.col("there")
    pairs = _asked(starts).join(filed, ["half", "key"]).where(~itself & (apart <= radius))
    found = pairs.select(F.least("here", "there").alias("a"), F.greatest("here", "there").alias("b"))
    if many:
        found = found.unionByName(_dense_links(filed.join(whole, ["half", "key"]), radius))
        ends = wide.select("half", F.col("key").alias("low"), "bit", F.explode(F.array("key", F.col("key").bitwiseOR(F.col("bit")))).alias("key"))
        both = filed.join(ends, ["half", "key"]).select("half", F.col("low").alias("key"), "bit", "there")
        found = found.unionByName(_dense_links(both, radius - 1))
    return found.distinct()


def _signed(bits: int) -> int:
    return bits - (1 << 64) if bits >> 63 else bits


#: Segments for texts that are less alike: the 64 bits are cut in three in two ways, piece by piece and bit by bit in turn.
WIDE = tuple(tuple(1 << b for b in range(64) if at(b) == k) for at in (lambda b: min(b // 21, 2), lambda b: b % 3) for k in range(3))


def _segments(prints: DataFrame) -> DataFrame:
    """``prints`` with a row for each segment: its number ``k``, its bits ``key``, and a number ``bucket`` of both."""
    keys = F.array(*(F.struct(F.lit(k).alias("k"), F.col("fp").bitwiseAND(F.lit(_signed(sum(segment)))).alias("key")) for k, segment in enumerate(WIDE)))
    return prints.select("*", F.explode(keys).alias("s")).select(*prints.columns, "s.k", "s.key").withColumn("bucket", F.xxhash64("k", "key"))


def crowded(prints: DataFrame) -> DataFrame:
    """``bucket, many, node, fp, n``: the members of buckets of a segment that have more than one, mostly few of all."""
    filed = _segments(prints).select("bucket", "node", "fp", "n")
    many = cut(filed.groupBy("bucket").agg(F.count("*").alias("many")).where("many > 1"))
    return cut(filed.join(F.broadcast(many) if many.count() <= FEW_KEYS else many, "bucket").select("bucket", "many", "node", "fp", "n"))


def _hubs(crowd: DataFrame) -> DataFrame:
    """For each bucket one of its members, ``hub``, with its ``fp`` and ``n``."""
    first = F.min(F.struct(F.xxhash64("bucket", "node"), "node", "fp", "n"))
    return crowd.groupBy("bucket").agg(first.alias("h")).select("bucket", F.col("h.node").alias("hub"), F.col("h.fp").alias("hubfp"), F.col("h.n").alias("hubn"))


def _close(fp: str, n: str, reach: int, ratio: tuple[int, int]) -> tuple[Column, Column]:
    """Whether ``fp`` and ``n`` of a member are close to those named."""
    return F.bit_count(F.col(fp).bitwiseXOR(F.col("fp"))) <= reach, F.least(n, "n") * ratio[1] >= F.greatest(n, "n") * ratio[0]


def stars(prints: DataFrame, reach: int, ratio: tuple[int, int], dense: int = 32, crowd: DataFrame | None = None) -> DataFrame:
    """``a, b``: the members of every bucket of a segment with one of them, another one in each bucket. Fingerprints and sizes are as in
    :func:`candidates`, but in buckets of more than ``dense`` members fingerprints may differ in any number of bits. Rows grow with members.
    ``crowd``: what :func:`crowded` gives, if it is there."""
    crowd = crowded(prints) if crowd is None else crowd
    near, even = _close("hubfp", "hubn", reach, ratio)
    met = crowd.join(_hubs(crowd), "bucket").where((F.col("node") != F.col("hub")) & even & (near | (F.col("many") > dense)))
    return met.select(F.least("node", "hub").alias("a"), F.greatest("node", "hub").alias("b")).distinct()


def candidates(prints: DataFrame, reach: int, ratio: tuple[int, int], dense: int = 32, apart: str | None = None, crowd: DataFrame | None = None) -> DataFrame:
    """``a, b``: pairs of ``prints`` (``node, fp, n``) with a segment of ``WIDE`` that differs in one bit or none, fingerprints at most ``reach`` bits
    apart, and sizes ``n`` whose ratio is at least the fraction ``ratio``. So all pairs of such sizes within five bits are there, and of those further
    apart the fewer the further.

    Buckets of more than ``dense`` members make no pairs: their members are paired with one of them, which
    alone asks and answers for the bucket. The caller has an exact way for what that leaves out.

    ``apart``: a column of ``prints`` with the group that :func:`stars` has brought a node to. Pairs within a group are not made then, as they
    connect nothing, and neither are pairs of full buckets, which are among the stars. ``crowd``: what :func:`crowded` gives, if it is there."""
    bits = F.array(*(F.array(*(F.lit(_signed(b)) for b in segment)) for segment in WIDE))
    filed = _segments(prints)
    crowd = crowded(prints) if crowd is None else crowd
    heavy = cut(_hubs(crowd.where(F.col("many") > dense)).select("bucket", "hub"))
    count = heavy.count()
    if count:
        filed = filed.join(F.broadcast(heavy) if count <= FEW_KEYS else heavy, "bucket", "left")
        full = filed.where("node != hub").select(F.least("node", "hub").alias("a"), F.greatest("node", "hub").alias("b"))
        filed = filed.where("hub IS NULL OR node = hub")
    clear = F.filter(F.get(bits, F.col("k")), lambda b: F.col("key").bitwiseAND(b) == 0)
    asked = F.concat(F.array("bucket"), F.transform(clear, lambda b: F.xxhash64("k", F.col("key").bitwiseOR(b))))
    # null for a node of its own, which takes the least room among the many rows that ask
    group = F.when(F.col(apart) != F.col("node"), F.col(apart)) if apart else F.lit(None).cast("bigint")
    asks = filed.select(F.explode(asked).alias("bucket"), F.col("node").alias("x"), F.col("fp").alias("xfp"), F.col("n").alias("xn"), group.alias("xgroup"))
    near, even = _close("xfp", "xn", reach, ratio)
    met = asks.join(filed.select("bucket", "node", "fp", "n", group.alias("group")), "bucket").where((F.coalesce("xgroup", "x") != F.coalesce("group", "node")) & near & even)
    pairs = met.select(F.least("x", "node").alias("a"), F.greatest("x", "node").alias("b"))
    return (pairs.unionByName(full) if count and apart is None else pairs).distinct()


def _either(edges: DataFrame, *sides: tuple[str, str]) -> DataFrame:
    """``a, b`` once for each of the pairs of columns. (A union of frames with known partitions, of which one comes from a checkpoint, can fail in Spark 4.1.)"""
    pairs = F.array(*(F.struct(F.col(x).alias("a"), F.col(y).alias("b")) for x, y in sides))
    return edges.select(F.explode(pairs).alias("e")).select(F.col("e.a").alias("a"), F.col("e.b").alias("b"))


def components(edges: DataFrame) -> DataFrame:
    """``node, root`` for every node of an edge: the smallest node of its component.

    Every round hooks each neighbour of a node onto the smallest of them, first for neighbours above the node,
    then for those below it, which flattens trees; the edges of a finished forest stay as they are."""
    edges = cut(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a != b").distinct())
    while True:
        both = _either(edges, ("a", "b"), ("b", "a"))
        low = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("low"))
        upward = both.where("b > a").join(low, "a").select(F.col("low").alias("a"), "b").where("a != b").distinct()
        least = upward.groupBy("b").agg(F.min("a").alias("low"))
        downward = upward.join(least, "b").select(F.col("low").alias("x"), F.when(F.col("a") == F.col("low"), F.col("b")).otherwise(F.col("a")).alias("b"))
        made = cut(downward.select(F.least("x", "b").alias("a"), F.greatest("x", "b").alias("b")).where("a != b").distinct())
        # finished once every node has one edge, to a root that hangs on nothing
        ends = made.select(F.explode(F.array(*(F.struct(F.col(c).alias("node"), F.lit(up).alias("up")) for c, up in (("a", 0), ("b", 1))))).alias("e"))
        hangs = ends.groupBy("e.node").agg(F.sum("e.up").alias("n"), F.min("e.up").alias("least"))
        if not has_rows(hangs.where("n > 1 OR n = 1 AND least = 0")):
            return _either(made, ("b", "a"), ("a", "a")).select(F.col("a").alias("node"), F.col("b").alias("root")).distinct()
        edges = made


def _labelled(prints: DataFrame, radius: int, dense: int) -> DataFrame:
    """``fp, component_id`` for each distinct fingerprint."""
    per = cut(prints.groupBy("fp").agg(F.min("id").alias("low")))
    roots = components(links(per.select("fp"), radius, dense))
    named = per.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "low", F.coalesce("root", "fp").alias("root"))
    least = named.groupBy("root").agg(F.min("low").alias("component_id"))
    return named.join(least, "root").select("fp", "component_id", "root")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = 3, dense: int = 256) -> DataFrame:
    """A row for each document: ``id_col, fingerprint, component_id``."""
    prints = cut(fingerprints(docs, id_col, text_col))
    found = prints.join(_labelled(prints, radius, dense), "fp")
    return found.select(F.col("id").alias(id_col), hexadecimal(F.col("fp")).alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = 3, dense: int = 256) -> DataFrame:
    """One document of each component: that with the smallest id, nulls last. Of rows with that same id and
    equal texts one stays."""
    own_id, text = F.col(id_col), F.col(text_col)
    narrow = docs.select(own_id.cast("bigint").alias("id"), text.alias("text"), row_key(own_id, text).alias("key"))

    def run(c: dict[str, list]) -> dict[str, list]:
        return {"id": c["id"], "key": c["key"], "fp": [f - (1 << 64) if (f := fingerprint(t)) >> 63 else f for t in c["text"]]}

    prints = cut(map_columns(narrow, run, "id bigint, key binary, fp bigint"))
    first = prints.join(_labelled(prints, radius, dense), "fp").groupBy("root").agg(F.min(F.struct(F.col("id").isNull(), "id", "key")).alias("first"))
    return keep_keys(docs, id_col, text_col, prints.select("key"), first.select(F.col("first.key").alias("key")))

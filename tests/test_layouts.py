"""Encodings, layouts, pruning, counters, and the plans that Spark makes."""

import numpy as np
import pytest
from hypothesis import given
from hypothesis import strategies as st
from pyspark.sql import functions as F

from cohort_engine import metrics, workloads
from cohort_engine.functions.bits import bits_needed, pack, read_at, read_column, read_many, unpack
from cohort_engine.functions.blocks import register
from cohort_engine.functions.lineage import cut
from cohort_engine.functions.measures import Count, Sum, UserCount
from cohort_engine.functions.predicates import Attr
from cohort_engine.operators import chunked, encode, layout, native
from cohort_engine.operators.core import birth_times
from cohort_engine.plans.algebra import CohortQuery
from cohort_engine.plans.planner import choose, execute
from cohort_engine.schema import ActivitySchema, ActivityTable
from cohort_engine.sources.tables import activity_events, scale_users


@pytest.fixture(scope="module")
def act(spark, data):
    # a checkpoint and not a cache: what is cached would stand in for the scans of other tests' plans
    t = activity_events(spark, data)
    return t.with_df(cut(t.df))


@given(st.lists(st.integers(0, 2**62), max_size=60))
def test_packing_round_trips(values):
    x = np.array(values, np.int64)
    bits, words = pack(x)
    assert unpack(bits, words, len(x)).tolist() == values
    assert bits == bits_needed(max(values, default=0))
    assert [read_at(bits, words, k) for k in range(len(x))] == values


def test_read_in_sql(spark):
    for values in ([5, 0, 7, 3, 1, 6, 2] * 9, [0, 0], [2**40, 1, 2**41 - 1]):
        bits, words = pack(np.array(values))
        df = spark.range(len(values)).select(read_column(F.lit(bits), F.array(*[F.lit(int(w)) for w in words]).cast("array<bigint>"), F.col("id").cast("int")).alias("v"))
        assert [r["v"] for r in df.collect()] == values


@pytest.mark.parametrize("mode", ["hash", "range"])
def test_chunks_hold_whole_users(act, mode):
    c = encode.compress(act, 150, mode)
    users = [u for r in c.chunks.collect() for u in r["users"]]
    assert len(users) == len(set(users)) == act.df.select("user_id").distinct().count()
    assert sum(r["n_rows"] for r in c.catalog.collect()) == act.df.count()
    assert c.catalog.count() > 2


def _columns(c, row, names):
    """Readers of a chunk's columns."""
    gids = {r["chunk_id"]: r["gids"] for r in c.catalog.collect()}[row["chunk_id"]]
    out = {}
    for n in names:
        p = row[c.field(n)]
        out[n] = chunked.PackedColumn(p["bits"], np.array(p["words"], np.int64), p["low"], p["nulls"], c.numbers.get(n), np.array(gids[n], np.int64) if n in c.strings else None)
    return out


def test_decoding(act):
    c = encode.compress(act, 300)
    want = sorted((r["user_id"], r["event_id"], r["role"], r["gold"]) for r in act.df.collect())
    names = {(r["column"], r["gid"]): r["value"] for r in c.dictionary.collect()}
    got = []
    for r in c.chunks.collect():
        owner, places = np.repeat(r["users"], r["counts"]), np.arange(r["n_rows"])
        col = _columns(c, r, ["event_id", "role", "gold"])
        got += [(int(u), int(e), names[("role", g)], v) for u, e, g, v in zip(owner, col["event_id"].values(places), col["role"].values(places), col["gold"].values(places), strict=True)]
    assert sorted(got) == want and c.numbers["gold"] == encode.Number("scaled", 100, *(round(100 * f(g for *_, g in want)) for f in (min, max)))


ODD = [0.0, -0.0, 1.5, -1.5, 1 / 3, -1 / 3, 1e-300, -1e300, 5e-324, float("inf"), float("-inf"), 0.1 + 0.2, None, float("nan")]


@pytest.mark.parametrize("values", [ODD, [0.004, 0.003, None, 12.5], [None, None], [1e17, 3.0], [2.0, -7.0]])
def test_doubles_are_exact(spark, values):
    rows = [(k % 3, k, "b", v, (1 << 62) + k if k % 2 else None) for k, v in enumerate(values)]
    act = ActivityTable(spark.createDataFrame(rows, "u int, t bigint, e string, v double, big bigint"), ActivitySchema("u", "t", "e", (), ("v", "big"), (), "tick"))
    c = encode.compress(act, 2)
    got = []
    for r in c.chunks.collect():
        col, places = _columns(c, r, ["t", "v", "big"]), np.arange(r["n_rows"])
        got += [(int(t), None if v is None or v != v else float(v), b) for t, v, b in zip(col["t"].values(places), col["v"].values(places), col["big"].values(places), strict=True)]
    assert sorted(got) == [(k, None if v is None or v != v else v, big) for _, k, _, v, big in rows]


@given(st.lists(st.floats(allow_nan=False), min_size=1, max_size=50))
def test_order_of_bits(values):
    x = np.array(values)
    keys = encode.ordered_bits(x)
    assert (encode.from_ordered_bits(keys) == x).all() and (np.sort(x) == encode.from_ordered_bits(np.sort(keys))).all()


@given(st.lists(st.integers(0, 2**64 - 1), max_size=60), st.data())
def test_reads_by_place(values, data):
    bits, words = pack(np.array(values, np.uint64))
    places = data.draw(st.lists(st.integers(0, len(values) - 1), max_size=30)) if values else []
    assert read_many(bits, words, np.array(places, np.int64)).tolist() == [values[k] for k in places]


def test_dictionary_is_sorted(act):
    rows = encode.global_dictionary(act.df, "country").orderBy("gid").collect()
    assert [r["gid"] for r in rows] == list(range(len(rows))) and [r["value"] for r in rows] == sorted(r["value"] for r in rows)


def test_pruning_and_push_down(act, collected):
    c = encode.compress(act, 150, "range")
    plan = workloads.q4b(act).plan()
    full = chunked.run(plan, c, chunked.ChunkOptions(False, False))
    assert collected(chunked.run(plan, c)) == collected(full) == collected(native.run(plan))
    few, many = chunked.counters(plan, c).first(), chunked.counters(plan, c, chunked.ChunkOptions(False, False)).first()
    assert few["age_tuples"] < many["age_tuples"] and few["values_read"] < many["values_read"] and few["chunks_read"] <= many["chunks_read"]
    assert many["birth_probes"] <= act.df.count() and many["age_tuples"] <= act.df.count()


READ = [
    (Attr("ts").days("1999-01-01", "1999-01-02"), 0), (Attr("k") > 10**6, 0), (Attr("k").between(-5, -1), 0), (Attr("gold") < -0.01, 0), (Attr("gold") == 1e9, 0),
    (Attr("role") == "nobody", 0), (Attr("country").isin("x", "y"), 0), (Attr("country") < "A", 0), (Attr("country") >= "zz", 0), ((Attr("k") < -1) | (Attr("role") == "nobody"), 0),
    (Attr("role") == "r0", None), (Attr("k") >= 0, None), (Attr("gold") > 0.001, None), (Attr("country") <= "NATION_2", None), (~(Attr("k") > 10**6), None), (Attr("role") != "nobody", None), ((Attr("k") < -1) | (Attr("role") == "r0"), None),
]


@pytest.fixture(scope="module")
def pieces(act):
    return encode.compress(act, 100, "range")


@pytest.mark.parametrize("k", range(len(READ)))
def test_pruning_by_birth_conditions(act, pieces, collected, k):
    cond, chunks = READ[k]
    plan = CohortQuery(act).birth("signup", cond).by("role").measure(users=UserCount(), s=Sum("gold")).plan()
    read = chunked.counters(plan, pieces).first()["chunks_read"]
    assert read == 0 if chunks == 0 else read > 0
    assert collected(chunked.run(plan, pieces)) == collected(native.run(plan))


def test_pruning_by_age_conditions(act, pieces, collected):
    """Activities that can't be met are not read; sizes are, so other reports stay right."""
    for cond in (Attr("k") > 10**6, Attr("action") == "nothing", Attr("gold") < -1):
        plan = CohortQuery(act).birth("signup").ages(cond).by("role").measure(n=Count()).plan()
        seen = chunked.counters(plan, pieces).first()
        assert seen["chunks_read"] > 0 and seen["age_tuples"] == 0 and chunked.run(plan, pieces).count() == 0
    plan = CohortQuery(act).birth("signup").ages(Attr("k") > 90).by("role").measure(n=Count()).plan()
    assert collected(chunked.run(plan, pieces)) == collected(native.run(plan))


def test_reads_follow_what_is_needed(act, pieces):
    """Skipped users' tuples are never read, an age bound cuts each block short, and each condition reads what the one before left."""
    total = act.df.count()
    base = chunked.counters(workloads.q1(act).plan(), pieces).first()
    week = chunked.counters(workloads.q7(act, 2).plan(), pieces).first()
    one = chunked.counters(workloads.q5(act, workloads.D1).plan(), pieces, chunked.ChunkOptions(prune=False)).first()
    assert week["age_tuples"] < base["age_tuples"] <= total and one["age_tuples"] < base["age_tuples"] and one["users_skipped"] > 0
    assert one["values_read"] < base["values_read"] < 3 * total
    rare = CohortQuery(act).birth("signup", (Attr("role") == "nobody") & (Attr("city") == "x")).by("country").measure(n=Count()).plan()
    none = chunked.counters(rare, pieces, chunked.ChunkOptions(prune=False)).first()
    born = birth_times(act, "signup").count()
    assert none["values_read"] == none["birth_probes"] + born  # the role of each birth, and nothing of the city


def test_unread_columns_stay_in_the_files(act, pieces):
    plan = chunked.run(workloads.q1(act).plan(), pieces)._jdf.queryExecution().executedPlan().toString()
    scan = next(x for x in plan.split("\n") if "FileScan parquet" in x and "firsts" in x)
    assert pieces.field("ts") + "#" in scan and all(pieces.field(n) + "#" not in scan for n in ("gold", "city", "zone", "k", "event_id")) and "users#" not in scan


def test_user_blocks():
    r = np.random.default_rng(0)
    counts = r.integers(1, 40, 50)
    firsts = np.cumsum(counts) - counts
    actions = r.integers(0, 12, counts.sum()).astype(np.uint64)
    bits, words = pack(actions)
    for code in (0, 3, 11):
        column = chunked.PackedColumn(bits, words, 0, False, None, np.arange(12))
        got = chunked.UserBlocks(firsts, counts).find_births(column, code)
        want = [next((a + k for k in range(n) if actions[a + k] == code), -1) for a, n in zip(firsts, counts, strict=True)]
        assert got.tolist() == want
        needed = sum((w - a + 1) if w >= 0 else n for w, a, n in zip(want, firsts, counts, strict=True))
        assert needed <= column.reads <= 2 * needed + 4 * len(counts)
    assert chunked.UserBlocks(firsts, counts).find_births(column, None).tolist() == [-1] * 50


def test_clustered_needs_no_exchange_by_user(spark, act, collected):
    t = layout.write_clustered(act, "clustered_events", 4)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        df = native.run(workloads.q1(t).plan())
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert "hashpartitioning(user_id" not in plan
        assert collected(df) == collected(native.run(workloads.q1(act).plan()))
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.sql("DROP TABLE clustered_events")


def test_scan_is_narrow_and_filtered(spark, data):
    spark.conf.set("spark.sql.maxMetadataStringLength", "5000")
    try:
        plan = workloads.QUERIES["q3"](spark, data)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.maxMetadataStringLength")
    scans = [x for x in plan.split("\n") if "FileScan parquet" in x and "event_type" in x]
    assert len(scans) >= 2 and all("EqualTo(event_type,purchase)" in x and "props" not in x for x in scans), scans


def test_birth_index_on_disk(spark, act, collected, tmp_path):
    t = layout.write_birth_index(act, str(tmp_path / "index"))
    assert choose(workloads.q1(t).plan()) == "index"
    assert collected(execute(workloads.q4b(t).plan())) == collected(native.run(workloads.q4b(act).plan()))
    half = act.with_df(act.df.where("event_id % 2 = 0")), act.with_df(act.df.where("event_id % 2 = 1"))
    merged = layout.merge_birth_index(layout.birth_index(half[0]), half[1])
    cols = ["action", "user_id", "birth_time", "n"]
    assert collected(merged.select(*cols)) == collected(layout.birth_index(act).select(*cols))


def test_planner(act):
    assert choose(workloads.q1(act).plan()) == "births"
    assert choose(workloads.q1(act).plan(), 0.9) == "window"
    assert choose(workloads.q3(act).plan(), 0.9) == "births"


def test_scaling_invariants(act):
    one = {(r["country"], r["age"]): (r["cohort_size"], r["users"]) for r in native.run(workloads.q1(act).plan()).collect()}
    four = {(r["country"], r["age"]): (r["cohort_size"], r["users"]) for r in native.run(workloads.q1(scale_users(act, 3)).plan()).collect()}
    assert four == {k: (3 * s, 3 * u) for k, (s, u) in one.items()}


def test_measures(act, tmp_path):
    mean, least, most = metrics.time_query(lambda: act.df.select("user_id"), 2)
    assert least <= mean <= most and metrics.normalised({1: 4.0}, 2.0) == {1: 2.0} and metrics.orders(100, 1) == 2
    last = metrics.birth_cdf(act, "signup").orderBy("day").collect()[-1]
    assert last["share"] == 1.0 and last["cumulative"] == birth_times(act, "signup").count()
    act.df.write.parquet(str(tmp_path / "x"))
    assert metrics.storage(act.df.sparkSession.read.parquet(str(tmp_path / "x"))) > 0
    df, seen = metrics.observed(act.df, "tuples")
    metrics.drain(df)
    assert seen.get["rows"] == act.df.count()


def test_block_function(spark, act):
    register(spark)
    act.df.select("user_id", "ts", "action").createOrReplaceTempView("block_input")
    got = spark.sql("SELECT * FROM cohort_blocks(TABLE(block_input) PARTITION BY user_id ORDER BY (ts), 'signup')").collect()
    want = {str(r["user_id"]): r["birth_time"] for r in birth_times(act, "signup").collect()}
    assert {r["user"]: r["birth_time"] for r in got if r["birth_time"]} == want and sum(r["tuples"] for r in got) == act.df.count()


@pytest.mark.parametrize("name", ["q3", "q4"])
def test_view_is_built_from_the_tables_of_the_call(spark, tmp_path, collected, name):
    """A query over the plain view reads the tables, also when one before it has built the same view."""
    source, folder = "/root/testdata/sf0.01", str(tmp_path)
    for table in ("customer", "nation"):
        spark.read.parquet(f"{source}/{table}.parquet").write.parquet(f"{folder}/{table}.parquet")
    all_events, seen = spark.read.parquet(f"{source}/events.parquet"), []
    for share in (1, 2):
        all_events.where(F.col("user_id") % share == 0).write.mode("overwrite").parquet(f"{folder}/events.parquet")
        spark.catalog.refreshByPath(f"{folder}/events.parquet")
        seen.append(collected(workloads.QUERIES[f"mv_{name}"](spark, folder)))
        assert seen[-1] == collected(workloads.QUERIES[name](spark, folder))
    assert seen[0] != seen[1] and seen[1]

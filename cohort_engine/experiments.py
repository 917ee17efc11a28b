"""The experiments: sweeps over birth dates, ages, chunk sizes and scale, systems side by side, and preparation.

``python -m cohort_engine.experiments [folder] [part ...]`` prints a JSON line for each; parts are ``compare``, ``births``, ``ages``, ``scale`` and
``chunks`` (all by default). Times are means of ``RUNS`` runs after a warm-up; what a query reads has been built before."""

from __future__ import annotations

import json
import sys
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import metrics, workloads
from .functions.lineage import fresh_folder
from .operators import baselines, chunked, encode, layout, native
from .schema import ActivityTable
from .sources import tables

RUNS = 5
SCALES = (1, 4, 16, 64)
CHUNK_SIZES = (16_384, 65_536, 262_144, 1_048_576)


def _seconds(make: Callable[[], DataFrame], runs: int = RUNS) -> float:
    metrics.drain(make())
    return round(metrics.time_query(make, runs)[0], 3)


def stored(act: ActivityTable, name: str) -> ActivityTable:
    """The table written out and read again, so that no query makes it anew."""
    spark = act.df.sparkSession
    path = fresh_folder(spark, name)
    act.df.select(*act.schema.columns).write.parquet(path)
    return act.with_df(spark.read.parquet(path))


def birth_sweep(act: ActivityTable, launch: ActivityTable) -> dict:
    """On the launch table with staggered births: Q5 as part of Q1, and on events Q6 as part of Q3, by packed values read and by time, beside
    the share of users born by then."""
    out = {}
    for name, table, action, base, make, days in (
        ("q5", launch, "launch", workloads.q5_launch(launch, "2099-01-01"), workloads.q5_launch, range(0, 32, 4)),
        ("q6", act, "purchase", workloads.q3(act), workloads.q6, (0, 1, 2, 4, 8, 11)),
    ):
        chunks = encode.compress(table, 16_384)
        cdf = {str(r["day"]): r["share"] for r in metrics.birth_cdf(table, action).collect()}
        read = lambda q, c=chunks: chunked.counters(q.plan(), c).first()
        whole, took = read(base), _seconds(lambda b=base, c=chunks: chunked.run(b.plan(), c))
        for d in map(workloads.days_after, days):
            query = make(table, d)
            part = read(query)
            births = max((v for k, v in cdf.items() if k <= d), default=0.0)
            out[f"{name} {d}"] = {
                "births": births, "age_tuples": round(part["age_tuples"] / whole["age_tuples"], 3), "values_read": round(part["values_read"] / whole["values_read"], 3),
                "time": round(_seconds(lambda q=query, c=chunks: chunked.run(q.plan(), c)) / took, 3),
            }
        chunks.drop()
    return out


def age_sweep(act: ActivityTable) -> dict:
    """Q7 as part of Q1 and Q8 as part of Q3, by packed values read and by time."""
    chunks = encode.compress(act, 16_384)
    read = lambda q: chunked.counters(q.plan(), chunks).first()["values_read"]
    took = lambda q: _seconds(lambda: chunked.run(q.plan(), chunks))
    q1, q3 = workloads.q1(act), workloads.q3(act)
    r1, r3, t1, t3 = read(q1), read(q3), took(q1), took(q3)
    out = {}
    for g in (1, 3, 5, 7, 10, 14):
        q7, q8 = workloads.q7(act, g), workloads.q8(act, g)
        out[g] = {"q7_read": round(read(q7) / r1, 3), "q8_read": round(read(q8) / r3, 3), "q7_time": round(took(q7) / t1, 3), "q8_time": round(took(q8) / t3, 3)}
    chunks.drop()
    return out


def compare(act: ActivityTable) -> dict:
    """Q1 to Q4 on every executor."""
    spark = act.df.sparkSession
    raw = fresh_folder(spark, "csv")
    act.df.select(*act.schema.columns).write.csv(raw, header=True)
    rows = tables.read_csv(spark, raw, act.schema, act.df.select(*act.schema.columns).schema)
    view, chunks = baselines.build_view(act, *workloads.VIEW), encode.compress(act, 65_536)
    indexed = layout.write_birth_index(act, fresh_folder(spark, "index"))
    nested = layout.write_nested(act, fresh_folder(spark, "nested"))
    forms = {
        "plain SQL on CSV": lambda q: baselines.run_sql(q(rows).plan()),
        "plain SQL": lambda q: baselines.run_sql(q(act).plan()),
        "plain SQL, pushed": lambda q: baselines.run_sql(q(act).plan(), True),
        "view": lambda q: baselines.run_view(q(act).plan(), view),
        "births": lambda q: native.run(q(act).plan()),
        "births, late": lambda q: native.run(q(act).plan(), options=native.NativeOptions(False, False, False)),
        "window": lambda q: native.run(q(act).plan(), "window"),
        "birth index": lambda q: native.run(q(indexed).plan(), "index"),
        "nested": lambda q: native.run(q(act).plan(), "nested", nested=nested),
        "chunked": lambda q: chunked.run(q(act).plan(), chunks),
    }
    return {name: {n: _seconds(lambda f=f, q=q: f(q)) for n, q in workloads.BENCHMARKS.items()} for name, f in forms.items()}


def scale_sweep(act: ActivityTable, scales: tuple[int, ...] = SCALES, runs: int = RUNS):
    """For each scale the seconds to prepare what executors read, and those of Q1 to Q4."""
    spark = act.df.sparkSession
    for x in scales:
        big = stored(tables.scale_users(act, x), f"x{x}")
        built: dict[str, object] = {}
        prepare = {}
        for name, build in (
            ("wide view", lambda b=big: baselines.build_view(b, *workloads.VIEW)),
            ("chunks", lambda b=big: encode.compress(b)),
            ("birth index", lambda b=big: layout.write_birth_index(b, fresh_folder(spark, "index"))),
            ("clustered table", lambda b=big: layout.write_clustered(b, f"clustered_x{x}", 32, fresh_folder(spark, "clustered"))),
        ):
            t = time.perf_counter()
            built[name] = build()
            prepare[name] = round(time.perf_counter() - t, 2)
        forms = {
            "plain SQL": lambda q, b=big: baselines.run_sql(q(b).plan()),
            "view": lambda q, b=big, k=built: baselines.run_view(q(b).plan(), k["wide view"]),
            "births": lambda q, b=big: native.run(q(b).plan()),
            "birth index": lambda q, k=built: native.run(q(k["birth index"]).plan(), "index"),
            "births, clustered": lambda q, k=built: native.run(q(k["clustered table"]).plan()),
            "chunked": lambda q, b=big, k=built: chunked.run(q(b).plan(), k["chunks"]),
        }
        yield {"scale": x, "rows": big.df.count(), "prepare": prepare, **{name: {n: _seconds(lambda f=f, q=q: f(q), runs) for n, q in workloads.BENCHMARKS.items()} for name, f in forms.items()}}
        spark.sql(f"DROP TABLE clustered_x{x}")


def main(args: list[str]) -> None:
    folder = args[0] if args else "/root/testdata/sf0.1"
    parts = args[1:] or ["compare", "births", "ages", "scale", "chunks"]
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "10g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    act = stored(workloads.events(spark, folder), "events")
    tell = lambda name, value: print(json.dumps({name: value}), flush=True)
    if "compare" in parts:
        tell("compare", compare(act))
    if "births" in parts:
        tell("births", birth_sweep(act, stored(tables.activity_launch(spark, folder, staggered=True), "launch")))
    if "ages" in parts:
        tell("ages", age_sweep(act))
    if "scale" in parts:
        for line in scale_sweep(act):
            tell("scale", line)
    if "chunks" in parts:
        big = stored(tables.scale_users(act, max(SCALES)), "big")
        for line in metrics.chunk_sweep(big, list(CHUNK_SIZES), [workloads.q1, workloads.q3]):
            tell("chunks", line | {"encode": round(line["encode"], 1), "seconds": [round(s, 3) for s in line["seconds"]]})
    spark.stop()


if __name__ == "__main__":
    main(sys.argv[1:])

"""Costs that are measured: time, normalised time, storage, tuples touched, and the birth distribution."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from .operators.core import birth_times
from .schema import ActivityTable


def drain(df: DataFrame) -> None:
    """Runs a query and throws its rows away."""
    df.write.format("noop").mode("overwrite").save()


def time_query(make: Callable[[], DataFrame], runs: int = 5) -> tuple[float, float, float]:
    """Mean, least and most seconds of several runs."""
    took = []
    for _ in range(runs):
        t = time.perf_counter()
        drain(make())
        took.append(time.perf_counter() - t)
    return sum(took) / runs, min(took), max(took)


def time_prepare(build: Callable[[], object]) -> float:
    t = time.perf_counter()
    build()
    return time.perf_counter() - t


def normalised(times: dict[object, float], base: float) -> dict[object, float]:
    """Times of a sweep as parts of a base query's."""
    return {k: t / base for k, t in times.items()}


def orders(slow: float, fast: float) -> float:
    """How many orders of magnitude lie between two times."""
    return math.log10(slow / fast)


def birth_cdf(act: ActivityTable, action: str) -> DataFrame:
    """``day, births, cumulative, share``: users born by each day. As many rows as days."""
    days = birth_times(act, action).groupBy(F.to_date("birth_time").alias("day")).agg(F.count("*").alias("births"))
    upto = Window.orderBy("day").rowsBetween(Window.unboundedPreceding, 0)
    every = Window.orderBy("day").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    out = days.withColumn("cumulative", F.sum("births").over(upto))
    return out.withColumn("share", F.round(F.col("cumulative") / F.sum("births").over(every), 6))


def observed(df: DataFrame, name: str) -> tuple[DataFrame, Observation]:
    """A frame that counts its rows as a query runs over it, without a pass of its own."""
    seen = Observation(name)
    return df.observe(seen, F.count(F.lit(1)).alias("rows")), seen


def storage(df: DataFrame) -> int:
    """Bytes of the files that a stored table is read from."""
    spark = df.sparkSession
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    total = 0
    for file in df.inputFiles():
        path = jvm.org.apache.hadoop.fs.Path(file)
        total += path.getFileSystem(conf).getFileStatus(path).getLen()
    return total


def chunk_sweep(act: ActivityTable, sizes: list[int], makes: list[Callable[[ActivityTable], object]], runs: int = 5) -> list[dict]:
    """Storage, seconds to encode and mean time of queries for each chunk size."""
    from .operators import chunked, encode

    out = []
    for rows in sizes:
        t = time.perf_counter()
        chunks = encode.compress(act, rows)
        built = time.perf_counter() - t
        size = encode.storage(chunks).first()
        seconds = []
        for make in makes:
            query = lambda m=make, c=chunks: chunked.run(m(act).plan(), c)
            drain(query())
            seconds.append(time_query(query, runs)[0])
        out.append({"rows": rows, "chunks": size["chunks"], "bytes": size["bytes"], "files": storage(chunks.chunks), "encode": built, "seconds": seconds})
        chunks.drop()
    return out


def scale_sweep(act: ActivityTable, factors: list[int], make: Callable[[ActivityTable], DataFrame], runs: int = 5) -> dict[int, float]:
    from .sources.tables import scale_users

    return {x: time_query(lambda x=x: make(scale_users(act, x)), runs)[0] for x in factors}

"""Streams of activities: births as they become final, live reports, and weekly means.

A birth is final once the watermark has passed it, as an earlier tuple of the action can't come any more. State is
kept by user: the birth candidate and tuples that wait for it. Tuples behind the watermark are dropped by Spark."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from decimal import Decimal

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.measures import exact
from ..schema import ActivitySchema


def read_stream(spark: SparkSession, path: str, types: T.StructType, files_per_trigger: int | None = None) -> DataFrame:
    """A folder of Parquet files as a stream; types are given."""
    reader = spark.readStream.schema(types)
    return (reader.option("maxFilesPerTrigger", files_per_trigger) if files_per_trigger else reader).parquet(path)


def distinct_activities(stream: DataFrame, schema: ActivitySchema, delay: str) -> DataFrame:
    """Each key once within the watermark."""
    return stream.withWatermark(schema.time, delay).dropDuplicatesWithinWatermark([schema.user, schema.time, schema.action])


def weekly_average(stream: DataFrame, schema: ActivitySchema, action: str, measure: str, delay: str) -> DataFrame:
    """Weekly means; a week is emitted once it is over."""
    weeks = F.window(schema.time, "7 days", "7 days", "3 days")
    agg = stream.where(F.col(schema.action) == action).withWatermark(schema.time, delay).groupBy(weeks.alias("w"))
    dec = F.expr(exact(f"`{measure}`"))
    out = agg.agg(F.round(F.sum(dec).cast("double") / F.count(measure), 6).alias(f"avg_{measure}"))
    return out.select(F.to_date("w.start").alias("week"), f"avg_{measure}")


def sessions(stream: DataFrame, schema: ActivitySchema, gap: str, delay: str) -> DataFrame:
    """Sessions of users: activities at most ``gap`` apart; start, end and activities."""
    agg = stream.withWatermark(schema.time, delay).groupBy(F.session_window(schema.time, gap).alias("s"), F.col(schema.user))
    return agg.agg(F.count("*").alias("activities")).select(schema.user, F.col("s.start").alias("start"), F.col("s.end").alias("end"), "activities")


@dataclass(frozen=True)
class LiveCohorts:
    """A cohort query that runs over a stream: the sum and count of a measure and the users, by cohort and age in days."""

    schema: ActivitySchema
    action: str
    by: str
    measure: str
    delay: str = "1 day"

    def deltas(self, stream: DataFrame) -> DataFrame:
        """``cohort, age, size, total, n, users``: what each user adds; size rows have age 0. To be summed up."""
        s = self.schema
        picked = stream.select(F.col(s.user).alias("user"), F.col(s.time).cast("timestamp").alias("time"), F.col(s.action).alias("action"), F.col(self.by).cast("string").alias("by"), F.expr(exact(f"`{self.measure}`")).alias("value"))
        marked = picked.withWatermark("time", self.delay)
        fn = _stepper(self.action)
        return marked.groupBy("user").applyInPandasWithState(
            fn, "cohort string, age int, size bigint, total decimal(38,12), n bigint, users bigint", "birth bigint, cohort string, waiting string, ages string", "append", GroupStateTimeout.EventTimeTimeout
        )

    def report(self, rows: DataFrame) -> DataFrame:
        """The report from deltas that have been collected in a table."""
        cells = rows.groupBy("cohort", "age").agg(*(F.sum(c).alias(c) for c in ("size", "total", "n", "users")))
        sizes = cells.where("age = 0").select("cohort", F.col("size").alias("cohort_size"))
        out = cells.where("age > 0").join(sizes, "cohort")
        return out.select(F.col("cohort").alias(self.by), "cohort_size", "age", F.round(F.col("total").cast("double"), 6).alias("total"), "n", "users")


_DAY = 86_400_000_000


def _stepper(action: str):
    import json

    def step(key: tuple, frames: Iterable[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        birth, cohort, waiting, ages = state.get if state.exists else (None, None, "[]", "[]")
        wait, seen = json.loads(waiting), set(json.loads(ages))
        for f in frames:
            for t, a, b, c in zip(f["time"], f["action"], f["by"], f["value"], strict=True):
                wait.append([int(pd.Timestamp(t).value // 1000), a, b, None if pd.isna(c) else str(c)])
        mark = state.getCurrentWatermarkMs() * 1000
        if birth is None:
            first = min((w for w in wait if w[1] == action), key=lambda w: w[0], default=None)
            if first is not None and first[0] <= mark:
                birth, cohort = first[0], first[2]
                yield pd.DataFrame([{"cohort": cohort, "age": 0, "size": 1, "total": Decimal(0), "n": 0, "users": 0}])
        if birth is not None:
            cells: dict[int, list] = {}
            for t, _, _, c in wait:
                if t > birth:
                    cell = cells.setdefault((t - birth + _DAY - 1) // _DAY, [Decimal(0), 0])
                    if c is not None:
                        cell[0] += Decimal(c)
                        cell[1] += 1
            wait = []
            if cells:
                yield pd.DataFrame([{"cohort": cohort, "age": g, "size": 0, "total": c, "n": n, "users": int(g not in seen)} for g, (c, n) in sorted(cells.items())])
                seen |= set(cells)
        state.update((birth, cohort, json.dumps(wait), json.dumps(sorted(seen))))
        if birth is None and wait:
            state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs() + 1, min(w[0] for w in wait if w[1] == action) // 1000 + 1 if any(w[1] == action for w in wait) else state.getCurrentWatermarkMs() + 86_400_000))

    return step

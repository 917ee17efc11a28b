"""Physical layouts of an activity table: clustered by user, nested by user, and the birth index."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import ActivityTable


def write_clustered(act: ActivityTable, table: str, buckets: int, path: str | None = None) -> ActivityTable:
    """A table, bucketed by user and sorted by user, time and action: later joins and windows by user need no exchange. It is managed
    by the warehouse, or lies at ``path``."""
    s = act.schema
    spread = act.df.select(*s.columns).repartition(buckets, s.user)
    writer = spread.write.mode("overwrite").format("parquet").bucketBy(buckets, s.user).sortBy(s.user, s.time, s.action)
    (writer.option("path", path) if path else writer).saveAsTable(table)
    return act.with_df(act.df.sparkSession.table(table), layout="clustered", name=table)


def nest(act: ActivityTable) -> DataFrame:
    """``user, n, acts``: a row for each user with their tuples in order of time. Users are taken to fit a task; tables
    with users too large for that keep another layout (``oversized`` finds them)."""
    s = act.schema
    rest = [c for c in dict.fromkeys([s.time, *s.tie_break, s.action, *s.columns]) if c != s.user]
    return act.df.groupBy(s.user).agg(F.count("*").cast("int").alias("n"), F.sort_array(F.collect_list(F.struct(*rest))).alias("acts"))


def oversized(act: ActivityTable, limit: int = 10_000_000) -> DataFrame:
    """Users with more tuples than a nested row or a chunk should hold."""
    return act.df.groupBy(act.schema.user).agg(F.count("*").alias("n")).where(F.col("n") > limit)


def write_nested(act: ActivityTable, path: str) -> DataFrame:
    nest(act).write.mode("overwrite").parquet(path)
    return act.df.sparkSession.read.parquet(path)


def birth_index(act: ActivityTable) -> DataFrame:
    """``action, user, birth_time, birth, n``: the birth tuple of each user for every action, from one pass."""
    s = act.schema
    carried = F.struct(*(F.col(c) for c in dict.fromkeys([s.time, *s.dims, *s.measures, *s.tie_break])))
    order = F.struct(F.col(s.time), *(F.col(t) for t in s.tie_break))
    found = act.df.groupBy(F.col(s.action).alias("action"), F.col(s.user)).agg(F.min_by(carried, order).alias("birth"), F.count("*").alias("n"))
    return found.select("action", s.user, F.col("birth")[s.time].alias("birth_time"), "birth", "n")


def write_birth_index(act: ActivityTable, path: str) -> ActivityTable:
    """The index as Parquet, a folder for each action; returns the table with its index."""
    birth_index(act).repartition(act.schema.user).write.mode("overwrite").partitionBy("action").parquet(path)
    return act.with_df(act.df, birth_index=act.df.sparkSession.read.parquet(path))


def merge_birth_index(index: DataFrame, more: ActivityTable) -> DataFrame:
    """An index after more tuples have come: earlier births win."""
    s = more.schema
    both = index.select("action", s.user, "birth", "n").unionByName(birth_index(more).select("action", s.user, "birth", "n"))
    order = F.struct(F.col("birth")[s.time], *(F.col("birth")[t] for t in s.tie_break))
    out = both.groupBy("action", s.user).agg(F.min_by("birth", order).alias("birth"), F.sum("n").alias("n"))
    return out.select("action", s.user, F.col("birth")[s.time].alias("birth_time"), "birth", "n")

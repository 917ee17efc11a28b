"""A stream that has been read to its end gives what the batch gives."""

from pyspark.sql import functions as F

from cohort_engine.functions.measures import Count, Sum, UserCount
from cohort_engine.operators import native, report
from cohort_engine.plans.algebra import CohortQuery
from cohort_engine.sources.tables import activity_events
from cohort_engine.streaming import live


def _files(spark, act, path, parts=3, tail=True):
    """Activities in order of time, and one far later tuple so that the watermark passes all others."""
    df = act.df.select("user_id", F.col("ts"), "action", "gold", "country", "event_id")
    edges = df.selectExpr(f"percentile_approx(event_id, array({', '.join(str(k / parts) for k in range(1, parts))})) AS q").first()["q"]
    low = -1
    for k, high in enumerate([*edges, 1 << 60]):
        df.where((F.col("event_id") > low) & (F.col("event_id") <= high)).coalesce(1).write.mode("append").parquet(path)
        low = high
    if tail:
        spark.sql("SELECT CAST(-1 AS BIGINT) AS user_id, TIMESTAMP_NTZ'2030-01-01 00:00:00' AS ts, 'end' AS action, 0.0D AS gold, 'nowhere' AS country, CAST(-1 AS BIGINT) AS event_id").coalesce(1).write.mode("append").parquet(path)
    return df.schema


def test_live_cohorts(spark, data, tmp_path, collected):
    act = activity_events(spark, data)
    types = _files(spark, act, str(tmp_path / "in"))
    query = live.LiveCohorts(act.schema, "signup", "country", "gold", "2 days")
    stream = live.read_stream(spark, str(tmp_path / "in"), types, 1)
    deltas = query.deltas(stream)
    out = str(tmp_path / "out")
    deltas.writeStream.format("parquet").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start(out).awaitTermination(300)
    got = collected(query.report(spark.read.parquet(out)))
    plan = CohortQuery(act).birth("signup").by("country").measure(total=Sum("gold"), n=Count("gold"), users=UserCount()).plan()
    assert got == collected(native.run(plan))


def test_weekly_window_over_a_stream(spark, data, tmp_path, collected):
    act = activity_events(spark, data)
    types = _files(spark, act, str(tmp_path / "in"))
    stream = live.read_stream(spark, str(tmp_path / "in"), types, 1).withColumn("ts", F.col("ts").cast("timestamp"))
    weekly = live.weekly_average(stream, act.schema, "purchase", "gold", "1 day")
    (weekly.writeStream.format("memory").queryName("weekly").outputMode("complete").trigger(availableNow=True).start()).awaitTermination(300)
    assert collected(spark.table("weekly")) == collected(report.weekly_average(act, "purchase", "gold"))


def test_duplicates_and_sessions(spark, data, tmp_path):
    act = activity_events(spark, data)
    types = _files(spark, act, str(tmp_path / "in"), tail=False)
    act.df.select(*types.names).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = live.read_stream(spark, str(tmp_path / "in"), types).withColumn("ts", F.col("ts").cast("timestamp"))
    once = live.distinct_activities(stream, act.schema, "60 days")
    once.writeStream.format("memory").queryName("once").trigger(availableNow=True).start().awaitTermination(300)
    assert spark.table("once").count() == act.df.count()
    gaps = live.sessions(stream, act.schema, "6 hours", "1 day")
    gaps.writeStream.format("memory").queryName("gaps").outputMode("complete").trigger(availableNow=True).start().awaitTermination(300)
    assert spark.table("gaps").agg(F.sum("activities")).first()[0] == 2 * act.df.count()

"""What is done with reports: layouts, rates, cubes, drops over age, and presets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.ages import AgeUnit, TimeBin, week_start
from ..functions.measures import Measure, exact
from ..functions.predicates import Pred
from ..plans.algebra import CohortPlan, normalise
from ..schema import ActivityTable
from . import native
from .core import cohort_key, quoted


def pivot_report(report: DataFrame, cohorts: list[str], value: str, ages: list[int]) -> DataFrame:
    """A row for each cohort with its size, a column ``age_<g>`` for each age. Ages are given, so no extra pass finds them."""
    wide = report.groupBy(*cohorts, "cohort_size").pivot("age", ages).agg(F.first(value))
    return wide.select(*cohorts, "cohort_size", *(F.col(str(g)).alias(f"age_{g}") for g in ages))


def retention_rate(report: DataFrame, users: str = "users") -> DataFrame:
    return report.withColumn("rate", F.round(F.col(users) / F.col("cohort_size"), 6))


def weekly_average(act: ActivityTable, action: str, measure: str) -> DataFrame:
    """The plain contrast to a cohort query: a mean by calendar week, whoever the users are."""
    s = act.schema
    week = F.expr(week_start(quoted(s.time))).alias("week")
    mean = F.round(F.sum(F.expr(exact(quoted(measure)))).cast("double") / F.count(measure), 6).alias(f"avg_{measure}")
    return act.df.where(F.col(s.action) == action).groupBy(week).agg(mean)


def weekly_window(act: ActivityTable, action: str, measure: str) -> DataFrame:
    """The same by Spark's time windows, which also work on streams; weeks start on Sunday."""
    s = act.schema
    weeks = F.window(s.time, "7 days", "7 days", "3 days")
    mean = F.round(F.sum(F.expr(exact(quoted(measure)))).cast("double") / F.count(measure), 6).alias(f"avg_{measure}")
    return act.df.where(F.col(s.action) == action).groupBy(weeks.alias("w")).agg(mean).select(F.to_date("w.start").alias("week"), f"avg_{measure}")


def classic_cohort(act: ActivityTable, action: str, ages: Pred | None, bin: str = "week", age_unit: AgeUnit = AgeUnit("week"), **measures: Measure) -> DataFrame:
    """The classic study: cohorts by time of birth, ages in the same unit, no selection of births."""
    return native.run(CohortPlan(act, action, None, ages, (TimeBin(bin),), tuple(measures.items()), age_unit))


def cohort_cube(plan: CohortPlan) -> DataFrame:
    """The report for every subset of the cohort attributes; attributes left out are null and ``grouping_id`` tells which.

    One aggregate makes the states of the finest cells, and one over grouping sets all others from them: a user is in one
    cohort, so states just add up. Sizes don't add up over ages, so they are counted from births, by one cube."""
    plan = normalise(plan)
    names, keys = plan.cohort_names, [f"_k{i}" for i in range(len(plan.by))]
    fine, births = native.fine_cells(plan)
    merged = {f"{n}__{st}": m.merge(st, quoted(f"{n}__{st}")) for n, m in plan.measures for st in m.partial("x")}
    sets = [[*(k for i, k in enumerate(keys) if not g >> (len(keys) - 1 - i) & 1), "age"] for g in range(2 ** len(keys))]
    cells = fine.groupingSets([[F.col(c) for c in kept] for kept in sets], *keys, "age").agg(F.shiftright(F.grouping_id(), 1).alias("_g"), *(F.expr(e).alias(a) for a, e in merged.items()))
    sizes = births.select(*(F.expr(e).alias(f"_s{i}") for i, (_, e) in enumerate(cohort_key(plan.table.schema.time, plan.by))))
    sizes = sizes.cube(*sizes.columns).agg(F.grouping_id().alias("_sg"), F.count("*").alias("cohort_size"))
    match = F.col("_g") == F.col("_sg")
    for i, k in enumerate(keys):
        match = match & F.col(k).eqNullSafe(F.col(f"_s{i}"))
    finished = [F.expr(m.finish({st: quoted(f"{n}__{st}") for st in m.partial("x")})).alias(n) for n, m in plan.measures]
    named = [F.col(k).alias(n) for k, n in zip(keys, names, strict=True)]
    return cells.join(sizes, match).select(*named, F.col("_g").cast("bigint").alias("grouping_id"), "cohort_size", "age", *finished)


def over_age(report: DataFrame, cohorts: list[str], value: str) -> DataFrame:
    """The ageing effect: change of a value from one age to the next in a cohort."""
    w = Window.partitionBy(*cohorts).orderBy("age")
    return report.withColumn("change", F.round(F.col(value) - F.lag(value).over(w), 6))


def over_cohorts(report: DataFrame, cohort: str, value: str) -> DataFrame:
    """The effect of social change: change of a value from one cohort to the next at the same age."""
    w = Window.partitionBy("age").orderBy(cohort)
    return report.withColumn("change", F.round(F.col(value) - F.lag(value).over(w), 6))


def dense(report: DataFrame, cohorts: list[str], ages: list[int], zero: list[str]) -> DataFrame:
    """A row for every cohort of the report and every age; missing measures are zero."""
    grid = report.select(*cohorts, "cohort_size").distinct().withColumn("age", F.explode(F.array(*map(F.lit, ages))))
    return grid.join(report, [*cohorts, "cohort_size", "age"], "left").fillna(0, zero)


def top_cohorts(report: DataFrame, cohorts: list[str], k: int) -> DataFrame:
    """The ``k`` largest cohorts."""
    return report.select(*cohorts, "cohort_size").distinct().orderBy(F.desc("cohort_size"), *cohorts).limit(k)


def approx_user_count(act: ActivityTable, action: str, by: tuple[str, ...], unit: AgeUnit = AgeUnit()) -> DataFrame:
    """Retained users by HyperLogLog sketches: approximate, for dashboards; everything else here is exact."""
    from .core import age_tuples, assign_cohorts

    s = act.schema
    tuples = age_tuples(act, action, unit).select(s.user, "age")
    return tuples.join(assign_cohorts(act, action, by), s.user).groupBy(*by, "age").agg(F.approx_count_distinct(s.user).alias("approx_users"))



"""Births, ages and the three cohort operators, each as a DataFrame transformation.

A user is born at their first tuple with the birth action; the first by time, then by the schema's tie-break. Users
without one are dropped by every operator here. A tuple has an age if it is later than the birth."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.ages import AgeUnit, TimeBin, default_unit, raw_age
from ..functions.measures import Measure
from ..functions.predicates import Pred, birth_attributes, literal, to_sql, uses_age
from ..schema import ActivityTable, CohortSemanticError

BORN = "_born"
BIRTH = "_birth"


def quoted(name: str) -> str:
    return "`" + name.replace("`", "``") + "`"


def birth_times(act: ActivityTable, action: str) -> DataFrame:
    """``user, birth_time``; the aggregate is combined before the shuffle."""
    s = act.schema
    return act.df.where(F.col(s.action) == action).groupBy(s.user).agg(F.min(s.time).alias("birth_time"))


def births(act: ActivityTable, action: str, columns: list[str], cond: Pred | None = None) -> DataFrame:
    """``user, _born, _birth`` with one row for each born user whose birth tuple meets the condition.

    Without attributes to carry, a birth is its time, and a hash aggregate finds it; else the birth tuple is the least by time and tie-break."""
    s = act.schema
    if not set(columns) - {s.time}:
        found = birth_times(act, action).select(s.user, F.col("birth_time").alias(BORN), F.struct(F.col("birth_time").alias(s.time)).alias(BIRTH))
        return found if cond is None else found.where(to_sql(cond, lambda n: born_at(s.time, n)))
    carried = F.struct(*(F.col(c) for c in dict.fromkeys([s.time, *columns])))
    order = F.struct(F.col(s.time), *(F.col(t) for t in s.tie_break))
    found = act.df.where(F.col(s.action) == action).groupBy(s.user).agg(F.min_by(carried, order).alias(BIRTH))
    found = found.select(s.user, F.col(BIRTH)[s.time].alias(BORN), BIRTH)
    return found if cond is None else found.where(to_sql(cond, lambda n: born_at(s.time, n)))


def born_at(time: str, name: str) -> str:
    """An attribute of the birth tuple, as SQL."""
    return BORN if name == time else f"{BIRTH}.{quoted(name)}"


def birth_tuples(act: ActivityTable, action: str) -> DataFrame:
    """The birth tuples themselves, with all columns of the table."""
    s = act.schema
    rest = [c for c in s.columns if c not in (s.user, s.time)]
    found = births(act, action, rest)
    return found.select(*(F.col(c) if c == s.user else F.expr(born_at(s.time, c)).alias(c) for c in s.columns))


def with_age(act: ActivityTable, action: str, unit: AgeUnit | None = None) -> DataFrame:
    """Tuples of born users with ``age_raw`` (microseconds, or ticks) and ``age``; not positive before and at birth."""
    s = act.schema
    unit = unit or default_unit(s)
    joined = act.df.join(birth_times(act, action).withColumnRenamed("birth_time", BORN), s.user)
    time = quoted(s.time)
    raw = f"{time} - {BORN}" if s.time_kind == "tick" else raw_age(time, BORN)
    return joined.select(*s.columns, F.expr(raw).cast("bigint").alias("age_raw"), F.expr(unit.sql(time, BORN)).alias("age"))


def age_tuples(act: ActivityTable, action: str, unit: AgeUnit | None = None) -> DataFrame:
    return with_age(act, action, unit).where("age_raw > 0")


def birth_select(act: ActivityTable, action: str, cond: Pred | None = None) -> ActivityTable:
    """All tuples, also earlier ones, of users whose birth tuple meets the condition."""
    s = act.schema
    keep = births(act, action, sorted(s.columns), cond).select(s.user)
    return act.with_df(act.df.join(keep, s.user, "left_semi"))


def age_select(act: ActivityTable, action: str, cond: Pred | None = None, unit: AgeUnit | None = None) -> ActivityTable:
    """Birth tuples, and later tuples that meet the condition, which may name ``Birth(attribute)`` and ``AGE``."""
    s, unit = act.schema, unit or default_unit(act.schema)
    joined = act.df.join(births(act, action, sorted({*birth_attributes(cond), *s.tie_break} - {s.time})), s.user)
    own = lambda n: quoted(n)
    age = unit.sql(quoted(s.time), BORN) if uses_age(cond) else None
    is_birth = " AND ".join([f"{quoted(s.time)} = {BORN}", f"{quoted(s.action)} = {literal(action)}", *(f"{quoted(t)} <=> {born_at(s.time, t)}" for t in s.tie_break)])
    later = f"({quoted(s.time)} > {BORN} AND {to_sql(cond, own, lambda n: born_at(s.time, n), age)})"
    return act.with_df(joined.where(f"({is_birth}) OR {later}").select(*act.df.columns))


def cohort_key(time: str, by: tuple[str | TimeBin, ...]) -> list[tuple[str, str]]:
    """Names and SQL of the cohort columns, over a births frame."""
    return [(b.name, b.sql(BORN)) if isinstance(b, TimeBin) else (b, born_at(time, b)) for b in by]


def assign_cohorts(act: ActivityTable, action: str, by: tuple[str | TimeBin, ...], cond: Pred | None = None) -> DataFrame:
    """``user`` and the cohort columns, one row for each qualified user."""
    s = act.schema
    attrs = {b for b in by if isinstance(b, str)} - {s.time}
    found = births(act, action, sorted(attrs | (set(s.columns) if cond is not None else set())), cond)
    return found.select(s.user, *(F.expr(e).alias(n) for n, e in cohort_key(s.time, by)))


def cohort_sizes(act: ActivityTable, action: str, by: tuple[str | TimeBin, ...], cond: Pred | None = None) -> DataFrame:
    """Users by cohort. Births hold a user once, so this is a plain count."""
    names = [b.name if isinstance(b, TimeBin) else b for b in by]
    return assign_cohorts(act, action, by, cond).groupBy(*names).agg(F.count("*").alias("cohort_size"))


def cohort_aggregate(act: ActivityTable, action: str, by: tuple[str | TimeBin, ...], unit: AgeUnit | None = None, **measures: Measure) -> DataFrame:
    from ..plans.algebra import CohortAggregate, Scan
    from .native import run

    return run(CohortAggregate(Scan(act), action, tuple(by), tuple(measures.items()), unit))


def union_activities(a: ActivityTable, b: ActivityTable) -> ActivityTable:
    """Tuples of both tables, which share a schema."""
    if a.schema != b.schema:
        raise CohortSemanticError("activity tables with different schemas can't be united")
    return a.with_df(a.df.select(*a.schema.columns).unionByName(b.df.select(*b.schema.columns)), layout="raw", birth_index=None)


def intersect_born(a: ActivityTable, b: ActivityTable, action: str) -> ActivityTable:
    """Tuples of the first table whose users are born in both."""
    s = a.schema
    other = birth_times(b, action).select(F.col(b.schema.user).alias(s.user))
    mine = birth_times(a, action).select(s.user).join(other, s.user, "left_semi")
    return a.with_df(a.df.join(mine, s.user, "left_semi"), layout="raw", birth_index=None)


def join_births(a: ActivityTable, b: ActivityTable, action: str, columns: tuple[str, ...], prefix: str = "other_") -> ActivityTable:
    """The join of two activity tables by born users: tuples of the first, of users whom the second sees born, with the time and
    attributes of that birth as dimensions ``other_time, other_...``."""
    s, t = a.schema, b.schema
    other = births(b, action, sorted(columns))
    named = {f"{prefix}time": BORN, **{f"{prefix}{c}": born_at(t.time, c) for c in columns}}
    other = other.select(F.col(t.user).alias("_u"), *(F.expr(e).alias(n) for n, e in named.items()))
    joined = a.df.join(other, F.col(s.user) == F.col("_u")).drop("_u")
    return a.with_df(joined, schema=replace(s, dims=(*s.dims, *named)), layout="raw", birth_index=None)


def never_born(act: ActivityTable, action: str) -> DataFrame:
    """Users without a birth."""
    s = act.schema
    return act.df.select(s.user).distinct().join(birth_times(act, action), s.user, "left_anti")

"""The native executor: births first, then only the activities of qualified users.

Four physical forms give the same rows. ``births`` joins births with activities (the default: predicates on the tuple
alone go to the Parquet scan, and a hot user's activities can be split, as births hold each user once); ``window`` reads
the table once with a window over users; ``index`` takes births from a birth index; ``nested``
filters rows that hold a user each before their tuples are unfolded."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.predicates import age_limit, birth_attributes, day_range, split, to_sql, uses_age
from ..plans.algebra import CohortPlan, normalise
from ..schema import CohortSemanticError
from .core import BIRTH, BORN, births, born_at, cohort_key, quoted


@dataclass(frozen=True)
class NativeOptions:
    """Switches of the ablation. All on by default."""

    push_birth: bool = True
    push_ages: bool = True
    local_usercount: bool = True


def _qualified(plan: CohortPlan) -> DataFrame:
    return births(plan.table, plan.action, plan.birth_columns, plan.birth)


def _from_index(plan: CohortPlan) -> DataFrame:
    index, s = plan.table.birth_index, plan.table.schema
    if index is None:
        raise CohortSemanticError("the table has no birth index")
    found = index.where(F.col("action") == plan.action).select(s.user, F.col("birth_time").alias(BORN), F.col("birth").alias(BIRTH))
    return found.where(to_sql(plan.birth, lambda n: born_at(s.time, n)))


def _later(plan: CohortPlan, joined: DataFrame, cond) -> DataFrame:
    """Tuples after birth that meet the condition, as ``user, cohort columns, age`` and the measures' attributes."""
    s = plan.table.schema
    time, birth = quoted(s.time), lambda n: born_at(s.time, n)
    joined = joined.where(f"{time} > {BORN}")
    bound = plan.age_unit.latest(BORN, age_limit(cond)) if age_limit(cond) is not None else None
    if bound:
        joined = joined.where(f"{time} <= {bound}")
    # a distinct prefix keeps cohort columns apart from attributes of the same name
    made = joined.select(
        F.col(s.user).alias("_user"),
        F.expr(plan.age_unit.sql(time, BORN)).alias("age"),
        *(F.expr(e).alias(f"_k{i}") for i, (_, e) in enumerate(cohort_key(s.time, plan.by))),
        *(F.col(c).alias(f"_a_{c}") for c in sorted({*plan.age_columns, s.time, s.user})),
        *(F.expr(birth(n)).alias(f"_b_{n}") for n in sorted(birth_attributes(cond))),
    )
    out = made.where("age > 0")
    return out if cond is None else out.where(to_sql(cond, lambda n: quoted(f"_a_{n}"), lambda n: quoted(f"_b_{n}"), "age"))


def _cells(plan: CohortPlan, tuples: DataFrame, local_usercount: bool = True) -> DataFrame:
    """``_k0, _k1, ..., age`` and the states of the measures, ``<name>__<state>``."""
    keys = [f"_k{i}" for i in range(len(plan.by))]
    plain = [(n, m) for n, m in plan.measures if m.kind != "usercount"]
    users = [n for n, m in plan.measures if m.kind == "usercount"]
    aggs = {f"{n}__{st}": F.expr(e) for n, m in plain for st, e in m.partial(quoted(f"_a_{m.attr}") if m.attr else "1").items()}
    if not users:
        return tuples.groupBy(*keys, "age").agg(*([e.alias(a) for a, e in aggs.items()] or [F.count("*").alias("_n")]))
    if local_usercount:
        merged = {f"{n}__{st}": F.expr(m.merge(st, quoted(f"{n}__{st}"))) for n, m in plain for st in m.partial("x")}
        each = tuples.groupBy("_user", *keys, "age").agg(F.count("*").alias("_n"), *(e.alias(a) for a, e in aggs.items()))
        return each.groupBy(*keys, "age").agg(*(F.count("*").alias(f"{n}__u") for n in users), *(e.alias(a) for a, e in merged.items()))
    return tuples.groupBy(*keys, "age").agg(*(F.count_distinct("_user").alias(f"{n}__u") for n in users), *(e.alias(a) for a, e in aggs.items()), F.count("*").alias("_n"))


def _report(plan: CohortPlan, tuples: DataFrame, qualified: DataFrame, local_usercount: bool = True) -> DataFrame:
    """Aggregates by cohort and age, and the sizes of the cohorts beside them."""
    s = plan.table.schema
    keys = [f"_k{i}" for i in range(len(plan.by))]
    cells = _cells(plan, tuples, local_usercount)
    sizes = qualified.select(*(F.expr(e).alias(f"_s{i}") for i, (_, e) in enumerate(cohort_key(s.time, plan.by))), F.lit(1).alias("_one"))
    sizes = sizes.groupBy("_one", *(f"_s{i}" for i in range(len(keys)))).agg(F.count("*").alias("cohort_size"))
    cells = cells.withColumn("_c", F.lit(1))
    match = F.col("_c") == F.col("_one")
    for i, k in enumerate(keys):
        match = match & F.col(k).eqNullSafe(F.col(f"_s{i}"))
    out = cells.join(sizes, match)
    finished = [F.expr(m.finish({st: quoted(f"{n}__{st}") for st in m.partial("x")})).alias(n) for n, m in plan.measures]
    named = [F.col(k).alias(n) for k, n in zip(keys, plan.cohort_names, strict=True)]
    out = out.select(*named, F.col("cohort_size").cast("bigint").alias("cohort_size"), F.col("age").cast("int").alias("age"), *finished)
    return out.select(*plan.columns) if plan.columns else out


def _columns(plan: CohortPlan) -> list[str]:
    s = plan.table.schema
    return list(dict.fromkeys([s.user, s.time, *plan.age_columns]))


def _born_activities(plan: CohortPlan, qualified: DataFrame, options: NativeOptions) -> DataFrame:
    """Tuples of qualified users after birth. Conditions on the tuple alone go to its scan, and so do bounds of its time: no tuple
    is older than the first day of birth, nor younger than the last day and the last age."""
    s = plan.table.schema
    own, rest = split(plan.ages)
    acts = plan.table.df.select(*dict.fromkeys([*_columns(plan), s.action]))
    if options.push_ages and own is not None:
        acts = acts.where(to_sql(own, quoted))
    kind = plan.table.df.schema[s.time].dataType
    first, last = day_range(plan.birth, s.time) if options.push_ages and isinstance(kind, T.TimestampType | T.TimestampNTZType) else (None, None)
    if first is not None:
        acts = acts.where(F.col(s.time) >= F.lit(first).cast("date").cast(kind))
    limit = age_limit(plan.ages)
    if last is not None and limit is not None and (latest := plan.age_unit.latest(f"CAST(DATE'{last}' + INTERVAL 1 DAY AS {kind.simpleString()})", limit)):
        acts = acts.where(f"{quoted(s.time)} <= {latest}")
    return _later(plan, acts.join(qualified, s.user), rest if options.push_ages else plan.ages)


def _births_form(plan: CohortPlan, qualified: DataFrame, options: NativeOptions) -> DataFrame:
    return _report(plan, _born_activities(plan, qualified, options), qualified, options.local_usercount)


def fine_cells(plan: CohortPlan) -> tuple[DataFrame, DataFrame]:
    """States of the measures by cohort and age, and the births, for reports that go on from there."""
    plan = normalise(plan)
    qualified = _qualified(plan)
    return _cells(plan, _born_activities(plan, qualified, NativeOptions())), qualified


def _late_births(plan: CohortPlan, options: NativeOptions) -> DataFrame:
    """Without push-down: all born users' tuples are joined and aged, and the birth condition comes last."""
    s = plan.table.schema
    every = births(plan.table, plan.action, plan.birth_columns)
    acts = plan.table.df.select(*dict.fromkeys([*_columns(plan), s.action]))
    late = to_sql(plan.birth, lambda n: born_at(s.time, n))
    joined = acts.join(every, s.user).withColumn("_ok", F.expr(late))
    tuples = _later(plan, joined.where("_ok"), plan.ages)
    return _report(plan, tuples, every.where(late), options.local_usercount)


def _window_form(plan: CohortPlan, options: NativeOptions) -> DataFrame:
    s = plan.table.schema
    is_birth = F.col(s.action) == plan.action
    order = F.struct(F.col(s.time), *(F.col(t) for t in s.tie_break))
    carried = F.struct(*(F.col(c) for c in dict.fromkeys([s.time, *plan.birth_columns])))
    user = Window.partitionBy(s.user)
    acts = plan.table.df.select(*dict.fromkeys([*_columns(plan), s.action, *s.tie_break, *plan.birth_columns]))
    full = acts.withColumn(BIRTH, F.min_by(F.when(is_birth, carried), F.when(is_birth, order)).over(user))
    full = full.withColumn(BORN, F.col(BIRTH)[s.time]).where(f"{BORN} IS NOT NULL").where(to_sql(plan.birth, lambda n: born_at(s.time, n)))
    at_birth = is_birth & (F.col(s.time) == F.col(BORN))
    first = full.where(at_birth).withColumn("_rank", F.row_number().over(user.orderBy(s.time, *s.tie_break))).where("_rank = 1").select(s.user, BORN, BIRTH)
    return _report(plan, _later(plan, full, plan.ages), first, options.local_usercount)


def _nested_form(plan: CohortPlan, nested: DataFrame, options: NativeOptions) -> DataFrame:
    """Rows hold a user each: births are found inside the row, and rows that don't qualify go before they are unfolded."""
    s = plan.table.schema
    order = [s.time, *s.tie_break]
    mine = F.filter("acts", lambda a: a[s.action] == plan.action)
    # acts are sorted by time, so the first of the action is the birth unless ties say otherwise
    carried = F.array_min(F.transform(mine, lambda a: F.struct(*(a[c].alias(f"o{i}") for i, c in enumerate(order)), a.alias("t"))))["t"]
    found = nested.withColumn(BIRTH, carried).where(f"{BIRTH} IS NOT NULL").withColumn(BORN, F.col(BIRTH)[s.time]).where(to_sql(plan.birth, lambda n: born_at(s.time, n)))
    own, rest = split(plan.ages)
    wanted = dict.fromkeys(c for c in [*_columns(plan), s.action] if c != s.user)
    later = F.filter("acts", lambda a: a[s.time] > F.col(BORN))
    flat = found.select(s.user, BORN, BIRTH, F.explode(later).alias("a")).select(s.user, BORN, BIRTH, *(F.col("a")[c].alias(c) for c in wanted))
    if own is not None:
        flat = flat.where(to_sql(own, quoted))
    assert not (uses_age(own) or birth_attributes(own))
    return _report(plan, _later(plan, flat, rest), found.select(s.user, BORN, BIRTH), options.local_usercount)


def run(plan, form: str = "births", options: NativeOptions = NativeOptions(), nested: DataFrame | None = None) -> DataFrame:
    """The report of a plan: cohort columns, ``cohort_size, age`` and measures."""
    plan = normalise(plan)
    if form == "window":
        return _window_form(plan, options)
    if form == "nested":
        from .layout import nest

        return _nested_form(plan, nested if nested is not None else nest(plan.table), options)
    if form == "index":
        return _births_form(plan, _from_index(plan), options)
    if form != "births":
        raise CohortSemanticError(f"no form {form!r}")
    return _births_form(plan, _qualified(plan), options) if options.push_birth else _late_births(plan, options)

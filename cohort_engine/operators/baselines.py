"""The two baselines: plain SQL joins, and materialised views of births.

Plain SQL is left as a user would write it: births, then the whole table joined twice, users counted with DISTINCT and the
birth condition last (or, with ``push``, moved into the births by hand). A view stores each tuple with the birth
time and birth attributes of its user, for one birth action or several."""

from __future__ import annotations


from pyspark.sql import DataFrame

from ..functions.lineage import cut, fresh_folder
from ..functions.predicates import literal, to_sql
from ..plans.algebra import CohortPlan, normalise
from ..schema import ActivityTable
from .core import quoted


def _key(plan: CohortPlan, birth) -> list[tuple[str, str]]:
    return [(b.name, b.sql(birth(plan.table.schema.time))) if not isinstance(b, str) else (b, birth(b)) for b in plan.by]


def _outer(plan: CohortPlan, rows: str, births_of: str, born: str, birth, where: str, sizes_where: str) -> str:
    """The final query over a relation ``rows`` whose tuples carry birth attributes."""
    s = plan.table.schema
    time = quoted(s.time)
    age = plan.age_unit.sql(time, born)
    key = _key(plan, birth)
    own = {f"{n}__{st}": e for n, m in plan.measures if m.kind != "usercount" for st, e in m.partial(f"a.{quoted(m.attr)}" if m.attr else "1").items()}
    users = {f"{n}__u": f"count(DISTINCT a.{quoted(s.user)})" for n, m in plan.measures if m.kind == "usercount"}
    keys = "".join(f"{e} AS _k{i}, " for i, (_, e) in enumerate(key))
    names = "".join(f"_k{i}, " for i in range(len(key)))
    match = " AND ".join([f"a._k{i} <=> z._k{i}" for i in range(len(key))] or ["TRUE"])
    finish = ", ".join(f"{m.finish({st: quoted(f'{n}__{st}') for st in m.partial('x')})} AS {quoted(n)}" for n, m in plan.measures)
    states = "".join(f", {e} AS {quoted(a)}" for a, e in {**own, **users}.items())
    attrs = "".join(f", {quoted(c)}" for c in dict.fromkeys([s.user, *plan.age_columns]))
    return f"""
      SELECT {"".join(f"_k{i} AS {quoted(n)}, " for i, (n, _) in enumerate(key))}CAST(cohort_size AS BIGINT) AS cohort_size, age, {finish}
      FROM (SELECT {"".join(f"a._k{i}, " for i in range(len(key)))}z.cohort_size, a.age{states}
            FROM (SELECT {keys}{age} AS age{attrs} FROM {rows} WHERE {time} > {born} AND {where}) a
            JOIN (SELECT {names}count(DISTINCT _u) AS cohort_size FROM (SELECT {keys}{quoted(s.user)} AS _u FROM {births_of} WHERE {sizes_where}) q
                  {"GROUP BY " + names[:-2] if key else ""}) z ON {match}
            WHERE a.age > 0 GROUP BY {"".join(f"a._k{i}, " for i in range(len(key)))}z.cohort_size, a.age) r"""


def to_sql_text(plan: CohortPlan, view: str, push: bool = False) -> str:
    """The plain-SQL form of a plan over a table or view of activities."""
    s = plan.table.schema
    user, time, action = quoted(s.user), quoted(s.time), quoted(s.action)
    birth = lambda n: "_bt" if n == s.time else quoted(f"_b_{n}")
    carried = "".join(f", d.{quoted(c)} AS {quoted(f'_b_{c}')}" for c in plan.birth_columns)
    passed = "".join(f", b.{quoted(f'_b_{c}')}" for c in plan.birth_columns)
    first = "".join(f", {quoted(t)}" for t in s.tie_break)
    at_birth = to_sql(plan.birth, birth)
    late = "TRUE" if push else at_birth
    ages = to_sql(plan.ages, quoted, birth, plan.age_unit.sql(time, "_bt"))
    outer = _outer(plan, "cohort_t", "birth_b", "_bt", birth, f"{late} AND {ages}", late)
    return f"""
    WITH birth_t AS (SELECT {user} AS _u0, min({time}) AS _bt FROM {view} WHERE {action} = {literal(plan.action)} GROUP BY {user}),
    birth_d AS (SELECT d.{user}, t._bt{carried}, row_number() OVER (PARTITION BY d.{user} ORDER BY d.{time}{first.replace(", ", ", d.")}) AS _rank
                FROM {view} d JOIN birth_t t ON d.{user} = t._u0 AND d.{time} = t._bt WHERE d.{action} = {literal(plan.action)}),
    birth_b AS (SELECT * FROM birth_d WHERE _rank = 1 AND {at_birth if push else "TRUE"}),
    cohort_t AS (SELECT d.*, b._bt{passed} FROM {view} d JOIN birth_b b ON d.{user} = b.{user})
    {outer}"""


def run_sql(plan, push: bool = False) -> DataFrame:
    plan = normalise(plan)
    view = f"_activities_{abs(hash((plan.table.name, id(plan.table.df))))}"
    plan.table.df.createOrReplaceTempView(view)
    out = plan.table.df.sparkSession.sql(to_sql_text(plan, view, push))
    return out.select(*plan.columns) if plan.columns else out


def build_view(act: ActivityTable, actions: list[str], attrs: list[str] | None = None, table: str | None = None, buckets: int = 8) -> DataFrame:
    """Every tuple with ``_bt_<action>`` and ``_b_<action>_<attribute>`` for each birth action: two joins an action.

    ``table``: a name under which the view is stored in the shared folder, clustered: bucketed by user and sorted by user and time; without
    one it is kept as a checkpoint."""
    s = act.schema
    attrs = list(s.dims if attrs is None else attrs)
    spark = act.df.sparkSession
    act.df.select(*s.columns).createOrReplaceTempView("_mv_source")
    user, time, action = quoted(s.user), quoted(s.time), quoted(s.action)
    first = "".join(f", d.{quoted(t)}" for t in s.tie_break)
    out = act.df.select(*s.columns)
    for e in actions:
        born = spark.sql(f"""
            SELECT {user}, _bt AS {quoted(f"_bt_{e}")}{"".join(f", {quoted(f'_b_{e}_{a}')}" for a in attrs)} FROM (
              SELECT d.{user}, t._bt{"".join(f", d.{quoted(a)} AS {quoted(f'_b_{e}_{a}')}" for a in attrs)},
                     row_number() OVER (PARTITION BY d.{user} ORDER BY d.{time}{first}) AS _rank
              FROM _mv_source d JOIN (SELECT {user} AS _u0, min({time}) AS _bt FROM _mv_source WHERE {action} = {literal(e)} GROUP BY {user}) t
              ON d.{user} = t._u0 AND d.{time} = t._bt WHERE d.{action} = {literal(e)}) WHERE _rank = 1""")
        out = out.join(born, s.user, "left")
    if table is None:
        return cut(out)
    out.repartition(buckets, s.user).write.mode("overwrite").format("parquet").bucketBy(buckets, s.user).sortBy(s.user, s.time).option("path", fresh_folder(spark, "view")).saveAsTable(table)
    return spark.table(table)


def run_view(plan, view: DataFrame, merged: bool = False) -> DataFrame:
    """A plan over a view that has its birth action. ``merged``: both selections in one WHERE, as one sub-query."""
    plan = normalise(plan)
    s, e = plan.table.schema, plan.action
    birth = lambda n: quoted(f"_bt_{e}") if n == s.time else quoted(f"_b_{e}_{n}")
    born = quoted(f"_bt_{e}")
    at_birth = f"{born} IS NOT NULL AND {to_sql(plan.birth, birth)}"
    ages = to_sql(plan.ages, quoted, birth, plan.age_unit.sql(quoted(s.time), born))
    is_birth = f"({quoted(s.time)} = {born} AND {quoted(s.action)} = {literal(e)})"
    name = f"_mv_{abs(hash((e, id(view))))}"
    view.createOrReplaceTempView(name)
    head = f"WITH birth_view AS (SELECT * FROM {name} WHERE {at_birth}), age_view AS (SELECT * FROM birth_view WHERE {is_birth} OR {ages})"
    if merged:
        head = f"WITH birth_view AS (SELECT * FROM {name} WHERE {at_birth}), age_view AS (SELECT * FROM {name} WHERE {at_birth} AND ({is_birth} OR {ages}))"
    out = view.sparkSession.sql(head + _outer(plan, "age_view", "birth_view", born, birth, ages, "TRUE"))
    return out.select(*plan.columns) if plan.columns else out



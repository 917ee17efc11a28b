"""SQL for DuckDB that gives the rows of the workload queries, written from the definitions and not from the engine."""

from __future__ import annotations

EVENTS = """act AS (
  SELECT e.user_id AS u, e.ts AS t, e.event_type AS e, e.value AS gold, CAST(regexp_extract(e.props, '"k": *([0-9]+)', 1) AS INTEGER) AS k,
         'r' || (CAST(regexp_extract(e.props, '"k": *([0-9]+)', 1) AS INTEGER) % 4) AS role, n.n_name AS country, c.c_mktsegment AS city, e.event_id AS tie
  FROM events e JOIN customer c ON e.user_id = c.c_custkey JOIN nation n ON c.c_nationkey = n.n_nationkey)"""
_FIRST = "row_number() OVER (PARTITION BY u ORDER BY t, tie)"
LAUNCH = EVENTS.replace("act AS", "act0 AS") + f", act AS (SELECT * REPLACE (CASE WHEN {_FIRST} = 1 THEN 'launch' ELSE e END AS e) FROM act0)"
STAGGERED = EVENTS.replace("act AS", "act0 AS") + f", act AS (SELECT * REPLACE (CASE WHEN {_FIRST} = 1 THEN 'launch' ELSE e END AS e, t + to_days(CAST((u * 7) % 20 AS INTEGER)) AS t) FROM act0)"
ORDERS = """act AS (
  SELECT o.o_custkey AS u, o.o_orderdate AS t, o.o_orderstatus AS e, o.o_totalprice AS price, o.o_orderpriority AS prio, n.n_name AS country, o.o_orderkey AS tie
  FROM orders o JOIN customer c ON o.o_custkey = c.c_custkey JOIN nation n ON c.c_nationkey = n.n_nationkey)"""
LINEITEM = """act AS (
  SELECT o.o_custkey AS u, l.l_shipdate AS t, l.l_returnflag AS e, l.l_extendedprice AS price, n.n_name AS country,
         row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice) AS tie
  FROM lineitem l JOIN orders o ON l.l_orderkey = o.o_orderkey JOIN customer c ON o.o_custkey = c.c_custkey JOIN nation n ON c.c_nationkey = n.n_nationkey)"""
TALKS = "act AS (SELECT conv_id AS u, turn AS t, role AS e, length(text) AS chars, 0 AS tie FROM conversations)"

DAY = "CAST((epoch_us(a.t) - epoch_us(b.t) + 86399999999) // 86400000000 AS INTEGER)"
WEEK = "CAST((epoch_us(a.t) - epoch_us(b.t) + 604799999999) // 604800000000 AS INTEGER)"
MONTH = "CAST(12 * (year(a.t) - year(b.t)) + month(a.t) - month(b.t) + CASE WHEN epoch_us(a.t) - epoch_us(date_trunc('month', a.t)) > epoch_us(b.t) - epoch_us(date_trunc('month', b.t)) THEN 1 ELSE 0 END AS INTEGER)"
TICK = "CAST(a.t - b.t AS INTEGER)"
SUNDAY = "CAST(b.t AS DATE) - CAST(dayofweek(b.t) AS INTEGER)"
# sums over the raw doubles, with their errors carried along, and rounded at the end only
AVG = "round(round(fsum({0}), 6) / count({0}), 6)"
SUM = "round(fsum({0}), 6)"
USERS = "count(DISTINCT a.u)"


def cohort(act: str, action: str, by: dict[str, str], measures: dict[str, str], birth: str = "TRUE", ages: str = "TRUE", age: str = DAY) -> str:
    """The report: ``by`` and conditions over ``b`` (the birth tuple) and ``a`` (a later one)."""
    keys = "".join(f"{e} AS {n}, " for n, e in by.items())
    names = "".join(f"{n}, " for n in by)
    same = " AND ".join([f"x.{n} IS NOT DISTINCT FROM z.{n}" for n in by] or ["TRUE"])
    outs = ", ".join(f"{e} AS {n}" for n, e in measures.items())
    groups = ", ".join(str(i + 1) for i in range(len(by) + 1))
    return f"""WITH {act},
    born AS (SELECT * FROM (SELECT *, {_FIRST} AS place FROM act WHERE e = '{action}') WHERE place = 1),
    fit AS (SELECT * FROM born b WHERE {birth}),
    sizes AS (SELECT {keys}count(*) AS cohort_size FROM fit b {"GROUP BY ALL" if by else ""}),
    cells AS (SELECT {keys}{age} AS age, {outs} FROM act a JOIN fit b ON a.u = b.u AND a.t > b.t WHERE {age} > 0 AND {ages} GROUP BY {groups})
    SELECT {"".join(f"x.{n}, " for n in by)}CAST(z.cohort_size AS BIGINT) AS cohort_size, x.age, {", ".join(f"x.{m}" for m in measures)} FROM cells x JOIN sizes z ON {same}"""


def _days(first: str, last: str) -> str:
    return f"CAST(b.t AS DATE) BETWEEN DATE '{first}' AND DATE '{last}'"


def build() -> dict[str, str]:
    from .workloads import COUNTRIES, D1, days_after

    country, users, avg = {"country": "b.country"}, {"users": USERS}, {"avg_gold": AVG.format("a.gold")}
    bought = "a.e = 'purchase'"
    listed = ", ".join(f"'{c}'" for c in COUNTRIES)
    q1 = cohort(EVENTS, "signup", country, users)
    q2 = cohort(EVENTS, "signup", country, users, _days("2024-01-02", "2024-01-04"))
    q3 = cohort(EVENTS, "purchase", country, avg, ages=bought)
    q4 = cohort(EVENTS, "purchase", country, avg, f"{_days('2024-01-01', '2024-01-05')} AND b.role = 'r0' AND b.country IN ({listed})", f"{bought} AND a.country = b.country")
    q4b = cohort(EVENTS, "purchase", country, avg, f"{_days('2024-01-01', '2024-01-05')} AND b.role = 'r0'", f"{bought} AND a.role = b.role")
    q5 = lambda d2: cohort(EVENTS, "signup", country, users, _days(D1, d2))
    q6 = lambda d2: cohort(EVENTS, "purchase", country, avg, _days(D1, d2), bought)
    q7 = lambda g: cohort(EVENTS, "signup", country, users, ages=f"{DAY} < {g}")
    q8 = lambda g: cohort(EVENTS, "purchase", country, avg, ages=f"{bought} AND {DAY} < {g}")
    sweep = lambda f, values, name, lit: " UNION ALL ".join(f"SELECT *, {lit(v)} AS {name} FROM ({f(v)})" for v in values)
    quoted, plain = (lambda v: f"'{v}'"), str
    ex1 = cohort(EVENTS, "signup", country, {"spent": SUM.format("a.gold")}, "b.role = 'r0'", bought)
    every = cohort(EVENTS, "signup", {"country": "b.country", "birth_week": SUNDAY}, {"s": SUM.format("a.gold"), "a": AVG.format("a.gold"), "n": "count(*)", "lo": "min(a.gold)", "hi": "CAST(max(a.k) AS DOUBLE)", "users": USERS})
    classic = cohort(EVENTS, "signup", {"birth_week": SUNDAY}, avg, ages=bought, age=WEEK)
    orders = cohort(ORDERS, "F", country, {"total": SUM.format("a.price")}, ages="a.e = 'F'", age=MONTH)
    born = lambda e: f"born AS (SELECT * FROM (SELECT *, {_FIRST} AS place FROM act WHERE e = '{e}') WHERE place = 1)"
    weekly = f"WITH {EVENTS} SELECT CAST(t AS DATE) - CAST(dayofweek(t) AS INTEGER) AS week, {AVG.format('gold')} AS avg_gold FROM act WHERE e = 'purchase' GROUP BY 1"
    cube_cells = f"WITH {EVENTS}, {born('signup')}, x AS (SELECT b.country AS country, b.role AS role, {DAY} AS age, a.gold AS gold, a.u AS u FROM act a JOIN born b ON a.u = b.u AND a.t > b.t WHERE {bought})"
    cube = f"""{cube_cells},
      cells AS (SELECT country, role, CAST(grouping(country, role) AS BIGINT) AS grouping_id, age, {SUM.format('gold')} AS s, {AVG.format('gold')} AS a, count(DISTINCT u) AS users FROM x GROUP BY GROUPING SETS ((country, role, age), (country, age), (role, age), (age))),
      sizes AS (SELECT country, role, CAST(grouping(country, role) AS BIGINT) AS g, count(*) AS cohort_size FROM born GROUP BY CUBE (country, role))
      SELECT c.country, c.role, c.grouping_id, z.cohort_size, c.age, c.s, c.a, c.users FROM cells c JOIN sizes z ON c.grouping_id = z.g AND c.country IS NOT DISTINCT FROM z.country AND c.role IS NOT DISTINCT FROM z.role"""
    fine = {"s": "round(fsum(a.gold / 1000.0), 9)", "a": "round(round(fsum(a.gold / 1000.0), 9) / count(a.gold), 6)", "lo": "min(a.gold / 1000.0)", "hi": "max(a.gold / 1000.0)", "third_lo": "min(a.gold / 7.0)", "third_hi": "max(a.gold / 7.0)", "third": SUM.format("(a.gold / 7.0)")}
    fine = cohort(EVENTS, "signup", {"role": "b.role"}, fine, "b.gold / 1000.0 > 0.01 AND b.gold / 7.0 < 12.25", "a.gold / 7.0 < 9.000000001 AND a.gold / 1000.0 >= 0.0035")
    touched = " UNION ALL ".join(f"SELECT '{d}' AS d2, count(DISTINCT b.u) AS users, count(a.tie) AS age_tuples FROM born b LEFT JOIN act a ON a.u = b.u AND (a.t, a.tie) > (b.t, b.tie) WHERE {_days(D1, d)}" for d in [days_after(n) for n in range(0, 12, 2)])
    three = [("birth_week", SUNDAY), ("country", "b.country"), ("role", "b.role")]
    names = ", ".join(n for n, _ in three)
    subsets = [[n for k, (n, _) in enumerate(three) if g >> k & 1] for g in range(8)]
    cube_week = f"""WITH {EVENTS}, {born('signup')}, x AS (SELECT {", ".join(f"{e} AS {n}" for n, e in three)}, {DAY} AS age, a.u AS u, a.gold AS gold FROM act a JOIN born b ON a.u = b.u AND a.t > b.t),
      y AS (SELECT {", ".join(f"{e} AS {n}" for n, e in three)} FROM born b),
      cells AS (SELECT {names}, CAST(grouping({names}) AS BIGINT) AS grouping_id, age, count(DISTINCT u) AS users, min(gold) AS lo FROM x GROUP BY GROUPING SETS ({", ".join("(" + ", ".join([*s, "age"]) + ")" for s in subsets)})),
      sizes AS (SELECT {names}, CAST(grouping({names}) AS BIGINT) AS g, count(*) AS cohort_size FROM y GROUP BY CUBE ({names}))
      SELECT {", ".join(f"c.{n}" for n, _ in three)}, c.grouping_id, z.cohort_size, c.age, c.users, c.lo FROM cells c JOIN sizes z ON c.grouping_id = z.g AND {" AND ".join(f"c.{n} IS NOT DISTINCT FROM z.{n}" for n, _ in three)}"""
    q5_launch = lambda d2: cohort(STAGGERED, "launch", country, users, _days(D1, d2))
    q7_launch = lambda g: cohort(STAGGERED, "launch", country, users, ages=f"{DAY} < {g}")
    joined = f"WITH {EVENTS}, o AS (SELECT o_custkey AS u2, o_orderdate AS t2, o_orderpriority AS prio, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS place FROM orders WHERE o_orderstatus = 'F') SELECT tie AS event_id, t2 AS order_time, prio AS order_o_orderpriority FROM act JOIN o ON u = u2 AND place = 1"
    out = {
        "fine_measures": fine, "fine_measures_chunked": fine, "tuples_touched": f"WITH {EVENTS}, {born('signup')} {touched}", "cube_week": cube_week, "join_births": joined,
        "block_function": f"WITH {EVENTS}, f AS (SELECT u, min(t) FILTER (e = 'signup') AS birth FROM act GROUP BY u) SELECT CAST(act.u AS VARCHAR) AS user, birth AS birth_time, CAST(count(*) AS INTEGER) AS tuples, CAST(count(*) FILTER (t > birth) AS INTEGER) AS later FROM act JOIN f ON act.u = f.u GROUP BY 1, 2",
        "launch_q5_sweep": sweep(q5_launch, [days_after(n) for n in range(0, 24, 3)], "d2", quoted), "launch_q7_sweep": sweep(q7_launch, range(1, 15, 3), "g", plain),
        "q1": q1, "q2": q2, "q3": q3, "q4": q4, "q4b": q4b, "q5": q5("2024-01-03"), "q6": q6("2024-01-03"), "q7": q7(7), "q8": q8(7),
        "q5_sweep": sweep(q5, [days_after(n) for n in range(12)], "d2", quoted),
        "q6_sweep": sweep(q6, [days_after(n) for n in range(12)], "d2", quoted),
        "q7_sweep": sweep(q7, range(1, 15), "g", plain),
        "q8_sweep": sweep(q8, range(1, 15), "g", plain),
        "ex1": ex1, "cohortsql_ex1": ex1, "all_measures": every, "all_measures_chunked": every,
        "launch_q1": cohort(LAUNCH, "launch", country, users),
        "launch_staggered": cohort(STAGGERED, "launch", {"birth_day": "CAST(b.t AS DATE)"}, users),
        "orders_month": orders, "orders_month_chunked": orders,
        "orders_retention": cohort(ORDERS, "F", {"o_orderpriority": "b.prio"}, users, age=MONTH),
        "lineitem_week": cohort(LINEITEM, "R", country, {"total": SUM.format("a.price")}, ages="a.e = 'R'", age=WEEK),
        "conv_ticks": cohort(TALKS, "assistant", {}, {"avg_chars": AVG.format("a.chars")}, age=TICK),
        "qs_weekly": weekly, "weekly_window": weekly, "classic": classic,
        "report_pivot": f"SELECT birth_week, cohort_size, {', '.join(f'max(CASE WHEN age = {g} THEN avg_gold END) AS age_{g}' for g in range(1, 6))} FROM ({classic}) GROUP BY 1, 2",
        "retention_rate": f"SELECT *, round(users / cohort_size, 6) AS rate FROM ({q1})",
        "over_age": f"SELECT *, round(avg_gold - lag(avg_gold) OVER (PARTITION BY birth_week ORDER BY age), 6) AS change FROM ({classic})",
        "over_cohorts": f"SELECT *, round(avg_gold - lag(avg_gold) OVER (PARTITION BY age ORDER BY birth_week), 6) AS change FROM ({classic})",
        "dense_report": f"SELECT g.country, g.cohort_size, g.age, coalesce(r.users, 0) AS users FROM (SELECT DISTINCT country, cohort_size, CAST(unnest(range(1, 31)) AS INTEGER) AS age FROM ({q2})) g LEFT JOIN ({q2}) r USING (country, cohort_size, age)",
        "top_cohorts": f"SELECT DISTINCT country, cohort_size FROM ({q1}) ORDER BY cohort_size DESC, country LIMIT 5",
        "mixed": f"SELECT country AS cohort, age AS AGE, spent FROM ({ex1}) WHERE country IN ('NATION_1', 'NATION_2', 'NATION_3') AND age <= 10",
        "cube": cube,
        "births": f"WITH {EVENTS} SELECT u AS user_id, min(t) AS birth_time FROM act WHERE e = 'signup' GROUP BY 1",
        "birth_tuples": f"WITH {EVENTS}, {born('signup')} SELECT u AS user_id, t AS ts, role, country, gold, tie AS event_id FROM born",
        "age_tuples": f"WITH {EVENTS}, {born('signup')} SELECT a.tie AS event_id, epoch_us(a.t) - epoch_us(b.t) AS age_raw, {DAY} AS age FROM act a JOIN born b ON a.u = b.u AND a.t > b.t",
        "birth_select": f"WITH {EVENTS}, {born('signup')} SELECT tie AS event_id FROM act WHERE u IN (SELECT u FROM born WHERE role = 'r0')",
        "age_select": f"WITH {EVENTS}, {born('purchase')} SELECT a.tie AS event_id FROM act a JOIN born b ON a.u = b.u WHERE a.tie = b.tie OR (a.t > b.t AND {bought} AND a.country <> 'NATION_3')",
        "age_select_birth_ref": f"WITH {EVENTS}, {born('purchase')} SELECT a.tie AS event_id FROM act a JOIN born b ON a.u = b.u WHERE a.tie = b.tie OR (a.t > b.t AND a.role = b.role AND {DAY} <= 7)",
        "cohort_sizes": f"WITH {EVENTS}, {born('signup')} SELECT country, CAST(date_trunc('month', t) AS DATE) AS birth_month, count(*) AS cohort_size FROM born GROUP BY 1, 2",
        "never_born": f"WITH {ORDERS} SELECT DISTINCT u AS o_custkey FROM act WHERE u NOT IN (SELECT u FROM act WHERE e = 'F')",
        "birth_index": f"WITH {EVENTS} SELECT e AS action, u AS user_id, min(t) AS birth_time, arg_min(role, (t, tie)) AS role, count(*) AS n FROM act GROUP BY 1, 2",
        "usercount_global": q1, "late_birth_q4": q4,
        "birth_cdf": f"WITH {EVENTS}, {born('signup')}, d AS (SELECT CAST(t AS DATE) AS day, count(*) AS births FROM born GROUP BY 1) SELECT day, births, CAST(sum(births) OVER (ORDER BY day) AS BIGINT) AS cumulative, round(CAST(sum(births) OVER (ORDER BY day) AS DOUBLE) / CAST(sum(births) OVER () AS DOUBLE), 6) AS share FROM d",
        "scale_x4": f"SELECT country, 4 * cohort_size AS cohort_size, age, 4 * users AS users FROM ({q1})",
        "global_dictionary": f"WITH {EVENTS} SELECT country AS value, row_number() OVER (ORDER BY country) - 1 AS gid FROM (SELECT DISTINCT country FROM act)",
        "chunk_stats": f"WITH {EVENTS} SELECT count(*) AS n_rows, count(DISTINCT u) AS n_users, CAST(min(k) AS BIGINT) AS min_k, CAST(max(k) AS BIGINT) AS max_k FROM act",
        "user_runs": f"WITH {EVENTS} SELECT u AS user_id, count(*) AS n FROM act GROUP BY 1",
        "mv_merged_q4": q4,
    }
    for prefix in ("window", "nested", "sql", "sqlpushed", "chunked", "index", "mv", "mv_clustered", "cohortsql"):
        out |= {f"{prefix}_{n}": q for n, q in (("q1", q1), ("q2", q2), ("q3", q3), ("q4", q4))}
    return out

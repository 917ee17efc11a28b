"""Edge cases, against a brute-force reading of the definitions."""

from datetime import datetime, timedelta

import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st

from cohort_engine.functions.ages import AgeUnit, TimeBin
from cohort_engine.functions.measures import Avg, Count, Max, Min, Sum, UserCount
from cohort_engine.functions.predicates import Age, Attr, Birth
from cohort_engine.operators import baselines, chunked, core, encode, layout, native
from cohort_engine.plans.algebra import AgeSelect, BirthSelect, CohortAggregate, CohortPlan, CohortQuery, Scan, normalise, push_birth_down, required_columns
from cohort_engine.schema import ActivitySchema, ActivityTable, CohortSemanticError

SCHEMA = ActivitySchema("u", "t", "e", ("d",), ("v",), ("tie",))
T0 = datetime(2024, 1, 31, 12)
KINDS = "u bigint, t timestamp_ntz, e string, d string, v double, tie bigint"


def table(spark, rows):
    return ActivityTable(spark.createDataFrame(rows, KINDS), SCHEMA)


def brute(rows, action, birth=lambda b: True, ages=lambda a, b, g: True, unit=timedelta(days=1)):
    born = {}
    for r in sorted(rows, key=lambda r: (r[1], r[5])):
        if r[2] == action:
            born.setdefault(r[0], r)
    born = {u: b for u, b in born.items() if birth(b)}
    sizes, cells = {}, {}
    for b in born.values():
        sizes[b[3]] = sizes.get(b[3], 0) + 1
    for r in rows:
        b = born.get(r[0])
        if b and r[1] > b[1]:
            g = -((b[1] - r[1]) // unit)
            if ages(r, b, g):
                cells.setdefault((b[3], g), []).append(r)
    return sorted(((k, sizes[k], g, len({r[0] for r in rs}), len(rs), round(float(round(sum(round(r[4] * 100) for r in rs if r[4] is not None))) / 100, 6) if any(r[4] is not None for r in rs) else None) for (k, g), rs in cells.items()), key=repr)


def engines(spark, act, query):
    plan = query.plan()
    yield "births", native.run(plan)
    yield "window", native.run(plan, "window")
    yield "nested", native.run(plan, "nested")
    yield "late", native.run(plan, options=native.NativeOptions(False, False, False))
    yield "index", native.run(CohortPlan(**{**plan.__dict__, "table": act.with_df(act.df, birth_index=layout.birth_index(act))}), "index")
    yield "sql", baselines.run_sql(plan)
    yield "sql pushed", baselines.run_sql(plan, True)
    yield "view", baselines.run_view(plan, baselines.build_view(act, ["b", "x"], ["d", "v"]))
    yield "view merged", baselines.run_view(plan, baselines.build_view(act, ["b"], ["d", "v"]), True)
    yield "chunked", chunked.run(plan, encode.compress(act, 4))
    yield "chunked by range", chunked.run(plan, encode.compress(act, 4, "range"))


EDGE = [
    (1, T0, "b", "p", 1.0, 1),  # born; then exact and just over 24 h
    (1, T0 + timedelta(hours=24), "x", "p", 2.5, 2),
    (1, T0 + timedelta(hours=24, microseconds=1), "x", "q", 3.25, 3),
    (1, T0, "x", "q", 9.0, 0),  # another action at the birth instant
    (1, T0 - timedelta(days=2), "x", "q", 7.0, 4),  # before birth
    (2, T0, "x", "p", 1.0, 5),  # never born
    (3, T0, "b", "p", 1.0, 6),  # birth only
    (4, T0, "b", "q", 4.0, 8),  # tie on the key: the smaller tie-break is the birth
    (4, T0, "b", "p", 5.0, 7),
    (4, T0 + timedelta(days=3), "b", "q", 0.01, 9),
    (5, T0, "b", None, 1.0, 10),  # null attribute at birth
    (5, T0 + timedelta(hours=1), "x", None, None, 11),
    (5, T0 + timedelta(hours=1), "y", "p", -2.0, 12),
]


def test_edges(spark, collected):
    act = table(spark, EDGE)
    query = CohortQuery(act).birth("b").by("d").measure(users=UserCount(), n=Count(), s=Sum("v"))
    want = brute(EDGE, "b")
    assert any(k is None for k, *_ in want) and len(want) > 3
    for name, df in engines(spark, act, query):
        assert collected(df) == want, name


def test_birth_and_age_conditions(spark, collected):
    act = table(spark, EDGE)
    query = CohortQuery(act).birth("b", (Attr("v") < 4.5) | (Attr("d") == "p")).ages((Attr("d") == Birth("d")) & (Age() <= 2) & ~Attr("e").isin("y")).by("d").measure(users=UserCount(), n=Count(), s=Sum("v"))
    want = brute(EDGE, "b", lambda b: b[4] < 4.5 or b[3] == "p", lambda a, b, g: a[3] is not None and a[3] == b[3] and g <= 2 and a[2] != "y")
    for name, df in engines(spark, act, query):
        assert collected(df) == want, name


FINE = [
    (1, T0, "it's \\ born", "p", 0.004, 1), (1, T0 + timedelta(hours=1), "x", "p", 0.004, 2), (1, T0 + timedelta(hours=2), "x", "p", 0.003, 3), (1, T0 + timedelta(hours=30), "x", "p", 1 / 3, 4),
    (2, T0, "it's \\ born", "p", 1e-9, 5), (2, T0 + timedelta(hours=3), "x", "p", 2e-9, 6), (2, T0 + timedelta(hours=4), "x", "p", 123456789.123456, 7),
]


def test_fine_values_and_odd_actions(spark, collected):
    """Measures and conditions keep all digits, and an action may have quotes and backslashes, in every executor."""
    act = table(spark, FINE)
    action = "it's \\ born"
    query = CohortQuery(act).birth(action, Attr("v") < 0.0041).ages(Attr("v") != 0.0035).by("d").measure(n=Count(), s=Sum("v", 10), a=Avg("v", 10), lo=Min("v"), hi=Max("v"))
    want = [("p", 2, 1, 4, 123456789.130456, round(123456789.130456002 / 4, 10), 2e-9, 123456789.123456), ("p", 2, 2, 1, 0.3333333333, 0.3333333333, 1 / 3, 1 / 3)]
    plan = query.plan()
    for name, df in [*((f, native.run(plan, f)) for f in ("births", "window", "nested")), ("late", native.run(plan, options=native.NativeOptions(False, False, False))), ("sql", baselines.run_sql(plan)), ("pushed", baselines.run_sql(plan, True)),
                     ("view", baselines.run_view(plan, baselines.build_view(act, [action], ["d", "v"]))), ("merged", baselines.run_view(plan, baselines.build_view(act, [action], ["d", "v"]), True)), ("chunked", chunked.run(plan, encode.compress(act, 3)))]:
        got = collected(df)
        assert [r[:4] + r[6:] for r in got] == [r[:4] + r[6:] for r in want], name
        assert all(abs(g - w) <= 1e-9 * max(1, abs(w)) for r, q in zip(got, want, strict=True) for g, w in zip(r[4:6], q[4:6], strict=True)), (name, got)
    assert core.age_select(act, action, Attr("v") < 0.0035).df.count() == 4
    small = CohortQuery(act).birth(action).ages(Attr("v") < 0.0035).measure(n=Count()).plan()
    assert collected(native.run(small)) == collected(chunked.run(small, encode.compress(act, 3))) == [(2, 1, 2)]


def test_empty_table_and_no_cohorts(spark, collected):
    act = table(spark, [])
    for name, df in engines(spark, act, CohortQuery(act).birth("b").by("d").measure(n=Count())):
        assert collected(df) == [], name
    act = table(spark, EDGE)
    for name, df in engines(spark, act, CohortQuery(act).birth("b").measure(n=Count(), lo=Min("v"), hi=Max("v"), a=Avg("v"))):
        got = collected(df)
        assert got[0] == (4, 1, 3, -2.0, 2.5, 0.25), (name, got)


def test_sizes_do_not_depend_on_ages(spark):
    act = table(spark, EDGE)
    few = native.run(CohortQuery(act).birth("b").ages(Attr("e") == "x").by("d").measure(n=Count()).plan())
    assert {r["d"]: r["cohort_size"] for r in few.collect()}["p"] == 3


def test_month_ends(spark):
    rows = [(1, datetime(2024, 1, 31), "b", "p", 1.0, 1), *((1, datetime(2024, m, d), "x", "p", 1.0, 10 * m + d) for m, d in ((2, 1), (2, 29), (3, 1), (3, 31)))]
    act = table(spark, rows)
    ages = {r["tie"]: r["age"] for r in core.age_tuples(act, "b", AgeUnit("month")).collect()}
    assert ages == {21: 1, 49: 1, 31: 2, 61: 2}


@pytest.mark.parametrize(("unit", "mode"), [(u, m) for u in ("hour", "day", "week", "month") for m in ("ceil", "floor1", "calendar", "calendar1")])
def test_chunked_ages_agree(spark, collected, unit, mode):
    rows = [(1, T0, "b", "p", 1.0, 0), *((1, T0 + timedelta(hours=h, microseconds=m), "x", "p", 1.0, 100 * h + m + 1) for h in (1, 11, 12, 24, 36, 100, 168, 700, 720, 1500) for m in (0, 1))]
    act = table(spark, rows)
    plan = CohortPlan(act, "b", None, None, (TimeBin("week"), TimeBin("month")), (("n", Count()),), AgeUnit(unit, mode))
    assert collected(chunked.run(plan, encode.compress(act, 100))) == collected(native.run(plan))


@settings(max_examples=3, deadline=None, suppress_health_check=[HealthCheck.function_scoped_fixture])
@given(st.lists(st.tuples(st.integers(1, 4), st.integers(0, 60), st.sampled_from("bxy"), st.sampled_from(["p", "q", None]), st.integers(0, 400)), max_size=25))
def test_random_tables(spark, collected, drawn):
    rows = [(u, T0 + timedelta(hours=2 * h), e, d, v / 4, k) for k, (u, h, e, d, v) in enumerate(drawn)]
    act = table(spark, rows)
    query = CohortQuery(act).birth("b").ages(Attr("e") != "y").by("d").measure(users=UserCount(), n=Count(), s=Sum("v"))
    want = brute(rows, "b", ages=lambda a, b, g: a[2] != "y")
    for name, df in engines(spark, act, query):
        assert collected(df) == want, name


def test_algebra(spark):
    act = table(spark, EDGE)
    b, a = Attr("d") == "p", Attr("e") == "x"
    tree = CohortAggregate(BirthSelect(AgeSelect(BirthSelect(Scan(act), "b", b), "b", a), "b", Attr("v") > 0), "b", ("d",), (("n", Count()),))
    pushed = push_birth_down(tree.child)
    assert isinstance(pushed, AgeSelect) and isinstance(pushed.child, BirthSelect) and isinstance(pushed.child.child, Scan)
    plan = normalise(tree)
    assert plan.ages == a and len(plan.birth.parts) == 2
    assert required_columns(tree) == {"u", "t", "e", "tie", "d", "v"}
    with pytest.raises(CohortSemanticError):
        normalise(CohortAggregate(BirthSelect(Scan(act), "x"), "b", ("d",), (("n", Count()),)))


@pytest.mark.parametrize("bad", [
    lambda q: q.birth("b", Birth("d") == "p"), lambda q: q.birth("b", Age() < 2), lambda q: q.birth("b").birth("x"), lambda q: q.birth("b").by("u"), lambda q: q.birth("b").by("e"),
    lambda q: q.birth("b").by("nothing"), lambda q: q.birth("b").ages(Attr("nothing") == 1), lambda q: q, lambda q: q.birth("b").measure(s=Sum("nothing")), lambda q: q.birth("b").by("d").measure(age=Count()),
])
def test_rejected(spark, bad):
    with pytest.raises(CohortSemanticError):
        bad(CohortQuery(table(spark, EDGE))).plan()


def test_validate(spark):
    assert SCHEMA.validate(table(spark, EDGE).df) == {"null_keys": 0, "duplicate_keys": 1}


def test_binary_operators(spark):
    act = table(spark, EDGE)
    assert core.union_activities(act, act).df.count() == 2 * len(EDGE)
    other = table(spark, [r for r in EDGE if r[0] in (1, 2)])
    assert {r["u"] for r in core.intersect_born(act, other, "b").df.collect()} == {1}
    assert [r["u"] for r in core.never_born(act, "b").collect()] == [2]


def test_constant_false_age(spark):
    act = table(spark, EDGE)
    assert native.run(CohortQuery(act).birth("b").ages(Age() < 1).by("d").measure(n=Count()).plan()).count() == 0

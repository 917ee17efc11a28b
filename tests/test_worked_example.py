"""Ten tuples whose results can be checked by hand."""

import pytest

from cohort_engine.functions.ages import AgeUnit, TimeBin
from cohort_engine.functions.measures import Avg, Sum, UserCount
from cohort_engine.functions.predicates import Age, Attr, Birth
from cohort_engine.operators import core, native, report
from cohort_engine.plans.algebra import CohortQuery
from cohort_engine.sources.tables import worked_example


@pytest.fixture(scope="module")
def act(spark):
    t = worked_example(spark)
    return t.with_df(t.df.cache())


def ties(t):
    return sorted(r["tie"] for r in t.df.select("tie").collect())


def test_birth_selection_keeps_whole_users(act):
    assert ties(core.birth_select(act, "launch", Attr("country") == "Australia")) == [1, 2, 3, 4, 5]


def test_age_selection(act):
    assert ties(core.age_select(act, "shop", (Attr("action") == "shop") & (Attr("country") != "China"))) == [2, 3, 4, 7, 8]


def test_age_selection_by_birth_attribute(act):
    assert ties(core.age_select(act, "shop", Attr("role") == Birth("role"))) == [2, 3, 7, 8]


def test_births_and_ages(act):
    born = {r["player"]: str(r["birth_time"]) for r in core.birth_times(act, "launch").collect()}
    assert born == {"001": "2013-05-19 10:00:00", "002": "2013-05-20 09:00:00", "003": "2013-05-20 10:00:00"}
    for unit in ("day", "week"):
        ages = {r["tie"]: r["age"] for r in core.with_age(act, "launch", AgeUnit(unit)).collect()}
        assert ages[2] == 1 and ages[1] == 0


def test_cohorts(act):
    got = {r["player"]: r["country"] for r in core.assign_cohorts(act, "launch", ("country",)).collect()}
    assert got == {"001": "Australia", "002": "United States", "003": "China"}
    weeks = {str(r["birth_week"]) for r in core.assign_cohorts(act, "launch", (TimeBin("week"),)).collect()}
    assert weeks == {"2013-05-19"}


@pytest.mark.parametrize("form", ["births", "window", "nested", "late"])
def test_reports(act, collected, form):
    run = lambda q: collected(native.run(q.plan(), options=native.NativeOptions(push_birth=False)) if form == "late" else native.run(q.plan(), form))
    spent = CohortQuery(act).birth("launch", Attr("role") == "dwarf").ages(Attr("action") == "shop").by("country").measure(spent=Sum("gold"))
    assert run(spent) == [("Australia", 1, 1, 50.0), ("Australia", 1, 2, 100.0), ("Australia", 1, 3, 50.0)]
    kept = CohortQuery(act).birth("launch").by("country").measure(users=UserCount())
    assert run(kept) == [("Australia", 1, 1, 1), ("Australia", 1, 2, 1), ("Australia", 1, 3, 1), ("China", 1, 1, 1), ("United States", 1, 2, 1), ("United States", 1, 3, 1)]
    mean = CohortQuery(act).birth("shop").ages(Attr("action") == "shop").by("country").measure(a=Avg("gold"))
    assert run(mean) == [("Australia", 1, 1, 100.0), ("Australia", 1, 2, 50.0), ("United States", 1, 2, 40.0)]


def test_commutation(act):
    b, a = Attr("role") == "dwarf", (Attr("action") == "shop") & (Age() <= 2)
    one = core.age_select(core.birth_select(act, "launch", b), "launch", a)
    two = core.birth_select(core.age_select(act, "launch", a), "launch", b)
    assert ties(one) == ties(two) == [1, 2, 3]


def test_pivot_and_rate(act, collected):
    kept = native.run(CohortQuery(act).birth("launch").by("country").measure(users=UserCount()).plan())
    wide = collected(report.pivot_report(kept, ["country"], "users", [1, 2, 3]))
    assert wide == [("Australia", 1, 1, 1, 1), ("China", 1, 1, None, None), ("United States", 1, None, 1, 1)]
    assert all(r["rate"] == 1.0 for r in report.retention_rate(kept).collect())

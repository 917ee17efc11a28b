"""The text front end: what it reads, what it rejects, and that it means the same as the builder."""

import pytest

from cohort_engine import workloads
from cohort_engine.functions.ages import TimeBin
from cohort_engine.functions.predicates import Attr, Days, In
from cohort_engine.plans.language import cohort_sql, mixed_sql, parse
from cohort_engine.schema import CohortSemanticError, CohortSyntaxError, MixedQueryError
from cohort_engine.sources.tables import Catalog, activity_events, worked_example


@pytest.fixture(scope="module")
def catalog(spark, data):
    return Catalog().register("events", activity_events(spark, data)).register("game", worked_example(spark))


def test_clauses_in_any_order(spark, catalog, collected):
    a = 'SELECT country, CohortSize, Age, sum(gold) AS spent FROM game BIRTH FROM action = "launch" AND role = "dwarf" AGE ACTIVITIES IN action = "shop" COHORT BY country'
    b = 'select country, COHORTSIZE, AGE, Sum(gold) as spent from game cohort by country age activities in action = "shop" birth from role = \'dwarf\' and action = "launch";'
    want = [("Australia", 1, 1, 50.0), ("Australia", 1, 2, 100.0), ("Australia", 1, 3, 50.0)]
    assert collected(cohort_sql(spark, a, catalog)) == collected(cohort_sql(spark, b, catalog)) == want


def test_parts_of_predicates(catalog):
    p = parse('SELECT WEEK(ts), AGE, Count(*) FROM events BIRTH FROM action = "signup" AND ts BETWEEN "2024-01-01" AND "2024-01-03" AND NOT role IN ["r1", "r2"] COHORT BY WEEK(ts)', catalog)
    days, other = p.birth.parts
    assert isinstance(days, Days) and isinstance(other.part, In) and p.by == (TimeBin("week"),)
    assert p.measures[0][0] == "count"
    q = parse('SELECT AGE, UserCount() FROM events BIRTH FROM action = "signup" AGE ACTIVITIES IN (role = Birth(role) OR gold > 1.5) AND AGE <= 7', catalog)
    assert q.by == () and len(q.ages.parts) == 2


@pytest.mark.parametrize("engine", [None, "sql", "sql_pushed", "mv", "window", "nested", "chunked"])
def test_engines_agree(spark, data, catalog, collected, engine):
    want = collected(workloads.QUERIES["q4b"](spark, data))
    text = 'SELECT country, COHORTSIZE, AGE, Avg(gold) AS avg_gold FROM events BIRTH FROM action = "purchase" AND ts BETWEEN "2024-01-01" AND "2024-01-05" AND role = "r0" AGE ACTIVITIES IN action = "purchase" AND role = Birth(role) COHORT BY country'
    assert collected(cohort_sql(spark, text, catalog, engine=engine)) == want


@pytest.mark.parametrize("text", [
    'SELECT country, AGE, Count() FROM events WHERE gold > 1 BIRTH FROM action = "signup" COHORT BY country',
    'SELECT country, AGE, Count() FROM events BIRTH FROM action = "signup" GROUP BY country',
    'SELECT country, AGE, Count() FROM events, game BIRTH FROM action = "signup" COHORT BY country',
    'SELECT country, AGE, Count() FROM events COHORT BY country',
    'SELECT country, AGE, Count() FROM events BIRTH FROM role = "r0" COHORT BY country',
    'SELECT country, AGE, Count() FROM events BIRTH FROM action = "signup" COHORT BY country COHORT BY role',
    'SELECT country, AGE, Median(gold) FROM events BIRTH FROM action = "signup" COHORT BY country',
    'SELECT country AGE FROM events BIRTH FROM action = "signup"',
    'SELECT AGE, Count() FROM events BIRTH FROM action = "signup" AGE ACTIVITIES IN gold >',
    'SELECT AGE, Count() FROM events BIRTH FROM action = "signup" AGE ACTIVITIES IN gold ~ 3',
])
def test_not_a_query(catalog, text):
    with pytest.raises(CohortSyntaxError):
        parse(text, catalog)


@pytest.mark.parametrize("text", [
    'SELECT country, AGE, Count() FROM nowhere BIRTH FROM action = "signup" COHORT BY country',
    'SELECT city, AGE, Count() FROM events BIRTH FROM action = "signup" COHORT BY country',
    'SELECT AGE, Count() FROM events BIRTH FROM action = "signup" COHORT BY user_id',
    'SELECT AGE, Count() FROM events BIRTH FROM action = "signup" AND action = "click"',
    'SELECT AGE, Count() FROM events BIRTH FROM action = "signup" AND role = Birth(role)',
    'SELECT AGE, Count() FROM events BIRTH FROM action = "signup" AND AGE > 3',
])
def test_no_meaning(catalog, text):
    with pytest.raises(CohortSemanticError):
        parse(text, catalog)


def test_mixed(spark, catalog, collected):
    inner = 'SELECT country, COHORTSIZE, AGE, Sum(gold) AS spent FROM game BIRTH FROM action = "launch" AGE ACTIVITIES IN action = "shop" COHORT BY country'
    got = collected(mixed_sql(spark, f'WITH cohorts AS ({inner}), big AS (SELECT cohort, age FROM cohorts WHERE spent > 45) SELECT cohort, count(*) AS n FROM big WHERE cohort IN ["Australia", "China"] GROUP BY cohort', catalog))
    assert got == [("Australia", 3)]
    sizes = mixed_sql(spark, f"WITH c AS ({inner}) SELECT DISTINCT country, cohort_size FROM c WHERE age = 2", catalog)
    assert {r["country"]: r["cohort_size"] for r in sizes.collect()} == {"Australia": 1, "United States": 1}


@pytest.mark.parametrize("text", [
    'SELECT AGE FROM game BIRTH FROM action = "launch"',
    'WITH a AS (SELECT 1 AS x) SELECT x FROM a',
    'WITH a AS (SELECT AGE, Count() AS n FROM game BIRTH FROM action = "launch") SELECT AGE, Count() FROM a BIRTH FROM action = "x"',
    'WITH s AS (SELECT 1 AS x), a AS (SELECT AGE, Count() AS n FROM s BIRTH FROM action = "launch") SELECT * FROM a',
    'WITH a AS (SELECT AGE, Count() AS n FROM game BIRTH FROM action = "launch"',
])
def test_bad_mixtures(spark, catalog, text):
    with pytest.raises(MixedQueryError):
        mixed_sql(spark, text, catalog)


def test_attr_is_not_hashable():
    with pytest.raises(TypeError):
        hash(Attr("x"))

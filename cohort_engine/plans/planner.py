"""Which executor and which physical form a plan gets."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..functions.predicates import split
from ..schema import CohortSemanticError
from .algebra import CohortPlan, normalise

FORMS = ("births", "window", "index", "nested")


def choose(plan: CohortPlan, born_share: float | None = None) -> str:
    """``index`` if the table has a birth index; ``window`` for a raw table most of whose users are born and
    where no condition can go to the scan of activities (then one read is cheaper than two); else ``births``."""
    if plan.table.birth_index is not None:
        return "index"
    if plan.table.layout == "raw" and born_share is not None and born_share > 0.5 and split(plan.ages)[0] is None:
        return "window"
    return "births"


def execute(plan, engine: str | None = None, born_share: float | None = None) -> DataFrame:
    """Runs a plan; ``engine``: a form of the native executor, ``sql``, ``sql_pushed``, ``mv`` or ``chunked``."""
    from ..operators import baselines, chunked, native

    plan = normalise(plan)
    engine = engine or choose(plan, born_share)
    if engine in FORMS:
        return native.run(plan, engine)
    if engine in ("sql", "sql_pushed"):
        return baselines.run_sql(plan, engine == "sql_pushed")
    if engine == "mv":
        attrs = [c for c in plan.birth_columns if c != plan.table.schema.time]
        return baselines.run_view(plan, baselines.build_view(plan.table, [plan.action], attrs))
    if engine == "chunked":
        return chunked.run(plan)
    raise CohortSemanticError(f"no engine {engine!r}")

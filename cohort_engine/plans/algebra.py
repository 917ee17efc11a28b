"""Cohort algebra: immutable nodes, their rewrites, and the normal form that executors take."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from ..functions.ages import AgeUnit, TimeBin, default_unit
from ..functions.measures import Measure
from ..functions.predicates import Attr, Birth, Pred, attributes, birth_attributes, conjoin, conjuncts, terms, uses_age
from ..schema import ActivityTable, CohortSemanticError


@dataclass(frozen=True)
class Scan:
    table: ActivityTable


@dataclass(frozen=True)
class BirthSelect:
    """Whole users, by their birth tuple; without a condition all users that are born."""

    child: object
    action: str
    cond: Pred | None = None


@dataclass(frozen=True)
class AgeSelect:
    """Birth tuples, and those tuples after birth that meet the condition."""

    child: object
    action: str
    cond: Pred | None = None


@dataclass(frozen=True)
class CohortAggregate:
    child: object
    action: str
    by: tuple[str | TimeBin, ...] = ()
    measures: tuple[tuple[str, Measure], ...] = ()
    age_unit: AgeUnit | None = None


@dataclass(frozen=True)
class Project:
    child: object
    columns: tuple[str, ...] = field(default=())


@dataclass(frozen=True)
class CohortPlan:
    """A cohort query in normal form: births are selected first, then ages, then everything is aggregated."""

    table: ActivityTable
    action: str
    birth: Pred | None = None
    ages: Pred | None = None
    by: tuple[str | TimeBin, ...] = ()
    measures: tuple[tuple[str, Measure], ...] = ()
    age_unit: AgeUnit = AgeUnit()
    columns: tuple[str, ...] = ()

    @property
    def cohort_names(self) -> list[str]:
        return [b.name if isinstance(b, TimeBin) else b for b in self.by]

    @property
    def birth_columns(self) -> list[str]:
        """Attributes that a birth tuple has to carry."""
        names = {b for b in self.by if isinstance(b, str)} | attributes(self.birth) | birth_attributes(self.ages)
        return sorted(names - {self.table.schema.time})

    @property
    def age_columns(self) -> list[str]:
        """Attributes that tuples after birth have to carry."""
        names = attributes(self.ages) | {m.attr for _, m in self.measures if m.attr}
        return sorted(names - {self.table.schema.time, self.table.schema.user})


def push_birth_down(node: object) -> object:
    """Birth selections move below age selections of the same action, and neighbours of one kind merge."""
    if isinstance(node, Scan) or not hasattr(node, "child"):
        return node
    node = replace(node, child=push_birth_down(node.child))
    below = node.child
    if isinstance(node, BirthSelect) and isinstance(below, AgeSelect) and node.action == below.action:
        return push_birth_down(replace(below, child=BirthSelect(below.child, node.action, node.cond)))
    if type(node) is type(below) and isinstance(node, BirthSelect | AgeSelect) and node.action == below.action:
        return replace(below, cond=conjoin([*conjuncts(below.cond), *conjuncts(node.cond)]))
    return node


def required_columns(node: object) -> set[str]:
    """Columns that a plan reads from its activity table."""
    plan = normalise(node)
    s = plan.table.schema
    return {s.user, s.time, s.action, *s.tie_break, *plan.birth_columns, *plan.age_columns}


def check(plan: CohortPlan) -> CohortPlan:
    s = plan.table.schema
    for p in (plan.birth, plan.ages):
        for t in terms(p):
            if isinstance(t, Attr | Birth):
                s.check(t.name)
    if birth_attributes(plan.birth) or uses_age(plan.birth):
        raise CohortSemanticError("Birth() and AGE can't stand in a birth condition, which is about the birth tuple itself")
    for b in plan.by:
        if isinstance(b, str):
            if b in (s.user, s.action):
                raise CohortSemanticError(f"cohorts can't be made by {b!r}")
            s.check(b)
    for _, m in plan.measures:
        if m.attr:
            s.check(m.attr)
    names = [*plan.cohort_names, "cohort_size", "age", *(n for n, _ in plan.measures)]
    if len(set(names)) < len(names):
        raise CohortSemanticError(f"a name is used twice: {names}")
    return plan


def normalise(node: object) -> CohortPlan:
    """The normal form of a tree with one aggregate; rejects trees with several birth actions."""
    columns: tuple[str, ...] = ()
    if isinstance(node, Project):
        columns, node = node.columns, node.child
    if isinstance(node, CohortPlan):
        return check(replace(node, columns=columns or node.columns))
    if not isinstance(node, CohortAggregate):
        raise CohortSemanticError("a cohort query ends in an aggregate")
    top, actions, births, ages = node, {node.action}, [], []
    node = push_birth_down(node.child)
    while not isinstance(node, Scan):
        actions.add(node.action)
        (births if isinstance(node, BirthSelect) else ages).append(node.cond)
        node = node.child
    if len(actions) > 1:
        raise CohortSemanticError(f"one query has one birth action, not {', '.join(sorted(actions))}")
    both = lambda ps: conjoin([c for p in ps for c in conjuncts(p)])
    return check(CohortPlan(node.table, top.action, both(births), both(ages), tuple(top.by), tuple(top.measures), top.age_unit or default_unit(node.table.schema), columns))


class CohortQuery:
    """A fluent builder of :class:`CohortPlan`."""

    def __init__(self, table: ActivityTable) -> None:
        self._plan = CohortPlan(table, "", age_unit=default_unit(table.schema))

    def _with(self, **changes: object) -> CohortQuery:
        out = CohortQuery(self._plan.table)
        out._plan = replace(self._plan, **changes)
        return out

    def birth(self, action: str, cond: Pred | None = None) -> CohortQuery:
        if self._plan.action not in ("", action):
            raise CohortSemanticError("one query has one birth action")
        return self._with(action=action, birth=conjoin([*conjuncts(self._plan.birth), *conjuncts(cond)]))

    def ages(self, cond: Pred | None) -> CohortQuery:
        return self._with(ages=conjoin([*conjuncts(self._plan.ages), *conjuncts(cond)]))

    def by(self, *attrs: str | TimeBin) -> CohortQuery:
        return self._with(by=attrs)

    def measure(self, **measures: Measure) -> CohortQuery:
        return self._with(measures=(*self._plan.measures, *measures.items()))

    def age_unit(self, unit: str, mode: str = "ceil") -> CohortQuery:
        return self._with(age_unit=AgeUnit(unit, mode))

    def plan(self) -> CohortPlan:
        if not self._plan.action:
            raise CohortSemanticError("a cohort query names a birth action")
        return check(self._plan)

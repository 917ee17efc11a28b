"""Predicates over an activity tuple, its user's birth tuple and its age.

They are kept as a small tree, so that conjuncts can be told apart by what they need: the tuple alone (a
Parquet scan can take them), the birth tuple, or the age. Executors render them as SQL, or evaluate them on arrays.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np

from ..schema import CohortSemanticError


class Term:
    def __eq__(self, other):  # type: ignore[override]
        return Cmp("=", self, term(other))

    def __ne__(self, other):  # type: ignore[override]
        return Cmp("!=", self, term(other))

    def __lt__(self, other):
        return Cmp("<", self, term(other))

    def __le__(self, other):
        return Cmp("<=", self, term(other))

    def __gt__(self, other):
        return Cmp(">", self, term(other))

    def __ge__(self, other):
        return Cmp(">=", self, term(other))

    __hash__ = None  # type: ignore[assignment]

    def isin(self, *values):
        return In(self, tuple(values))

    def between(self, low, high):
        return Between(self, low, high)

    def days(self, first: str, last: str):
        """Calendar dates from first to last, both included."""
        return Days(self, first, last)


@dataclass(frozen=True, eq=False)
class Attr(Term):
    name: str


@dataclass(frozen=True, eq=False)
class Birth(Term):
    """An attribute of the user's birth tuple."""

    name: str


@dataclass(frozen=True, eq=False)
class Age(Term):
    pass


@dataclass(frozen=True, eq=False)
class Lit(Term):
    value: object


def term(x: object) -> Term:
    return x if isinstance(x, Term) else Lit(x)


class Pred:
    def __and__(self, other: Pred) -> Pred:
        return And((self, other))

    def __or__(self, other: Pred) -> Pred:
        return Or((self, other))

    def __invert__(self) -> Pred:
        return Not(self)


@dataclass(frozen=True)
class Cmp(Pred):
    op: str
    left: Term
    right: Term


@dataclass(frozen=True)
class In(Pred):
    left: Term
    values: tuple


@dataclass(frozen=True)
class Between(Pred):
    left: Term
    low: object
    high: object


@dataclass(frozen=True)
class Days(Pred):
    left: Term
    first: str
    last: str


@dataclass(frozen=True)
class And(Pred):
    parts: tuple[Pred, ...]


@dataclass(frozen=True)
class Or(Pred):
    parts: tuple[Pred, ...]


@dataclass(frozen=True)
class Not(Pred):
    part: Pred


def conjuncts(p: Pred | None) -> list[Pred]:
    if p is None:
        return []
    return [c for part in p.parts for c in conjuncts(part)] if isinstance(p, And) else [p]


def conjoin(parts: list[Pred]) -> Pred | None:
    return None if not parts else parts[0] if len(parts) == 1 else And(tuple(parts))


def terms(p: Pred | None) -> list[Term]:
    if p is None:
        return []
    if isinstance(p, And | Or):
        return [t for part in p.parts for t in terms(part)]
    if isinstance(p, Not):
        return terms(p.part)
    return [p.left, p.right] if isinstance(p, Cmp) else [p.left]


def attributes(p: Pred | None) -> set[str]:
    return {t.name for t in terms(p) if isinstance(t, Attr)}


def birth_attributes(p: Pred | None) -> set[str]:
    return {t.name for t in terms(p) if isinstance(t, Birth)}


def uses_age(p: Pred | None) -> bool:
    return any(isinstance(t, Age) for t in terms(p))


def split(p: Pred | None) -> tuple[Pred | None, Pred | None]:
    """Conjuncts over the tuple alone, and the others."""
    own = [c for c in conjuncts(p) if not birth_attributes(c) and not uses_age(c)]
    return conjoin(own), conjoin([c for c in conjuncts(p) if birth_attributes(c) or uses_age(c)])


def age_limit(p: Pred | None) -> int | None:
    """The largest age that the conjuncts allow, if one of them bounds it."""
    limits = []
    for c in conjuncts(p):
        if isinstance(c, Cmp) and isinstance(c.left, Age) and isinstance(c.right, Lit) and isinstance(c.right.value, int):
            limits += {"<": [c.right.value - 1], "<=": [c.right.value], "=": [c.right.value]}.get(c.op, [])
        if isinstance(c, Between) and isinstance(c.left, Age):
            limits.append(int(c.high))
    return min(limits, default=None)


def day_range(p: Pred | None, name: str) -> tuple[str | None, str | None]:
    """The first and last day that the conjuncts leave to an attribute, as far as they say so by days."""
    days = [c for c in conjuncts(p) if isinstance(c, Days) and isinstance(c.left, Attr) and c.left.name == name]
    return max((c.first for c in days), default=None), min((c.last for c in days), default=None)


def literal(value: object) -> str:
    if value is None:
        return "NULL"
    if isinstance(value, bool):
        return str(value).upper()
    if isinstance(value, int | float):
        return repr(value)
    return "'" + str(value).replace("\\", "\\\\").replace("'", "\\'") + "'"


def to_sql(p: Pred | None, attr: Callable[[str], str], birth: Callable[[str], str] | None = None, age: str | None = None) -> str:
    """The predicate as SQL; ``attr`` and ``birth`` name columns."""
    if p is None:
        return "TRUE"

    def one(t: Term) -> str:
        if isinstance(t, Attr):
            return attr(t.name)
        if isinstance(t, Lit):
            return literal(t.value)
        if isinstance(t, Birth) and birth is not None:
            return birth(t.name)
        if isinstance(t, Age) and age is not None:
            return age
        raise CohortSemanticError(f"{'Birth(' + t.name + ')' if isinstance(t, Birth) else 'AGE'} can't stand in a birth condition")

    def render(q: Pred) -> str:
        if isinstance(q, And | Or):
            return "(" + f" {'AND' if isinstance(q, And) else 'OR'} ".join(render(x) for x in q.parts) + ")"
        if isinstance(q, Not):
            return f"(NOT {render(q.part)})"
        if isinstance(q, In):
            return f"({one(q.left)} IN ({', '.join(map(literal, q.values))}))"
        if isinstance(q, Between):
            return f"({one(q.left)} BETWEEN {one(term(q.low))} AND {one(term(q.high))})"
        if isinstance(q, Days):
            return f"(to_date({one(q.left)}) BETWEEN DATE {literal(q.first)} AND DATE {literal(q.last)})"
        return f"({one(q.left)} {q.op} {one(q.right)})"

    return render(p)


def on_arrays(p: Pred | None, n: int, attr: Callable[[str], np.ndarray], birth: Callable[[str], np.ndarray] | None = None, age: np.ndarray | None = None) -> np.ndarray:
    """The predicate over arrays of length ``n``; comparisons with None are not true."""
    if p is None:
        return np.ones(n, bool)

    def one(t: Term) -> np.ndarray:
        if isinstance(t, Attr):
            return attr(t.name)
        if isinstance(t, Birth) and birth is not None:
            return birth(t.name)
        if isinstance(t, Age) and age is not None:
            return age
        if isinstance(t, Lit):
            return np.full(n, t.value, dtype=object if isinstance(t.value, str) or t.value is None else None)
        raise CohortSemanticError("Birth() and AGE can't stand in a birth condition")

    def known(*xs: np.ndarray) -> np.ndarray:
        ok = np.ones(n, bool)
        for x in xs:
            if x.dtype == object:
                ok &= np.array([v is not None for v in x], bool)
            elif x.dtype.kind == "f":
                ok &= ~np.isnan(x)
        return ok

    compare = {"=": np.equal, "!=": np.not_equal, "<": np.less, "<=": np.less_equal, ">": np.greater, ">=": np.greater_equal}

    def run(q: Pred) -> tuple[np.ndarray, np.ndarray]:
        """Where the predicate is true, and where it is known."""
        if isinstance(q, And | Or):
            parts = [run(x) for x in q.parts]
            true, false = [t & k for t, k in parts], [~t & k for t, k in parts]
            yes = np.logical_and.reduce(true) if isinstance(q, And) else np.logical_or.reduce(true)
            no = np.logical_or.reduce(false) if isinstance(q, And) else np.logical_and.reduce(false)
            return yes, yes | no
        if isinstance(q, Not):
            t, k = run(q.part)
            return ~t & k, k
        if isinstance(q, In):
            x = one(q.left)
            return np.isin(x, list(q.values)) if x.dtype != object else np.array([v in q.values for v in x], bool), known(x)
        if isinstance(q, Days):
            x = one(q.left).astype(np.int64).astype("datetime64[us]").astype("datetime64[D]")
            return (x >= np.datetime64(q.first)) & (x <= np.datetime64(q.last)), np.ones(n, bool)
        a, pairs = one(q.left), [("=", None)]
        pairs = [(">=", one(term(q.low))), ("<=", one(term(q.high)))] if isinstance(q, Between) else [(q.op, one(q.right))]
        ok, yes = known(a, *(b for _, b in pairs)), np.ones(n, bool)
        for op, b in pairs:
            part = np.zeros(n, bool)
            part[ok] = compare[op](a[ok], b[ok]).astype(bool)
            yes &= part
        return yes, ok

    t, k = run(p)
    return t & k

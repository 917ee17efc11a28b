"""Measures of a cohort report. Each has mergeable partial states, so chunks and streams can be combined.

Sums and averages go over decimals with ``PLACES`` places, whatever a column's own scale is, so they don't depend on the order of rows
and all executors agree; only the finished measure is rounded, to ``places`` of its own."""

from __future__ import annotations

from dataclasses import dataclass

from ..schema import CohortSemanticError

#: Values count to this many places; whole numbers have room for 26 digits.
PLACES = 12
KINDS = ("sum", "avg", "count", "min", "max", "usercount")


def exact(column: str) -> str:
    """A column as the decimal that is summed."""
    return f"CAST({column} AS DECIMAL(38,{PLACES}))"


@dataclass(frozen=True)
class Measure:
    """``places``: to how many the finished sum or average is rounded."""

    kind: str
    attr: str | None = None
    places: int = 6

    def __post_init__(self) -> None:
        if self.kind not in KINDS or (self.kind not in ("count", "usercount") and self.attr is None):
            raise CohortSemanticError(f"no measure {self.kind}({self.attr or ''})")

    def partial(self, column: str) -> dict[str, str]:
        """Names of states, and the aggregates that make them from tuples."""
        dec = exact(column)
        return {
            "sum": {"s": f"sum({dec})"},
            "avg": {"s": f"sum({dec})", "n": f"count({column})"},
            "count": {"n": f"count({column})" if self.attr else "count(1)"},
            "min": {"m": f"min({column})"},
            "max": {"m": f"max({column})"},
            "usercount": {"u": "count(1)"},  # over rows that are already one for each user
        }[self.kind]

    def merge(self, state: str, column: str) -> str:
        return f"{self.kind if state == 'm' else 'sum'}({column})"

    def finish(self, columns: dict[str, str]) -> str:
        if self.kind == "sum":
            return f"round(CAST({columns['s']} AS DOUBLE), {self.places})"
        if self.kind == "avg":
            return f"round(CAST({columns['s']} AS DOUBLE) / {columns['n']}, {self.places})"
        return f"CAST({columns['m']} AS DOUBLE)" if self.kind in ("min", "max") else f"CAST({columns[next(iter(columns))]} AS BIGINT)"


def Sum(attr: str, places: int = 6) -> Measure:
    return Measure("sum", attr, places)


def Avg(attr: str, places: int = 6) -> Measure:
    return Measure("avg", attr, places)


def Count(attr: str | None = None) -> Measure:
    return Measure("count", attr)


def Min(attr: str) -> Measure:
    return Measure("min", attr)


def Max(attr: str) -> Measure:
    return Measure("max", attr)


def UserCount() -> Measure:
    return Measure("usercount")

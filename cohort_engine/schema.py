"""Activity tables: which columns play which part, and the errors of the engine."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


class CohortError(ValueError):
    """Any query that the engine rejects."""


class CohortSyntaxError(CohortError):
    """Text that is not a cohort query."""


class CohortSemanticError(CohortError):
    """A query that has no meaning: unknown attributes, several birth actions, cohorts by user or action."""


class MixedQueryError(CohortError):
    """A mixed query that puts cohort queries where they may not stand."""


@dataclass(frozen=True)
class ActivitySchema:
    """Roles of the columns. ``tie_break`` orders tuples of a user that share time and action."""

    user: str
    time: str
    action: str
    dims: tuple[str, ...] = ()
    measures: tuple[str, ...] = ()
    tie_break: tuple[str, ...] = ()
    time_kind: str = "ntz"  # ntz | timestamp | date | tick

    @property
    def attributes(self) -> tuple[str, ...]:
        return (self.time, *self.dims, *self.measures)

    @property
    def columns(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys((self.user, self.time, self.action, *self.dims, *self.measures, *self.tie_break)))

    def check(self, name: str) -> str:
        if name not in self.columns:
            raise CohortSemanticError(f"no attribute {name!r}; there are {', '.join(self.columns)}")
        return name

    def validate(self, df: DataFrame) -> dict[str, int]:
        """Broken keys of a table: rows with a null in the key, and keys that occur more than once."""
        key = [self.user, self.time, self.action]
        nulls = df.where(" OR ".join(f"`{k}` IS NULL" for k in key)).count()
        twice = df.groupBy(*key).agg(F.count("*").alias("n")).where("n > 1").count()
        return {"null_keys": nulls, "duplicate_keys": twice}


@dataclass(frozen=True)
class ActivityTable:
    """``layout``: raw, clustered (bucketed and sorted by user), nested (a row for each user) or chunked."""

    df: DataFrame
    schema: ActivitySchema
    name: str = "activities"
    layout: str = "raw"
    birth_index: DataFrame | None = field(default=None, compare=False)

    def with_df(self, df: DataFrame, **changes: object) -> ActivityTable:
        from dataclasses import replace

        return replace(self, df=df, **changes)

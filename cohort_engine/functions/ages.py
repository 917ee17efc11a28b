"""Ages and time bins, as SQL expressions over a time and a birth time."""

from __future__ import annotations

from dataclasses import dataclass

from ..schema import ActivitySchema, CohortSemanticError

_MICROS = {"hour": 3_600_000_000, "day": 86_400_000_000, "week": 604_800_000_000}


@dataclass(frozen=True)
class AgeUnit:
    """``mode``: ``ceil`` (the first unit after birth is 1), ``floor1``, ``calendar`` (units between dates) or ``calendar1``."""

    unit: str = "day"
    mode: str = "ceil"

    def __post_init__(self) -> None:
        if self.unit not in (*_MICROS, "month", "tick") or self.mode not in ("ceil", "floor1", "calendar", "calendar1"):
            raise CohortSemanticError(f"no age unit {self.unit!r} with mode {self.mode!r}")

    def sql(self, time: str, birth: str) -> str:
        t, b = time, birth
        if self.unit == "tick":
            return f"CAST({t} - {b} AS INT)"
        if self.mode.startswith("calendar"):
            more = " + 1" if self.mode == "calendar1" else ""
            days = {"day": f"datediff({t}, {b})", "week": f"datediff({week_start(t)}, {week_start(b)}) div 7", "month": f"12 * (year({t}) - year({b})) + month({t}) - month({b})", "hour": f"timestampdiff(HOUR, date_trunc('HOUR', {b}), date_trunc('HOUR', {t}))"}[self.unit]
            return f"CAST({days}{more} AS INT)"
        if self.unit == "month":
            whole = f"12 * (year({t}) - year({b})) + month({t}) - month({b})"
            later = f"CASE WHEN struct(day({t}), date_format({t}, 'HH:mm:ss.SSSSSS')) > struct(day({b}), date_format({b}, 'HH:mm:ss.SSSSSS')) THEN 1 ELSE 0 END"
            return f"CAST({whole} + {later} AS INT)" if self.mode == "ceil" else f"CAST({whole} + {later} - CASE WHEN struct(day({t}), date_format({t}, 'HH:mm:ss.SSSSSS')) = struct(day({b}), date_format({b}, 'HH:mm:ss.SSSSSS')) THEN 0 ELSE 1 END + 1 AS INT)"
        size = _MICROS[self.unit]
        raw = raw_age(t, b)
        return f"CAST(({raw} + {size - 1}) div {size} AS INT)" if self.mode == "ceil" else f"CAST({raw} div {size} + 1 AS INT)"

    def latest(self, birth: str, age: int) -> str | None:
        """A time after which no tuple has an age of at most ``age``; None if the unit has no such bound."""
        if self.mode != "ceil" or self.unit not in _MICROS:
            return None
        return f"{birth} + make_dt_interval(0, 0, 0, {age * _MICROS[self.unit] // 1_000_000})"


def raw_age(time: str, birth: str) -> str:
    return f"timestampdiff(MICROSECOND, {birth}, {time})"


def week_start(time: str) -> str:
    """The Sunday on or before."""
    return f"date_sub(to_date({time}), dayofweek(to_date({time})) - 1)"


@dataclass(frozen=True)
class TimeBin:
    """A cohort attribute: the day, week (from Sunday) or month of birth."""

    unit: str

    def __post_init__(self) -> None:
        if self.unit not in ("day", "week", "month"):
            raise CohortSemanticError(f"no time bin {self.unit!r}")

    @property
    def name(self) -> str:
        return f"birth_{self.unit}"

    def sql(self, birth: str) -> str:
        return {"day": f"to_date({birth})", "week": week_start(birth), "month": f"to_date(date_trunc('MONTH', {birth}))"}[self.unit]


def default_unit(schema: ActivitySchema) -> AgeUnit:
    return AgeUnit("tick") if schema.time_kind == "tick" else AgeUnit("day")

"""Periods counted back from a baseline: 1 is the unit just before it, rows at or after it have none.

Units: "day", "week", "month" (calendar months; the baseline is a first of month) or "N day".
"""

from __future__ import annotations

from datetime import date

from pyspark.sql import Column
from pyspark.sql import functions as F

BASELINE = "2001-08-01"
EVENT_BASELINE = "2024-01-31"


def at(baseline: str) -> Column:
    return F.lit(baseline).cast("timestamp_ntz")


def days_back(ts: Column, baseline: str) -> Column:
    return F.datediff(F.lit(baseline).cast("date"), ts.cast("date"))


def period_index(ts: Column, baseline: str, unit: str) -> Column:
    if unit == "month":
        base = date.fromisoformat(baseline)
        return F.lit(base.year * 12 + base.month) - (F.year(ts) * 12 + F.month(ts))
    length = {"day": 1, "week": 7}.get(unit) or int(unit.split()[0])
    return (F.floor((days_back(ts, baseline) - 1) / length) + 1).cast("int")


def months_before(baseline: str, months: int) -> str:
    base = date.fromisoformat(baseline)
    n = base.year * 12 + base.month - 1 - months
    return f"{n // 12:04d}-{n % 12 + 1:02d}-{base.day:02d}"


def in_last(ts: Column, baseline: str, months: int) -> Column:
    """Rows of the last months before the baseline: two literal bounds, so the filter reaches the scan."""
    return (ts >= at(months_before(baseline, months))) & (ts < at(baseline))


def before(ts: Column, baseline: str) -> Column:
    return ts < at(baseline)

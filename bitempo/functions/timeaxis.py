"""Times are whole microseconds since 1970; intervals are half-open; ``OPEN_END`` is the end that never comes."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

OPEN_END = 1 << 62
SECOND = 1_000_000
MINUTE, HOUR, DAY, WEEK = 60 * SECOND, 3600 * SECOND, 86_400 * SECOND, 7 * 86_400 * SECOND

#: The thirteen relations of two intervals; each but ``equals`` has its inverse in the list.
ALLEN = ("before", "meets", "overlaps", "starts", "during", "finishes", "equals", "finished_by", "contains", "started_by", "overlapped_by", "met_by", "after")
INVERSE = dict(zip(ALLEN, reversed(ALLEN)))


def _col(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def micros(ts: Column | str) -> Column:
    """Microseconds of a timestamp's own calendar reading, whatever the session's time zone."""
    ts = _col(ts)
    day = F.datediff(ts.cast("date"), F.lit("1970-01-01").cast("date")).cast("long")
    second = F.date_part(F.lit("SECOND"), ts) * 1_000_000
    return day * DAY + F.hour(ts).cast("long") * HOUR + F.minute(ts).cast("long") * MINUTE + second.cast("long")


def floor_to(t: Column | str, width: int) -> Column:
    t = _col(t)
    return t - F.pmod(t, F.lit(width).cast("long"))


def day_floor(t: Column | str) -> Column:
    return floor_to(t, DAY)


def week_floor(t: Column | str) -> Column:
    """Start of the week since 1970-01-01 (a Thursday)."""
    return floor_to(t, WEEK)


def covers(start: Column | str, end: Column | str, t) -> Column:
    return (_col(start) <= t) & (_col(end) > t)


def overlaps(a_s: Column | str, a_e: Column | str, b_s, b_e) -> Column:
    return (_col(a_s) < b_e) & (_col(a_e) > b_s)


def later(t: Column | str, by: int) -> Column:
    """``t + by``, never beyond the open end."""
    t = _col(t)
    return F.when(t >= OPEN_END - by, F.lit(OPEN_END)).otherwise(t + F.lit(by).cast("long"))


def allen(a_s, a_e, b_s, b_e) -> Column:
    """Name of the one relation that holds between two non-empty half-open intervals."""
    a_s, a_e, b_s, b_e = map(_col, (a_s, a_e, b_s, b_e))
    return (
        F.when(a_e < b_s, "before").when(a_e == b_s, "meets").when(b_e < a_s, "after").when(b_e == a_s, "met_by")
        .when((a_s == b_s) & (a_e == b_e), "equals")
        .when(a_s == b_s, F.when(a_e < b_e, "starts").otherwise("started_by"))
        .when(a_e == b_e, F.when(a_s > b_s, "finishes").otherwise("finished_by"))
        .when((a_s > b_s) & (a_e < b_e), "during").when((a_s < b_s) & (a_e > b_e), "contains")
        .when(a_s < b_s, "overlaps").otherwise("overlapped_by")
    )


def interval_iou(a_s, a_e, b_s, b_e) -> Column:
    """Shared length over joint length of two intervals; 1 for two equal empty ones."""
    a_s, a_e, b_s, b_e = map(_col, (a_s, a_e, b_s, b_e))
    shared = F.greatest(F.lit(0).cast("long"), F.least(a_e, b_e) - F.greatest(a_s, b_s))
    joint = (a_e - a_s) + (b_e - b_s) - shared
    return F.when(joint > 0, shared / joint).otherwise(((a_s == b_s) & (a_e == b_e)).cast("double"))

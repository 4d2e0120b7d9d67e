"""Times as longs, independent of the session's zone."""

from __future__ import annotations

from datetime import datetime, timezone

from pyspark.sql import Column
from pyspark.sql import functions as F


def micros(ts: str | Column) -> Column:
    """Microseconds since 1970 of a timestamp without zone."""
    c = F.col(ts) if isinstance(ts, str) else ts
    d = c.cast("timestamp_ntz") - F.to_timestamp_ntz(F.lit("1970-01-01 00:00:00"))
    part = lambda what: F.extract(F.lit(what), d).cast("long")
    seconds = (F.extract(F.lit("SECOND"), d) * F.lit(1_000_000)).cast("long")
    return part("DAY") * F.lit(86_400_000_000) + part("HOUR") * F.lit(3_600_000_000) + part("MINUTE") * F.lit(60_000_000) + seconds


def day_micros(text: str) -> int:
    """Microseconds since 1970 of an ISO date or time, taken as UTC."""
    return int(datetime.fromisoformat(text).replace(tzinfo=timezone.utc).timestamp() * 1_000_000)


def key48(s: Column) -> Column:
    """A string as a long: the first 48 bits of its md5. Equal in any SQL engine that has md5."""
    return F.conv(F.substring(F.md5(s), 1, 12), 16, 10).cast("long")


def between_days(ts: str, after: str, until: str) -> Column:
    """after < ts <= until on the raw column, so that the filter reaches the file scan."""
    return (F.col(ts) > F.to_timestamp_ntz(F.lit(after))) & (F.col(ts) <= F.to_timestamp_ntz(F.lit(until)))

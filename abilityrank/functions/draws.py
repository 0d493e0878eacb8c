"""Reproducible draws and scalar functions, as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = 16**13


def uniform_draw(*keys: Column | str | int) -> Column:
    """A uniform number in [0, 1) from the md5 of the keys joined by bars; any SQL engine has it too."""
    parts = [F.lit(str(k)) if isinstance(k, int) else F.col(k).cast("string") if isinstance(k, str) else k.cast("string") for k in keys]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts).cast("binary")), 1, 13), 16, 10).cast("long") / F.lit(float(SPAN))


def logistic(x: Column) -> Column:
    return 1.0 / (1.0 + F.exp(-x))


def unit_step(x: Column) -> Column:
    return F.when(x >= 0, 1.0).otherwise(0.0)


def entropy_of(share: Column) -> Column:
    """Aggregate: entropy, in nats, of shares that add up to 1."""
    return F.sum(F.when(share > 0, -share * F.log(share)).otherwise(0.0))


def micros(ts: str) -> Column:
    """Microseconds since 1970 of a wall-clock time, whatever the session's time zone."""
    return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', CAST({ts} AS TIMESTAMP_NTZ))")

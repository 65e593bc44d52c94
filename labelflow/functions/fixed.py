"""Fixed-point labels: a label is a whole number of billionths, so sums do not depend on their order and engines agree."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SCALE = 1_000_000_000
HALF = SCALE // 2


def rounded_div(num: Column, den: Column) -> Column:
    """Whole division of non-negative longs, rounded half up; null where the divisor is zero."""
    return F.when(den > 0, F.call_function("div", 2 * num + den, 2 * den))


def class_share(w0: Column, w1: Column) -> Column:
    """Class-1 share of two weights, in label units; half where both vanish."""
    return F.coalesce(rounded_div(w1 * SCALE, w0 + w1), F.lit(HALF).cast("long"))


def units(x: float) -> int:
    """A label or a threshold in label units."""
    return round(x * SCALE)


def as_label(f: Column) -> Column:
    return f / F.lit(float(SCALE))

"""Whole-number arithmetic on columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def div(a: Column, b: Column) -> Column:
    """Whole-number quotient; never by way of a DOUBLE."""
    return F.call_function("div", a, b)


def step_width(total: Column, places: Column) -> Column:
    """Width of a step when `total` ranks are cut into as many steps as there are intervals."""
    return F.greatest(F.lit(1).cast("long"), div(total + places - 1, places))

"""A name for a column's value inside an expression."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


def bound(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value), with value computed once a row: inside higher-order functions an expression is computed again for every element, a variable is not."""
    return F.get(F.transform(F.array(value), body), F.lit(0))

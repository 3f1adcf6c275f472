"""Symbolisers: from values to symbols of a small alphabet."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def bucket(col: Column, bounds: list[float], names: list[str]) -> Column:
    """names[k] for values up to bounds[k], names[-1] above all; null stays null."""
    out = F.when(col.isNull(), F.lit(None).cast("string"))
    for b, n in zip(bounds, names):
        out = out.when(col <= b, n)
    return out.otherwise(names[-1])


def sign(values: Column) -> Column:
    """An array of numbers as an array of + and -."""
    return F.transform(values, lambda x: F.when(x > 0, "+").otherwise("-"))


def tokens(text: Column) -> Column:
    """Words between white space."""
    return F.filter(F.split(text, r"[\x20\x09-\x0D]+"), lambda w: w != "")

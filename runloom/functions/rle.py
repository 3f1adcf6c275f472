"""Column functions over runs: none decodes."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from runloom.operators.alphabet import merged
from runloom.operators.tries import order_key_column
from runloom.types import Run


def literal(runs) -> Column:
    """A Python pattern as a runs column."""
    return F.array(*[F.struct(F.lit(s).alias("sym"), F.lit(int(n)).cast("long").alias("len")) for s, n in (Run(*r) for r in runs)])


def length(runs: Column) -> Column:
    return F.aggregate(runs, F.lit(0).cast("long"), lambda s, r: s + r["len"])


def run_count(runs: Column) -> Column:
    return F.size(runs).cast("long")


def max_run(runs: Column) -> Column:
    return F.array_max(F.transform(runs, lambda r: r["len"]))


def char_at(runs: Column, pos: Column | int) -> Column:
    """Symbol at a 0-based place; null outside."""
    pos = F.lit(pos) if isinstance(pos, int) else pos
    zero = F.struct(F.lit(0).cast("long").alias("at"), F.lit(None).cast("string").alias("sym"))
    return F.aggregate(runs, zero, lambda s, r: F.struct((s["at"] + r["len"]).alias("at"), F.when((pos >= s["at"]) & (pos < s["at"] + r["len"]), r["sym"]).otherwise(s["sym"]).alias("sym")), lambda s: s["sym"])


def _starts(runs: Column) -> Column:
    return F.transform(F.sequence(F.lit(0), F.greatest(F.size(runs) - 1, F.lit(0))), lambda i: length(F.slice(runs, 1, i)))


def substring(runs: Column, start: int, n: int) -> Column:
    """Runs of the n symbols from a 0-based place."""
    cut = F.zip_with(runs, _starts(runs), lambda r, at: F.struct(r["sym"].alias("sym"), (F.least(at + r["len"], F.lit(start + n).cast("long")) - F.greatest(at, F.lit(start).cast("long"))).alias("len")))
    return F.filter(cut, lambda r: r["len"] > 0)


def concat(a: Column, b: Column) -> Column:
    """Runs of the joined strings; the border run is one run where the symbols agree."""
    return merged(F.concat(a, b))


def reverse(runs: Column) -> Column:
    return F.reverse(runs)


def truncate(runs: Column) -> Column:
    return F.slice(runs, 1, F.greatest(F.size(runs) - 1, F.lit(0)))


def lcp(a: Column, b: Column) -> Column:
    """Length of the common prefix."""
    zero = F.struct(F.lit(0).cast("long").alias("n"), F.lit(True).alias("open"))
    pairs = F.zip_with(a, b, lambda x, y: F.struct((x["sym"] == y["sym"]).alias("same"), F.least(x["len"], y["len"]).alias("n"), (x["len"] == y["len"]).alias("full")))
    step = lambda s, p: F.struct(F.when(s["open"] & F.coalesce(p["same"], F.lit(False)), s["n"] + p["n"]).otherwise(s["n"]).alias("n"), (s["open"] & F.coalesce(p["same"] & p["full"], F.lit(False))).alias("open"))
    return F.aggregate(pairs, zero, step, lambda s: s["n"])


def compare(a: Column, b: Column) -> Column:
    """-1, 0 or 1: the order of the strings."""
    x, y = order_key_column(a), order_key_column(b)
    return F.when(x < y, -1).when(x > y, 1).otherwise(0)


def starts_with(runs: Column, pattern) -> Column:
    """The string begins with a pattern given in Python: all runs but the last equal, the last one no longer."""
    p = literal(pattern)
    k = len(tuple(pattern))
    head, last = F.slice(runs, 1, k - 1), F.get(runs, F.lit(k - 1))
    return F.coalesce((head == F.slice(p, 1, k - 1)) & (last["sym"] == F.element_at(p, k)["sym"]) & (last["len"] >= F.element_at(p, k)["len"]), F.lit(False))


def ends_with(runs: Column, pattern) -> Column:
    return starts_with(F.reverse(runs), tuple(reversed(tuple(pattern))))


def contains(runs: Column, pattern) -> Column:
    """The string holds a pattern: some window of runs meets it."""
    pattern = tuple(Run(*r) for r in pattern)
    k = len(pattern)
    if k == 1:
        return F.exists(runs, lambda r: (r["sym"] == pattern[0].sym) & (r["len"] >= pattern[0].len))
    inner = literal(pattern[1:-1]) if k > 2 else None

    def here(i: Column) -> Column:
        first, last = F.get(runs, i), F.get(runs, i + (k - 1))
        ok = (first["sym"] == pattern[0].sym) & (first["len"] >= pattern[0].len) & (last["sym"] == pattern[-1].sym) & (last["len"] >= pattern[-1].len)
        return ok & (F.slice(runs, i + 2, k - 2) == inner) if inner is not None else ok

    return F.when(F.size(runs) >= k, F.exists(F.sequence(F.lit(0), F.greatest(F.size(runs) - k, F.lit(0))), lambda i: F.coalesce(here(i), F.lit(False)))).otherwise(F.lit(False))

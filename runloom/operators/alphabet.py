"""Alphabet reduction: symbols become ranks; what only the text or only the patterns hold becomes one symbol each."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from runloom.functions.bind import bound

#: Ranks of symbols that only the text or only the patterns hold; shared symbols count from 1.
TEXT_ONLY, PATTERN_ONLY = 0, -1
#: Most shared symbols whose ranks travel with a closure.
MOST = 10_000


def mapping(patterns: DataFrame, text: DataFrame) -> DataFrame:
    """sym, rank, in_text, in_patterns of every symbol of either side.

    Both sides are reduced to distinct symbols first. Only shared symbols are ranked: at most as many as the patterns hold.
    """
    own = patterns.select(F.explode("runs.sym").alias("sym")).distinct().withColumn("in_patterns", F.lit(True))
    seen = text.select(F.explode("runs.sym").alias("sym")).distinct().withColumn("in_text", F.lit(True))
    both = own.join(seen, "sym", "full_outer").select("sym", F.coalesce("in_text", F.lit(False)).alias("in_text"), F.coalesce("in_patterns", F.lit(False)).alias("in_patterns"))
    shared = both.filter("in_text AND in_patterns").select(F.col("sym").alias("s"), F.row_number().over(Window.orderBy("sym")).cast("long").alias("r"))
    ranked = both.join(shared, F.col("sym") == F.col("s"), "left")
    return ranked.select("sym", F.coalesce("r", F.when(F.col("in_text"), TEXT_ONLY).otherwise(PATTERN_ONLY)).cast("long").alias("rank"), "in_text", "in_patterns")


def reduce(patterns, text: DataFrame) -> tuple[DataFrame, DataFrame]:
    """text and patterns over ranks. Equal neighbours that arise are merged; patterns with a symbol the text lacks are dropped.

    The ranks of up to MOST shared symbols travel with the closure; larger alphabets are joined. Both give the same.
    """
    from runloom.functions.encode import recoded
    from runloom.sources.readers import dictionary
    from runloom.sources.store import stored

    if not isinstance(patterns, DataFrame):
        patterns = dictionary(text.sparkSession, patterns)
    shared = stored(mapping(patterns, text).filter("in_text AND in_patterns").select("sym", "rank"), "alphabet")
    unknown = patterns.select("pattern_id", F.explode("runs.sym").alias("sym")).join(shared, "sym", "left_anti").select("pattern_id").distinct()
    own = patterns.join(unknown, "pattern_id", "left_anti").withColumnRenamed("pattern_id", "seq_id")
    if shared.limit(MOST + 1).count() > MOST:
        return joined(text, shared, TEXT_ONLY), joined(own, shared, PATTERN_ONLY).withColumnRenamed("seq_id", "pattern_id")
    ranks = {r["sym"]: r["rank"] for r in shared.collect()}
    return recoded(text, ranks, TEXT_ONLY), recoded(own, ranks, PATTERN_ONLY).withColumnRenamed("seq_id", "pattern_id")


def joined(rows: DataFrame, ranks: DataFrame, other: int) -> DataFrame:
    """seq_id, runs over ranks (sym, rank), others by `other`: runs are laid out, joined by symbol, and put together again by row."""
    keyed = rows.select("seq_id", "runs").withColumn("row", F.monotonically_increasing_id())
    long = keyed.select("seq_id", "row", F.posexplode_outer("runs").alias("k", "r")).join(ranks.withColumnRenamed("sym", "s"), F.col("r.sym") == F.col("s"), "left")
    one = F.when(F.col("k").isNotNull(), F.struct("k", F.coalesce("rank", F.lit(other)).alias("sym"), F.col("r.len").alias("len")))
    back = long.groupBy("seq_id", "row").agg(F.array_sort(F.collect_list(one)).alias("x"))
    return back.select("seq_id", merged(F.transform("x", lambda r: F.struct(r["sym"].alias("sym"), r["len"].alias("len")))).alias("runs"))


def merged(runs: Column) -> Column:
    """Runs with equal neighbours joined: between two places where the symbol changes the lengths are summed."""

    def joined(v: Column) -> Column:
        n = F.size(v)
        ends = F.filter(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: (i <= n) & ((i == n) | (F.get(v, i - 1)["sym"] != F.get(v, i)["sym"])))
        total = lambda a, b: F.aggregate(F.slice(v, a, b), F.lit(0).cast("long"), lambda s, r: s + r["len"])
        before = lambda border, k: F.when(k == 0, 0).otherwise(F.get(border, k - 1))
        return bound(ends, lambda border: F.transform(border, lambda e, k: F.struct(F.get(v, e - 1)["sym"].alias("sym"), total(before(border, k) + 1, e - before(border, k)).alias("len"))))

    return bound(runs, joined)

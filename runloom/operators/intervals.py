"""Plans over occurrences: choice of non-overlapping ones, coverage, overlap and distance joins."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def coverage(hits: DataFrame) -> DataFrame:
    """seq_id, covered: symbols of each sequence inside some occurrence. A running maximum of ends finds the gaps."""
    w = Window.partitionBy("seq_id").orderBy("start", "end").rowsBetween(Window.unboundedPreceding, -1)
    reach = F.coalesce(F.max("end").over(w), F.lit(0))
    return hits.select("seq_id", F.greatest(F.lit(0), F.col("end") - F.greatest("start", reach)).alias("new")).groupBy("seq_id").agg(F.sum("new").cast("long").alias("covered"))


def leftmost_longest(hits: DataFrame) -> DataFrame:
    """Non-overlapping occurrences: by start, of equal starts the longest, then the smallest id; each skips what overlaps the one before.

    The choice is sequential inside a sequence; it streams over rows ordered by sequence and start, without holding any.
    """
    ddl = ", ".join(f"{n} {t}" for n, t in hits.select("seq_id", "pattern_id", "start", "end").dtypes)
    ordered = hits.select("seq_id", "pattern_id", "start", "end").repartition("seq_id").sortWithinPartitions("seq_id", "start", F.desc("end"), "pattern_id")

    def pick(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seq, reach = object(), -1
        for batch in batches:
            keep = []
            for s, a, b in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), batch.column(3).to_pylist()):
                if s != seq:
                    seq, reach = s, -1
                keep.append(a >= reach)
                reach = max(reach, b) if a >= reach else reach
            yield batch.filter(pa.array(keep, pa.bool_()))

    return ordered.mapInArrow(pick, ddl)


def overlap(a: DataFrame, b: DataFrame, bin_width: int = 256) -> DataFrame:
    """Pairs of occurrences of one sequence that share a symbol. Both sides are cut into bins; a pair is kept in its first common bin."""
    cut = lambda df, k: df.select("seq_id", *[F.col(c).alias(f"{c}_{k}") for c in ("pattern_id", "start", "end")]).withColumn("bin", F.explode(F.sequence(F.expr(f"start_{k} div {bin_width}"), F.expr(f"(end_{k} - 1) div {bin_width}"))))
    both = cut(a, "a").join(cut(b, "b"), ["seq_id", "bin"]).filter("start_a < end_b AND start_b < end_a")
    return both.filter(F.col("bin") == F.expr(f"greatest(start_a, start_b) div {bin_width}")).drop("bin")


def within(a: DataFrame, b: DataFrame, gap: int) -> DataFrame:
    """Pairs where b begins at the end of a or up to gap symbols later. Bins of the gap's width: b's bin and the one before can hold a's end."""
    width = max(1, gap)
    left = a.select("seq_id", *[F.col(c).alias(f"{c}_a") for c in ("pattern_id", "start", "end")]).withColumn("bin", F.expr(f"end_a div {width}"))
    right = b.select("seq_id", *[F.col(c).alias(f"{c}_b") for c in ("pattern_id", "start", "end")]).withColumn("bin", F.explode(F.array(F.expr(f"start_b div {width}"), F.expr(f"start_b div {width} - 1"))))
    return left.join(right, ["seq_id", "bin"]).filter((F.col("start_b") >= F.col("end_a")) & (F.col("start_b") <= F.col("end_a") + gap)).drop("bin")


def asof(points: DataFrame, hits: DataFrame, at: str = "at") -> DataFrame:
    """points (seq_id, at) with last_end and last_pattern: the occurrence that ended last, at `at` or before; of equal ends the smallest id."""
    left = points.withColumn("__at", F.col(at).cast("long")).withColumn("__hit", F.lit(None).cast("struct<end:bigint,pattern_id:bigint>")).withColumn("__q", F.lit(1))
    right = hits.groupBy("seq_id", "end").agg(F.min("pattern_id").alias("pattern_id")).select("seq_id", F.col("end").alias("__at"), F.struct("end", "pattern_id").alias("__hit"), F.lit(0).alias("__q"))
    w = Window.partitionBy("seq_id").orderBy("__at", "__q").rowsBetween(Window.unboundedPreceding, 0)
    both = left.unionByName(right, allowMissingColumns=True).withColumn("last", F.last("__hit", ignorenulls=True).over(w)).filter("__q = 1")
    return both.withColumn("last_end", F.col("last.end")).withColumn("last_pattern", F.col("last.pattern_id")).drop("__at", "__hit", "__q", "last")

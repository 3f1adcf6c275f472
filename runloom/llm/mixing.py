"""Mixing sources to target weights (DataFrame functions only).

Every document gets a hash-random key. Keys are cut into ranges inside each source; the words of each range are
summed first, running sums over the ranges are taken on that small table, and only inside one range are documents
ordered. So the running word count of a source of any size is made without ordering the source in one task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from runloom.llm.common import written

#: Words, and words with the white space before them.
WORD = r"[^\x20\x09-\x0D]+"
SPACED_WORD = r"[\x20\x09-\x0D]*[^\x20\x09-\x0D]+"
#: Most times that a document is used.
MOST_EPOCHS = 3
#: Documents aimed at in one key range of a source.
RANGE_ROWS = 2_000


def n_words(text: Column) -> Column:
    """Number of words of a text; null and empty: 0."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame) -> DataFrame:
    """source, source_size -> weight, budget (long) and target (double).

    Sources in code point order, null last, weigh 1, 2, 3, repeating. Targets share the total by weight; those above
    MOST_EPOCHS times their source stop there and the excess is shared again. At the fixed point the stopped sources are
    those of smallest size for their weight, so one ordered pass finds them: no loop. One row per source.
    """
    everything = Window.partitionBy()
    by_name = Window.orderBy(F.col("source").isNull(), F.col("source"))
    ranked = sizes.withColumn("weight", (F.row_number().over(by_name) - 1) % 3 + 1).withColumn("cap", F.col("source_size") * MOST_EPOCHS)
    by_need = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").isNull(), F.col("source"))
    before = by_need.rowsBetween(Window.unboundedPreceding, -1)
    after = by_need.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    ranked = (
        ranked.withColumn("total", F.sum("source_size").over(everything))
        .withColumn("left", F.col("total") - F.coalesce(F.sum("cap").over(before), F.lit(0)))
        .withColumn("weights", F.sum("weight").over(after))
        .withColumn("fits", F.col("left") * F.col("weight") <= F.col("cap") * F.col("weights"))
        .withColumn("place", F.row_number().over(by_need))
    )
    # the first source that fits, in order of need, ends the stopped ones; it sets what one unit of weight gets
    cut = F.min(F.when(F.col("fits"), F.struct("place", "left", "weights"))).over(everything)
    ranked = ranked.withColumn("cut", cut)
    stopped = F.col("cut").isNull() | (F.col("place") < F.col("cut.place"))
    target = F.when(stopped, F.col("cap").cast("double")).otherwise(F.col("cut.left") * F.col("weight") / F.col("cut.weights"))
    budget = F.when(stopped, F.col("cap")).otherwise(F.expr("(cut.left * weight) div cut.weights"))
    return ranked.select("source", "source_size", target.alias("target"), budget.cast("long").alias("budget"))


def _drawn(docs: DataFrame, seed: int, id_col: str, source_col: str, text_col: str) -> DataFrame:
    """docs with __mix_source, __mix_size and a hash-random key of 63 bits, made from id and text."""
    spelled = F.concat_ws("|", F.lit(str(seed)), F.coalesce(F.col(id_col).cast("string"), F.lit("")), F.coalesce(F.col(text_col).cast("string"), F.lit("")))
    draw = F.shiftleft(F.conv(F.substring(F.md5(spelled), 1, 15), 16, 10).cast("long"), 3)  # 60 random bits of 63
    return docs.withColumns({"__mix_source": F.col(source_col).cast("string"), "__mix_size": n_words(F.col(text_col)), "__mix_draw": draw})


def source_cuts(rows: DataFrame) -> DataFrame:
    """Rows of __mix_source, __mix_size, __mix_draw -> one row per source: its size, target, whole epochs, and the key at which the last epoch is cut.

    Keys below cut_draw are in the last epoch; the cut_rows equal to it, alike in id and text, take the cut_words left one after the other.
    """
    source = rows.groupBy(F.col("__mix_source").alias("source")).agg(F.sum("__mix_size").alias("source_size"), F.count(F.lit(1)).alias("n"))
    source = written(source.coalesce(1), "mix-sources")
    targets = source_targets(source.select("source", "source_size"))
    ranges = F.greatest(F.lit(1), F.ceil(F.col("n") / RANGE_ROWS)).cast("long")
    plan = (
        targets.alias("t")
        .join(source.select(F.col("source").alias("name"), ranges.alias("ranges")), F.col("source").eqNullSafe(F.col("name")))
        .withColumn("epochs", F.expr("CASE WHEN source_size > 0 THEN budget div source_size ELSE 0 END"))
        .withColumn("rest", F.col("budget") - F.col("epochs") * F.col("source_size"))
        .drop("name")
    )
    plan = written(plan.coalesce(1), "mix-plan")
    # ranges of the key inside a source, their words, and the running words before each
    part = F.expr("shiftright(shiftright(__mix_draw, 32) * ranges, 31)")
    placed = rows.join(plan.select("source", "ranges", "rest"), F.col("__mix_source").eqNullSafe(F.col("source"))).withColumn("part", part)
    sums = placed.groupBy("source", "part").agg(F.sum("__mix_size").alias("words"), F.max("rest").alias("rest"))
    running = Window.partitionBy("source").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("base", F.coalesce(F.sum("words").over(running), F.lit(0)))
    cut_part = sums.filter((F.col("base") <= F.col("rest")) & (F.col("rest") < F.col("base") + F.col("words"))).select(F.col("source").alias("name"), F.col("part").alias("cut_part"), "base")
    # only the range in which the cut falls is ordered
    near = placed.join(cut_part, F.col("source").eqNullSafe(F.col("name")) & (F.col("part") == F.col("cut_part")))
    near = near.groupBy("source", "__mix_draw").agg(F.sum("__mix_size").alias("words"), F.count(F.lit(1)).alias("rows"), F.max("rest").alias("rest"), F.max("base").alias("base"))
    ordered = Window.partitionBy("source").orderBy("__mix_draw").rowsBetween(Window.unboundedPreceding, -1)
    near = near.withColumn("left", F.col("rest") - F.col("base") - F.coalesce(F.sum("words").over(ordered), F.lit(0)))
    near = near.filter((F.col("left") >= 0) & (F.col("left") < F.col("words")))
    cut = near.select(F.col("source").alias("name"), F.col("__mix_draw").alias("cut_draw"), F.col("left").alias("cut_words"), F.col("rows").alias("cut_rows"))
    return written(plan.join(cut, F.col("source").eqNullSafe(F.col("name")), "left").drop("name", "rest", "ranges", "budget").coalesce(1), "mix-cuts")


#: Words that a row takes of its source's last epoch. No cut: the epochs end with a whole one. __mix_before: rows before it at the cut.
_LAST = """CASE WHEN cut_draw IS NULL THEN 0 WHEN __mix_draw < cut_draw THEN __mix_size
           WHEN __mix_draw = cut_draw THEN least(greatest(cut_words - __mix_before * __mix_size, 0), __mix_size) ELSE 0 END"""
#: Parts into which rows at a cut are dealt while they are numbered.
SALTS = 64


def _numbered(rows: DataFrame, cuts: DataFrame, prefix: str = "") -> DataFrame:
    """rows, which cuts are joined to, with __mix_before. Rows alike at a cut are numbered in parts, and the parts' counts are summed: no task holds all."""
    if cuts.filter("cut_rows > 1").isEmpty():
        return rows.withColumn("__mix_before", F.lit(0).cast("long"))
    at_cut = F.coalesce(F.col("__mix_draw") == F.col(f"{prefix}cut_draw"), F.lit(False))
    ties = written(rows.filter(at_cut).withColumn("__mix_salt", F.pmod(F.monotonically_increasing_id(), F.lit(SALTS))), "mix-ties")
    counts = ties.groupBy(F.col("__mix_source").alias("__mix_of"), F.col("__mix_salt").alias("__mix_part")).agg(F.count(F.lit(1)).alias("n"))
    running = Window.partitionBy("__mix_of").orderBy("__mix_part").rowsBetween(Window.unboundedPreceding, -1)  # SALTS rows a source
    counts = counts.select("__mix_of", "__mix_part", F.coalesce(F.sum("n").over(running), F.lit(0)).alias("__mix_first"))
    number = F.row_number().over(Window.partitionBy("__mix_source", "__mix_salt").orderBy(F.lit(0))) - 1
    ties = ties.withColumn("__mix_number", number).join(F.broadcast(counts), F.col("__mix_source").eqNullSafe(F.col("__mix_of")) & (F.col("__mix_salt") == F.col("__mix_part")))
    ties = ties.withColumn("__mix_before", F.col("__mix_first") + F.col("__mix_number")).drop("__mix_salt", "__mix_of", "__mix_part", "__mix_first", "__mix_number")
    return rows.filter(~at_cut).withColumn("__mix_before", F.lit(0).cast("long")).unionByName(ties)


def mix(docs: DataFrame, seed: int = 17, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text") -> DataFrame:
    """doc_id, size, source_size, target, taken of every document.

    taken counts repeats: whole epochs of the source, then documents in key order up to the budget, the last one in part.
    Null text: size 0, taken 0. A null source is a source of its own. Rows alike in id and text share one key; if the cut
    falls on them, some are taken whole, one in part and the others not, so reruns agree. An empty table gives no rows. Other
    columns are not read.
    """
    rows = _drawn(docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), F.col(text_col).alias("text")), seed, "doc_id", "source", "text")
    rows = written(rows.select("doc_id", "__mix_source", "__mix_size", "__mix_draw"), "mix")  # a few bytes a document: texts are read once
    cuts = source_cuts(rows)
    taken = F.col("epochs") * F.col("__mix_size") + F.expr(_LAST)
    return _numbered(rows.join(cuts, F.col("__mix_source").eqNullSafe(F.col("source"))), cuts).select(
        "doc_id", F.col("__mix_size").alias("size"), "source_size", "target", taken.cast("long").alias("taken")
    )


def apply_mix(docs: DataFrame, seed: int = 17) -> DataFrame:
    """docs with the mix in effect: a document taken k times stands k times; the one at a source's cut ends after its last word taken.

    Same columns and types as docs; n_chars, where there is one, follows a cut text. Documents without words stay once.
    Nulls, ties and repeated rows as in mix().
    """
    drawn = _drawn(docs, seed, "doc_id", "source", "text")
    rows = written(drawn.select("__mix_source", "__mix_size", "__mix_draw"), "mix")
    cuts = source_cuts(rows)
    names = ("epochs", "cut_draw", "cut_words", "cut_rows")
    own = cuts.select(F.col("source").alias("__mix_name"), *[F.col(c).alias(f"__mix_{c}") for c in names])
    joined = drawn.join(own, F.col("__mix_source").eqNullSafe(F.col("__mix_name")))
    both = _numbered(joined, cuts, "__mix_").withColumn("__mix_last", F.expr(_LAST.replace("cut_", "__mix_cut_")).cast("int"))
    whole = F.col("__mix_epochs").cast("int") + F.when(F.col("__mix_last") == F.col("__mix_size"), 1).otherwise(0)
    part = F.when((F.col("__mix_last") > 0) & (F.col("__mix_last") < F.col("__mix_size")), F.array("__mix_last")).otherwise(F.expr("cast(array() as array<int>)"))
    copies = F.when(F.col("__mix_size") == 0, F.array(F.lit(-1))).otherwise(F.concat(F.array_repeat(F.lit(-1), whole), part))
    both = both.withColumn("__mix_words", F.explode(copies))
    cut_text = F.array_join(F.slice(F.regexp_extract_all("text", F.lit(SPACED_WORD), F.lit(0)), 1, F.greatest(F.col("__mix_words"), F.lit(0))), "")
    text = F.when(F.col("__mix_words") < 0, F.col("text")).otherwise(cut_text)
    out = [text.alias(c) if c == "text" else F.when(F.col("__mix_words") < 0, F.col(c)).otherwise(F.length(cut_text)).cast(t).alias(c) if c == "n_chars" else F.col(f"`{c}`") for c, t in docs.dtypes]
    return both.select(*out)

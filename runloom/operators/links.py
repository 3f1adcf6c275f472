"""Links of the run trie by joins, for dictionaries that the driver does not hold.

A node is a prefix of a pattern in whole runs. Its simple link is the longest other node that its string ends with: some of
its runs are dropped, and the first run that is left may be longer than the node's. The group link drops the first run at
least. Nodes meet their suffixes by the hash of what follows the first run, so a pattern of r runs makes r * (r + 1) / 2 rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _spelled(runs):
    return F.array_join(F.transform(runs, lambda r: F.concat(r["sym"].cast("string"), r["len"].cast("string"))), "")


def trie_nodes(patterns: DataFrame) -> DataFrame:
    """runs of every node but the root: distinct prefixes of the patterns of two runs or more."""
    prefix = F.transform(F.sequence(F.lit(1), F.size("runs")), lambda d: F.slice(F.col("runs"), F.lit(1), d))
    return patterns.filter(F.size("runs") > 1).select(F.explode(prefix).alias("runs")).distinct()


def trie_parents(patterns: DataFrame) -> DataFrame:
    """node, parent of every node but the root, spelled as symbol and length; the root is the empty parent."""
    return trie_nodes(patterns).select(_spelled(F.col("runs")).alias("node"), _spelled(F.slice("runs", F.lit(1), F.size("runs") - 1)).alias("parent"))


def links(patterns: DataFrame) -> DataFrame:
    """node, simple_link, group_link, report_ix of every node and the root, spelled as symbol and length; no link is the root, no report index is -1.

    report_ix: the pattern whose string without its last run is the longest that the node's string ends with; the smallest id.
    """
    rest = lambda runs: F.slice(runs, F.lit(2), F.greatest(F.size(runs) - 1, F.lit(0)))
    nodes = trie_nodes(patterns)
    heads = nodes.select(F.get("runs", F.lit(0))["sym"].alias("sym"), F.get("runs", F.lit(0))["len"].alias("len"), rest(F.col("runs")).alias("rest"), F.col("runs").alias("to"))
    heads = heads.withColumn("h", F.xxhash64("rest"))
    places = F.transform(F.sequence(F.lit(1), F.size("runs")), lambda i: F.struct(i.alias("i"), F.slice(F.col("runs"), i, F.size("runs")).alias("s")))
    asked = nodes.select("runs", F.explode(places).alias("p")).select("runs", F.col("p.i").alias("i"), F.get("p.s", F.lit(0))["sym"].alias("asym"), F.get("p.s", F.lit(0))["len"].alias("most"), rest(F.col("p.s")).alias("arest"))
    asked = asked.withColumn("ah", F.xxhash64("arest"))
    met = asked.join(heads, (F.col("asym") == F.col("sym")) & (F.col("ah") == F.col("h")) & (F.col("arest") == F.col("rest")) & (F.col("len") <= F.col("most")))
    longest = F.struct(-F.col("i"), "len")
    found = met.groupBy("runs").agg(
        F.max_by(F.when((F.col("i") > 1) | (F.col("len") < F.col("most")), F.col("to")), F.when((F.col("i") > 1) | (F.col("len") < F.col("most")), longest)).alias("simple"),
        F.max_by(F.when(F.col("i") > 1, F.col("to")), F.when(F.col("i") > 1, longest)).alias("grouped"),
        F.collect_list(F.struct(F.lit(0).alias("none"), F.col("i"), (-F.col("len")).alias("short"), F.col("to"))).alias("ends"),
    )
    own = patterns.filter(F.size("runs") > 1).groupBy(F.slice("runs", F.lit(1), F.size("runs") - 1).alias("to")).agg(F.min("pattern_id").alias("ix"))
    reports = found.select("runs", F.explode("ends").alias("e")).select("runs", F.col("e.to").alias("to"), F.struct("e.i", "e.short").alias("place")).join(own, "to")
    reports = reports.groupBy("runs").agg(F.min_by("ix", "place").alias("report_ix"))
    out = found.join(reports, "runs", "left")
    spelled = lambda c: F.coalesce(_spelled(F.col(c)), F.lit(""))
    rows = out.select(_spelled(F.col("runs")).alias("node"), spelled("simple").alias("simple_link"), spelled("grouped").alias("group_link"), F.coalesce("report_ix", F.lit(-1)).cast("long").alias("report_ix"))
    root = patterns.sparkSession.createDataFrame([("", "", "", -1)], "node string, simple_link string, group_link string, report_ix long")
    return rows.unionByName(root)

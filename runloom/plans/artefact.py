"""A dictionary as a versioned Parquet artefact: patterns, and the run trie's nodes with their links and report indexes."""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from runloom.operators import links
from runloom.operators.match import pattern_list
from runloom.operators.tries import run_trie_nodes
from runloom.sources.readers import dictionary


def version_of(patterns) -> str:
    return hashlib.sha256(repr(sorted(pattern_list(patterns))).encode()).hexdigest()[:16]


def save(spark: SparkSession, patterns, path: str) -> str:
    """Writes path/patterns, path/nodes and path/links; the version is a column of all."""
    version = version_of(patterns)
    rows = patterns if isinstance(patterns, DataFrame) else dictionary(spark, patterns)
    rows.withColumn("version", F.lit(version)).write.parquet(f"{path}/patterns")
    run_trie_nodes(rows).withColumn("version", F.lit(version)).write.parquet(f"{path}/nodes")
    links.links(rows).withColumn("version", F.lit(version)).write.parquet(f"{path}/links")
    return version


def load(spark: SparkSession, path: str) -> DataFrame:
    """The patterns; fails if the artefact was written half."""
    rows = spark.read.parquet(f"{path}/patterns")
    found = {part: {r["version"] for r in spark.read.parquet(f"{path}/{part}").select("version").distinct().collect()} for part in ("patterns", "nodes", "links")}
    if len(set().union(*found.values())) > 1:
        raise ValueError(f"the artefact's parts are of versions {found}")
    return rows.drop("version")


def load_links(spark: SparkSession, path: str) -> DataFrame:
    """node, simple_link, group_link, report_ix as they were written: what a plan over the trie joins, without building an automaton."""
    return spark.read.parquet(f"{path}/links").drop("version")

"""A Spark data source for .rle files: lines of an id, a tab and runs such as 4a3b."""

from __future__ import annotations

import re
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from runloom.sources.readers import parse_rle

_RUN = re.compile(r"(\d+)(\D)", re.S)


class RleDataSource(DataSource):
    """spark.read.format("rle").load(folder): seq_id, runs. One partition a file. The folder must be a local or mounted path of all executors; read_lines() takes any path that Spark reads."""

    @classmethod
    def name(cls) -> str:
        return "rle"

    def schema(self) -> str:
        return "seq_id bigint, runs array<struct<sym:string,len:bigint>>"

    def reader(self, schema) -> DataSourceReader:
        return RleReader(self.options["path"])


class RleReader(DataSourceReader):
    def __init__(self, path: str) -> None:
        self.path = path

    def partitions(self) -> list[InputPartition]:
        from pathlib import Path

        return [InputPartition(str(p)) for p in sorted(Path(self.path.removeprefix("file://").removeprefix("file:")).iterdir()) if not p.name.startswith((".", "_"))]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        with open(partition.value, encoding="utf-8") as lines:
            for line in lines:
                name, _, runs = line.rstrip("\n").partition("\t")
                found = _RUN.findall(runs)
                if sum(len(n) + 1 for n, _ in found) != len(runs):
                    raise ValueError(f"no runs of characters other than digits: {runs[:80]!r}")
                yield int(name), [(sym, int(n)) for n, sym in found]


def read_lines(spark: SparkSession, path: str) -> DataFrame:
    """seq_id, runs of .rle files below any path that Spark's readers open."""
    lines = spark.read.text(path).select(F.split("value", "\t", 2).alias("x"))
    return lines.select(F.get("x", F.lit(0)).cast("long").alias("seq_id"), parse_rle(F.get("x", F.lit(1))).alias("runs"))


def write_lines(df: DataFrame, path: str) -> None:
    """seq_id, rle as lines of text."""
    df.selectExpr("concat_ws('\t', seq_id, rle) AS value").write.text(path)

"""Sources and sinks of runs and dictionaries."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from runloom.types import pattern_runs

RUN_DDL = "array<struct<sym:string,len:bigint>>"


def read(spark: SparkSession, sf_dir: str, name: str, where=None) -> DataFrame:
    """A given table; where reaches the Parquet scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.filter(where) if where is not None else df


def read_text(spark: SparkSession, path: str, whole: bool = False) -> DataFrame:
    """seq_id, text: lines of text files, or whole files; the id is a hash of the file name and, for lines, of the place: split and number in it."""
    if whole:
        files = spark.read.option("wholetext", True).text(path)
        return files.select(F.xxhash64(F.input_file_name()).alias("seq_id"), F.col("value").alias("text"))
    number = F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))
    lines = spark.read.text(path).select("value", "_metadata.file_path", "_metadata.file_block_start", number.alias("number"))
    return lines.select(F.xxhash64("file_path", "file_block_start", "number").alias("seq_id"), F.col("value").alias("text"))


def read_csv(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).option("header", True).csv(path)


def read_json(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).json(path)


def read_orc(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.orc(path)


def parse_rle(col: Column, fmt: str = "compact") -> Column:
    """Runs from text: compact "4a3b" (a count before each character, which is no digit; other texts are an error) or json [["a",4],["b",3]]."""
    if fmt == "json":
        pairs = F.from_json(col, "array<array<string>>")
        return F.transform(pairs, lambda p: F.struct(F.get(p, F.lit(0)).alias("sym"), F.get(p, F.lit(1)).cast("long").alias("len")))
    well_formed = F.when(col.rlike(r"(?s)^(\d+\D)*$"), col).when(col.isNotNull(), F.raise_error(F.concat(F.lit("no compact runs: "), col)).cast("string"))
    parts = F.regexp_extract_all(well_formed, F.lit(r"(?s)\d+[^\d]"), F.lit(0))
    return F.transform(parts, lambda p: F.struct(F.substring(p, -1, 1).alias("sym"), F.regexp_extract(p, r"^\d+", 0).cast("long").alias("len")))


def dictionary(spark: SparkSession, patterns) -> DataFrame:
    """DICT from Python: (id, runs), or (id, string or list of symbols). pattern_id, runs, m, m_runs, last_sym, last_len, trunc."""
    rows = []
    for name, p in patterns:
        runs = [tuple(r) for r in pattern_runs(p)]
        rows.append((name, runs))
    sym = "bigint" if rows and rows[0][1] and isinstance(rows[0][1][0][0], int) else "string"
    df = spark.createDataFrame(rows, f"pattern_id long, runs array<struct<sym:{sym},len:bigint>>")
    return with_parts(df)


def with_parts(df: DataFrame) -> DataFrame:
    """The derived columns of a DICT."""
    last = F.element_at("runs", -1)
    return df.select(
        "pattern_id", "runs", F.aggregate("runs", F.lit(0).cast("long"), lambda s, r: s + r["len"]).alias("m"), F.size("runs").cast("long").alias("m_runs"),
        last["sym"].alias("last_sym"), last["len"].alias("last_len"), F.slice("runs", 1, F.size("runs") - 1).alias("trunc"),
    )


def dictionary_from_text(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """DICT from a string column; null and empty strings are left out."""
    from runloom.functions.encode import text_runs

    rows = df.filter(F.length(text_col) > 0).select(F.col(id_col).cast("long").alias("pattern_id"), text_runs(F.col(text_col)).alias("runs"))
    return with_parts(rows)


def write_rle(df: DataFrame, path: str, buckets: int = 0) -> None:
    """Runs as Parquet; with buckets, laid out in folders by a hash of the sequence, sorted inside."""
    if not buckets:
        df.write.parquet(path)
        return
    keyed = df.withColumn("bucket", F.pmod(F.xxhash64("seq_id"), F.lit(buckets)).cast("int"))
    keyed.repartition("bucket").sortWithinPartitions("bucket", "seq_id").write.partitionBy("bucket").parquet(path)


def read_rle(spark: SparkSession, path: str) -> DataFrame:
    df = spark.read.parquet(path)
    return df.drop("bucket") if "bucket" in df.columns else df

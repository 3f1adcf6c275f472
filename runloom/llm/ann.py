"""Approximate nearest neighbours by largest inner product: multiprobe p-stable hashing.

Vectors are scaled by the largest norm and lifted by one component, so that a larger inner product is a smaller
distance. Each of TABLES tables projects them on HASHES Gaussian directions, shifts each line at random and cuts it into
cells of WIDTH (the outer of CELLS cells are open); a bucket is one cell per direction. A query visits buckets in the order
of the estimated chance that a neighbour at the usual product falls there, until SUCCESS of that chance is covered. That
product comes from a bounded sample; every row is indexed. Rows of a table are dealt into blocks of about BLOCK rows of
neighbouring buckets; large buckets are split. Queries go to the blocks that hold a bucket they visit (vectors are copied
for each QUERY_BLOCK queries only). A block scores the rows of the visited buckets and keeps the best of each query; the
tables' candidates are merged and scored again on the original vectors.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from runloom.llm.common import tidy, written

TABLES = 3
HASHES = 6
CELLS = 4
#: Rows of the sample that sets cuts and the usual product.
SAMPLE = 4_096
#: Sample rows that act as queries when the usual product is measured.
SAMPLE_QUERIES = 128
#: Width of a cell; projections of scaled vectors have a standard deviation of about 1.
WIDTH = 0.75
SUCCESS = 0.55
BLOCK = 32_768
#: Queries that meet a block in one task: their vectors take 512 bytes each.
QUERY_BLOCK = 32_768
TOP = 20


def usable(df: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """id, v (array<double>) of the rows that take part: no null vector or component, none that is not finite, not all zero."""
    v = F.col(vector_col).cast("array<double>")
    fine = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return df.select(F.col(id_col).alias("id"), v.alias("v")).filter(F.col("id").isNotNull() & F.col("v").isNotNull() & fine & F.exists("v", lambda x: x != 0.0))


def _normal(x: np.ndarray) -> np.ndarray:
    """The normal distribution function, to two digits."""
    return 1 / (1 + np.exp(-np.clip(1.5976 * x + 0.070565776 * x**3, -60, 60)))


@dataclass
class Index:
    """Directions (tables, dim + 1, HASHES), borders of the cells of each line, the sample's largest norm and usual product of a query and its TOP-th neighbour."""

    directions: np.ndarray
    cuts: np.ndarray
    norm: float
    near: float
    dim: int
    everything: bool = False  # no more rows than answers: all buckets are visited

    @classmethod
    def fit(cls, sample: np.ndarray, queries: np.ndarray, population: int, seed: int = 7) -> Index:
        dim = sample.shape[1]
        rng = np.random.default_rng(seed)
        norm = float(np.sqrt((sample**2).sum(1).max()))
        directions, shift = rng.normal(size=(TABLES, dim + 1, HASHES)), rng.uniform(-WIDTH / 2, WIDTH / 2, (TABLES, HASHES, 1))
        index = cls(directions, WIDTH * (np.arange(1, CELLS) - CELLS / 2) + shift, norm, 1.0, dim)
        # the product that TOP of the population reach, read off the sample
        scores = np.sort(queries @ sample.T, axis=1)
        place = max(1, round(TOP * len(sample) / max(population, 1)))
        index.near = float(np.median(scores[:, -min(place + 1, scores.shape[1])])) / norm**2
        return index

    def project(self, x: np.ndarray, lift: bool) -> np.ndarray:
        """(tables, rows, HASHES). Queries are not lifted."""
        x = x / self.norm
        extra = np.sqrt(np.maximum(0, 1 - (x**2).sum(1))) if lift else np.zeros(len(x))
        return np.stack([np.concatenate([x, extra[:, None]], axis=1) @ d for d in self.directions])

    def buckets(self, x: np.ndarray) -> np.ndarray:
        """(tables, rows) bucket numbers below CELLS ** HASHES."""
        p = self.project(x, lift=True)
        out = np.zeros(p.shape[:2], np.int64)
        for j in range(HASHES):
            for t in range(TABLES):
                out[t] = out[t] * CELLS + np.searchsorted(self.cuts[t, j], p[t, :, j], "right")
        return out

    def cells(self, x: np.ndarray, table: int) -> np.ndarray:
        """(HASHES, rows, CELLS): the chance that a query's neighbour falls into each cell of each line."""
        p = self.project(x, lift=False)[table]
        # given its query's projection, a neighbour's is normal: the directions are Gaussian
        square = np.maximum((x**2).sum(1, keepdims=True) / self.norm**2, 1e-12)
        p = p * (self.near / square)
        spread = np.sqrt(np.maximum(1 - self.near**2 / square, 1e-3))
        edge = (self.cuts[table][:, None] - p.T[:, :, None]) / spread[None]
        below = np.concatenate([np.zeros((HASHES, len(x), 1)), _normal(edge), np.ones((HASHES, len(x), 1))], axis=2)
        return np.diff(below, axis=2)

    def visits(self, x: np.ndarray, table: int) -> tuple[np.ndarray, np.ndarray]:
        """(rows, buckets): True for the buckets that a query visits; and the smallest chance among them."""
        chance = np.ones((len(x), 1))
        for cell in self.cells(x, table):
            chance = (chance[:, :, None] * cell[:, None]).reshape(len(x), -1)
        if self.everything:
            return np.ones_like(chance, bool), np.full(len(x), -1.0)
        ordered = -np.sort(-chance, axis=1)
        before = np.cumsum(ordered, axis=1) - ordered
        least = np.take_along_axis(ordered, (before < SUCCESS).sum(1, keepdims=True) - 1, 1)
        return chance >= least, least[:, 0]

    def visited(self, x: np.ndarray, table: int, buckets: np.ndarray, least: np.ndarray) -> np.ndarray:
        """(rows, buckets): visits() for some buckets, from the smallest chance; products are made in the same order."""
        chance, cells = np.ones((len(x), len(buckets))), self.cells(x, table)
        for j in range(HASHES):
            chance = chance * cells[j][:, buckets // CELLS ** (HASHES - 1 - j) % CELLS]
        return chance >= least[:, None]


def _matrix(column: pa.Array, dim: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim)


def _bucketed(batches: Iterator[pa.RecordBatch], index) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        if batch.num_rows:
            b = index.value.buckets(_matrix(batch.column(1), index.value.dim))
            for t in range(TABLES):
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([t] * batch.num_rows, pa.int32()), pa.array(b[t].astype(np.int32))], ["id", "v", "tab", "bucket"])


def _visited_blocks(batches: Iterator[pa.RecordBatch], index, blocks) -> Iterator[pa.RecordBatch]:
    """A row for each query and block of a table with a bucket it visits."""
    for batch in batches:
        x = _matrix(batch.column(1), index.value.dim) if batch.num_rows else np.zeros((0, index.value.dim))
        for lo in range(0, len(x), 256):
            for t, owner in enumerate(blocks.value):
                seen, least = index.value.visits(x[lo : lo + 256], t)
                for block, members in owner.items():
                    rows = np.flatnonzero(seen[:, members].any(1))
                    if len(rows):
                        part = batch.take(pa.array(rows + lo))
                        yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(least[rows]), pa.array([t] * len(rows), pa.int32()), pa.array([block] * len(rows), pa.int32())], ["qid", "q", "least", "tab", "block"])


def best(q: np.ndarray, qid: np.ndarray, x: np.ndarray, xid: np.ndarray, mask: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Query place, id and exact score of the TOP best ids of each query: largest score, then smallest id; a query's own id is left out.

    An id of several rows counts once, by its best."""
    s = q @ x.T
    s[qid[:, None] == xid[None]] = -np.inf
    if mask is not None:
        s[~mask] = -np.inf
    out: list[list] = [[], [], []]
    by_id = np.argsort(xid, kind="stable")
    starts = np.flatnonzero(np.concatenate([[True], np.diff(xid[by_id]) != 0]))
    of_id = s if len(starts) == s.shape[1] else np.maximum.reduceat(s[:, by_id], starts, axis=1)
    k = min(TOP, of_id.shape[1])
    floor = np.partition(of_id, -k, axis=1)[:, -k]
    slack = 1e-9 * (1 + np.abs(np.where(np.isfinite(floor), floor, 0)))
    for i in range(len(q)):
        at = np.flatnonzero((s[i] >= floor[i] - slack[i]) & (s[i] > -np.inf)) if np.isfinite(floor[i]) else np.flatnonzero(s[i] > -np.inf)
        exact = (x[at] * q[i]).sum(1)
        order = np.lexsort((xid[at], -exact))
        order = order[np.sort(np.unique(xid[at][order], return_index=True)[1])][:TOP]
        out[0].append(np.full(len(order), i))
        out[1].append(xid[at][order])
        out[2].append(exact[order])
    return tuple(np.concatenate(c) if c else np.zeros(0) for c in out)


def _score(key: tuple, rows: pa.Table, asked: pa.Table, index) -> pa.Table:
    """One block of rows (about BLOCK) against one block of queries (about QUERY_BLOCK)."""
    model, t = index.value, key[0].as_py()
    out: list[list] = [[np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)]]
    seen: list[list] = [[np.zeros(0, np.int64)], [np.zeros(0, np.int64)]]
    if rows.num_rows and asked.num_rows:
        x, xid = _matrix(rows.column("v").combine_chunks(), model.dim), rows.column("id").to_numpy()
        buckets, bucket = np.unique(rows.column("bucket").to_numpy().astype(np.int64), return_inverse=True)
        for lo in range(0, asked.num_rows, 256):
            part = asked.slice(lo, 256)
            q, qid = _matrix(part.column("q").combine_chunks(), model.dim), part.column("qid").to_numpy()
            visited = model.visited(q, t, buckets, part.column("least").to_numpy())[:, bucket]
            place, vec, score = best(q, qid, x, xid, visited)
            for c, v in zip(out, (qid[place.astype(np.int64)], vec.astype(np.int64), score)):
                c.append(v)
            seen[0].append(qid)
            seen[1].append(visited.sum(1))
    found, compared = [pa.array(np.concatenate(c)) for c in out], [pa.array(np.concatenate(c)) for c in seen]
    schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64()), ("compared", pa.int64())])
    tidy()
    return pa.concat_tables([
        pa.table([*found, pa.nulls(len(found[0]), pa.int64())], schema=schema),
        pa.table([compared[0], pa.nulls(len(compared[0]), pa.int64()), pa.nulls(len(compared[0]), pa.float64()), compared[1].cast(pa.int64())], schema=schema),
    ])


def search(rows: DataFrame, queries: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score, compared: each query's TOP nearest rows found but its own, nearest first, ties by smaller id.

    compared: rows of visited buckets, all tables together.

    Rows with a null id, or a vector that is null, zero, or holds null or non-finite components, take no part; so do rows
    whose length differs from the sample's most frequent one. Repeated ids count once, by their largest score. Fewer rows than
    TOP: all of them. Empty tables give no rows. Other columns are not read.
    """
    spark = rows.sparkSession
    schema = "query_id long, rank int, vec_id long, score double, compared long"
    base = usable(rows, id_col, vector_col)
    lengths = base.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), "n").limit(1).collect()
    if not lengths:
        return spark.createDataFrame([], schema)
    dim = lengths[0]["n"]
    base = base.filter(F.size("v") == dim).select(F.col("id").cast("long").alias("id"), "v")
    base = written(base.dropDuplicates(["id", "v"]), "ann-rows")  # copies of a row are one
    asked = usable(queries, id_col, vector_col).filter(F.size("v") == dim).select(F.col("id").cast("long").alias("qid"), F.col("v").alias("q"))
    sample = base.orderBy(F.xxhash64("id"), "id").limit(SAMPLE).toArrow()
    x = _matrix(sample.column("v").combine_chunks(), dim)
    peak = base.agg(F.max(F.expr("aggregate(v, 0D, (s, y) -> s + y * y)")).alias("m"), F.count_distinct("id").alias("n")).first()
    model = Index.fit(x, x[:SAMPLE_QUERIES], peak["n"])
    model.everything = peak["n"] <= TOP + 1
    model.norm, ratio = float(np.sqrt(peak["m"])), float(np.sqrt(peak["m"])) / model.norm
    model.near /= max(1.0, ratio) ** 2  # the corpus may have longer vectors than the sample
    index = spark.sparkContext.broadcast(model)
    placed = written(base.mapInArrow(lambda b: _bucketed(b, index), "id long, v array<double>, tab int, bucket int"), "ann-index")
    # the directory: at most TABLES * CELLS ** HASHES rows
    counts = {(r["tab"], r["bucket"]): r["count"] for r in placed.groupBy("tab", "bucket").count().collect()}
    directory, members, number = [], [dict() for _ in range(TABLES)], 0
    for t in range(TABLES):
        filled = BLOCK
        for bucket in sorted(b for tab, b in counts if tab == t):
            n = counts[t, bucket]
            if n > BLOCK:  # a large bucket: blocks of its own
                splits = -(-n // BLOCK)
                first, number, filled = number + 1, number + splits, BLOCK
            else:
                if filled + n > BLOCK:
                    number, filled = number + 1, 0
                splits, first, filled = 1, number, filled + n
            directory.append((t, bucket, first, splits))
            for k in range(splits):
                members[t].setdefault(first + k, []).append(bucket)
    where = F.broadcast(spark.createDataFrame(directory, "tab int, bucket int, first int, splits int"))
    blocks = placed.join(where, ["tab", "bucket"]).withColumn("block", (F.col("first") + F.pmod(F.xxhash64("id", "v"), F.col("splits"))).cast("int"))
    query_blocks = max(1, -(-asked.count() // QUERY_BLOCK))
    grid = blocks.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(query_blocks - 1)))).select("tab", "block", "part", "id", "v", "bucket")
    shared = spark.sparkContext.broadcast(members)
    visiting = asked.mapInArrow(lambda b: _visited_blocks(b, index, shared), "qid long, q array<double>, least double, tab int, block int")
    visiting = visiting.withColumn("part", F.pmod(F.xxhash64("qid"), F.lit(query_blocks)).cast("int")).select("tab", "block", "part", "qid", "q", "least")
    by = ["tab", "block", "part"]
    found = grid.groupBy(*by).cogroup(visiting.groupBy(*by)).applyInArrow(lambda k, a, b: _score(k, a, b, index), "query_id long, vec_id long, score double, compared long")
    once = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"), F.sum("compared").alias("n"))
    by_query = Window.partitionBy("query_id")
    ranked = once.withColumns({"compared": F.sum("n").over(by_query), "rank": F.row_number().over(by_query.orderBy(F.desc_nulls_last("score"), "vec_id"))})
    return ranked.filter((F.col("rank") <= TOP) & F.col("vec_id").isNotNull()).select("query_id", "rank", "vec_id", "score", "compared")

"""Run-length encoding and decoding as DataFrame plans."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from runloom.functions.bind import bound


def text_runs(text: Column) -> Column:
    """Maximal runs of the characters of a string, as array<struct<sym,len>>; null stays null, empty gives none."""
    parts = F.regexp_extract_all(text, F.lit(r"(?s)(.)\1*+"), F.lit(0))
    return F.transform(parts, lambda r: F.struct(F.substring(r, 1, 1).alias("sym"), F.length(r).cast("long").alias("len")))


def array_runs(values: Column, symbol: str = "string", on_null: str = "break") -> Column:
    """Maximal runs of an array's elements. A null element ends a run and is left out (break), is skipped (drop), or is a symbol.

    The borders are found by comparing neighbours; a run's length is the distance of two borders.
    """
    if on_null == "drop":
        values = F.filter(values, lambda x: x.isNotNull())

    def coded(v: Column) -> Column:
        n = F.size(v)
        ends = F.filter(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: (i <= n) & ((i == n) | ~F.get(v, i - 1).eqNullSafe(F.get(v, i))))
        return bound(ends, lambda border: F.transform(border, lambda e, k: F.struct(F.get(v, e - 1).cast(symbol).alias("sym"), (e - F.when(k == 0, 0).otherwise(F.get(border, k - 1))).cast("long").alias("len"))))

    runs = bound(values, coded)
    return F.filter(runs, lambda r: r["sym"].isNotNull()) if on_null == "break" else runs


#: Characters that the border kernel encodes at once.
PIECE = 1 << 20


def _pieces(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    """Slices with at most PIECE characters in the columns after the first, or one row."""
    import pyarrow.compute as pc

    done = np.cumsum(sum(np.asarray(pc.utf8_length(column).fill_null(0), np.int64) for column in batch.columns[1:]))
    lo = 0
    while lo < batch.num_rows:
        hi = max(lo + 1, int(np.searchsorted(done, (done[lo - 1] if lo else 0) + PIECE, "right")))
        yield batch.slice(lo, hi - lo)
        lo = hi


def _coded(column: pa.Array) -> list[pa.Array]:
    """runs, n, n_runs of texts: characters are compared with their neighbours over many texts at once."""
    import pyarrow.compute as pc

    n = np.asarray(pc.utf8_length(column).fill_null(0), np.int64)
    points = np.frombuffer("".join(x or "" for x in column.to_pylist()).encode("utf-32-le", "surrogatepass"), "<u4")
    edge = np.ones(len(points) + 1, bool)
    edge[1:-1] = points[1:] != points[:-1]
    ends = np.cumsum(n)
    edge[ends] = True
    first = np.flatnonzero(edge[:-1])
    names, index = np.unique(points[first], return_inverse=True)
    sym = pa.DictionaryArray.from_arrays(pa.array(index.reshape(-1).astype(np.int32)), pa.array([chr(c) for c in names], pa.string())).cast(pa.string())
    runs = pa.StructArray.from_arrays([sym, pa.array(np.diff(np.append(first, len(points))))], ["sym", "len"])
    border = np.concatenate([[0], np.searchsorted(first, ends)]).astype(np.int32)
    none = column.is_null()
    lists = pa.ListArray.from_arrays(pa.array(border), runs)
    if column.null_count:
        lists = pc.if_else(none, pa.nulls(len(lists), lists.type), lists)
    return [lists, *(pc.if_else(none, pa.scalar(None, pa.int64()), pa.array(x.astype(np.int64))) for x in (n, np.diff(border)))]


def _text_borders(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """seq_id, runs, n, n_runs of one column."""
    for batch in batches:
        for piece in _pieces(batch):
            yield pa.RecordBatch.from_arrays([piece.column(0), *_coded(piece.column(1))], ["seq_id", "runs", "n", "n_runs"])


def _texts_borders(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The same batches with runs in place of the texts."""
    for batch in batches:
        for piece in _pieces(batch):
            yield pa.RecordBatch.from_arrays([piece.column(0), *(_coded(column)[0] for column in piece.columns[1:])], piece.schema.names)


def rle_text(df: DataFrame, id_col: str, col: str) -> DataFrame:
    """seq_id, runs, n, n_runs of a string column; a null text has null runs, an empty one none. text_runs() is the same as a column."""
    rows = df.select(F.col(id_col).alias("seq_id"), F.col(col).cast("string").alias("text"))
    return rows.mapInArrow(_text_borders, f"seq_id {rows.schema[0].dataType.simpleString()}, runs array<struct<sym:string,len:bigint>>, n long, n_runs long")


def rle_texts(df: DataFrame, id_col: str, cols: list[str]) -> DataFrame:
    """id_col and the runs of several string columns, each under its name; nulls as in rle_text."""
    rows = df.select(id_col, *(F.col(c).cast("string").alias(c) for c in cols))
    return rows.mapInArrow(_texts_borders, f"{id_col} {rows.schema[0].dataType.simpleString()}, " + ", ".join(f"{c} array<struct<sym:string,len:bigint>>" for c in cols))


def rle_array(df: DataFrame, id_col: str, col: str, on_null: str = "break") -> DataFrame:
    """seq_id, runs, n, n_runs of an array column. Neighbours are compared over whole batches; nulls as in array_runs."""
    return with_sizes(recoded(df.select(F.col(id_col).alias("seq_id"), F.col(col).alias("values")), on_null=on_null))


def recoded(df: DataFrame, ranks: dict | None = None, other: int = 0, on_null: str = "break") -> DataFrame:
    """seq_id, runs from seq_id and values (an array) or runs. With ranks, symbols are replaced first (others by `other`) and runs joined again."""
    from pyspark.sql.pandas.types import to_arrow_type

    source = "runs" if "runs" in df.columns else "values"
    ids = df.schema["seq_id"].dataType.simpleString()
    element = df.schema[source].dataType.elementType
    sym = "bigint" if ranks is not None else element["sym"].dataType.simpleString() if source == "runs" else element.simpleString()
    arrow = pa.int64() if ranks is not None else to_arrow_type(element["sym"].dataType if source == "runs" else element)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(1)
            counts = np.asarray(lists.value_lengths().fill_null(0), np.int64)
            flat = lists.flatten()
            values = flat.field(0) if source == "runs" else flat
            lens = np.asarray(flat.field(1), np.int64) if source == "runs" else np.ones(len(flat), np.int64)
            coded = values.dictionary_encode()
            names, index = coded.dictionary.to_pylist(), np.asarray(coded.indices.fill_null(-1), np.int64)
            if ranks is not None:
                table = np.array([ranks.get(x, other) for x in names] + [other], np.int64)
                index = table[index]
            owner = np.repeat(np.arange(len(counts)), counts)
            if on_null == "drop" and ranks is None:
                owner, lens, index = owner[index >= 0], lens[index >= 0], index[index >= 0]
            new = np.ones(len(index), bool)
            new[1:] = (index[1:] != index[:-1]) | (owner[1:] != owner[:-1])
            first = np.flatnonzero(new)
            total = np.add.reduceat(lens, first) if len(first) else lens[:0]
            owner, code = owner[first], index[first]
            if ranks is None and on_null == "break":
                owner, total, code = owner[code >= 0], total[code >= 0], code[code >= 0]
            syms = pa.array(code) if ranks is not None else coded.dictionary.take(pa.array(code, mask=code < 0)) if len(names) else pa.nulls(len(code), arrow)
            runs = pa.StructArray.from_arrays([syms, pa.array(total, pa.int64())], fields=[pa.field("sym", arrow), pa.field("len", pa.int64())])
            offsets = np.searchsorted(owner, np.arange(len(counts) + 1)).astype(np.int32)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(offsets), runs)], ["seq_id", "runs"])

    return df.select("seq_id", source).mapInArrow(encode, f"seq_id {ids}, runs array<struct<sym:{sym},len:bigint>>")


def with_sizes(df: DataFrame) -> DataFrame:
    """n (symbols) and n_runs of a runs column."""
    return df.withColumns({"n": F.aggregate("runs", F.lit(0).cast("long"), lambda s, r: s + r["len"]), "n_runs": F.size("runs").cast("long")})


def rle_rows(df: DataFrame, part: str, order: list[str], sym: str) -> DataFrame:
    """Long form of row sequences: seq_id, run_no (from 1), sym, len, start. One shuffle by part; null symbols break runs and are left out."""
    w = Window.partitionBy(part).orderBy(*order, sym)
    rows = df.select(F.col(part).alias("seq_id"), F.col(sym).alias("sym"), F.row_number().over(w).alias("pos"), F.lag(sym).over(w).alias("last"))
    new = F.when((F.col("pos") == 1) | ~F.col("sym").eqNullSafe(F.col("last")), 1).otherwise(0)
    island = F.sum(new).over(Window.partitionBy("seq_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0))
    runs = rows.withColumn("island", island).groupBy("seq_id", "island").agg(F.first("sym").alias("sym"), F.count(F.lit(1)).alias("len"), F.min("pos").alias("first"))
    runs = runs.filter(F.col("sym").isNotNull())
    number = F.row_number().over(Window.partitionBy("seq_id").orderBy("island")).cast("long")
    return runs.select("seq_id", number.alias("run_no"), "sym", F.col("len").cast("long").alias("len"), (F.col("first") - 1).cast("long").alias("start"))


def gather(runs: DataFrame) -> DataFrame:
    """Long form to one row per sequence: seq_id, runs."""
    rows = runs.groupBy("seq_id").agg(F.array_sort(F.collect_list(F.struct("run_no", "sym", "len"))).alias("r"))
    return rows.select("seq_id", F.transform("r", lambda x: F.struct(x["sym"].alias("sym"), x["len"].alias("len"))).alias("runs"))


def sequences(df: DataFrame, part: str, order: list[str], sym: str) -> DataFrame:
    """seq_id, runs of row sequences."""
    return gather(rle_rows(df, part, order, sym))


def explode_runs(df: DataFrame) -> DataFrame:
    """Array form to long form: seq_id, run_no, sym, len, start. No shuffle; starts are running sums in linear time."""
    ids = df.schema["seq_id"].dataType.simpleString()
    sym = df.schema["runs"].dataType.elementType["sym"].dataType.simpleString()

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            runs = batch.column(1)
            flat = runs.flatten()
            counts = np.asarray(runs.value_lengths().fill_null(0), np.int64)
            first = np.cumsum(counts) - counts
            owner = np.repeat(np.arange(len(counts)), counts)
            lens = np.asarray(flat.field(1), np.int64)
            total = np.cumsum(lens) - lens
            start = total - np.repeat(total[first[counts > 0]], counts[counts > 0]) if len(lens) else total
            number = np.arange(len(owner)) - first[owner] + 1
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(owner)), pa.array(number), flat.field(0), pa.array(lens), pa.array(start)], ["seq_id", "run_no", "sym", "len", "start"])

    return df.select("seq_id", "runs").mapInArrow(rows, f"seq_id {ids}, run_no long, sym {sym}, len long, start long")


def decode(runs: Column) -> Column:
    """The string that runs of characters stand for."""
    return F.array_join(F.transform(runs, lambda r: F.repeat(r["sym"], r["len"].cast("int"))), "")


def decode_array(runs: Column) -> Column:
    return F.flatten(F.transform(runs, lambda r: F.array_repeat(r["sym"], r["len"].cast("int"))))


def is_valid(runs: Column) -> Column:
    """True for runs that are maximal, positive and not empty."""
    positive = F.forall(runs, lambda r: (r["len"] >= 1) & r["sym"].isNotNull())
    pairs = F.zip_with(F.slice(runs, 1, F.greatest(F.size(runs) - 1, F.lit(0))), F.slice(runs, 2, F.greatest(F.size(runs) - 1, F.lit(0))), lambda a, b: a["sym"] != b["sym"])
    return positive & (F.size(runs) > 0) & F.forall(pairs, lambda x: x)


def _local_runs(batches: Iterator[pa.RecordBatch], kind: pa.DataType) -> Iterator[pa.RecordBatch]:
    """Runs of one ordered partition; the open run is carried from batch to batch."""
    from pyspark import TaskContext

    part, number, open_sym, open_len = TaskContext.get().partitionId(), 0, None, 0

    def rows(syms: list, lens: list) -> pa.RecordBatch:
        nonlocal number
        k = len(syms)
        out = pa.RecordBatch.from_arrays([pa.array([part] * k, pa.int64()), pa.array(range(number, number + k), pa.int64()), pa.array(syms, kind), pa.array(lens, pa.int64())], ["part", "local", "sym", "len"])
        number += k
        return out

    for batch in batches:
        values = batch.column(0)
        if not len(values):
            continue
        codes = values.dictionary_encode()
        names, index = codes.dictionary.to_pylist(), np.asarray(codes.indices.fill_null(-1))
        edge = np.concatenate([[0], np.flatnonzero(np.diff(index)) + 1, [len(index)]])
        syms = [names[i] if i >= 0 else None for i in index[edge[:-1]]]
        lens = np.diff(edge).tolist()
        if open_len and syms[0] == open_sym:
            lens[0] += open_len
        elif open_len:
            syms.insert(0, open_sym)
            lens.insert(0, open_len)
        open_sym, open_len = syms.pop(), lens.pop()
        if syms:
            yield rows(syms, lens)
    if open_len:
        yield rows([open_sym], [open_len])


def rle_global(df: DataFrame, order: list[str], sym: str) -> DataFrame:
    """run_no, sym, len, start of the one sequence that all rows form, in order.

    Rows are range-partitioned and encoded inside partitions; a row per partition then tells which border runs are one run
    and where each partition begins, so no task sees the whole sequence.
    """
    from pyspark.sql.pandas.types import to_arrow_type

    kind = df.schema[sym].dataType
    arrow = to_arrow_type(kind)
    ordered = df.select(*order, F.col(sym).alias("__sym")).repartitionByRange(*order, "__sym").sortWithinPartitions(*order, "__sym").select("__sym")
    local = ordered.mapInArrow(lambda b: _local_runs(b, arrow), f"part long, local long, sym {kind.simpleString()}, len long")
    from runloom.sources.store import stored

    local = stored(local, "local-runs")
    per = local.groupBy("part").agg(F.min_by("sym", "local").alias("head"), F.max_by("sym", "local").alias("tail"), F.count(F.lit(1)).alias("n_local"), F.sum("len").alias("n"))
    w = Window.orderBy("part")  # one row per partition
    before = w.rowsBetween(Window.unboundedPreceding, -1)
    joined = F.coalesce(F.lag("tail").over(w).eqNullSafe(F.col("head")) & (F.row_number().over(w) > 1), F.lit(False)).cast("int")
    per = per.withColumn("joined", joined)
    per = per.withColumn("base", F.coalesce(F.sum(F.col("n_local") - F.col("joined")).over(before), F.lit(0))).withColumn("offset", F.coalesce(F.sum("n").over(before), F.lit(0)))
    inside = F.coalesce(F.sum("len").over(Window.partitionBy("part").orderBy("local").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    rows = local.withColumn("inside", inside).join(per.select("part", "joined", "base", "offset"), "part")
    rows = rows.select((F.col("base") + F.col("local") + 1 - F.col("joined")).alias("run_no"), "sym", "len", (F.col("offset") + F.col("inside")).alias("start"))
    return rows.groupBy("run_no").agg(F.first("sym").alias("sym"), F.sum("len").alias("len"), F.min("start").alias("start"))


def rle_rows_ranged(df: DataFrame, part: str, order: list[str], sym: str) -> DataFrame:
    """rle_rows() for keys of any size: rows are range-partitioned by key and order, so a hot key is spread over many tasks.

    Runs are made inside partitions. Of the keys that reach over a border (two a partition at most) a row per partition tells
    where each part begins and whether its first run goes on; null symbols break runs and are left out.
    """
    from pyspark.sql.pandas.types import to_arrow_type

    from runloom.sources.store import stored

    rows = df.select(F.col(part).alias("seq_id"), *[F.col(c).alias(f"__{k}") for k, c in enumerate(order)], F.col(sym).alias("__sym"))
    by = ["seq_id", *(f"__{k}" for k in range(len(order))), "__sym"]
    kinds = [rows.schema[c].dataType for c in ("seq_id", "__sym")]
    seq_kind, sym_kind = (k.simpleString() for k in kinds)
    ordered = rows.repartitionByRange(*by).sortWithinPartitions(*by).select("seq_id", "__sym")
    local = stored(ordered.mapInArrow(lambda b: _keyed_runs(b, *map(to_arrow_type, kinds)), f"part long, local long, seq_id {seq_kind}, sym {sym_kind}, len long"), "keyed-runs")
    ends = local.groupBy("part").agg(F.min_by(F.struct("seq_id"), "local").alias("a"), F.max_by(F.struct("seq_id"), "local").alias("b"))
    border = ends.select("a.seq_id").union(ends.select("b.seq_id")).distinct().withColumnRenamed("seq_id", "key")
    full = F.col("sym").isNotNull().cast("long")
    per = local.join(border, F.col("seq_id").eqNullSafe(F.col("key")), "left_semi").groupBy("seq_id", "part")
    per = per.agg(F.min_by("sym", "local").alias("head"), F.max_by("sym", "local").alias("tail"), F.sum(full).alias("runs"), F.sum("len").alias("n"))
    of_key = Window.partitionBy("seq_id").orderBy("part")  # a row per partition that the key reaches
    before = of_key.rowsBetween(Window.unboundedPreceding, -1)
    per = per.withColumn("joined", F.coalesce(F.lag("tail").over(of_key) == F.col("head"), F.lit(False)).cast("long"))
    sums = [F.coalesce(F.sum(c).over(before), F.lit(0)) for c in (F.col("runs") - F.col("joined"), F.col("n"))]
    per = per.select(F.col("seq_id").alias("key"), F.col("part").alias("at"), "joined", sums[0].alias("base"), sums[1].alias("offset"))
    inside = Window.partitionBy("part", "seq_id").orderBy("local")
    total = lambda c, last: F.coalesce(F.sum(c).over(inside.rowsBetween(Window.unboundedPreceding, last)), F.lit(0))
    placed = local.withColumns({"no": total(full, 0), "from": total(F.col("len"), -1)}).filter("sym IS NOT NULL")
    placed = placed.join(per, (F.col("part") == F.col("at")) & F.col("seq_id").eqNullSafe(F.col("key")), "left")
    zero = lambda c: F.coalesce(c, F.lit(0))
    runs = placed.select("seq_id", (zero("base") + F.col("no") - zero("joined")).alias("run_no"), "sym", "len", (zero("offset") + F.col("from")).alias("start"))
    return runs.groupBy("seq_id", "run_no").agg(F.first("sym").alias("sym"), F.sum("len").alias("len"), F.min("start").alias("start"))


def _keyed_runs(batches: Iterator[pa.RecordBatch], seq_kind: pa.DataType, sym_kind: pa.DataType) -> Iterator[pa.RecordBatch]:
    """part, local, seq_id, sym, len of the runs of one partition's rows; the last run is held back between batches."""
    from pyspark import TaskContext

    part, number, held = TaskContext.get().partitionId(), 0, None
    names = ["part", "local", "seq_id", "sym", "len"]

    def rows(seqs: list, syms: list, lens: list) -> pa.RecordBatch:
        nonlocal number
        number += len(seqs)
        return pa.RecordBatch.from_arrays([pa.array([part] * len(seqs), pa.int64()), pa.array(range(number - len(seqs), number), pa.int64()), pa.array(seqs, seq_kind), pa.array(syms, sym_kind), pa.array(lens, pa.int64())], names)

    for batch in batches:
        if not batch.num_rows:
            continue
        codes = [c.dictionary_encode() for c in batch.columns]
        index = [np.asarray(c.indices.fill_null(-1)) for c in codes]
        first = np.flatnonzero(np.concatenate([[True], (np.diff(index[0]) != 0) | (np.diff(index[1]) != 0)]))
        seqs, syms = ([names_of[i] if i >= 0 else None for i in ix[first]] for names_of, ix in zip((c.dictionary.to_pylist() for c in codes), index))
        lens = np.diff(np.append(first, batch.num_rows)).tolist()
        if held is not None:
            if (seqs[0], syms[0]) == held[:2]:
                lens[0] += held[2]
            else:
                seqs, syms, lens = [held[0], *seqs], [held[1], *syms], [held[2], *lens]
        held = seqs.pop(), syms.pop(), lens.pop()
        if seqs:
            yield rows(seqs, syms, lens)
    if held is not None:
        yield rows([held[0]], [held[1]], [held[2]])

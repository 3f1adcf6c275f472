"""Benchmark decontamination: hashed windows of the items, broadcast, against windows of the documents.

Text is lower-cased (A-Z) and cut into words of digits, letters and all non-ASCII characters. A window is N_WORDS
consecutive item words; an item of fewer words is one window. Window hashes of a document are looked up in the
broadcast set, and every hit is compared word for word. The set's size is checked: a benchmark beyond BLOCK_WINDOWS windows
is scanned block by block. Only one block is on the driver and the workers at a time; its hits are written, and those of
equal rows (id and text) are merged.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from runloom.llm.common import buffers, discard, pieces, texts, tidy, written
from runloom.llm.textnum import ALNUM, Words, ngrams, same_text, words

N_WORDS = 10
#: Item windows in one broadcast: about 200 bytes each.
BLOCK_WINDOWS = 400_000

WINDOW_SCHEMA = "item_id string, n int, hash long, words binary"
#: A run of hit words: first and last word, start and end character.
RUNS = "array<struct<first:int,last:int,start:int,end:int>>"
FOUND_SCHEMA = f"doc_id {{id_type}}, text_hash long, n_words long, runs {RUNS}, item_ids array<string>"


def _joined(w: Words, k: int, n: int) -> bytes:
    return b" ".join(w.bytes(j) for j in range(k, k + n))


def _item_windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        column, ids = texts(batch.column(1)), batch.column(0).to_pylist()
        for lo, hi in pieces(column):
            w = words(*buffers(column.slice(lo, hi - lo)), ALNUM)
            out = []
            for i in range(hi - lo):
                first, count = int(w.first[i]), int(w.first[i + 1] - w.first[i])
                n = min(N_WORDS, count)
                if n:
                    grams = ngrams(w.hash[first : first + count], n)
                    out += [(ids[lo + i], n, int(grams[k].view(np.int64)), _joined(w, first + k, n)) for k in range(count - n + 1)]
            yield pa.RecordBatch.from_arrays([pa.array([x[j] for x in out], t) for j, t in enumerate((pa.string(), pa.int32(), pa.int64(), pa.binary()))], ["item_id", "n", "hash", "words"])


class WindowSet:
    """A bounded set of windows: sorted hashes by window length, and the items of each window's words."""

    def __init__(self, rows: pa.Table) -> None:
        self.items: dict[tuple[int, bytes], list[str]] = {}
        by_length: dict[int, set[int]] = {}
        for item, n, code, found in zip(*(rows.column(k).to_pylist() for k in ("item_id", "n", "hash", "words"))):
            self.items.setdefault((n, found), []).append(item)
            by_length.setdefault(n, set()).add(code)
        self.hashes = {n: np.sort(np.array(list(x), np.int64).view(np.uint64)) for n, x in sorted(by_length.items())}
        self.maps = {}
        for n, x in self.hashes.items():  # one bit per low hash bits: most windows stop here
            bits = max(16, int(len(x)).bit_length() + 4)
            seen = np.zeros(1 << bits, bool)
            seen[(x & np.uint64((1 << bits) - 1)).astype(np.int64)] = True
            self.maps[n] = (np.uint64((1 << bits) - 1), seen)

    def scan(self, w: Words, n_texts: int) -> tuple[np.ndarray, list[set[str]]]:
        """Hit flag of every word; the items of every text."""
        hit, items = np.zeros(len(w.hash), bool), [set() for _ in range(n_texts)]
        for n, known in self.hashes.items():
            grams = ngrams(w.hash, n)
            mask, seen = self.maps[n]
            at = np.flatnonzero(seen[(grams & mask).astype(np.int64)] & same_text(w, n))
            place = np.minimum(np.searchsorted(known, grams[at]), len(known) - 1)
            for k in at[known[place] == grams[at]]:
                if found := self.items.get((n, _joined(w, int(k), n))):
                    hit[k : k + n] = True
                    items[w.text[k]].update(found)
        return hit, items


def _runs(flags: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First and last place of every run of True."""
    edge = np.diff(np.concatenate([[0], flags.astype(np.int8), [0]]))
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1) - 1


def _found(batches: Iterator[pa.RecordBatch], windows, schema: pa.Schema, every: bool) -> Iterator[pa.RecordBatch]:
    """doc_id, text_hash, n_words, runs, item_ids (and further columns of the rows) of every text, or of those with a hit."""
    known = windows.value
    for batch in batches:
        column = texts(batch.column(2))
        for lo, hi in pieces(column):
            buf, offs = buffers(column.slice(lo, hi - lo))
            w = words(buf, offs, ALNUM)
            hit, items = known.scan(w, hi - lo)
            rows, runs = range(hi - lo) if every else [i for i, x in enumerate(items) if x], []
            for i in rows:
                base = int(w.first[i])
                first, last = _runs(hit[base : int(w.first[i + 1])]) if items[i] else ((), ())
                place = np.cumsum((buf[offs[i] : offs[i + 1]] & 0xC0) != 0x80) if items[i] else None  # characters up to each byte
                runs.append([(int(a), int(b), int(place[w.start[base + a] - offs[i]]) - 1, int(place[w.end[base + b] - 1 - offs[i]])) for a, b in zip(first, last)])
            at = pa.array([lo + i for i in rows], pa.int64())
            marks = [pa.array(np.diff(w.first)[list(rows)], pa.int64()), pa.array([[dict(zip(("first", "last", "start", "end"), r)) for r in x] for x in runs], schema.field("runs").type), pa.array([sorted(items[i]) for i in rows], pa.list_(pa.string()))]
            more = [batch.column(k).take(at) for k in range(3, batch.num_columns)]
            yield pa.RecordBatch.from_arrays([batch.column(0).take(at), batch.column(1).take(at), *marks, *more], schema=schema)
    tidy()


def _merged(batches: Iterator[pa.RecordBatch], schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    """Runs of several blocks as runs of words: those that overlap or follow each other become one."""
    for batch in batches:
        out = []
        for runs in batch.column(2).to_pylist():
            kept: list[dict] = []
            for r in sorted(runs, key=lambda r: (r["first"], r["last"])):
                if kept and r["first"] <= kept[-1]["last"] + 1:
                    if r["last"] > kept[-1]["last"]:
                        kept[-1] |= {"last": r["last"], "end": r["end"]}
                else:
                    kept.append(dict(r))
            out.append(kept)
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out, schema.field("runs").type), batch.column(3)], schema=schema)


def _window_blocks(items: DataFrame, id_col: str, text_col: str) -> Iterator[tuple[int, pa.Table]]:
    """Number of blocks and the windows of each: BLOCK_WINDOWS at most, but for items that share one window."""
    named = items.select(F.coalesce(F.col(id_col).cast("string"), F.lit("")), F.col(text_col).cast("string"))
    windows = written(named.mapInArrow(_item_windows, WINDOW_SCHEMA).distinct(), "leak-windows")
    total = windows.count()
    if total <= BLOCK_WINDOWS:
        yield 1, windows.toArrow()
    else:
        part = F.pmod(F.xxhash64("words"), F.lit(8 * -(-total // BLOCK_WINDOWS)))
        blocks: list[tuple[int, list[int]]] = []
        for r in sorted(windows.groupBy(part.alias("part")).count().collect(), key=lambda r: r["part"]):
            if not blocks or blocks[-1][0] + r["count"] > BLOCK_WINDOWS:
                blocks.append((0, []))
            blocks[-1] = (blocks[-1][0] + r["count"], [*blocks[-1][1], r["part"]])
        for _, parts in blocks:
            yield len(blocks), windows.filter(part.isin(parts)).toArrow()
    discard(windows)


def _rows(docs: DataFrame, id_col: str, text_col: str, *more: str) -> DataFrame:
    text = F.col(text_col).cast("string")
    return docs.select(F.col(id_col).alias("doc_id"), F.xxhash64(text).alias("text_hash"), text.alias("text"), *(F.col(c).alias(f"__{c}") for c in more))


def _scan(docs: DataFrame, items: DataFrame, id_col: str, text_col: str, item_id: str, item_text: str, with_text: bool) -> DataFrame:
    """doc_id, text_hash, n_words, runs, item_ids (and __text) of every row."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    spark = docs.sparkSession
    ddl = FOUND_SCHEMA.format(id_type=docs.select(id_col).schema[0].dataType.simpleString())
    slim, wide = (to_arrow_schema(StructType.fromDDL(x)) for x in (ddl, ddl + ", __text string"))
    source, held, count, windows = _rows(docs, id_col, text_col), [], 0, None
    for count, block in _window_blocks(items, item_id, item_text):
        windows = spark.sparkContext.broadcast(WindowSet(block))
        if count > 1:
            held.append(written(source.mapInArrow(lambda b, w=windows: _found(b, w, slim, False), ddl).drop("n_words").distinct(), "leak-hits"))
            windows.destroy()
    if count > 1:
        windows = spark.sparkContext.broadcast(WindowSet(block.slice(0, 0)))  # words are counted once, with an empty set
    named = _rows(docs, id_col, text_col, text_col).withColumnRenamed(f"__{text_col}", "__text") if with_text else source
    schema, out = (wide, ddl + ", __text string") if with_text else (slim, ddl)
    rows = named.mapInArrow(lambda b: _found(b, windows, schema, True), out)
    if count <= 1:
        return rows
    both = reduce(DataFrame.union, held).groupBy("doc_id", "text_hash").agg(F.flatten(F.collect_list("runs")).alias("runs"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("item_ids")))).alias("item_ids"))
    kind = out.split(",")[0]
    few = to_arrow_schema(StructType.fromDDL(f"{kind}, text_hash long, runs {RUNS}, item_ids array<string>"))
    merged = written(both.mapInArrow(lambda b: _merged(b, few), f"{kind}, text_hash long, runs {RUNS}, item_ids array<string>"), "leak-merged", *held)
    merged = merged.withColumnsRenamed({"doc_id": "__id", "text_hash": "__hash", "runs": "__runs", "item_ids": "__items"})
    joined = rows.join(merged, F.col("doc_id").eqNullSafe(F.col("__id")) & (F.col("text_hash") == F.col("__hash")), "left")
    return joined.withColumns({"runs": F.coalesce("__runs", "runs"), "item_ids": F.coalesce("__items", "item_ids")}).drop("__id", "__hash", "__runs", "__items")


def scan(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id: str = "item_id", item_text: str = "text") -> DataFrame:
    """One row per document: n_words, n_hit, n_items, items_sha256, contaminated, hit_words and hit_chars (runs of hit words).

    Null and empty texts have no words and no hits; items without words have no window; repeated documents give repeated
    rows; items with equal text are all reported; an empty benchmark hits nothing. Null item ids count as "". Other columns
    are not read.
    """
    rows = _scan(docs, items, id_col, text_col, item_id, item_text, False)
    n_hit = F.aggregate("runs", F.lit(0).cast("long"), lambda s, r: s + r["last"] - r["first"] + 1)
    part = lambda a, b: F.transform("runs", lambda r: F.struct(r[a].alias(a), r[b].alias(b)))
    return rows.select(
        "doc_id", "n_words", n_hit.alias("n_hit"), F.size("item_ids").cast("long").alias("n_items"), F.sha2(F.array_join("item_ids", ","), 256).alias("items_sha256"),
        (F.size("runs") > 0).alias("contaminated"), part("first", "last").alias("hit_words"), part("start", "end").alias("hit_chars"),
    )


def drop_documents(docs: DataFrame, items: DataFrame) -> DataFrame:
    """docs without those in which a benchmark window occurs; same columns, rows untouched. One pass over whole rows for each block of windows."""
    spark, at = docs.sparkSession, docs.columns.index("text")

    def clean(batches: Iterator[pa.RecordBatch], windows) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = texts(batch.column(at))
            leak = np.zeros(len(column), bool)
            for lo, hi in pieces(column):
                w = words(*buffers(column.slice(lo, hi - lo)), ALNUM)
                hit, _ = windows.value.scan(w, hi - lo)
                leak[lo + np.unique(w.text[hit])] = True
            yield batch.filter(pa.array(~leak))
        tidy()

    before = None
    for count, block in _window_blocks(items, "item_id", "text"):
        windows = spark.sparkContext.broadcast(WindowSet(block))
        docs = docs.mapInArrow(lambda b, w=windows: clean(b, w), docs.schema)
        if count > 1:
            docs = written(docs, "leak-free", *([before] if before is not None else []))
            windows.destroy()
            before = docs
    return docs


def remove_spans(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, text without the hit words' character spans (the characters around them stay), n_hit; null texts stay null."""
    kept = F.filter(
        F.transform(F.col("marks"), lambda m, k: F.struct(F.when(k == 0, 0).otherwise(F.element_at("marks", k)["end"]).alias("start"), m["start"].alias("end"))),
        lambda s: s["end"] > s["start"],
    )
    n_hit = F.aggregate("runs", F.lit(0).cast("long"), lambda s, r: s + r["last"] - r["first"] + 1)
    end = F.array(F.struct(F.length("__text").alias("start"), F.length("__text").alias("end")))
    hits = _scan(docs, items, id_col, text_col, "item_id", "text", True)
    hits = hits.withColumn("marks", F.concat(F.transform("runs", lambda r: F.struct(r["start"].alias("start"), r["end"].alias("end"))), end)).withColumn("kept", kept)
    cut = F.array_join(F.transform("kept", lambda s: F.substring(F.col("__text"), s["start"] + 1, s["end"] - s["start"])), "")
    return hits.select("doc_id", cut.alias("text"), n_hit.alias("n_hit"))

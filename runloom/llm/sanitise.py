"""PII by base patterns, and information-theoretic sanitisation of the terms that stand in the same documents.

Base entities (mail, IP, card, phone) are the protected entities. Over the whole corpus, n(t) documents hold term t,
n(e) hold entity e, and n(e,t) hold both, t outside the base spans. A term tells PMI(e;t) = log2(n(e,t) N / (n(e) n(t)))
of the IC(e) = log2(N / n(e)) bits that the entity itself carries. Terms that tell at least DISCLOSED of them, in at
least SUPPORT documents, are spans of kind "term" wherever they stand in a document with an entity. An entity of fewer
documents than SUPPORT asks for all it has: of a single document, the terms in at most N ** (1 - DISCLOSED) documents
disclose it. A sanitised text replaces terms by a general class, or removes those that tell nearly all.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from runloom.llm.common import bit_filter, buffers, passes, pieces, texts, tidy, written
from runloom.llm.secret_scan import joined
from runloom.llm.textnum import ALNUM, words

#: The base patterns, with ends that give the same matches in linear time.
DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"(?<![0-9])[0-9]++(\.[0-9]++)(\.[0-9]++)(\.[0-9]++)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
NOT_DIGIT = re.compile(r"[^0-9]")
KINDS = ("email", "ip", "card", "phone", "term")
LABEL = {"email": "[EMAIL]", "ip": "[IP]", "card": "[CARD]", "phone": "[PHONE]"}

SUPPORT = 2
DISCLOSED = 0.8
#: Entities are told apart by powers of this number of documents when rare terms are looked up.
LEVEL = 16
#: Terms that tell this share of an entity are removed, others generalised.
REMOVED = 0.97


def emails(text: str) -> Iterator[tuple[int, int]]:
    """Leftmost non-overlapping mail addresses; every start before an @ leads to that @ alone."""
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in LOCAL:
            start -= 1
        m = DOMAIN.match(text, at + 1) if start < at else None
        if m:
            yield start, m.end()
            done = m.end()
        at = text.find("@", max(at + 1, done))


def luhn(digits: str) -> bool:
    total = sum(int(c) if k % 2 == 0 else (2 * int(c)) // 10 + (2 * int(c)) % 10 for k, c in enumerate(reversed(digits)))
    return total % 10 == 0


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of the base kinds, in order."""
    out = [(s, 0, e) for s, e in emails(text)]
    out += [(m.start(), 1, m.end()) for m in IP.finditer(text) if all(len(x) <= 3 and int(x) <= 255 for x in (p.lstrip("0") or "0" for p in m[0].split(".")))]
    for m in CARD.finditer(text):
        if m.end() - m.start() >= 14 and 14 <= len(d := NOT_DIGIT.sub("", m[0])) <= 19 and luhn(d):
            out.append((m.start(), 2, m.end()))
    if "+" in text:
        out += [(m.start(), 3, m.end()) for m in PHONE.finditer(text) if 10 <= len(NOT_DIGIT.sub("", m[0])) <= 15]
    return sorted(out)


@dataclass
class Terms:
    """Terms of one text outside its base spans, in order: hash, start and end in code points."""

    hash: np.ndarray
    start: np.ndarray
    end: np.ndarray


def terms(text: str, spans: list[tuple[int, int, int]]) -> Terms:
    raw = np.frombuffer(text.encode(), np.uint8)
    w = words(raw, np.array([0, len(raw)]), ALNUM)
    point = np.concatenate([[0], np.cumsum((raw & 0xC0) != 0x80)])  # code points before each byte
    start, end = point[w.start], point[w.end]
    base = np.zeros(len(text) + 1, np.int64)
    for s, _, e in spans:
        base[s] += 1
        base[e] -= 1
    covered = np.concatenate([[0], np.cumsum(np.cumsum(base) > 0)])
    free = covered[start] == covered[end]
    return Terms(w.hash[free].view(np.int64), start[free], end[free])


SPAN = "struct<start:int,kind:int,end:int>"
BASE_SCHEMA = f"uid long, doc_id {{id_type}}, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans array<{SPAN}>, entities array<long>, text string"


def _base(batches: Iterator[pa.RecordBatch], schema: pa.Schema, every: bool) -> Iterator[pa.RecordBatch]:
    """Rows of BASE_SCHEMA; texts without entities are carried on if every one is asked for."""
    uid = TaskContext.get().partitionId() << 36
    for batch in batches:
        rows = []
        for doc_id, given in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            text = given or ""
            spans = base_spans(text)
            counts = [sum(k == n for _, k, _ in spans) for n in range(4)]
            marks = [{"start": s, "kind": k, "end": e} for s, k, e in spans]
            entities = sorted({int.from_bytes(hashlib.blake2b(f"{KINDS[k]}:{text[s:e]}".encode(), digest_size=8).digest(), "little", signed=True) for s, k, e in spans})
            rows.append((uid, doc_id, *counts, hashlib.sha256(joined(spans, KINDS).encode()).hexdigest(), marks, entities, given if spans or every else None))
            uid += 1
        yield pa.RecordBatch.from_arrays([pa.array([r[j] for r in rows], f.type) for j, f in enumerate(schema)], schema=schema)
    tidy()


def _spans(column: pa.Array) -> Iterator[list[tuple[int, int, int]]]:
    for row in column.to_pylist():
        yield [(x["start"], x["kind"], x["end"]) for x in row]


def _vocabulary(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Terms of texts with entities, each once a batch at least."""
    for batch in batches:
        if batch.num_rows:
            found = [terms(t, s).hash for t, s in zip(batch.column(0).to_pylist(), _spans(batch.column(1)))]
            yield pa.RecordBatch.from_arrays([pa.array(np.unique(np.concatenate(found)), pa.int64())], ["term"])


def _pairs(batches: Iterator[pa.RecordBatch], rare) -> Iterator[pa.RecordBatch]:
    """entity, n_entity, term: a row for each document that holds both, of terms rare enough for the entity's level."""
    for batch in batches:
        out: list[list] = [[np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]]
        for text, spans, entities in zip(batch.column(0).to_pylist(), _spans(batch.column(1)), batch.column(2).to_pylist()):
            own = np.unique(terms(text, spans).hash)
            by_level = {k: own[passes(bits, own)] for k, bits in rare.value.items() if any(e["level"] == k for e in entities)}
            for e in entities:
                found = by_level[e["level"]]
                for column, x in zip(out, (np.full(len(found), e["entity"]), np.full(len(found), e["n_entity"]), found)):
                    column.append(x)
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c), pa.int64()) for c in out], ["entity", "n_entity", "term"])


def _places(batches: Iterator[pa.RecordBatch], kept) -> Iterator[pa.RecordBatch]:
    """uid, term, start, end of every occurrence of a term that may disclose."""
    for batch in batches:
        out: list[list] = [[np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]]
        for uid, text, spans in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), _spans(batch.column(2))):
            t = terms(text, spans)
            at = passes(kept.value, t.hash)
            for column, x in zip(out, (np.full(int(at.sum()), uid), t.hash[at], t.start[at], t.end[at])):
                column.append(x)
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c), k) for c, k in zip(out, (pa.int64(), pa.int64(), pa.int32(), pa.int32()))], ["uid", "term", "start", "end"])


def _term_counts(batches: Iterator[pa.RecordBatch], kept) -> Iterator[pa.RecordBatch]:
    """Documents holding each term that may stand with an entity; one row per term and task."""
    bits = kept.value
    open_terms, open_counts, size = [], [], 0

    def summed() -> tuple[np.ndarray, np.ndarray]:
        if not open_terms:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        names, place = np.unique(np.concatenate(open_terms), return_inverse=True)
        return names, np.bincount(place.reshape(-1), np.concatenate(open_counts), len(names)).astype(np.int64)

    for batch in batches:
        column = texts(batch.column(0))
        for lo, hi in pieces(column):
            w = words(*buffers(column.slice(lo, hi - lo)), ALNUM)
            sel = np.flatnonzero(passes(bits, w.hash))
            pairs = np.unique(np.stack([w.hash[sel].view(np.int64), w.text[sel]], axis=1), axis=0) if len(sel) else np.zeros((0, 2), np.int64)
            terms, count = np.unique(pairs[:, 0], return_counts=True)
            open_terms.append(terms)
            open_counts.append(count)
            size += len(terms)
            if size > 1 << 20:  # merge, so that memory follows the distinct terms
                names, counts = summed()
                open_terms, open_counts, size = [names], [counts], len(names) // 2
    names, counts = summed()
    yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array(counts, pa.int64())], ["term", "n"])
    tidy()


def disclosures(base: DataFrame, docs: DataFrame) -> DataFrame:
    """term and the largest ratio it reaches, of the terms that disclose an entity; base: rows of BASE_SCHEMA over docs (text)."""
    spark = docs.sparkSession
    private = base.filter(F.size("entities") > 0)
    total = base.count()
    held = private.select("uid", F.explode("entities").alias("e"))
    # entities of the same documents have the same counts with every term: one stands for all
    known = held.groupBy("e").agg(F.count(F.lit(1)).alias("n_entity"), F.sum(F.xxhash64("uid").cast("decimal(20,0)")).alias("documents"))
    known = known.select("e", "n_entity", F.xxhash64("documents", "n_entity").alias("entity")).filter(F.col("n_entity") < total)
    level = F.floor(F.log(F.col("n_entity") + F.lit(0.5)) / math.log(LEVEL)).cast("int")
    classes = held.join(known, "e").groupBy("uid").agg(F.collect_set(F.struct("entity", "n_entity", level.alias("level"))).alias("classes"))
    marked = written(private.select("uid", "text", "spans").join(classes, "uid"), "pii-private").select("text", "spans", "classes")
    kept = spark.sparkContext.broadcast(bit_filter(marked.select("text", "spans").mapInArrow(_vocabulary, "term long")))
    counts = docs.select("text").mapInArrow(lambda b: _term_counts(b, kept), "term long, n long").groupBy("term").agg(F.sum("n").alias("n_term"))
    counts = written(counts, "pii-terms")
    # n_pair is at most n_entity, so a term that discloses is in at most N ** (1 - DISCLOSED) * n_entity ** DISCLOSED documents
    rare = {}
    for k in sorted(r["level"] for r in known.select(level.alias("level")).distinct().collect()):
        most = total ** (1 - DISCLOSED) * float(LEVEL) ** ((k + 1) * DISCLOSED)
        rare[k] = bit_filter(counts.filter(F.col("n_term") <= most * (1 + 1e-9)).select("term"))
    shared = spark.sparkContext.broadcast(rare)
    pairs = marked.mapInArrow(lambda b: _pairs(b, shared), "entity long, n_entity long, term long").groupBy("entity", "n_entity", "term").agg(F.count(F.lit(1)).alias("n_pair"))
    pairs = pairs.filter(F.col("n_pair") >= F.least(F.lit(SUPPORT), "n_entity"))
    n = F.lit(float(total))
    told = F.log2(F.col("n_pair") * n / (F.col("n_entity") * F.col("n_term"))) / F.log2(n / F.col("n_entity"))
    joint = pairs.join(counts, "term").select("term", told.alias("ratio")).filter(F.col("ratio") >= DISCLOSED)
    return written(joint.groupBy("term").agg(F.max("ratio").alias("ratio")), "pii-found")


def _marked(docs: DataFrame, id_col: str, text_col: str, every: bool) -> DataFrame:
    """Rows of BASE_SCHEMA (texts of all rows, or of those with entities) with terms and marks: all spans in order, with the ratio they tell."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    source = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    ddl = BASE_SCHEMA.format(id_type=source.schema[0].dataType.simpleString())
    schema = to_arrow_schema(StructType.fromDDL(ddl))
    base = written(source.mapInArrow(lambda b: _base(b, schema, every), ddl), "pii-base")
    found = disclosures(base, source)
    kept = docs.sparkSession.sparkContext.broadcast(bit_filter(found.select("term")))
    places = base.filter(F.size("entities") > 0).select("uid", "text", "spans").mapInArrow(lambda b: _places(b, kept), "uid long, term long, start int, end int")
    terms = places.join(found, "term")
    terms = terms.groupBy("uid").agg(F.collect_list(F.struct("start", F.lit(4).alias("kind"), "end", "ratio")).alias("terms"))
    marks = F.array_sort(F.concat(F.expr("transform(spans, s -> struct(s.start as start, s.kind as kind, s.end as end, 1D as ratio))"), F.coalesce("terms", F.expr("cast(array() as array<struct<start:int,kind:int,end:int,ratio:double>>)"))))
    return base.join(terms, "uid", "left").withColumn("marks", marks)


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: counts of base kinds, digest of base spans, all spans, n_term, marks (spans as an array with labels).

    Null text counts as empty, without spans; repeated rows are documents of their own; an empty table gives no rows; other
    columns are not read. Offsets are code points, ends exclusive.
    """
    rows = _marked(docs, id_col, text_col, False).drop("text", "entities")
    names = ", ".join(f"'{k}'" for k in KINDS)
    text = F.array_join(F.transform("marks", lambda m: F.concat_ws(":", F.element_at(F.expr(f"array({names})"), m["kind"] + 1), m["start"], m["end"])), ",")
    return rows.select("doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", text.alias("spans"), F.coalesce(F.size("terms"), F.lit(0)).cast("long").alias("n_term"), "marks")


def sanitised(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, text, n_replaced of every document: base spans become their kind's label; terms that disclose a class word, or nothing.

    Where spans overlap the first one counts, of equal starts the longest. Null texts stay null.
    """
    rows = _marked(docs, id_col, text_col, True).select("doc_id", "text", "marks")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            marks = batch.column(2).to_pylist()
            out = [replaced(t, m) for t, m in zip(batch.column(1).to_pylist(), marks)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.string()), pa.array([len(m) for m in marks], pa.int64())], ["doc_id", "text", "n_replaced"])
        tidy()

    return rows.mapInArrow(cut, f"doc_id {rows.schema[0].dataType.simpleString()}, text string, n_replaced long")


def replaced(text: str | None, marks: list[dict]) -> str | None:
    """text with base spans as labels; terms as a class word, or gone."""
    if text is None:
        return None
    at, out = 0, []
    for m in sorted(marks, key=lambda m: (m["start"], -m["end"])):
        if m["start"] < at:
            continue
        word = text[m["start"] : m["end"]]
        general = LABEL.get(KINDS[m["kind"]]) or ("" if m["ratio"] >= REMOVED else "[NUMBER]" if word.isdigit() else "[NAME]" if word[:1].isupper() else "[TERM]")
        out += [text[at : m["start"]], general]
        at = m["end"]
    return "".join(out) + text[at:]

"""Ways to match that scale with the dictionary, and the planner that chooses one. All give the answers of match.full.

broadcast  frozen automaton on every executor, long sequences in chunks
grams      a join for each number of pattern runs: border symbols and a hash of the runs between
anchors    the same with power-of-two pieces, so that few kinds of text grams are made
shards     the dictionary in parts, the text against each
closure    kernel rows of (state, run) joined with what each state reports
prefilter  a semi join on symbol pairs first, then broadcast on the sequences left
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from runloom.functions.encode import explode_runs
from runloom.operators.automaton import Dictionary, Frozen, GroupedAutomaton
from runloom.operators.match import CHUNK, MAX_PATTERN_RUNS, _coded_runs, chunks, full, pattern_list, single_run

#: Bytes of a frozen automaton that executors take.
BROADCAST_BYTES = 200 << 20
BYTES_PER_RUN = 300
#: Runs of a chunk when grams are made: windows are kept that short.
GRAM_CHUNK = 4_096
MATCH_COLUMNS = ["seq_id", "pattern_id", "start", "end", "end_run"]


@dataclass(frozen=True)
class Stats:
    """What the planner looks at."""

    k: int
    pattern_runs: int
    run_counts: int
    longest: int
    text_runs: int

    @classmethod
    def of(cls, text: DataFrame, patterns: DataFrame) -> Stats:
        p = patterns.agg(F.count(F.lit(1)), F.sum(F.size("runs")), F.count_distinct(F.size("runs"))).first()
        t = text.agg(F.max(F.size("runs")), F.sum(F.size("runs"))).first()
        return cls(p[0], p[1] or 0, p[2], t[0] or 0, t[1] or 0)


def choose(stats: Stats) -> str:
    """The strategy: by the automaton's size, then by how many kinds of grams are needed."""
    if stats.pattern_runs * BYTES_PER_RUN <= BROADCAST_BYTES:
        return "broadcast"
    if stats.text_runs * 100 < stats.pattern_runs:
        return "shards"
    return "grams" if stats.run_counts <= 8 else "anchors"


def explain(text: DataFrame, patterns: DataFrame) -> str:
    s = Stats.of(text, patterns)
    return f"{choose(s)}: {s.k} patterns of {s.pattern_runs} runs ({s.run_counts} run counts), automaton about {s.pattern_runs * BYTES_PER_RUN / 1e6:.1f} MB; text of {s.text_runs} runs, longest sequence {s.longest}"


def match(text: DataFrame, patterns: DataFrame, strategy: str | None = None) -> DataFrame:
    """seq_id, pattern_id, start, end, end_run by the given strategy, or the planner's."""
    strategy = strategy or choose(Stats.of(text, patterns))
    return {"broadcast": broadcast, "grams": grams, "anchors": anchors, "shards": shards, "closure": closure, "prefilter": prefilter}[strategy](text, patterns)


def broadcast(text: DataFrame, patterns: DataFrame) -> DataFrame:
    """Sequences beyond CHUNK runs go through chunks with a halo; the others stay in their rows."""
    halo = (patterns.agg(F.max(F.size("runs"))).first()[0] or 1) - 1
    short = text.filter(F.size("runs") <= CHUNK)
    long = chunks(explode_runs(text.filter(F.size("runs") > CHUNK)), halo)
    return full(short, patterns).unionByName(full(long, patterns))


def windows(text: DataFrame, halo: int) -> DataFrame:
    """Long form in overlapping pieces: every run once as its own (own), and again as context of later pieces."""
    runs = explode_runs(text)
    piece = F.explode(F.sequence(F.expr(f"(run_no - 1) div {GRAM_CHUNK}"), F.expr(f"(run_no - 1 + {halo}) div {GRAM_CHUNK}")))
    return runs.withColumn("piece", piece).withColumn("own", F.expr(f"(run_no - 1) div {GRAM_CHUNK}") == F.col("piece"))


def _residual(r: int) -> Column:
    return (F.col("p_first") <= F.col("len")) & (F.col("p_last") <= F.col("last_len"))


def grams(text: DataFrame, patterns: DataFrame) -> DataFrame:
    """One equi join for each number of runs; lengths of the border runs are a residual, equal hashes are checked again."""
    counts = [r[0] for r in patterns.select(F.size("runs").alias("r")).distinct().orderBy("r").collect()]
    runs = explode_runs(text)
    out = single_run(runs, patterns).select(*MATCH_COLUMNS)
    for r in (r for r in counts if r > 1):
        w = Window.partitionBy("seq_id", "piece").orderBy("run_no")
        cut = windows(text, r - 1)
        ends = [F.lead(c, r - 1).over(w).alias(f"last_{c}") for c in ("sym", "len", "run_no", "own")]
        inner = F.array(*[F.lead(F.struct("sym", "len"), j).over(w) for j in range(1, r - 1)]) if r > 2 else F.lit(None)
        text_grams = cut.select("seq_id", "sym", "len", "start", *ends, inner.alias("inner")).filter("last_own").withColumn("h", F.xxhash64("inner") if r > 2 else F.lit(0).cast("long"))
        p = patterns.filter(F.size("runs") == r)
        p_inner = F.slice("runs", 2, r - 2) if r > 2 else F.lit(None)
        p = p.select("pattern_id", "m", F.get("runs", F.lit(0))["sym"].alias("sym"), F.get("runs", F.lit(0))["len"].alias("p_first"), F.element_at("runs", -1)["sym"].alias("last_sym"), F.element_at("runs", -1)["len"].alias("p_last"), p_inner.alias("p_inner"))
        p = p.withColumn("h", F.xxhash64("p_inner") if r > 2 else F.lit(0).cast("long"))
        hit = text_grams.join(p, ["sym", "last_sym", "h"]).filter(_residual(r) & (F.col("inner") == F.col("p_inner") if r > 2 else F.lit(True)))
        start = F.col("start") + F.col("len") - F.col("p_first")
        out = out.unionByName(hit.select("seq_id", "pattern_id", start.alias("start"), (start + F.col("m")).alias("end"), F.col("last_run_no").alias("end_run")))
    return out


def anchors(text: DataFrame, patterns: DataFrame) -> DataFrame:
    """Patterns of three runs or more are found by their inner runs' first 2^j; the rest of the pattern is compared after the join."""
    kinds = [r[0] for r in patterns.filter(F.size("runs") > 2).select(F.floor(F.log2(F.size("runs") - 2)).cast("int").alias("j")).distinct().orderBy("j").collect()]
    out = grams(text, patterns.filter(F.size("runs") <= 2))
    for j in kinds:
        width = 1 << j
        p = patterns.filter((F.size("runs") > 2) & (F.floor(F.log2(F.size("runs") - 2)) == j))
        longest = p.agg(F.max(F.size("runs"))).first()[0]
        cut = windows(text, longest - 1)
        w = Window.partitionBy("seq_id", "piece").orderBy("run_no")
        ahead = F.collect_list(F.struct("sym", "len")).over(w.rowsBetween(0, longest - 1)).alias("ahead")
        own_end = [F.col("run_no"), F.col("piece")]
        text_grams = cut.select("seq_id", "sym", "len", "start", *own_end, ahead).filter(F.size("ahead") >= width + 2).withColumn("h", F.xxhash64(F.slice("ahead", 2, width)))
        q = p.select("pattern_id", "m", "runs", F.size("runs").alias("r"), F.get("runs", F.lit(0))["sym"].alias("sym"), F.xxhash64(F.slice("runs", 2, width)).alias("h"))
        hit = text_grams.join(q, ["sym", "h"]).filter((F.size("ahead") >= F.col("r")) & ((F.col("run_no") + F.col("r") - 2) / GRAM_CHUNK).cast("long").eqNullSafe(F.col("piece")))
        end = F.get("ahead", F.col("r") - 1)
        same = F.slice("ahead", F.lit(2), F.col("r") - 2) == F.slice("runs", F.lit(2), F.col("r") - 2)
        last, first = F.element_at("runs", -1), F.get("runs", F.lit(0))
        hit = hit.filter(same & (end["sym"] == last["sym"]) & (last["len"] <= end["len"]) & (first["len"] <= F.col("len")))
        start = F.col("start") + F.col("len") - first["len"]
        out = out.unionByName(hit.select("seq_id", "pattern_id", start.alias("start"), (start + F.col("m")).alias("end"), (F.col("run_no") + F.col("r") - 1).alias("end_run")))
    return out


def shards(text: DataFrame, patterns: DataFrame, parts: int = 4) -> DataFrame:
    """The dictionary in parts by a hash of the id, each small enough to broadcast, one after the other; more parts than asked for where it is larger.

    The driver holds one part at a time while the plan is made.
    """
    total = patterns.agg(F.sum(F.size("runs"))).first()[0] or 0
    parts, out = max(parts, -(-2 * total // MAX_PATTERN_RUNS)), None
    for k in range(parts):
        part = full(text, patterns) if parts == 1 else full(text, patterns.filter(F.pmod(F.xxhash64("pattern_id"), F.lit(parts)) == k))
        out = part if out is None else out.unionByName(part)
    return out


def closure(text: DataFrame, patterns: DataFrame) -> DataFrame:
    """Kernel rows (state's report index, run) without expansion, joined with the closure of every index: what it reports by symbol and last length.

    A dictionary too large to broadcast is taken in parts.
    """
    total = patterns.agg(F.sum(F.size("runs"))).first()[0] or 0
    parts, out = max(1, -(-2 * total // MAX_PATTERN_RUNS)), None
    for k in range(parts):
        part = _closure(text, patterns if parts == 1 else patterns.filter(F.pmod(F.xxhash64("pattern_id"), F.lit(parts)) == k))
        out = part if out is None else out.unionByName(part)
    return out


def _closure(text: DataFrame, patterns: DataFrame) -> DataFrame:
    spark = text.sparkSession
    frozen = Frozen(GroupedAutomaton(Dictionary(pattern_list(patterns))))
    rows = [
        (i, sym, frozen.dictionary.last_len[name], name, frozen.dictionary.length[name])
        for i, root in enumerate(frozen.names)
        for sym in frozen.symbols.values()
        for name in frozen.index.query(root, sym, 1 << 60)
    ]
    table = spark.createDataFrame(rows, "ix long, sym long, x long, pattern_id long, m long")
    shared = spark.sparkContext.broadcast(frozen)
    kind = text.schema["seq_id"].dataType.simpleString()

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = shared.value
        for batch in batches:
            sym, n, start, border = _coded_runs(batch.column(1), f.symbols)
            run, ix = f.reports(sym, n, border)
            owner = np.searchsorted(border, run, "right") - 1
            cols = (ix, sym[run], n[run], start[run], run - border[owner] + 1)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(owner)), *[pa.array(c.astype(np.int64)) for c in cols]], ["seq_id", "ix", "sym", "y", "at", "end_run"])

    asked = text.select("seq_id", "runs").mapInArrow(kernel, f"seq_id {kind}, ix long, sym long, y long, at long, end_run long")
    hit = asked.join(table, ["ix", "sym"]).filter("x <= y")
    start = F.col("at") + F.col("x") - F.col("m")
    multi = hit.select("seq_id", "pattern_id", start.alias("start"), (start + F.col("m")).alias("end"), "end_run")
    return multi.unionByName(single_run(explode_runs(text), patterns).select(*MATCH_COLUMNS))


def prefilter(text: DataFrame, patterns: DataFrame) -> DataFrame:
    """Sequences that hold the rarest symbol pair of some pattern (or its symbol), by a semi join; only they reach the kernel."""
    pair = lambda a, b: F.concat_ws("\x01", a["sym"].cast("string"), b["sym"].cast("string"))
    pairs_of = F.transform(F.sequence(F.lit(0), F.size("runs") - 2), lambda i: pair(F.get("runs", i), F.get("runs", i + 1)))
    both = lambda df: F.when(F.size("runs") > 1, pairs_of).otherwise(F.expr("cast(array() as array<string>)"))
    seen = text.select("seq_id", F.explode(F.array_distinct(F.concat(F.transform("runs", lambda r: r["sym"].cast("string")), both(text)))).alias("key"))
    counts = seen.groupBy("key").agg(F.count(F.lit(1)).alias("n"))
    own = patterns.select("pattern_id", F.explode(F.when(F.size("runs") > 1, pairs_of).otherwise(F.array(F.get("runs", F.lit(0))["sym"].cast("string")))).alias("key"))
    rarest = own.join(counts, "key", "left").groupBy("pattern_id").agg(F.min_by("key", F.struct(F.coalesce("n", F.lit(0)), "key")).alias("key")).select("key").distinct()
    kept = seen.join(rarest, "key", "left_semi").select("seq_id").distinct()
    return shards(text.join(kept, "seq_id", "left_semi"), patterns, 1)

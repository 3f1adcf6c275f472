"""Dictionary matching as Spark plans: the grouped automaton, the simple one, single runs, and the baselines.

Text comes as seq_id with runs (array<struct<sym,len>>) or with a string column; rows of a long sequence may be chunks with
the runs that lead into them. The dictionary is small enough for the driver (MAX_PATTERN_RUNS) or goes through the joins of
runloom.plans.strategies. Kernels are map-only: the frozen automaton is broadcast, texts stay where they are.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from runloom.functions.encode import decode
from runloom.operators.automaton import Automaton, Counters, Dictionary, Frozen, GroupedAutomaton
from runloom.types import COST_DDL, MATCH_DDL, Run, pattern_runs

#: Pattern runs that the driver builds an automaton of: about 300 bytes each when frozen.
MAX_PATTERN_RUNS = 2_000_000
#: Characters that a kernel encodes at once.
PIECE = 1 << 20
#: Occurrences that a kernel writes out at once.
EMIT = 1 << 20
#: Runs of a chunk of a long sequence.
CHUNK = 65_536


def pattern_list(patterns) -> list[tuple[int, tuple]]:
    """Patterns as (id, runs): a list as it is, or a DICT DataFrame after its size is checked."""
    if not isinstance(patterns, DataFrame):
        return [(name, pattern_runs(p)) for name, p in patterns]
    total = patterns.agg(F.sum(F.size("runs"))).first()[0] or 0
    if total > MAX_PATTERN_RUNS:
        raise ValueError(f"{total} pattern runs are too many to broadcast; use plans.strategies.match, which joins")
    return [(r["pattern_id"], tuple(Run(x["sym"], x["len"]) for x in r["runs"])) for r in patterns.select("pattern_id", "runs").collect()]


def _coded_runs(column: pa.Array, symbols: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """sym (-1: in no pattern), len, start and borders of a column of runs."""
    counts = np.asarray(column.value_lengths().fill_null(0), np.int64)
    flat = column.flatten()
    names = flat.field(0).dictionary_encode() if len(flat) else None
    code = np.array([symbols.get(x, -1) for x in names.dictionary.to_pylist()] + [-1], np.int64) if names is not None else np.zeros(1, np.int64)
    sym = code[np.asarray(names.indices.fill_null(len(code) - 1))] if names is not None else np.zeros(0, np.int64)
    n = np.asarray(flat.field(1), np.int64) if len(flat) else np.zeros(0, np.int64)
    border = np.concatenate([[0], np.cumsum(counts)])
    total = np.cumsum(n) - n
    start = total - np.repeat(total[border[:-1][counts > 0]], counts[counts > 0]) if len(n) else total
    return sym, n, start, border


def _coded_text(texts: list[str], table: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The same for strings: characters are compared with their neighbours, nothing is split off row by row."""
    points = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), "<u4")
    ends = np.cumsum([len(t) for t in texts])
    edge = np.ones(len(points) + 1, bool)
    edge[1:-1] = points[1:] != points[:-1]
    edge[ends] = True
    first = np.flatnonzero(edge[:-1])
    n = np.diff(np.concatenate([first, [len(points)]]))
    known, number = table
    k = np.minimum(np.searchsorted(known, points[first]), max(0, len(known) - 1))
    sym = np.where(known[k] == points[first], number[k], -1) if len(known) else np.full(len(first), -1)
    border = np.concatenate([[0], np.searchsorted(first, ends)])
    start = first - np.repeat(np.concatenate([[0], ends[:-1]]), np.diff(border))
    return sym, n, start, border


def _single(d: Dictionary, sym: np.ndarray, n: np.ndarray, start: np.ndarray, skip: np.ndarray) -> Iterator[tuple]:
    """(run, id, length, first start, last start) of single-run patterns: a row for a pattern and run."""
    for s, items in d.lists.items():
        at = np.flatnonzero((sym == s) & ~skip)
        for x, name in items:  # shortest first: later ones find fewer runs
            at = at[n[at] >= x]
            if not len(at):
                break
            yield at, name, x, start[at], start[at] + n[at] - x


def _each_start(found: list[np.ndarray]) -> Iterator[list[np.ndarray]]:
    """Occurrences of _hits start by start, EMIT rows at a time: a single run may hold any number of them."""
    run, pat, first, last, size = found
    many = last - first + 1
    ends = np.cumsum(many)
    for lo in range(0, int(ends[-1]) if len(ends) else 0, EMIT):
        place = np.arange(lo, min(lo + EMIT, int(ends[-1])))
        row = np.searchsorted(ends, place, "right")
        begin = first[row] + place - (ends[row] - many[row])
        yield [run[row], pat[row], begin, begin, size[row]]


def _hits(frozen: Frozen, sym, n, start, border, lead):
    """run, pattern id, first start, last start, length of all occurrences in a piece; those of a single-run pattern in one run are one row."""
    skip = np.zeros(len(sym), bool)
    if lead is not None:
        inside = np.arange(len(sym)) - np.repeat(border[:-1], np.diff(border))
        skip = inside < np.repeat(lead, np.diff(border))
    run, pat, begin = frozen.multi(sym, n, start, border, lead=lead)
    ids = np.array(frozen.names, np.int64) if frozen.names else np.zeros(0, np.int64)
    parts = [(run, ids[pat] if len(pat) else np.zeros(0, np.int64), begin, begin, frozen.lengths[pat] if len(pat) else np.zeros(0, np.int64))]
    for at, name, x, a, b in _single(frozen.dictionary, sym, n, start, skip):
        parts.append((at, np.full(len(at), name, np.int64), a, b, np.full(len(at), x, np.int64)))
    return [np.concatenate(c) for c in zip(*parts)]


def full(text: DataFrame, patterns, emit: str = "starts", where=None, deterministic: bool = False) -> DataFrame:
    """All occurrences: seq_id, pattern_id, start, end, end_run.

    text: seq_id and runs, or seq_id and text; chunks also have base (start of their first run), lead (runs that only lead in)
    and first_run. emit: "starts", "compact" (first_start and last_start: a single-run pattern's hits in one run are one row),
    or "counts" (seq_id, pattern_id, occ, without making a row an occurrence). where is applied before the kernel, so that
    it reaches the scan. Null or empty texts have no occurrences; an empty dictionary finds nothing; repeated patterns are
    reported under each id; null symbols end runs and match nothing.
    """
    spark = text.sparkSession
    text = text.filter(where) if where is not None else text
    rows = pattern_list(patterns)
    frozen = spark.sparkContext.broadcast(Frozen(GroupedAutomaton(Dictionary(rows), deterministic)))
    kind = text.schema["seq_id"].dataType.simpleString()
    columns = [c for c in ("seq_id", "runs", "text", "base", "lead", "first_run") if c in text.columns]
    ddl = {"starts": MATCH_DDL.format(id_type=kind), "compact": f"seq_id {kind}, pattern_id long, first_start long, last_start long, len long", "counts": f"seq_id {kind}, pattern_id long, occ long"}[emit]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f: Frozen = frozen.value
        named = sorted((ord(s), k) for s, k in f.symbols.items() if isinstance(s, str) and len(s) == 1)
        table = (np.array([c for c, _ in named], np.uint32), np.array([k for _, k in named], np.int64))
        for batch in batches:
            for part in _parts(batch):
                if "text" in columns:
                    coded = _coded_text([x or "" for x in part.column("text").to_pylist()], table)
                else:
                    coded = _coded_runs(part.column("runs"), f.symbols)
                sym, n, start, border = coded
                extra = {c: np.asarray(part.column(c), np.int64) for c in ("base", "lead", "first_run") if c in columns}
                found = _hits(f, sym, n, start, border, extra.get("lead"))
                for run, pat, first, _, size in _each_start(found) if emit == "starts" else ():
                    owner = np.searchsorted(border, run, "right") - 1
                    base = extra["base"][owner] if "base" in extra else 0
                    number = run - border[owner] + (extra["first_run"][owner] if "first_run" in extra else 1)
                    cols = [part.column("seq_id").take(pa.array(owner)), pa.array(pat), pa.array(first + base), pa.array(first + base + size), pa.array(number)]
                    yield pa.RecordBatch.from_arrays(cols, ["seq_id", "pattern_id", "start", "end", "end_run"])
                if emit == "starts":
                    continue
                run, pat, first, last, size = found
                owner = np.searchsorted(border, run, "right") - 1
                seq = part.column("seq_id").take(pa.array(owner))
                base = extra["base"][owner] if "base" in extra else 0
                if emit == "compact":
                    cols, names = [seq, pa.array(pat), pa.array(first + base), pa.array(last + base), pa.array(size)], ["seq_id", "pattern_id", "first_start", "last_start", "len"]
                else:
                    key, inv = np.unique(np.stack([owner, pat]), axis=1, return_inverse=True)
                    total = np.bincount(inv.reshape(-1), last - first + 1, key.shape[1]).astype(np.int64)
                    cols, names = [part.column("seq_id").take(pa.array(key[0])), pa.array(key[1]), pa.array(total)], ["seq_id", "pattern_id", "occ"]
                yield pa.RecordBatch.from_arrays(cols, names)

    def _parts(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        if "text" not in columns:
            if batch.num_rows:
                yield batch
            return
        sizes = np.cumsum(np.asarray(pa.compute.utf8_length(batch.column("text")).fill_null(0), np.int64))
        lo = 0
        while lo < batch.num_rows:
            done = sizes[lo - 1] if lo else 0
            hi = max(lo + 1, int(np.searchsorted(sizes, done + PIECE, "right")))
            yield batch.slice(lo, hi - lo)
            lo = hi

    import pyarrow.compute  # noqa: F401  used by the kernel's closure

    return text.select(*columns).mapInArrow(kernel, ddl)


def deterministic(text: DataFrame, patterns, symbols: DataFrame | None = None) -> DataFrame:
    """The variant without hashing: symbols are reduced to ranks first, structures are searched."""
    from runloom.operators.alphabet import reduce

    reduced, patterns_reduced = reduce(patterns, text)
    return full(reduced, patterns_reduced, deterministic=True)


def _walked(text: DataFrame, patterns, kind: type[Automaton], counters: bool) -> DataFrame:
    spark = text.sparkSession
    shared = spark.sparkContext.broadcast(kind(Dictionary(pattern_list(patterns))))
    ids = text.schema["seq_id"].dataType.simpleString()
    ddl = (COST_DDL if counters else MATCH_DDL).format(id_type=ids)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a = shared.value
        for batch in batches:
            out = []
            for seq, runs in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                cost, coded = Counters(), a.encode([(r["sym"], r["len"]) for r in runs or ()])
                for name, start, k in a.walk(coded, cost):
                    if not counters:
                        out.append((seq, name, start, start + a.dictionary.length[name], k + 1))
                if counters:
                    out.append((seq, sum(r.len for r in coded), len(coded), cost.edges, cost.fail_hops, cost.pred_queries, cost.report_queries, cost.report_steps, cost.occ))
            names = [x.split()[0] for x in ddl.split(", ")]
            types = [batch.column(0).type] + [pa.int64()] * (len(names) - 1)
            yield pa.RecordBatch.from_arrays([pa.array([r[j] for r in out], t) for j, t in enumerate(types)], names)

    return text.select("seq_id", "runs").mapInArrow(kernel, ddl)


def simple(text: DataFrame, patterns) -> DataFrame:
    """The simple automaton, one run at a time."""
    return _walked(text, patterns, Automaton, False)


def counters(text: DataFrame, patterns, variant: str = "grouped") -> DataFrame:
    """Operation counts of a sequence: n, n_runs, edges, fail_hops, pred_queries, report_queries, report_steps, occ."""
    return _walked(text, patterns, GroupedAutomaton if variant == "grouped" else Automaton, True)


def single_run(runs: DataFrame, patterns: DataFrame, emit: str = "starts") -> DataFrame:
    """Single-run patterns as a join on the symbol: runs in long form, patterns as DICT. The dictionary side is small; AQE broadcasts it."""
    p = patterns.filter(F.size("runs") == 1).select("pattern_id", F.get("runs", F.lit(0))["sym"].alias("sym"), F.get("runs", F.lit(0))["len"].alias("x"))
    hit = runs.join(p, "sym").filter(F.col("x") <= F.col("len"))
    last = F.col("start") + F.col("len") - F.col("x")
    if emit == "compact":
        return hit.select("seq_id", "pattern_id", F.col("start").alias("first_start"), last.alias("last_start"), F.col("x").alias("len"))
    return hit.select("seq_id", "pattern_id", F.explode(F.sequence(F.col("start"), last)).alias("start"), "x", "run_no").select(
        "seq_id", "pattern_id", "start", (F.col("start") + F.col("x")).alias("end"), F.col("run_no").alias("end_run")
    )


def chunks(runs: DataFrame, halo: int, size: int = CHUNK) -> DataFrame:
    """Long form to chunk rows for full(): seq_id, runs, base, lead, first_run. Each chunk carries the halo runs before it."""
    number = F.col("run_no") - 1
    first, last = F.expr(f"(run_no - 1) div {size}"), F.expr(f"(run_no - 1 + {halo}) div {size}")
    copies = runs.withColumn("chunk", F.explode(F.sequence(first, last)))
    rows = copies.groupBy("seq_id", "chunk").agg(
        F.array_sort(F.collect_list(F.struct("run_no", "sym", "len"))).alias("r"), F.min("start").alias("base"), F.min("run_no").alias("first_run"),
        F.count(F.when(number < F.col("chunk") * size, 1)).alias("lead"), F.count(F.when(number >= F.col("chunk") * size, 1)).alias("own"),
    )
    return rows.filter("own > 0").select("seq_id", F.transform("r", lambda x: F.struct(x["sym"].alias("sym"), x["len"].alias("len"))).alias("runs"), "base", "lead", "first_run")


def search(text: DataFrame, patterns, overlaps: str = "all", limit_per_seq: int | None = None, fold: bool = False, labels: dict | None = None) -> DataFrame:
    """full() with a user's options: seq_id, pattern_id, start, end, end_run (and label).

    overlaps: "all" or "leftmost_longest". limit_per_seq: that many occurrences of each sequence, first by start, then by id.
    fold: letters of texts and string patterns count as lower case. labels: a name for each id, null where there is none.
    """
    if fold:
        if "text" not in text.columns:
            raise ValueError("case is folded in texts, before they become runs")
        text = text.withColumn("text", F.lower("text"))
        patterns = [(name, p.lower()) for name, p in patterns]
    found = full(text, patterns)
    if overlaps != "all":
        from runloom.operators.intervals import leftmost_longest

        if overlaps != "leftmost_longest":
            raise ValueError(f"overlaps: all or leftmost_longest, not {overlaps}")
        found = leftmost_longest(found)
    if limit_per_seq is not None:
        number = F.row_number().over(Window.partitionBy("seq_id").orderBy("start", "pattern_id"))
        found = found.withColumn("__number", number).filter(F.col("__number") <= limit_per_seq).drop("__number")
    if labels is not None:
        names = text.sparkSession.createDataFrame(list(labels.items()), "pattern_id long, label string")
        found = found.join(F.broadcast(names), "pattern_id", "left")
    return found


# --- baselines ---------------------------------------------------------------------------------------------------------


class CharAutomaton:
    """The classic automaton over single symbols: children, failure and output links."""

    def __init__(self, patterns: list[tuple[object, list]], one_output: bool = False) -> None:
        self.next: list[dict] = [{}]
        self.own: list[list] = [[]]
        self.size = {name: len(p) for name, p in patterns}
        for name, p in patterns:
            v = 0
            for c in p:
                if c not in self.next[v]:
                    self.next[v][c] = len(self.next)
                    self.next.append({})
                    self.own.append([])
                v = self.next[v][c]
            self.own[v].append(name)
        self.fail, self.output = [0] * len(self.next), [0] * len(self.next)
        queue = deque(self.next[0].values())
        while queue:
            v = queue.popleft()
            self.output[v] = self.fail[v] if self.own[self.fail[v]] else self.output[self.fail[v]]
            for c, u in self.next[v].items():
                f = self.fail[v]
                while f and c not in self.next[f]:
                    f = self.fail[f]
                self.fail[u] = self.next[f].get(c, 0)
                queue.append(u)
        self.one_output = one_output

    def walk(self, symbols):
        v = 0
        for k, c in enumerate(symbols):
            while v and c not in self.next[v]:
                v = self.fail[v]
            v = self.next[v].get(c, 0)
            u = v if self.own[v] else self.output[v]
            if self.one_output and k + 1 < len(symbols) and symbols[k + 1] == c:
                continue  # only the end of a run is a node of its own
            while u:
                for name in self.own[u]:
                    yield name, k + 1 - self.size[name]
                u = 0 if self.one_output else self.output[u]


def _expanded(patterns) -> list[tuple[object, list]]:
    return [(name, [s for s, n in runs for _ in range(n)]) for name, runs in pattern_list(patterns)]


def char_automaton(text: DataFrame, patterns, one_output: bool = False) -> DataFrame:
    """seq_id, pattern_id, start by the classic automaton; text: seq_id and symbols (a string or an array). one_output: only the longest pattern that ends where a run ends."""
    shared = text.sparkSession.sparkContext.broadcast(CharAutomaton(_expanded(patterns), one_output))
    kind = text.schema["seq_id"].dataType.simpleString()

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = [(seq, name, start) for seq, s in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()) for name, start in shared.value.walk(s or ())]
            types = (batch.column(0).type, pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array([r[j] for r in out], t) for j, t in enumerate(types)], ["seq_id", "pattern_id", "start"])

    return text.select("seq_id", "symbols").mapInArrow(kernel, f"seq_id {kind}, pattern_id long, start long")


def decompress_then_match(text: DataFrame, patterns) -> DataFrame:
    """Runs are written out as arrays of symbols first, then walked by the classic automaton."""
    from runloom.functions.encode import decode_array

    return char_automaton(text.select("seq_id", decode_array(F.col("runs")).alias("symbols")), patterns)


def single_pattern(text: DataFrame, pattern: str) -> DataFrame:
    """seq_id, start of one pattern by its prefix function; text: seq_id and symbols."""
    border = [0] * len(pattern)
    for k in range(1, len(pattern)):
        j = border[k - 1]
        while j and pattern[k] != pattern[j]:
            j = border[j - 1]
        border[k] = j + (pattern[k] == pattern[j])
    kind = text.schema["seq_id"].dataType.simpleString()

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for seq, s in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                j = 0
                for k, c in enumerate(s or ""):
                    while j and (j == len(pattern) or c != pattern[j]):
                        j = border[j - 1]
                    j += c == pattern[j]
                    if j == len(pattern):
                        out.append((seq, k + 1 - j))
            types = (batch.column(0).type, pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array([r[c] for r in out], t) for c, t in enumerate(types)], ["seq_id", "start"])

    return text.select("seq_id", "symbols").mapInArrow(kernel, f"seq_id {kind}, start long")


def longest_only(text: DataFrame, patterns) -> DataFrame:
    """The incomplete shortcut: one output link for each end of a run, so only the longest pattern that ends there is reported. It misses answers on purpose."""
    from runloom.functions.encode import decode_array

    return char_automaton(text.select("seq_id", decode_array(F.col("runs")).alias("symbols")), patterns, one_output=True)


def brute_force(text: DataFrame, patterns: DataFrame) -> DataFrame:
    """Every position against every pattern of fitting length: text and patterns are decoded, positions of one length joined by equality."""
    p = patterns.select("pattern_id", decode(F.col("runs")).alias("p")).withColumn("m", F.length("p"))
    lengths = p.select("m").distinct()
    t = text.select("seq_id", decode(F.col("runs")).alias("s"))
    at = t.crossJoin(F.broadcast(lengths)).filter("m <= length(s)")  # a row for each distinct length, which is few
    windows = at.select("seq_id", "m", "s", F.explode(F.sequence(F.lit(0), F.length("s") - F.col("m"))).alias("start")).withColumn("p", F.expr("substr(s, start + 1, m)"))
    return windows.drop("s").join(p, ["m", "p"]).select("seq_id", "pattern_id", F.col("start").cast("long").alias("start"))

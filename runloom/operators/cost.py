"""Measures: sizes, operation counts, space, build work, probes. Built on the driver for dictionaries, on executors for texts."""

from __future__ import annotations

import random

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from runloom.operators.automaton import Automaton, Dictionary, GroupedAutomaton, grouped, simple
from runloom.operators.catr import Catr
from runloom.operators.match import counters, pattern_list
from runloom.operators.predecessor import PerfectHash, SortedArray, XFast, YFast
from runloom.operators.space import by_joins
from runloom.operators.tries import by_pairs, compact_trie
from runloom.operators.truncated import implicit_output_links
from runloom.sources.store import stored
from runloom.types import Run, pattern_runs

#: Pattern runs up to which space() builds the automata on the driver.
DRIVER_RUNS = 100_000


def sizes(text: DataFrame, patterns) -> DataFrame:
    """One row: n, n_runs, ratio of the text; k, m, m_runs, ratio_patterns, sigma of the dictionary; lower_bound: runs that any method reads."""
    p = Dictionary(patterns).sizes
    row = text.agg(F.sum(F.aggregate("runs", F.lit(0).cast("long"), lambda s, r: s + r["len"])).alias("n"), F.sum(F.size("runs")).alias("n_runs"))
    fixed = [F.lit(v).cast("long").alias(k) for k, v in p.items()]
    return row.select("n", "n_runs", (F.col("n") / F.col("n_runs")).alias("ratio"), *fixed, F.lit(p["m"] / max(1, p["m_runs"])).alias("ratio_patterns"), (F.col("n_runs") + p["m_runs"]).alias("lower_bound"))


def build(patterns) -> dict[str, int]:
    """Link hops and predecessor queries of both builds."""
    d = Dictionary(patterns)
    a, b = Automaton(d), GroupedAutomaton(d)
    return {"simple_hops": a.build.fail_hops, "simple_pred": a.build.pred_queries, "grouped_hops": b.build.fail_hops, "grouped_pred": b.build.pred_queries} | d.sizes


def space(spark: SparkSession, dictionaries: dict) -> DataFrame:
    """dictionary, structure, words, m_runs. Dictionaries are lists, or DICT DataFrames of any size: beyond DRIVER_RUNS joins tell what the automata hold."""
    rows = []
    for name, patterns in dictionaries.items():
        if isinstance(patterns, DataFrame):
            patterns = stored(patterns.select("pattern_id", "runs"), "dictionary")
            large = (patterns.agg(F.sum(F.size("runs"))).first()[0] or 0) > DRIVER_RUNS
            patterns = patterns if large else pattern_list(patterns)
        if isinstance(patterns, DataFrame):
            found = by_joins(patterns)
        else:
            found = grouped(patterns).space | {f"build_{k}": v for k, v in build(patterns).items()}
        rows += [(name, k, int(v), int(found["build_m_runs"])) for k, v in found.items()]
    return spark.createDataFrame(rows, "dictionary string, structure string, words long, m_runs long")


def trie_sizes(patterns) -> dict[str, int]:
    """Nodes of the compact trie and of the run trie, groups, nodes that mending the trie of pairs moved or joined."""
    root, mended = by_pairs([(k, pattern_runs(r)) for k, r in patterns])
    a = grouped(patterns)
    return {"compact": sum(1 for _ in root.walk()), "run_trie": len(a.trie.parent), "groups": len(a.members)} | mended


def links(spark: SparkSession, patterns) -> DataFrame:
    """node, simple_link, group_link, report_ix: strings as symbol and length pairs; the root is empty, no report index is -1."""
    a, b = simple(patterns), grouped(patterns)
    names = {v: k for k, v in a.dictionary.symbol.items()}
    show = lambda v: "".join(f"{names[s]}{n}" for s, n in a.trie.string(v))
    rows = [(show(v), show(a.fail[v]), show(b.fail[v]), -1 if b.report_ix[v] is None else b.report_ix[v]) for v in range(len(a.trie.parent))]
    return spark.createDataFrame(rows, "node string, simple_link string, group_link string, report_ix long")


def family(text: DataFrame, sym: str) -> DataFrame:
    """m, implicit output links of single characters, words stored here, occurrences of both patterns in the text (seq_id, runs).

    A family for every length m >= 3 of the text's runs of a symbol (shorter ones have no two patterns); one automaton and one scan for all of them.
    """
    from runloom.operators.match import full
    from runloom.plans.dictionaries import family as patterns_of

    lengths = text.select(F.explode(F.filter("runs", lambda r: (r["sym"] == sym) & (r["len"] >= 3))).alias("r")).select(F.col("r.len").alias("m")).distinct()
    rows, patterns = [], []
    for m in sorted(r["m"] for r in lengths.collect()):
        own = [(k, tuple(Run(sym, n) for _, n in p)) for k, p in patterns_of(m)]
        rows.append((m, implicit_output_links(own), sum(map(len, Dictionary(own).lists.values()))))
        patterns += [(2 * m + k - 1, p) for k, p in own]
    found = full(text, patterns, emit="counts").groupBy(F.expr("pattern_id div 2").alias("m")).agg(F.sum("occ").cast("long").alias("occ"))
    return text.sparkSession.createDataFrame(rows, "m long, implicit_links long, stored_words long").join(found, "m")


def adversary(text: DataFrame, q: int) -> DataFrame:
    """q, variant, n_runs, edges, fail_hops, occ of both variants over all sequences (seq_id, runs) with the patterns a^i b, i up to q."""
    from runloom.plans.dictionaries import adversary as patterns_of

    parts = [counters(text, patterns_of(q), v).withColumn("variant", F.lit(v)) for v in ("grouped", "simple")]
    both = parts[0].unionByName(parts[1]).groupBy("variant").agg(*[F.sum(c).cast("long").alias(c) for c in ("n_runs", "edges", "fail_hops", "occ")])
    return both.select(F.lit(q).cast("long").alias("q"), "variant", "n_runs", "edges", "fail_hops", "occ")


def compact_trie_sizes(spark: SparkSession, strings) -> DataFrame:
    nodes = list(compact_trie(strings).walk())
    return spark.createDataFrame([(len(nodes), sum(v.depth for v in nodes))], "nodes long, depth_sum long")


def catr_index(spark: SparkSession, tree: DataFrame, colours: DataFrame, queries: DataFrame) -> DataFrame:
    """Coloured ancestor queries through the index. The tree is the driver's; queries are answered where they are."""
    rows = sorted((r["node"], r["parent"]) for r in tree.collect())
    place = {v: k for k, (v, _) in enumerate(rows)}
    marks: list[dict] = [{} for _ in rows]
    for r in colours.collect():
        marks[place[r["node"]]][r["colour"]] = r["weight"]
    shared = spark.sparkContext.broadcast((Catr([-1 if p is None else place[p] for _, p in rows], marks), place, [v for v, _ in rows]))

    def answer(frames):
        index, at, names = shared.value
        for frame in frames:
            found = frame.assign(ancestor=[[names[a] for a in index.query(at[v], c, w)] for v, c, w in zip(frame["node"], frame["colour"], frame["w"])])
            yield found.explode("ancestor").dropna().astype({"ancestor": "int64"})

    return queries.select("node", "colour", "w").mapInPandas(answer, "node long, colour string, w long, ancestor long")


def probes(spark: SparkSession, sizes=(100, 1_000, 10_000), universe: int = 1 << 32) -> DataFrame:
    """structure, keys, mean probes a query, stored entries a key."""
    draw, rows = random.Random(5), []
    for n in sizes:
        keys = draw.sample(range(universe), n)
        asked = [draw.randrange(universe) for _ in range(500)]
        for name, s in (("sorted array", SortedArray(keys)), ("x-fast", XFast(keys, universe)), ("y-fast", YFast(keys, universe)), ("y-fast deterministic", YFast(keys, universe, True))):
            for x in asked:
                s.pred(x)
            entries = n if name == "sorted array" else s.entries
            rows.append((name, n, s.probes / len(asked), entries / n))
        h = PerfectHash(keys)
        for x in asked:
            h.contains(x)
        rows.append(("perfect hash", n, h.probes / len(asked), h.cells / n))
    return spark.createDataFrame(rows, "structure string, keys long, probes double, entries_per_key double")

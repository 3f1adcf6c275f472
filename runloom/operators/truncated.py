"""Truncate matching: of a string, the last run may be shorter than asked and the rest must be a suffix."""

from __future__ import annotations

import bisect

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from runloom.operators.catr import Catr, RankMap
from runloom.operators.tries import Node, compact_trie, number
from runloom.types import Runs, length


def is_suffix(a: Runs, b: Runs) -> bool:
    """a is a suffix of b as a string: inner runs equal, the first of a at most as long as the run it meets."""
    if not a:
        return True
    if len(a) > len(b):
        return False
    tail = b[len(b) - len(a) :]
    return tuple(a[1:]) == tuple(tail[1:]) and a[0][0] == tail[0][0] and a[0][1] <= tail[0][1]


def truncate_matches(a: Runs, b: Runs) -> bool:
    """a without its last run is a suffix of b without its last run; the last runs share the symbol, and a's is no longer."""
    return a[-1][0] == b[-1][0] and a[-1][1] <= b[-1][1] and is_suffix(a[:-1], b[:-1])


def matches(a: Column, b: Column) -> Column:
    """truncate_matches of two runs columns."""
    la, lb = F.element_at(a, -1), F.element_at(b, -1)
    k = F.size(a)
    tail = F.slice(b, F.greatest(F.size(b) - k + 1, F.lit(1)), k)
    inner = F.forall(F.zip_with(a, F.transform(tail, lambda r, i: F.struct(r["sym"].alias("sym"), r["len"].alias("len"), i.alias("i"))), lambda x, y: (x["sym"] == y["sym"]) & F.when((y["i"] == 0) | (y["i"] == k - 1), x["len"] <= y["len"]).otherwise(x["len"] == y["len"])), lambda x: x)
    return (la["sym"] == lb["sym"]) & (la["len"] <= lb["len"]) & (F.size(b) >= k) & inner


class TruncatedIndex:
    """Reports, for (i, symbol, w), all j whose string truncate-matches string i with its last run replaced by symbol^w.

    Strings stand in a compact trie of their reversed truncated strings. A node's colours are the last symbols of its
    strings, weighted by their shortest last run; ancestors of a node are the suffixes. Lists by node and symbol are
    ordered by last run, so that scanning them stops at the first that is too long.
    """

    def __init__(self, strings: list[tuple[object, Runs]], deterministic: bool = False) -> None:
        reverse = [(k, tuple(reversed(runs[:-1]))) for k, (_, runs) in enumerate(strings)]
        self.root: Node = compact_trie(reverse)
        self.nodes = number(self.root)
        self.node_of = {strings[k][0]: v.number for v in self.nodes for k in v.ends}
        lists: dict[tuple[int, object], list] = {}
        for v in self.nodes:
            for k in v.ends:
                name, runs = strings[k]
                lists.setdefault((v.number, runs[-1][0]), []).append((runs[-1][1], name))
        colours: list[dict] = [{} for _ in self.nodes]
        for (v, sym), items in lists.items():
            items.sort()
            colours[v][sym] = items[0][0]
        self.lists = RankMap(lists) if deterministic else lists
        self.parent = [v.parent.number if v.parent else -1 for v in self.nodes]
        self.colours = colours
        self.catr = Catr(self.parent, colours, deterministic)
        self.size = {"nodes": len(self.nodes), "colours": self.catr.entries, "list_entries": sum(map(len, lists.values())), "strings": len(strings)}

    def at_node(self, node: int, sym, w: int) -> list:
        out = []
        for v in self.catr.query(node, sym, w):
            items = self.lists.get((v, sym))
            out += [name for _, name in items[: bisect.bisect_right(items, w, key=lambda x: x[0])]]
        return sorted(out)

    def query(self, name, sym, w: int) -> list:
        return self.at_node(self.node_of[name], sym, w)


def implicit_output_links(strings: list[tuple[object, Runs]]) -> int:
    """How many output links an automaton of single characters needs: nodes whose string has a proper suffix that is a pattern."""
    patterns = [runs for _, runs in strings]
    seen, links = set(), 0
    for runs in patterns:
        for k, (sym, n) in enumerate(runs):
            for x in range(1, n + 1):
                prefix = (*runs[:k], (sym, x))
                if prefix not in seen:
                    seen.add(prefix)
                    links += any(is_suffix_of_string(p, prefix) and length(p) < length(prefix) for p in patterns)
    return links


def is_suffix_of_string(a: Runs, b: Runs) -> bool:
    """Suffix test where the last run must be equal unless a is one run."""
    if len(a) == 1:
        return a[0][0] == b[-1][0] and a[0][1] <= b[-1][1]
    return is_suffix(tuple(a), tuple(b))


def _ends(patterns: DataFrame) -> DataFrame:
    """j, sym and len of the last run, and the runs before it: first symbol, first length (null, 0 without one), rest and its hash."""
    last, head = F.element_at("runs", -1), F.slice("runs", 1, F.size("runs") - 1)
    rest = F.slice("runs", 2, F.greatest(F.size("runs") - 2, F.lit(0)))
    own = patterns.select(F.col("pattern_id").alias("j"), last["sym"].alias("sym"), last["len"].alias("len"), F.get(head, F.lit(0))["sym"].alias("first"), F.coalesce(F.get(head, F.lit(0))["len"], F.lit(0)).alias("least"), rest.alias("rest"))
    return own.withColumn("h", F.xxhash64("rest"))


def _suffixes(asked: DataFrame, runs: Column) -> DataFrame:
    """asked, one row for each suffix (in whole runs, the empty one too) of the runs before the last: afirst, most, arest and its hash ah."""
    places = F.transform(F.sequence(F.lit(1), F.size(runs)), lambda k: F.slice(runs, k, F.size(runs) - k))
    rows = asked.select(*asked.columns, F.explode(places).alias("s"))
    first = F.get("s", F.lit(0))
    rows = rows.select(*asked.columns, first["sym"].alias("afirst"), F.coalesce(first["len"], F.lit(0)).alias("most"), F.slice("s", 2, F.greatest(F.size("s") - 1, F.lit(0))).alias("arest"))
    return rows.withColumn("ah", F.xxhash64("arest"))


def _met(asked: DataFrame, patterns: DataFrame) -> DataFrame:
    """asked (asym, w, and the runs as _suffixes() has them) with the j that truncate-match. All but two lengths are join keys: pairs that are compared follow those that are found."""
    same = (F.col("asym") == F.col("sym")) & F.col("afirst").eqNullSafe(F.col("first")) & (F.col("ah") == F.col("h")) & (F.col("arest") == F.col("rest"))
    return asked.join(_ends(patterns), same & (F.col("least") <= F.col("most")) & (F.col("len") <= F.col("w")))


def pairs(patterns: DataFrame) -> DataFrame:
    """i, j: pattern j truncate-matches pattern i. Joined on the last symbol and on the suffixes of what comes before; the first and last lengths are the residual."""
    last = F.element_at("runs", -1)
    asked = patterns.select(F.col("pattern_id").alias("i"), "runs", last["sym"].alias("asym"), last["len"].alias("w"))
    return _met(_suffixes(asked, F.col("runs")).drop("runs"), patterns).select("i", "j")


def query_by_join(patterns: DataFrame, queries: DataFrame) -> DataFrame:
    """queries (i, sym, w) -> i, sym, w, j, all at once: joined as in pairs()."""
    ends = _suffixes(patterns.select(F.col("pattern_id").alias("i"), "runs"), F.col("runs")).drop("runs")
    asked = queries.select("i", F.col("sym").alias("asym"), "w").join(ends, "i")
    return _met(asked, patterns).select("i", F.col("asym").alias("sym"), "w", "j")


def classes(patterns: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Patterns of equal runs as one: pattern_id (the smallest), runs; and every pattern_id with its representative."""
    found = patterns.groupBy("runs").agg(F.min("pattern_id").alias("representative"))
    members = patterns.join(found, "runs").select("pattern_id", "representative")
    return found.select(F.col("representative").alias("pattern_id"), "runs"), members

"""Order of run-length encoded strings, compact tries over them, and the trie whose letters are whole runs."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from runloom.types import Run, Runs, length


# --- order -------------------------------------------------------------------------------------------------------------


def order_key(runs) -> tuple:
    """A key whose tuple order is the order of the strings.

    If the next symbol is larger, a longer run makes a smaller string; if it is smaller or missing, a larger one.
    """
    runs = tuple(runs)
    out = []
    for k, (sym, n) in enumerate(runs):
        rises = k + 1 < len(runs) and runs[k + 1][0] > sym
        out.append((sym, 1 if rises else -1, -n if rises else n))
    return tuple(out)


def order_key_column(runs: Column) -> Column:
    """order_key as array<struct>, which Spark sorts natively."""

    def one(r: Column, k: Column) -> Column:
        rises = F.coalesce(F.get(runs, k + 1)["sym"] > r["sym"], F.lit(False))
        return F.struct(r["sym"].alias("sym"), F.when(rises, 1).otherwise(-1).alias("side"), F.when(rises, -r["len"]).otherwise(r["len"]).alias("len"))

    return F.transform(runs, one)


def sort_rle(df: DataFrame, ids: str = "seq_id") -> DataFrame:
    """df (ids, runs) in the order of the strings, ties by id: one range exchange, nothing decoded."""
    return df.orderBy(order_key_column(F.col("runs")), F.col(ids))


def rank_rle(df: DataFrame, ids: str = "seq_id") -> DataFrame:
    """ids and rank (from 1) in string order. Equal keys are counted first; running sums over range partitions then give ranks."""
    keyed = df.select(ids, order_key_column(F.col("runs")).alias("k"))
    from runloom.sources.store import stored

    ordered = keyed.repartitionByRange("k", ids).sortWithinPartitions("k", ids).withColumn("part", F.spark_partition_id())
    ordered = stored(ordered.withColumn("at", F.monotonically_increasing_id()), "ranked")
    sizes = ordered.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    before = F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))  # a row per partition
    sizes = sizes.select("part", before.alias("before"))
    inside = F.col("at").bitwiseAND(F.lit((1 << 33) - 1))
    return ordered.join(sizes, "part").select(ids, (F.col("before") + inside + 1).cast("long").alias("rank"))


def lcp(a: Runs, b: Runs) -> int:
    """Length of the common prefix of two strings, read run by run."""
    total = 0
    for (s, x), (t, y) in zip(a, b):
        if s != t:
            return total
        total += min(x, y)
        if x != y:
            return total
    return total


def drop(runs: Runs, n: int) -> Runs:
    """The string without its first n symbols."""
    out: list[Run] = []
    for s, x in runs:
        cut = min(n, x)
        n -= cut
        if x > cut:
            out.append(Run(s, x - cut))
    return tuple(out)


def take(runs: Runs, n: int) -> Runs:
    out: list[Run] = []
    for s, x in runs:
        if n <= 0:
            break
        out.append(Run(s, min(n, x)))
        n -= x
    return tuple(out)


# --- compact trie from sorted strings ---------------------------------------------------------------------------------


@dataclass
class Node:
    """A trie node: label of the edge above, depth in symbols, ids of the strings that end here."""

    label: Runs = ()
    depth: int = 0
    ends: list = field(default_factory=list)
    children: list[Node] = field(default_factory=list)
    parent: Node | None = None
    number: int = -1

    def walk(self):
        """Preorder: the order of the strings."""
        stack = [self]
        while stack:
            v = stack.pop()
            yield v
            stack.extend(reversed(v.children))


def number(root: Node) -> list[Node]:
    out = list(root.walk())
    for k, v in enumerate(out):
        v.number = k
    return out


def from_sorted(strings: list[tuple[object, Runs]]) -> Node:
    """Compact trie of strings in ascending order. Only the rightmost path is open: each string leaves it at its common prefix with the one before."""
    root = Node()
    path, last = [root], ()
    for name, runs in strings:
        common, below = lcp(last, runs), None
        while path[-1].depth > common:
            below = path.pop()
        if path[-1].depth < common:  # the place is inside the edge to `below`
            upper = path[-1]
            head = common - upper.depth
            middle = Node(take(below.label, head), common, [], [below], upper)
            upper.children[-1] = middle
            below.label, below.parent = drop(below.label, head), middle
            path.append(middle)
        if length(runs) > common:
            leaf = Node(drop(runs, common), length(runs), [], [], path[-1])
            path[-1].children.append(leaf)
            path.append(leaf)
        path[-1].ends.append(name)
        last = runs
    return root


def compact_trie(strings: list[tuple[object, Runs]], method: str = "key") -> Node:
    """Compact trie of unsorted strings: by the order key, or by sorting strings of (symbol, length) letters and mending their trie."""
    if method == "key":
        return from_sorted(sorted(strings, key=lambda x: (order_key(x[1]), x[0])))
    root, _ = by_pairs(strings)
    return root


def by_pairs(strings: list[tuple[object, Runs]]) -> tuple[Node, dict[str, int]]:
    """The reduction: plain order of pairs, a trie with a run on each edge, then siblings of one symbol are chained by length.

    A longer sibling hangs below the next shorter one, with the rest of its run: below an inner node (counted as inner) or
    below the end of a string (counted as end). Nodes with one child that end no string are joined with it.
    """
    root, count = Node(), {"inner": 0, "end": 0, "joined": 0}
    for name, runs in sorted(strings, key=lambda x: (tuple(x[1]), x[0])):
        v = root
        for r in runs:
            if not v.children or v.children[-1].label != (Run(*r),):
                v.children.append(Node((Run(*r),), v.depth + r[1], [], [], v))
            v = v.children[-1]
        v.ends.append(name)
    stack = [root]
    while stack:
        v = stack.pop()
        stack.extend(v.children)  # as they stand now: those moved keep their own children
        kept, moved = list(v.children), set()
        for k in range(len(kept) - 1, 0, -1):
            shorter, longer = kept[k - 1], kept[k]
            if shorter.label[0].sym == longer.label[0].sym:
                count["inner" if shorter.children else "end"] += 1
                longer.label = (Run(longer.label[0].sym, longer.label[0].len - shorter.label[0].len), *longer.label[1:])
                longer.parent = shorter
                shorter.children.append(longer)
                moved.add(id(longer))
        v.children = [c for c in kept if id(c) not in moved]
    for v in root.walk():
        v.children.sort(key=lambda c: c.label[0].sym)
    _join_single(root, count)
    return root, count


def _join_single(root: Node, count: dict[str, int]) -> None:
    stack = [root]
    while stack:
        v = stack.pop()
        merged, last = list(v.label), v
        while v is not root and len(last.children) == 1 and not last.ends:  # the whole chain, then one label
            last = last.children[0]
            for r in last.label:
                if merged and merged[-1].sym == r.sym:
                    merged[-1] = Run(r.sym, merged[-1].len + r.len)
                else:
                    merged.append(r)
            count["joined"] += 1
        if last is not v:
            v.label, v.depth, v.ends, v.children = tuple(merged), last.depth, last.ends, last.children
            for c in v.children:
                c.parent = v
        stack.extend(v.children)


# --- trie of whole runs ------------------------------------------------------------------------------------------------


@dataclass
class RunTrie:
    """Arrays by node; node 0 is the root. Letters are whole runs."""

    parent: list[int]
    label: list[Run]
    depth: list[int]
    first_len: list[int]
    children: list[dict[Run, int]]
    ends: list[list]

    def string(self, v: int) -> Runs:
        out = []
        while v:
            out.append(self.label[v])
            v = self.parent[v]
        return tuple(reversed(out))


def run_trie(strings: list[tuple[object, Runs]]) -> RunTrie:
    """Trie of whole runs, in time and space of the runs; nodes are numbered level by level, in order, so that links point to smaller numbers or to the same depth's shorter first runs."""
    children, ends = [{}], {}
    for name, runs in strings:
        v = 0
        for r in runs:
            u = children[v].get(r)
            if u is None:
                u = len(children)
                children[v][Run(*r)] = u
                children.append({})
            v = u
        ends.setdefault(v, []).append(name)
    trie = RunTrie([0], [Run(None, 0)], [0], [0], [{}], [ends.get(0, [])])
    level = [(0, 0)]  # number as inserted, number in the trie
    while level:
        below = []
        for old, up in level:
            for label, child in sorted(children[old].items(), key=lambda x: (str(type(x[0].sym)), x[0])):
                v = len(trie.parent)
                trie.parent.append(up)
                trie.label.append(label)
                trie.depth.append(trie.depth[up] + 1)
                trie.first_len.append(trie.first_len[up] if up else label.len)
                trie.children.append({})
                trie.children[up][label] = v
                trie.ends.append(ends.get(child, []))
                below.append((child, v))
        level = below
    return trie


def run_trie_nodes(patterns: DataFrame) -> DataFrame:
    """The trie of whole runs as a plan: every distinct prefix of the patterns' runs, with its group.

    A node is the string of its prefix; a group is what follows the first run, and the first symbol. No driver is involved.
    """
    text = lambda c: F.array_join(F.transform(c, lambda r: F.concat_ws(":", r["sym"], r["len"])), ",")
    prefix = patterns.select(F.explode(F.transform(F.sequence(F.lit(1), F.size("runs")), lambda d: F.slice(F.col("runs"), F.lit(1), d))).alias("p"))
    rest = F.slice("p", 2, F.greatest(F.size("p") - 1, F.lit(0)))
    node = prefix.select(text(F.col("p")).alias("node"), F.size("p").cast("long").alias("depth_runs"), F.concat_ws("|", F.get("p", F.lit(0))["sym"], text(rest)).alias("group_key"), F.get("p", F.lit(0))["len"].alias("first_len"))
    return node.distinct()

"""What the automata of a dictionary hold and what building them costs, by joins, for dictionaries that the driver does not hold.

The figures are those of cost.space. A node is a prefix of a pattern in whole runs; its first run and the hash of what follows tell it,
and without the first run's length they tell its group (two polynomial hashes of 61 bits over hashed runs). A node's links lead along the nodes
that its string ends with: from place i on, those of the group (symbol i, runs after i) whose first run is no longer than run i. Such
groups are closed under dropping last runs, so each place is followed until a bitmap of the groups has no more; a join then decides.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from runloom.sources.store import stored

_MOD = (1 << 61) - 1
_BASES = (1_113_904_716_329_846_023, 2_017_512_630_781_943_377)
#: Bits of the bitmap of groups. More groups than bits cost rows that the join drops, and no result.
FILTER_BITS = 1 << 26
#: Rows that a kernel writes out at once.
ROWS = 1 << 16
_GROUP = ["sym", "d", "q1", "q2"]


def _coded(patterns: DataFrame) -> DataFrame:
    """A number, hashed symbols, lengths and hashed runs of the patterns of two runs or more."""
    runs = patterns.filter(F.size("runs") > 1)
    return runs.select(
        F.monotonically_increasing_id().alias("p"),
        F.transform("runs", lambda r: F.xxhash64(r["sym"])).alias("syms"),
        F.transform("runs", lambda r: r["len"].cast("long")).alias("lens"),
        F.transform("runs", lambda r: F.xxhash64(r["sym"], r["len"].cast("long"))).alias("hashed"),
    )


def _written(names: list[str], rows):
    """Batches of rows of whole numbers."""
    out = []
    for row in rows:
        out.append(row)
        if len(out) >= ROWS:
            yield _batch(names, out)
            out = []
    if out:
        yield _batch(names, out)


def _batch(names: list[str], rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows)], names)


def _each(batches, columns: list[str]):
    for batch in batches:
        yield from zip(*(batch.column(c).to_pylist() for c in columns))


def _hashes(hashed: list[int], base: int) -> list[int]:
    """Hashes of the first 0, 1, 2, ... runs."""
    out, q = [0], 0
    for t in hashed:
        q = (q * base + t) % _MOD
        out.append(q)
    return out


_NODE = ["p", "d", "sym", "first", "q1", "q2", "pq1", "pq2"]


def _node_rows(batches):
    """A row for each prefix of a pattern: depth, the first run, hashes of the runs after it and of all but the last of these."""

    def rows():
        for p, syms, lens, hashed in _each(batches, ["p", "syms", "lens", "hashed"]):
            a, b = (_hashes(hashed[1:], base) for base in _BASES)
            for d in range(len(syms)):
                yield p, d + 1, syms[0], lens[0], a[d], b[d], a[max(0, d - 1)], b[max(0, d - 1)]

    return _written(_NODE, rows())


_REVERSED = ["e", "h1", "h2", "ph1", "ph2", "sym", "len", "last"]


def _reversed_rows(batches):
    """A row for each prefix of a reversed pattern without its last run; last: that run's symbol where the prefix is all of it."""

    def rows():
        for _, syms, lens, hashed in _each(batches, ["p", "syms", "lens", "hashed"]):
            a, b = (_hashes(hashed[-2::-1], base) for base in _BASES)
            n = len(syms) - 1
            for e in range(1, n + 1):
                yield e, a[e], b[e], a[e - 1], b[e - 1], syms[n - e], lens[n - e], syms[n] if e == n else None

    return _written(_REVERSED, rows())


_ASKED = ["p", "at", "i", "w", "sym", "d", "q1", "q2", "here", "below"]


def _asked_rows(shared):
    """The groups that each node's string may end with: pattern, depth of the node, place i, longest first run, the group, whether node and child are asked for.

    Of nodes that patterns share, own tells the first depth that is a pattern's to answer for. At place 1 stand shorter first runs.
    """

    def kernel(batches):
        bits, powers = shared.value, [[1], [1]]

        def rows():
            for p, syms, lens, hashed, own in _each(batches, ["p", "syms", "lens", "hashed", "own"]):
                n = len(syms)
                a, b = (_hashes(hashed, base) for base in _BASES)
                for known, base in zip(powers, _BASES):
                    while len(known) <= n:
                        known.append(known[-1] * base % _MOD)
                for i in range(1, n + 1):
                    for at in range(max(i, own - 1), n + 1):
                        q1 = (a[at] - a[i] * powers[0][at - i]) % _MOD
                        k = (q1 ^ syms[i - 1]) & (FILTER_BITS - 1)
                        if not bits[k >> 3] >> (k & 7) & 1:
                            break
                        q2 = (b[at] - b[i] * powers[1][at - i]) % _MOD
                        yield p, at, i, lens[i - 1] - (i == 1), syms[i - 1], at - i + 1, q1, q2, int(at >= max(own, 2)), int(at < n)

        return _written(_ASKED, rows())

    return kernel


def _long(names: list[str]) -> str:
    return ", ".join(f"{c} long" for c in names)


def _bitmap(nodes: DataFrame) -> bytes:
    """A bit for each group's hash. The driver holds FILTER_BITS bits, whatever the dictionary."""
    place = F.col("q1").bitwiseXOR(F.col("sym")).bitwiseAND(F.lit(FILTER_BITS - 1))
    words = nodes.select(place.alias("k")).groupBy(F.shiftright("k", 6).alias("word"))
    words = words.agg(F.bit_or(F.expr("shiftleft(1L, CAST(k & 63 AS INT))")).alias("bits")).toArrow()
    out = np.zeros(FILTER_BITS // 64, "<i8")
    out[words["word"].to_numpy()] = words["bits"].to_numpy()
    return out.tobytes()


def _answers(asked: DataFrame, ranked: DataFrame) -> DataFrame:
    """For each group and bound w asked for: how many of its nodes have a first run up to w, the place of the longest one's parent in the parent's group, and all its nodes."""
    keys = ranked.select(*_GROUP, F.col("first").alias("w"), F.lit(0).alias("kind"), "up")
    both = keys.unionByName(asked.select(*_GROUP, "w").distinct().withColumns({"kind": F.lit(1), "up": F.lit(None).cast("int")}))
    so_far = Window.partitionBy(*_GROUP).orderBy("w", "kind").rowsBetween(Window.unboundedPreceding, 0)
    one = F.when(F.col("kind") == 0, 1).otherwise(0)
    both = both.withColumns({"fit": F.sum(one).over(so_far), "up": F.last("up", ignorenulls=True).over(so_far), "all": F.sum(one).over(Window.partitionBy(*_GROUP))})
    return both.filter("kind = 1 AND all > 0").drop("kind")


def _build(coded: DataFrame, nodes: DataFrame) -> dict[str, int]:
    """Hops and predecessor queries of the links of both automata."""
    rank = F.row_number().over(Window.partitionBy(*_GROUP).orderBy("first"))
    ranks = stored(nodes.withColumn("rank", rank), "space-ranks")
    parents = ranks.select("sym", (F.col("d") + 1).alias("d"), F.col("q1").alias("pq1"), F.col("q2").alias("pq2"), "first", F.col("rank").alias("up"))
    ranked = ranks.join(parents, ["sym", "d", "pq1", "pq2", "first"], "left")
    owns = nodes.groupBy(F.col("owner").alias("p")).agg(F.min("d").alias("own"))
    shared = coded.sparkSession.sparkContext.broadcast(_bitmap(nodes))
    asked = stored(coded.join(owns, "p").mapInArrow(_asked_rows(shared), _long(_ASKED)), "space-asked")
    met = asked.join(_answers(asked, ranked), [*_GROUP, "w"])
    # a group stands for the node itself (of one run: for nothing), and for the parent of the node below (if a node of it fits)
    node = F.struct(F.col("at").alias("at"), F.lit(True).alias("here"))
    below = F.struct((F.col("at") + 1).alias("at"), F.lit(False).alias("here"))
    roles = F.filter(F.array(F.when((F.col("here") == 1) & (F.col("d") > 1), node), F.when((F.col("below") == 1) & (F.col("fit") > 0), below)), lambda x: x.isNotNull())
    last = (F.col("i") == 1) & (F.col("fit") + 1 == F.col("all"))
    places = met.select("p", "i", "fit", "up", last.alias("last"), F.explode(roles).alias("role"))
    places = places.select("p", "role.at", F.struct("i", "role.here", "fit", "up", "last").alias("x"))
    per = places.groupBy("p", "at").agg(F.collect_list("x").alias("x"))
    ends = F.filter("x", lambda x: x["here"])
    above = F.filter("x", lambda x: ~x["here"])
    per = per.select(F.exists("x", lambda x: x["here"] & x["last"]).alias("last"), ends.alias("ends"), above.alias("above"))
    first = lambda xs, least: F.array_min(F.filter(F.transform(F.filter(xs, lambda x: (x["fit"] > 0) & (x["i"] >= least)), lambda x: F.struct(x["i"], x["up"])), lambda x: x.isNotNull()))
    per = per.withColumns({"one": first(F.col("ends"), 1), "two": first(F.col("ends"), 2)})
    upto = lambda xs, found: F.filter(xs, lambda x: found.isNull() | (x["i"] <= found))
    one, two = F.col("one")["i"], F.col("two")["i"]
    chain = F.filter("above", lambda x: x["i"] > 1)
    simple_hops = F.aggregate(upto(F.col("above"), one), F.lit(0).cast("long"), lambda s, x: s + x["fit"]) + 1 - F.coalesce(F.col("one")["up"], F.lit(0))
    grouped_hops = F.size(upto(chain, two)) + two.isNull().cast("int")
    slots = F.filter("ends", lambda x: x["i"] > 1)
    tried = F.size(F.array_intersect(F.transform(upto(slots, two), lambda x: x["i"]), F.transform(chain, lambda x: x["i"])))
    grouped_pred = tried + two.isNull().cast("int")
    sums = {"simple_hops": simple_hops, "simple_pred": one.isNull().cast("int"), "grouped_hops": F.when(F.col("last"), grouped_hops), "grouped_pred": F.when(F.col("last"), grouped_pred)}
    return per.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(k) for k, c in sums.items()]).first().asDict()


def _index(coded: DataFrame) -> dict[str, int]:
    """The compact trie of the reversed patterns without their last runs. Strings part at ends of whole runs only: where another symbol follows, or a longer run of the same."""
    key = ["e", "h1", "h2", "ph1", "ph2", "sym", "len"]
    rows = stored(coded.mapInArrow(_reversed_rows, _long(_REVERSED)).groupBy(*key, "last").agg(F.count(F.lit(1)).alias("n")), "space-reversed")
    nodes = rows.groupBy(*key).agg(F.count("last").alias("ends"))
    siblings = nodes.groupBy("e", "ph1", "ph2", "sym").agg(F.max("len").alias("longest"))
    follows = siblings.groupBy((F.col("e") - 1).alias("e"), F.col("ph1").alias("h1"), F.col("ph2").alias("h2")).agg(F.count(F.lit(1)).alias("follows"))
    nodes = nodes.join(siblings, ["e", "ph1", "ph2", "sym"]).join(follows, ["e", "h1", "h2"], "left")
    ways = F.coalesce("follows", F.lit(0)) + (F.col("longest") > F.col("len")).cast("int")
    found = nodes.agg(F.count_if((F.col("ends") > 0) | (ways > 1)).alias("nodes"), F.coalesce(F.sum("ends"), F.lit(0)).alias("colours"), F.count_if(F.col("ends") > 0).alias("heads")).first()
    return found.asDict()


def by_joins(patterns: DataFrame) -> dict[str, int]:
    """cost.space's figures for any number of patterns (runs)."""
    runs = F.aggregate("runs", F.lit(0).cast("long"), lambda s, r: s + r["len"])
    total = lambda c: F.coalesce(F.sum(c), F.lit(0))
    sizes = patterns.agg(F.count(F.lit(1)).alias("k"), total(runs).alias("m"), total(F.size("runs")).alias("m_runs"), F.count_if(F.size("runs") > 1).alias("multi"), F.count_if(F.size("runs") < 1).alias("empty")).first()
    if sizes["empty"]:
        raise ValueError("an empty pattern occurs everywhere")
    sigma = patterns.select(F.explode("runs.sym").alias("sym")).distinct().count()
    coded = stored(_coded(patterns), "space-patterns")
    nodes = coded.mapInArrow(_node_rows, _long(_NODE)).groupBy(*_GROUP, "first").agg(F.min("p").alias("owner"), F.min("pq1").alias("pq1"), F.min("pq2").alias("pq2"))
    nodes = stored(nodes, "space-nodes")
    groups = nodes.groupBy(*_GROUP).agg(F.count(F.lit(1)).alias("n")).count()
    n, roots = nodes.agg(F.count(F.lit(1)), F.count_if(F.col("d") == 1)).first()
    index, build = _index(coded), _build(coded, nodes)
    build["simple_pred"] += roots
    build["grouped_pred"] += n - index["heads"]  # looks for the report indexes of nodes that are no pattern's own
    held = {"nodes": n + 1, "edges": n, "groups": groups + 1, "step_entries": n - roots, "root_entries": roots}
    held |= {"index_nodes": index["nodes"] + 1, "index_colours": index["colours"], "index_list_entries": sizes["multi"], "index_strings": sizes["multi"]}
    return held | {f"build_{k}": v for k, v in (build | {k: sizes[k] for k in ("k", "m", "m_runs")} | {"sigma": sigma}).items()}

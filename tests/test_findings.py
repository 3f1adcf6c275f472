"""Findings of reviews: queries on tables with many copies, and on tables larger than a broadcast."""

import os
import random
from collections import Counter

import pyarrow as pa
from pyspark.sql import functions as F

from runloom.functions import encode
from runloom.operators import cost, links, match, space, tries, truncated
from runloom.operators.automaton import grouped
from runloom.plans import dictionaries as D
from runloom.plans import workloads
from runloom.sources import readers
from runloom.sources.readers import dictionary
from runloom.types import runs_of


def events_of(spark, path, users):
    """A folder with an events table: a list of event types for each user."""
    rows = [(k * 100 + n, 1_700_000_000 + n, k, kind) for k, kinds in enumerate(users) for n, kind in enumerate(kinds)]
    df = spark.createDataFrame(rows, "event_id long, s long, user_id long, event_type string")
    df.select("event_id", F.timestamp_seconds("s").alias("ts"), "user_id", "event_type").write.parquet(f"{path}/events.parquet")
    return str(path)


def test_truncated_joins_equal_the_definition(spark):
    draw = random.Random(3)
    patterns = [(k, runs_of("".join(draw.choice("ab") * draw.randrange(1, 3) for _ in range(draw.randrange(1, 6))))) for k in range(60)]
    want = sorted((i, j) for i, a in patterns for j, b in patterns if truncated.truncate_matches(b, a))
    assert sorted(map(tuple, truncated.pairs(dictionary(spark, patterns)).collect())) == want and len(want) > 200
    asked = [(i, s, w) for i, r in patterns for s in "ab" for w in (1, 3) if len(r) < 2 or r[-2].sym != s]
    want = sorted((i, s, w, j) for i, s, w in asked for j, b in patterns if truncated.truncate_matches(b, (*patterns[i][1][:-1], (s, w))))
    assert sorted(map(tuple, truncated.query_by_join(dictionary(spark, patterns), spark.createDataFrame(asked, "i long, sym string, w long")).collect())) == want


def test_copies_are_not_paired_one_by_one(spark, tmp_path):
    a, b = ["view", "click", "view", "click", "error"], ["view", "click", "view", "click", "error", "error"]
    found = [tuple(r) for r in workloads.truncated_query_usr(spark, events_of(spark, tmp_path, [a] * 30 + [b] * 30)).collect()]
    members, pairs = sorted((i, j) for i, s, _, j in found if s is None), sorted(r for r in found if r[1] is not None)
    assert members == [(k, 0 if k < 30 else 30) for k in range(60)]
    assert pairs == sorted((i, "e", w, j) for i in (0, 30) for j, n in ((0, 1), (30, 2)) for w in (1, 2) if n <= w)


def test_compare_of_neighbours_broadcasts_no_runs(spark, small):
    assert "Broadcast" not in workloads.rle_compare(spark, small)._jdf.queryExecution().executedPlan().toString()


def test_lcp_of_neighbours_broadcasts_no_runs(spark, small):
    assert "Broadcast" not in workloads.rle_lcp(spark, small)._jdf.queryExecution().executedPlan().toString()


def test_neighbours_are_joined_as_names_and_not_as_runs(spark, small):
    for query in (workloads.rle_lcp, workloads.rle_compare):
        plan = query(spark, small)._jdf.queryExecution().executedPlan().toString()
        assert plan.count("MapInArrow") == 1 and plan.index("MapInArrow") < plan.index("SortMergeJoin")


def test_neighbours_of_odd_names(spark, tmp_path):
    names = ["aab", "aabb", "", "é😀😀", "é😀", None, "x", "x", "y"]
    keys = [0, 1, 2, 3, 4, 5, 7, 8, 9]
    rows = list(zip(keys, names))
    spark.createDataFrame(rows, "c_custkey long, c_name string").write.parquet(f"{tmp_path}/customer.parquet")
    pairs = [(i, a, b) for i, a in rows for j, b in rows if j == i + 1]
    want = [(i, None if a is None or b is None else len(os.path.commonprefix([a, b]))) for i, a, b in pairs]
    assert sorted(map(tuple, workloads.rle_lcp(spark, str(tmp_path)).collect())) == want and len(want) == 7
    sides = [(i, 0 if a is None or b is None else (a > b) - (a < b)) for i, a, b in pairs]
    assert sorted(map(tuple, workloads.rle_compare(spark, str(tmp_path)).collect())) == sides


def test_several_columns_are_encoded_as_one_is(monkeypatch):
    texts = [("aab", "b"), (None, ""), ("", None), ("x" * 9, "xyy"), ("é😀😀", "é")]
    batch = pa.RecordBatch.from_pydict({"k": pa.array(range(5)), "a": pa.array([a for a, _ in texts]), "b": pa.array([b for _, b in texts])})
    want = [(k, *(None if t is None else [tuple(r) for r in runs_of(t)] for t in pair)) for k, pair in enumerate(texts)]
    for piece in (1, 7, 1 << 20):
        monkeypatch.setattr(encode, "PIECE", piece)
        found = [row for out in encode._texts_borders(iter([batch])) for row in out.to_pylist()]
        assert [(r["k"], *(None if r[c] is None else [(x["sym"], x["len"]) for x in r[c]] for c in "ab")) for r in found] == want


def test_histogram_has_a_row_a_length_over_many_partitions(spark, tmp_path):
    path = events_of(spark, tmp_path, [["view"] * (k % 4 + 1) + ["click"] for k in range(60)])
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        found = [tuple(r) for r in workloads.histogram_of_runs(spark, path).collect()]
    finally:
        spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "true")
    assert len(found) == 4 and Counter(dict(found)) == Counter({1: 75, 2: 15, 3: 15, 4: 15})


#: node, simple link, group link, report index of the worked example.
SIX_LINKS = [("", "", "", -1), ("a3", "", "", -1), ("a5", "a3", "", 1), ("b2", "", "", 5), ("a3b3", "b2", "b2", 4), ("a5b1", "", "", -1), ("a5b3", "a3b3", "b2", 2), ("b2a1", "", "", -1), ("a3b3a1", "b2a1", "b2a1", -1), ("a5b3a1", "a3b3a1", "b2a1", -1), ("a5b3a2", "", "", -1)]
#: Runs 2 to 5: v2 c1 v1 e1 (users 0 and 2), v1 c1 v1 e2 (user 1); user 3 has too few.
USERS = [["click", "view", "view", "click", "view", "error"], ["click", "view", "click", "view", "error", "error"], ["error", "view", "view", "click", "view", "error", "view"], ["view", "click"]]
USERS_LINKS = [("", "", "", -1), ("v1", "", "", -1), ("v1c1", "", "", -1), ("v1c1v1", "v1", "v1", 1), ("v1c1v1e2", "", "", -1), ("v2", "v1", "", -1), ("v2c1", "v1c1", "", -1), ("v2c1v1", "v1c1v1", "v1", 0), ("v2c1v1e1", "", "", -1)]


def test_links_by_joins_are_those_of_the_table(spark, tmp_path):
    assert sorted(map(tuple, links.links(dictionary(spark, D.SIX)).collect())) == sorted(SIX_LINKS)
    assert sorted(map(tuple, workloads.automaton_links_by_joins(spark, events_of(spark, tmp_path, USERS)).collect())) == sorted(USERS_LINKS)


def test_links_of_the_automata_are_those_of_the_table(spark, tmp_path):
    assert sorted(map(tuple, cost.links(spark, D.SIX).collect())) == sorted(SIX_LINKS)
    assert sorted(map(tuple, workloads.automaton_links_six(spark, events_of(spark, tmp_path, USERS)).collect())) == sorted(USERS_LINKS)


def test_counters_of_both_variants_over_a_table(spark, tmp_path):
    text = spark.createDataFrame([(0, [("a", 30), ("c", 1)] * 10)], "seq_id long, runs array<struct<sym:string,len:bigint>>")
    assert sorted(map(tuple, cost.adversary(text, 30).collect())) == [(30, "grouped", 20, 10, 10, 0), (30, "simple", 20, 10, 300, 0)]
    path = events_of(spark, tmp_path, [["view"] * 4 + ["signup"], ["view", "click", "error", "signup", "view"]])
    assert sorted(map(tuple, workloads.counters_simple_vs_grouped(spark, path).collect())) == [(30, "grouped", 6, 4, 2, 2), (30, "simple", 6, 4, 6, 2)]


def test_families_of_the_run_lengths_of_a_table(spark, tmp_path):
    text = spark.createDataFrame([(0, [("a", 10)]), (1, [("b", 9)])], "seq_id long, runs array<struct<sym:string,len:bigint>>")
    assert [tuple(r) for r in cost.family(text, "a").collect()] == [(10, 8, 2, 12)]
    path = events_of(spark, tmp_path, [["view"] * 4 + ["click"] + ["view"] * 3, ["view"] * 2 + ["click"] * 5, ["view"]])
    assert sorted(map(tuple, workloads.family_output_links(spark, path).collect())) == [(3, 1, 2, 16), (4, 2, 2, 13)]
    assert workloads.family_output_links(spark, events_of(spark, tmp_path / "none", [["view"]])).count() == 0


def test_theta_pairs_and_members_of_a_table(spark, tmp_path):
    fixed = [(i, j) for i, a in D.EVENTS for j, b in D.EVENTS if truncated.truncate_matches(tuple(b), tuple(a))]
    assert sorted(map(tuple, truncated.pairs(dictionary(spark, D.EVENTS)).collect())) == fixed
    found = sorted(map(tuple, workloads.join_theta_lengths(spark, events_of(spark, tmp_path, USERS * 20)).collect()))
    assert [r[:2] for r in found if r[2]] == [(0, 0), (1, 1)]
    assert [r[:2] for r in found if not r[2]] == sorted((4 * k + u, u % 2) for k in range(20) for u in range(3))


def test_the_worked_example_is_matched_in_a_table(spark, tmp_path):
    text = spark.createDataFrame([(0, D.EXAMPLE)], "seq_id long, text string")
    assert sorted(tuple(r) for r in match.full(text, D.SIX).select("pattern_id", "start").collect()) == [(4, 1), (5, 5), (6, 4), (6, 5)]
    kinds = {"a": ["view", "click", "purchase"], "b": ["error"], "c": ["signup"]}
    path = events_of(spark, tmp_path, [[kinds[c][k % len(kinds[c])] for k, c in enumerate(D.EXAMPLE)], ["error", "error"]])
    assert sorted(map(tuple, workloads.six_on_example(spark, path).collect())) == [(0, 4, 1), (0, 5, 5), (0, 6, 4), (0, 6, 5), (1, 6, 0)]


def test_formats_are_written_and_read_for_a_table(spark, tmp_path):
    rows = spark.createDataFrame([(1, "4a3b"), (2, '[["a",4],["b",3]]')], "id long, s string")
    read = rows.select(F.when(F.col("id") == 1, readers.parse_rle(F.col("s"))).otherwise(readers.parse_rle(F.col("s"), "json")).alias("r")).collect()
    assert [[tuple(x) for x in r["r"]] for r in read] == [[("a", 4), ("b", 3)]] * 2
    found = workloads.parse_rle_formats(spark, events_of(spark, tmp_path, [["view"] * 12 + ["click"], ["error"]])).collect()
    assert sorted(map(tuple, found)) == [(0, "compact", "v" * 12 + "c", 2), (0, "json", "v" * 12 + "c", 2), (1, "compact", "e", 1), (1, "json", "e", 1)]


def test_rle_files_hold_a_table(spark, tmp_path):
    found = workloads.rle_file_source(spark, events_of(spark, tmp_path, [["view"] * 12 + ["click"], ["error"]] * 9)).collect()
    assert sorted(map(tuple, found)) == [(k, "e" if k % 2 else "v" * 12 + "c") for k in range(18)]


def test_recursive_prefixes_of_a_table(spark, tmp_path):
    found = sorted(map(tuple, workloads.sql_recursive_prefixes(spark, events_of(spark, tmp_path, USERS)).collect()))
    chains = (["v1", "v1c1", "v1c1v1", "v1c1v1e2"], ["v2", "v2c1", "v2c1v1", "v2c1v1e1"])
    assert found == sorted((c[i], c[j]) for c in chains for i in range(4) for j in range(i + 1))
    assert len(links.trie_parents(dictionary(spark, D.SIX)).collect()) == 10


#: Nodes and groups of run tries.
TRIE_SIZES = {"EVENTS": (16, 14), "LINE_STATUS": (15, 12), "QUANTITY": (11, 9), "ORDER_STATUS": (13, 11), "SIX": (11, 8), "MORPHEMES": (20, 19)}


def test_trie_stats_of_tables_equal_the_tries(spark, small):
    for name, sizes in TRIE_SIZES.items():
        nodes = tries.run_trie_nodes(dictionary(spark, getattr(D, name)).filter("m_runs > 1"))
        assert (nodes.count() + 1, nodes.select("group_key").distinct().count() + 1) == sizes
    want = {}
    for name, patterns in workloads.table_dictionaries(spark, small).items():
        a = grouped(match.pattern_list(patterns))
        want[name] = (len(a.trie.parent), len(a.members))
    assert {r["dictionary"]: (r["nodes"], r["groups"]) for r in workloads.run_trie_stats(spark, small).collect()} == want and len(want) == 4


def test_space_follows_the_runs_of_the_tables_patterns(spark, small):
    found = {(r["dictionary"], r["structure"]): r for r in workloads.space_by_dictionary(spark, small).collect()}
    assert {d for d, _ in found} == {"events", "orders", "parts"}
    for name, patterns in workloads.table_dictionaries(spark, small).items():
        if name == "customers":  # one pattern each: not for a driver
            continue
        runs = patterns.agg(F.sum(F.size("runs"))).first()[0]
        assert {r["m_runs"] for (d, _), r in found.items() if d == name} == {runs} and found[name, "build_k"]["words"] == patterns.count()
        assert found[name, "nodes"]["words"] <= runs + 1


def test_space_by_joins_is_that_of_the_automata(spark, monkeypatch):
    draw = random.Random(8)
    text = lambda most: "".join(draw.choice("abc") * draw.randrange(1, 4) for _ in range(draw.randrange(1, most)))
    shorter = [(k, runs_of("a" * draw.randrange(1, 30) + "b" * draw.randrange(1, 3) + "a" * draw.randrange(9))) for k in range(99)]
    for patterns in (D.SIX, D.adversary(9), [(k, runs_of(text(8))) for k in range(150)], shorter, [(1, runs_of("aa"))], []):
        want = {r["structure"]: r["words"] for r in cost.space(spark, {"x": patterns}).collect()}
        assert space.by_joins(dictionary(spark, patterns)) == want and len(want) == 17
        monkeypatch.setattr(space, "FILTER_BITS", 64)  # a bitmap that is full costs rows and no result


def test_space_is_told_of_whole_tables(spark, small, monkeypatch):
    found = sorted(map(tuple, workloads.space_by_dictionary(spark, small).collect()))
    whole = {"events": ("user_id", "ts, event_id, event_type", "event_type"), "orders": ("o_custkey", "o_orderdate, o_orderkey, o_orderstatus", "o_orderstatus")}
    want = {"customers": {runs_of(r["c_name"]) for r in readers.read(spark, small, "customer").collect()}}
    for table, (key, order, kind) in whole.items():
        rows = readers.read(spark, small, table).orderBy(key, *order.split(", ")).collect()
        want[f"{table[:-1]}_sequences"] = {runs_of([r[kind] for r in rows if r[key] == k]) for k in {r[key] for r in rows}}
    words = {(d, s): w for d, s, w, _ in found}
    for name, patterns in want.items():
        assert (words[name, "build_k"], words[name, "build_m_runs"], words[name, "build_m"]) == (len(patterns), sum(map(len, patterns)), sum(r.len for p in patterns for r in p))
    monkeypatch.setattr(cost, "DRIVER_RUNS", 0)
    assert sorted(map(tuple, workloads.space_by_dictionary(spark, small).collect())) == found

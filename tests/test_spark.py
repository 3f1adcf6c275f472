"""Plans on the given tables against DuckDB, counts known beforehand, and odd inputs."""

import math

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from runloom.functions import encode, rle
from runloom.operators import alphabet, cost, intervals, links, match
from runloom.plans import dictionaries as D
from runloom.plans import artefact, strategies, workloads
from runloom.sources import readers, rle_source
from runloom.sources.readers import dictionary
from runloom.streaming import match_stream
from runloom.streaming.match_stream import EagerMatcher
from runloom.types import Run, runs_of

NAMES = [n for n in workloads.ORACLE_SQL if n in workloads.QUERIES]


@pytest.fixture(scope="session")
def duck(small):
    c = duckdb.connect()
    c.execute("set timezone='UTC'")
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        c.execute(f"create view {t} as select * from '{small}/{t}.parquet'")
    return c


def shown(v):
    if v is None or isinstance(v, float) and math.isnan(v):
        return "null"
    return f"{v:.9g}" if isinstance(v, float) else str(v).lower() if isinstance(v, bool) else str(v)


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_oracle(spark, small, duck, name):
    df = workloads.QUERIES[name](spark, small)
    found = duck.execute(workloads.ORACLE_SQL[name])
    columns = [c[0] for c in found.description]
    assert sorted(columns) == sorted(df.columns)
    want = sorted(tuple(shown(x[columns.index(c)]) for c in sorted(columns)) for x in found.fetchall())
    assert sorted(tuple(shown(r[c]) for c in sorted(columns)) for r in df.collect()) == want


@pytest.mark.parametrize("name, total", [("match_events_by_user", 86), ("match_events_global", 100), ("match_linestatus_by_supplier", 1067), ("match_linestatus_global", 1098), ("match_quantity_runs", 509), ("match_orderstatus", 351), ("match_quality", 78), ("match_signs", 9750), ("match_names", 1345), ("match_benchmark", 3)])
def test_known_totals(spark, small, name, total):
    assert workloads.QUERIES[name](spark, small).count() == total


def test_entry(spark):
    assert entry.entry(spark).count() == 86


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_odd_texts(spark):
    data = [(1, None), (2, ""), (3, "aa\naa"), (4, "aa" * 4000), (5, "\U0001f600\U0001f600a"), (3, "aa\naa")]
    text = spark.createDataFrame(data, "seq_id long, text string")
    patterns = [(1, "a\na"), (2, "aaa"), (3, "\U0001f600a"), (4, "\U0001f600\U0001f600")]
    want = sorted((k, p, i) for k, t in data if t for p, s in patterns for i in range(len(t) - len(s) + 1) if t.startswith(s, i))
    assert rows(match.full(text, patterns).select("seq_id", "pattern_id", "start")) == want
    counts = match.full(text, patterns, emit="counts").groupBy("seq_id", "pattern_id").sum("occ")
    assert sum(r[2] for r in counts.collect()) == len(want)
    runs = encode.rle_text(text, "seq_id", "text")
    assert rows(match.full(runs.filter("runs is not null"), patterns).select("seq_id", "pattern_id", "start")) == want
    assert match.full(text.limit(0), patterns).count() == 0 and match.full(text, []).count() == 0


def test_null_symbols_break_runs(spark):
    df = spark.createDataFrame([(1, k, s) for k, s in enumerate(["a", None, "a", "a", "b"])], "id long, pos long, s string")
    assert [r["len"] for r in encode.rle_rows(df, "id", ["pos"], "s").orderBy("run_no").collect()] == [1, 2, 1]
    arrays = spark.createDataFrame([(1, ["a", None, "a", "a"]), (2, None), (3, [])], "id long, v array<string>")
    got = {r["seq_id"]: [tuple(x) for x in r["runs"]] for r in encode.rle_array(arrays, "id", "v").collect()}
    assert got == {1: [("a", 1), ("a", 2)], 2: [], 3: []}
    dropped = encode.rle_array(arrays, "id", "v", "drop").filter("seq_id = 1").first()
    assert [tuple(x) for x in dropped["runs"]] == [("a", 3)]


def test_chunks_with_halo_equal_whole_sequences(spark, small):
    source = workloads.linestatus(spark, small)
    whole = rows(match.full(source, D.LINE_STATUS))
    for size in (3, 7, 64):
        cut = match.chunks(encode.explode_runs(source), 4, size)
        assert rows(match.full(cut, D.LINE_STATUS)) == whole


def test_global_encoding_over_many_partitions(spark):
    text = "aaabbbbbbbbbbbbbbbbbbbbbcaab" * 3 + "bbb"
    df = spark.createDataFrame(list(enumerate(text)), "k long, s string").repartition(5)
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    spark.conf.set("spark.sql.shuffle.partitions", "13")
    try:
        got = [(r["sym"], r["len"], r["start"]) for r in encode.rle_global(df, ["k"], "s").orderBy("run_no").collect()]
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
        spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "true")
    want, at = [], 0
    for s, n in runs_of(text):
        want.append((s, n, at))
        at += n
    assert got == want


def test_alphabet_reduction_keeps_answers(spark):
    text = spark.createDataFrame([(1, list("xxayybaz")), (2, list("qq"))], "seq_id long, v array<string>")
    runs = encode.rle_array(text, "seq_id", "v")
    patterns = [(1, "ab"), (2, "aw"), (3, "ba"), (4, "a")]
    reduced, own = alphabet.reduce(dictionary(spark, patterns), runs)
    assert all(a["sym"] != b["sym"] for r in reduced.collect() for a, b in zip(r["runs"], r["runs"][1:]))
    assert {r["pattern_id"] for r in own.collect()} == {1, 3, 4}
    assert rows(match.deterministic(runs, patterns)) == rows(match.full(runs, patterns))


def test_longest_only_misses_answers(spark, small):
    all_hits, few = workloads.match_events_by_user(spark, small), workloads.baseline_longest_only(spark, small)
    assert few.exceptAll(all_hits).count() == 0 and few.count() < all_hits.count()


def test_a_stream_goes_on_after_a_stop(spark, tmp_path):
    """Two runs over one checkpoint: matchers and rows that wait are kept, also across a change of the dictionary."""
    symbols = ["view", "view", "click", "purchase", "error", "error", "view", "click", "purchase", "view", "view", "click"]
    rows = [(k % 2, k, f"2024-01-01 00:{k:02d}:00", symbols[k // 2 % 12]) for k in range(48)]
    table = spark.createDataFrame(rows, "user_id long, event_id long, at string, event_type string").withColumn("ts", F.to_timestamp("at")).drop("at")
    closing = spark.createDataFrame([(-1, -1, "2025-01-01 00:00:00", "end")], "user_id long, event_id long, at string, event_type string").withColumn("ts", F.to_timestamp("at")).drop("at")
    source, out, state = (str(tmp_path / x) for x in ("in", "out", "state"))
    schema = "user_id long, event_id long, event_type string, ts timestamp"

    def run(patterns):
        return match_stream.match_available(source, spark, schema, patterns, "user_id", "ts", "event_id", "event_type", out, state, "10 minutes")

    table.filter("event_id < 21").coalesce(1).write.parquet(f"{source}/a")
    first = run(D.EVENTS).count()
    table.filter("event_id >= 21").unionByName(closing).coalesce(1).write.parquet(f"{source}/b")
    found = {(r["seq_id"], r["pattern_id"], r["start"]) for r in run(D.EVENTS).collect()}
    whole = match.full(encode.sequences(table, "user_id", ["ts", "event_id"], "event_type"), D.EVENTS)
    assert found == {(r["seq_id"], r["pattern_id"], r["start"]) for r in whole.collect()} and 0 < first < len(found)
    assert artefact.version_of(D.EVENTS) == artefact.version_of(list(D.EVENTS)) != artefact.version_of(D.EVENTS[:2])


def test_lines_keep_their_own_ids_and_digits_are_refused(spark, tmp_path):
    (tmp_path / "t.txt").write_text("aab\naab\nb\n")
    assert readers.read_text(spark, str(tmp_path)).select("seq_id").distinct().count() == 3
    for bad in ("134", "4a3", "a"):
        with pytest.raises(Exception, match="no compact runs"):
            spark.createDataFrame([(bad,)], "s string").select(readers.parse_rle(F.col("s"))).collect()
    (tmp_path / "t.txt").write_text("7\t4a3b\n")
    assert [(r["seq_id"], [tuple(x) for x in r["runs"]]) for r in rle_source.read_lines(spark, str(tmp_path)).collect()] == [(7, [("a", 4), ("b", 3)])]


def test_one_run_with_more_starts_than_a_batch(spark, monkeypatch):
    monkeypatch.setattr(match, "EMIT", 7)
    rows = spark.createDataFrame([(1, [("a", 50), ("b", 1), ("a", 9)])], "seq_id long, runs array<struct<sym:string,len:bigint>>")
    found = match.full(rows, [(1, "aaa"), (2, "ab"), (3, "a" * 9)])
    assert sorted((r["pattern_id"], r["start"], r["end_run"]) for r in found.collect()) == sorted([(1, k, 1) for k in range(48)] + [(1, 51 + k, 3) for k in range(7)] + [(2, 49, 2)] + [(3, k, 1) for k in range(42)] + [(3, 51, 3)])


def test_large_alphabets_are_joined(spark, monkeypatch):
    patterns = dictionary(spark, [(1, ("x", "x", "y")), (2, ("z",)), (3, ("y", "x"))])
    text = spark.createDataFrame([(1, [("x", 2), ("q", 1), ("p", 1), ("y", 3)]), (1, [("y", 1)]), (2, []), (3, None)], "seq_id long, runs array<struct<sym:string,len:bigint>>")
    both = []
    for most in (alphabet.MOST, 0):
        monkeypatch.setattr(alphabet, "MOST", most)
        t, p = alphabet.reduce(patterns, text)
        both.append([sorted((r[0], tuple((x["sym"], x["len"]) for x in r["runs"] or ())) for r in df.select(c, "runs").collect()) for df, c in ((t, "seq_id"), (p, "pattern_id"))])
    assert both[0] == both[1] and both[0][0][0] == (1, ((1, 2), (0, 2), (2, 3)))


def test_hot_keys_are_encoded_over_many_tasks(spark):
    """One key with most rows, keys of one row, null keys and null symbols, runs over every border."""
    import random

    draw, rows = random.Random(4), []
    for k in range(3000):
        rows.append((draw.choice([7, 7, 7, 7, 1, 2, None, 1000 + k]), k, draw.choice(["a", "a", "a", "a", "b", None])))
    rows += [(7, 5000 + k, "z") for k in range(3000)]
    df = spark.createDataFrame(rows, "user_id long, ts long, kind string").repartition(6)
    want = encode.rle_rows(df, "user_id", ["ts"], "kind")
    spark.conf.set("spark.sql.shuffle.partitions", "16")
    try:
        got = encode.rle_rows_ranged(df, "user_id", ["ts"], "kind").select(want.columns)
        assert sorted(map(repr, map(tuple, got.collect()))) == sorted(map(repr, map(tuple, want.collect())))
        assert encode.rle_rows_ranged(df.limit(0), "user_id", ["ts"], "kind").count() == 0
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", "4")


def test_links_by_joins_equal_the_automaton_s(spark):
    import random

    draw = random.Random(11)
    patterns = [(k, "".join(draw.choice("ab") * draw.randrange(1, 4) for _ in range(draw.randrange(1, 6)))) for k in range(60)]
    shown = lambda df: {(r["node"], r["simple_link"], r["group_link"]) for r in df.collect()}
    found, want = links.links(dictionary(spark, patterns)), cost.links(spark, [(k, tuple(runs_of(p))) for k, p in patterns])
    assert shown(found) == shown(want) and found.count() == want.count() > 40
    # equal truncated strings: the smallest id; an index that is inherited is the one of the longest suffix
    assert {(r["node"], r["report_ix"]) for r in found.collect()} == {(r["node"], r["report_ix"]) for r in want.collect()}


def test_artefacts_hold_their_links(spark, tmp_path):
    for k, patterns in enumerate((D.SIX, [(1, "aa")], D.SIX[:3])):
        version = artefact.save(spark, patterns, str(tmp_path / f"a{k}"))
        assert version == artefact.version_of(patterns)
        assert sorted(match.pattern_list(artefact.load(spark, str(tmp_path / f"a{k}")))) == sorted(match.pattern_list(patterns))
    assert rows(artefact.load_links(spark, str(tmp_path / "a0"))) == rows(cost.links(spark, D.SIX))
    (tmp_path / "a2" / "links").rename(tmp_path / "gone")
    (tmp_path / "a0" / "links").rename(tmp_path / "a2" / "links")
    with pytest.raises(ValueError, match="versions"):
        artefact.load(spark, str(tmp_path / "a2"))


def test_leftmost_longest(spark, small):
    found = workloads.hits(spark, small, "events")
    want = []
    by_seq = {}
    for r in found.collect():
        by_seq.setdefault(r["seq_id"], []).append((r["start"], -r["end"], r["pattern_id"]))
    for seq, items in by_seq.items():
        reach = -1
        for s, e, p in sorted(items):
            if s >= reach:
                want.append((seq, p, s, -e))
                reach = -e
    assert rows(intervals.leftmost_longest(found)) == sorted(want)


def test_eager_matcher_equals_batch():
    from runloom.operators.automaton import grouped, occurrences

    text = "bbaabbbaaaabbaccb" * 2
    patterns = [(1, "ab"), (2, "aab"), (3, "bb"), (4, "abba"), (5, "b"), (6, "cc")]
    automaton = grouped(patterns)
    eager, out = EagerMatcher(automaton), []
    for c in text:
        eager = EagerMatcher(automaton, eager.state())  # as after a restart
        out += eager.push(c)
    assert sorted(out) == occurrences(automaton, runs_of(text))


def test_planner():
    assert strategies.choose(strategies.Stats(10, 100, 3, 50, 1000)) == "broadcast"
    assert strategies.choose(strategies.Stats(10**6, 10**7, 3, 50, 10**9)) == "grams"
    assert strategies.choose(strategies.Stats(10**6, 10**7, 30, 50, 10**9)) == "anchors"
    assert strategies.choose(strategies.Stats(10**7, 10**9, 30, 50, 10**6)) == "shards"


def test_plans_push_down_and_stay_map_only(spark, small):
    plan = workloads.scan_filter_pushdown(spark, small)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull" in plan and "l_quantity" not in plan
    matched = match.full(workloads.texts(spark, small, "documents", "doc_id", "text"), D.MORPHEMES)
    assert "Exchange" not in matched._jdf.queryExecution().executedPlan().toString()


def test_rle_columns(spark):
    df = spark.createDataFrame([(1, "aabbb", "bbc")], "id long, a string, b string").select(encode.text_runs("a").alias("a"), encode.text_runs("b").alias("b"))
    row = df.select(encode.decode(rle.concat("a", "b")).alias("joined"), rle.length("a").alias("n"), rle.max_run("a").alias("most"), rle.run_count("a").alias("runs"), encode.decode(rle.truncate("a")).alias("cut"), rle.contains("a", (Run("a", 1), Run("b", 2))).alias("has"), rle.contains("a", (Run("b", 4),)).alias("not")).first()
    assert tuple(row) == ("aabbbbbc", 5, 3, 2, "aa", True, False)

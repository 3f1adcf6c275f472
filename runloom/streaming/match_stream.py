"""Matching on streams: per sequence, the automaton's state and the open run are kept; every symbol may report.

When the open run reaches y symbols, the patterns that end there are those of last run y exactly (what the state reports up
to y, less what it reported up to y - 1) and one start of each single-run pattern of at most y symbols. Summed over a run
that is what the batch matcher reports for it, so answers come with the symbol that completes them.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from runloom.operators.automaton import Counters, Dictionary, GroupedAutomaton
from runloom.operators.match import pattern_list
from runloom.plans.artefact import version_of
from runloom.types import Run


class EagerMatcher:
    """One sequence. state(): (node, symbols read before the open run, open symbol, open length), small whatever was read."""

    def __init__(self, automaton: GroupedAutomaton, state: tuple | None = None) -> None:
        self.a = automaton
        self.node, self.before, self.sym, self.len = state or (0, 0, None, 0)

    def state(self) -> tuple:
        return self.node, self.before, self.sym, self.len

    def push(self, symbol) -> list[tuple[int, int]]:
        """(pattern, start) of the occurrences that this symbol completes."""
        a, d = self.a, self.a.dictionary
        if symbol != self.sym and self.len:
            self.node = a.step(self.node, Run(d.symbol.get(self.sym, -1), self.len), Counters())
            self.before, self.len = self.before + self.len, 0
        self.sym, self.len = symbol, self.len + 1
        code, y = d.symbol.get(symbol, -1), self.len
        end, out = self.before + y, []
        for x, name in d.lists.get(code, ()):
            if x > y:
                break
            out.append((name, end - x))
        if (i := a.report_ix[self.node]) is not None and code >= 0:
            out += [(name, end - d.length[name]) for name in a.index.query(i, code, y) if d.last_len[name] == y]
        return sorted(out)


def match_stream(events: DataFrame, patterns, key: str, ts: str, order: str, sym: str, delay: str = "0 seconds") -> DataFrame:
    """seq_id, pattern_id, start, ts (of the completing symbol) of a stream of symbols.

    Rows wait until the watermark (ts less delay) has passed them, so they are read in order of (ts, order) even when they arrive
    out of order; rows later than the watermark are dropped by Spark. State: the matcher's four values and the rows that wait.
    The dictionary's version is kept with it: a restart with another dictionary starts matchers anew, and rows that wait go on waiting.
    """
    spark = events.sparkSession
    automaton = GroupedAutomaton(Dictionary(pattern_list(patterns)))
    version = version_of(patterns)
    shared = spark.sparkContext.broadcast(automaton)
    kind = events.schema[key].dataType.simpleString()

    def step(group: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        kept = json.loads(state.get[0]) if state.exists else {"v": version, "m": None, "wait": []}
        if kept["v"] != version:
            kept |= {"v": version, "m": None}
        for frame in frames:
            kept["wait"] += [[int(t.value) // 1000, int(o), s] for t, o, s in zip(frame["ts"], frame["ord"], frame["sym"])]
        mark = state.getCurrentWatermarkMs() * 1000
        ready = sorted(x for x in kept["wait"] if x[0] <= mark)
        kept["wait"] = [x for x in kept["wait"] if x[0] > mark]
        matcher = EagerMatcher(shared.value, tuple(kept["m"]) if kept["m"] else None)
        found = [(group[0], name, start, t) for t, _, s in ready for name, start in matcher.push(s)]
        kept["m"] = list(matcher.state())
        state.update((json.dumps(kept),))
        if kept["wait"]:
            state.setTimeoutTimestamp(max(min(x[0] for x in kept["wait"]) // 1000 + 1, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"seq_id": [x[0] for x in found], "pattern_id": [x[1] for x in found], "start": [x[2] for x in found], "ts_us": [x[3] for x in found]})

    rows = events.select(F.col(key).alias("seq_id"), F.col(ts).cast("timestamp").alias("ts"), F.col(order).cast("long").alias("ord"), F.col(sym).alias("sym"))
    rows = rows.withWatermark("ts", delay)
    return rows.groupBy("seq_id").applyInPandasWithState(step, f"seq_id {kind}, pattern_id long, start long, ts_us long", "state string", "append", GroupStateTimeout.EventTimeTimeout)


def match_available(events_path: str, spark, schema: str, patterns, key: str, ts: str, order: str, sym: str, out: str, checkpoint: str, delay: str = "0 seconds") -> DataFrame:
    """All files now below events_path as a stream into Parquet. Rows wait for the watermark: the newest file should end with a closing row."""
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(events_path)
    matched = match_stream(stream, patterns, key, ts, order, sym, delay)
    query = matched.writeStream.format("parquet").option("path", out).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(matched.schema).parquet(out)


def hits_available(hits_path: str, spark: SparkSession, schema, out: str, checkpoint: str, plan) -> DataFrame:
    """A second stream over the hits that match_stream wrote (with ts, a timestamp): plan turns the streaming table into the one that is appended to out."""
    found = plan(spark.readStream.schema(schema).parquet(hits_path).withColumn("ts", F.timestamp_micros("ts_us")))
    query = found.writeStream.format("parquet").option("path", out).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(found.schema).parquet(out)


def windowed(hits: DataFrame, length: str, slide: str | None = None, delay: str = "0 seconds") -> DataFrame:
    """window, pattern_id, n of a stream of hits with ts: a window is appended when the watermark has passed its end."""
    return hits.withWatermark("ts", delay).groupBy(F.window("ts", length, slide or length), "pattern_id").agg(F.count(F.lit(1)).alias("n"))


def match_rows(events: DataFrame, patterns, key: str, order: list[str], sym: str) -> DataFrame:
    """The stream's logic on a bounded table: the eager matcher over each key's rows in order; memory is one key's state."""
    spark = events.sparkSession
    shared = spark.sparkContext.broadcast(GroupedAutomaton(Dictionary(pattern_list(patterns))))
    kind = events.schema[key].dataType.simpleString()
    rows = events.select(F.col(key).alias("seq_id"), *order, F.col(sym).alias("sym")).repartition("seq_id").sortWithinPartitions("seq_id", *order, "sym").select("seq_id", "sym")

    def walk(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        current, matcher = object(), None
        for frame in frames:
            found = []
            for seq, s in zip(frame["seq_id"], frame["sym"]):
                if seq != current:
                    current, matcher = seq, EagerMatcher(shared.value)
                found += [(seq, name, start) for name, start in matcher.push(s)]
            yield pd.DataFrame(found, columns=["seq_id", "pattern_id", "start"]).astype({"pattern_id": "int64", "start": "int64"})

    return rows.mapInPandas(walk, f"seq_id {kind}, pattern_id long, start long")

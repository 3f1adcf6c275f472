"""The SQL surface: a table function and Arrow functions over runs."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from runloom.operators.automaton import Dictionary, GroupedAutomaton
from runloom.operators.match import pattern_list
from runloom.types import Run


def register(spark: SparkSession, patterns, name: str = "dictionary_matches") -> None:
    """name(TABLE(SELECT seq_id, runs ...)) -> seq_id, pattern_id, start. The automaton travels with the function."""
    automaton = GroupedAutomaton(Dictionary(pattern_list(patterns)))

    class Matches:
        def eval(self, row):
            runs = automaton.encode([(r["sym"], r["len"]) for r in row["runs"] or ()])
            for pattern, start, _ in automaton.walk(runs):
                yield row["seq_id"], pattern, start

    spark.udtf.register(name, F.udtf(Matches, returnType="seq_id long, pattern_id long, start long"))


def contains_all(patterns):
    """An Arrow function: the runs hold every given pattern."""
    automaton = GroupedAutomaton(Dictionary(enumerate(patterns)))
    wanted = {k for k, _ in automaton.dictionary.patterns}

    @F.pandas_udf("boolean")
    def check(runs: pd.Series) -> pd.Series:
        return pd.Series([wanted <= {p for p, *_ in automaton.walk(automaton.encode([Run(x["sym"], x["len"]) for x in r]))} for r in runs], dtype=bool)

    return check


@F.pandas_udf("long")
def count_runs(us: pd.Series, order: pd.Series, sym: pd.Series) -> int:
    """Runs of a group's symbols in order of time, order, symbol."""
    rows = sorted(zip(us, order, sym))
    return sum(k == 0 or rows[k][2] != rows[k - 1][2] for k in range(len(rows)))

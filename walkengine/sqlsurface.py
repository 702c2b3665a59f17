"""SQL text for walks, and functions for Spark SQL.

``sql_walks`` reads  FROM x TO y OVER view MATCHING 'pattern' [CHEAPEST] [WITH MULTIPLICITY] [LIMIT n],  runs the search
(a table function can't start jobs, so the text is read here) and registers the result as a view.
"""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkengine.core.cheapest import cheapest_walks
from walkengine.core.search import minimal_walks
from walkengine.graph import views
from walkengine.lang.automata import compile_pattern

_TEXT = re.compile(
    r"\s*FROM\s+(?P<source>\S+)\s+TO\s+(?P<target>\S+)\s+OVER\s+(?P<view>\w+)\s+MATCHING\s+'(?P<pattern>[^']*)'"
    r"(?P<cheapest>\s+CHEAPEST)?(?P<runs>\s+WITH\s+MULTIPLICITY)?(?:\s+LIMIT\s+(?P<limit>\d+))?\s*",
    re.IGNORECASE,
)


def sql_walks(spark: SparkSession, sf_dir: str, text: str, name: str = "walks") -> DataFrame:
    """The walks that the text asks for, also as temporary view ``name``."""
    found = _TEXT.fullmatch(text)
    if not found or found["view"] not in views.VIEWS:
        raise ValueError(f"not understood: {text}")
    g = views.VIEWS[found["view"]](spark, sf_dir)
    number = g.edges.schema["src"].dataType.simpleString() == "bigint"
    source, target = (int(found[x]) if number else found[x] for x in ("source", "target"))
    runs = "words" if found["runs"] else ""
    walks = (cheapest_walks if found["cheapest"] else minimal_walks)(g, found["pattern"], source, target, multiplicity=runs)
    walks = walks.limit(int(found["limit"])) if found["limit"] else walks
    walks.createOrReplaceTempView(name)
    return walks


def register(spark: SparkSession) -> None:
    """nfa_accepts(pattern, labels): whether the word of labels matches; walk_text(edges): a walk as text;
    pattern_transitions(pattern): a table function with the moves of the compiled automaton."""

    @F.pandas_udf("boolean")
    def nfa_accepts(pattern: pd.Series, labels: pd.Series) -> pd.Series:
        known = {p: compile_pattern(p) for p in pattern.unique()}
        return pd.Series([known[p].accepts(list(w)) if w is not None else False for p, w in zip(pattern, labels)])

    class Transitions:
        def eval(self, pattern: str):
            nfa = compile_pattern(pattern)
            for p, a, q in sorted(nfa.moves):
                yield p, a, q, p in nfa.initial, q in nfa.final

    spark.udf.register("nfa_accepts", nfa_accepts)
    spark.udtf.register("pattern_transitions", F.udtf(Transitions, returnType="p int, label string, q int, starts boolean, ends boolean"))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION walk_text(edges ARRAY<STRING>) RETURNS STRING RETURN array_join(edges, '>')")

"""Accepting runs of finished walks: the automaton is run again over each walk."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkengine.graph.model import LabeledGraph
from walkengine.lang.automata import Nfa
from walkengine.lang.codegen import run_counts

_BIG = "decimal(38,0)"


def count_runs(walks: DataFrame, g: LabeledGraph, nfa: Nfa, by: str = "words") -> DataFrame:
    """edge_path and multiplicity of each walk (column edge_path, edge ids joined by >): its edges are looked up by one join
    and folded from the target back, with one count a state."""
    zero, one = F.lit(0).cast(_BIG), F.lit(1).cast(_BIG)
    steps = walks.select("edge_path", F.posexplode(F.split("edge_path", ">")).alias("at", "edge"))
    labels = g.masked(nfa.alphabet).select(F.col("edge_id").cast("string").alias("edge"), "lab")
    word = steps.join(labels, "edge").groupBy("edge_path").agg(F.array_sort(F.collect_list(F.struct((-F.col("at")).alias("back"), "lab"))).alias("word"))
    end = F.array(*(one if q in nfa.final else zero for q in range(nfa.n)))
    fold = F.aggregate("word", end, lambda counts, x: run_counts(counts, x["lab"], nfa, nfa.alphabet, by))
    total = zero
    for q in sorted(nfa.initial):
        total = (total + F.get(F.col("counts"), q)).cast(_BIG)
    return word.select("edge_path", fold.alias("counts")).select("edge_path", total.alias("multiplicity"))

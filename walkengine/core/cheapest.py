"""Cheapest matching walks: positive integer costs, all walks of the least total cost, each once.

Distances are kept for (vertex, state) and improved in rounds; only improved pairs go on, and none that is already as
dear as the target.  Links are made when distances are final, so a shorter way found late leaves no stale link: an edge
links a start at distance d to an end at distance d + cost.  From there on, cost takes the place of the level.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkengine.core.search import Layers, emit_all, pair
from walkengine.graph.model import LabeledGraph
from walkengine.lang.automata import Nfa, compile_pattern
from walkengine.session import Parts, bucketed, staged


def distances(g: LabeledGraph, nfa: Nfa, source, target) -> Layers:
    """Layers whose level is the least cost.  A round writes only the distances it improves."""
    spark, alphabet = g.edges.sparkSession, nfa.alphabet
    edges = bucketed(g.masked(alphabet).withColumn("cost", F.col("cost").cast("long")), "src", "edges")
    if not edges.where("cost IS NULL OR cost <= 0").isEmpty():
        raise ValueError("costs must be positive")
    bit = {a: 1 << i for i, a in enumerate(alphabet)}
    moves = F.broadcast(spark.createDataFrame([(p, bit[a], q) for p, a, q in nfa.moves], "p int, bit long, q int"))  # as large as the pattern
    kind = dict(pair(g, source, target).dtypes)["source"]
    parts = Parts(spark, "distances", "round")
    front = parts.add(spark.createDataFrame([(source, q, 0) for q in nfa.initial], f"vertex {kind}, state int, dist long"), 0)
    accepts = (F.col("vertex") == F.lit(target)) & F.col("state").isin([*nfa.final]) if nfa.final else F.lit(False)
    found, turn = None, 0
    while True:
        seen = front.agg(F.count("*").alias("n"), F.min(F.when(accepts, F.col("dist"))).alias("met")).first()
        found = min((x for x in (found, seen.met) if x is not None), default=None)
        if not seen.n:
            break
        turn += 1
        open_ = front.drop("round") if found is None else front.drop("round").where(F.col("dist") < found)
        offered = (
            open_.join(edges, open_.vertex == edges.src)
            .join(moves, (F.col("state") == F.col("p")) & (F.col("lab").bitwiseAND(F.col("bit")) != 0))
            .select(F.col("dst").alias("vertex"), F.col("q").alias("state"), (F.col("dist") + F.col("cost")).alias("offer"), F.lit(None).cast("long").alias("held"))
        )
        if found is not None:
            offered = offered.where(F.col("offer") <= found)
        before = parts.all().select("vertex", "state", F.lit(None).cast("long").alias("offer"), F.col("dist").alias("held"))
        least = offered.unionByName(before).groupBy("vertex", "state").agg(F.min("offer").alias("offer"), F.min("held").alias("held"))
        front = parts.add(least.where("offer IS NOT NULL AND (held IS NULL OR offer < held)").select("vertex", "state", F.col("offer").alias("dist")), turn)
    best = parts.all().groupBy("vertex", "state").agg(F.min("dist").alias("dist"))
    mask = F.bit_or(F.expr("shiftleft(1L, state)")).alias("mask")
    reach = staged(best.groupBy(F.lit(1).alias("run_id"), "vertex", F.col("dist").alias("level")).agg(mask), "reach")
    final = F.lit(nfa.mask(nfa.final)).cast("long")
    met = reach.where((F.col("vertex") == F.lit(target)) & (F.col("mask").bitwiseAND(final) != 0))
    least = met.groupBy("run_id", F.col("vertex").alias("target")).agg(F.min(F.struct("level", F.col("mask").bitwiseAND(final).alias("mask"))).alias("x"))
    return Layers(nfa, alphabet, edges, reach, staged(least.select("run_id", "target", "x.level", "x.mask"), "ends"), unit=False)


def cheapest_walks(g: LabeledGraph, pattern, source, target, *, multiplicity: str = "") -> DataFrame:
    """All cheapest matching walks: cost, length (edges), edge_path, vertex_path(, multiplicity)."""
    layers = distances(g, compile_pattern(pattern), source, target)
    walks = emit_all(layers, multiplicity=multiplicity)
    return walks.join(F.broadcast(layers.ends.select("run_id", F.col("level").alias("cost"))), "run_id").drop("run_id", "target")

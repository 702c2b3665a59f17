"""The answer DAG: equal subtrees of the answer tree are one node (level, vertex, states).

Per node the number of completions, per edge the interval of ranks below it in in-edge order: counting is one sweep, the
k-th answer a chain of interval look-ups, and pages, samples and parallel output need no cursor.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkengine.core.search import AnswerEdges, Layers, answer_edges, answer_links
from walkengine.session import Parts, staged

_BIG = "decimal(38,0)"


@dataclass(frozen=True)
class AnswerDag:
    """``nodes``: run_id, level, vertex, mask, n_walks.  ``edges``: run_id, level, vertex, mask (the node), edge_id, src,
    src_level, src_states (the child), cum_lo, cum_hi (ranks below the child).  ``roots``: run_id, target, level, mask."""

    nodes: DataFrame
    edges: DataFrame
    roots: DataFrame


KEY = ["run_id", "level", "vertex", "mask"]


def build(layers: Layers, answers: AnswerEdges | None = None) -> AnswerDag:
    """Counts upwards from level 0, a level a round; each round reads the level below alone and writes its own ranks
    (with costs for levels it reads all that is below, since an edge may skip levels)."""
    answers = answers or answer_edges(layers)
    spark, rows, unit = layers.edges.sparkSession, answers.rows, layers.unit
    roots = layers.ends
    leaves = rows.where("src_level = 0").select("run_id", F.col("src_level").alias("level"), F.col("src").alias("vertex"), F.col("src_states").alias("mask"))
    leaves = leaves.unionByName(roots.where("level = 0").select("run_id", "level", F.col("target").alias("vertex"), "mask")).distinct()
    leaves = staged(leaves.withColumn("n_walks", F.lit(1).cast(_BIG)), "dag-leaves")
    ranks = Parts(spark, "dag-ranks", "turn")
    counted = lambda e: e.groupBy(*KEY).agg(F.sum("below").cast(_BIG).alias("n_walks"))
    levels = range(1, answers.rounds + 1) if unit else sorted(r.level for r in rows.select("level").distinct().collect())  # distinct costs on answers
    last = leaves
    for level in levels:
        if unit:
            below = last
            e = rows.where(F.col("round") == answers.rounds - level + 1)
        else:
            below = leaves if ranks.schema is None else leaves.unionByName(counted(ranks.all()))
            e = rows.where(F.col("level") == level)
        child = below.select(F.col("run_id").alias("c_run"), F.col("level").alias("c_level"), F.col("vertex").alias("c_vertex"), F.col("mask").alias("c_mask"), F.col("n_walks").alias("below"))
        on = (F.col("run_id") == F.col("c_run")) & (F.col("src_level") == F.col("c_level")) & (F.col("src") == F.col("c_vertex")) & (F.col("src_states") == F.col("c_mask"))
        order = W.partitionBy(*KEY).orderBy("edge_id").rowsBetween(W.unboundedPreceding, 0)
        e = e.join(child, on).select(*KEY, "edge_id", "src", "lab", "src_level", "src_states", "below")
        e = e.withColumn("cum_hi", F.sum("below").over(order).cast(_BIG)).withColumn("cum_lo", (F.col("cum_hi") - F.col("below")).cast(_BIG))
        last = counted(ranks.add(e, level))
    if ranks.schema is None:
        none = rows.limit(0).select(*KEY, "edge_id", "src", "lab", "src_level", "src_states", F.lit(0).cast(_BIG).alias("below"), F.lit(0).cast(_BIG).alias("cum_hi"), F.lit(0).cast(_BIG).alias("cum_lo"))
        ranks.add(none, 0)
    edges = ranks.all().drop("turn")
    return AnswerDag(staged(leaves.unionByName(counted(edges)), "dag-nodes"), edges, roots)


def totals(dag: AnswerDag) -> DataFrame:
    """run_id, target, length (or cost), n_walks of every root."""
    r = dag.roots.withColumnRenamed("target", "vertex")
    return r.join(dag.nodes, ["run_id", "level", "vertex", "mask"]).select("run_id", F.col("vertex").alias("target"), F.col("level").alias("length"), "n_walks")


def walks_at(dag: AnswerDag, ranks: DataFrame) -> DataFrame:
    """The walks of the given ranks (column ``rank``, from 0, in in-edge order read from the target), for every root."""
    kind = F.col("rank").cast(_BIG)
    rows = dag.roots.crossJoin(F.broadcast(ranks.select(kind.alias("rank")))).select(
        "run_id", "target", "level", F.col("target").alias("vertex"), "mask", "rank", F.col("rank").alias("rest"), F.lit("").alias("edge_path"), F.lit(0).alias("length")
    )
    ok = totals(dag).select(F.col("run_id").alias("t_run"), F.col("target").alias("t_target"), "n_walks")
    rows = rows.join(ok, (rows.run_id == ok.t_run) & (rows.target == ok.t_target)).where("rank < n_walks AND rank >= 0").drop("t_run", "t_target", "n_walks")
    out = rows.where("level = 0")
    steps = dag.roots.agg(F.max("level")).first()[0] or 0
    e = dag.edges
    for _ in range(steps):
        r, x = rows.where("level > 0").alias("r"), e.alias("x")
        on = (F.col("r.run_id") == F.col("x.run_id")) & (F.col("r.level") == F.col("x.level")) & (F.col("r.vertex") == F.col("x.vertex"))
        on = on & (F.col("r.mask") == F.col("x.mask")) & (F.col("r.rest") >= F.col("x.cum_lo")) & (F.col("r.rest") < F.col("x.cum_hi"))
        rows = r.join(x, on).select(
            "r.run_id", "r.target", F.col("x.src_level").alias("level"), F.col("x.src").alias("vertex"), F.col("x.src_states").alias("mask"), "r.rank",
            (F.col("r.rest") - F.col("x.cum_lo")).cast(_BIG).alias("rest"),
            F.when(F.col("r.length") == 0, F.col("x.edge_id").cast("string")).otherwise(F.concat_ws(">", "x.edge_id", "r.edge_path")).alias("edge_path"),
            (F.col("r.length") + 1).alias("length"),
        )
        out = out.unionByName(rows.where("level = 0"))
    return out.select("run_id", "target", F.col("rank").cast("long").alias("rank"), "length", "edge_path")


def rank_of(dag: AnswerDag, path: list) -> int | None:
    """The rank of a walk given as its edges, first edge first, for a DAG of one root: the intervals along the walk add
    up.  Nothing but the DAG and the walk is read, so the walk itself is a token for the next page."""
    steps = list(reversed(path))
    rows = dag.roots.select("run_id", "level", F.col("target").alias("vertex"), "mask", F.lit(0).cast(_BIG).alias("rank"))
    for edge in steps:
        r, x = rows.alias("r"), dag.edges.where(F.col("edge_id") == F.lit(edge)).alias("x")
        rows = r.join(x, [F.col(f"r.{c}") == F.col(f"x.{c}") for c in KEY]).select(
            "r.run_id", F.col("x.src_level").alias("level"), F.col("x.src").alias("vertex"), F.col("x.src_states").alias("mask"), (F.col("r.rank") + F.col("x.cum_lo")).cast(_BIG).alias("rank")
        )
    found = rows.where("level = 0").select("rank").first()
    return None if found is None else int(found[0])


def page_after(dag: AnswerDag, token: list | None, size: int) -> DataFrame:
    """The page after the walk ``token`` (from the first walk on without one)."""
    first = 0 if token is None else rank_of(dag, token)
    if first is None:
        raise ValueError("the token is no answer of this run")
    return page(dag, first + (token is not None), size)


def save_run(dag: AnswerDag, path: str) -> None:
    """A run as Parquet files: another driver can page, count and sample from them."""
    for name in ("nodes", "edges", "roots"):
        getattr(dag, name).write.parquet(f"{path}/{name}")


def load_run(spark, path: str) -> AnswerDag:
    return AnswerDag(*(spark.read.parquet(f"{path}/{name}") for name in ("nodes", "edges", "roots")))


def page(dag: AnswerDag, first: int, size: int) -> DataFrame:
    """A page of answers; nothing is kept between pages, and any driver can ask for the next one."""
    spark = dag.nodes.sparkSession
    return walks_at(dag, spark.range(first, first + size).select(F.col("id").alias("rank")))


def total_runs(layers: Layers, answers: AnswerEdges | None = None) -> DataFrame:
    """run_id, target, length and the number of accepting runs over all answers, by one count a (vertex, state) and level
    on the vertices that lie on answers."""
    nfa = layers.nfa
    answers = answers or answer_edges(layers)
    spark = layers.edges.sparkSession
    bit = {a: 1 << i for i, a in enumerate(layers.alphabet)}
    moves = F.broadcast(spark.createDataFrame([(p, bit[a], q) for p, a, q in nfa.moves], "p int, bit long, q int"))  # as large as the pattern
    links = staged(answer_links(layers, answers), "links")
    flag = lambda mask, state: F.col(mask).bitwiseAND(F.expr(f"shiftleft(1L, {state})")) != 0
    state = F.explode(F.sequence(F.lit(0), F.lit(max(0, nfa.n - 1)))).alias("state")
    first = links.where("level = 1").select("run_id", F.col("src").alias("vertex"), "src_mask", state).where(flag("src_mask", "state"))
    zero = layers.ends.where("level = 0").select("run_id", F.col("target").alias("vertex"), F.col("mask").alias("src_mask"), state).where(flag("src_mask", "state"))
    first = first.unionByName(zero).select("run_id", "vertex", "state").distinct()
    counts = Parts(spark, "runs", "level")
    now = counts.add(first.withColumn("runs", F.lit(1).cast(_BIG)), 0)
    for level in range(1, answers.rounds + 1):
        own = links.where(F.col("level") == level).withColumnRenamed("run_id", "k_run")
        moved = now.join(own, (F.col("run_id") == F.col("k_run")) & (F.col("vertex") == F.col("src"))).join(moves, (F.col("state") == F.col("p")) & (F.col("lab").bitwiseAND(F.col("bit")) != 0))
        moved = moved.where(flag("dst_mask", "q")).groupBy("run_id", F.col("dst").alias("vertex"), F.col("q").alias("state")).agg(F.sum("runs").cast(_BIG).alias("runs"))
        now = counts.add(moved, level)
    ends = layers.ends.withColumnRenamed("target", "vertex")
    return (
        ends.join(counts.all(), ["run_id", "vertex", "level"]).where(flag("mask", "state"))
        .groupBy("run_id", F.col("vertex").alias("target"), F.col("level").alias("length")).agg(F.sum("runs").cast(_BIG).alias("n_runs"))
    )

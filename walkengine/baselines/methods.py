"""Baselines that the engine is compared with."""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkengine.core.search import Layers, answer_edges, layer_forward, pair
from walkengine.graph.model import LabeledGraph
from walkengine.lang.automata import Nfa, compile_pattern, determinize
from walkengine.session import staged


def _moves(layers: Layers) -> DataFrame:
    bit = {a: 1 << i for i, a in enumerate(layers.alphabet)}
    rows = [(p, bit[a], q) for p, a, q in layers.nfa.moves]
    return F.broadcast(layers.edges.sparkSession.createDataFrame(rows, "p int, bit long, q int"))  # as large as the pattern


def product_paths(layers: Layers) -> DataFrame:
    """One row for every accepting run over a minimal walk: the shortest paths of graph x automaton, seen as edges."""
    flag = F.expr("shiftleft(1L, state)")
    moves = _moves(layers)
    pairs = staged(
        layers.reach.select("*", F.explode(F.sequence(F.lit(0), F.lit(max(0, layers.nfa.n - 1)))).alias("state")).where(F.col("mask").bitwiseAND(flag) != 0), "product"
    ).select(F.col("run_id").alias("x_run"), F.col("vertex").alias("x_vertex"), F.col("level").alias("x_level"), F.col("state").alias("x_state"))
    rows = layers.ends.select(
        "run_id", "target", F.col("target").alias("vertex"), "level", F.explode(F.sequence(F.lit(0), F.lit(max(0, layers.nfa.n - 1)))).alias("state"), "mask", F.lit("").alias("edge_path")
    ).where(F.col("mask").bitwiseAND(flag) != 0)
    steps = layers.ends.agg(F.max("level")).first()[0] or 0
    for k in range(steps):
        rows = (
            rows.join(layers.edges, rows.vertex == layers.edges.dst)
            .join(moves, (F.col("state") == F.col("q")) & (F.col("lab").bitwiseAND(F.col("bit")) != 0))
            .join(pairs, (F.col("run_id") == F.col("x_run")) & (F.col("src") == F.col("x_vertex")) & (F.col("p") == F.col("x_state")) & (F.col("level") == F.col("x_level") + 1))
            .select(
                "run_id", "target", F.col("src").alias("vertex"), F.col("x_level").alias("level"), F.col("p").alias("state"),
                (F.col("edge_id").cast("string") if k == 0 else F.concat_ws(">", "edge_id", "edge_path")).alias("edge_path"),
            )
        )
    return rows.where("level = 0").select("run_id", "target", "edge_path")


def product_distinct(layers: Layers) -> DataFrame:
    """The same, with copies removed after the fact."""
    return product_paths(layers).distinct()


def simple_walks(g: LabeledGraph, dfa: Nfa, source, target) -> DataFrame:
    """Deterministic pattern, one label an edge: a run is a walk, so no state sets are needed."""
    if not dfa.is_deterministic() or not g.single_labelled():
        raise ValueError("needs a deterministic automaton and one label an edge")
    return product_paths(layer_forward(g, dfa, pair(g, source, target))).select("edge_path")


def determinized_walks(g: LabeledGraph, nfa: Nfa, source, target) -> DataFrame:
    """Determinise over label sets, relabel each edge by its set, then the simple case."""
    alphabet = nfa.alphabet
    dfa = determinize(nfa, by_label_sets=True)
    own = F.array_sort(F.filter(F.array_distinct("labels"), lambda x: x.isin(*alphabet)))
    edges = g.edges.withColumn("labels", own).where(F.size("labels") > 0)
    single = LabeledGraph(edges.withColumn("labels", F.array(F.array_join("labels", "+"))))
    return product_paths(layer_forward(single, dfa, pair(g, source, target))).select("edge_path")


class CrossSection:
    """Words of length ``level`` of the product automaton in lexicographic order, edges being letters.

    ``finish[i]`` holds the (vertex, state) pairs that can end at the target in exactly i edges.  The next word changes
    the last letter that can be changed and fills up with the least tail; every step may look at all edges.
    """

    def __init__(self, nfa: Nfa, alphabet, edges: list[tuple], source, target, level: int):
        """``edges``: (edge_id, src, dst, lab)."""
        bit = {a: 1 << i for i, a in enumerate(alphabet)}
        self.moves = [(p, bit[a], q) for p, a, q in nfa.moves]
        self.edges, self.level, self.source, self.steps = sorted(edges), level, source, 0
        self.initial = frozenset((source, q) for q in nfa.initial)
        self.finish = [{(target, q) for q in nfa.final}]
        for _ in range(level):
            last = self.finish[-1]
            self.finish.append({(s, p) for _, s, d, lab in self.edges for p, b, q in self.moves if lab & b and (d, q) in last})

    def _after(self, now: frozenset, edge: tuple) -> frozenset:
        self.steps += len(self.moves)
        _, s, d, lab = edge
        return frozenset((d, q) for p, b, q in self.moves if lab & b and (s, p) in now)

    def words(self) -> Iterator[tuple]:
        if self.level == 0:
            if self.initial & self.finish[0]:
                yield ()
            return
        path: list = []

        def grow(now: frozenset, left: int) -> Iterator[tuple]:
            for edge in self.edges:
                then = self._after(now, edge)
                if then & self.finish[left - 1] if then else False:
                    path.append(edge[0])
                    if left == 1:
                        yield tuple(path)
                    else:
                        yield from grow(then, left - 1)
                    path.pop()

        yield from grow(self.initial, self.level)


def cross_section(g: LabeledGraph, pattern, source, target) -> DataFrame:
    """rank, edge_path, steps in forward-lexicographic order; edges that don't lie on an answer are dropped beforehand, so
    the one task that lists the words holds the answers' edges alone."""
    nfa = compile_pattern(pattern)
    layers = layer_forward(g, nfa, pair(g, source, target))
    alphabet = layers.alphabet
    edges = answer_edges(layers).rows.select("run_id", "edge_id", "src", F.col("vertex").alias("dst"), "lab").distinct()

    def run(rows: pd.DataFrame, ends: pd.DataFrame) -> pd.DataFrame:
        out = []
        for level in ends["level"].tolist():
            method = CrossSection(nfa, alphabet, list(rows[["edge_id", "src", "dst", "lab"]].itertuples(index=False, name=None)), source, target, int(level))
            last = 0
            for rank, path in enumerate(method.words()):
                out.append((rank, ">".join(map(str, path)), method.steps - last))
                last = method.steps
        return pd.DataFrame(out, columns=["rank", "edge_path", "steps"])

    ends = layers.ends.select("run_id", "level")
    return edges.groupBy("run_id").cogroup(ends.groupBy("run_id")).applyInPandas(run, "rank long, edge_path string, steps long")


def brute_force(edges: list[tuple], nfa: Nfa, source, target, longest: int) -> tuple[int | None, list[tuple]]:
    """(length, walks) by listing all walks; edges: (edge_id, src, dst, labels).  Handles spontaneous moves itself."""
    out = defaultdict(list)
    for e in edges:
        out[e[1]].append(e)
    front = [(source, (), nfa.closure(nfa.initial))]
    for length in range(longest + 1):
        found = [path for v, path, states in front if v == target and states & nfa.final]
        if found:
            return length, sorted(found)
        front = [
            (e[2], (*path, e[0]), then) for v, path, states in front for e in out[v] if (then := nfa.closure(nfa.step(states, set(e[3]))))
        ]
    return None, []


def recursive_sql(g: LabeledGraph, nfa: Nfa, source, target, longest: int) -> DataFrame:
    """Bounded recursion in Spark SQL, over edges that lie on answers.  Its UNION ALL has no set semantics, so copies stay
    until the last step.  Spark ends a recursion by an error beyond a number of rows or levels; both limits are lifted while
    the result is written."""
    spark = g.edges.sparkSession
    alphabet = nfa.alphabet
    layers = layer_forward(g, nfa, pair(g, source, target), max_levels=longest)
    rows = answer_edges(layers).rows
    staged(rows.select("edge_id", "src", F.col("vertex").alias("dst"), "lab", F.col("src_level").alias("at")).distinct(), "edges").createOrReplaceTempView("_walk_edges")
    bit = {a: 1 << i for i, a in enumerate(alphabet)}
    spark.createDataFrame([(p, bit[a], q) for p, a, q in nfa.moves], "p int, bit long, q int").createOrReplaceTempView("_walk_moves")
    starts = " UNION ALL ".join(f"SELECT {q} AS state" for q in sorted(nfa.initial))
    lit = lambda v: f"'{v}'" if isinstance(v, str) else str(v)
    kind = dict(g.edges.dtypes)["src"]
    text = f"""
        WITH RECURSIVE found(vertex, state, length, edge_path) AS (
          SELECT CAST({lit(source)} AS {kind}), state, 0, CAST('' AS STRING) FROM ({starts})
          UNION ALL
          SELECT e.dst, m.q, f.length + 1, CASE WHEN f.length = 0 THEN CAST(e.edge_id AS STRING) ELSE concat(f.edge_path, '>', e.edge_id) END
          FROM found f JOIN _walk_edges e ON e.src = f.vertex AND e.at = f.length JOIN _walk_moves m ON m.p = f.state AND (e.lab & m.bit) <> 0
          WHERE f.length < {longest}),
        ends AS (SELECT * FROM found WHERE vertex = {lit(target)} AND state IN ({', '.join(map(str, nfa.final))}))
        SELECT DISTINCT length, edge_path FROM ends WHERE length = (SELECT min(length) FROM ends)"""
    limits = {"spark.sql.cteRecursionRowLimit": "-1", "spark.sql.cteRecursionLevelLimit": "-1"}
    before = {name: spark.conf.get(name) for name in limits}
    try:
        for name, value in limits.items():
            spark.conf.set(name, value)
        return staged(spark.sql(text), "recursive")
    finally:
        for name, value in before.items():
            spark.conf.set(name, value)

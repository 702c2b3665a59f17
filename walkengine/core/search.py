"""Forward layering, back links, seeds and emission, set at a time.

All tables carry ``run_id``, so one pass serves a batch of (source, target) pairs.  A state set is one BIGINT, so a
vertex has one row a level and no row is ever multiplied by the automaton.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkengine.graph.model import LabeledGraph
from walkengine.lang.automata import Nfa, compile_pattern, inductive_nfa, reverse, trim_states
from walkengine.lang.patterns import parse_pattern
from walkengine.lang.codegen import closure_expr, inverse_step_expr, run_counts, step_expr
from walkengine.session import Parts, bucketed, staged

#: Levels after which a search that has found nothing gives up: there are at most vertices x states of them.
NO_LIMIT = 1 << 30


@dataclass(frozen=True)
class Layers:
    """Result of layering.  ``edges``: those the pattern can use, bucketed by src.  ``reach``: run_id, vertex, level, mask
    (states first met there).  ``ends``: run_id, target, level, mask (final states at the least level of the target).
    ``unit``: a level is a number of edges; else it is a sum of costs."""

    nfa: Nfa
    alphabet: tuple[str, ...]
    edges: DataFrame
    reach: DataFrame
    ends: DataFrame
    unit: bool = True


def layer_forward(g: LabeledGraph, nfa: Nfa, pairs: DataFrame, *, all_targets: bool = False, max_levels: int = NO_LIMIT, eps: str = "eager") -> Layers:
    """Breadth-first over (vertex, states) from each run's source.

    ``pairs``: run_id, source, target (without target if ``all_targets``).  A run stops after the whole level in which
    its target meets a final state; with ``all_targets`` when nothing new is met.  A level is one join on ``src`` (the
    edges stay in their buckets) and one ``bit_or`` by vertex over what was stepped to and what was met before; only what
    is new is written, and two numbers come to the driver.

    Spontaneous moves: ``eager`` expects none (compile_pattern closes them); ``lazy`` keeps arrivals as they are and
    closes them when they are stepped from or tested, so the automaton is never enlarged.
    """
    spark, alphabet = g.edges.sparkSession, nfa.alphabet
    if nfa.eps and eps != "lazy":
        raise ValueError("spontaneous moves are left: compile the pattern or ask for eps='lazy'")
    edges = bucketed(g.masked(alphabet), "src", "edges")
    final = F.lit(nfa.mask(reverse(nfa).closure(nfa.final))).cast("long")  # also states that move on to an end spontaneously
    start = F.lit(nfa.mask(nfa.initial)).cast("long")
    goal = F.lit(None).cast(dict(pairs.dtypes)["source"]) if all_targets else F.col("target")
    meets = F.col("mask").bitwiseAND(final) != 0
    hit = F.lit(False) if all_targets else (F.col("vertex") == F.col("goal")) & meets
    parts = Parts(spark, "reach", "level")
    start = F.col("start") if "start" in pairs.columns else start  # a run may have initial states of its own
    first = pairs.select("run_id", F.col("source").alias("vertex"), start.alias("mask"), goal.alias("goal")).where("mask <> 0")
    front, level = parts.add(first.withColumn("hit", hit), 0), 0
    while level < max_levels and nfa.final:
        seen = front.agg(F.count("*").alias("n"), F.count_if("hit").alias("hits")).first()
        if not seen.n:
            break
        if seen.hits:
            front = front.join(front.where("hit").select("run_id"), "run_id", "left_anti")
            if seen.hits == seen.n or front.isEmpty():
                break
        level += 1
        none = F.lit(0).cast("long")
        moved = front.join(edges, front.vertex == edges.src).select(
            "run_id", F.col("dst").alias("vertex"), step_expr(closure_expr(F.col("mask"), nfa), F.col("lab"), nfa, alphabet).alias("out"), none.alias("old"), "goal"
        ).where("out <> 0")
        before = parts.all().select("run_id", "vertex", none.alias("out"), F.col("mask").alias("old"), "goal")
        merged = moved.unionByName(before).groupBy("run_id", "vertex").agg(F.bit_or("out").alias("out"), F.bit_or("old").alias("old"), F.any_value("goal").alias("goal"))
        new = merged.select("run_id", "vertex", F.col("out").bitwiseAND(F.bitwise_not("old")).alias("mask"), "goal").where("mask <> 0")
        front = parts.add(new.withColumn("hit", hit), level)
    reach = parts.all()
    met = reach.where(F.lit(False) if not nfa.final else meets if all_targets else F.col("hit"))
    ends = met.groupBy("run_id", F.col("vertex").alias("target")).agg(F.min(F.struct("level", F.col("mask").bitwiseAND(final).alias("mask"))).alias("x"))
    return Layers(nfa, alphabet, edges, reach.select("run_id", "vertex", "level", "mask"), staged(ends.select("run_id", "target", "x.level", "x.mask"), "ends"))


def back_links(layers: Layers) -> DataFrame:
    """run_id, level, dst, edge_id, src, lab, src_mask, dst_mask: every link of everything that was reached, one row for an
    edge and level however many states it links.  A link keeps only states that its end meets first at this level, from
    states its start met just before.  Answers need far fewer: see ``answer_edges``."""
    a, e, b = layers.reach.alias("a"), layers.edges.alias("e"), layers.reach.alias("b")
    moved = a.join(e, F.col("a.vertex") == F.col("e.src")).select(
        "a.run_id", "e.edge_id", "e.src", "e.dst", "e.lab", F.col("a.mask").alias("src_mask"), F.col("a.level").alias("from_level"),
        step_expr(F.col("a.mask"), F.col("e.lab"), layers.nfa, layers.alphabet).alias("out"),
    ).where("out <> 0").alias("m")
    same = (F.col("m.run_id") == F.col("b.run_id")) & (F.col("m.dst") == F.col("b.vertex")) & (F.col("b.level") == F.col("m.from_level") + 1)
    return (
        moved.join(b, same)
        .select("m.run_id", "b.level", "m.dst", "m.edge_id", "m.src", "m.lab", "m.src_mask", F.col("m.out").bitwiseAND(F.col("b.mask")).alias("dst_mask"))
        .where("dst_mask <> 0")
    )


@dataclass(frozen=True)
class AnswerEdges:
    """``rows``: run_id, level, vertex, mask (a node: a vertex with the states from which the rest is accepted), edge_id,
    src, lab, src_level, src_states (the node before), src_mask (all states that src met at that level), and round.
    ``rounds``: the most edges of an answer.  ``level``: the level of all targets, if they share one."""

    rows: DataFrame
    rounds: int
    level: int | None


def answer_edges(layers: Layers) -> AnswerEdges:
    """Backwards from the targets, a level a round: only edges that lie on answers are ever touched."""
    nfa, alphabet, unit = layers.nfa, layers.alphabet, layers.unit
    spark = layers.edges.sparkSession
    low, top = layers.ends.agg(F.min("level"), F.max("level")).first()
    parts = Parts(spark, "answer-edges", "round")
    roots = layers.ends.select("run_id", "level", F.col("target").alias("vertex"), "mask")
    edges = bucketed(layers.edges, "dst", "edges_in") if top else layers.edges
    met = layers.reach.select(F.col("run_id").alias("x_run"), F.col("vertex").alias("x_vertex"), F.col("level").alias("src_level"), F.col("mask").alias("src_mask"))
    step = F.lit(1) if unit else F.col("cost")

    def before(here: DataFrame, prior: DataFrame) -> DataFrame:
        joined = here.join(edges, here.vertex == edges.dst).withColumn("x_level", F.col("level") - step)
        on = (F.col("run_id") == F.col("x_run")) & (F.col("src") == F.col("x_vertex")) & (F.col("x_level") == F.col("src_level"))
        states = closure_expr(inverse_step_expr(F.col("mask"), F.col("lab"), nfa, alphabet), reverse(nfa)).bitwiseAND(F.col("src_mask"))
        return joined.join(prior, on).select("run_id", "level", "vertex", "mask", "edge_id", "src", "lab", "src_level", states.alias("src_states"), "src_mask").where("src_states <> 0")

    child = lambda part: part.select("run_id", F.col("src_level").alias("level"), F.col("src").alias("vertex"), F.col("src_states").alias("mask"))
    rounds = 0
    if unit:
        below = None
        for level in range(top or 0, 0, -1):
            here = roots.where(F.col("level") == level)
            here = here if below is None else here.unionByName(below).distinct()
            rounds += 1
            below = child(parts.add(before(here, met.where(F.col("src_level") == level - 1)), rounds))
    elif top is not None:
        nodes = Parts(spark, "answer-nodes", "round")
        here = nodes.add(roots.distinct(), 0)
        while True:
            rounds += 1
            below = child(parts.add(before(here.drop("round"), met), rounds)).distinct()
            here = nodes.add(below.join(nodes.all().drop("round"), ["run_id", "level", "vertex", "mask"], "left_anti"), rounds)
            if here.where("level > 0").isEmpty():
                break
    if not rounds:
        parts.add(before(roots.limit(0), met.limit(0)), 0)
    return AnswerEdges(parts.all(), rounds, top if unit and low == top else None)


def answer_links(layers: Layers, answers: AnswerEdges | None = None) -> DataFrame:
    """The links that answers use, in the form of ``back_links``."""
    rows = (answers or answer_edges(layers)).rows
    masks = rows.groupBy("run_id", "level", F.col("vertex").alias("dst"), "edge_id", "src", "lab", "src_mask").agg(F.bit_or("mask").alias("wanted"))
    out = step_expr(closure_expr(F.col("src_mask"), layers.nfa), F.col("lab"), layers.nfa, layers.alphabet).bitwiseAND(F.col("wanted"))
    return masks.select("run_id", "level", "dst", "edge_id", "src", "lab", "src_mask", out.alias("dst_mask"))


def emit_all(layers: Layers, answers: AnswerEdges | None = None, *, multiplicity: str = "", keep_inner: bool = False) -> DataFrame:
    """Every walk once: run_id, target, length, edge_path, vertex_path (text), first edge first.

    Walks grow from the target by joins.  A row stands for a suffix and the states from which it is accepted; an edge
    extends it once, so nothing is ever de-duplicated.  ``multiplicity``: words or states adds accepting runs.
    """
    nfa, alphabet = layers.nfa, layers.alphabet
    answers = answers or answer_edges(layers)
    rows = layers.ends.select(
        "run_id", "target", "level", F.col("target").alias("vertex"), "mask", F.lit("").alias("edge_path"), F.col("target").cast("string").alias("vertex_path"), F.lit(0).alias("length")
    )
    nothing, one = F.lit(0).cast("decimal(38,0)"), F.lit(1).cast("decimal(38,0)")
    if multiplicity:
        bits = [F.when(F.col("mask").bitwiseAND(F.lit(1 << q).cast("long")) != 0, one).otherwise(nothing) for q in range(nfa.n)]
        rows = rows.withColumn("runs", F.array(*bits))
    inner = [rows]
    level_kind = dict(layers.ends.dtypes)["level"]
    for turn in range(answers.rounds):
        own = answers.rows if answers.level is None else answers.rows.where(F.col("round") == turn + 1)
        r, k = rows.alias("r"), own.alias("k")
        on = (F.col("r.run_id") == F.col("k.run_id")) & (F.col("r.level") == F.col("k.level")) & (F.col("r.vertex") == F.col("k.vertex")) & (F.col("r.mask") == F.col("k.mask"))
        whole = F.col("k.src").isNull()  # no edge has level 0, so the outer join hands a finished walk on
        kept = lambda name, value: F.when(whole, F.col(f"r.{name}")).otherwise(value).alias(name)  # noqa: B023, E731
        columns = [
            F.col("r.run_id"), F.col("r.target"), kept("level", F.col("k.src_level").cast(level_kind)), kept("vertex", F.col("k.src")), kept("mask", F.col("k.src_states")),
            kept("edge_path", F.when(F.col("r.length") == 0, F.col("k.edge_id").cast("string")).otherwise(F.concat_ws(">", "k.edge_id", "r.edge_path"))),
            kept("vertex_path", F.concat_ws(">", F.col("k.src").cast("string"), "r.vertex_path")), kept("length", F.col("r.length") + 1),
        ]
        if multiplicity:
            counts = run_counts(F.col("r.runs"), F.col("k.lab"), nfa, alphabet, multiplicity)
            held = [F.when(F.col("k.src_states").bitwiseAND(F.lit(1 << q).cast("long")) != 0, F.get(counts, q)).otherwise(nothing) for q in range(nfa.n)]
            columns.append(kept("runs", F.array(*held)))
        rows = r.join(k, on, "left" if answers.level is None else "inner").select(*columns)
        if keep_inner or (turn % 8 == 7):  # many turns: cut the plan
            rows = staged(rows, "walks")
        if keep_inner:
            inner.append(rows.where(F.col("length") == turn + 1))
    if keep_inner:
        out = inner[0]
        for x in inner[1:]:
            out = out.unionByName(x)
        return out
    out = rows.where("level = 0")
    names = ["run_id", "target", "length", "edge_path", "vertex_path"]
    if multiplicity:
        total = F.aggregate("runs", nothing, lambda a, x: (a + x).cast("decimal(38,0)"))
        out = out.withColumn("multiplicity", total)
        names.append("multiplicity")
    return out.select(*names)


def pair(g: LabeledGraph, source, target) -> DataFrame:
    """A batch of one pair, typed like the graph's vertices."""
    kind = g.edges.schema["src"].dataType.simpleString()
    return g.edges.sparkSession.createDataFrame([(1, source, target)], f"run_id int, source {kind}, target {kind}")


def choose_plan(g: LabeledGraph, nfa: Nfa) -> str:
    """``simple`` where a walk has one accepting run at most: an unambiguous automaton (a deterministic one is) and one
    label an edge, so runs need no state sets; else ``general``.  The automaton is tested first, as it costs no job."""
    return "simple" if nfa.is_unambiguous() and g.single_labelled(nfa.alphabet) else "general"


def minimal_walks(
    g: LabeledGraph, pattern, source, target, *, multiplicity: str = "", construction: str = "inductive", eps: str = "eager", plan: str = "general",
    max_levels: int = NO_LIMIT, limit: int | None = None,
) -> DataFrame:
    """All minimal matching walks from source to target, each once: length, edge_path, vertex_path(, multiplicity).

    ``eps``: lazy keeps spontaneous moves of the inductive construction.  ``plan``: auto goes by ``choose_plan``."""
    if eps == "lazy":
        nfa = trim_states(pattern if isinstance(pattern, Nfa) else inductive_nfa(parse_pattern(pattern)))
        if multiplicity:
            raise ValueError("runs are counted over automata without spontaneous moves")
    else:
        nfa = pattern if isinstance(pattern, Nfa) and not pattern.eps else compile_pattern(pattern, (), construction)
    layers = layer_forward(g, nfa, pair(g, source, target), max_levels=max_levels, eps=eps)
    if plan == "auto" and choose_plan(g, nfa) == "simple" and not multiplicity:
        walks = simple_emit(layers)
    else:
        walks = emit_all(layers, multiplicity=multiplicity).drop("run_id", "target")
    return walks.limit(limit) if limit is not None else walks


def simple_emit(layers: Layers) -> DataFrame:
    """Emission where each walk has one run: a row is a suffix and one state, and an edge has one move at most back to a
    state of the level before.  length, edge_path, vertex_path."""
    nfa, spark = layers.nfa, layers.edges.sparkSession
    bit = {a: 1 << i for i, a in enumerate(layers.alphabet)}
    moves = F.broadcast(spark.createDataFrame([(p, bit[a], q) for p, a, q in nfa.moves], "p int, bit long, q int"))  # as large as the pattern
    states = F.explode(F.sequence(F.lit(0), F.lit(max(0, nfa.n - 1)))).alias("state")
    has = F.col("mask").bitwiseAND(F.expr("shiftleft(1L, state)")) != 0
    rows = layers.ends.select(F.col("target").alias("vertex"), "level", "mask", states).where(has).select(
        "vertex", "level", "state", F.lit("").alias("edge_path"), F.col("vertex").cast("string").alias("vertex_path"), F.col("level").alias("length")
    )
    top = layers.ends.agg(F.max("level")).first()[0] or 0
    for level in range(top, 0, -1):
        met = layers.reach.where(F.col("level") == level - 1).select(F.col("vertex").alias("x"), F.col("mask").alias("x_mask"))
        joined = rows.join(layers.edges, rows.vertex == layers.edges.dst).join(moves, (F.col("state") == F.col("q")) & (F.col("lab").bitwiseAND(F.col("bit")) != 0))
        joined = joined.join(met, (F.col("src") == F.col("x")) & (F.col("x_mask").bitwiseAND(F.expr("shiftleft(1L, p)")) != 0))
        rows = joined.select(
            F.col("src").alias("vertex"), F.lit(level - 1).alias("level"), F.col("p").alias("state"),
            (F.col("edge_id").cast("string") if level == top else F.concat_ws(">", "edge_id", "edge_path")).alias("edge_path"),
            F.concat_ws(">", F.col("src").cast("string"), "vertex_path").alias("vertex_path"), "length",
        )
    return rows.select("length", "edge_path", "vertex_path")


def minimal_walks_batch(g: LabeledGraph, pattern, pairs: DataFrame, **options) -> DataFrame:
    """The same for many pairs (run_id, source, target) in one pass over the edges a level."""
    layers = layer_forward(g, compile_pattern(pattern), pairs)
    return emit_all(layers, **options)


def minimal_walks_of_patterns(g: LabeledGraph, patterns: dict[str, object], source, target) -> DataFrame:
    """pattern, length, edge_path for many patterns between one pair.  The automata are laid side by side and one run
    starts in each, so every level scans the edges once for all of them; needs as many bits as they have states."""
    moves, initial, final, at = set(), {}, set(), 0
    for name, pattern in patterns.items():
        nfa = compile_pattern(pattern)
        moves |= {(p + at, a, q + at) for p, a, q in nfa.moves}
        initial[name] = nfa.mask(q + at for q in nfa.initial)
        final |= {q + at for q in nfa.final}
        at += nfa.n
    joint = Nfa.of(at, moves, range(at), final)
    kind = g.edges.schema["src"].dataType.simpleString()
    names = list(patterns)
    runs = g.edges.sparkSession.createDataFrame([(i, source, target, initial[n]) for i, n in enumerate(names)], f"run_id int, source {kind}, target {kind}, start long")
    walks = emit_all(layer_forward(g, joint, runs))
    return walks.select(F.element_at(F.array(*map(F.lit, names)), F.col("run_id") + 1).alias("pattern"), "length", "edge_path")


def min_length(g: LabeledGraph, pattern, pairs: DataFrame) -> DataFrame:
    """run_id, source, target and length (null: no walk)."""
    layers = layer_forward(g, compile_pattern(pattern), pairs)
    return pairs.join(layers.ends.select("run_id", F.col("level").alias("length")), "run_id", "left")


def minimal_lengths_from(g: LabeledGraph, pattern, source, targets: DataFrame | None = None) -> tuple[Layers, DataFrame]:
    """One source, all (or the listed) targets: layers, and a table target, length."""
    batch = pair(g, source, source).select("run_id", "source")
    layers = layer_forward(g, compile_pattern(pattern), batch, all_targets=True)
    if targets is not None:
        ends = layers.ends.join(targets.select("target"), "target", "left_semi")
        layers = Layers(layers.nfa, layers.alphabet, layers.edges, layers.reach, ends.select("run_id", "target", "level", "mask"))
    return layers, layers.ends.select("target", F.col("level").alias("length"))

"""Workloads and measures beyond the basic ones: lists of pairs, sweeps, paging, ablations, SQL text, sources and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkengine import sqlsurface
from walkengine.baselines import methods as base
from walkengine.core import dag as answer
from walkengine.core import local
from walkengine.core.cheapest import cheapest_walks
from walkengine.core.runs import count_runs
from walkengine.core.search import (
    answer_edges, choose_plan, emit_all, layer_forward, minimal_lengths_from, minimal_walks, minimal_walks_of_patterns, pair,
)
from walkengine.graph import io, views
from walkengine.graph.model import LabeledGraph
from walkengine.graph.views import VIEW_SQL
from walkengine.lang.automata import Nfa, compile_pattern
from walkengine.operators.automata import P1, P2, P3, PATTERNS, TEXT
from walkengine.operators.oracles import cheapest, ranked, runs, search, walks
from walkengine.session import fresh_folder, staged
from walkengine.streaming.queries import drain, event_stream

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
FROM, TO = 100, 1899


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return keep


def union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def totals(g: LabeledGraph, nfa: Nfa, pairs: DataFrame) -> DataFrame:
    """run_id, length, n_walks, n_runs of every pair that has an answer; no walk is expanded."""
    layers = layer_forward(g, nfa, pairs)
    answers = answer_edges(layers)
    both = answer.totals(answer.build(layers, answers)).join(answer.total_runs(layers, answers), ["run_id", "target", "length"])
    return both.select("run_id", "length", F.col("n_walks").cast("string").alias("n_walks"), F.col("n_runs").cast("string").alias("n_runs"))


# --- lists of pairs ---------------------------------------------------------------------------------------------------

_PAIRS = {
    "basket": (("p1", "p2", "p3"), ((0, 1), (100, 189), (100, 1899), (1001, 999), (10, 10))),
    "trade": (("p1", "p2"), (("C:1001", "S:99"), ("C:0", "C:1"))),
    "handoff": (("p1", "p2", "p3"), ((0, 1), (102, 99), (10, 10))),
}


def _pair_counts(view: str, patterns, pairs) -> None:
    sql = " UNION ALL ".join(
        f"SELECT '{p}' AS pattern, {i} AS run_id, * FROM ({runs(view, PATTERNS[p], s, t, 6)} SELECT length::INT AS length, count(DISTINCT edge_path)::VARCHAR AS n_walks, count(*)::VARCHAR AS n_runs FROM walks GROUP BY length)"
        for p in patterns for i, (s, t) in enumerate(pairs)
    )

    def f(spark, sf_dir):
        g = views.VIEWS[view](spark, sf_dir)
        kind = g.edges.schema["src"].dataType.simpleString()
        table = spark.createDataFrame([(i, s, t) for i, (s, t) in enumerate(pairs)], f"run_id int, source {kind}, target {kind}")
        return union([totals(g, PATTERNS[p], table).select(F.lit(p).alias("pattern"), "*") for p in patterns])

    query(f"{view}_pair_counts", sql)(f)


for _view, (_patterns, _list) in _PAIRS.items():
    _pair_counts(_view, _patterns, _list)


@query("trade_pair_p3", f"{runs('trade', P3, 'C:0', 'C:1', 5)} SELECT length::INT AS length, count(DISTINCT edge_path)::VARCHAR AS n_walks, count(*)::VARCHAR AS n_runs FROM walks GROUP BY length")
def trade_pair_p3(spark, sf_dir):
    g = views.trade(spark, sf_dir)
    return totals(g, P3, pair(g, "C:0", "C:1")).drop("run_id")


_TIES = ((0, 1, 6), (100, 189, 10))


@query("cheapest_pairs_ties", " UNION ALL ".join(f"SELECT {s} AS source, * FROM ({cheapest('basket', P2, s, t, 'ceil(cost / 10)::BIGINT', most)})" for s, t, most in _TIES))
def cheapest_pairs_ties(spark, sf_dir):
    g = LabeledGraph(views.basket(spark, sf_dir).edges.withColumn("cost", F.ceil(F.col("cost") / 10).cast("long")))
    return union([cheapest_walks(g, P2, s, t).select(F.lit(s).alias("source"), "cost", "length", "edge_path") for s, t, _ in _TIES])


_DOTS = compile_pattern(". . .*", ("h", "o", "s"))


@query("any_label_walks", walks("basket", _DOTS, FROM, TO))
def any_label_walks(spark, sf_dir):
    """A pattern of any labels: two edges at least."""
    return minimal_walks(views.basket(spark, sf_dir), _DOTS, FROM, TO).select("length", "edge_path")


@query("walks_within_3_edges", " UNION ALL ".join(
    f"SELECT {i} AS run_id, coalesce((SELECT max(l) FROM ({runs('basket', P2, s, t, 3)} SELECT length AS l FROM walks)), -1)::INT AS length" for i, (s, t) in enumerate(_PAIRS["basket"][1])
))
def walks_within_3_edges(spark, sf_dir):
    """Lengths of walks of three edges at most; -1 where the shortest is longer."""
    g = views.basket(spark, sf_dir)
    table = spark.createDataFrame([(i, s, t) for i, (s, t) in enumerate(_PAIRS["basket"][1])], "run_id int, source long, target long")
    found = layer_forward(g, P2, table, max_levels=3).ends.select("run_id", F.col("level").alias("length"))
    return table.select("run_id").join(found, "run_id", "left").select("run_id", F.coalesce("length", F.lit(-1)).alias("length"))


# --- variants and ablations -------------------------------------------------------------------------------------------

_P8 = "(s|s s?) (h|s)*"


@query("eps_eager_vs_lazy", " UNION ALL ".join(f"SELECT '{e}' AS eps, * FROM ({walks('basket', compile_pattern(_P8), FROM, TO)})" for e in ("eager", "lazy")))
def eps_eager_vs_lazy(spark, sf_dir):
    """Spontaneous moves closed beforehand, and closed only when states are stepped from or tested."""
    g = views.basket(spark, sf_dir)
    return union([minimal_walks(g, _P8, FROM, TO, eps=e).select(F.lit(e).alias("eps"), "length", "edge_path") for e in ("eager", "lazy")])


@query("runs_during_vs_after", f"{runs('basket', P2, FROM, TO)} SELECT edge_path, count(*)::VARCHAR AS during, count(*)::VARCHAR AS afterwards FROM walks GROUP BY edge_path")
def runs_during_vs_after(spark, sf_dir):
    """Accepting runs counted while walks are emitted, and by running the automaton over finished walks."""
    g = views.basket(spark, sf_dir)
    found = staged(minimal_walks(g, P2, FROM, TO, multiplicity="words").select("edge_path", F.col("multiplicity").cast("string").alias("during")), "walks")
    after = count_runs(found.select("edge_path"), g, P2).select("edge_path", F.col("multiplicity").cast("string").alias("afterwards"))
    return found.join(after, "edge_path", "left")


_FIRST = "AS MATERIALIZED (SELECT edge_id, src, dst, labels[:1] AS labels, cost FROM"


@query("favourable_case_walks", walks("basket", P1, FROM, TO).replace("AS MATERIALIZED (SELECT * FROM", _FIRST))
def favourable_case_walks(spark, sf_dir):
    """One label an edge and a deterministic automaton: the plan without state sets is chosen."""
    g = LabeledGraph(views.basket(spark, sf_dir).edges.withColumn("labels", F.slice("labels", 1, 1)))
    return minimal_walks(g, P1, FROM, TO, plan="auto").select("length", "edge_path")


_MANY = "SELECT count(*) > 0 FROM ({}) WHERE len(list_filter(labels, lambda x: x IN ('h', 's'))) > 1"


@query("chosen_plans", " UNION ALL ".join(
    f"SELECT '{v}' AS view, '{p}' AS pattern, CASE WHEN ({_MANY.format(VIEW_SQL[v])}) OR {'false' if p == 'p1' else 'true'} THEN 'general' ELSE 'simple' END AS plan" for v in ("basket", "session") for p in ("p1", "p2")
))
def chosen_plans(spark, sf_dir):
    """Which plan each view and pattern gets: P1 is unambiguous, P2 is not."""
    rows = [(v, p, choose_plan(views.VIEWS[v](spark, sf_dir), PATTERNS[p])) for v in ("basket", "session") for p in ("p1", "p2")]
    return spark.createDataFrame(rows, "view string, pattern string, plan string")


@query("ambiguity_report", " UNION ALL ".join(f"SELECT '{p}' AS pattern, count(*) > count(DISTINCT edge_path) AS ambiguous FROM ({runs('basket', n, FROM, TO)} SELECT * FROM walks)" for p, n in PATTERNS.items()))
def ambiguity_report(spark, sf_dir):
    """Whether the minimal walks of a pattern have more accepting runs than there are walks."""
    g = views.basket(spark, sf_dir)
    one = lambda p: totals(g, PATTERNS[p], pair(g, FROM, TO)).agg(F.coalesce(F.max(F.col("n_runs") != F.col("n_walks")), F.lit(False)).alias("ambiguous")).select(F.lit(p).alias("pattern"), "ambiguous")
    return union([one(p) for p in PATTERNS])


@query("pattern_batch", " UNION ALL ".join(f"SELECT '{p}' AS pattern, * FROM ({walks('basket', n, FROM, TO)})" for p, n in PATTERNS.items()))
def pattern_batch(spark, sf_dir):
    """Four patterns in one pass over the edges a level."""
    return minimal_walks_of_patterns(views.basket(spark, sf_dir), PATTERNS, FROM, TO)


# --- paging and saved runs --------------------------------------------------------------------------------------------

_RANKED = ranked("basket", P2, FROM, TO)


@query("pages_concatenated", f"{_RANKED} SELECT rank, edge_path FROM ranked")
def pages_concatenated(spark, sf_dir):
    """All pages of seven; each is found from the saved run and the last walk of the page before alone."""
    g = views.basket(spark, sf_dir)
    path = fresh_folder(spark, "run")
    answer.save_run(answer.build(layer_forward(g, P2, pair(g, FROM, TO))), path)
    pages, token = [], None
    while True:
        page = staged(answer.page_after(answer.load_run(spark, path), token, 7).select("rank", "edge_path"), "page")
        pages.append(page)
        last = page.orderBy(F.desc("rank")).first()
        if last is None:
            return union(pages)
        token = last.edge_path.split(">")


@query("resumed_run_page", f"{_RANKED} SELECT rank, edge_path FROM ranked WHERE rank BETWEEN 3 AND 5")
def resumed_run_page(spark, sf_dir):
    g = views.basket(spark, sf_dir)
    path = fresh_folder(spark, "run")
    answer.save_run(answer.build(layer_forward(g, P2, pair(g, FROM, TO))), path)
    return answer.page(answer.load_run(spark, path), 3, 3).select("rank", "edge_path")


# --- measures ---------------------------------------------------------------------------------------------------------


@query("measure_edge_visits", f"""{search('basket', P2, FROM)}, stop AS (SELECT min(lv) AS l FROM firsts WHERE v = {TO} AND q = 1)
    SELECT count(*) AS n_visits, (SELECT count(*) FROM e WHERE list_contains(labels, 'h') OR list_contains(labels, 's')) * 5 AS bound
    FROM firsts a JOIN e ON e.src = a.v JOIN d ON d.p = a.q AND list_contains(e.labels, d.l), stop WHERE a.lv < stop.l""")  # fmt: skip
def measure_edge_visits(spark, sf_dir):
    """Visits of (edge, move) while layering, at most edges times moves: every (vertex, state) is left once."""
    g = views.basket(spark, sf_dir)
    layers = layer_forward(g, P2, pair(g, FROM, TO))
    bit = {a: 1 << i for i, a in enumerate(layers.alphabet)}
    has = lambda c, x: (F.col(c).bitwiseAND(F.lit(x).cast("long")) != 0).cast("long")
    visits = sum((has("mask", 1 << p) * has("lab", bit[a]) for p, a, _ in P2.moves), F.lit(0))
    top = layers.ends.agg(F.max("level")).first()[0] or 0
    met = layers.reach.where(F.col("level") < top)
    n = met.join(layers.edges, met.vertex == layers.edges.src).agg(F.coalesce(F.sum(visits), F.lit(0)).cast("long").alias("n_visits"))
    return n.crossJoin(layers.edges.agg((F.count("*") * len(P2.moves)).alias("bound")))  # one row each


@query("measure_duplicates", f"{runs('basket', P2, FROM, TO)} SELECT count(DISTINCT edge_path) AS n_rows, count(DISTINCT edge_path) AS n_distinct FROM walks")
def measure_duplicates(spark, sf_dir):
    return minimal_walks(views.basket(spark, sf_dir), P2, FROM, TO).agg(F.count("*").alias("n_rows"), F.countDistinct("edge_path").alias("n_distinct"))


@query("measure_exactness", "SELECT p AS pattern, 0 AS missing, 0 AS extra FROM (VALUES ('p1'), ('p2'), ('p3')) AS t(p)")
def measure_exactness(spark, sf_dir):
    """Walks that the method lacks or has beyond those of the product baseline with copies removed."""
    g, rows = views.basket(spark, sf_dir), []
    for p in ("p1", "p2", "p3"):
        layers = layer_forward(g, PATTERNS[p], pair(g, FROM, TO))
        ours, theirs = (staged(x.select("edge_path"), "walks") for x in (emit_all(layers), base.product_distinct(layers)))
        rows.append((p, theirs.exceptAll(ours).count(), ours.exceptAll(theirs).count()))
    return spark.createDataFrame(rows, "pattern string, missing int, extra int")


@query("measure_emission", f"""{runs('basket', P2, FROM, TO)}, parts AS (SELECT DISTINCT edge_path, string_split(edge_path, '>') AS x FROM walks),
    nodes AS (SELECT DISTINCT x[i:] AS s FROM parts, range(1, 10) AS r(i) WHERE i <= len(x))
    SELECT (SELECT count(*) FROM nodes)::BIGINT AS calls, (SELECT count(*) FROM parts)::BIGINT AS n_walks, true AS calls_within_bound, true AS stack_within_bound, true AS memoryless WHERE (SELECT count(*) FROM parts) > 0""")  # fmt: skip
def measure_emission(spark, sf_dir):
    """Calls of the lazy emitter (tree nodes but the root, at most length of them a walk), its deepest stack (length,
    however many walks come out), and whether a new emitter finds each next walk from the one before alone."""

    def body(emitter, target):
        found, deepest = [], 0
        for path in emitter.walks():
            found.append(path)
            deepest = max(deepest, emitter.depth)
        calls, level = emitter.calls, emitter.root[0]
        again = all(emitter.next_walk(a, m) == b for m in ("pointer", "scan") for a, b in zip(found, [*found[1:], None]))
        yield calls, len(found), calls <= level * len(found), deepest <= level, again

    g = views.basket(spark, sf_dir)
    schema = "calls long, n_walks long, calls_within_bound boolean, stack_within_bound boolean, memoryless boolean"
    return local.per_run(layer_forward(g, P2, pair(g, FROM, TO)), body, schema, in_edges=True)


@query("measure_in_degree_sweep", "SELECT noise, true AS compact_flat, noise > 0 AS browse_grows FROM (VALUES (0), (40), (400)) AS t(noise)")
def measure_in_degree_sweep(spark, sf_dir):
    """Most steps a walk with useless edges into every vertex: the compact form stays flat, browsing grows with them."""
    nfa, rows, first = Nfa.of(1, [(0, "a", 0), (0, "b", 0)], [0], [0]), [], None
    for noise in (0, 40, 400):
        g = views.ladder(spark, 3, noise=noise)
        layers = layer_forward(g, nfa, pair(g, 0, 3))
        answers = answer_edges(layers)
        most = [local.emit_local(layers, compact=c, answers=answers).agg(F.max("steps")).first()[0] for c in (True, False)]
        first = first or most
        rows.append((noise, most[0] == first[0], most[1] > first[1] + noise))
    return spark.createDataFrame(rows, "noise int, compact_flat boolean, browse_grows boolean")


@query("ladder_copies_20", "SELECT k::BIGINT AS k, (2::HUGEINT ** k)::HUGEINT::VARCHAR AS n_walks, (4::HUGEINT ** k)::HUGEINT::VARCHAR AS n_runs FROM range(0, 21) AS t(k)")
def ladder_copies_20(spark, sf_dir):
    """Walks and runs of ladders of up to 20 stages in one run to all targets: copies grow as 4 to the k, nodes as k."""
    g = views.ladder(spark, 20)
    layers, _ = minimal_lengths_from(g, Nfa.of(1, [(0, "a", 0), (0, "b", 0)], [0], [0]), 0)
    answers = answer_edges(layers)
    both = answer.totals(answer.build(layers, answers)).join(answer.total_runs(layers, answers), ["run_id", "target", "length"])
    return both.select(F.col("target").alias("k"), F.col("n_walks").cast("string").alias("n_walks"), F.col("n_runs").cast("string").alias("n_runs"))


# --- other views ------------------------------------------------------------------------------------------------------


@query("geo_region_mates", "SELECT 'N:' || b.n_nationkey AS nation, 2 AS length FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey WHERE a.n_nationkey = 3")
def geo_region_mates(spark, sf_dir):
    """Nations that a walk up to the region and down again leads to."""
    _, lengths = minimal_lengths_from(views.geo(spark, sf_dir), "in has", "N:3")
    return lengths.where("target LIKE 'N:%'").select(F.col("target").alias("nation"), "length")


_NAV = compile_pattern("nav rev nav")


@query("links_nav_rev_nav", f"{runs('links', _NAV, 'G:0', None, 3)} SELECT target, length::INT AS length, count(DISTINCT edge_path)::VARCHAR AS n_walks FROM walks GROUP BY ALL")
def links_nav_rev_nav(spark, sf_dir):
    """What pages link to that share a link with page 0."""
    layers, _ = minimal_lengths_from(views.links(spark, sf_dir), _NAV, "G:0")
    return answer.totals(answer.build(layers)).select("target", "length", F.col("n_walks").cast("string").alias("n_walks"))


_MATES = compile_pattern("samelang* good")
_DOC = "(SELECT min(src) FROM e)"


@query("docs_good_mates", search("docs", _MATES, "@", 12).replace("'@'", _DOC) + " SELECT v AS target, min(lv)::INT AS length FROM firsts WHERE q = 1 GROUP BY v".replace("q = 1", f"q IN ({', '.join(map(str, _MATES.final))})"))
def docs_good_mates(spark, sf_dir):
    """Good documents that lines shared within a language lead to, from the first document that shares a line."""
    g = LabeledGraph(staged(views.docs(spark, sf_dir).edges, "edges"))
    first = g.edges.agg(F.min("src")).first()[0]
    _, lengths = minimal_lengths_from(g, _MATES, -1 if first is None else first)
    return lengths


# --- SQL text, functions, sources and sinks, streams ------------------------------------------------------------------


@query("sql_text_walks", f"{walks('basket', compile_pattern(TEXT['p2']), FROM, TO)}")
def sql_text_walks(spark, sf_dir):
    sqlsurface.sql_walks(spark, sf_dir, f"FROM {FROM} TO {TO} OVER basket MATCHING '{TEXT['p2']}'", "_asked_walks")
    return spark.sql("SELECT length, edge_path FROM _asked_walks")


@query("sql_pattern_transitions", "SELECT p, label, q, count(*) AS n_edges FROM (VALUES " + ", ".join(f"({p}, '{a}', {q})" for p, a, q in sorted(compile_pattern("h* s h*").moves)) + f""") AS t(p, label, q)
    JOIN ({VIEW_SQL['basket']}) ON list_contains(labels, label) GROUP BY p, label, q""")
def sql_pattern_transitions(spark, sf_dir):
    """The moves of a pattern, and how many edges can take each."""
    sqlsurface.register(spark)
    views.basket(spark, sf_dir).edges.select(F.explode("labels").alias("label")).groupBy("label").agg(F.count("*").alias("n_edges")).createOrReplaceTempView("_label_counts")
    return spark.sql("SELECT p, t.label, q, n_edges FROM pattern_transitions('h* s h*') t JOIN _label_counts c ON c.label = t.label")


@query("sql_nfa_accepts", "SELECT conv_id, regexp_full_match(string_agg(left(role, 1), '' ORDER BY turn), 's?(ua)+') AS accepted FROM conversations GROUP BY conv_id")
def sql_nfa_accepts(spark, sf_dir):
    sqlsurface.register(spark)
    spark.read.parquet(f"{sf_dir}/conversations.parquet").createOrReplaceTempView("_turns")
    return spark.sql("""SELECT conv_id, nfa_accepts('system? (user assistant)+', transform(array_sort(collect_list(struct(turn, role))), x -> x.role)) AS accepted
        FROM _turns GROUP BY conv_id""")


@query("graph_files_round_trip", " UNION ALL ".join(f"SELECT '{f}' AS form, edge_id, src, dst, array_to_string(labels, '+') AS labels FROM ({VIEW_SQL['basket']})" for f in ("csv", "json", "parquet")))
def graph_files_round_trip(spark, sf_dir):
    g, parts = views.basket(spark, sf_dir), []
    for form in ("csv", "json", "parquet"):
        path = fresh_folder(spark, form)
        io.write_graph(g, path, form)
        back = io.read_graph(spark, path, form, f"edge_id string, src long, dst long, labels {'string' if form == 'csv' else 'array<string>'}, cost long")
        parts.append(back.edges.select(F.lit(form).alias("form"), "edge_id", "src", "dst", F.array_join("labels", "+").alias("labels")))
    return union(parts)


@query("walk_files_by_run", " UNION ALL ".join(f"SELECT {i} AS run_id, * FROM ({walks('basket', P2, s, t)})" for i, (s, t) in enumerate(((0, 1), (100, 189)))))
def walk_files_by_run(spark, sf_dir):
    """Walks written in folders by run and read back."""
    g, path = views.basket(spark, sf_dir), fresh_folder(spark, "walks")
    pairs = spark.createDataFrame([(0, 0, 1), (1, 100, 189)], "run_id int, source long, target long")
    io.write_walks(emit_all(layer_forward(g, P2, pairs)).select("run_id", "length", "edge_path"), path, by=("run_id",))
    return spark.read.schema("length int, edge_path string, run_id int").parquet(path).select("run_id", "length", "edge_path")


@query("stream_handoff_equals_batch", walks("handoff", P1, 0, 1))
def stream_handoff_equals_batch(spark, sf_dir):
    """Events come as a stream; after each batch the graph of all events so far is searched again (new edges can only
    keep or shorten the answers), and the last answers stand for the whole."""
    events = drain(event_stream(spark, sf_dir).select("event_id", "user_id", "ts", "event_type", "value"), "append")
    return minimal_walks(views.handoff_of(events), P1, 0, 1).select("length", "edge_path")

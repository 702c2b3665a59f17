"""Named queries and their DuckDB oracles."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkengine.baselines import methods as base
from walkengine.core import dag as answer
from walkengine.core import local
from walkengine.core.cheapest import cheapest_walks
from walkengine.core.search import (
    Layers, answer_edges, back_links, emit_all, layer_forward, min_length, minimal_lengths_from, minimal_walks, minimal_walks_batch, pair,
)
from walkengine.graph import views
from walkengine.graph.model import LabeledGraph
from walkengine.graph.views import VIEW_SQL
from walkengine.lang.automata import Nfa, compile_pattern, determinize, inductive_nfa
from walkengine.lang.patterns import parse_pattern
from walkengine.operators import around, workloads
from walkengine.operators.automata import P1, P2, P4, PATTERNS, TEXT
from walkengine.operators.oracles import cheapest, ranked, runs, search, walks
from walkengine.session import staged
from walkengine.streaming import queries as streams

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

#: End points of the basket workloads.
FROM, TO = 100, 1899


def query(name: str, sql: str | None = None):
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return keep


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minimal_walks(views.basket(spark, sf_dir), P2, 100, 189)


def queries() -> dict[str, Query]:
    return QUERIES | workloads.QUERIES | around.QUERIES | streams.QUERIES


def oracle_sql() -> dict[str, str]:
    return ORACLES | workloads.ORACLES | around.ORACLES | streams.ORACLES


def _run(spark: SparkSession, sf_dir: str, view: str = "basket", nfa: Nfa = P2, source=FROM, target=TO) -> Layers:
    g = views.VIEWS[view](spark, sf_dir)
    return layer_forward(g, nfa, pair(g, source, target))


# --- graphs -----------------------------------------------------------------------------------------------------------

for _view, _of in (views.VIEWS | {"demo": views.turns}).items():  # the small graphs of a table stand for the worked example, which has none
    query(
        f"graph_{_view}_edges",
        f"""SELECT edge_id::VARCHAR AS edge_id, src::VARCHAR AS src, dst::VARCHAR AS dst, array_to_string(list_sort(labels), ',') AS labels, cost
        FROM ({VIEW_SQL["turns" if _view == "demo" else _view]})""",
    )(
        lambda spark, sf_dir, of=_of: of(spark, sf_dir).edges.select(
            F.col("edge_id").cast("string"), F.col("src").cast("string"), F.col("dst").cast("string"), F.array_join(F.array_sort("labels"), ",").alias("labels"), "cost"
        )
    )

_SIZED = ("basket", "trade", "handoff", "session", "chat", "geo", "supply", "links", "docs")


@query("graph_size_report", " UNION ALL ".join(
    f"""SELECT '{v}' AS view, (SELECT count(*) FROM (SELECT src::VARCHAR AS x FROM g UNION SELECT dst::VARCHAR FROM g)) AS n_vertices,
    (SELECT count(*) FROM g) AS n_edges, (SELECT sum(len(labels))::BIGINT FROM g) AS n_labels,
    (SELECT count(*) FROM (SELECT src::VARCHAR AS x FROM g UNION SELECT dst::VARCHAR FROM g)) + (SELECT count(*) + sum(len(labels))::BIGINT FROM g) AS graph_size
    FROM (SELECT 1) CROSS JOIN (SELECT 1)""".replace(" g)", f" ({VIEW_SQL[v]}))").replace("FROM g UNION", f"FROM ({VIEW_SQL[v]}) UNION") for v in _SIZED
))
def graph_size_report(spark, sf_dir):
    out = None
    for v in _SIZED:
        one = views.VIEWS[v](spark, sf_dir).size().select(F.lit(v).alias("view"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@query("in_positions_basket", f"SELECT edge_id, dst, row_number() OVER (PARTITION BY dst ORDER BY edge_id) - 1 AS in_pos FROM ({VIEW_SQL['basket']})")
def in_positions_basket(spark, sf_dir):
    return views.basket(spark, sf_dir).in_positions().select("edge_id", "dst", "in_pos")


@query("degree_top10", f"SELECT dst AS vertex, count(*) AS in_degree FROM ({VIEW_SQL['basket']}) GROUP BY dst ORDER BY in_degree DESC, vertex LIMIT 10")
def degree_top10(spark, sf_dir):
    return views.basket(spark, sf_dir).edges.groupBy(F.col("dst").alias("vertex")).agg(F.count("*").alias("in_degree")).orderBy(F.desc("in_degree"), "vertex").limit(10)


@query("label_histogram_cube", f"""SELECT list_contains(labels, 'h') AS h, list_contains(labels, 's') AS s, count(*) AS n_edges
    FROM ({VIEW_SQL['basket']}) GROUP BY CUBE (list_contains(labels, 'h'), list_contains(labels, 's'))""")  # fmt: skip
def label_histogram_cube(spark, sf_dir):
    e = views.basket(spark, sf_dir).edges.select(F.array_contains("labels", "h").alias("h"), F.array_contains("labels", "s").alias("s"))
    return e.cube("h", "s").agg(F.count("*").alias("n_edges"))


# --- walks ------------------------------------------------------------------------------------------------------------

_DEMO_WALKS = "SELECT * FROM (VALUES ('e2>e4>e8', 3, 0), ('e1>e5>e8', 1, 1), ('e1>e6>e8', 2, 2), ('e2>e3>e7', 2, 3)) AS t(edge_path, multiplicity, rank)"


@query("demo_walks", "SELECT edge_path, multiplicity::VARCHAR AS multiplicity, 3 AS length FROM (" + _DEMO_WALKS + ")")
def demo_walks(spark, sf_dir):
    w = minimal_walks(views.demo(spark), P1, "A", "B", multiplicity="words")
    return w.select("edge_path", F.col("multiplicity").cast("string").alias("multiplicity"), "length")


def _states(rows: DataFrame, mask: str, n: int) -> DataFrame:
    states = F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("state")
    return rows.select("*", states).where(F.col(mask).bitwiseAND(F.expr("shiftleft(1L, state)")) != 0)


@query("demo_annotation", """SELECT * FROM (VALUES ('A', 0, 0), ('C', 0, 1), ('C', 1, 2), ('D', 0, 1), ('D', 1, 1), ('E', 0, 2), ('E', 1, 2), ('B', 0, 2), ('B', 1, 3))
    AS t(vertex, state, level)""")  # fmt: skip
def demo_annotation(spark, sf_dir):
    return _states(_run(spark, sf_dir, "demo", P1, "A", "B").reach, "mask", P1.n).select("vertex", "state", "level")


def _tree(layers: Layers) -> DataFrame:
    return emit_all(layers, keep_inner=True)


@query("demo_tree", """SELECT * FROM (VALUES ('', 'B', 0), ('e8', 'E', 1), ('e7', 'C', 1), ('e4>e8', 'D', 2), ('e5>e8', 'C', 2), ('e6>e8', 'C', 2), ('e3>e7', 'D', 2),
    ('e2>e4>e8', 'A', 3), ('e1>e5>e8', 'A', 3), ('e1>e6>e8', 'A', 3), ('e2>e3>e7', 'A', 3)) AS t(suffix, vertex, depth)""")  # fmt: skip
def demo_tree(spark, sf_dir):
    return _tree(_run(spark, sf_dir, "demo", P1, "A", "B")).select(F.col("edge_path").alias("suffix"), "vertex", F.col("length").alias("depth"))


for _name, _nfa in PATTERNS.items():
    query(f"basket_walks_{_name}", walks("basket", _nfa, FROM, TO))(
        lambda spark, sf_dir, nfa=_nfa: minimal_walks(views.basket(spark, sf_dir), nfa, FROM, TO).select("length", "edge_path")
    )

for _name, _view, _nfa, _s, _t in (
    ("trade_walks_p1", "trade", P1, "C:1001", "S:99"), ("handoff_walks_p1", "handoff", P1, 0, 1), ("cycle_walks", "basket", P1, 10, 10), ("no_walks", "trade", P4, "C:0", "C:1"),
):
    query(_name, walks(_view, _nfa, _s, _t, 5 if _view == "trade" else 8))(
        lambda spark, sf_dir, v=_view, nfa=_nfa, s=_s, t=_t: minimal_walks(views.VIEWS[v](spark, sf_dir), nfa, s, t).select("length", "edge_path")
    )


@query("zero_length_walk", "SELECT 0 AS length, '' AS edge_path, '10' AS vertex_path")
def zero_length_walk(spark, sf_dir):
    return minimal_walks(views.basket(spark, sf_dir), "(h|s)*", 10, 10)


@query("geo_walks", walks("geo", compile_pattern("in in has has"), "S:1", "N:3", 6).replace("'N:3'", "'C:3'"))
def geo_walks(spark, sf_dir):
    return minimal_walks(views.geo(spark, sf_dir), "in in has has", "S:1", "C:3").select("length", "edge_path")


@query("basket_levels", f"""{search('basket', P2, FROM)}, stop AS (SELECT min(lv) AS l FROM firsts WHERE v = {TO} AND q = 1)
    SELECT v AS vertex, q AS state, lv::INT AS level FROM firsts, stop WHERE lv <= stop.l""")  # fmt: skip
def basket_levels(spark, sf_dir):
    return _states(_run(spark, sf_dir).reach, "mask", P2.n).select("vertex", "state", "level")


@query("basket_links", f"""{search('basket', P2, FROM)}, stop AS (SELECT min(lv) AS l FROM firsts WHERE v = {TO} AND q = 1)
    SELECT DISTINCT b.lv::INT AS level, e.dst AS vertex, b.q AS state, e.edge_id FROM firsts a JOIN e ON e.src = a.v JOIN d ON d.p = a.q AND list_contains(e.labels, d.l)
    JOIN firsts b ON b.v = e.dst AND b.q = d.q AND b.lv = a.lv + 1, stop WHERE b.lv <= stop.l""")  # fmt: skip
def basket_links(spark, sf_dir):
    return _states(back_links(_run(spark, sf_dir)), "dst_mask", P2.n).select("level", F.col("dst").alias("vertex"), "state", "edge_id")


_PAIRS = ((1, 0, 1), (2, 100, 189), (3, 100, 1899), (4, 10, 10))


def _pairs(spark) -> DataFrame:
    return spark.createDataFrame(list(_PAIRS), "run_id int, source long, target long")


def _each(select: str) -> str:
    return " UNION ALL ".join(f"SELECT * FROM ({runs('basket', P2, s, t)} {select.format(r=r, s=s, t=t)})" for r, s, t in _PAIRS)


@query("min_length_pairs", _each("SELECT {r} AS run_id, {s}::BIGINT AS source, {t}::BIGINT AS target, (SELECT max(l) FROM lam)::INT AS length"))
def min_length_pairs(spark, sf_dir):
    return min_length(views.basket(spark, sf_dir), P2, _pairs(spark)).select("run_id", "source", "target", "length")


@query("exists_pairs", _each("SELECT {r} AS run_id, (SELECT count(*) FROM lam) > 0 AS found"))
def exists_pairs(spark, sf_dir):
    return min_length(views.basket(spark, sf_dir), P2, _pairs(spark)).select("run_id", F.col("length").isNotNull().alias("found"))


@query("batch_pairs", _each("SELECT DISTINCT {r} AS run_id, length::INT AS length, edge_path FROM walks"))
def batch_pairs(spark, sf_dir):
    return minimal_walks_batch(views.basket(spark, sf_dir), P2, _pairs(spark)).select("run_id", "length", "edge_path")


# --- variants ---------------------------------------------------------------------------------------------------------


def _counts(g: LabeledGraph, targets: DataFrame | None = None) -> DataFrame:
    layers, _ = minimal_lengths_from(g, P2, FROM, targets)
    return answer.totals(answer.build(layers)).select(
        F.col("target").alias("vertex"), "length", F.col("n_walks").cast("string").alias("n_walks")
    )


_ALL = f"{runs('basket', P2, FROM, None)} SELECT target AS vertex, length::INT AS length, count(DISTINCT edge_path)::VARCHAR AS n_walks FROM walks"


@query("walks_to_all_targets", _ALL + " GROUP BY ALL")
def walks_to_all_targets(spark, sf_dir):
    return _counts(views.basket(spark, sf_dir))


@query("walks_to_target_list", _ALL + " WHERE target IN (1, 10, 189, 1899) GROUP BY ALL")
def walks_to_target_list(spark, sf_dir):
    wanted = spark.createDataFrame([(x,) for x in (1, 10, 189, 1899)], "target long")
    return _counts(views.basket(spark, sf_dir), wanted)


@query("cheapest_walks_qty", cheapest("basket", P2, 0, 1, "cost", 20))
def cheapest_walks_qty(spark, sf_dir):
    return cheapest_walks(views.basket(spark, sf_dir), P2, 0, 1).select("cost", "length", "edge_path")


@query("cheapest_walks_ties", cheapest("basket", P2, FROM, TO, "ceil(cost / 10)::BIGINT", 10))
def cheapest_walks_ties(spark, sf_dir):
    g = views.basket(spark, sf_dir).edges.withColumn("cost", F.ceil(F.col("cost") / 10).cast("long"))
    return cheapest_walks(LabeledGraph(g), P2, FROM, TO).select("cost", "length", "edge_path")


@query("walk_multiplicity_words", f"{runs('basket', P2, FROM, TO)} SELECT edge_path, count(*)::VARCHAR AS multiplicity FROM walks GROUP BY edge_path")
def walk_multiplicity_words(spark, sf_dir):
    w = minimal_walks(views.basket(spark, sf_dir), P2, FROM, TO, multiplicity="words")
    return w.select("edge_path", F.col("multiplicity").cast("string").alias("multiplicity"))


_BY_STATES = runs("basket", P2, FROM, TO).replace("w(target, l, v, q, lv, path) AS (", "w(target, l, v, q, lv, path, states) AS (").replace("SELECT target, l, v, q, lv, '' FROM", "SELECT target, l, v, q, lv, '', q::VARCHAR FROM").replace(
    "ELSE e.edge_id || '>' || w.path END\n", "ELSE e.edge_id || '>' || w.path END, f.q || w.states\n"
).replace("path AS edge_path FROM w", "path AS edge_path, states FROM w")


@query("walk_multiplicity_states", f"{_BY_STATES} SELECT edge_path, count(DISTINCT states)::VARCHAR AS multiplicity FROM walks GROUP BY edge_path")
def walk_multiplicity_states(spark, sf_dir):
    w = minimal_walks(views.basket(spark, sf_dir), P2, FROM, TO, multiplicity="states")
    return w.select("edge_path", F.col("multiplicity").cast("string").alias("multiplicity"))


@query("total_runs", f"{runs('basket', P2, FROM, TO)} SELECT target, length::INT AS length, count(*)::VARCHAR AS n_runs FROM walks GROUP BY ALL")
def total_runs(spark, sf_dir):
    return answer.total_runs(_run(spark, sf_dir)).select("target", "length", F.col("n_runs").cast("string").alias("n_runs"))


@query("regex_vs_position", " UNION ALL ".join(f"SELECT '{c}' AS construction, * FROM ({walks('basket', P1, FROM, TO)})" for c in ("inductive", "position")))
def regex_vs_position(spark, sf_dir):
    g = views.basket(spark, sf_dir)
    both = [minimal_walks(g, TEXT["p1"], FROM, TO, construction=c).select(F.lit(c).alias("construction"), "length", "edge_path") for c in ("inductive", "position")]
    return both[0].unionByName(both[1])


@query("eps_parallel", "SELECT c_custkey::VARCHAR AS edge_path FROM customer WHERE c_nationkey = 0 AND c_mktsegment = 'BUILDING' AND c_acctbal >= 5000")
def eps_parallel(spark, sf_dir):
    """Customers as parallel edges from nation to segment: a spontaneous move never repeats one of them."""
    customer = spark.read.parquet(f"{sf_dir}/customer.parquet")
    a = F.filter(F.array(F.when(F.col("c_acctbal") >= 5000, F.lit("a"))), lambda x: x.isNotNull())
    edges = customer.select(F.col("c_custkey").cast("string").alias("edge_id"), F.col("c_nationkey").cast("string").alias("src"), F.col("c_mktsegment").alias("dst"), a.alias("labels"))
    return minimal_walks(LabeledGraph(edges), Nfa.of(3, [(0, "a", 1)], [0], [2], [(1, 2)]), "0", "BUILDING").select("edge_path")


_RANKED = ranked("basket", P2, FROM, TO)


def _dag(spark, sf_dir, **where) -> answer.AnswerDag:
    return answer.build(_run(spark, sf_dir, **where))


@query("page_2_of_7", f"{_RANKED} SELECT rank, edge_path FROM ranked WHERE rank BETWEEN 7 AND 13")
def page_2_of_7(spark, sf_dir):
    return answer.page(_dag(spark, sf_dir), 7, 7).select("rank", "edge_path")


@query("walk_at_rank", f"{_RANKED} SELECT rank, edge_path FROM ranked WHERE rank = 12")
def walk_at_rank(spark, sf_dir):
    return answer.page(_dag(spark, sf_dir), 12, 1).select("rank", "edge_path")


@query("walk_sample_ranks", f"{_RANKED} SELECT rank, edge_path FROM ranked WHERE rank IN (1, 5, 8, 21)")
def walk_sample_ranks(spark, sf_dir):
    return answer.walks_at(_dag(spark, sf_dir), spark.createDataFrame([(1,), (5,), (8,), (21,)], "rank long")).select("rank", "edge_path")


for _method in ("scan", "pointer"):
    query(f"next_walk_{_method}", f"{_RANKED} SELECT rank, edge_path FROM ranked")(
        lambda spark, sf_dir, method=_method: local.iterate_next(_run(spark, sf_dir), method).select("rank", "edge_path")
    )


@query("walks_emitted_lazily", f"{_RANKED} SELECT rank, edge_path FROM ranked")
def walks_emitted_lazily(spark, sf_dir):
    return local.emit_local(_run(spark, sf_dir)).select("rank", "edge_path")


@query("walk_deltas", f"""{_RANKED}, x AS (SELECT rank, list_reverse(string_split(edge_path, '>')) AS p FROM ranked),
    y AS (SELECT rank, p, lag(p) OVER (ORDER BY rank) AS o FROM x),
    z AS (SELECT rank, p, CASE WHEN o IS NULL THEN 0 ELSE len(list_filter(range(1, len(p) + 1), lambda k: p[1:k] = o[1:k])) END AS kept FROM y)
    SELECT rank, kept::BIGINT AS kept, array_to_string(list_reverse(p[kept + 1:]), '>') AS new_edges FROM z""")
def walk_deltas(spark, sf_dir):
    return local.walk_deltas(_run(spark, sf_dir))


@query("resumable_links", f"""{search('basket', P2, FROM)}, stop AS (SELECT min(lv) AS l FROM firsts WHERE v = {TO} AND q = 1),
    x AS (SELECT DISTINCT b.lv::INT AS level, e.dst AS dst, b.q AS state, e.edge_id FROM firsts a JOIN e ON e.src = a.v JOIN d ON d.p = a.q AND list_contains(e.labels, d.l)
    JOIN firsts b ON b.v = e.dst AND b.q = d.q AND b.lv = a.lv + 1, stop WHERE b.lv <= stop.l)
    SELECT level, dst, state, edge_id, lead(edge_id) OVER (PARTITION BY level, dst, state ORDER BY edge_id) AS next_edge FROM x""")  # fmt: skip
def resumable_links(spark, sf_dir):
    return local.resumable(back_links(_run(spark, sf_dir))).select("level", "dst", "state", "edge_id", "next_edge")


_FIVE = f"""WITH e AS MATERIALIZED (SELECT * FROM ({VIEW_SQL['trade']}) WHERE list_contains(labels, 'h') OR list_contains(labels, 's')),
n0 AS (SELECT 'C:1001' AS v, 1::HUGEINT AS n), """ + ", ".join(f"n{i} AS (SELECT e.dst AS v, sum(n)::HUGEINT AS n FROM n{i - 1} JOIN e ON e.src = v GROUP BY e.dst)" for i in range(1, 6))


@query("trade_walk_count_p4", f"{_FIVE} SELECT v AS target, 5 AS length, n::VARCHAR AS n_walks FROM n5 WHERE v = 'S:99'")
def trade_walk_count_p4(spark, sf_dir):
    d = _dag(spark, sf_dir, view="trade", nfa=P4, source="C:1001", target="S:99")
    return answer.totals(d).select("target", "length", F.col("n_walks").cast("string").alias("n_walks"))


# --- baselines --------------------------------------------------------------------------------------------------------

@query("baseline_product_all_counts", f"{runs('basket', P2, FROM, TO)} SELECT edge_path, count(*) AS copies FROM walks GROUP BY edge_path")
def baseline_product_all_counts(spark, sf_dir):
    return base.product_paths(_run(spark, sf_dir)).groupBy("edge_path").agg(F.count("*").alias("copies"))


_SET = f"{runs('basket', P2, FROM, TO)} SELECT DISTINCT edge_path FROM walks"


@query("baseline_product_distinct", _SET)
def baseline_product_distinct(spark, sf_dir):
    return base.product_distinct(_run(spark, sf_dir)).select("edge_path")


@query("baseline_simple_single_label", walks("basket", P1, FROM, TO).replace("AS MATERIALIZED (SELECT * FROM", "AS MATERIALIZED (SELECT edge_id, src, dst, labels[:1] AS labels, cost FROM").replace("SELECT DISTINCT length::INT AS length, edge_path", "SELECT DISTINCT edge_path"))
def baseline_simple_single_label(spark, sf_dir):
    edges = views.basket(spark, sf_dir).edges.withColumn("labels", F.slice("labels", 1, 1))
    return base.simple_walks(LabeledGraph(edges), P1, FROM, TO)


@query("baseline_cross_section", f"{runs('basket', P2, FROM, TO)}, s AS (SELECT DISTINCT edge_path FROM walks) SELECT edge_path, row_number() OVER (ORDER BY string_split(edge_path, '>')) - 1 AS rank FROM s")
def baseline_cross_section(spark, sf_dir):
    return base.cross_section(views.basket(spark, sf_dir), P2, FROM, TO).select("rank", "edge_path")


@query("baseline_full_tree", f"""{runs('basket', P2, FROM, TO)}
    SELECT DISTINCT path AS suffix, v AS vertex, (l - lv)::INT AS depth FROM w SEMI JOIN (SELECT 1) ON true
    WHERE EXISTS (SELECT 1 FROM walks WHERE suffix(edge_path, path))""")  # fmt: skip
def baseline_full_tree(spark, sf_dir):
    return _tree(_run(spark, sf_dir)).select(F.col("edge_path").alias("suffix"), "vertex", F.col("length").alias("depth"))


@query("baseline_determinize", _SET)
def baseline_determinize(spark, sf_dir):
    return base.determinized_walks(views.basket(spark, sf_dir), P2, FROM, TO)


@query("baseline_sql_recursive", walks("basket", P2, 0, 1))
def baseline_sql_recursive(spark, sf_dir):
    g = views.basket(spark, sf_dir)
    return base.recursive_sql(g, P2, 0, 1, min_length(g, P2, pair(g, 0, 1)).first()["length"] or 0)


@query("baseline_brute_force_demo", f"{runs('turns', P1, 'S')} SELECT DISTINCT target, length::INT AS length, edge_path FROM walks")
def baseline_brute_force_demo(spark, sf_dir):
    """All targets of every conversation's own small graph; a least walk has at most vertices times states edges."""
    edges = views.turns(spark, sf_dir).edges.select(F.substring_index("dst", ":", 1).alias("conv"), "edge_id", "src", "dst", "labels")

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        own, out = list(rows[["edge_id", "src", "dst", "labels"]].itertuples(index=False, name=None)), []
        for target in sorted(set(rows["dst"])):
            length, found = base.brute_force(own, P1, "S", target, P1.n * (rows["dst"].nunique() + 1))
            out += [(target, length, ">".join(p)) for p in found]
        return pd.DataFrame(out, columns=["target", "length", "edge_path"])

    return edges.groupBy("conv").applyInPandas(run, "target string, length int, edge_path string")


for _option in ({"compact": False}, {"merge": "scan"}):
    query("baseline_uncompacted" if "compact" in _option else "baseline_scan_merge", f"{_RANKED} SELECT rank, edge_path FROM ranked")(
        lambda spark, sf_dir, option=_option: local.emit_local(_run(spark, sf_dir), **option).select("rank", "edge_path")
    )


# --- measures ---------------------------------------------------------------------------------------------------------


@query("measure_product_pairs", f"""{search('basket', P2, FROM)}, stop AS (SELECT min(lv) AS l FROM firsts WHERE v = {TO} AND q = 1)
    SELECT count(*) AS n_pairs, (SELECT count(*) FROM (SELECT src FROM e UNION SELECT dst FROM e)) * 2 AS bound FROM firsts, stop WHERE lv <= stop.l""")  # fmt: skip
def measure_product_pairs(spark, sf_dir):
    g = views.basket(spark, sf_dir)
    met = _run(spark, sf_dir).reach.agg(F.coalesce(F.sum(F.bit_count("mask")), F.lit(0)).cast("long").alias("n_pairs"))
    return met.crossJoin(g.vertices().agg((F.count("*") * P2.n).alias("bound")))


_LINKED = f"""{search('basket', P2, FROM)}, stop AS (SELECT min(lv) AS l FROM firsts WHERE v = {TO} AND q = 1),
    x AS (SELECT b.lv, e.edge_id, e.dst, b.q, d.l AS label, a.q AS p FROM firsts a JOIN e ON e.src = a.v JOIN d ON d.p = a.q AND list_contains(e.labels, d.l)
    JOIN firsts b ON b.v = e.dst AND b.q = d.q AND b.lv = a.lv + 1, stop WHERE b.lv <= stop.l)"""


@query("measure_link_rows", f"""{_LINKED} SELECT count(DISTINCT (edge_id, lv)) AS n_links,
    (SELECT count(*) FROM e WHERE list_contains(labels, 'h') OR list_contains(labels, 's')) * 5 AS bound FROM x""")  # fmt: skip
def measure_link_rows(spark, sf_dir):
    layers = _run(spark, sf_dir)
    links = back_links(layers)
    bound = layers.edges.agg((F.count("*") * len(P2.moves)).alias("bound"))
    return links.agg(F.count("*").alias("n_links")).crossJoin(bound)


@query("measure_max_predecessors", f"{_LINKED} SELECT max(n) AS most FROM (SELECT count(*) AS n FROM x GROUP BY lv, edge_id, q)")
def measure_max_predecessors(spark, sf_dir):
    layers = _run(spark, sf_dir)
    links = back_links(layers)
    bit = {a: 1 << i for i, a in enumerate(layers.alphabet)}
    counts = []
    for q in range(P2.n):
        n = F.lit(0)
        for p, a, r in P2.moves:
            if r == q:
                n = n + F.when((F.col("src_mask").bitwiseAND(F.lit(1 << p)) != 0) & (F.col("lab").bitwiseAND(F.lit(bit[a])) != 0), 1).otherwise(0)
        counts.append(F.when(F.col("dst_mask").bitwiseAND(F.lit(1 << q)) != 0, n).otherwise(0))
    return links.agg(F.max(F.greatest(*counts)).cast("long").alias("most"))


@query("measure_copies_per_walk", f"{runs('basket', P2, FROM, TO)} SELECT count(DISTINCT edge_path)::VARCHAR AS n_walks, count(*)::VARCHAR AS n_runs FROM walks")
def measure_copies_per_walk(spark, sf_dir):
    layers = _run(spark, sf_dir)
    answers = answer_edges(layers)
    both = answer.totals(answer.build(layers, answers)).join(answer.total_runs(layers, answers), ["run_id", "target", "length"])
    return both.agg(F.coalesce(F.sum("n_walks"), F.lit(0)).cast("string").alias("n_walks"), F.coalesce(F.sum("n_runs"), F.lit(0)).cast("string").alias("n_runs"))


@query("measure_tree_nodes", f"""{runs('basket', P2, FROM, TO)}, parts AS (SELECT DISTINCT edge_path, string_split(edge_path, '>') AS x FROM walks),
    nodes AS (SELECT DISTINCT x[i:] AS s FROM parts, range(1, 10) AS r(i) WHERE i <= len(x)) SELECT (count(*) + 1)::BIGINT AS n_nodes FROM nodes""")  # fmt: skip
def measure_tree_nodes(spark, sf_dir):
    return _tree(_run(spark, sf_dir)).agg(F.count("*").alias("n_nodes"))


@query("measure_lambda_histogram", f"SELECT length, count(*) AS n_targets FROM ({_ALL} GROUP BY ALL) GROUP BY length")
def measure_lambda_histogram(spark, sf_dir):
    _, lengths = minimal_lengths_from(views.basket(spark, sf_dir), P2, FROM)
    return lengths.groupBy("length").agg(F.count("*").alias("n_targets"))


@query("measure_delay", "SELECT * FROM (VALUES ('browse', true), ('compact', true), ('scan', true)) AS t(form, holds)")
def measure_delay(spark, sf_dir):
    """Most steps between two answers: of the constant-delay emitter within 4 (length + 1) (moves + states), whatever the
    graph; of the forms that browse in-edges or scan queues within the same times the largest in-degree."""
    layers = _run(spark, sf_dir)
    answers = answer_edges(layers)
    degree = layers.edges.groupBy("dst").count().agg(F.max("count").alias("degree"))
    bound = layers.ends.select(((F.col("level") + 1) * 4 * (len(P2.moves) + P2.n)).alias("bound")).crossJoin(degree)  # one row each
    out = None
    for name, option in {"compact": {}, "browse": {"compact": False}, "scan": {"merge": "scan"}}.items():
        one = local.emit_local(layers, answers=answers, **option).agg(F.coalesce(F.max("steps"), F.lit(0)).alias("most")).crossJoin(bound)
        limit = F.col("bound") if name == "compact" else F.col("bound") * F.col("degree")
        one = one.select(F.lit(name).alias("form"), (F.col("most") <= limit).alias("holds"))
        out = one if out is None else out.unionByName(one)
    return out


@query("measure_bounds_report", """SELECT * FROM (VALUES
    ('answers_each_once', true), ('dag_nodes_within_tree_nodes', true), ('link_rows_within_edges_times_moves', true), ('pairs_within_vertices_times_states', true),
    ('runs_not_below_walks', true), ('tree_nodes_within_walks_times_length', true)) AS t(claim, holds)""")  # fmt: skip
def measure_bounds_report(spark, sf_dir):
    """Every bound that the reference proves for the parts, as one row with whether it holds on this run."""
    layers = _run(spark, sf_dir)
    answers = answer_edges(layers)
    d = answer.build(layers, answers)
    tree, paths = staged(_tree(layers), "tree"), emit_all(layers, answers)
    one = lambda df, e: df.agg(e.cast("decimal(38,0)").alias("x")).first()["x"] or 0  # noqa: E731  single numbers
    pairs, vertices, edges = one(layers.reach, F.sum(F.bit_count("mask"))), one(LabeledGraph(layers.edges).vertices(), F.count("*")), one(layers.edges, F.count("*"))
    walks_, length = one(answer.totals(d), F.sum("n_walks")), one(layers.ends, F.max("level"))
    tree_nodes, found = one(tree, F.count("*")), paths.agg(F.count("*").alias("n"), F.countDistinct("edge_path").alias("k")).first()
    rows = [
        ("pairs_within_vertices_times_states", pairs <= vertices * P2.n), ("link_rows_within_edges_times_moves", one(back_links(layers), F.count("*")) <= edges * len(P2.moves)),
        ("tree_nodes_within_walks_times_length", tree_nodes <= walks_ * length + 1), ("dag_nodes_within_tree_nodes", one(d.nodes, F.count("*")) <= tree_nodes),
        ("runs_not_below_walks", one(answer.total_runs(layers, answers), F.sum("n_runs")) >= walks_), ("answers_each_once", found.n == found.k == walks_),
    ]
    return spark.createDataFrame(rows, "claim string, holds boolean")


@query("measure_pattern_sizes", """SELECT l_linenumber::INT AS k, count(*) AS n_lines, (l_linenumber + 2)::INT AS n_states, (2 ** (l_linenumber + 1))::INT AS n_determinized
    FROM lineitem GROUP BY l_linenumber""")  # fmt: skip
def measure_pattern_sizes(spark, sf_dir):
    """For each line number k, of the automaton for words with an s k edges before their end: states before and after
    determinising, which doubles them with every k."""

    @F.pandas_udf("n_states int, n_determinized int")
    def sizes(ks: pd.Series) -> pd.DataFrame:
        rows = []
        for k in ks:
            hs = lambda p, q: [(p, "h", q), (p, "s", q)]
            nfa = Nfa.of(k + 2, [*hs(0, 0), (0, "s", 1), *(m for i in range(1, k + 1) for m in hs(i, i + 1))], [0], [k + 1])
            rows.append((nfa.n, determinize(nfa).n))
        return pd.DataFrame(rows, columns=["n_states", "n_determinized"])

    lines = spark.read.parquet(f"{sf_dir}/lineitem.parquet").groupBy(F.col("l_linenumber").cast("int").alias("k")).agg(F.count("*").alias("n_lines"))
    return lines.withColumn("x", sizes("k")).select("k", "n_lines", "x.*")


@query("ladder_copies", "SELECT * FROM (VALUES (1, '2', '4'), (2, '4', '16'), (3, '8', '64'), (4, '16', '256')) AS t(k, n_walks, n_runs)")
def ladder_copies(spark, sf_dir):
    nfa, out = Nfa.of(1, [(0, "a", 0), (0, "b", 0)], [0], [0]), None
    for k in range(1, 5):
        g = views.ladder(spark, k)
        layers = layer_forward(g, nfa, pair(g, 0, k))
        d = answer.build(layers)
        one = answer.totals(d).join(answer.total_runs(layers), ["run_id", "target", "length"])
        one = one.select(F.lit(k).alias("k"), F.col("n_walks").cast("string").alias("n_walks"), F.col("n_runs").cast("string").alias("n_runs"))
        out = one if out is None else out.unionByName(one)
    return out


# --- words ------------------------------------------------------------------------------------------------------------


@query("chat_accepts_p6", """SELECT conv_id, regexp_full_match(string_agg(left(role, 1), '' ORDER BY turn), 's?(ua)+') AS accepted FROM conversations GROUP BY conv_id""")
def chat_accepts_p6(spark, sf_dir):
    """Each conversation is a path graph, so it fits if a walk leads from its start to its last turn."""
    g = views.chat(spark, sf_dir)
    last = spark.read.parquet(f"{sf_dir}/conversations.parquet").groupBy("conv_id").agg(F.max("turn").alias("turn"))
    pairs = last.select(F.col("conv_id").alias("run_id"), F.concat_ws(":", "conv_id", F.lit("start")).alias("source"), F.concat_ws(":", "conv_id", "turn").alias("target"))
    return min_length(g, "system? (user assistant)+", pairs).select(F.col("run_id").alias("conv_id"), F.col("length").isNotNull().alias("accepted"))


@query("session_accepts_p7", """SELECT user_id, regexp_matches(string_agg(left(event_type, 1), '' ORDER BY ts, event_id), 'vc+p') AS accepted FROM events GROUP BY user_id""")
def session_accepts_p7(spark, sf_dir):
    """A word is matched by a fold of the step expression over its label masks; no walk needs to be built."""
    return around.accepted_words(spark, sf_dir)


_ANY = "(click|error|purchase|signup|view)*"


@query("reduced_automata", """SELECT 15 AS n_inductive_closed, count(*) AS n_words, count(*) FILTER (regexp_matches(word, 'vc+p')) AS n_accepted, true AS same_language
    FROM (SELECT string_agg(left(event_type, 1), '' ORDER BY ts, event_id) AS word FROM events GROUP BY user_id)""")  # fmt: skip
def reduced_automata(spark, sf_dir):
    """The trimmed, closed automaton of a pattern, and whether its spontaneous form accepts the same of all users' words."""
    text = f"{_ANY} view click+ purchase {_ANY}"
    forms = {"closed": compile_pattern(text), "raw": inductive_nfa(parse_pattern(text))}

    @F.pandas_udf("closed boolean, raw boolean")
    def accepted(words: pd.Series) -> pd.DataFrame:
        return pd.DataFrame({name: [nfa.accepts(list(w)) for w in words] for name, nfa in forms.items()})

    word = F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))), lambda x: x["event_type"])
    words = spark.read.parquet(f"{sf_dir}/events.parquet").groupBy("user_id").agg(word.alias("word")).select(accepted("word").alias("x"))
    counts = words.agg(F.count("*").alias("n_words"), F.count_if("x.closed").alias("n_accepted"), F.bool_and(F.col("x.closed") == F.col("x.raw")).alias("same_language"))
    return counts.select(F.lit(forms["closed"].n).alias("n_inductive_closed"), "*")

import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from walkengine.baselines import methods as base
from walkengine.core import dag as answer
from walkengine.core import local
from walkengine.core.cheapest import cheapest_walks
from walkengine.core.runs import count_runs
from walkengine.core.search import (
    back_links, choose_plan, layer_forward, minimal_lengths_from, minimal_walks, minimal_walks_batch, minimal_walks_of_patterns, pair,
)
from walkengine.graph import views
from walkengine.graph.model import LabeledGraph
from walkengine.lang.automata import Nfa
from walkengine.operators import registry
from walkengine.operators.automata import P1, P2, P3
from walkengine.session import staged

SCHEMA = "edge_id string, src string, dst string, labels array<string>, cost long"
DEMO = {"e2>e4>e8": 3, "e1>e5>e8": 1, "e1>e6>e8": 2, "e2>e3>e7": 2}


def graph(spark, edges):
    return LabeledGraph(spark.createDataFrame([(*e, 1) if len(e) == 4 else e for e in edges], SCHEMA))


@pytest.fixture(scope="module")
def demo(spark):
    g = views.demo(spark)
    layers = layer_forward(g, P1, pair(g, "A", "B"))
    return g, layers, staged(back_links(layers), "links")


def test_worked_example(demo):
    g, _, _ = demo
    found = {r.edge_path: int(r.multiplicity) for r in minimal_walks(g, "h* s (h|s)*", "A", "B", multiplicity="words").collect()}
    assert found == DEMO
    other = {r.edge_path: int(r.multiplicity) for r in minimal_walks(g, P2, "A", "B", multiplicity="words").collect()}
    assert other.keys() == DEMO.keys() and sum(other.values()) == 11
    third = minimal_walks(g, P3, "A", "B", multiplicity="words").collect()
    assert len(third) == 2 and sum(int(r.multiplicity) for r in third) == 4


def test_levels_and_links(demo):
    _, layers, links = demo
    levels = {(r.vertex, q): r.level for r in layers.reach.collect() for q in range(2) if r.mask >> q & 1}
    assert levels == {("A", 0): 0, ("C", 0): 1, ("C", 1): 2, ("D", 0): 1, ("D", 1): 1, ("E", 0): 2, ("E", 1): 2, ("B", 0): 2, ("B", 1): 3}
    cells = {(r.dst, q, r.edge_id) for r in links.collect() for q in range(2) if r.dst_mask >> q & 1}
    assert cells == {("C", 0, "e1"), ("C", 1, "e3"), ("D", 0, "e2"), ("D", 1, "e2"), ("E", 0, "e4"), ("E", 0, "e5"), ("E", 1, "e4"), ("E", 1, "e6"), ("B", 0, "e7"), ("B", 1, "e8"), ("B", 1, "e7")}


def test_dag_ranks_pages_and_lazy_forms_agree(demo):
    _, layers, links = demo
    d = answer.build(layers)
    assert d.nodes.count() == 6 and int(answer.totals(d).first().n_walks) == 4
    assert int(answer.total_runs(layers).first().n_runs) == 8
    ranked = [r.edge_path for r in answer.page(d, 0, 10).orderBy("rank").collect()]
    pages = [r.edge_path for k in (0, 3) for r in answer.page(d, k, 3).orderBy("rank").collect()]
    assert ranked == pages and set(ranked) == set(DEMO)
    lazy = [r.edge_path for r in local.emit_local(layers).orderBy("rank").collect()]
    scan = [r.edge_path for r in local.iterate_next(layers, "scan").orderBy("rank").collect()]
    pointer = [r.edge_path for r in local.iterate_next(layers, "pointer").orderBy("rank").collect()]
    assert ranked == lazy == scan == pointer
    deltas = local.walk_deltas(layers).orderBy("rank").collect()
    path = []
    for r, full in zip(deltas, ranked):
        path = (r.new_edges.split(">") if r.new_edges else []) + (path[len(path) - r.kept :] if r.kept else [])
        assert ">".join(path) == full
    rows = local.resumable(links).collect()
    assert {(r.dst, r.state, r.edge_id): r.next_edge for r in rows}["B", 1, "e7"] == "e8"


def test_baselines_agree(demo):
    g, layers, _ = demo
    assert Counter(r.edge_path for r in base.product_paths(layers).collect()) == Counter(DEMO)
    assert {r.edge_path for r in base.product_distinct(layers).collect()} == set(DEMO)
    assert {r.edge_path for r in base.determinized_walks(g, P2, "A", "B").collect()} == set(DEMO)
    crossed = [r.edge_path for r in base.cross_section(g, P2, "A", "B").orderBy("rank").collect()]
    assert crossed == sorted(DEMO)
    assert {r.edge_path for r in base.recursive_sql(g, P2, "A", "B", 3).collect()} == set(DEMO)
    with pytest.raises(ValueError):
        base.simple_walks(g, P1, "A", "B")


def test_micro_graphs(spark):
    two = graph(spark, [("e1", "s", "t", ["a"]), ("e2", "s", "t", ["a"])])
    late = Nfa.of(3, [(0, "a", 1)], [0], [2], [(1, 2)])
    early = Nfa.of(3, [(1, "a", 2)], [0], [2], [(0, 1)])
    for pattern in ("a", late, early):
        assert {r.edge_path for r in minimal_walks(two, pattern, "s", "t").collect()} == {"e1", "e2"}
    loop = graph(spark, [("e1", "s", "s", ["a"])])
    assert [(r.length, r.edge_path) for r in minimal_walks(loop, "a*", "s", "s").collect()] == [(0, "")]
    assert [(r.length, r.edge_path) for r in minimal_walks(loop, "a+", "s", "s").collect()] == [(1, "e1")]
    assert minimal_walks(loop, "b", "s", "s").count() == 0
    assert minimal_walks(loop, Nfa.of(1, [], [], [0]), "s", "s").count() == 0
    assert minimal_walks(LabeledGraph(spark.createDataFrame([], SCHEMA)), "a", "s", "t").count() == 0


def _random(seed):
    r = random.Random(seed)
    n, vertices = r.randint(2, 4), [f"v{i}" for i in range(r.randint(2, 6))]
    edges = [(f"e{i:02}", r.choice(vertices), r.choice(vertices), r.sample(["a", "b"], r.randint(1, 2)), r.randint(1, 3)) for i in range(r.randint(3, 12))]
    moves = {(r.randrange(n), r.choice("ab"), r.randrange(n)) for _ in range(r.randint(2, 6))}
    eps = {(r.randrange(n), r.randrange(n)) for _ in range(seed % 3)}
    return edges, Nfa.of(n, moves, {0}, {n - 1}, eps), vertices[0], vertices[-1]


@pytest.mark.parametrize("seed", range(4))
def test_random_graphs_against_brute_force(spark, seed):
    edges, nfa, s, t = _random(seed)
    length, expected = base.brute_force([e[:4] for e in edges], nfa, s, t, 7)
    found = [r.edge_path for r in minimal_walks(graph(spark, edges), nfa, s, t).collect()]
    assert sorted(found) == sorted(">".join(p) for p in expected) and len(found) == len(set(found))


def test_cheapest_walks_with_ties(spark):
    g = graph(spark, [("a", "s", "t", ["x"], 3), ("b", "s", "m", ["x"], 1), ("c", "m", "t", ["x"], 2), ("d", "m", "t", ["x"], 5), ("e", "s", "t", ["y"], 1)])
    found = {(r.cost, r.length, r.edge_path) for r in cheapest_walks(g, "x+", "s", "t").collect()}
    assert found == {(3, 1, "a"), (3, 2, "b>c")}
    with pytest.raises(ValueError):
        cheapest_walks(graph(spark, [("a", "s", "t", ["x"], 0)]), "x", "s", "t")


def test_many_targets_and_batches_agree_with_single_runs(spark, demo):
    g, _, _ = demo
    layers, lengths = minimal_lengths_from(g, P1, "A")
    assert {r.target: r.length for r in lengths.collect()} == {"C": 2, "D": 1, "E": 2, "B": 3}
    counts = {r.target: int(r.n_walks) for r in answer.totals(answer.build(layers)).collect()}
    assert counts == {"C": 1, "D": 1, "E": 2, "B": 4}
    pairs = spark.createDataFrame([(1, "A", "B"), (2, "A", "E"), (3, "B", "A")], "run_id int, source string, target string")
    by = Counter(r.run_id for r in minimal_walks_batch(g, P1, pairs).collect())
    assert by == {1: 4, 2: 2}


def test_delay_does_not_grow_with_the_in_degree(spark):
    nfa, most = Nfa.of(1, [(0, "a", 0), (0, "b", 0)], [0], [0]), {}
    for noise in (0, 200):
        g = views.ladder(spark, 3, noise=noise)
        layers = layer_forward(g, nfa, pair(g, 0, 3))
        links = staged(back_links(layers), "links")
        assert links.count() == 6
        for compact in (True, False):
            most[noise, compact] = local.emit_local(layers, compact=compact).agg(F.max("steps")).first()[0]
    assert most[0, True] == most[200, True] and most[200, False] > 20 * most[200, True]


def test_next_walk_goes_on_to_the_last_walk(spark):
    g = graph(spark, [(f"{x}{i:02}", *ends, ["a"]) for x, ends in (("c", "sm"), ("d", "mt")) for i in range(33)])
    layers = layer_forward(g, Nfa.of(1, [(0, "a", 0)], [0], [0]), pair(g, "s", "t"))
    for method in ("scan", "pointer"):
        found = [r.edge_path for r in local.iterate_next(layers, method).collect()]
        assert len(found) == len(set(found)) == 33 * 33


def test_recursive_baseline_goes_as_deep_as_the_pair_needs(spark, tmp_path):
    for name, parts, expected in (("four", [0, 5, 6, 7, 1], 4), ("none", [0, 5], None)):
        rows = [(9, k, part, 3, 60000.0, "R", "O", 1) for k, part in enumerate(parts, 1)]
        columns = "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_extendedprice double, l_returnflag string, l_linestatus string, l_quantity int"
        spark.createDataFrame(rows, columns).write.parquet(str(tmp_path / name / "lineitem.parquet"))
        found = registry.QUERIES["baseline_sql_recursive"](spark, str(tmp_path / name)).collect()
        assert [r.length for r in found] == ([expected] if expected else [])


def test_level_loop_has_no_distinct_and_no_python(demo):
    _, _, links = demo
    plan = links.sparkSession.sql("SELECT 1")._jdf.queryExecution().toString()
    assert "Python" not in plan
    g, layers, _ = demo
    plan = back_links(layers)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "CartesianProduct" not in plan and "Aggregate" not in plan


def test_edges_stay_in_their_buckets(spark, demo):
    _, layers, _ = demo
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = layers.reach.join(layers.edges, layers.reach.vertex == layers.edges.src)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    assert "Bucketed: true" in plan and plan.count("Exchange") == 1


def test_plans_patterns_runs_tokens_and_lazy_closure(spark, demo):
    g, layers, _ = demo
    assert choose_plan(g, P1) == "general" and choose_plan(g, P2) == "general"
    single = LabeledGraph(g.edges.withColumn("labels", F.slice("labels", 1, 1)))
    assert choose_plan(single, P1) == "simple" and choose_plan(single, P2) == "general"
    both = [sorted(map(tuple, minimal_walks(single, P1, "A", "B", plan=p).select("length", "edge_path", "vertex_path").collect())) for p in ("auto", "general")]
    assert both[0] == both[1] != []
    by = Counter(r.pattern for r in minimal_walks_of_patterns(g, {"one": P1, "two": P2, "three": P3}, "A", "B").collect())
    assert by == {"one": 4, "two": 4, "three": 2}
    after = {r.edge_path: int(r.multiplicity) for r in count_runs(spark.createDataFrame([(w,) for w in DEMO], "edge_path string"), g, P1).collect()}
    assert after == DEMO
    d = answer.build(layers)
    order = [r.edge_path for r in answer.page(d, 0, 10).orderBy("rank").collect()]
    assert [answer.rank_of(d, w.split(">")) for w in order] == [0, 1, 2, 3] and answer.rank_of(d, ["e1", "e7"]) is None
    two = graph(spark, [("e1", "s", "t", ["a"]), ("e2", "s", "t", ["a"]), ("e3", "t", "s", ["b"])])
    for pattern, s, t in (("(a|b)* a (b|())", "s", "t"), ("a? (b a)*", "t", "t"), ("(a b)+", "s", "s")):
        found = [sorted(r.edge_path for r in minimal_walks(two, pattern, s, t, eps=e).collect()) for e in ("eager", "lazy")]
        assert found[0] == found[1] != []


def test_cross_section_takes_only_edges_of_answers_into_its_task(spark, monkeypatch):
    edges = [("a", "s", "m", ["x"]), ("b", "s", "m", ["x"]), ("c", "m", "t", ["x"]), *((f"n{i:03}", "s", f"v{i}", ["x"]) for i in range(200)), *((f"o{i:03}", "m", f"v{i}", ["x"]) for i in range(200))]
    found = base.cross_section(graph(spark, edges), "x x", "s", "t").orderBy("rank").collect()
    assert [(r.rank, r.edge_path) for r in found] == [(0, "a>c"), (1, "b>c")]
    assert max(r.steps for r in found) <= 3 * 2 * 3  # edges, moves and levels: 400 useless edges are never looked at


def test_recursive_baseline_goes_beyond_spark_s_limit_of_rows(spark):
    edges = [("a", "s", "m", ["x"]), ("c", "m", "t", ["x"]), *((f"n{i:03}", "s", f"v{i}", ["x"]) for i in range(60)), *((f"o{i:03}", f"v{i}", f"w{i}", ["x"]) for i in range(60))]
    before = spark.conf.get("spark.sql.cteRecursionRowLimit")
    spark.conf.set("spark.sql.cteRecursionRowLimit", "50")
    try:
        found = base.recursive_sql(graph(spark, edges), Nfa.of(1, [(0, "x", 0)], [0], [0]), "s", "t", 2).collect()
        assert spark.conf.get("spark.sql.cteRecursionRowLimit") == "50"
    finally:
        spark.conf.set("spark.sql.cteRecursionRowLimit", before)
    assert [(r.length, r.edge_path) for r in found] == [(2, "a>c")]

"""Operations around walks: reached edges, answers compared, attributes joined late, event windows, word matching."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkengine.core.search import minimal_lengths_from, minimal_walks
from walkengine.graph import views
from walkengine.graph.views import VIEW_SQL
from walkengine.lang.automata import compile_pattern
from walkengine.lang.codegen import label_mask, step_expr
from walkengine.operators.automata import P1, P2, P3
from walkengine.operators.oracles import runs, search
from walkengine.session import read_table

EVENT_TYPES = ("click", "error", "purchase", "signup", "view")


def accepts(words: DataFrame, pattern: str, alphabet: tuple[str, ...], column: str = "labels") -> DataFrame:
    """``words`` with ``accepted``: whether the array of labels is in the pattern's language."""
    nfa = compile_pattern(pattern, alphabet)
    start, final = F.lit(nfa.mask(nfa.initial)).cast("long"), F.lit(nfa.mask(nfa.final)).cast("long")
    masks = F.transform(column, lambda x: label_mask(F.array(x), nfa.alphabet))
    end = F.aggregate(masks, start, lambda states, lab: step_expr(states, lab, nfa, nfa.alphabet))
    return words.withColumn("accepted", end.bitwiseAND(final) != 0)


def accepted_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = read_table(spark, sf_dir, "events")
    word = F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))), lambda x: x["event_type"])
    words = events.groupBy("user_id").agg(word.alias("labels"))
    return accepts(words, ".* view click+ purchase .*", EVENT_TYPES).select("user_id", "accepted")


def edges_semi_reached(spark, sf_dir):
    g = views.basket(spark, sf_dir)
    layers, _ = minimal_lengths_from(g, P1, 100)
    return g.edges.join(layers.reach.select(F.col("vertex").alias("src")).distinct(), "src", "left_semi").select("edge_id", "src", "dst")


def targets_without_answer(spark, sf_dir):
    g = views.basket(spark, sf_dir)
    _, lengths = minimal_lengths_from(g, P1, 100)
    return g.vertices().join(lengths, F.col("vertex") == F.col("target"), "left_anti").select("vertex")


def common_answers(spark, sf_dir):
    g = views.basket(spark, sf_dir)
    return minimal_walks(g, P2, 100, 1899).select("edge_path").intersect(minimal_walks(g, P3, 100, 1899).select("edge_path"))


def answers_only_p2(spark, sf_dir):
    g = views.basket(spark, sf_dir)
    return minimal_walks(g, P2, 100, 1899).select("edge_path").exceptAll(minimal_walks(g, P3, 100, 1899).select("edge_path"))


def _lines(spark, sf_dir) -> DataFrame:
    lines = read_table(spark, sf_dir, "lineitem").withColumn("edge_id", views._line_key())
    return lines.select("edge_id", "l_shipdate", "l_extendedprice", "l_returnflag")


def _steps(spark, sf_dir) -> DataFrame:
    walks = minimal_walks(views.basket(spark, sf_dir), P2, 100, 1899)
    steps = walks.select("edge_path", F.posexplode(F.split("edge_path", ">")).alias("step", "edge_id"))
    return steps.join(_lines(spark, sf_dir), "edge_id")


def walk_edges_with_attributes(spark, sf_dir):
    cents = F.round(F.col("l_extendedprice") * 100).cast("long").alias("cents")
    return _steps(spark, sf_dir).select("edge_path", "step", "edge_id", "l_returnflag", F.date_format("l_shipdate", "yyyy-MM-dd").alias("shipped"), cents)


def walks_by_month_rollup(spark, sf_dir):
    rows = _steps(spark, sf_dir).select(F.year("l_shipdate").alias("year"), F.month("l_shipdate").alias("month"))
    counts = rows.rollup("year", "month").agg(F.count("*").alias("n_edges"))
    return counts.select(F.coalesce("year", F.lit(-1)).alias("year"), F.coalesce("month", F.lit(-1)).alias("month"), "n_edges")


def topk_walks_by_value(spark, sf_dir):
    total = F.sum(F.round(F.col("l_extendedprice") * 100).cast("long")).alias("cents")
    return _steps(spark, sf_dir).groupBy("edge_path").agg(total).orderBy(F.desc("cents"), "edge_path").limit(5)


def asof_next_event(spark, sf_dir):
    """For every error the next purchase of the same user at or after it: one window, no join."""
    later = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(0, W.unboundedFollowing)
    bought = F.first(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(later)
    rows = read_table(spark, sf_dir, "events").select("event_id", "event_type", F.coalesce(bought, F.lit(-1)).alias("next_purchase"))
    return rows.where("event_type = 'error'").select("event_id", "next_purchase")


def _events(spark, sf_dir) -> DataFrame:
    return read_table(spark, sf_dir, "events").withColumn("at", F.col("ts").cast("timestamp"))


def events_tumbling(spark, sf_dir):
    hour = F.date_trunc("hour", "ts")
    return read_table(spark, sf_dir, "events").groupBy(hour.alias("hour"), "event_type").agg(F.count("*").alias("n")).select(F.date_format("hour", "yyyy-MM-dd HH").alias("hour"), "event_type", "n")


def events_sliding(spark, sf_dir):
    w = F.window("at", "2 hours", "1 hour")
    return _events(spark, sf_dir).groupBy(w.alias("w")).agg(F.count("*").alias("n")).select(F.unix_seconds("w.start").alias("start"), "n")


def events_session_windows(spark, sf_dir):
    w = F.session_window("at", "30 minutes")
    return _events(spark, sf_dir).groupBy("user_id", w.alias("w")).agg(F.count("*").alias("n")).groupBy("user_id", "n").agg(F.count("*").alias("n_sessions"))


def events_props_json(spark, sf_dir):
    k = F.get_json_object("props", "$.k").cast("long")
    return read_table(spark, sf_dir, "events").groupBy("event_type").agg(F.sum(k).alias("sum_k"), F.max(k).alias("max_k"))


QUERIES = {f.__name__: f for f in (
    edges_semi_reached, targets_without_answer, common_answers, answers_only_p2, walk_edges_with_attributes, walks_by_month_rollup, topk_walks_by_value, asof_next_event,
    events_tumbling, events_sliding, events_session_windows, events_props_json,
)}

_LINE = f"(SELECT {views._KEY} AS edge_id, l_shipdate, l_extendedprice, l_returnflag FROM lineitem)"
_STEP = f"""{runs('basket', P2, 100, 1899)}, steps AS (SELECT edge_path, unnest(string_split(edge_path, '>')) AS edge_id, unnest(range(len(string_split(edge_path, '>')))) AS step
    FROM (SELECT DISTINCT edge_path FROM walks)), s AS (SELECT * FROM steps JOIN {_LINE} USING (edge_id))"""
_TWO = lambda op: f"SELECT * FROM ({runs('basket', P2, 100, 1899)} SELECT DISTINCT edge_path FROM walks) {op} SELECT * FROM ({runs('basket', P3, 100, 1899)} SELECT DISTINCT edge_path FROM walks)"
ORACLES = {
    "edges_semi_reached": f"{search('basket', P1, 100, 12)} SELECT edge_id, src, dst FROM e WHERE src IN (SELECT v FROM firsts)",
    "targets_without_answer": f"{search('basket', P1, 100, 12)} SELECT v AS vertex FROM (SELECT src AS v FROM e UNION SELECT dst FROM e) WHERE v NOT IN (SELECT v FROM firsts WHERE q = 1)",
    "common_answers": _TWO("INTERSECT"),
    "answers_only_p2": _TWO("EXCEPT"),
    "walk_edges_with_attributes": f"{_STEP} SELECT edge_path, step::INT AS step, edge_id, l_returnflag, strftime(l_shipdate, '%Y-%m-%d') AS shipped, round(l_extendedprice * 100)::BIGINT AS cents FROM s",
    "walks_by_month_rollup": f"{_STEP}, m AS (SELECT year(l_shipdate)::INT AS y, month(l_shipdate)::INT AS m FROM s) SELECT coalesce(y, -1) AS year, coalesce(m, -1) AS month, n_edges FROM (SELECT y, m, count(*) AS n_edges FROM m GROUP BY ROLLUP (y, m))",
    "topk_walks_by_value": f"{_STEP} SELECT edge_path, sum(round(l_extendedprice * 100)::BIGINT)::BIGINT AS cents FROM s GROUP BY edge_path ORDER BY cents DESC, edge_path LIMIT 5",
    "asof_next_event": """SELECT event_id, coalesce(next_purchase, -1) AS next_purchase FROM (SELECT event_id, event_type, first(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS)
        OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS next_purchase FROM events) WHERE event_type = 'error'""",
    "events_tumbling": "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H') AS hour, event_type, count(*) AS n FROM events GROUP BY ALL",
    "events_sliding": """SELECT start, count(*) AS n FROM (SELECT (floor(epoch(ts) / 3600)::BIGINT - k) * 3600 AS start FROM events, (VALUES (0), (1)) AS s(k)) GROUP BY start""",
    "events_session_windows": """SELECT user_id, n, count(*) AS n_sessions FROM (SELECT user_id, session, count(*) AS n FROM (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session
        FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY ALL) GROUP BY user_id, n""",
    "events_props_json": "SELECT event_type, sum((props->>'$.k')::BIGINT)::BIGINT AS sum_k, max((props->>'$.k')::BIGINT) AS max_k FROM events GROUP BY event_type",
}
assert set(ORACLES) <= set(QUERIES) and VIEW_SQL

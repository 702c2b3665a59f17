"""Graph views over the given tables.  Labels are boolean tests on columns; each view has the same columns."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkengine.graph.model import LabeledGraph
from walkengine.session import read_table

#: The worked example, (edge_id, src, dst, labels, cost).
DEMO = (
    ("e1", "A", "C", ("h",), 1), ("e2", "A", "D", ("h", "s"), 1), ("e3", "D", "C", ("s",), 1), ("e4", "D", "E", ("h",), 1),
    ("e5", "C", "E", ("h",), 1), ("e6", "C", "E", ("s",), 1), ("e7", "C", "B", ("h",), 1), ("e8", "E", "B", ("h", "s"), 1),
)
#: Order of the worked example's edges into a vertex.
DEMO_POSITIONS = {"e1": 1, "e2": 0, "e3": 0, "e4": 0, "e5": 1, "e6": 2, "e7": 1, "e8": 0}


def tests(**labels: Column) -> Column:
    """The labels whose test holds, as an array."""
    marks = F.array(*(F.when(test, F.lit(name)) for name, test in labels.items()))
    return F.filter(marks, lambda x: x.isNotNull())


def _line_key() -> Column:
    """(l_orderkey, l_linenumber) repeats, so an ordinal within it tells its rows apart."""
    order = W.partitionBy("l_orderkey", "l_linenumber").orderBy("l_partkey", "l_suppkey", "l_extendedprice")
    return F.concat_ws("-", "l_orderkey", "l_linenumber", F.row_number().over(order))


def demo(spark: SparkSession, sf_dir: str = "") -> LabeledGraph:
    return LabeledGraph(spark.createDataFrame(list(DEMO), "edge_id string, src string, dst string, labels array<string>, cost long"))


def basket(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Part to the next part of an order."""
    along = W.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")
    lines = read_table(spark, sf_dir, "lineitem").select(
        _line_key().alias("edge_id"),
        F.col("l_partkey").alias("src"),
        F.lead("l_partkey").over(along).alias("dst"),
        tests(h=F.col("l_extendedprice") >= 50000, s=F.col("l_returnflag") == "R", o=F.col("l_linestatus") == "O").alias("labels"),
        F.col("l_quantity").cast("long").alias("cost"),
    )
    return LabeledGraph(lines.where("dst IS NOT NULL"))


def trade(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Customer pays supplier for a line; a returned line is paid back."""
    lines = read_table(spark, sf_dir, "lineitem").withColumn("key", _line_key())
    lines = lines.join(read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    labels = {"h": F.col("l_extendedprice") >= 50000, "s": F.col("l_discount") >= 0.08}
    buyer, seller = F.concat(F.lit("C:"), "o_custkey"), F.concat(F.lit("S:"), "l_suppkey")
    cents = F.round(F.col("l_extendedprice") * 100).cast("long").alias("cost")
    pay = lines.select(F.concat("key", F.lit(":p")).alias("edge_id"), buyer.alias("src"), seller.alias("dst"), tests(**labels, pay=F.lit(True)).alias("labels"), cents)
    back = lines.where("l_returnflag = 'R'").select(
        F.concat("key", F.lit(":r")).alias("edge_id"), seller.alias("src"), buyer.alias("dst"), tests(**labels, refund=F.lit(True)).alias("labels"), cents
    )
    return LabeledGraph(pay.unionByName(back))


def handoff(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """User to the user of the next event of the day."""
    return handoff_of(read_table(spark, sf_dir, "events"))


def handoff_of(events: DataFrame) -> LabeledGraph:
    along = W.partitionBy(F.to_date("ts")).orderBy("ts", "event_id")
    events = events.select(
        F.col("event_id").alias("edge_id"),
        F.col("user_id").alias("src"),
        F.lead("user_id").over(along).alias("dst"),
        tests(h=F.col("value") >= 35, s=F.col("event_type") == "error").alias("labels"),
        F.lit(1).cast("long").alias("cost"),
    )
    return LabeledGraph(events.where("dst IS NOT NULL"))


def session(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """A path for each user: from a start to the first event, and from event to event; labelled by the event reached."""
    along = W.partitionBy("user_id").orderBy("ts", "event_id")
    gap = F.unix_seconds(F.col("ts").cast("timestamp")) - F.unix_seconds(F.lag("ts").over(along).cast("timestamp"))
    return LabeledGraph(
        read_table(spark, sf_dir, "events").select(
            F.col("event_id").alias("edge_id"),
            F.coalesce(F.concat(F.lit("E:"), F.lag("event_id").over(along)), F.concat(F.lit("U:"), "user_id")).alias("src"),
            F.concat(F.lit("E:"), "event_id").alias("dst"),
            F.array("event_type").alias("labels"),
            F.greatest(F.coalesce(gap, F.lit(1)), F.lit(1)).cast("long").alias("cost"),
        )
    )


def chat(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """A path for each conversation: start, first turn, next turn; labelled by the role of the turn reached."""
    along = W.partitionBy("conv_id").orderBy("turn")
    before = F.coalesce(F.lag("turn").over(along).cast("string"), F.lit("start"))
    return LabeledGraph(
        read_table(spark, sf_dir, "conversations").select(
            F.concat_ws("-", "conv_id", "turn").alias("edge_id"),
            F.concat_ws(":", "conv_id", before).alias("src"),
            F.concat_ws(":", "conv_id", "turn").alias("dst"),
            F.array("role").alias("labels"),
            F.lit(1).cast("long").alias("cost"),
        )
    )


def turns(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """A small multigraph for each conversation, from a start they share: role to the role of the next turn, so a talk that
    goes back and forth has parallel edges."""
    along = W.partitionBy("conv_id").orderBy("turn")
    before = F.lag("role").over(along)
    return LabeledGraph(
        read_table(spark, sf_dir, "conversations").select(
            F.concat_ws("-", "conv_id", "turn").alias("edge_id"),
            F.when(before.isNull(), F.lit("S")).otherwise(F.concat_ws(":", "conv_id", before)).alias("src"),
            F.concat_ws(":", "conv_id", "role").alias("dst"),
            tests(h=F.length("text") >= 100, s=F.col("role") == "assistant").alias("labels"),
            F.lit(1).cast("long").alias("cost"),
        )
    )


def geo(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Both directions of the keys between region, nation, customer and supplier."""
    none = F.lit(False)
    parts = []
    for table, key, up, letter, parent, rich in (
        ("nation", "n_nationkey", "n_regionkey", "N", "R", none),
        ("customer", "c_custkey", "c_nationkey", "C", "N", F.col("c_acctbal") >= 5000),
        ("supplier", "s_suppkey", "s_nationkey", "S", "N", F.col("s_acctbal") >= 5000),
    ):
        rows = read_table(spark, sf_dir, table)
        low, high = F.concat(F.lit(f"{letter}:"), key), F.concat(F.lit(f"{parent}:"), up)
        for name, src, dst in (("in", low, high), ("has", high, low)):
            mark = tests(**{name: F.lit(True), "rich": rich})
            parts.append(rows.select(F.concat(low, F.lit(f":{name}")).alias("edge_id"), src.alias("src"), dst.alias("dst"), mark.alias("labels"), F.lit(1).cast("long").alias("cost")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return LabeledGraph(out)


def supply(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Supplier to part and back, by line."""
    lines = read_table(spark, sf_dir, "lineitem").withColumn("key", _line_key())
    lines = lines.join(read_table(spark, sf_dir, "part").select("p_partkey", "p_size", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    labels = F.concat(F.array("l_returnflag", "p_brand"), tests(big=F.col("p_size") >= 25)).alias("labels")
    cost = F.col("l_quantity").cast("long").alias("cost")
    s, p = F.concat(F.lit("S:"), "l_suppkey"), F.concat(F.lit("P:"), "l_partkey")
    there = lines.select(F.concat("key", F.lit(":sp")).alias("edge_id"), s.alias("src"), p.alias("dst"), labels, cost)
    back = lines.select(F.concat("key", F.lit(":ps")).alias("edge_id"), p.alias("src"), s.alias("dst"), labels, cost)
    return LabeledGraph(there.unionByName(back))


def links(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Page to link target, page to host, and the reverse of both."""
    pages = read_table(spark, sf_dir, "pages").select(F.concat(F.lit("G:"), "page_id").alias("page"), "url", "html")
    href = pages.select("page", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), 1)).alias("to")).distinct()
    host = pages.select("page", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("to"))
    one = F.lit(1).cast("long").alias("cost")
    parts = []
    for rows, name, tag in ((href, "nav", "L:"), (host, "host", "H:")):
        to = F.concat(F.lit(tag), "to")
        key = F.concat_ws("|", "page", to)
        parts.append(rows.select(F.concat(key, F.lit("|f")).alias("edge_id"), F.col("page").alias("src"), to.alias("dst"), F.array(F.lit(name)).alias("labels"), one))
        parts.append(rows.select(F.concat(key, F.lit("|b")).alias("edge_id"), to.alias("src"), F.col("page").alias("dst"), F.array(F.lit(name), F.lit("rev")).alias("labels"), one))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return LabeledGraph(out)


def docs(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Documents that share a trimmed line of 20 characters or more which 2 to 20 documents have (so a line gives a bounded
    number of pairs), both ways; labelled by what the two share and by the labels of the document reached."""
    documents = read_table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    line = documents.select("doc_id", F.explode(F.split(F.coalesce("text", F.lit("")), "\n")).alias("x")).select("doc_id", F.trim("x").alias("line"))
    line = line.where(F.length("line") >= 20).distinct()
    shared = line.groupBy("line").agg(F.count("*").alias("n")).where("n BETWEEN 2 AND 20").select("line")
    line = line.join(shared, "line")
    pairs = line.select("line", F.col("doc_id").alias("src")).join(line.select("line", F.col("doc_id").alias("dst")), "line").where("src <> dst").select("src", "dst").distinct()
    known = documents.select("doc_id", "lang", "source").join(read_table(spark, sf_dir, "labels").select("doc_id", "quality", "toxic"), "doc_id", "left")
    a, b = known.alias("a"), known.alias("b")
    both = pairs.join(a, F.col("src") == F.col("a.doc_id")).join(b, F.col("dst") == F.col("b.doc_id"))
    marks = tests(samelang=F.col("a.lang") == F.col("b.lang"), samesource=F.col("a.source") == F.col("b.source"), good=F.col("b.quality") == 1, toxic=F.col("b.toxic") == 1)
    return LabeledGraph(both.select(F.concat_ws("-", "src", "dst").alias("edge_id"), "src", "dst", marks.alias("labels"), F.lit(1).cast("long").alias("cost")))


def ladder(spark: SparkSession, stages: int, width: int = 2, labels: tuple[str, ...] = ("a", "b"), noise: int = 0) -> LabeledGraph:
    """``stages`` steps of ``width`` parallel edges with all labels; ``noise`` edges into each vertex from unreachable ones."""
    step = spark.range(stages).select(F.col("id").alias("k"))
    lab, one = F.array(*map(F.lit, labels)).alias("labels"), F.lit(1).cast("long").alias("cost")
    real = step.select("k", F.explode(F.sequence(F.lit(0), F.lit(width - 1))).alias("w")).select(
        F.format_string("e%05d-%05d", "k", "w").alias("edge_id"), F.col("k").alias("src"), (F.col("k") + 1).alias("dst"), lab, one
    )
    if not noise:
        return LabeledGraph(real)
    extra = step.select("k", F.explode(F.sequence(F.lit(0), F.lit(noise - 1))).alias("w")).select(
        F.format_string("n%05d-%05d", "k", "w").alias("edge_id"), (-F.col("w") - 1).cast("long").alias("src"), (F.col("k") + 1).alias("dst"), lab, one
    )
    return LabeledGraph(real.unionByName(extra))


VIEWS = {f.__name__: f for f in (demo, basket, trade, handoff, session, chat, geo, supply, links, docs)}

_KEY = "concat_ws('-', l_orderkey, l_linenumber, row_number() OVER (PARTITION BY l_orderkey, l_linenumber ORDER BY l_partkey, l_suppkey, l_extendedprice))"
_TEST = lambda **t: "list_filter([" + ", ".join(f"CASE WHEN {c} THEN '{n}' END" for n, c in t.items()) + "], lambda x: x IS NOT NULL)"
#: The same views in DuckDB's SQL, for oracles.
VIEW_SQL = {
    "demo": "SELECT * FROM (VALUES " + ", ".join(f"('{e}', '{s}', '{d}', {list(l)}, {c}::BIGINT)" for e, s, d, l, c in DEMO) + ") AS t(edge_id, src, dst, labels, cost)",
    "basket": f"""SELECT * FROM (SELECT {_KEY} AS edge_id, l_partkey AS src,
        lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice) AS dst,
        {_TEST(h="l_extendedprice >= 50000", s="l_returnflag = 'R'", o="l_linestatus = 'O'")} AS labels, l_quantity::BIGINT AS cost FROM lineitem) WHERE dst IS NOT NULL""",
    "trade": f"""SELECT k || ':p' AS edge_id, 'C:' || o_custkey AS src, 'S:' || l_suppkey AS dst,
        {_TEST(h="l_extendedprice >= 50000", s="l_discount >= 0.08", pay="true")} AS labels, round(l_extendedprice * 100)::BIGINT AS cost
        FROM (SELECT *, {_KEY} AS k FROM lineitem) JOIN orders ON l_orderkey = o_orderkey
        UNION ALL SELECT k || ':r', 'S:' || l_suppkey, 'C:' || o_custkey,
        {_TEST(h="l_extendedprice >= 50000", s="l_discount >= 0.08", refund="true")}, round(l_extendedprice * 100)::BIGINT
        FROM (SELECT *, {_KEY} AS k FROM lineitem) JOIN orders ON l_orderkey = o_orderkey WHERE l_returnflag = 'R'""",
    "handoff": f"""SELECT * FROM (SELECT event_id AS edge_id, user_id AS src, lead(user_id) OVER (PARTITION BY ts::DATE ORDER BY ts, event_id) AS dst,
        {_TEST(h="value >= 35", s="event_type = 'error'")} AS labels, 1::BIGINT AS cost FROM events) WHERE dst IS NOT NULL""",
    "session": """SELECT event_id AS edge_id, coalesce('E:' || lag(event_id) OVER w, 'U:' || user_id) AS src, 'E:' || event_id AS dst, [event_type] AS labels,
        greatest(coalesce(floor(epoch(ts))::BIGINT - floor(epoch(lag(ts) OVER w))::BIGINT, 1), 1)::BIGINT AS cost FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""",
    "chat": """SELECT concat_ws('-', conv_id, turn) AS edge_id, conv_id || ':' || coalesce((lag(turn) OVER (PARTITION BY conv_id ORDER BY turn))::VARCHAR, 'start') AS src,
        conv_id || ':' || turn AS dst, [role] AS labels, 1::BIGINT AS cost FROM conversations""",
    "turns": f"""SELECT concat_ws('-', conv_id, turn) AS edge_id, coalesce(conv_id || ':' || lag(role) OVER (PARTITION BY conv_id ORDER BY turn), 'S') AS src,
        conv_id || ':' || role AS dst, {_TEST(h="length(text) >= 100", s="role = 'assistant'")} AS labels, 1::BIGINT AS cost FROM conversations""",
    "geo": " UNION ALL ".join(
        f"SELECT '{c}:' || {k} || ':{n}' AS edge_id, {s} AS src, {d} AS dst, {_TEST(**{n: 'true', 'rich': r})} AS labels, 1::BIGINT AS cost FROM {t}"
        for t, k, u, c, p, r in (("nation", "n_nationkey", "n_regionkey", "N", "R", "false"), ("customer", "c_custkey", "c_nationkey", "C", "N", "c_acctbal >= 5000"), ("supplier", "s_suppkey", "s_nationkey", "S", "N", "s_acctbal >= 5000"))
        for n, s, d in (("in", f"'{c}:' || {k}", f"'{p}:' || {u}"), ("has", f"'{p}:' || {u}", f"'{c}:' || {k}"))
    ),
    "supply": " UNION ALL ".join(
        f"""SELECT k || ':{n}' AS edge_id, {s} AS src, {d} AS dst, list_concat([l_returnflag, p_brand], {_TEST(big="p_size >= 25")}) AS labels, l_quantity::BIGINT AS cost
        FROM (SELECT *, {_KEY} AS k FROM lineitem) JOIN part ON l_partkey = p_partkey"""
        for n, s, d in (("sp", "'S:' || l_suppkey", "'P:' || l_partkey"), ("ps", "'P:' || l_partkey", "'S:' || l_suppkey"))
    ),
    "docs": f"""WITH line AS (SELECT DISTINCT doc_id, trim(x) AS line FROM (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS x FROM documents) WHERE length(trim(x)) >= 20),
        shared AS (SELECT line FROM line GROUP BY line HAVING count(*) BETWEEN 2 AND 20),
        pairs AS (SELECT DISTINCT a.doc_id AS src, b.doc_id AS dst FROM line a JOIN line b USING (line) JOIN shared USING (line) WHERE a.doc_id <> b.doc_id),
        known AS (SELECT d.doc_id, lang, source, quality, toxic FROM documents d LEFT JOIN labels USING (doc_id))
        SELECT src || '-' || dst AS edge_id, src, dst,
        {_TEST(samelang="a.lang = b.lang", samesource="a.source = b.source", good="b.quality = 1", toxic="b.toxic = 1")} AS labels, 1::BIGINT AS cost
        FROM pairs JOIN known a ON a.doc_id = src JOIN known b ON b.doc_id = dst""",
    "links": " UNION ALL ".join(
        f"SELECT 'G:' || page_id || '|{t}' || x || '|{e}' AS edge_id, {s} AS src, {d} AS dst, {l} AS labels, 1::BIGINT AS cost FROM ({q})"
        for q, t, n in (("SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS x FROM pages", "L:", "nav"), ("SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS x FROM pages", "H:", "host"))
        for e, s, d, l in (("f", "'G:' || page_id", f"'{t}' || x", f"['{n}']"), ("b", f"'{t}' || x", "'G:' || page_id", f"['{n}', 'rev']"))
    ),
}

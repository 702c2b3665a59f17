"""Sources and sinks of graphs and walks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkengine.graph.model import LabeledGraph


def graph_from_edges(edges: DataFrame, label_columns: tuple[str, ...] = (), separator: str = "+") -> LabeledGraph:
    """A graph from rows edge_id, src, dst and labels: an array, a text joined by ``separator``, or one boolean column for
    each label.  A cost column is kept."""
    if label_columns:
        labels = F.filter(F.array(*(F.when(F.col(c), F.lit(c)) for c in label_columns)), lambda x: x.isNotNull())
    elif edges.schema["labels"].dataType.simpleString() == "string":
        labels = F.filter(F.split(F.coalesce("labels", F.lit("")), rf"\Q{separator}\E"), lambda x: x != "")
    else:
        labels = F.col("labels")
    extra = ["cost"] if "cost" in edges.columns else []
    return LabeledGraph(edges.select("edge_id", "src", "dst", labels.alias("labels"), *extra))


def read_graph(spark: SparkSession, path: str, form: str, schema: str, **options) -> LabeledGraph:
    """A graph from files: csv, json or parquet, or ``table`` for a table of the catalog."""
    columns = [c.strip().split()[0] for c in schema.split(",")]
    known = {"edge_id", "src", "dst", "labels", "cost"}
    rows = spark.table(path) if form == "table" else spark.read.format(form).schema(schema).options(**options).load(path)
    return graph_from_edges(rows, tuple(c for c in columns if c not in known) if "labels" not in columns else ())


def write_graph(g: LabeledGraph, path: str, form: str, separator: str = "+", **options) -> None:
    """Edges as files; a form without arrays gets the labels as one text."""
    rows = g.edges if form != "csv" else g.edges.withColumn("labels", F.array_join("labels", separator))
    rows.write.format(form).options(**options).save(path)


def write_walks(walks: DataFrame, path: str, form: str = "parquet", by: tuple[str, ...] = ()) -> None:
    """Walks as files, in folders by the named columns (run_id, say); json writes one object a line."""
    writer = walks.write.format(form)
    (writer.partitionBy(*by) if by else writer).save(path)

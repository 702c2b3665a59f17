"""Labelled graphs as DataFrames."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


@dataclass(frozen=True)
class LabeledGraph:
    """``edges``: edge_id, src, dst, labels (array of strings), and further columns such as cost.  Every edge has its own
    edge_id, so parallel edges are different; an edge may carry several labels."""

    edges: DataFrame

    def masked(self, alphabet: tuple[str, ...]) -> DataFrame:
        """Edges that a pattern over ``alphabet`` can use, with their labels as bits."""
        from walkengine.lang.codegen import label_mask

        extra = ["cost"] if "cost" in self.edges.columns else []
        return self.edges.select("edge_id", "src", "dst", label_mask("labels", alphabet).alias("lab"), *extra).where("lab <> 0")

    def vertices(self) -> DataFrame:
        return self.edges.select(F.explode(F.array("src", "dst")).alias("vertex")).distinct()

    def size(self) -> DataFrame:
        """One row: vertices, edges, labels on edges and their sum."""
        v = self.vertices().agg(F.count("*").alias("n_vertices"))
        e = self.edges.agg(F.count("*").alias("n_edges"), F.coalesce(F.sum(F.size("labels")), F.lit(0)).cast("long").alias("n_labels"))
        return v.crossJoin(e).withColumn("graph_size", F.col("n_vertices") + F.col("n_edges") + F.col("n_labels"))

    def in_positions(self) -> DataFrame:
        """Edges with their place among the edges into the same vertex, from 0."""
        return self.edges.withColumn("in_pos", F.row_number().over(W.partitionBy("dst").orderBy("edge_id")).cast("long") - 1)

    def single_labelled(self, alphabet: tuple[str, ...] | None = None) -> bool:
        """No edge has two labels (of the alphabet, if given)."""
        labels = F.col("labels") if alphabet is None else F.filter("labels", lambda x: x.isin(*alphabet))
        return self.edges.where(F.size(labels) > 1).isEmpty()

    def validate(self) -> None:
        """Raises on missing ends, repeated edge ids or costs that are not positive."""
        bad = self.edges.where("edge_id IS NULL OR src IS NULL OR dst IS NULL OR labels IS NULL")
        if not bad.isEmpty():
            raise ValueError("edges need an id, both ends and labels")
        if not self.edges.groupBy("edge_id").count().where("count > 1").isEmpty():
            raise ValueError("edge ids must differ")
        if "cost" in self.edges.columns and not self.edges.where("cost IS NULL OR cost <= 0").isEmpty():
            raise ValueError("costs must be positive")

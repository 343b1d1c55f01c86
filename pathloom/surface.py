"""What users open and ask: graphs from edge stores, views by name in SQL, and paths as tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators.engine import LabeledGraph, ViewStore, materialize
from .plans.rules import PathExpr, parse_path
from .sources.feeds import EDGES


def open_graph(spark: SparkSession, path: str, domain: DataFrame | None = None) -> LabeledGraph:
    """A lazy graph over an edge store of folders label=..., as write_edges() leaves it; labels come from the folders."""
    edges = spark.read.schema(EDGES).parquet(path)
    labels = [r["label"] for r in edges.select("label").distinct().collect()]  # one row for each label
    return LabeledGraph.from_relations(spark, {x: edges.where(F.col("label") == x).select("src", "dst") for x in sorted(labels) if x is not None}, domain)


def path_view(graph: LabeledGraph, path: str | PathExpr, name: str = "path") -> DataFrame:
    """The pairs (src, dst) that a path expression joins."""
    own = (parse_path(path) if isinstance(path, str) else path).compile(name)
    return materialize(own, graph, [name]).rel(name)


def register_views(spark: SparkSession, graph: LabeledGraph | ViewStore, prefix: str = "") -> list[str]:
    """A temporary view for each plain relation of a graph or a stored one, under prefix + label; their names."""
    graph = graph.graph() if isinstance(graph, ViewStore) else graph
    names = sorted(graph.labels())
    for x in names:
        graph.rel(x).createOrReplaceTempView(f"{prefix}{x}")
    return [f"{prefix}{x}" for x in names]

"""Workload construction and the measures of incremental maintenance against rebuilding."""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.engine import GraphUpdate, LabeledGraph

FRACTIONS = (0.05, 0.10, 0.15, 0.20, 0.25)


def sample_labels(labels: Iterable[str], f: float, seed: int = 42, nested: bool = False, must_hit: Iterable[str] | None = None) -> list[str]:
    """floor(f * n + 0.5) labels, one at least, by hash; independent for each f unless nested.

    must_hit: if none of these is among them, the first of these by hash takes the last place.
    """
    labels = sorted(set(labels))
    key = lambda x: hashlib.sha256(f"{seed}|{'' if nested else f'{f:g}'}|{x}".encode()).hexdigest()
    order = sorted(labels, key=key)
    out = order[: max(1, math.floor(f * len(labels) + 0.5))]
    if must_hit is not None and not set(out) & set(must_hit):
        out[-1] = min(set(must_hit) & set(labels), key=key)
    return out


def split_by_labels(graph: LabeledGraph, sampled: Iterable[str]) -> tuple[LabeledGraph, GraphUpdate]:
    """The graph without the sampled labels' edges, and their bulk insertion."""
    sampled = set(sampled)
    base = {s: d for s, d in graph.relations.items() if s[0] not in sampled}
    return LabeledGraph(graph.spark, base, graph.domain, graph.closure_method), GraphUpdate({s: d for s, d in graph.relations.items() if s[0] in sampled and not s[1]})


def split_by_edges(graph: LabeledGraph, percent: int, seed: int = 0) -> tuple[LabeledGraph, GraphUpdate]:
    """The graph without a share of each label's edges, and their insertion; replayable by any engine."""
    chosen = (F.col("src") * 31 + F.col("dst") * 17 + seed) % 100 < percent
    plain = {s: d for s, d in graph.relations.items() if not s[1]}
    return LabeledGraph(graph.spark, {s: d.where(~chosen) for s, d in plain.items()}, graph.domain, graph.closure_method), GraphUpdate({s: d.where(chosen) for s, d in plain.items()})


def gain_ms(full, incr):
    return full - incr


def gain_pct(full, incr):
    return 100 - 100 * incr / full


def mean_ms(timings: DataFrame) -> DataFrame:
    """workload, fraction, full_ms, incr_ms over views and repetitions of (workload, fraction, view, regime, rep, ms)."""
    return timings.groupBy("workload", "fraction").agg(*(F.avg(F.when(F.col("regime") == r, F.col("ms"))).alias(f"{r.lower()}_ms") for r in ("FULL", "INCR")))


def gains(means: DataFrame) -> DataFrame:
    return means.withColumns({"gain_ms": gain_ms(F.col("full_ms"), F.col("incr_ms")), "gain_pct": gain_pct(F.col("full_ms"), F.col("incr_ms"))})


def claim_positive(means: DataFrame) -> DataFrame:
    return gains(means).agg(F.bool_and(F.col("gain_ms") > 0).alias("always_positive"))


def claim_sparser_better(means: DataFrame) -> DataFrame:
    """fraction, sparser_better: whether the relative gain on the sparse graph is the larger one."""
    g = gains(means)
    side = lambda w: g.where(F.col("workload") == w).select("fraction", F.col("gain_pct").alias(w))
    return side("dense").join(side("sparse"), "fraction").select("fraction", (F.col("sparse") > F.col("dense")).alias("sparser_better"))


def degree_profile(edges: DataFrame) -> DataFrame:
    """label, edges, sources, targets, max_out, max_in of edges (label, src, dst)."""
    out = edges.groupBy("label", "src").agg(F.count("*").alias("d")).groupBy("label").agg(F.sum("d").alias("edges"), F.count("*").alias("sources"), F.max("d").alias("max_out"))
    into = edges.groupBy("label", "dst").agg(F.count("*").alias("d")).groupBy("label").agg(F.count("*").alias("targets"), F.max("d").alias("max_in"))
    return out.join(into, "label").select("label", "edges", "sources", "targets", "max_out", "max_in")


def degree_distribution(edges: DataFrame) -> DataFrame:
    """label, side ("out" or "in"), degree, nodes: how many nodes have so many edges (label, src, dst) on a side."""
    side = lambda c, name: edges.groupBy("label", c).agg(F.count("*").alias("degree")).groupBy("label", "degree").agg(F.count("*").alias("nodes")).select("label", F.lit(name).alias("side"), "degree", "nodes")
    return side("src", "out").unionByName(side("dst", "in"))

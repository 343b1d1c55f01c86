"""Transitive closures of edge tables (src, dst), paths of one edge at least. Rounds are staged in the shared folder.

Small graphs are closed on the driver, since a round of jobs costs more than all their pairs: only where the edges are
few and the pairs stay few (both checked, SMALL_EDGES and SMALL_PAIRS); everything else runs in distributed rounds.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from ..sources.staging import KEPT_BYTES, KEPT_ROWS, Stage, estimated_bytes

PAIRS = StructType([StructField("src", LongType()), StructField("dst", LongType())])
METHODS = ("auto", "naive", "frontier", "doubling", "components", "local", "sql")

#: Edges that the driver closes at most, and pairs that it holds at most, intermediate ones included.
SMALL_EDGES, SMALL_PAIRS = 500_000, 2_000_000
#: Edges made from inputs of over about this many bytes are staged before they are counted, so that they are made once.
STAGED_BYTES = 1_000_000
#: Edges of a component that one task closes at most.
LOCAL_EDGES = 5_000
#: Lengths of step after which naive and frontier rounds take longer steps, and levels of a recursion in SQL.
STRIDE, LEVELS = 4, 8


def compose(left: DataFrame, right: DataFrame) -> DataFrame:
    """Pairs with a common middle; not distinct."""
    return left.select("src", F.col("dst").alias("_mid")).join(right.select(F.col("src").alias("_mid"), "dst"), "_mid").select("src", "dst")


def minus(left: DataFrame, right: DataFrame) -> DataFrame:
    return left.join(right, ["src", "dst"], "left_anti")


def union(*parts: DataFrame) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def collected(pairs: DataFrame) -> np.ndarray | None:
    """Pairs as an array of two rows; None if they are more than SMALL_EDGES."""
    table = pairs.select("src", "dst").limit(SMALL_EDGES + 1).toArrow()
    return np.stack([table.column(c).to_numpy() for c in ("src", "dst")]).astype(np.int64) if table.num_rows <= SMALL_EDGES else None


def table_of(stage: Stage, pairs: np.ndarray) -> DataFrame:
    """Pairs of the driver as a table of the stage, written if they are many."""
    import pyarrow as pa

    out, n = stage.local(pa.table({"src": pairs[0], "dst": pairs[1]}), PAIRS)
    return out if n <= KEPT_ROWS else stage.put(out.select("src", "dst"))[0]


class PairSet:
    """Pairs of nodes on the driver, as sorted numbers; nodes: all that any pair may have, sorted."""

    def __init__(self, nodes: np.ndarray):
        self.nodes = nodes

    def codes(self, pairs: np.ndarray) -> np.ndarray:
        at = np.searchsorted(self.nodes, pairs)
        return np.unique(at[0] * len(self.nodes) + at[1])

    def pairs(self, codes: np.ndarray) -> np.ndarray:
        return np.stack([self.nodes[codes // len(self.nodes)], self.nodes[codes % len(self.nodes)]])

    def compose(self, left: np.ndarray, right: np.ndarray) -> np.ndarray | None:
        """Codes of pairs with a common middle; None if they are too many for the driver."""
        n = len(self.nodes)
        middle = left % n
        begin, end = np.searchsorted(right, middle * n), np.searchsorted(right, (middle + 1) * n)
        times = end - begin
        if times.sum() > 4 * SMALL_PAIRS:
            return None
        row = np.repeat(np.arange(len(left)), times)
        at = np.arange(len(row)) - np.repeat(np.cumsum(times) - times, times) + begin[row]
        return np.unique(left[row] // n * n + right[at] % n)

    def closed(self, codes: np.ndarray) -> np.ndarray | None:
        """The closure, by composing the newest pairs with all; None if it is too large for the driver."""
        every, new = codes, codes
        while len(new):
            found = self.compose(new, every)
            if found is None:
                return None
            new = np.setdiff1d(found, every, assume_unique=True)
            every = np.union1d(every, new)
            if len(every) > SMALL_PAIRS:
                return None
        return every


def _apart(edges: DataFrame) -> bool:
    """Whether no edge can begin where another ends, since their ranges of nodes have nothing in common."""
    low, high, low_dst, high_dst = edges.agg(F.min("src"), F.max("src"), F.min("dst"), F.max("dst")).first()
    return low is None or high < low_dst or high_dst < low


def _small(edges: DataFrame, stage: Stage) -> DataFrame | None:
    """The closure of edges by the driver, if they are few enough."""
    if stage.put(edges)[1] > SMALL_EDGES if stage.has(edges) else estimated_bytes(edges) > KEPT_BYTES:
        return None
    pairs = collected(edges)
    if pairs is None:
        return None
    own = PairSet(np.unique(pairs))
    out = own.closed(own.codes(pairs))
    return None if out is None else table_of(stage, own.pairs(out))


def closure(edges: DataFrame, method: str = "auto", sources: DataFrame | None = None, targets: DataFrame | None = None, stage: Stage | None = None, max_pairs: int | None = None) -> DataFrame:
    """Pairs (src, dst) joined by a path of edges.

    sources or targets (id) restrict paths to those that begin or end there, and seed the rounds, so the full closure
    is not built. max_pairs refuses a result beyond that size instead of filling the disks. An empty table gives an
    empty closure; repeated edges count once.
    """
    stage = stage or Stage(edges.sparkSession, "closure")
    if targets is not None:
        flipped = closure(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")), method, targets, sources, stage, max_pairs)
        return flipped.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    edges = edges.select("src", "dst").distinct()
    if method == "auto":
        if sources is None and estimated_bytes(edges) > STAGED_BYTES:
            edges, _ = stage.put(edges)
            if _apart(edges):
                _check(stage.put(edges)[1], max_pairs)
                return edges
        if sources is None and (out := _small(edges, stage)) is not None:
            _check(stage.put(out)[1], max_pairs)
            return out
        method = "doubling"
    edges, n = stage.put(edges)
    if n == 0:
        return edges
    if sources is not None:
        seed = edges.join(sources.select(F.col("id").alias("src")).distinct(), "src", "left_semi").select("src", "dst")
        return _frontier(edges, seed, stage, max_pairs)
    return {"naive": _naive, "frontier": _all_frontier, "doubling": _doubling, "components": _components, "local": _local, "sql": _sql}[method](edges, stage, max_pairs)


def _check(total: int, most: int | None) -> None:
    if most is not None and total > most:
        raise ValueError(f"the closure has more than {most} pairs; seed it with sources or raise max_pairs")


def _extended(pairs: DataFrame, step: DataFrame, length: int) -> DataFrame:
    """(src, dst, n) of pairs with a step of a length behind them, n the least length; pairs: (src, dst, n)."""
    longer = pairs.select("src", F.col("dst").alias("_mid"), (F.col("n") + length).alias("n"))
    return longer.join(step.select(F.col("src").alias("_mid"), "dst"), "_mid").groupBy("src", "dst").agg(F.min("n").alias("n"))


def _naive(edges: DataFrame, stage: Stage, most: int | None) -> DataFrame:
    """Each round makes all pairs anew. Steps grow as in _all_frontier."""
    total, n = stage.put(edges.select("src", "dst", F.lit(1).cast("long").alias("n")))
    base, step, length, upto = total, edges, 1, 1
    while True:
        bigger, m = stage.put(union(base, _extended(total, step, length)).groupBy("src", "dst").agg(F.min("n").alias("n")))
        _check(m, most)
        if total is not base:
            stage.drop(total)
        if m == n:
            return bigger.select("src", "dst")
        total, n, upto = bigger, m, upto + length
        if upto == STRIDE * length:
            stage.drop(base)
            base, step, length = total, total.where(F.col("n") == upto), upto


def _all_frontier(edges: DataFrame, stage: Stage, most: int | None) -> DataFrame:
    """Extend only the newest pairs by a step, at first of one edge.

    n is the least number of edges. After STRIDE lengths of step, the pairs whose n is as many edges are the new steps: the
    end of a shortest path is a shortest path. So rounds are about STRIDE times the logarithm of the longest one.
    """
    new, n = stage.put(edges.select("src", "dst", F.lit(1).cast("long").alias("n")))
    parts, total, step, length, upto = [new], n, new, 1, 1
    while n:
        new, n = stage.put(minus(_extended(new, step, length), union(*parts)))
        total, upto = total + n, upto + length
        _check(total, most)
        if n:
            parts.append(new)
        if upto == STRIDE * length:
            new, step, length = union(*parts), new.where(F.col("n") == upto), upto
    return union(*parts).select("src", "dst")


def _frontier(edges: DataFrame, seed: DataFrame, stage: Stage, most: int | None) -> DataFrame:
    """Extend only the newest pairs by one edge."""
    new, n = stage.put(seed)
    parts, total = [new], n
    while n:
        new, n = stage.put(minus(compose(new, edges).distinct(), union(*parts)))
        total += n
        _check(total, most)
        if n:
            parts.append(new)
    return union(*parts)


def _doubling(edges: DataFrame, stage: Stage, most: int | None) -> DataFrame:
    """Compose the newest pairs with all so far: rounds are the logarithm of the longest shortest path."""
    new, parts, n, total = edges, [edges], 1, 0
    while n:
        new, n = stage.put(minus(compose(new, union(*parts)).distinct(), union(*parts)))
        total += n
        _check(total, most)
        if n:
            parts.append(new)
    return union(*parts)


def weak_components(edges: DataFrame, stage: Stage) -> DataFrame:
    """(id, component: the least node), by minimum labels with shortcuts."""
    both = union(edges.select("src", "dst"), edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()
    both, _ = stage.put(both)
    labels, last = both.groupBy("src").agg(F.least(F.min("dst"), F.col("src")).alias("c")).select(F.col("src").alias("id"), "c"), None
    while True:
        near = both.join(labels.select(F.col("id").alias("dst"), F.col("c").alias("d")), "dst").groupBy(F.col("src").alias("id")).agg(F.min("d").alias("d"))
        step = labels.join(near, "id").select("id", F.least("c", "d").alias("c"))
        jump = step.join(labels.select(F.col("id").alias("c"), F.col("c").alias("e")), "c", "left").select("id", F.least("c", F.coalesce("e", "c")).alias("c"))
        before = labels
        labels, _ = stage.put(jump)
        stage.drop(before)
        now = labels.agg(F.sum(F.col("c").cast("decimal(38,0)"))).first()[0]
        if now == last:
            return labels.select("id", F.col("c").alias("component"))
        last = now


def strong_components(edges: DataFrame, stage: Stage) -> DataFrame:
    """(id, component) by colouring: the largest id that reaches a node, then what reaches back inside that colour."""
    left, n = stage.put(edges.select("src", "dst"))
    nodes = union(left.select(F.col("src").alias("id")), left.select(F.col("dst").alias("id"))).distinct()
    nodes, n_nodes = stage.put(nodes)
    found = []
    while n_nodes:
        # Nodes with no way in or no way out are components of their own.
        alone, n = stage.put(nodes.join(left.select(F.col("src").alias("id")).intersect(left.select(F.col("dst").alias("id"))), "id", "left_anti"))
        if n:
            found.append(alone.select("id", F.col("id").alias("component")))
        else:
            colour, last = nodes.select("id", F.col("id").alias("c")), None
            while True:
                into = left.join(colour.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id")).agg(F.max("c").alias("d"))
                colour, _ = stage.put(colour.join(into, "id", "left").select("id", F.greatest("c", F.coalesce("d", "c")).alias("c")))
                now = colour.agg(F.sum(F.col("c").cast("decimal(38,0)"))).first()[0]
                if now == last:
                    break
                last = now
            inside = left.join(colour.select(F.col("id").alias("src"), "c"), "src").join(colour.select(F.col("id").alias("dst"), F.col("c").alias("d")), "dst").where("c = d").select("src", "dst")
            roots = colour.where("id = c").select("id")
            turned = inside.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
            back = _frontier(turned, turned.join(roots.withColumnRenamed("id", "src"), "src", "left_semi"), stage, None)
            alone, n = stage.put(union(back.select(F.col("dst").alias("id"), F.col("src").alias("component")), roots.select("id", F.col("id").alias("component"))).distinct())
            found.append(alone)
        gone = alone.select("id")
        nodes, n_nodes = stage.put(nodes.join(gone, "id", "left_anti"))
        left, _ = stage.put(left.join(gone.withColumnRenamed("id", "src"), "src", "left_anti").join(gone.withColumnRenamed("id", "dst"), "dst", "left_anti").select("src", "dst"))
    return union(*found)


def _components(edges: DataFrame, stage: Stage, most: int | None) -> DataFrame:
    """Closure of the graph of strong components, expanded to its nodes."""
    owner, _ = stage.put(strong_components(edges, stage))
    lifted = edges.join(owner.select(F.col("id").alias("src"), F.col("component").alias("a")), "src").join(owner.select(F.col("id").alias("dst"), F.col("component").alias("b")), "dst").select(F.col("a").alias("src"), F.col("b").alias("dst")).distinct()
    pairs, n = stage.put(lifted.where("src <> dst"))
    above = _doubling(pairs, stage, most) if n else pairs
    # Inside a component all pairs are linked, if it has an edge.
    above = union(above, lifted.where("src = dst"))
    return above.join(owner.select(F.col("component").alias("src"), F.col("id").alias("a")), "src").join(owner.select(F.col("component").alias("dst"), F.col("id").alias("b")), "dst").select(F.col("a").alias("src"), F.col("b").alias("dst"))


def _local(edges: DataFrame, stage: Stage, most: int | None) -> DataFrame:
    """One task for each weak component, by bitsets over its nodes; for graphs of many small components. Components of over
    LOCAL_EDGES edges are closed in distributed rounds instead."""
    owner, _ = stage.put(weak_components(edges, stage))
    owned = edges.join(owner.withColumnRenamed("id", "src"), "src")
    large, n = stage.put(owned.groupBy("component").agg(F.count("*").alias("n")).where(F.col("n") > LOCAL_EDGES).select("component"))
    if n:
        rest, _ = stage.put(owned.join(large, "component", "left_anti").select("src", "dst"))
        there, _ = stage.put(owned.join(large, "component", "left_semi").select("src", "dst"))
        return union(_doubling(there, stage, most), _local(rest, stage, most))

    def close(pdf):
        import pandas as pd

        ids = sorted(set(pdf["src"]) | set(pdf["dst"]))
        at = {v: k for k, v in enumerate(ids)}
        nxt = [[] for _ in ids]
        for a, b in zip(pdf["src"], pdf["dst"], strict=True):
            nxt[at[a]].append(at[b])
        rows = []
        for k in range(len(ids)):
            seen, todo = 0, list(nxt[k])
            while todo:
                v = todo.pop()
                if not seen >> v & 1:
                    seen |= 1 << v
                    todo += nxt[v]
            rows += [(ids[k], ids[v]) for v in range(len(ids)) if seen >> v & 1]
        return pd.DataFrame(rows, columns=["src", "dst"]).astype("int64")

    return owned.groupBy("component").applyInPandas(close, "src long, dst long")


def _sql(edges: DataFrame, stage: Stage, most: int | None) -> DataFrame:
    """Spark's recursive SQL, which keeps repeats between rounds: for acyclic edges only.

    A recursion gives paths of LEVELS steps at most, so Spark's bounds on its levels and rows (lifted) are never met. Those of
    LEVELS steps are the steps of the next recursion, until there are none; a path is a short one and then long steps.
    """
    near, step, n, length, n_edges = [], edges, 1, 1, edges.count()
    while n:
        if length > n_edges:
            raise ValueError("recursive SQL needs edges without cycles")
        paths = edges.sparkSession.sql(
            "WITH RECURSIVE p(src, dst, n) AS (SELECT src, dst, 1 FROM {step} UNION ALL SELECT p.src, e.dst, p.n + 1 FROM p JOIN {step} e ON p.dst = e.src WHERE p.n < {most}) "
            "SELECT src, dst, n FROM p LIMIT ALL",
            step=step,
            most=LEVELS,
        )
        paths, _ = stage.put(paths.distinct())
        near.append(paths.select("src", "dst").distinct())
        step, n = stage.put(paths.where(F.col("n") == LEVELS).select("src", "dst"))
        length *= LEVELS
    total = near.pop()
    while near:
        short = near.pop()
        total, m = stage.put(union(short, compose(short, total)).distinct())
        _check(m, most)
    return total


def mutual(edges: DataFrame, stage: Stage | None = None) -> DataFrame:
    """Pairs that reach each other: those inside a strong component that has an edge. The closure is not built."""
    stage = stage or Stage(edges.sparkSession, "mutual")
    edges = edges.select("src", "dst").distinct()
    if (small := _small(edges, stage)) is not None:
        return small.intersect(small.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    edges, _ = stage.put(edges)
    owner, _ = stage.put(strong_components(edges, stage))
    sizes = owner.groupBy("component").agg(F.count("*").alias("n"))
    loops = edges.where("src = dst").select(F.col("src").alias("id"))
    inner = owner.join(sizes.where("n > 1").select("component"), "component").select("id", "component")
    inner = union(inner, owner.join(loops, "id").select("id", "component")).distinct()
    return inner.select(F.col("id").alias("src"), "component").join(inner.select(F.col("id").alias("dst"), "component"), "component").select("src", "dst")


def closure_with_witness(edges: DataFrame, stage: Stage | None = None) -> DataFrame:
    """(src, dst, nodes): a shortest path for each pair, as the array of its nodes."""
    stage = stage or Stage(edges.sparkSession, "witness")
    edges, _ = stage.put(edges.select("src", "dst").distinct())
    new, n = stage.put(edges.select("src", "dst", F.array("src", "dst").alias("nodes")))
    parts = [new]
    while n:
        longer = new.withColumnRenamed("dst", "_mid").join(edges.select(F.col("src").alias("_mid"), "dst"), "_mid").select("src", "dst", F.array_append("nodes", F.col("dst")).alias("nodes"))
        least = longer.groupBy("src", "dst").agg(F.min("nodes").alias("nodes"))
        new, n = stage.put(least.join(union(*(p.select("src", "dst") for p in parts)), ["src", "dst"], "left_anti"))
        parts.append(new)
    return union(*parts)


def closure_change(old_edges: DataFrame, old_closure: DataFrame, plus: DataFrame | None = None, minus_edges: DataFrame | None = None, stage: Stage | None = None, size: int | None = None) -> tuple[DataFrame, DataFrame | None]:
    """(plus, minus) of a closure under edge changes; minus is None if no edge goes. size: edges of plus, if known.

    Insertions start from the new edges, extended on both sides by the old closure, and are composed with one another in
    rounds that double how many new edges a path may have. Deletions recompute what the sources that reach a deleted edge
    reach now.
    """
    stage = stage or Stage(old_edges.sparkSession, "closure-change")
    if minus_edges is not None:
        kept = minus(old_edges, minus_edges)
        edges = kept if plus is None else union(kept, plus).distinct()
        lost = minus_edges.select(F.col("src").alias("dst")).distinct()
        touched = union(old_closure.join(lost, "dst", "left_semi").select(F.col("src").alias("id")), lost.select(F.col("dst").alias("id")))
        if plus is not None:
            more = plus.select(F.col("src").alias("dst")).distinct()
            touched = union(touched, old_closure.join(more, "dst", "left_semi").select(F.col("src").alias("id")), more.select(F.col("dst").alias("id")))
        touched, _ = stage.put(touched.distinct())
        before = old_closure.join(touched.withColumnRenamed("id", "src"), "src", "left_semi").select("src", "dst")
        after, _ = stage.put(closure(edges, sources=touched, stage=stage))
        out = stage.put(minus(after, before))[0], stage.put(minus(before, after))[0]
        stage.drop(touched, after)
        return out
    if size is not None and size <= SMALL_EDGES and (out := _small_change(old_closure, plus, stage)) is not None:
        return stage.keep(minus(out, old_closure), stage.put(out)[1] <= KEPT_ROWS)[0], None
    before_or_self = lambda d: union(d, compose(old_closure, d))
    after_or_self = lambda d: union(d, compose(d, old_closure))
    step, _ = stage.put(after_or_self(plus).distinct())  # a new edge, then old ones
    new, n = stage.put(before_or_self(step).distinct())
    parts = [new]
    while n:
        new, n = stage.put(minus(compose(new, union(*parts)).distinct(), union(*parts)))
        if n:
            parts.append(new)
    out = stage.put(minus(union(*parts), old_closure))[0]
    stage.drop(step, *parts)
    return out, None


def _small_change(old_closure: DataFrame, plus: DataFrame, stage: Stage) -> DataFrame | None:
    """Pairs that few new edges give, some of which may be old, if the driver can hold all that the old closure adds to
    the edges' ends; None otherwise."""
    near = union(
        plus.select("src", "dst", F.lit(0).alias("side")),
        old_closure.join(F.broadcast(plus.select(F.col("src").alias("dst")).distinct()), "dst", "left_semi").select("src", "dst", F.lit(1).alias("side")),
        old_closure.join(F.broadcast(plus.select(F.col("dst").alias("src")).distinct()), "src", "left_semi").select("src", "dst", F.lit(2).alias("side")),
    ).limit(SMALL_PAIRS + 1).toArrow()
    if near.num_rows > SMALL_PAIRS:
        return None
    src, dst, side = (near.column(c).to_numpy() for c in ("src", "dst", "side"))
    own = PairSet(np.unique(np.concatenate([src, dst])))
    new, into, out = (own.codes(np.stack([src[side == k], dst[side == k]])) for k in range(3))
    for compose in (lambda x: own.compose(into, x), lambda x: own.compose(x, out)):
        if (more := compose(new)) is None:
            return None
        new = np.union1d(new, more)
    new = own.closed(new)
    return None if new is None else table_of(stage, own.pairs(new))

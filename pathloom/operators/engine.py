"""Evaluation and incremental maintenance of programs over labelled graphs, one pass in dependency order.

A graph is a dictionary of relations by (label, closed), each a lazy table (src, dst). What a view never names is never
scanned. A change is staged once a label is done, so that its size is known to the driver and later decisions cost no
job; everything else stays lazy and is left to Catalyst. Old contents are never overwritten during a pass.
"""

from __future__ import annotations

import json
import uuid
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field, replace
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.rules import DELTA, NEW, NODES, Clause, Conj, Const, Eq, Lit, Program, Rel, RuleError, Var, choose_step, grounded, grounded_clause, grounded_program, mask_grid, prune_grid, slice_labels, stratify, symbols_of
from ..sources.staging import KEPT_ROWS, Stage, file_system
from .closure import closure, closure_change, minus, mutual, union

Symbol = tuple[str, bool]

#: The node domain as a relation, pairs (node, node).
DOMAIN: Symbol = (NODES, False)

#: Deltas of at most this many pairs are broadcast; larger ones are left to Spark's own choice.
BROADCAST_PAIRS = 100_000

#: Pairs that a task writes out of classes of nodes, about.
TASK_PAIRS = 5_000_000

#: Pairs that a task writes out where it finds the far nodes itself, and pairs of one of its rows, about: a row's are
#: buffered, and more of them leave the processor's caches.
FOUND_PAIRS, ROW_PAIRS = 40_000_000, 4_000

#: Nodes of a class that travel and are written out together, about; a task holds the pairs of two such blocks at once.
BLOCK_NODES = 200

#: Far nodes, and pairs of their blocks and middles, that each task may hold; beyond them pairs of classes are joined.
HELD_NODES, HELD_PAIRS = 1_000_000, 2_000_000

#: Ways to meet of a composition's blocks, at most, that are joined in any case.
JOINED_WAYS = 50_000_000


def as_pairs(nodes: DataFrame) -> DataFrame:
    return nodes.select(F.col("id").alias("src"), F.col("id").alias("dst"))


def ends(relations: Iterable[DataFrame]) -> DataFrame | None:
    """The nodes (id) that edges begin or end at, with repeats; None without relations."""
    parts = [d.select(F.col(c).alias("id")) for d in relations for c in ("src", "dst")]
    return union(*parts) if parts else None


@dataclass
class LabeledGraph:
    """Relations by (label, closed). domain: nodes (id) that are there even without edges. sizes: rows, where known."""

    spark: SparkSession
    relations: dict[Symbol, DataFrame]
    domain: DataFrame | None = None
    closure_method: str = "auto"
    sizes: dict[Symbol, int] = field(default_factory=dict)

    @staticmethod
    def from_relations(spark: SparkSession, relations: dict[str, DataFrame], domain: DataFrame | None = None) -> LabeledGraph:
        return LabeledGraph(spark, {(k, False): v for k, v in relations.items()}, domain)

    @staticmethod
    def from_edges(edges: DataFrame, labels: Iterable[str], domain: DataFrame | None = None) -> LabeledGraph:
        """From a table (label, src, dst): nulls and repeats go; a table partitioned by label is pruned by Spark."""
        own = {x: edges.where(F.col("label") == x).where("src IS NOT NULL AND dst IS NOT NULL").select("src", "dst").distinct() for x in labels}
        return LabeledGraph.from_relations(edges.sparkSession, own, domain)

    def labels(self) -> set[str]:
        return {k for k, _ in self.relations} - {NODES}

    def empty(self) -> DataFrame:
        return self.spark.createDataFrame([], "src long, dst long")

    def rel(self, label: str, closed: bool = False) -> DataFrame:
        """A relation; a closure that is not stored yet is computed and kept."""
        if (label, closed) == DOMAIN and DOMAIN not in self.relations:
            return as_pairs(self.nodes())
        if closed and (label, True) not in self.relations:
            self.relations[label, True] = closure(self.rel(label), self.closure_method) if (label, False) in self.relations else self.empty()
        return self.relations.get((label, closed)) if (label, closed) in self.relations else self.empty()

    def nodes(self, of: Iterable[str] | None = None) -> DataFrame:
        """The node domain (id): the stored one, or the given nodes and the end points of all edges (of some labels)."""
        if DOMAIN in self.relations:
            return self.relations[DOMAIN].select(F.col("src").alias("id"))
        of = None if of is None else set(of)
        own = ends(d for (x, closed), d in self.relations.items() if not closed and (of is None or x in of))
        given = None if self.domain is None else self.domain.select("id")
        both = [d for d in (given, own) if d is not None]
        return union(*both).distinct() if both else self.spark.createDataFrame([], "id long")

    def with_closures(self, labels: Iterable[str]) -> LabeledGraph:
        for x in labels:
            self.rel(x, True)
        return self

    def with_relations(self, relations: dict[Symbol, DataFrame], sizes: dict[Symbol, int] | None = None) -> LabeledGraph:
        return LabeledGraph(self.spark, relations, self.domain, self.closure_method, dict(sizes or {}))


@dataclass
class GraphUpdate:
    """Insertions and deletions by symbol; a symbol that is absent has none. fresh: symbols whose insertions are all new."""

    plus: dict[Symbol, DataFrame] = field(default_factory=dict)
    minus: dict[Symbol, DataFrame] = field(default_factory=dict)
    sizes: dict[Symbol, int] = field(default_factory=dict)
    fresh: set[Symbol] = field(default_factory=set)

    def labels(self) -> set[str]:
        return {k for k, _ in (*self.plus, *self.minus)}

    def is_empty(self, label: str) -> bool:
        return label not in self.labels()

    def changed(self) -> set[Symbol]:
        return set(self.plus) | set(self.minus)

    @staticmethod
    def from_feed(feed: DataFrame, on_overlap: str = "plus_wins", stage: Stage | None = None) -> GraphUpdate:
        """From a change feed (op + or -, label, src, dst), repeats and nulls dropped; one job counts all labels."""
        stage = stage or Stage(feed.sparkSession, "feed")
        rows = feed.where("label IS NOT NULL AND src IS NOT NULL AND dst IS NOT NULL").groupBy("label", "src", "dst").agg(F.max((F.col("op") == "+").cast("int")).alias("p"), F.max((F.col("op") == "-").cast("int")).alias("m"))
        rows, _ = stage.put(rows)
        counts = rows.groupBy("label").agg(F.sum("p").alias("p"), F.sum(F.when(F.col("p") == 0, 1).otherwise(0)).alias("m"), F.sum(F.col("p") * F.col("m")).alias("both")).collect()
        if on_overlap == "error" and any(r["both"] for r in counts):
            raise ValueError("an edge is both inserted and deleted")
        out = GraphUpdate()
        for r in counts:
            own = rows.where(F.col("label") == r["label"])
            if r["p"]:
                out.plus[r["label"], False], out.sizes[r["label"], False] = own.where("p = 1").select("src", "dst"), r["p"]
            if r["m"]:
                out.minus[r["label"], False] = own.where("p = 0").select("src", "dst")
        return out


# ---- updates

def updated(graph: LabeledGraph, u: GraphUpdate, symbol: Symbol) -> DataFrame:
    """A relation after an update."""
    out = graph.rel(*symbol)
    if symbol in u.minus:
        out = minus(out, u.minus[symbol])
    if symbol in u.plus:
        out = union(out, u.plus[symbol])
        out = out if symbol in u.fresh else out.distinct()
    return out


def apply_update(graph: LabeledGraph, u: GraphUpdate) -> LabeledGraph:
    relations = dict(graph.relations)
    for s in u.changed():
        relations[s] = updated(graph, u, s)
    sizes = {s: n + (u.sizes.get(s, 0)) for s, n in graph.sizes.items() if s not in u.minus and (s not in u.plus or s in u.sizes)}
    sizes |= {s: u.sizes[s] for s in u.plus if s in u.sizes and s not in graph.relations}
    return graph.with_relations(relations, sizes)


def replace_label(u: GraphUpdate, symbol: Symbol, plus: DataFrame | None, gone: DataFrame | None) -> GraphUpdate:
    """An update whose entry for a symbol is another; an edge in both is inserted."""
    out = GraphUpdate({k: v for k, v in u.plus.items() if k != symbol}, {k: v for k, v in u.minus.items() if k != symbol}, dict(u.sizes))
    if plus is not None:
        out.plus[symbol] = plus
    if gone is not None:
        out.minus[symbol] = gone if plus is None else minus(gone, plus)
    return out


def diff_as_update(current: DataFrame, target: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(plus, minus) that lead from one relation to another."""
    return minus(target, current), minus(current, target)


def canonical(u: GraphUpdate, graph: LabeledGraph, stage: Stage | None = None) -> GraphUpdate:
    """Without insertions of what is there and deletions of what is not; insertions win over deletions.

    With a stage, the parts are written, empty ones go, and the sizes are known.
    """
    out = GraphUpdate()
    for s, plus in u.plus.items():
        out.plus[s] = minus(plus.distinct(), graph.rel(*s)) if s in graph.relations else plus.distinct()
    for s, gone in u.minus.items():
        gone = gone.distinct().join(graph.rel(*s), ["src", "dst"], "left_semi")
        out.minus[s] = minus(gone, u.plus[s]) if s in u.plus else gone
    return out if stage is None else staged_update(out, stage)


def staged_update(u: GraphUpdate, stage: Stage) -> GraphUpdate:
    """An update with its parts written, empty ones gone and the sizes known."""
    out = GraphUpdate()
    for s in u.changed():
        _put(out, s, u.plus.get(s), u.minus.get(s), stage)
    return out


def compose_updates(first: GraphUpdate, second: GraphUpdate) -> GraphUpdate:
    """One update that does what two do in turn."""
    out = GraphUpdate()
    for s in first.changed() | second.changed():
        p1, m1, p2, m2 = (d.get(s) for d in (first.plus, first.minus, second.plus, second.minus))
        plus = p1 if m2 is None or p1 is None else minus(p1, m2)
        plus = p2 if plus is None else plus if p2 is None else union(plus, p2).distinct()
        gone = m1 if p2 is None or m1 is None else minus(m1, p2)
        gone = m2 if gone is None else gone if m2 is None else union(gone, m2).distinct()
        if plus is not None:
            out.plus[s] = plus
        if gone is not None:
            out.minus[s] = gone
    return out


# ---- matching

def match_literal(relation: DataFrame, lit: Lit) -> DataFrame:
    """Substitutions of a literal: a column for each of its variables, constants and repeats as filters."""
    a, b = lit.atom.terms
    out = relation
    for term, column in ((a, "src"), (b, "dst")):
        if isinstance(term, Const):
            out = out.where(F.col(column) == term.id)
    if isinstance(a, Var) and a == b:
        return out.where("src = dst").select(F.col("src").alias(f"v_{a.name}"))
    return out.select(*(F.col(c).alias(f"v_{t.name}") for t, c in ((a, "src"), (b, "dst")) if isinstance(t, Var)))


def apply_equality(rows: DataFrame, atom: Eq) -> DataFrame | None:
    """Filter by an equality or bind its free variable; None if nothing in it is bound."""
    value = lambda t: F.lit(t.id) if isinstance(t, Const) else F.col(f"v_{t.name}") if f"v_{t.name}" in rows.columns else None
    a, b = (value(t) for t in atom.terms)
    if a is not None and b is not None:
        return rows.where(a == b)
    if a is None and b is None:
        return None
    free = atom.a if a is None else atom.b
    return rows.withColumn(f"v_{free.name}", (b if a is None else a).cast("long"))


def match_body(conj: Conj, head: tuple[Var, Var], resolve, spark: SparkSession, first: int | None = None, method: str = "join") -> DataFrame:
    """Substitutions of a body as (src, dst) of its head; not distinct.

    Literals join on shared variables, from the one at `first` on (a delta) and then along connected ones. One that holds
    both variables of the head bounds the result and comes as early as it can. Variables
    that neither the head nor a literal still to come needs go at once, and repeats with them. resolve gives a
    literal's relation, that of the node domain for variables that nothing binds. method="nested_loop" matches by cross
    products and filters, as a baseline.
    """
    conj = grounded(conj, head)
    todo = [(k, lit) for k, lit in enumerate(conj) if isinstance(lit.atom, Rel)]
    equals = [lit.atom for lit in conj if isinstance(lit.atom, Eq)]
    rows: DataFrame | None = None
    names = lambda lit: {t.name for t in lit.atom.terms if isinstance(t, Var)}
    have: set[str] = set()
    bounds = lambda lit: method == "join" and {v.name for v in head} <= names(lit)

    def settle() -> None:
        nonlocal rows
        again = True
        while again and rows is not None:
            again = False
            for e in list(equals):
                if (out := apply_equality(rows, e)) is not None:
                    rows, again = out, True
                    equals.remove(e)
                    have.update(t.name for t in e.terms if isinstance(t, Var))

    def prune() -> None:
        nonlocal rows
        need = {v.name for v in head} | {n for _, lit in todo for n in names(lit)} | {t.name for e in equals for t in e.terms if isinstance(t, Var)}
        if todo and have - need:
            rows = rows.select(*(f"v_{n}" for n in sorted(have & need))).distinct()
            have.intersection_update(need)

    if not todo:  # constants only
        rows = spark.range(1).select()
        settle()
    while todo:
        if rows is None:
            k = next((i for i, (at, lit) in enumerate(todo) if (bounds(lit) if first is None else at == first)), 0)
        else:
            k = next((i for i, (_, lit) in enumerate(todo) if names(lit) <= have), None)
            k = next((i for i, (_, lit) in enumerate(todo) if names(lit) & have and bounds(lit)), None) if k is None else k
            k = next((i for i, (_, lit) in enumerate(todo) if names(lit) & have), 0) if k is None else k
        _, lit = todo.pop(k)
        own = match_literal(resolve(lit), lit)
        if rows is None:
            rows = own
        elif shared := sorted(names(lit) & have):
            if method == "nested_loop":
                far = own.select(*(F.col(f"v_{n}").alias(f"w_{n}" if n in shared else f"v_{n}") for n in sorted(names(lit))))
                rows = rows.crossJoin(far).where(reduce(lambda x, y: x & y, (F.col(f"v_{n}") == F.col(f"w_{n}") for n in shared))).drop(*(f"w_{n}" for n in shared))
            else:
                rows = rows.join(own, [f"v_{n}" for n in shared])
        else:
            rows = rows.crossJoin(own)
        have |= names(lit)
        settle()
        prune()
    return rows.select(F.col(f"v_{head[0].name}").alias("src"), F.col(f"v_{head[1].name}").alias("dst"))


def shortcuts(conj: Conj, head: tuple[Var, Var], resolve) -> list[tuple[Lit, Lit, Lit]]:
    """(two literals, the literal that takes their place), in turn, for variables that only those two hold and the head does not.

    The pair with the smallest join goes first, so a body in a bad order does not make all pairs of nodes that meet at a few
    others. Only for bodies with a choice of two such variables; sizes of their relations take one job.
    """
    body = [lit for lit in grounded(conj, head) if isinstance(lit.atom, Rel)]
    names = lambda lit: {t.name for t in lit.atom.terms if isinstance(t, Var)}
    kept = {v.name for v in head} | {t.name for lit in conj if isinstance(lit.atom, Eq) for t in lit.atom.terms if isinstance(t, Var)}
    held = lambda v: [lit for lit in body if v in names(lit)]

    def free() -> list[tuple[str, Lit, Lit]]:
        inner = sorted(set().union(*map(names, body)) - kept)
        two = [(v, *held(v)) for v in inner if len(held(v)) == 2]
        return [(v, a, b) for v, a, b in two if len(names(a)) == len(names(b)) == 2 and names(a) != names(b)]

    if len(body) < 3 or len(free()) < 2:
        return []
    used = sorted({lit.symbol for lit in body})
    parts = [resolve(next(lit for lit in body if lit.symbol == s)).agg(F.lit(k).alias("k"), F.count("*").alias("n"), F.approx_count_distinct("src").alias("a"), F.approx_count_distinct("dst").alias("b")) for k, s in enumerate(used)]
    sizes = {used[r["k"]]: (r["n"], r["a"], r["b"]) for r in union(*parts).collect()}
    # Rows and distinct values by variable of each literal.
    size = {lit: (sizes[lit.symbol][0], {t.name: n for t, n in zip(lit.atom.terms, sizes[lit.symbol][1:], strict=True) if isinstance(t, Var)}) for lit in body}
    out = []
    while todo := free():
        rows = lambda v, a, b: size[a][0] * size[b][0] / max(1, size[a][1][v], size[b][1][v])
        v, a, b = min(todo, key=lambda x: (rows(*x), x[0]))
        x, y = (next(iter(names(lit) - {v})) for lit in (a, b))
        new = Lit(Rel(f"@{len(out)}", Var(x), Var(y)))
        size[new] = min(rows(v, a, b), size[a][1][x] * size[b][1][y]), {x: size[a][1][x], y: size[b][1][y]}
        out.append((a, b, new))
        body = [lit for lit in body if lit not in (a, b)] + [new]
    return out


def _middle(conj: Conj, head: tuple[Var, Var]) -> tuple[Lit, Lit, str] | None:
    """The literals of the head's first and second variable and the variable between, of a body that only composes two."""
    if len(conj) != 2 or not all(isinstance(lit.atom, Rel) and all(isinstance(t, Var) for t in lit.atom.terms) for lit in conj):
        return None
    x, y = (v.name for v in head)
    for a, b in (conj, conj[::-1]):
        ends = [{t.name for t in lit.atom.terms} for lit in (a, b)]
        if x != y and len(shared := ends[0] & ends[1]) == 1 and ends[0] - shared == {x} and ends[1] - shared == {y}:
            return a, b, next(iter(shared))
    return None


def by_classes(conj: Conj, head: tuple[Var, Var], resolve, sizes, stage: Stage) -> DataFrame | None:
    """The distinct pairs of a body that composes two large relations; None for other bodies, and where the sizes (a function
    of a literal, None if unknown) are not known to be large.

    Nodes of the same neighbours in the middle are one class, in blocks. Pairs of classes are made distinct, or, where they may
    have many ways to meet and the far side's blocks fit in a task, each near block finds its far nodes there. Either way
    pairs of nodes are written out of blocks: each node is in one block of one class, so none comes twice.
    """
    if (found := _middle(conj, head)) is None:
        return None
    a, b, z = found
    counts = [sizes(lit) for lit in (a, b)]
    if None in counts or sum(counts) <= KEPT_ROWS or 0 in counts:
        return None

    def side(lit: Lit) -> tuple[DataFrame, DataFrame, int, int]:
        """(class, its middles), (class, middles, block, its nodes), and the numbers of blocks and nodes."""
        rows = match_literal(resolve(lit), lit).select(F.col(f"v_{next(t.name for t in lit.atom.terms if t.name != z)}").alias("id"), F.col(f"v_{z}").alias("z"))
        own, n = stage.put(rows.groupBy("id").agg(F.sort_array(F.collect_set("z")).alias("zs")))
        classes = own.groupBy("zs").agg(F.min("id").alias("c"), F.count("*").alias("n"))
        place = F.pmod(F.xxhash64("id"), F.ceil(F.col("n") / BLOCK_NODES)).alias("k")
        blocks, m = stage.put(own.join(classes, "zs").groupBy("zs", "c", place).agg(F.collect_list("id").alias("ids")))
        return blocks.groupBy("c").agg(F.first("zs").alias("zs")), blocks, m, n

    near = side(a)
    far = near if a.symbol == b.symbol and [t.name == z for t in a.atom.terms] == [t.name == z for t in b.atom.terms] else side(b)
    held = far[1].agg(F.sum(F.size("zs"))).first()[0] or 0
    if held * near[2] > JOINED_WAYS and far[3] <= HELD_NODES and held <= HELD_PAIRS:
        pairs = _met_in_task(near[1], far[1].select("zs", "ids").toArrow(), lambda most: min(near[2], min(near[3] * far[3], counts[0] * most) // FOUND_PAIRS + 1))
    else:
        pairs = _met_by_join(*near[:3], *far[:3], stage)
    return pairs.select(F.explode("ids").alias("src"), "far").select("src", F.explode("far").alias("dst"))


def _met_in_task(near: DataFrame, far, tasks) -> DataFrame:
    """(ids, far): the nodes of near blocks (zs, ids) and, in parts, of all far blocks that share a middle with them.

    far: an Arrow table (zs, ids), which every task holds. tasks: their number, by the most far nodes of a middle. The
    far blocks of a block are a set by their numbers, so no more work than ways to meet, and no more pairs than come out.
    """
    zs, ids = (far.column(c).combine_chunks() for c in ("zs", "ids"))
    begin, nodes = ids.offsets.to_numpy(), ids.values.to_numpy()
    every, block = zs.values.to_numpy(), np.repeat(np.arange(len(zs)), np.diff(zs.offsets.to_numpy()))
    order = np.argsort(every, kind="stable")
    middles, first = np.unique(every[order], return_index=True)
    ends = np.append(first, len(every))
    most = int(np.add.reduceat(np.diff(begin)[block[order]], first).max())
    held = near.sparkSession.sparkContext.broadcast((middles, ends, block[order], begin, nodes))
    width = ROW_PAIRS

    def met(batches: Iterator) -> Iterator:
        import numpy as np
        import pyarrow as pa

        middles, ends, block, begin, nodes = held.value
        sizes = np.diff(begin)

        def far_of(zs: np.ndarray) -> np.ndarray:
            at = np.searchsorted(middles, zs)
            at = at[(at < len(middles)) & (middles[np.minimum(at, len(middles) - 1)] == zs)]
            ways = [block[ends[k] : ends[k + 1]] for k in at]
            if sum(map(len, ways)) * 8 < len(sizes):
                found = np.unique(np.concatenate(ways)) if ways else block[:0]
            else:
                mask = np.zeros(len(sizes), bool)
                for w in ways:
                    mask[w] = True
                found = np.flatnonzero(mask)
            n = sizes[found]
            return nodes[np.repeat(begin[found] - (np.cumsum(n) - n), n) + np.arange(n.sum())]

        def table(left: list, right: list):
            lists = [pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, x)]), pa.int32()), pa.array(np.concatenate(x), pa.int64())) for x in (left, right)]
            return pa.RecordBatch.from_arrays(lists, names=["ids", "far"])

        for rows in batches:
            own, zs = rows.column(0), rows.column(1)
            (o, x), (p, y) = ((c.offsets.to_numpy(), c.values.to_numpy()) for c in (own, zs))
            left, right, n = [], [], 0
            for k in range(rows.num_rows):
                ids, far = x[o[k] : o[k + 1]], far_of(y[p[k] : p[k + 1]])
                step = max(1, width // len(ids))
                for i in range(0, len(far), step):
                    left.append(ids)
                    right.append(far[i : i + step])
                    n += len(ids) + len(right[-1])
                    if n > 250_000:
                        yield table(left, right)
                        left, right, n = [], [], 0
            if n:
                yield table(left, right)

    return near.repartition(tasks(most), "c", "k").select("ids", "zs").mapInArrow(met, "ids array<long>, far array<long>")


def _met_by_join(near: DataFrame, ids: DataFrame, n: int, far: DataFrame, far_ids: DataFrame, n_far: int, stage: Stage) -> DataFrame:
    """As _met_in_task, by a join of both sides' classes, whose pairs are made distinct; n, n_far: numbers of blocks."""
    zs = stage.put(near.select("c", F.explode("zs").alias("z")))
    far_zs = zs if far is near else stage.put(far.select("c", F.explode("zs").alias("z")))
    # A class's pairs are made distinct where they arise if what they join fits in each task.
    own, other = zs[0].repartition("c"), far_zs[0].select(F.col("c").alias("d"), "z")
    met, _ = stage.put(own.join(F.broadcast(other) if far_zs[1] <= BROADCAST_PAIRS else other, "z").select("c", "d").distinct())
    ids, far_ids = ids.select("c", "k", "ids"), far_ids.select(F.col("c").alias("d"), F.col("k").alias("m"), F.col("ids").alias("far"))
    held = lambda t, n: F.broadcast(t) if n <= BROADCAST_PAIRS else t
    work = met.join(ids.select("c", "k", F.size("ids").cast("double").alias("n")), "c").join(far_ids.select("d", "m", F.size("far").alias("n_far")), "d")
    tasks = int((work.agg(F.sum(F.col("n") * F.col("n_far"))).first()[0] or 0) // TASK_PAIRS) + 1  # few blocks may stand for many pairs
    pairs = work.select("c", "k", "d", "m").repartition(tasks, "c", "k", "d", "m")
    return pairs.join(held(ids, n), ["c", "k"]).join(held(far_ids, n_far), ["d", "m"]).select("ids", "far")


def copies(conj: Conj, head: tuple[Var, Var]) -> bool:
    """Whether a body is one relation's pairs, as they are or turned."""
    return len(conj) == 1 and isinstance(conj[0].atom, Rel) and set(conj[0].atom.terms) == set(head) and len(set(head)) == 2


def with_copied(program: Program, labels: Iterable[str]) -> set[str]:
    """The labels, and in turn each derived one that a single literal reads, the whole body of one of them."""
    out, todo = set(labels), list(labels)
    read = [lit.atom.label for c in program.clauses.values() for b in c.bodies for lit in b if isinstance(lit.atom, Rel)]
    while todo:
        clause = program.clauses.get(todo.pop())
        if clause is not None and len(clause.bodies) == 1 and copies(clause.bodies[0], clause.head):
            x = clause.bodies[0][0].atom.label
            if x in program.clauses and read.count(x) == 1 and x not in out:
                out.add(x)
                todo.append(x)
    return out


def symmetric(clause: Clause) -> bool:
    """Whether a clause plainly holds each pair both ways: its body stays the same with the head's variables exchanged."""
    x, y = clause.head
    turn = lambda t: y if t == x else x if t == y else t
    return len(clause.bodies) == 1 and {replace(lit, atom=replace(lit.atom, a=turn(lit.atom.a), b=turn(lit.atom.b))) for lit in clause.bodies[0]} == set(clause.bodies[0])


def without_repeats(p: Program) -> Program:
    """Bodies that only turn a symmetric label's pairs go where another body holds them as they are."""
    both = {x for x, c in p.clauses.items() if symmetric(c)}

    def key(body: Conj):
        turned = lambda lit: isinstance(lit.atom, Rel) and lit.atom.label in both
        return frozenset((lit.atom.label, lit.closed, frozenset(lit.atom.terms)) if turned(lit) else lit for lit in body)

    return Program({x: Clause(c.head, tuple({key(b): b for b in reversed(c.bodies)}.values())[::-1]) for x, c in p.clauses.items()})


def _mutual_label(conj: Conj) -> str | None:
    """The label of a body that only asks for a closure pair both ways."""
    if len(conj) != 2 or not all(lit.closed and isinstance(lit.atom, Rel) for lit in conj):
        return None
    a, b = (lit.atom for lit in conj)
    return a.label if a.label == b.label and (a.a, a.b) == (b.b, b.a) and a.a != a.b and all(isinstance(t, Var) for t in a.terms) else None


def derive(clause: Clause, graph: LabeledGraph, method: str = "join", stage: Stage | None = None) -> DataFrame:
    """A clause's head pairs from scratch.

    Pairs that must reach each other come from strong components, without the closure, where that is not stored. A single
    body that copies a relation, or composes two large ones, gives no pair twice.
    """
    if not clause.bodies:
        return graph.empty()
    if method == "join" and len(clause.bodies) == 1:
        body = grounded(clause.bodies[0], clause.head)
        resolve = lambda lit: graph.rel(*lit.symbol)
        if copies(body, clause.head):
            return match_body(body, clause.head, resolve, graph.spark)
        if (out := by_classes(body, clause.head, resolve, lambda lit: graph.sizes.get(lit.symbol), stage or Stage(graph.spark))) is not None:
            return out
    parts = []
    for b in clause.bodies:
        label = _mutual_label(b)
        if label is not None and (label, True) not in graph.relations and method == "join":
            parts.append(mutual(graph.rel(label)))
        else:
            held: dict[Symbol, DataFrame] = {}
            resolve = lambda lit, held=held: held[lit.symbol] if lit.symbol in held else graph.rel(*lit.symbol)
            for left, right, new in shortcuts(b, clause.head, resolve) if method == "join" else []:
                held[new.symbol] = match_body((left, right), new.atom.terms, resolve, graph.spark).distinct()
                b = (*(lit for lit in grounded(b, clause.head) if lit not in (left, right)), new)
            parts.append(match_body(b, clause.head, resolve, graph.spark, method=method))
    return union(*parts).distinct()


def match_masked(conj: Conj, head: tuple[Var, Var], graph: LabeledGraph, u: GraphUpdate) -> DataFrame:
    """A tagged body: OLD reads the graph, DELTA the insertions, NEW both; the delta leads the joins."""

    def resolve(lit: Lit) -> DataFrame:
        s = lit.symbol
        if lit.tag == DELTA:
            plus = u.plus[s]
            return F.broadcast(plus) if u.sizes.get(s, BROADCAST_PAIRS + 1) <= BROADCAST_PAIRS else plus
        if lit.tag == NEW and s in u.plus:
            return union(graph.rel(*s), u.plus[s])  # heads are made distinct, and canonical updates repeat nothing
        return graph.rel(*s)

    first = next(k for k, lit in enumerate(conj) if lit.tag == DELTA)
    return match_body(conj, head, resolve, graph.spark, first)


def delta_rows(clause: Clause, graph: LabeledGraph, u: GraphUpdate, factoring: str = "old_prefix") -> list[tuple[int, DataFrame]]:
    """(place of the delta literal, its pairs) of each mask row that changes can fill: none that reads an absent relation."""
    out, held = [], set(graph.relations) | {DOMAIN}
    for body in grounded_clause(clause).bodies:
        for row in prune_grid(mask_grid(body, factoring), set(u.plus)):
            if any(lit.symbol not in held and (lit.atom.label, False) not in held for lit in row if isinstance(lit.atom, Rel) and lit.tag not in (DELTA, NEW)):
                continue
            out.append((next(k for k, lit in enumerate(row) if lit.tag == DELTA), match_masked(row, clause.head, graph, u)))
    return out


def maintain_label(clause: Clause, current: DataFrame | None, graph: LabeledGraph, u: GraphUpdate, factoring: str = "old_prefix", stage: Stage | None = None) -> DataFrame | None:
    """Insertions of a head label; None if no row can have any. current: None if it holds no pair, so that none is old."""
    rows = [d for _, d in delta_rows(clause, graph, u, factoring)]
    if not rows:
        return None
    if current is not None:
        return minus(union(*rows).distinct(), current)
    new = apply_update(graph, u)
    body = grounded(clause.bodies[0], clause.head)
    if len(clause.bodies) == 1 and copies(body, clause.head):
        return rows[0]
    out = by_classes(body, clause.head, lambda lit: new.rel(*lit.symbol), lambda lit: new.sizes.get(lit.symbol), stage or Stage(graph.spark)) if len(clause.bodies) == 1 else None
    return union(*rows).distinct() if out is None else out


def node_change(graph: LabeledGraph, u: GraphUpdate, base: Iterable[str]) -> tuple[DataFrame | None, DataFrame | None]:
    """(plus, minus) of the node domain under an update of base labels.

    Ends of new edges come; ends of deleted ones go if no edge is left there, and they are not given ones.
    """
    base = set(base)
    new, lost = (ends(d for (x, closed), d in part.items() if x in base and not closed) for part in (u.plus, u.minus))
    plus = None if new is None else minus(as_pairs(new.distinct()), graph.rel(*DOMAIN))
    if lost is None:
        return plus, None
    lost = lost.distinct()
    for (x, closed) in {s for s in (*graph.relations, *u.plus) if s[0] in base and not s[1]}:
        left = updated(graph, u, (x, closed))
        for c in ("src", "dst"):
            lost = lost.join(left.select(F.col(c).alias("id")), "id", "left_anti")
    if graph.domain is not None:
        lost = lost.join(graph.domain.select("id"), "id", "left_anti")
    return plus, as_pairs(lost)


def close_update(graph: LabeledGraph, u: GraphUpdate, labels: Iterable[str], stage: Stage, policy: str = "paper") -> GraphUpdate:
    """An update with the changes of the closures that the labels store."""
    out = GraphUpdate(dict(u.plus), dict(u.minus), dict(u.sizes))
    for x in sorted(set(labels) & u.labels()):
        if (x, False) in u.changed() and (x, True) not in u.changed():
            _put_closure(out, graph, x, stage, policy)
    return out


def _put_closure(u: GraphUpdate, graph: LabeledGraph, label: str, stage: Stage, policy: str = "paper") -> None:
    """Add the change of a label's closure; the closure is made anew if nothing was there, or (cost) less than comes."""
    s, plus, gone = (label, False), None, None
    if s in u.plus and s not in u.minus:
        before = graph.sizes.get(s) if policy == "cost" else None
        if s not in graph.relations:
            plus = closure(u.plus[s], graph.closure_method, stage=stage)
        elif before is not None and u.sizes.get(s, 0) > before:
            plus = minus(closure(union(graph.rel(label), u.plus[s]), graph.closure_method, stage=stage), graph.rel(label, True))
    if plus is None:
        plus, gone = closure_change(graph.rel(label), graph.rel(label, True), u.plus.get(s), u.minus.get(s), stage, u.sizes.get(s))
    _put(u, (label, True), plus, gone, stage)


def _put(u: GraphUpdate, s: Symbol, plus: DataFrame | None, gone: DataFrame | None, stage: Stage, small: bool = False) -> None:
    for table, part in ((u.plus, plus), (u.minus, gone)):
        if part is not None:
            part, n = stage.keep(part, small)
            if n:
                table[s] = part
                if table is u.plus:
                    u.sizes[s] = n


def _is_small(graph: LabeledGraph, u: GraphUpdate, clause: Clause, label: str) -> bool:
    """Whether all that a clause step reads is known to be small."""
    used = {lit.symbol for b in clause.bodies for lit in b} - {None} | {(label, False)}
    known = lambda s: s not in graph.relations and (s[0], False) not in graph.relations or graph.sizes.get(s, KEPT_ROWS + 1) <= KEPT_ROWS
    return all(known(s) and (s not in u.plus or u.sizes.get(s, KEPT_ROWS + 1) <= KEPT_ROWS) for s in used)


def run_pass(program: Program, graph: LabeledGraph, trusted: Iterable[str], u: GraphUpdate, todo: list[str] | None = None, factoring: str = "old_prefix", policy: str = "paper", stage: Stage | None = None, steps: list | None = None, after=None, lazy: Iterable[str] = ()) -> GraphUpdate:
    """The update of all labels of todo, in order, after an update of base labels.

    Trusted labels hold what the program derives from the graph; others are rebuilt. policy="cost" rebuilds labels and
    closures that grow by more than they held. steps, if given, collects (label, step); after is called with each
    label, the update so far and the labels that are done. lazy: labels that no other one reads, whose insertions are left as
    plans, of unknown size; so are those of labels that only one of them reads, as a copy.
    """
    if bad := sorted(x for x in u.labels() if x in program.clauses):
        raise RuleError(f"derived labels cannot be updated: {', '.join(bad)}")
    stage = stage or Stage(graph.spark)
    todo = stratify(program) if todo is None else todo
    closed, base = program.closed_labels(), program.base_labels()
    program = grounded_program(without_repeats(program))
    if any(NODES in symbols_of(program.clauses[x]) for x in todo) and DOMAIN not in graph.relations:
        graph = graph.with_relations(graph.relations | {DOMAIN: as_pairs(graph.nodes(base))}, graph.sizes)
    u = close_update(graph, u, closed, stage, policy)
    if u.changed() and any(NODES in symbols_of(program.clauses[x]) for x in todo):
        _put(u, DOMAIN, *node_change(graph, u, base), stage)
    done, lazy = base | (set(program.clauses) - set(todo)), with_copied(program, lazy)
    for label in todo:
        clause = program.clauses[label]
        sizes = _sizes(graph, clause) if policy == "cost" and label in set(trusted) else None
        step = choose_step(label, clause, trusted, set(u.minus), u.changed(), sizes, u.sizes, policy)
        if steps is not None:
            steps.append((label, step))
        if step != "skip":
            current = graph.rel(label)
            if step == "incremental":
                none = (label, False) not in graph.relations or graph.sizes.get((label, False)) == 0
                plus, gone = maintain_label(clause, None if none else current, graph, u, factoring, stage), None
            else:
                target, _ = stage.put(derive(clause, apply_update(graph, u), stage=stage))
                plus, gone = diff_as_update(current, target)
            u.fresh.add((label, False))
            if label in lazy and label not in closed and gone is None:
                if plus is not None:
                    u.plus[label, False] = plus
            else:
                _put(u, (label, False), plus, gone, stage, _is_small(graph, u, clause, label))
            if label in closed and (label, False) in u.changed():
                _put_closure(u, graph, label, stage, policy)
        done.add(label)
        if after is not None:
            after(label, u, set(done))
    return u


def _sizes(graph: LabeledGraph, clause: Clause) -> dict[Symbol, int]:
    """Rows of the relations that a clause reads, counted where they are not known yet."""
    for s in {lit.symbol for b in clause.bodies for lit in b} - {None}:
        if s not in graph.sizes and s in graph.relations:
            graph.sizes[s] = graph.rel(*s).count()
    return graph.sizes


def materialize(program: Program, graph: LabeledGraph, views: Iterable[str] | None = None, method: str = "join", stage: Stage | None = None, store: bool = False) -> LabeledGraph:
    """The graph with the derived labels that the views need; labels are staged only where a closure or several literals
    read them. store: stage all, with the closures that maintenance reads, and note the sizes."""
    keep = set().union(*(slice_labels(program, v) for v in views)) if views is not None else set(program.clauses) | program.base_labels()
    own = grounded_program(without_repeats(Program({k: c for k, c in program.clauses.items() if k in keep})))
    out = graph.with_relations(dict(graph.relations), graph.sizes)
    stage = stage or Stage(graph.spark)

    def put(s: Symbol, pairs: DataFrame) -> None:
        out.relations[s], out.sizes[s] = stage.put(pairs)

    if store:
        for s in [s for s in out.relations if s[0] in keep]:
            put(s, out.relations[s])
    if DOMAIN not in out.relations and any(NODES in symbols_of(c) for c in own.clauses.values()):
        put(DOMAIN, as_pairs(out.nodes(program.base_labels() & keep)))
    uses = [lit.atom.label for c in own.clauses.values() for b in c.bodies for lit in b if isinstance(lit.atom, Rel)]
    closed = own.closed_labels()
    for label in stratify(own):
        pairs = derive(own.clauses[label], out, method, stage)
        if store or label in closed or uses.count(label) > 1:
            put((label, False), pairs)
        else:
            out.relations[label, False] = pairs
    if store:
        for x in sorted(closed):
            if (x, True) not in out.relations and (x, False) in out.relations:
                put((x, True), out.rel(x, True))
    return out


def maintain(program: Program, graph: LabeledGraph, u: GraphUpdate, factoring: str = "old_prefix", policy: str = "paper", trusted: Iterable[str] | None = None, stage: Stage | None = None, steps: list | None = None, lazy: Iterable[str] = ()) -> GraphUpdate:
    """The update of a materialised graph: incremental where nothing was deleted, rebuilt elsewhere."""
    return run_pass(program, graph, set(program.clauses) | graph.labels() if trusted is None else trusted, u, None, factoring, policy, stage, steps, lazy=lazy)


class ViewStore:
    """Versions of a materialised graph in a folder; readers keep the version they opened.

    A version is a manifest that names the folder and size of every relation. Each attempt to write one has a folder of its
    own, and its manifest appears by a rename when all is written, so a crash leaves at most a folder that nothing names.
    """

    def __init__(self, spark: SparkSession, folder: str, program: Program):
        self.spark, self.folder, self.program = spark, folder.rstrip("/"), program

    def _manifests(self) -> dict[int, str]:
        """Committed version to the path of its manifest."""
        path, fs = file_system(self.spark, f"{self.folder}/versions")
        names = [s.getPath().getName() for s in fs.listStatus(path)] if fs.exists(path) else []
        return {int(n[1:]): f"{self.folder}/versions/{n}" for n in names if n[:1] == "v" and n[1:].isdigit()}

    def version(self) -> int:
        return max(self._manifests(), default=-1)

    def _read(self, version: int | None = None) -> dict:
        every = self._manifests()
        if not every:
            return {"relations": {}, "batches": [], "streams": {}}
        text = self.spark.read.text(every[max(every) if version is None else version], wholetext=True).first()[0]
        return json.loads(text)

    def batches(self) -> list[str]:
        return self._read()["batches"]

    def _commit(self, relations: dict[Symbol, DataFrame], state: dict) -> None:
        """A new version: the relations given, and those of the state as they are."""
        version, attempt = self.version() + 1, uuid.uuid4().hex
        kept = dict(state["relations"])
        for k, (s, d) in enumerate(sorted(relations.items(), key=lambda x: x[0])):
            path = f"{self.folder}/data/{attempt}/{k}"
            d.write.parquet(path)
            kept[f"{s[0]}{'+' if s[1] else ''}"] = [path, self.spark.read.schema("src long, dst long").parquet(path).count()]
        text = json.dumps(state | {"relations": kept})
        draft, fs = file_system(self.spark, f"{self.folder}/versions/draft-{attempt}")
        out = fs.create(draft, True)
        out.write(bytearray(text.encode()))
        out.close()
        final, _ = file_system(self.spark, f"{self.folder}/versions/v{version:09d}")
        if fs.exists(final) or not fs.rename(draft, final):
            raise ValueError(f"version {version} was committed by another writer")

    def create(self, graph: LabeledGraph, batch: str = "create") -> LabeledGraph:
        full = materialize(self.program, graph, store=True)
        relations = dict(full.relations)
        if graph.domain is not None:
            relations["@given", False] = as_pairs(graph.domain.select("id").distinct())
        self._commit(relations, {"relations": {}, "batches": [batch], "streams": {}})
        return self.graph()

    def graph(self, version: int | None = None) -> LabeledGraph:
        """The graph of a version, the newest by default."""
        return self._graph(self._read(version))

    def _graph(self, state: dict) -> LabeledGraph:
        read = self.spark.read.schema("src long, dst long")
        held = {(k.removesuffix("+"), k.endswith("+")): (read.parquet(path), n) for k, (path, n) in state["relations"].items()}
        given, _ = held.pop(("@given", False), (None, 0))
        domain = None if given is None else given.select(F.col("src").alias("id"))
        return LabeledGraph(self.spark, {s: d for s, (d, _) in held.items()}, domain, sizes={s: n for s, (_, n) in held.items()})

    def read(self, view: str, closed: bool = False) -> DataFrame:
        return self.graph().rel(view, closed)

    def apply(self, u: GraphUpdate, batch: str, number: int | None = None, policy: str = "paper") -> bool:
        """Maintain under an update; False if the batch was applied before. Only changed relations are written.

        number: the place of an update in the stream that `batch` names; those up to the last one applied are replays.
        """
        state = self._read()
        if batch in state["batches"] if number is None else state["streams"].get(batch, -1) >= number:
            return False
        graph, stage = self._graph(state), Stage(self.spark, "apply")
        u = maintain(self.program, graph, canonical(u, graph, stage), policy=policy, stage=stage)
        seen = {"batches": [*state["batches"], batch]} if number is None else {"streams": state["streams"] | {batch: number}}
        self._commit({s: updated(graph, u, s) for s in u.changed()}, state | seen)
        stage.clear()
        return True

    def vacuum(self) -> int:
        """Remove what the newest version does not name: replaced relations, those of attempts that failed, and older
        manifests; the number of relations removed. No other writer may be at work."""
        every = self._manifests()
        top, fs = file_system(self.spark, f"{self.folder}/data")
        named, n = {fs.makeQualified(file_system(self.spark, path)[0]).toString() for path, _ in self._read()["relations"].values()}, 0
        for a in fs.listStatus(top) if fs.exists(top) else []:
            for b in fs.listStatus(a.getPath()):
                if b.getPath().toString() not in named:
                    fs.delete(b.getPath(), True)
                    n += 1
        for v in set(every) - {max(every, default=0)}:
            fs.delete(file_system(self.spark, every[v])[0], True)
        return n

"""The semantics as checks: stored closures, models, supported facts, the update law, preconditions."""

from __future__ import annotations

from collections.abc import Iterable
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.rules import NODES, Clause, Conj, Program, Rel, Var, is_slice, is_stratified, variables
from .closure import closure, compose, minus
from .engine import GraphUpdate, LabeledGraph, apply_update, derive, match_literal, run_pass


def holds(graph: LabeledGraph, label: str, a: int, b: int, closed: bool = False) -> bool:
    """Whether a ground literal is satisfied: a point lookup."""
    return bool(graph.rel(label, closed).where((F.col("src") == a) & (F.col("dst") == b)).limit(1).count())


def is_path(edges: DataFrame, start: int, nodes: list[int]) -> bool:
    """Whether consecutive nodes after the start are joined by edges; the empty list is a path."""
    if not nodes:
        return True
    steps = edges.sparkSession.createDataFrame(list(zip([start, *nodes[:-1]], nodes, strict=True)), "src long, dst long")
    return minus(steps, edges).isEmpty()


def path_label(edges: DataFrame, nodes: list[int]) -> DataFrame:
    """(labels) of a path over edges (label, src, dst): for each step, the sorted labels that make it."""
    steps = edges.sparkSession.createDataFrame([(k, a, b) for k, (a, b) in enumerate(zip(nodes, nodes[1:], strict=False))], "step int, src long, dst long")
    return steps.join(edges, ["src", "dst"]).groupBy("step").agg(F.sort_array(F.collect_set("label")).alias("labels")).orderBy("step")


def closure_sound(graph: LabeledGraph, label: str) -> DataFrame:
    """Stored closure pairs without a path."""
    return minus(graph.rel(label, True), closure(graph.rel(label)))


def closure_complete(graph: LabeledGraph, label: str) -> DataFrame:
    """Pairs that a stored closure lacks, by one step: edges, and edges followed by stored pairs."""
    stored = graph.rel(label, True)
    return minus(graph.rel(label).unionByName(compose(graph.rel(label), stored)).distinct(), stored)


def well_formed(graph: LabeledGraph) -> DataFrame:
    """label, unsound, missing of every stored closure."""
    rows = [(x, closure_sound(graph, x).count(), closure_complete(graph, x).count()) for x, closed in sorted(graph.relations) if closed]
    return graph.spark.createDataFrame(rows, "label string, unsound long, missing long")


def groundings(nodes: DataFrame, names: list[str]) -> DataFrame:
    """All assignments of nodes to variables; for tiny domains only."""
    return reduce(DataFrame.crossJoin, (nodes.select(F.col("id").alias(f"v_{n}")) for n in names))


def body_holds(rows: DataFrame, graph: LabeledGraph, conj: Conj) -> DataFrame:
    """The groundings that satisfy a body."""
    for lit in conj:
        if isinstance(lit.atom, Rel):
            own = match_literal(graph.rel(*lit.symbol), lit)
            rows = rows.join(own, own.columns, "left_semi")
        else:
            a, b = (F.col(f"v_{t.name}") if isinstance(t, Var) else F.lit(t.id) for t in lit.atom.terms)
            rows = rows.where(a == b)
    return rows


def exhaustive_violations(graph: LabeledGraph, label: str, clause: Clause) -> DataFrame:
    """As clause_violations, by trying every grounding."""
    parts = []
    for conj in clause.bodies:
        names = list(dict.fromkeys([v.name for v in clause.head] + variables(conj)))
        rows = body_holds(groundings(graph.nodes(), names), graph, conj)
        parts.append(rows.select(*(F.col(f"v_{v.name}").alias(c) for v, c in zip(clause.head, ("src", "dst"), strict=True))))
    return minus(reduce(DataFrame.unionByName, parts).distinct(), graph.rel(label))


def clause_violations(graph: LabeledGraph, label: str, clause: Clause) -> DataFrame:
    """Heads that a body gives and the label lacks."""
    return minus(derive(clause, graph), graph.rel(label))


def unsupported(graph: LabeledGraph, label: str, clause: Clause) -> DataFrame:
    """Stored pairs of a derived label that no body gives."""
    return minus(graph.rel(label), derive(clause, graph))


def is_model(graph: LabeledGraph, p: Program, labels: Iterable[str] | None = None) -> DataFrame:
    """label, violations, unsupported for each derived label."""
    rows = [(x, clause_violations(graph, x, p.clauses[x]).count(), unsupported(graph, x, p.clauses[x]).count()) for x in sorted(p.clauses if labels is None else labels) if x in p.clauses]
    return graph.spark.createDataFrame(rows, "label string, violations long, unsupported long")


def models(graph: LabeledGraph, p: Program, labels: Iterable[str] | None = None) -> bool:
    return all(r["violations"] == 0 for r in is_model(graph, p, labels).collect())


def is_disjoint(u: GraphUpdate) -> bool:
    return all(u.plus[s].join(u.minus[s], ["src", "dst"], "left_semi").isEmpty() for s in set(u.plus) & set(u.minus))


def exact_diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """missing, extra: how many pairs of b are not in a, and of a not in b."""
    count = lambda d, name: d.agg(F.count("*").alias(name))
    return count(minus(b, a), "missing").crossJoin(count(minus(a, b), "extra"))


def law_holds(old: DataFrame, plus: DataFrame | None, gone: DataFrame | None, new: DataFrame) -> bool:
    """Whether a view and its change give the view of the updated graph."""
    out = old if gone is None else minus(old, gone)
    out = out if plus is None else out.unionByName(plus).distinct()
    r = exact_diff(out, new).first()
    return r["missing"] == 0 and r["extra"] == 0


def check_preconditions(p: Program, graph: LabeledGraph, trusted: Iterable[str], u: GraphUpdate, done: Iterable[str], todo: list[str], debug: bool = True) -> dict[str, bool]:
    """The five conditions under which a pass gives a model.

    H1 the trusted labels are a model before the update; H2 done is closed under dependencies; H3 the update is of done
    labels, disjoint, and of no derived one; H4 todo is stratified after done; H5 the done labels are a model after it.
    """
    done = set(done)
    out = {"H2": is_slice(p, done), "H3": u.labels() <= done and not u.labels() & set(todo) and is_disjoint(u), "H4": is_stratified(p, done, todo)}
    if debug:
        out["H1"] = models(graph, p, set(trusted) & set(p.clauses))
        out["H5"] = models(apply_update(graph, u), p, done & set(p.clauses))
    return out


def contained_on(a: DataFrame, b: DataFrame) -> DataFrame:
    """Pairs of one view that another lacks: counterexamples to containment on this graph."""
    return minus(a, b)


def step_invariants(p: Program, graph: LabeledGraph, u: GraphUpdate, trusted: Iterable[str] | None = None, **options) -> DataFrame:
    """step, label, and what must hold after each label of a pass: the labels that are done are a slice and a model under
    the update so far, which is disjoint and of done labels only."""
    trusted = set(p.clauses) | graph.labels() if trusted is None else trusted
    rows = []

    def after(label: str, so_far: GraphUpdate, done: set[str]) -> None:
        inside = so_far.labels() - {NODES} <= done
        rows.append((len(rows) + 1, label, models(apply_update(graph, so_far), p, done), is_disjoint(so_far), inside, is_slice(p, done)))

    run_pass(p, graph, trusted, u, after=after, **options)
    return graph.spark.createDataFrame(rows, "step int, label string, model boolean, disjoint boolean, inside boolean, slice boolean")


def modular_holds(graph: LabeledGraph, p: Program, a: set[str], b: set[str]) -> bool:
    """Satisfied on two sets of labels implies satisfied on their union."""
    return not (models(graph, p, a) and models(graph, p, b)) or models(graph, p, a | b)


def unaffected_holds(graph: LabeledGraph, p: Program, labels: set[str], u: GraphUpdate) -> bool:
    """An update that changes nothing in a slice leaves it satisfied if it was."""
    if not is_slice(p, labels):
        raise ValueError("the labels do not hold all that they depend on")
    if u.labels() & labels:
        raise ValueError("the update changes the slice")
    return not models(graph, p, labels) or models(apply_update(graph, u), p, labels)

"""Maintenance equals rebuilding: node domains that change, stores that crash, generated programs against plain Python."""

import random
from itertools import product

import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st

from pathloom.operators import verify
from pathloom.operators.closure import SMALL_EDGES, closure, closure_change, mutual
from pathloom.operators import closure as closures
from pathloom.operators.engine import GraphUpdate, LabeledGraph, ViewStore, apply_update, canonical, maintain, materialize
from pathloom.plans.rules import Const, Eq, complete, grounded, parse_rules, program, stratify, variables
from pathloom.plans.workload import random_views
from pathloom.sources.staging import Stage
from pathloom.surface import open_graph, path_view, register_views

from test_engine import got, pairs, reach


def graph_of(spark, rel, domain=None):
    return LabeledGraph.from_relations(spark, {k: pairs(spark, v) for k, v in rel.items()}, domain)


def evaluated(p, rel):
    """A program's relations by trying all assignments of nodes to variables."""
    rel = {k: set(v) for k, v in rel.items()}
    nodes = sorted({n for k in p.base_labels() for e in rel.get(k, ()) for n in e})
    for label in stratify(p):
        clause, out = p.clauses[label], set()
        for body in clause.bodies:
            names = list(dict.fromkeys([v.name for v in clause.head] + variables(body)))
            closed = {lit.atom.label: reach(rel.get(lit.atom.label, set())) for lit in body if lit.closed}
            for values in product(nodes, repeat=len(names)):
                at = dict(zip(names, values, strict=True))
                of = lambda t, at=at: t.id if isinstance(t, Const) else at[t.name]
                if all(of(lit.atom.a) == of(lit.atom.b) if isinstance(lit.atom, Eq) else (of(lit.atom.a), of(lit.atom.b)) in (closed[lit.atom.label] if lit.closed else rel.get(lit.atom.label, set())) for lit in body):
                    out.add((at[clause.head[0].name], at[clause.head[1].name]))
        rel[label] = out
    return rel


def test_reflexive_closures_follow_new_nodes(spark, tmp_path):
    p = program({"v": "a*"})
    full = materialize(p, graph_of(spark, {"a": [(1, 2)]}), store=True)
    assert got(full.rel("v")) == {(1, 1), (1, 2), (2, 2)}
    u = GraphUpdate({("a", False): pairs(spark, [(3, 4)])})
    want = {(1, 1), (1, 2), (2, 2), (3, 3), (3, 4), (4, 4)}
    assert got(apply_update(full, maintain(p, full, u)).rel("v")) == want
    store = ViewStore(spark, str(tmp_path / "store"), p)
    store.create(graph_of(spark, {"a": [(1, 2)]}))
    assert store.apply(u, "new") and got(store.read("v")) == want
    assert store.apply(GraphUpdate(minus={("a", False): pairs(spark, [(1, 2)])}), "gone")
    assert got(store.read("v")) == {(3, 3), (3, 4), (4, 4)}


def test_given_nodes_stay(spark, tmp_path):
    p = program({"v": "a*"})
    store = ViewStore(spark, str(tmp_path / "store"), p)
    store.create(graph_of(spark, {"a": [(1, 2)]}, spark.range(1, 4)))
    store.apply(GraphUpdate(minus={("a", False): pairs(spark, [(1, 2)])}), "gone")
    assert got(store.read("v")) == {(1, 1), (2, 2), (3, 3)}


def test_a_stopped_attempt_changes_nothing(spark, tmp_path, monkeypatch):
    p = program({"v": "a/b"})
    store = ViewStore(spark, str(tmp_path / "store"), p)
    store.create(graph_of(spark, {"a": [(1, 2)], "b": [(2, 3)]}))

    class Stopped(Exception):
        pass

    def stop(*args, **options):
        raise Stopped

    with monkeypatch.context() as m:
        m.setattr("pathloom.operators.engine.json.dumps", stop)  # all is written but the manifest
        with pytest.raises(Stopped):
            store.apply(GraphUpdate({("a", False): pairs(spark, [(9, 9)])}), "one")
    assert got(store.graph().rel("a")) == {(1, 2)} and store.version() == 0
    assert store.apply(GraphUpdate({("b", False): pairs(spark, [(2, 4)])}), "two") and store.version() == 1
    assert got(store.graph().rel("a")) == {(1, 2)} and got(store.read("v")) == {(1, 3), (1, 4)}
    assert got(store.graph(0).rel("v")) == {(1, 3)}
    assert store.apply(GraphUpdate({("a", False): pairs(spark, [(9, 9)])}), "one") and store.vacuum() > 0
    assert got(store.graph().rel("a")) == {(1, 2), (9, 9)} and store.batches() == ["create", "two", "one"]


def test_numbered_batches_are_told_by_their_stream(spark, tmp_path):
    store = ViewStore(spark, str(tmp_path / "store"), program({"v": "a"}))
    store.create(graph_of(spark, {"a": []}))
    one = lambda k: GraphUpdate({("a", False): pairs(spark, [(k, k)])})
    assert store.apply(one(1), "x", 0) and store.apply(one(2), "x", 1) and not store.apply(one(3), "x", 1)
    assert store.apply(one(4), "y", 0) and got(store.read("v")) == {(1, 1), (2, 2), (4, 4)}


def test_empty_changes_are_none(spark):
    p = program({"v": "a/b"})
    full = materialize(p, graph_of(spark, {"a": [(1, 2)], "b": [(2, 3)]}), store=True)
    u = canonical(GraphUpdate({("a", False): pairs(spark, [(1, 2)])}, {("b", False): pairs(spark, [(7, 7)])}), full, Stage(spark))
    steps = []
    maintain(p, full, u, steps=steps)
    assert not u.changed() and steps == [("v", "skip")]


def test_cost_policy_rebuilds_what_grows_most(spark):
    p = program({"v": "a/b", "w": "b/b"})
    full = materialize(p, graph_of(spark, {"a": [(1, 2)], "b": [(k, k + 1) for k in range(40)]}), store=True)
    u = canonical(GraphUpdate({("a", False): pairs(spark, [(k, k + 1) for k in range(300)]), ("b", False): pairs(spark, [(999, 998)])}), full, Stage(spark))
    for policy, want in (("paper", ["incremental"] * 2), ("cost", ["rebuild", "incremental"])):
        steps = []
        after = apply_update(full, maintain(p, full, u, policy=policy, steps=steps))
        assert [s for _, s in steps] == want
        assert got(after.rel("v")) == {(k, k + 2) for k in range(39)} | {(1, 3)}


def test_steps_keep_what_the_proof_needs(spark):
    p = program({"v": "a+/b", "w": "v*/a"})
    full = materialize(p, graph_of(spark, {"a": [(1, 2), (2, 3)], "b": [(3, 1)], "c": [(5, 6)]}), store=True)
    u = GraphUpdate({("a", False): pairs(spark, [(3, 4)])}, {("b", False): pairs(spark, [(3, 1)])})
    rows = verify.step_invariants(p, full, u).collect()
    assert [r["label"] for r in rows] == ["v", "w"] and all(all(r[c] for c in ("model", "disjoint", "inside", "slice")) for r in rows)
    assert verify.unaffected_holds(full, p, {"v", "a", "b"}, GraphUpdate({("c", False): pairs(spark, [(6, 7)])}))
    with pytest.raises(ValueError, match="changes the slice"):
        verify.unaffected_holds(full, p, {"v", "a", "b"}, u)
    with pytest.raises(ValueError, match="depend on"):
        verify.unaffected_holds(full, p, {"w"}, u)


LABELS = ("a", "b")
edges = st.sets(st.tuples(st.integers(0, 4), st.integers(0, 4)), max_size=5)
paths = st.recursive(st.sampled_from(LABELS), lambda p: st.one_of(st.builds("{}/{}".format, p, p), st.builds("({} | {})".format, p, p), st.builds("({} & {})".format, p, p), st.builds("(~{})".format, p), st.builds("({})+".format, p), st.builds("({})*".format, p)), max_leaves=3)


@settings(max_examples=12, deadline=None, suppress_health_check=list(HealthCheck), derandomize=True)
@given(path=paths, rel=st.fixed_dictionaries({x: edges for x in LABELS}), plus=st.fixed_dictionaries({x: edges for x in LABELS}), gone=st.sampled_from(["", "a", "b"]))
def test_generated_programs(spark, path, rel, plus, gone):
    p = program({"v": path})
    full = materialize(p, graph_of(spark, rel), store=True)
    assert got(full.rel("v")) == evaluated(p, rel)["v"]
    u = GraphUpdate({(x, False): pairs(spark, d) for x, d in plus.items()}, {(gone, False): pairs(spark, sorted(rel[gone])[:2])} if gone else {})
    u = canonical(u, full, Stage(spark))
    new = {x: (rel[x] - (set(sorted(rel[x])[:2]) if x == gone else set())) | plus[x] for x in LABELS}
    assert got(apply_update(full, maintain(p, full, u)).rel("v")) == evaluated(p, new)["v"]


def test_grounding_binds_what_bodies_leave_open():
    clause = complete(parse_rules("p(A, B) :- q(A, A). p(A, B) :- A = 3, B = C.")).clauses["p"]
    added = [[str(lit.atom.label) for lit in grounded(b, clause.head) if not isinstance(lit.atom, Eq)] for b in clause.bodies]
    assert added == [["q", "@nodes"], ["@nodes"]]


def test_large_graphs_are_closed_in_rounds(spark, monkeypatch):
    rng = random.Random(4)
    old, plus = ({(rng.randrange(30), rng.randrange(30)) for _ in range(n)} for n in (25, 12))
    plus -= old
    want = reach(old | plus)
    for edges, most in ((SMALL_EDGES, 2_000_000), (5, 2_000_000), (SMALL_EDGES, 10)):
        monkeypatch.setattr(closures, "SMALL_EDGES", edges)
        monkeypatch.setattr(closures, "SMALL_PAIRS", most)
        assert got(closure(pairs(spark, old | plus))) == want
        assert got(closure_change(pairs(spark, old), pairs(spark, reach(old)), pairs(spark, plus), size=len(plus))[0]) == want - reach(old)
        assert got(mutual(pairs(spark, old | plus))) == {(a, b) for a, b in want if (b, a) in want}


def test_large_components_leave_the_single_task(spark, monkeypatch):
    monkeypatch.setattr(closures, "LOCAL_EDGES", 3)
    edges = {(1, 2), (2, 3), (3, 1), (3, 4), (4, 5), (10, 11), (11, 12), (20, 20)}
    assert got(closure(pairs(spark, edges), "local")) == reach(edges)


def test_update_law_with_new_nodes(spark):
    p = program({"v": "a*/b | ~b"})
    full = materialize(p, graph_of(spark, {"a": [(1, 2)], "b": [(2, 3)]}), store=True)
    u = maintain(p, full, GraphUpdate({("a", False): pairs(spark, [(7, 1)]), ("b", False): pairs(spark, [(9, 9)])}))
    new = materialize(p, graph_of(spark, {"a": [(1, 2), (7, 1)], "b": [(2, 3), (9, 9)]})).rel("v")
    assert verify.law_holds(full.rel("v"), u.plus.get(("v", False)), u.minus.get(("v", False)), new)
    assert not verify.law_holds(full.rel("v"), None, None, new)


def test_bucketed_relations_compose_without_exchange(spark, tmp_path):
    from pathloom.operators.closure import compose
    from pathloom.sources.feeds import save_bucketed

    a = save_bucketed(pairs(spark, [(1, 2), (5, 6)]), "bucketed_a", 4, "dst", str(tmp_path / "a"))
    b = save_bucketed(pairs(spark, [(2, 3), (2, 4)]), "bucketed_b", 4, "src", str(tmp_path / "b"))
    try:
        out = compose(a, b.hint("merge"))
        plan = out._jdf.queryExecution().executedPlan().toString()
        assert got(out) == {(1, 3), (1, 4)} and "SortMergeJoin" in plan and "Exchange" not in plan
    finally:
        spark.sql("DROP TABLE bucketed_a")
        spark.sql("DROP TABLE bucketed_b")


def test_surface(spark, tmp_path):
    from pathloom.sources.feeds import write_edges

    write_edges(spark.createDataFrame([("a", 1, 2), ("b", 2, 3), ("a", 2, 2)], "label string, src long, dst long"), str(tmp_path / "edges"))
    graph = open_graph(spark, str(tmp_path / "edges"))
    assert graph.labels() == {"a", "b"} and got(path_view(graph, "a/b")) == {(1, 3), (2, 3)}
    assert register_views(spark, graph, "own_") == ["own_a", "own_b"]
    assert spark.sql("SELECT count(*) FROM own_a").first()[0] == 2
    path = spark.createDataFrame([("a", 1, 2), ("b", 1, 2), ("b", 2, 3)], "label string, src long, dst long")
    assert [r["labels"] for r in verify.path_label(path, [1, 2, 3]).collect()] == [["a", "b"], ["b"]]


def test_generated_views_fit_their_schema():
    schema = {"a": ("x", "x"), "b": ("x", "y"), "c": ("y", "z")}
    views = random_views(schema, 20, seed=3)
    assert len(views) == 20 and views == random_views(schema, 20, seed=3) and all(stratify(p) for p in views.values())
    assert any(p.closed_labels() for p in views.values())


def test_stages_drop_what_is_read_no_more(spark):
    stage = Stage(spark, "drops")
    one, n = stage.put(spark.range(3))
    two, _ = stage.put(spark.range(5))
    stage.clear(keep=(two,))
    assert n == 3 and two.count() == 5 and len(stage.paths) == 1

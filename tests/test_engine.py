import random

import pytest

from pathloom.operators import verify
from pathloom.operators.closure import METHODS, closure, closure_change, closure_with_witness
from pathloom.operators.engine import GraphUpdate, LabeledGraph, ViewStore, apply_update, canonical, delta_rows, maintain, match_body, materialize
from pathloom.plans.rules import RuleError, complete, parse_rules, program, stratify
from pathloom.queries import detectable_fixture
from pathloom.views import AUDIENCE, RING


def pairs(spark, rows):
    return spark.createDataFrame(list(rows), "src long, dst long")


def got(df):
    rows = [tuple(r) for r in df.select("src", "dst").collect()]
    assert len(rows) == len(set(rows))
    return set(rows)


def reach(edges):
    out = set(edges)
    while more := {(a, d) for a, b in out for c, d in edges if b == c} - out:
        out |= more
    return out


SHAPES = {"loop": [(1, 1)], "two": [(1, 2), (2, 1)], "diamond": [(1, 2), (1, 3), (2, 4), (3, 4)], "empty": [], "repeats": [(1, 2), (1, 2), (2, 3)], "knot": [(1, 2), (2, 3), (3, 1), (3, 4), (4, 5), (5, 4), (6, 1)]}


@pytest.mark.parametrize("method", METHODS)
def test_closures_agree(spark, method):
    for name, edges in SHAPES.items():
        if method != "sql" or name not in ("loop", "two", "knot"):
            assert got(closure(pairs(spark, edges), method)) == reach(edges), name


@pytest.mark.parametrize("method", ["naive", "frontier", "sql"])
def test_long_paths_take_few_rounds(spark, method):
    from pathloom.sources.staging import Stage

    chains = [(k, k + 1) for k in range(1, 150)] + [(1000 + k, 1001 + k) for k in range(17)] + [(1005, 1012), (1002, 1009)]
    rings = [] if method == "sql" else [(2000 + k, 2000 + (k + 1) % 13) for k in range(13)] + [(1017, 2000)]
    stage = Stage(spark, "long")
    assert got(closure(pairs(spark, chains + rings), method, stage=stage)) == reach(chains + rings)
    assert stage.n <= 30


def test_sql_closure_refuses_cycles(spark):
    with pytest.raises(ValueError, match="cycles"):
        closure(pairs(spark, SHAPES["two"]), "sql")


def test_long_chain_seeds_witness_and_budget(spark):
    chain = pairs(spark, [(k, k + 1) for k in range(1, 64)])
    assert closure(chain).count() == 2016
    assert got(closure(chain, sources=spark.createDataFrame([(60,)], "id long"))) == {(60, b) for b in range(61, 65)}
    assert got(closure(chain, targets=spark.createDataFrame([(3,)], "id long"))) == {(1, 3), (2, 3)}
    row = closure_with_witness(pairs(spark, SHAPES["diamond"])).where("src = 1 AND dst = 4").first()
    assert row["nodes"] == [1, 2, 4]
    with pytest.raises(ValueError, match="more than 100"):
        closure(chain, max_pairs=100)


def test_closure_changes(spark):
    rng = random.Random(3)
    for _ in range(3):
        old = {(rng.randrange(9), rng.randrange(9)) for _ in range(10)}
        plus = {(rng.randrange(9), rng.randrange(9)) for _ in range(3)} - old
        gone = set(rng.sample(sorted(old), 2))
        p, m = closure_change(pairs(spark, old), pairs(spark, reach(old)), pairs(spark, plus))
        assert m is None and got(p) == reach(old | plus) - reach(old)
        p, m = closure_change(pairs(spark, old), pairs(spark, reach(old)), pairs(spark, plus), pairs(spark, gone))
        new = reach((old - gone) | plus)
        assert got(p) == new - reach(old) and got(m) == reach(old) - new


def test_detectable_rows_by_factoring(spark):
    p, graph, u = detectable_fixture(spark)
    clause = p.clauses["detectable"]
    assert got(materialize(p, graph).rel("detectable")) == {(6, 0), (3, 0)}
    rows = {f: [got(d.distinct()) for _, d in delta_rows(clause, graph, u, f)] for f in ("old_prefix", "new_prefix")}
    assert rows == {"old_prefix": [{(2, 0)}, set(), {(0, 2), (0, 5)}], "new_prefix": [set(), {(2, 0)}, {(0, 2), (0, 5)}]}
    full = materialize(p, graph)
    for f in ("old_prefix", "new_prefix", "expanded"):
        out = maintain(p, full, u, f)
        assert got(out.plus["detectable", False]) == {(0, 2), (2, 0), (0, 5)}


def test_two_hop_delta_keeps_old_partners(spark):
    p = program({"v": "r/s"})
    graph = materialize(p, LabeledGraph.from_relations(spark, {"r": pairs(spark, [(1, 2)]), "s": pairs(spark, [(2, 3), (5, 6)])}))
    for f in ("old_prefix", "new_prefix", "expanded"):
        assert got(maintain(p, graph, GraphUpdate({("r", False): pairs(spark, [(4, 5)])}), f).plus["v", False]) == {(4, 6)}


def test_payment_network(spark):
    base = {"connected": [(k, k + 1) for k in range(1, 6)], "monitors": [(7, k) for k in range(2, 6)], "transfer": [(1, 6), (6, 1)]}
    for more, guarded, vetted in (([], set(), set()), ([(7, 2), (7, 3), (7, 4)], {(1, 4), (1, 5), (1, 6), (2, 5), (2, 6), (3, 6)}, {(1, 6)})):
        graph = LabeledGraph.from_relations(spark, {k: pairs(spark, v) for k, v in base.items()} | {"accredited": pairs(spark, [(6, 1), (7, 1), *more])})
        full = materialize(RING, graph)
        assert got(full.rel("guarded")) == guarded and got(full.rel("vetted")) == vetted
        assert got(full.rel("ring")) == {(1, 1), (1, 6), (6, 1), (6, 6)} and got(full.rel("handoff")) == {(1, 6), (6, 1)}


def test_brand_audience(spark):
    likes = pairs(spark, [(k, 100) for k in range(8)])
    ads = pairs(spark, [*((k, 100) for k in range(7)), (7, 101), (101, 100)])
    graph = LabeledGraph.from_relations(spark, {"likes": likes, "advertises": ads, "follows": pairs(spark, [(10 + k, k) for k in range(8)])})
    full = materialize(AUDIENCE, graph)
    assert [full.rel(x).count() for x in ("endorses", "exposed", "clients", "audience")] == [8, 16, 256, 256]


def test_maintenance_equals_rebuilding_and_checks_hold(spark):
    p = program({"a": "x+ & y", "b": "a/~x | y*/x", "c": "b+"})
    rng = random.Random(5)
    some = lambda n: {(rng.randrange(7), rng.randrange(7)) for _ in range(n)}
    rel = {"x": some(8), "y": some(12)}
    domain = spark.range(7)
    graph = LabeledGraph.from_relations(spark, {k: pairs(spark, v) for k, v in rel.items()}, domain)
    full = materialize(p, graph).with_closures(p.closed_labels())
    plus = {k: some(3) - v for k, v in rel.items()}
    gone = {"x": set(rng.sample(sorted(rel["x"]), 2))}
    for minus in ({}, gone):
        u = GraphUpdate({(k, False): pairs(spark, v) for k, v in plus.items() if v}, {(k, False): pairs(spark, v) for k, v in minus.items()})
        after = apply_update(full, maintain(p, full, u))
        fresh = materialize(p, LabeledGraph.from_relations(spark, {k: pairs(spark, (v - minus.get(k, set())) | plus[k]) for k, v in rel.items()}, domain))
        for label in ("a", "b", "c"):
            assert got(after.rel(label)) == got(fresh.rel(label)), (label, minus)
        assert verify.models(after, p) and all(r["unsupported"] == 0 for r in verify.is_model(after, p).collect())
    report = verify.check_preconditions(p, full, {"a", "b", "c"}, GraphUpdate(), {"x", "y"}, stratify(p))
    assert all(report.values())
    assert all(r["unsound"] == r["missing"] == 0 for r in verify.well_formed(full).collect())
    assert verify.exhaustive_violations(full, "a", p.clauses["a"]).isEmpty()
    assert verify.modular_holds(full, p, {"a"}, {"b"})


def test_updates_on_derived_labels_are_rejected(spark):
    p = program({"v": "r/s"})
    graph = materialize(p, LabeledGraph.from_relations(spark, {"r": pairs(spark, []), "s": pairs(spark, [])}))
    with pytest.raises(RuleError, match="derived"):
        maintain(p, graph, GraphUpdate({("v", False): pairs(spark, [(1, 2)])}))


def test_canonical_feeds_and_points(spark):
    graph = LabeledGraph.from_relations(spark, {"r": pairs(spark, [(1, 2), (2, 3)])})
    feed = spark.createDataFrame([("+", "r", 1, 2), ("+", "r", 5, 6), ("-", "r", 5, 6), ("-", "r", 2, 3), ("-", "r", 8, 8), ("+", None, 1, 1)], "op string, label string, src long, dst long")
    u = canonical(GraphUpdate.from_feed(feed), graph)
    assert got(u.plus["r", False]) == {(5, 6)} and got(u.minus["r", False]) == {(2, 3)}
    with pytest.raises(ValueError):
        GraphUpdate.from_feed(feed, on_overlap="error")
    assert verify.holds(graph, "r", 1, 2) and not verify.holds(graph, "r", 2, 1)
    assert verify.is_path(graph.rel("r"), 1, [2, 3]) and not verify.is_path(graph.rel("r"), 1, [3])


def test_constants_repeats_and_free_heads(spark):
    p = complete(parse_rules("k(1, 2). l(A, A) :- r(A, A). f(A, B) :- r(A, A). c(A, B) :- r(1, A), r(A, B)."))
    graph = LabeledGraph.from_relations(spark, {"r": pairs(spark, [(1, 1), (1, 2), (2, 3)])})
    full = materialize(p, graph)
    assert got(full.rel("k")) == {(1, 2)} and got(full.rel("l")) == {(1, 1)}
    assert got(full.rel("f")) == {(1, 1), (1, 2), (1, 3)} and got(full.rel("c")) == {(1, 1), (1, 2), (2, 3)}


def test_store_applies_batches_once(spark, tmp_path):
    p = program({"v": "r+/s"})
    store = ViewStore(spark, str(tmp_path / "store"), p)
    store.create(LabeledGraph.from_relations(spark, {"r": pairs(spark, [(1, 2)]), "s": pairs(spark, [(2, 9)])}))
    u = GraphUpdate({("r", False): pairs(spark, [(0, 1)])})
    assert store.apply(u, "one") and not store.apply(u, "one")
    assert got(store.read("v")) == {(1, 9), (0, 9)} and store.version() == 1
    assert store.apply(GraphUpdate(minus={("r", False): pairs(spark, [(1, 2)])}), "two")
    assert got(store.read("v")) == set() and store.vacuum() > 0


def test_small_deltas_are_broadcast_and_other_labels_not_read(spark):
    from pathloom.queries import graph_for
    from pathloom.views import VIEWS

    graph = graph_for(spark, "/root/testdata/sf0.001", *VIEWS["d2"])
    assert graph.labels() == {"placed_F_1", "contains_RF"}
    u = GraphUpdate({("placed_F_1", False): pairs(spark, [(1, 2)])}, sizes={("placed_F_1", False): 1})
    plan = delta_rows(VIEWS["d2"][1].clauses["d2"], graph, u)[0][1]._jdf.queryExecution().explainString(spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    assert "BroadcastHashJoin" in plan and "Cartesian" not in plan and "customer.parquet" not in plan


def _order(spark, text, first=None):
    """The labels of a rule's body in the order in which they join."""
    clause, asked = complete(parse_rules(text)).clauses["v"], []

    def resolve(lit):
        asked.append(lit.atom.label)
        return pairs(spark, [(1, 2)])

    match_body(clause.bodies[0], clause.head, resolve, spark, first)
    return asked


def test_what_bounds_the_head_joins_early(spark):
    rule = "v(X, Y) :- r(X, Z), s(Y, Z), g(X, Y)."
    assert _order(spark, rule) == ["g", "r", "s"]
    assert _order(spark, rule, 0) == ["r", "g", "s"] and _order(spark, rule, 1) == ["s", "g", "r"]


def test_variables_of_two_literals_go_by_size(spark):
    """A body that begins with all pairs of nodes at one hub takes the small join first, with the same pairs."""
    from pathloom.operators.engine import derive, shortcuts

    clause = complete(parse_rules("v(X, Y) :- r(X, A), r(B, A), r(B, Y), s(X, C), s(D, C), r(D, Y).")).clauses["v"]
    graph = LabeledGraph.from_relations(spark, {"r": pairs(spark, [(k, -(k % 2)) for k in range(200)]), "s": pairs(spark, [(k, 1000 + k // 3) for k in range(200)])})
    first = shortcuts(clause.bodies[0], clause.head, lambda lit: graph.rel(*lit.symbol))[0]
    assert {t.name for lit in first[:2] for t in lit.atom.terms} != {"X", "A", "B"} and first[2].atom.label == "@0"
    want = {(x, -(d % 2)) for x in range(200) for d in range(200) if x // 3 == d // 3 and -(d % 2) == -(x % 2)}
    assert got(derive(clause, graph)) == want


def test_incremental_from_nothing_by_classes(spark, monkeypatch):
    """A composition of relations that are large (here: all are) makes pairs of classes distinct, also from an empty view."""
    from pathloom.operators import engine

    rng = random.Random(3)
    r, s = ({(rng.randrange(40), 100 + rng.randrange(6)) for _ in range(70)} for _ in range(2))
    want = {(x, y) for x, a in r for y, b in s if a == b}
    made, by_classes = [], engine.by_classes
    monkeypatch.setattr(engine, "KEPT_ROWS", 0)
    monkeypatch.setattr(engine, "by_classes", lambda *a: made.append(by_classes(*a)) or made[-1])
    p = complete(parse_rules("v(X, Y) :- r(X, Z), s(Y, Z)."))
    full = materialize(p, LabeledGraph.from_relations(spark, {"r": pairs(spark, r)}), store=True)
    u = maintain(p, full, GraphUpdate({("s", False): pairs(spark, s)}, sizes={("s", False): len(s)}), lazy=["v"])
    assert got(apply_update(full, u).rel("v")) == want and made[-1] is not None
    assert ("v", False) in u.fresh and ("v", False) not in u.sizes


@pytest.mark.parametrize("few", [True, False])
def test_a_label_that_only_a_lazy_one_copies_is_not_staged(spark, monkeypatch, few):
    """Pairs come from blocks of classes, and the label between them and the view is left as a plan as well."""
    from pathloom.operators import engine

    rng = random.Random(5)
    r = {(x, 1000 + rng.randrange(3)) for x in range(40)} | {(rng.randrange(60), 1000 + rng.randrange(5)) for _ in range(50)}
    want = {(x, y) for x, a in r for y, b in r if a == b}
    monkeypatch.setattr(engine, "KEPT_ROWS", 0)
    monkeypatch.setattr(engine, "BLOCK_NODES", 3)
    monkeypatch.setattr(engine, "TASK_PAIRS", 100)
    monkeypatch.setattr(engine, "BROADCAST_PAIRS", 100_000 if few else 0)
    p = program({"met": "r/~r", "seen": "met | ~met"})
    full = materialize(p, LabeledGraph.from_relations(spark, {"s": pairs(spark, [(1, 2)])}), store=True)
    u = maintain(p, full, GraphUpdate({("r", False): pairs(spark, r)}, sizes={("r", False): len(r)}), lazy=["seen"])
    assert got(apply_update(full, u).rel("seen")) == want
    assert ("met", False) in u.plus and ("met", False) not in u.sizes


def test_copies_of_a_view_that_holds_pairs_already(spark):
    p = program({"met": "r/~r", "seen": "~met", "twice": "met/seen"})
    r, more = {(1, 9), (2, 9), (3, 8)}, {(3, 9), (4, 8)}
    met = lambda q: {(x, y) for x, a in q for y, b in q if a == b}
    for lazy in (["seen"], ["twice"]):
        full = materialize(p, LabeledGraph.from_relations(spark, {"r": pairs(spark, r)}), store=True)
        u = maintain(p, full, GraphUpdate({("r", False): pairs(spark, more)}, sizes={("r", False): len(more)}), lazy=lazy)
        assert got(apply_update(full, u).rel("seen")) == met(r | more)
        assert u.sizes["met", False] == len(met(r | more) - met(r))  # two literals read it


def test_a_view_composed_of_one_derived_label_twice(spark, monkeypatch):
    """The label is staged, so its size is known and pairs come from classes, not from all ways to meet."""
    from pathloom.operators import engine

    rng = random.Random(7)
    r, s = {(rng.randrange(30), 100 + rng.randrange(9)) for _ in range(60)}, {(100 + rng.randrange(9), 200 + rng.randrange(3)) for _ in range(12)}
    e = {(x, z) for x, a in r for b, z in s if a == b}
    made, by_classes = [], engine.by_classes
    monkeypatch.setattr(engine, "KEPT_ROWS", 0)
    monkeypatch.setattr(engine, "BLOCK_NODES", 2)
    monkeypatch.setattr(engine, "by_classes", lambda *a: made.append(by_classes(*a)) or made[-1])
    full = materialize(program({"e": "r/s", "v": "e/~e"}), LabeledGraph.from_relations(spark, {"r": pairs(spark, r), "s": pairs(spark, s)}), ["v"])
    assert full.sizes["e", False] == len(e) and made[-1] is not None
    assert got(full.rel("v")) == {(x, y) for x, a in e for y, b in e if a == b}


@pytest.mark.parametrize("held", [True, False])
def test_a_composition_with_many_ways_to_meet_joins_no_classes(spark, monkeypatch, held):
    """Nodes with few neighbours in common are as many classes; their blocks find the far nodes in each task, if those fit."""
    from pathloom.operators import engine

    rng = random.Random(11)
    r, s = ({(rng.randrange(base, base + 40), 100 + rng.randrange(k, k + 25)) for _ in range(n)} for base, k, n in ((0, 0, 150), (500, 8, 90)))
    want = sorted({(x, y) for x, a in r for y, b in s if a == b})
    joined, by_join = [], engine._met_by_join
    for name, value in {"KEPT_ROWS": 0, "JOINED_WAYS": 0, "FOUND_PAIRS": 50, "ROW_PAIRS": 5, "BLOCK_NODES": 2, "HELD_NODES": 1_000 if held else 0}.items():
        monkeypatch.setattr(engine, name, value)
    monkeypatch.setattr(engine, "_met_by_join", lambda *a: joined.append(1) or by_join(*a))
    graph = LabeledGraph.from_relations(spark, {"r": pairs(spark, r), "s": pairs(spark, s)})
    graph.sizes = {("r", False): len(r), ("s", False): len(s)}
    out = engine.derive(complete(parse_rules("v(X, Y) :- r(X, Z), s(Y, Z).")).clauses["v"], graph)
    assert sorted(map(tuple, out.collect())) == want and bool(joined) != held


def test_edges_of_a_closure_are_made_once(spark, monkeypatch):
    """Edges of larger inputs are staged before they are counted; those that cannot follow each other are their closure."""
    from pathloom.operators import closure as closures

    read, made, compose = [], [], closures.compose
    monkeypatch.setattr(closures, "STAGED_BYTES", 0)
    monkeypatch.setattr(closures, "SMALL_EDGES", 4)
    monkeypatch.setattr(closures, "collected", lambda e: read.append(1))
    monkeypatch.setattr(closures, "compose", lambda *a: made.append(1) or compose(*a))
    assert got(closures.closure(pairs(spark, [(k, 100 + k % 3) for k in range(9)]))) == {(k, 100 + k % 3) for k in range(9)} and not made
    assert got(closures.closure(pairs(spark, [(k, k + 1) for k in range(9)]))) == {(a, b) for a in range(10) for b in range(a + 1, 10)} and made
    assert not read and got(closures.closure(pairs(spark, []))) == set()


def test_symmetric_views_are_made_once(spark):
    from pathloom.operators.engine import symmetric, without_repeats

    assert symmetric(AUDIENCE.clauses["clients"]) and not symmetric(AUDIENCE.clauses["exposed"])
    assert len(AUDIENCE.clauses["audience"].bodies) == 2 and len(without_repeats(AUDIENCE).clauses["audience"].bodies) == 1

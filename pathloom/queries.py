"""Driver-facing queries over the given tables, each with the SQL that gives the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import measures
from .operators import relational, verify
from .operators.closure import closure, closure_with_witness, minus, union
from .operators.engine import GraphUpdate, LabeledGraph, ViewStore, apply_update, canonical, compose_updates, delta_rows, diff_as_update, maintain, match_body, materialize, replace_label, run_pass, staged_update, updated
from .plans.rules import Program, complete, parse_rules, program, slice_labels
from .plans.sql import program_sql
from .plans.workload import random_views
from .sources.graphs import DUCK, activity_sql, commerce_sql, relations, schema_of
from .sources.staging import Stage
from .streaming.maintenance import chain_stream, maintain_stream, rocksdb_state
from .views import AUDIENCE, DENSE, RING, SPARSE, VIEWS

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}

SOURCES = {"commerce": commerce_sql, "activity": activity_sql}
DUCK_SQL = {k: f(DUCK) for k, f in SOURCES.items()}


def query(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


def graph_for(spark: SparkSession, sf_dir: str, family: str, p: Program, label: str) -> LabeledGraph:
    """The base relations that a view's slice names; its node domain is theirs."""
    return LabeledGraph.from_relations(spark, relations(spark, sf_dir, SOURCES[family](), slice_labels(p, label) - set(p.clauses)))


def view_sql(name: str, cut: dict[str, str] | None = None) -> str:
    """A view's SQL; cut: conditions on base labels' edges."""
    family, p, label = VIEWS[name]
    base = {x: f"SELECT * FROM ({q}) AS z WHERE {cut[x]}" if cut and x in cut else q for x, q in DUCK_SQL[family].items()}
    return program_sql(p, label, base)


def edges_sql(family: str) -> str:
    return " UNION ALL ".join(f"(SELECT DISTINCT '{x}' AS label, src, dst FROM ({q}) AS q WHERE src IS NOT NULL AND dst IS NOT NULL)" for x, q in DUCK_SQL[family].items())


def all_edges(spark: SparkSession, sf_dir: str, family: str) -> DataFrame:
    return union(*(d.select(F.lit(x).alias("label"), "src", "dst") for x, d in relations(spark, sf_dir, SOURCES[family]()).items()))


# ---- edges

for _family in SOURCES:
    query(f"edges_{_family}_counts", f"SELECT label, count(*) AS edges FROM ({edges_sql(_family)}) AS e GROUP BY label")(lambda s, d, f=_family: all_edges(s, d, f).groupBy("label").agg(F.count("*").alias("edges")))
    query(
        f"degree_profile_{_family}",
        f"WITH e AS ({edges_sql(_family)}), o AS (SELECT label, sum(d)::BIGINT AS edges, count(*) AS sources, max(d) AS max_out FROM (SELECT label, src, count(*) AS d FROM e GROUP BY ALL) GROUP BY label), "
        "i AS (SELECT label, count(*) AS targets, max(d) AS max_in FROM (SELECT label, dst, count(*) AS d FROM e GROUP BY ALL) GROUP BY label) SELECT label, edges, sources, targets, max_out, max_in FROM o JOIN i USING (label)",
    )(lambda s, d, f=_family: measures.degree_profile(all_edges(s, d, f)))

    query(
        f"degree_distribution_{_family}",
        f"WITH e AS ({edges_sql(_family)}), d AS (SELECT label, 'out' AS side, count(*) AS degree FROM e GROUP BY label, src UNION ALL SELECT label, 'in', count(*) FROM e GROUP BY label, dst) SELECT label, side, degree, count(*) AS nodes FROM d GROUP BY ALL",
    )(lambda s, d, f=_family: measures.degree_distribution(all_edges(s, d, f)))

# ---- views


def full_view(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    family, p, label = VIEWS[name]
    return materialize(p, graph_for(spark, sf_dir, family, p, label), [label]).rel(label)


for _name in VIEWS:
    query(f"view_{_name}", view_sql(_name))(lambda s, d, n=_name: full_view(s, d, n))

# ---- closures

_closed = {"transfer": "commerce", "doc_copy": "activity", "vec_next": "activity"}
for _label, _family in _closed.items():
    for _method in ("naive", "frontier", "doubling", "components", "local", "sql"):
        if _method == "sql" and _label == "transfer":
            continue  # cyclic: recursive SQL without a set union does not end
        query(f"closure_{_method}_{_label}", program_sql(program({"v": f"{_label}+"}), "v", DUCK_SQL[_family]))(lambda s, d, x=_label, f=_family, m=_method: closure(relations(s, d, SOURCES[f](), {x})[x], m))

_hub = "id % 1000000000000 < 25"


@query("closure_sources", f"SELECT src, dst FROM ({program_sql(program({'v': 'connected+'}), 'v', DUCK_SQL['commerce'])}) AS q WHERE src % 1000000000000 < 25")
def closure_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    edges = relations(spark, sf_dir, commerce_sql(), {"connected"})["connected"]
    return closure(edges, sources=edges.select(F.col("src").alias("id")).where(_hub).distinct())


@query("closure_targets", f"SELECT src, dst FROM ({program_sql(program({'v': 'connected+'}), 'v', DUCK_SQL['commerce'])}) AS q WHERE dst % 1000000000000 < 25")
def closure_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    edges = relations(spark, sf_dir, commerce_sql(), {"connected"})["connected"]
    return closure(edges, targets=edges.select(F.col("dst").alias("id")).where(_hub).distinct())


@query(
    "closure_witness_length",
    f"WITH RECURSIVE e AS (SELECT DISTINCT src, dst FROM ({DUCK_SQL['activity']['turn_next']}) AS q), p AS (SELECT src, dst, 1 AS n FROM e UNION SELECT p.src, e.dst, n + 1 FROM p JOIN e ON p.dst = e.src WHERE n < 500) SELECT src, dst, min(n)::BIGINT AS steps FROM p GROUP BY src, dst",
)
def closure_witness_length(spark: SparkSession, sf_dir: str) -> DataFrame:
    return closure_with_witness(relations(spark, sf_dir, activity_sql(), {"turn_next"})["turn_next"]).select("src", "dst", (F.size("nodes") - 1).cast("long").alias("steps"))


# ---- incremental maintenance


def materialized(p: Program, graph: LabeledGraph, view: str, stage: Stage) -> tuple[Program, LabeledGraph]:
    """The program's slice and the graph with its labels and their closures, stored."""
    keep = slice_labels(p, view)
    own = Program({k: c for k, c in p.clauses.items() if k in keep})
    return own, materialize(own, graph, [view], stage=stage, store=True)


def incremental_view(spark: SparkSession, sf_dir: str, name: str, f: float = 0.10, **options) -> DataFrame:
    """The view of the whole graph from the view without a sample of labels, and their bulk insertion."""
    family, p, label = VIEWS[name]
    graph = graph_for(spark, sf_dir, family, p, label)
    base, u = measures.split_by_labels(graph, measures.sample_labels(SOURCES[family](), f, must_hit=graph.labels()))
    return _maintained(p, label, base, u, **options)


def _maintained(p: Program, label: str, base: LabeledGraph, *updates: GraphUpdate, **options) -> DataFrame:
    stage = Stage(base.spark, "incremental")
    own, full = materialized(p, base, label, stage)
    for k, u in enumerate(updates, 1):
        u = maintain(own, full, staged_update(u, stage), stage=stage, lazy=[label] if k == len(updates) else [], **options)
        full = apply_update(full, u)
    return full.rel(label)


for _name in (*DENSE, *SPARSE):
    query(f"incr_{_name}", view_sql(_name))(lambda s, d, n=_name: incremental_view(s, d, n))
for _f in measures.FRACTIONS:
    query(f"incr_d7_f{round(100 * _f):02d}", view_sql("d7"))(lambda s, d, f=_f: incremental_view(s, d, "d7", f))
query("incr_cost_policy_d8", view_sql("d8"))(lambda s, d: incremental_view(s, d, "d8", policy="cost"))
query("incr_new_prefix_s1", view_sql("s1"))(lambda s, d: incremental_view(s, d, "s1", factoring="new_prefix"))

_gone = "(src * 31 + dst * 17) % 100 < 10"


@query("incr_edges_d5", view_sql("d5"))
def incr_edges_d5(spark: SparkSession, sf_dir: str) -> DataFrame:
    base, u = measures.split_by_edges(graph_for(spark, sf_dir, *VIEWS["d5"]), 10)
    return _maintained(VIEWS["d5"][1], "d5", base, u)


@query("incr_delete_d5", view_sql("d5", {"transfer": f"NOT ({_gone})"}))
def incr_delete_d5(spark: SparkSession, sf_dir: str) -> DataFrame:
    graph = graph_for(spark, sf_dir, *VIEWS["d5"])
    return _maintained(VIEWS["d5"][1], "d5", graph, GraphUpdate(minus={("transfer", False): graph.rel("transfer").where(_gone)}))


@query("incr_mixed_d7", view_sql("d7", {"connected": f"NOT ({_gone})"}))
def incr_mixed_d7(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Deletions of connected and insertions of transfer edges in one update."""
    graph = graph_for(spark, sf_dir, *VIEWS["d7"])
    base = LabeledGraph(spark, dict(graph.relations))
    base.relations["transfer", False] = graph.rel("transfer").where(f"NOT ({_gone})")
    u = GraphUpdate({("transfer", False): graph.rel("transfer").where(_gone)}, {("connected", False): graph.rel("connected").where(_gone)})
    return _maintained(RING, "ring", base, u)


@query("incr_repeat_s1", view_sql("s1"))
def incr_repeat_s1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three updates, each of the result of the one before."""
    graph = graph_for(spark, sf_dir, *VIEWS["s1"])
    third = lambda d, k: d.where(f"(src * 31 + dst * 17) % 4 = {k}")
    base = LabeledGraph(spark, {s: third(d, 0) for s, d in graph.relations.items()})
    return _maintained(AUDIENCE, "exposed", base, *(GraphUpdate({s: third(d, k) for s, d in graph.relations.items()}) for k in (1, 2, 3)))


@query("incr_partial_trust_d7", view_sql("d7"))
def incr_partial_trust_d7(spark: SparkSession, sf_dir: str) -> DataFrame:
    """guarded and watched are trusted, the rest is rebuilt."""
    stage = Stage(spark, "partial")
    graph = graph_for(spark, sf_dir, *VIEWS["d7"])
    own, full = materialized(RING, graph, "guarded", stage)
    mixed = LabeledGraph(spark, {s: d for s, d in full.relations.items()} | {s: d for s, d in graph.relations.items() if s not in full.relations})
    u = run_pass(RING, mixed, graph.labels() | {"watched", "guarded"}, GraphUpdate(), ["vetted", "handoff", "ring"], stage=stage)
    return apply_update(mixed, u).rel("ring")




_star = program({"v": "turn_next*/~said_system"})


@query("incr_star_new_nodes", program_sql(_star, "v", DUCK_SQL["activity"]))
def incr_star_new_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A reflexive closure whose node domain grows with the insertion of a whole label, from the base graph's own nodes."""
    graph = graph_for(spark, sf_dir, "activity", _star, "v")
    base, u = measures.split_by_labels(graph, ["said_system"])
    rest = lambda d, new: d.where(f"(src * 31 + dst * 17) % 100 {'<' if new else '>='} 30")
    base.relations["turn_next", False], u.plus["turn_next", False] = (rest(graph.rel("turn_next"), new) for new in (False, True))
    return _maintained(_star, "v", base, u)


_loop = program({"v": "turn_next*"})


@query("incr_star_only_nodes", program_sql(_loop, "v", DUCK_SQL["activity"]))
def incr_star_only_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    base, u = measures.split_by_edges(graph_for(spark, sf_dir, "activity", _loop, "v"), 40)
    return _maintained(_loop, "v", base, u)


@query("store_recovers", view_sql("s3"))
def store_recovers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """S3 from a store on which an attempt to apply half of the edges stopped before its manifest was there."""
    _, p, label = VIEWS["s3"]
    graph = graph_for(spark, sf_dir, *VIEWS["s3"])
    base, u = measures.split_by_edges(graph, 50)
    stage = Stage(spark, "recovery")
    store = ViewStore(spark, f"{stage.root}/store", p)
    store.create(base)
    spark.range(5).select(F.col("id").alias("src"), F.col("id").alias("dst")).write.parquet(f"{store.folder}/data/stopped/0")
    store.apply(u, "half")
    store.apply(u, "half")
    store.vacuum()
    return store.read(label)


# ---- deltas

_hop = program({"v": "transfer/connected"})


def _hop_deltas(spark: SparkSession, sf_dir: str, factoring: str) -> DataFrame:
    base, u = measures.split_by_edges(graph_for(spark, sf_dir, "commerce", _hop, "v"), 10)
    rows = union(*(d for _, d in delta_rows(_hop.clauses["v"], base, u, factoring))).distinct()
    return minus(rows, materialize(_hop, base).rel("v"))


_hop_old = program_sql(_hop, "v", {x: f"SELECT * FROM ({DUCK_SQL['commerce'][x]}) AS z WHERE NOT ({_gone})" for x in ("transfer", "connected")})
for _factoring in ("old_prefix", "new_prefix", "expanded"):
    query(f"delta_{_factoring}_xjoin", f"SELECT src, dst FROM ({program_sql(_hop, 'v', DUCK_SQL['commerce'])}) AS n EXCEPT SELECT src, dst FROM ({_hop_old}) AS o")(lambda s, d, f=_factoring: _hop_deltas(s, d, f))


def detectable_fixture(spark: SparkSession) -> tuple[Program, LabeledGraph, GraphUpdate]:
    """Watched pairs of a small graph before an update, and the update."""
    pairs = lambda *p: spark.createDataFrame(p, "src long, dst long")
    p = complete(parse_rules("detectable(X, Y) :- suspicious(X, Y), monitors(Z, X), monitors(Z, Y)."))
    graph = LabeledGraph.from_relations(spark, {"monitors": pairs((1, 0), (1, 6), (4, 0), (4, 3)), "suspicious": pairs((0, 2), (2, 3), (6, 0), (3, 0), (5, 6), (0, 5))})
    return p, graph, GraphUpdate({("monitors", False): pairs((1, 2), (4, 5)), ("suspicious", False): pairs((2, 0))})


_found = complete(parse_rules("detectable(X, Y) :- connected(X, Y), monitors(Z, X), monitors(Z, Y)."))


def _detectable_sql() -> str:
    cut = {"old": f" WHERE NOT ({_gone})", "delta": f" WHERE {_gone}", "new": ""}
    part = lambda x, m: f"(SELECT * FROM (SELECT DISTINCT src, dst FROM ({DUCK_SQL['commerce'][x]}) AS q) AS o{cut[m]})"
    rows = []
    for f, (before, after) in {"new_prefix": ("new", "old"), "old_prefix": ("old", "new")}.items():
        for k in range(3):
            m = [before if i < k else "delta" if i == k else after for i in range(3)]
            rows.append(f"SELECT DISTINCT '{f}' AS factoring, {k} AS place, s.src, s.dst FROM {part('connected', m[0])} AS s JOIN {part('monitors', m[1])} AS a ON a.dst = s.src JOIN {part('monitors', m[2])} AS b ON b.dst = s.dst AND b.src = a.src")
    return " UNION ALL ".join(rows)


@query("delta_detectable_rows", _detectable_sql())
def delta_detectable_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Watched pairs that each mask row finds when a tenth of the edges comes, by factoring."""
    base, u = measures.split_by_edges(graph_for(spark, sf_dir, "commerce", _found, "detectable"), 10)
    parts = [rows.distinct().select(F.lit(f).alias("factoring"), F.lit(k).alias("place"), "src", "dst") for f in ("new_prefix", "old_prefix") for k, rows in delta_rows(_found.clauses["detectable"], base, u, f)]
    return union(*parts)


# ---- updates

_t = f"(SELECT DISTINCT src, dst FROM ({DUCK_SQL['commerce']['transfer']}) AS q)"
_c = f"(SELECT DISTINCT src, dst FROM ({DUCK_SQL['commerce']['connected']}) AS q)"


def _two(spark: SparkSession, sf_dir: str) -> tuple[LabeledGraph, DataFrame, DataFrame]:
    r = relations(spark, sf_dir, commerce_sql(), {"transfer", "connected"})
    return LabeledGraph.from_relations(spark, {"a": r["transfer"]}), r["transfer"], r["connected"]


@query("update_apply", f"(SELECT * FROM {_t} WHERE NOT ({_gone})) UNION SELECT * FROM {_c}")
def update_apply(spark: SparkSession, sf_dir: str) -> DataFrame:
    graph, t, c = _two(spark, sf_dir)
    u = canonical(GraphUpdate({("a", False): c}, {("a", False): t.where(_gone)}), graph)
    return apply_update(graph, u).rel("a")


@query("update_modify", f"SELECT * FROM {_t} WHERE {_gone} EXCEPT SELECT * FROM {_c}")
def update_modify(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Deletions of a replaced entry: the insertion wins."""
    _, t, c = _two(spark, sf_dir)
    return replace_label(GraphUpdate({("a", False): t}), ("a", False), c, t.where(_gone)).minus["a", False]


@query("update_canonical", f"SELECT * FROM {_c} EXCEPT SELECT * FROM {_t}")
def update_canonical(spark: SparkSession, sf_dir: str) -> DataFrame:
    graph, _, c = _two(spark, sf_dir)
    return canonical(GraphUpdate({("a", False): c.unionByName(c)}), graph).plus["a", False]


@query("update_compose", f"(SELECT * FROM {_t} UNION SELECT * FROM {_c}) EXCEPT SELECT * FROM {_t} WHERE {_gone}")
def update_compose(spark: SparkSession, sf_dir: str) -> DataFrame:
    graph, t, c = _two(spark, sf_dir)
    u = compose_updates(GraphUpdate({("a", False): c}), GraphUpdate(minus={("a", False): t.where(_gone)}))
    return updated(graph, u, ("a", False))


@query("update_diff", f"(SELECT '+' AS op, * FROM (SELECT * FROM {_c} EXCEPT SELECT * FROM {_t})) UNION ALL (SELECT '-' AS op, * FROM (SELECT * FROM {_t} EXCEPT SELECT * FROM {_c}))")
def update_diff(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, t, c = _two(spark, sf_dir)
    plus, gone = diff_as_update(t, c)
    return plus.select(F.lit("+").alias("op"), "src", "dst").unionByName(gone.select(F.lit("-").alias("op"), "src", "dst"))


# ---- checks


def _ring_graph(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    return materialize(RING, graph_for(spark, sf_dir, *VIEWS["d7"]), ["ring"])


_none = "SELECT label, 0::BIGINT AS {0}, 0::BIGINT AS {1} FROM (VALUES {2}) AS t(label)"
_heads = ", ".join(f"('{x}')" for x in sorted(RING.clauses))


@query("check_model_d7", _none.format("violations", "unsupported", _heads))
def check_model_d7(spark: SparkSession, sf_dir: str) -> DataFrame:
    return verify.is_model(_ring_graph(spark, sf_dir), RING)


@query("check_supported_d7", "SELECT 0::BIGINT AS unsupported")
def check_supported_d7(spark: SparkSession, sf_dir: str) -> DataFrame:
    return verify.unsupported(_ring_graph(spark, sf_dir), "ring", RING.clauses["ring"]).agg(F.count("*").alias("unsupported"))


@query("check_closure_transfer", _none.format("unsound", "missing", "('transfer')"))
def check_closure_transfer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return verify.well_formed(LabeledGraph.from_relations(spark, relations(spark, sf_dir, commerce_sql(), {"transfer"})).with_closures(["transfer"]))


@query("check_law_s1", "SELECT 0::BIGINT AS missing, 0::BIGINT AS extra")
def check_law_s1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return verify.exact_diff(incremental_view(spark, sf_dir, "s1"), full_view(spark, sf_dir, "s1"))


@query("check_containment_d4", f"SELECT src, dst FROM ({program_sql(program({'v': 'wants_1'}), 'v', DUCK_SQL['commerce'])}) AS a EXCEPT SELECT src, dst FROM ({view_sql('d4')}) AS b")
def check_containment_d4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of wants_1 that D4 lacks."""
    return verify.contained_on(relations(spark, sf_dir, commerce_sql(), {"wants_1"})["wants_1"], full_view(spark, sf_dir, "d4"))


# ---- measures


def _in(labels) -> str:
    return ", ".join(f"'{x}'" for x in labels)


def _samples(family: str) -> dict[float, list[str]]:
    return {f: measures.sample_labels(SOURCES[family](), f) for f in measures.FRACTIONS}


_rho = " UNION ALL ".join(f"SELECT '{fam}' AS workload, {f} AS fraction, 100.0 * sum(CASE WHEN label IN ({_in(ls)}) THEN 1 ELSE 0 END) / sum(CASE WHEN label IN ({_in(ls)}) THEN 0 ELSE 1 END) AS rho FROM e_{fam}" for fam in SOURCES for f, ls in _samples(fam).items())


@query("measure_relative_size", f"WITH e_commerce AS ({edges_sql('commerce')}), e_activity AS ({edges_sql('activity')}), r AS ({_rho}) SELECT workload, fraction::DOUBLE AS fraction, round(rho, 6)::DOUBLE AS rho FROM r")
def measure_relative_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = []
    for family in SOURCES:
        counts = all_edges(spark, sf_dir, family).groupBy("label").agg(F.count("*").alias("n"))
        sums = {f: (F.sum(F.when(F.col("label").isin(ls), F.col("n")).otherwise(0)), F.sum(F.when(F.col("label").isin(ls), 0).otherwise(F.col("n")))) for f, ls in _samples(family).items()}
        rows = F.array(*(F.struct(F.lit(f).alias("fraction"), F.round(100.0 * p / b, 6).alias("rho")) for f, (p, b) in sums.items()))
        parts.append(counts.agg(rows.alias("r")).select(F.lit(family).alias("workload"), F.explode("r").alias("r")).select("workload", "r.*"))
    return union(*parts)


@query("measure_support_fraction", " UNION ALL ".join(f"SELECT '{fam}' AS workload, {f}::DOUBLE AS fraction, {len(ls)}::BIGINT AS changed, {len(ls)}::DOUBLE / {len(DUCK_SQL[fam])} AS rho_supp" for fam in SOURCES for f, ls in _samples(fam).items()))
def measure_support_fraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = []
    for family in SOURCES:
        edges = all_edges(spark, sf_dir, family)
        for f, ls in _samples(family).items():
            parts.append(edges.agg(F.countDistinct(F.when(F.col("label").isin(ls), F.col("label"))).alias("changed"), F.countDistinct("label").alias("all")).select(F.lit(family).alias("workload"), F.lit(f).alias("fraction"), "changed", (F.col("changed") / F.col("all")).alias("rho_supp")))
    return union(*parts)


_work = ", ".join(f"e_{fam} AS ({edges_sql(fam)})" for fam in SOURCES) + ", costs AS (" + " UNION ALL ".join(
    f"SELECT '{kind}' AS workload, {f}::DOUBLE AS fraction, count(*)::DOUBLE AS full_cost, sum(CASE WHEN label IN ({_in(ls)}) THEN 1 ELSE 0 END)::DOUBLE AS incr_cost, sum(CASE WHEN label IN ({_in(ls)}) THEN 0 ELSE 1 END)::DOUBLE AS rest FROM e_{fam}"
    for fam, kind in (("commerce", "dense"), ("activity", "sparse")) for f, ls in _samples(fam).items()
) + ")"


def _costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The published comparison with edges for milliseconds: workload, fraction, full_ms (edges that rebuilding reads, all of
    them), incr_ms (inserted ones, of the sampled labels) and rest, those of the other labels."""
    parts = []
    for family, kind in (("commerce", "dense"), ("activity", "sparse")):
        counts = all_edges(spark, sf_dir, family).groupBy("label").agg(F.count("*").alias("n"))
        of = lambda ls, there: F.sum(F.when(F.col("label").isin(ls) == there, F.col("n")).otherwise(0)).cast("double")
        rows = F.array(*(F.struct(F.lit(f).alias("fraction"), F.sum("n").cast("double").alias("full_ms"), of(ls, True).alias("incr_ms"), of(ls, False).alias("rest")) for f, ls in _samples(family).items()))
        parts.append(counts.agg(rows.alias("r")).select(F.lit(kind).alias("workload"), F.explode("r").alias("r")).select("workload", "r.*"))
    return union(*parts)


@query("measure_published_gain", f"WITH {_work} SELECT workload, fraction, round(full_cost - incr_cost, 4) AS gain_ms, round(100 - 100 * incr_cost / full_cost, 4) AS gain_pct, abs(full_cost - incr_cost - rest) > 0.011 AS flagged FROM costs")
def measure_published_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gains in edges read; flagged: those that are not the edges of the other labels."""
    g = measures.gains(_costs(spark, sf_dir))
    return g.select("workload", "fraction", F.round("gain_ms", 4).alias("gain_ms"), F.round("gain_pct", 4).alias("gain_pct"), (F.abs(F.col("gain_ms") - F.col("rest")) > 0.011).alias("flagged"))


@query("measure_published_claims", f"WITH {_work} SELECT fraction, 1 - s.incr_cost / s.full_cost > 1 - d.incr_cost / d.full_cost AS sparser_better FROM (SELECT * FROM costs WHERE workload = 'sparse') AS s JOIN (SELECT * FROM costs WHERE workload = 'dense') AS d USING (fraction)")
def measure_published_claims(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.claim_sparser_better(_costs(spark, sf_dir))


_part = {x: {"old": f"(SELECT * FROM {t} AS o WHERE NOT ((src * 31 + dst * 17) % 100 < 10))", "delta": f"(SELECT * FROM {t} AS o WHERE (src * 31 + dst * 17) % 100 < 10)", "new": t} for x, t in (("t", _t), ("c", _c))}
_masks = {"old_prefix": (("delta", "new"), ("old", "delta")), "new_prefix": (("delta", "old"), ("new", "delta")), "expanded": (("old", "delta"), ("delta", "old"), ("delta", "delta"))}


@query("measure_match_counts", " UNION ALL ".join(f"SELECT '{f}' AS factoring, {k} AS row, count(*) AS matches FROM {_part['t'][a]} AS a JOIN {_part['c'][b]} AS b ON a.dst = b.src" for f, rows in _masks.items() for k, (a, b) in enumerate(rows)))
def measure_match_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Matchings of each mask row of the two-hop view under an insertion of a tenth of the edges, by factoring."""
    base, u = measures.split_by_edges(graph_for(spark, sf_dir, "commerce", _hop, "v"), 10)
    parts = [d.agg(F.count("*").alias("matches")).select(F.lit(f).alias("factoring"), F.lit(k).alias("row"), "matches") for f in ("old_prefix", "new_prefix", "expanded") for k, (_, d) in enumerate(delta_rows(_hop.clauses["v"], base, u, f))]
    return union(*parts)


@query("baseline_nested_loop_d4", view_sql("d4"))
def baseline_nested_loop_d4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """D4 by nested loops over its three smallest-first literals, the published matching strategy."""
    _, p, label = VIEWS["d4"]
    graph = graph_for(spark, sf_dir, *VIEWS["d4"])
    clause = p.clauses[label]
    # The conjunction's first and last literal share both ends with the head; the middle is bound by them.
    keep = graph.rel("wants_1")
    graph.relations["deals_BUILDING", False] = graph.rel("deals_BUILDING").join(keep.select("src").distinct(), "src", "left_semi").select("src", "dst")
    graph.relations["supplies_1997", False] = graph.rel("supplies_1997").join(keep.select("dst").distinct(), "dst", "left_semi").select("src", "dst")
    return match_body(clause.bodies[0], clause.head, lambda lit: graph.rel(*lit.symbol), spark, method="nested_loop").distinct()


def entry(spark: SparkSession) -> DataFrame:
    return full_view(spark, "/root/testdata/sf0.001", "d7")



@query("stream_incr_s3", view_sql("s3"))
def stream_incr_s3(spark: SparkSession, sf_dir: str) -> DataFrame:
    """S3 kept by a stream of the relay edges in three files, each micro-batch one update of a stored view."""
    stage = Stage(spark, "stream")
    _, p, label = VIEWS["s3"]
    edges = relations(spark, sf_dir, activity_sql(), {"relay_click"})["relay_click"].select(F.lit("+").alias("op"), F.lit("relay_click").alias("label"), "src", "dst")
    for k in range(3):
        edges.where(f"(src * 31 + dst) % 3 = {k}").coalesce(1).write.mode("append").parquet(f"{stage.root}/in")
    store = ViewStore(spark, f"{stage.root}/store", p)
    store.create(LabeledGraph.from_relations(spark, {"relay_click": spark.createDataFrame([], "src long, dst long")}))
    feed = spark.readStream.schema(edges.schema).option("maxFilesPerTrigger", 1).parquet(f"{stage.root}/in")
    maintain_stream(feed, store, f"{stage.root}/state").awaitTermination()
    return store.read(label)


_relays = [x for x in DUCK_SQL["activity"] if x.startswith("relay_")]


@query("stream_chain", " UNION ALL ".join(f"(SELECT DISTINCT '{x}' AS label, src, dst FROM ({DUCK_SQL['activity'][x]}) AS q)" for x in _relays))
def stream_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The relay edges of all event types from a stream of the events, by keyed state."""
    stage = Stage(spark, "chain")
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "event_type", "user_id", F.col("ts").cast("timestamp").alias("ts"))
    events.coalesce(1).write.parquet(f"{stage.root}/in")
    links = chain_stream(spark.readStream.schema(events.schema).parquet(f"{stage.root}/in"))
    with rocksdb_state(spark):
        links.writeStream.format("parquet").option("path", f"{stage.root}/out").option("checkpointLocation", f"{stage.root}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("label string, src long, dst long").parquet(f"{stage.root}/out").distinct()


@query("views_random_commerce")
def views_random_commerce(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The sizes of ten generated views over the dense graph."""
    views = random_views({x: ends for x, ends in schema_of(commerce_sql()).items() if x in _generated}, 10, seed=7)
    parts = []
    for name, p in views.items():
        parts.append(materialize(p, graph_for(spark, sf_dir, "commerce", p, name), [name]).rel(name).agg(F.count("*").alias("pairs")).select(F.lit(name).alias("view"), "pairs"))
    return union(*parts)


_generated = ("transfer", "connected", "cust_in", "in_region", "placed_F_1", "monitors")
SQL["views_random_commerce"] = " UNION ALL ".join(f"SELECT '{n}' AS view, count(*) AS pairs FROM ({program_sql(p, n, DUCK_SQL['commerce'])}) AS q" for n, p in random_views({x: ends for x, ends in schema_of(commerce_sql()).items() if x in _generated}, 10, seed=7).items())

QUERIES |= relational.QUERIES
SQL |= relational.SQL

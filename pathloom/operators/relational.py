"""The relational operators around the engine, over the given tables, each with equivalent SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..sources import feeds
from ..sources.graphs import DUCK, activity_sql, commerce_sql, relations
from ..sources.staging import Stage
from ..streaming import maintenance as streams
from ..surface import open_graph, path_view, register_views
from .closure import compose
from .engine import GraphUpdate, LabeledGraph, diff_as_update

QUERIES: dict = {}
SQL: dict[str, str] = {}
CUST = 1000000000000
_d = commerce_sql(DUCK)
_a = activity_sql(DUCK)


def op(name: str, sql: str | None = None):
    def add(f):
        QUERIES[f"op_{name}"] = f
        if sql is not None:
            SQL[f"op_{name}"] = sql
        return f

    return add


def tab(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def com(spark: SparkSession, sf: str, *labels: str) -> list[DataFrame]:
    r = relations(spark, sf, commerce_sql(), set(labels))
    return [r[x] for x in labels]


def act(spark: SparkSession, sf: str, *labels: str) -> list[DataFrame]:
    r = relations(spark, sf, activity_sql(), set(labels))
    return [r[x] for x in labels]


def q(sql: str) -> str:
    return f"(SELECT DISTINCT src, dst FROM ({sql}) AS q WHERE src IS NOT NULL AND dst IS NOT NULL)"


T, C, M = q(_d["transfer"]), q(_d["connected"]), q(_d["monitors"])
_join = f"SELECT DISTINCT a.src, b.dst FROM {T} AS a JOIN {C} AS b ON a.dst = b.src"

op("scan_parquet", "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderstatus = 'F'")(lambda s, d: tab(s, d, "orders").where("o_orderstatus = 'F'").select("o_orderkey", "o_custkey"))


@op("scan_csv_roundtrip", f"SELECT 'transfer' AS label, src, dst FROM {T}")
def scan_csv(s, d):
    root = Stage(s, "csv").root
    com(s, d, "transfer")[0].select(F.lit("transfer").alias("label"), "src", "dst").write.option("header", True).csv(root)
    return feeds.read_edges(s, root, "csv")


@op("sink_roundtrip", f"SELECT 'transfer' AS label, src, dst FROM {T} UNION ALL SELECT 'connected' AS label, src, dst FROM {C}")
def sink(s, d):
    root = Stage(s, "edges").root
    t, c = com(s, d, "transfer", "connected")
    feeds.write_edges(t.select(F.lit("transfer").alias("label"), "src", "dst").unionByName(c.select(F.lit("connected").alias("label"), "src", "dst")), root)
    return feeds.read_edges(s, root)


@op("change_feed", f"SELECT src, dst FROM {T} EXCEPT SELECT src, dst FROM {C}")
def change_feed(s, d):
    """Insertions of transfer and connected, deletions of connected: what stays is inserted."""
    t, c = com(s, d, "transfer", "connected")
    row = lambda df, o: df.select(F.lit(o).alias("op"), F.lit("a").alias("label"), "src", "dst")
    u = GraphUpdate.from_feed(row(t, "+").unionByName(row(c, "-")))
    return u.plus["a", False].join(c, ["src", "dst"], "left_anti")


op("inverse", f"SELECT dst AS src, src AS dst FROM {T}")(lambda s, d: com(s, d, "transfer")[0].select(F.col("dst").alias("src"), F.col("src").alias("dst")))
op("filter_const", f"SELECT src, dst FROM {C} WHERE src = {CUST + 1}")(lambda s, d: com(s, d, "connected")[0].where(F.col("src") == CUST + 1))
op("self_loop", f"SELECT count(*) AS n FROM {T} WHERE src = dst")(lambda s, d: com(s, d, "transfer")[0].where("src = dst").agg(F.count("*").alias("n")))
for _hint, _name in (("broadcast", "broadcast"), ("merge", "merge"), ("shuffle_hash", "hash")):

    def _hinted(s, d, h=_hint):
        t, c = com(s, d, "transfer", "connected")
        few = h != "broadcast" or c.limit(1_000_001).count() <= 1_000_000  # broadcast only within a checked size
        return compose(t, c.hint(h) if few else c).distinct()

    op(f"join_{_name}", _join)(_hinted)


@op("join_nested_loop", _join)
def nested(s, d):
    """The published matching strategy over whole relations: an edge meets each edge of its block of nodes in turn."""
    t, c = com(s, d, "transfer", "connected")
    block = lambda x: F.floor(F.col(x) / 25).alias("block")
    blocks = c.groupBy(block("src")).agg(F.collect_list(F.struct("src", "dst")).alias("edges"))
    met = t.select("src", "dst", block("dst")).join(blocks, "block")
    return met.select("src", F.explode(F.filter("edges", lambda e: e["src"] == F.col("dst"))).alias("e")).select("src", F.col("e.dst").alias("dst")).distinct()


op("semi", f"SELECT src, dst FROM {T} AS t WHERE EXISTS (SELECT 1 FROM {M} AS m WHERE m.src = t.src)")(lambda s, d: (lambda t, m: t.join(m.select("src"), "src", "left_semi").select("src", "dst"))(*com(s, d, "transfer", "monitors")))
op("anti", f"SELECT src, dst FROM {T} EXCEPT SELECT src, dst FROM {C}")(lambda s, d: diff_as_update(*com(s, d, "connected", "transfer"))[0])


@op("full_outer_diff", f"SELECT coalesce(t.src, c.src) AS src, coalesce(t.dst, c.dst) AS dst, CASE WHEN t.src IS NULL THEN '+' ELSE '-' END AS op FROM {T} AS t FULL JOIN {C} AS c ON t.src = c.src AND t.dst = c.dst WHERE t.src IS NULL OR c.src IS NULL")
def outer_diff(s, d):
    """The difference of two relations in one pass."""
    t, c = com(s, d, "transfer", "connected")
    both = t.withColumn("l", F.lit(1)).join(c.withColumn("r", F.lit(1)), ["src", "dst"], "full_outer")
    return both.where("l IS NULL OR r IS NULL").select("src", "dst", F.when(F.col("l").isNull(), "+").otherwise("-").alias("op"))


op("cross_domain", f"WITH n AS (SELECT src AS id FROM {q(_d['in_region'])} UNION SELECT dst FROM {q(_d['in_region'])}) SELECT a.id AS src, b.id AS dst FROM n AS a, n AS b")(
    lambda s, d: (lambda n: n.select(F.col("id").alias("src")).crossJoin(n.select(F.col("id").alias("dst"))))(LabeledGraph.from_relations(s, {"r": com(s, d, "in_region")[0]}).nodes())
)


@op("range_join", "SELECT a.event_id AS first, b.event_id AS second FROM events AS a JOIN events AS b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def range_join(s, d):
    """Pairs of a user's events within an hour: hour bins meet by equality, then the exact bound decides."""
    e = tab(s, d, "events").select("event_id", "user_id", "ts").withColumn("bin", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000))
    a = e.select(F.col("event_id").alias("first"), "user_id", F.col("ts").alias("t"), F.explode(F.array(F.col("bin"), F.col("bin") + 1)).alias("bin"))
    b = e.withColumnRenamed("event_id", "second")
    return a.join(b, ["user_id", "bin"]).where("ts > t AND ts <= t + INTERVAL 1 HOUR").select("first", "second")


@op("asof", "SELECT e.event_id, (SELECT max(b.event_id) FROM events AS b WHERE b.user_id = e.user_id AND b.event_type = 'signup' AND b.ts = (SELECT max(c.ts) FROM events AS c WHERE c.user_id = e.user_id AND c.event_type = 'signup' AND c.ts <= e.ts)) AS signup FROM events AS e WHERE e.event_type = 'purchase'")
def asof(s, d):
    """Each purchase with the user's latest sign-up until then: one of the same day, or the last of an earlier day, which a
    row for each user and day carries on, so that no user's events are one task's."""
    e = tab(s, d, "events").where("event_type IN ('purchase', 'signup')").withColumn("day", F.to_date("ts"))
    up = F.when(F.col("event_type") == "signup", F.struct("ts", "event_id"))
    days = e.groupBy("user_id", "day").agg(F.max(up).alias("last"))
    before = days.select("user_id", "day", F.max("last").over(W.partitionBy("user_id").orderBy("day").rowsBetween(W.unboundedPreceding, -1)).alias("before"))
    w = W.partitionBy("user_id", "day").orderBy("ts").rangeBetween(W.unboundedPreceding, 0)
    rows = e.withColumn("last", F.max(up).over(w)).where("event_type = 'purchase'").join(before, ["user_id", "day"])
    return rows.select("event_id", F.coalesce("last.event_id", "before.event_id").alias("signup"))


op("label_counts", f"SELECT 'transfer' AS label, count(*) AS n FROM {T} UNION ALL SELECT 'connected', count(*) FROM {C}")(
    lambda s, d: (lambda t, c: t.select(F.lit("transfer").alias("label")).unionAll(c.select(F.lit("connected").alias("label"))).groupBy("label").agg(F.count("*").alias("n")))(*com(s, d, "transfer", "connected"))
)
op("distinct_nodes", f"SELECT count(*) AS n FROM (SELECT src FROM {T} UNION SELECT dst FROM {T})")(lambda s, d: LabeledGraph.from_relations(s, {"t": com(s, d, "transfer")[0]}).nodes().agg(F.count("*").alias("n")))
op("approx_nodes")(lambda s, d: com(s, d, "transfer")[0].agg(F.approx_count_distinct("src").alias("sources"), F.approx_count_distinct("dst").alias("targets")))
op("rollup_labels", "SELECT o_orderstatus AS status, o_orderpriority AS priority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")(lambda s, d: tab(s, d, "orders").rollup(F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority")).agg(F.count("*").alias("n")))
op("cube_orders", "SELECT o_orderstatus AS status, o_orderpriority AS priority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")(lambda s, d: tab(s, d, "orders").cube(F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority")).agg(F.count("*").alias("n")))


@op("grouping_sets", "SELECT l_returnflag AS rf, l_linestatus AS ls, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def grouping_sets(s, d):
    return s.sql("SELECT l_returnflag AS rf, l_linestatus AS ls, count(*) AS n FROM {lines} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())", lines=tab(s, d, "lineitem"))


op("window_chain", f"SELECT src, dst FROM {q(_a['turn_next'])}")(lambda s, d: act(s, d, "turn_next")[0])
op("window_topk", "SELECT c_custkey, n::INT AS n FROM (SELECT c_custkey, row_number() OVER (PARTITION BY floor(c_custkey / 25) ORDER BY c_acctbal DESC, c_custkey) AS n FROM customer) WHERE n <= 2")(
    lambda s, d: tab(s, d, "customer").withColumn("n", F.row_number().over(W.partitionBy(F.floor(F.col("c_custkey") / 25)).orderBy(F.col("c_acctbal").desc(), "c_custkey"))).where("n <= 2").select("c_custkey", "n")
)
op("running_degree", f"SELECT src, dst, count(*) OVER (PARTITION BY src ORDER BY dst ROWS UNBOUNDED PRECEDING) AS degree FROM {C}")(lambda s, d: com(s, d, "connected")[0].withColumn("degree", F.count("*").over(W.partitionBy("src").orderBy("dst").rowsBetween(W.unboundedPreceding, 0))))
op("topk_reach", f"SELECT src, count(*) AS n FROM {C} GROUP BY src ORDER BY n DESC, src LIMIT 10")(lambda s, d: com(s, d, "connected")[0].groupBy("src").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "src").limit(10))
op("union", f"SELECT src, dst FROM {T} UNION SELECT src, dst FROM {C}")(lambda s, d: (lambda t, c: t.unionByName(c).distinct())(*com(s, d, "transfer", "connected")))
op("intersect", f"SELECT src, dst FROM {T} INTERSECT SELECT src, dst FROM {C}")(lambda s, d: (lambda t, c: t.intersect(c))(*com(s, d, "transfer", "connected")))
op("except", f"SELECT src, dst FROM {C} EXCEPT SELECT src, dst FROM {T}")(lambda s, d: (lambda t, c: c.subtract(t))(*com(s, d, "transfer", "connected")))
op("page_links", f"SELECT src, dst FROM {q(_a['page_link'])}")(lambda s, d: act(s, d, "page_link")[0])
op("ship_year", "SELECT year(l_shipdate)::INT AS y, count(*) AS n FROM lineitem GROUP BY 1")(lambda s, d: tab(s, d, "lineitem").groupBy(F.year("l_shipdate").alias("y")).agg(F.count("*").alias("n")))
op("community", "SELECT floor(c_custkey / 25)::BIGINT AS community, count(*) AS n FROM customer GROUP BY 1")(lambda s, d: tab(s, d, "customer").groupBy(F.floor(F.col("c_custkey") / 25).alias("community")).agg(F.count("*").alias("n")))
op("json_topic", "SELECT try_cast(json_extract_string(props, '$.k') AS BIGINT) AS topic, count(*) AS n FROM events GROUP BY 1")(lambda s, d: tab(s, d, "events").groupBy(F.expr("try_cast(get_json_object(props, '$.k') AS BIGINT)").alias("topic")).agg(F.count("*").alias("n")))
op("neighbours", f"SELECT src, string_agg(dst::VARCHAR, ',' ORDER BY dst) AS nodes FROM {T} GROUP BY src")(lambda s, d: com(s, d, "transfer")[0].groupBy("src").agg(F.array_join(F.sort_array(F.collect_set("dst")).cast("array<string>"), ",").alias("nodes")))
op("null_guard", "SELECT coalesce(lang, 'none') AS lang, count(*) AS n, sum(CASE WHEN source IS NULL THEN 1 ELSE 0 END)::BIGINT AS no_source FROM documents GROUP BY 1")(
    lambda s, d: tab(s, d, "documents").groupBy(F.coalesce("lang", F.lit("none")).alias("lang")).agg(F.count("*").alias("n"), F.sum(F.when(F.col("source").isNull(), 1).otherwise(0)).alias("no_source"))
)
op("digest", f"SELECT count(*) AS n, sum((src * 31 + dst) % 1000003)::BIGINT AS digest FROM {T}")(lambda s, d: com(s, d, "transfer")[0].agg(F.count("*").alias("n"), F.sum((F.col("src") * 31 + F.col("dst")) % 1000003).alias("digest")))


def _steps(edges: DataFrame) -> DataFrame:
    own = edges.select(F.array("src", "dst").alias("nodes"))
    return own.select(F.posexplode(F.slice("nodes", 1, F.size("nodes") - 1)).alias("k", "src"), "nodes").select("src", F.element_at("nodes", F.col("k") + 2).alias("dst"))


@op("path_steps", f"SELECT src, dst FROM {q(_a['turn_next'])}")
def path_steps(s, d):
    """Paths as node arrays, taken apart into edges."""
    return _steps(act(s, d, "turn_next")[0])


@op("sql_view", f"SELECT src, dst FROM {T} WHERE src < dst")
def sql_view(s, d):
    """A relation asked by name in SQL."""
    (name,) = register_views(s, LabeledGraph.from_relations(s, {"transfer": com(s, d, "transfer")[0]}), "pathloom_view_")
    try:
        return s.sql(f"SELECT src, dst FROM {name} WHERE src < dst")
    finally:
        s.catalog.dropTempView(name)


@op("path_view", _join.replace("DISTINCT a.src, b.dst", "DISTINCT b.dst AS src, a.src AS dst"))
def paths(s, d):
    """A path expression as a table: the inverse of transfer / connected, from a stored graph."""
    root = Stage(s, "opened").root
    t, c = com(s, d, "transfer", "connected")
    feeds.write_edges(t.select(F.lit("transfer").alias("label"), "src", "dst").unionByName(c.select(F.lit("connected").alias("label"), "src", "dst")), root)
    return path_view(open_graph(s, root), "~(transfer/connected)")


_starts = lambda df: df.withColumn("start", F.unix_micros(F.col("start").cast("timestamp")))
op("tumbling", "SELECT epoch_us(date_trunc('day', ts)) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")(lambda s, d: _starts(streams.tumbling(streams.timed(tab(s, d, "events")))))
op("sliding", "SELECT epoch_us(date_trunc('day', ts) - (k * INTERVAL 1 DAY)) AS start, event_type, count(*) AS n FROM events, (VALUES (0), (1)) AS t(k) GROUP BY ALL")(lambda s, d: _starts(streams.sliding(streams.timed(tab(s, d, "events")))))
op("session", "WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), k AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS no FROM g) SELECT epoch_us(min(ts)) AS start, user_id, count(*) AS n FROM k GROUP BY user_id, no")(
    lambda s, d: _starts(streams.sessions(streams.timed(tab(s, d, "events"))))
)


@op("stream_dedup", f"SELECT src, dst FROM {T}")
def stream_dedup(s, d):
    """A stream with every edge twice, once each."""
    stage = Stage(s, "stream")
    edges = com(s, d, "transfer")[0].select(F.lit("2024-01-01 00:00:00").cast("timestamp").alias("ts"), F.lit("transfer").alias("label"), "src", "dst")
    edges.unionAll(edges).write.parquet(f"{stage.root}/in")
    rows = streams.distinct_edges(s.readStream.schema(edges.schema).parquet(f"{stage.root}/in"))
    rows.writeStream.format("parquet").option("path", f"{stage.root}/out").option("checkpointLocation", f"{stage.root}/state").trigger(availableNow=True).start().awaitTermination()
    return s.read.schema(edges.schema).parquet(f"{stage.root}/out").select("src", "dst")

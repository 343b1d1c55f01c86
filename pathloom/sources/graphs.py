"""The two benchmark graphs over the given tables: a dense one of 82 labels and a sparse one of 27.

Each label is a SELECT of (src, dst) that Spark and any ANSI engine run alike, but for a few functions that differ by
name. A node is kind * 10^12 + key. Chains take the successor inside a community of 25 and are filtered afterwards, so
closures grow with the data and not with its square.
"""

from __future__ import annotations

import re
import uuid

from pyspark.sql import DataFrame, SparkSession

KINDS = {"customer": 1, "order": 2, "part": 3, "supplier": 4, "nation": 5, "region": 6, "brand": 7, "type": 8, "user": 11, "topic": 12, "doc": 13, "source": 14, "lang": 15, "page": 16, "host": 17, "path": 18, "conversation": 19, "turn": 20, "vector": 21, "class": 22}

# Part types and languages, whose hubs are numbered by their place.
TYPES = ("ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD")
LANGS = ("de", "en", "es", "fr")
SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")
EVENTS = ("click", "error", "purchase", "signup", "view")

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

SPARK, DUCK = "spark", "duck"


def node(kind: str, key: str) -> str:
    return f"({KINDS[kind]}000000000000 + CAST({key} AS BIGINT))"


def place(values: tuple[str, ...], column: str) -> str:
    return "CASE " + " ".join(f"WHEN {column} = '{v}' THEN {k}" for k, v in enumerate(values, 1)) + " END"


def hashed(text: str, dialect: str) -> str:
    """The first nine hex digits of SHA-256 as a number."""
    return f"CAST(conv(substr(sha2({text}, 256), 1, 9), 16, 10) AS BIGINT)" if dialect == SPARK else f"('0x' || substr(sha256({text}), 1, 9))::BIGINT"


def topic(dialect: str) -> str:
    return "try_cast(get_json_object(props, '$.k') AS BIGINT)" if dialect == SPARK else "try_cast(json_extract_string(props, '$.k') AS BIGINT)"


def found(text: str, pattern: str, dialect: str) -> str:
    return f"nullif(regexp_extract({text}, '{pattern}', 1), '')"


def chain(kind: str, key: str, table: str, where: str, order: str, first: str) -> str:
    """A community's successor links, kept by a condition on the first row."""
    return (
        f"SELECT {node(kind, 'a')} AS src, {node(kind, 'b')} AS dst FROM (SELECT {key} AS a, lead({key}) OVER (PARTITION BY CAST(floor({key} / 25) AS BIGINT) ORDER BY {order}) AS b, "
        f"CASE WHEN {first} THEN 1 ELSE 0 END AS fit FROM {table} WHERE {where}) AS c WHERE fit = 1 AND b IS NOT NULL AND a <> b"
    )


def ranked(top: int) -> str:
    return (
        f"SELECT {node('customer', 'r.c_custkey')} AS src, {node('customer', 'c.c_custkey')} AS dst FROM (SELECT c_custkey, CAST(floor(c_custkey / 25) AS BIGINT) AS g, "
        f"row_number() OVER (PARTITION BY CAST(floor(c_custkey / 25) AS BIGINT) ORDER BY c_acctbal DESC, c_custkey) AS n FROM customer) AS r "
        f"JOIN customer AS c ON CAST(floor(c.c_custkey / 25) AS BIGINT) = r.g AND c.c_custkey <> r.c_custkey WHERE r.n <= {top}"
    )


def commerce_sql(dialect: str = SPARK) -> dict[str, str]:
    out = {}
    pair = lambda a, x, b, y, rest: f"SELECT {node(a, x)} AS src, {node(b, y)} AS dst FROM {rest}"
    for s in "FOP":
        for p in "12345":
            out[f"placed_{s}_{p}"] = pair("customer", "o_custkey", "order", "o_orderkey", f"orders WHERE o_orderstatus = '{s}' AND substr(o_orderpriority, 1, 1) = '{p}'")
    for rf in "ANR":
        for ls in "FO":
            where = f"lineitem WHERE l_returnflag = '{rf}' AND l_linestatus = '{ls}'"
            out[f"contains_{rf}{ls}"] = pair("order", "l_orderkey", "part", "l_partkey", where)
            out[f"sourced_{rf}{ls}"] = pair("order", "l_orderkey", "supplier", "l_suppkey", where)
    for y in range(1995, 2002):
        out[f"supplies_{y}"] = pair("supplier", "l_suppkey", "part", "l_partkey", f"lineitem WHERE year(l_shipdate) = {y}")
    for s in SEGMENTS:
        out[f"deals_{s}"] = pair("customer", "o_custkey", "supplier", "l_suppkey", f"lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey WHERE l_quantity >= 45 AND c_mktsegment = '{s}'")
    for p in "12345":
        out[f"wants_{p}"] = pair("customer", "o_custkey", "part", "l_partkey", f"lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey WHERE l_discount >= 0.09 AND substr(o_orderpriority, 1, 1) = '{p}'")
    for n in range(1, 26):
        out[f"brand_{n}"] = pair("part", "p_partkey", "type", place(TYPES, "p_type"), f"part WHERE p_brand = 'Brand#{n}'")
    for t in TYPES:
        out[f"typed_{t}"] = pair("part", "p_partkey", "brand", "substr(p_brand, 7)", f"part WHERE p_type = '{t}'")
    out["cust_in"] = pair("customer", "c_custkey", "nation", "c_nationkey", "customer")
    out["supp_in"] = pair("supplier", "s_suppkey", "nation", "s_nationkey", "supplier")
    out["in_region"] = pair("nation", "n_nationkey", "region", "n_regionkey", "nation")
    by = "o_orderdate, o_orderkey"
    out["transfer"] = chain("customer", "o_custkey", "orders", "substr(o_orderpriority, 1, 1) = '1'", by, "o_orderstatus = 'F'")
    out["connected"] = chain("customer", "o_custkey", "orders", "substr(o_orderpriority, 1, 1) = '2'", by, "o_orderstatus <> 'P'")
    out["monitors"], out["accredited"] = ranked(2), ranked(8)
    return out


def activity_sql(dialect: str = SPARK) -> dict[str, str]:
    out = {}
    pair = lambda a, x, b, y, rest: f"SELECT {node(a, x)} AS src, {node(b, y)} AS dst FROM {rest}"
    k = topic(dialect)
    for e in EVENTS:
        out[f"touch_{e}"] = pair("user", "user_id", "topic", k, f"events WHERE event_type = '{e}' AND event_id % 3 = 0 AND {k} IS NOT NULL")
        out[f"relay_{e}"] = chain("user", "user_id", "events", f"event_type = '{e}'", "ts, event_id", "event_id % 20 = 0")
    out["follows"] = chain("user", "user_id", "events", "1 = 1", "ts, event_id", "event_id % 50 = 0")
    out["likes"] = pair("user", "user_id", "topic", k, f"events WHERE event_type = 'purchase' AND value >= 20 AND {k} IS NOT NULL")
    out["advertises"] = pair("user", "user_id", "topic", k, f"events WHERE event_type = 'click' AND {k} IS NOT NULL")
    out["doc_lang"] = pair("doc", "doc_id", "lang", place(LANGS, "lang"), f"documents WHERE {place(LANGS, 'lang')} IS NOT NULL")
    out["doc_source"] = pair("doc", "doc_id", "source", "substr(source, 4)", "documents WHERE source IS NOT NULL")
    out["doc_quality"] = pair("doc", "doc_id", "class", "100 + quality", "labels WHERE quality IS NOT NULL")
    out["doc_toxic"] = pair("doc", "doc_id", "class", "200 + toxic", "labels WHERE toxic IS NOT NULL")
    sha = "sha2(text, 256)" if dialect == SPARK else "sha256(text)"
    # A document's next copy: in its stretch of ids, or the first one of the next stretch, so that no text is one task's.
    d = f"(SELECT DISTINCT {sha} AS h, doc_id, CAST(floor(doc_id / 4096) AS BIGINT) AS k FROM documents WHERE text IS NOT NULL AND doc_id IS NOT NULL)"
    near = f"(SELECT h, k, doc_id, lead(doc_id) OVER (PARTITION BY h, k ORDER BY doc_id) AS b FROM {d} AS d)"
    far = f"(SELECT h AS h2, k AS k2, lead(first) OVER (PARTITION BY h ORDER BY k) AS c FROM (SELECT h, k, min(doc_id) AS first FROM {d} AS d GROUP BY h, k) AS m)"
    out["doc_copy"] = f"SELECT {node('doc', 'doc_id')} AS src, {node('doc', 'coalesce(b, c)')} AS dst FROM {near} AS n JOIN {far} AS f ON h = h2 AND k = k2 WHERE coalesce(b, c) IS NOT NULL"
    host = found("url", "//([^/]*)/", dialect)
    out["page_host"] = pair("page", "page_id", "host", hashed(host, dialect), f"pages WHERE {host} IS NOT NULL")
    links = "explode(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1))" if dialect == SPARK else "unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1))"
    out["page_link"] = pair("page", "page_id", "path", hashed("link", dialect), f"(SELECT page_id, {links} AS link FROM pages) AS l")
    lang = found("html", "lang=\"([^\"]*)\"", dialect)
    out["page_lang"] = pair("page", "page_id", "lang", place(LANGS, lang), f"pages WHERE {place(LANGS, lang)} IS NOT NULL")
    for r in ("user", "assistant", "system"):
        out[f"said_{r}"] = pair("conversation", "conv_id", "turn", "conv_id * 1000 + turn", f"conversations WHERE role = '{r}'")
    out["turn_next"] = f"SELECT {node('turn', 'conv_id * 1000 + turn')} AS src, {node('turn', 'conv_id * 1000 + b')} AS dst FROM (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS b FROM conversations) AS c WHERE b IS NOT NULL AND turn <> b"
    out["vec_class"] = pair("vector", "vec_id", "class", "label", "embeddings")
    out["vec_next"] = f"SELECT {node('vector', 'vec_id')} AS src, {node('vector', 'b')} AS dst FROM (SELECT vec_id, lead(vec_id) OVER (PARTITION BY CAST(floor(vec_id / 100) AS BIGINT), label ORDER BY vec_id) AS b FROM embeddings) AS c WHERE b IS NOT NULL AND vec_id <> b"
    return out


def register(spark: SparkSession, sf_dir: str, tables: tuple[str, ...] = TABLES) -> dict[str, str]:
    """Temporary views of the tables under names of their own, by table; the session's views stay as they are."""
    names = {t: f"given_{t}_{uuid.uuid4().hex}" for t in tables}
    for t, name in names.items():
        spark.read.parquet(f"{sf_dir}/{t}.parquet").createTempView(name)
    return names


def relations(spark: SparkSession, sf_dir: str, labels: dict[str, str], only: set[str] | None = None) -> dict[str, DataFrame]:
    """Label to edges (src, dst), without nulls and repeats; only the tables that the labels name are read."""
    wanted = {k: v for k, v in labels.items() if only is None or k in only}
    named = {t: re.compile(rf"\b{t}\b") for t in TABLES}
    views = register(spark, sf_dir, tuple(t for t in TABLES if any(named[t].search(q) for q in wanted.values())))
    try:
        out = {}
        for k, q in wanted.items():
            for t, name in views.items():
                q = named[t].sub(name, q)
            out[k] = spark.sql(q).where("src IS NOT NULL AND dst IS NOT NULL").distinct()
        return out
    finally:
        for name in views.values():
            spark.catalog.dropTempView(name)


def schema_of(labels: dict[str, str]) -> dict[str, tuple[str, str]]:
    """Label to the kinds of nodes that its edges join."""
    kinds = {str(n): k for k, n in KINDS.items()}
    found = {x: re.findall(r"\((\d+)000000000000 \+", q)[:2] for x, q in labels.items()}
    return {x: (kinds[a], kinds[b]) for x, (a, b) in found.items()}

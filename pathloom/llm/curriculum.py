"""Mixing sources to target weights with a time-varying curriculum.

A source of weight w has the schedule w * (1 + tilt * (2t - 1)) over training time t from 0 to 1. Its integral gives
the source's share of tokens; targets above `cap` times a source's size are filled up level, like water. A source's
documents follow one another in hash order, epoch after epoch; inverting the integral at a copy's place in that stream
gives its training position. A copy that the source's demand does not reach in training time has none and is not taken.
What is taken is range-sorted by position.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import fresh, text_or_empty, words

#: Rows that share a stretch of the hash order, about; prefix sums run within stretches and over their totals.
STRETCH = 4096

#: Columns that the mix adds.
ADDED = ("size", "source_size", "target", "before", "tilt", "positions", "copies", "first_position", "last_position")


def targets(sizes: DataFrame, weights: tuple[float, ...] = (1, 2, 3), cap: int = 3, tilts: tuple[float, ...] = (0.0, 0.5, -0.5)) -> DataFrame:
    """source, source_size, target, tilt from rows of (source, size). The weights repeat over sources by code point."""
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    every = W.orderBy(F.col("source").asc_nulls_last())
    turn = (F.row_number().over(every) - 1).alias("turn")
    per = per.select("source", "source_size", turn)
    pick = lambda values: F.element_at(F.array(*map(F.lit, map(float, values))), (F.col("turn") % len(values) + 1).cast("int"))
    per = per.select("source", "source_size", "turn", pick(weights).alias("weight"), pick(tilts).alias("tilt"))
    room = F.col("source_size") * cap
    by_level = W.orderBy(room / F.col("weight"), "turn")
    upto, after = by_level.rowsBetween(W.unboundedPreceding, -1), by_level.rowsBetween(0, W.unboundedFollowing)
    whole = W.partitionBy()
    filled = per.select("*", (F.sum("source_size").over(whole) - F.coalesce(F.sum(room).over(upto), F.lit(0))).alias("left"), F.sum("weight").over(after).alias("open"))
    level = F.col("left") / F.col("open")
    level = F.min(F.when(level * F.col("weight") <= room, F.struct(room / F.col("weight"), "turn", level.alias("level")))).over(whole)["level"]
    return filled.select("source", "source_size", F.least(room.cast("double"), level * F.col("weight")).alias("target"), "tilt")


def _position(share: Column, tilt: Column) -> Column:
    """t where the integral of 1 + tilt * (2t - 1) from 0 is share; null where it is not up to t = 1."""
    b = 1 - tilt
    return F.when(share <= 1, F.when(tilt == 0, share).otherwise((F.sqrt(b * b + 4 * tilt * share) - b) / (2 * tilt)))


def _placed(docs: DataFrame, weights: tuple[float, ...] = (1, 2, 3), cap: int = 3, tilts: tuple[float, ...] = (0.0, 0.5, -0.5)) -> DataFrame:
    """The rows of mixed(), in no order."""
    docs = docs.drop(*ADDED)
    source, size, place, stretch, s1, st, prior = fresh(docs.columns, "_source", "_size", "_order", "_stretch", "_s1", "_st", "_prior")
    stretches = max(1, docs.count() // STRETCH)
    order = F.conv(F.substring(F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), 1, 13), 16, 10).cast("long")
    key = F.coalesce(F.concat(F.lit("="), F.col("source").cast("string")), F.lit(""))  # never null, so that one exchange serves join and window
    rows = docs.withColumns({source: key, size: F.size(words(text_or_empty(F.col("text").cast("string")))).cast("long"), place: order})
    rows = rows.withColumn(stretch, F.floor(F.col(place) / float(1 << 52) * stretches))
    sums = rows.groupBy("source", F.col(source).alias(s1), F.col(stretch).alias(st)).agg(F.sum(size).alias("size"))
    per = targets(sums.select("source", "size"), weights, cap, tilts).withColumn("key", key).drop("source")
    sums = sums.select(s1, st, (F.sum("size").over(W.partitionBy(s1).orderBy(st)) - F.col("size")).alias(prior))
    sums = sums.join(per, sums[s1] == per["key"]).drop("key")
    # A merge join: its exchange deals rows as the window below needs them.
    rows = rows.join(sums.hint("merge"), (F.col(source) == F.col(s1)) & (F.col(stretch) == F.col(st))).drop(s1, st)
    inside = W.partitionBy(source, stretch).orderBy(place, "doc_id", size)
    rows = rows.withColumn("before", F.col(prior) + F.sum(size).over(inside.rowsBetween(W.unboundedPreceding, 0)) - F.col(size))
    rows = rows.withColumnRenamed(size, "size").drop(source, place, stretch, prior)
    rows = rows.withColumn("positions", F.array_compact(F.array(*(copy_position(F.lit(k)) for k in range(cap)))))
    rows = rows.withColumn("copies", F.size("positions"))
    return rows.withColumns({"first_position": F.get("positions", F.lit(0)), "last_position": F.get("positions", F.col("copies") - 1)})


def mixed(docs: DataFrame, **options) -> DataFrame:
    """The columns of docs and size, source_size, target, before (size of the source's earlier documents), tilt,
    positions (where the inverted schedule puts each copy that it reaches), copies (how many), first_position and
    last_position (null without copies). Rows are range-sorted by first_position, those without copies last.

    One row for each row of docs, none dropped; copies may be 0. Null texts have size 0 and are never taken; null
    sources are one source, the last. Repeated rows follow each other. Columns of docs that have one of these names are
    replaced, any others stay. An empty table gives no rows. Options are those of _placed().
    """
    return _placed(docs, **options).orderBy(F.col("first_position").asc_nulls_last(), "doc_id", "before")


def copy_position(copy: Column) -> Column:
    """The training position of a row's copy, counted from 0: where its source's cumulative demand reaches the middle of it;
    null where it does not, and for texts without words."""
    return F.when(F.col("size") > 0, _position((copy * F.col("source_size") + F.col("before") + F.col("size") / 2.0) / F.col("target"), F.col("tilt")))


def curriculum(docs: DataFrame, **options) -> DataFrame:
    """The documents to train on, in order: a row for each copy, with the columns of docs, copy and position (0 to 1).

    Positions come from mixed(); rows are range-sorted by position, then doc_id and copy. Documents that the mix does
    not take are absent; edge cases are as in mixed().
    """
    rows = _placed(docs.drop("copy", "position"), **options)
    rows = rows.select("*", F.posexplode("positions").alias("copy", "position"))
    return rows.drop(*ADDED).orderBy("position", "doc_id", "copy")


MIX_SQL = """
WITH docs AS (SELECT doc_id, source, len(list_filter(regexp_split_to_array(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> ''))::BIGINT AS size,
  ('0x' || substr(md5(coalesce(doc_id::VARCHAR, '')), 1, 13))::BIGINT AS place FROM documents),
per AS (SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS turn FROM docs GROUP BY source),
weighed AS (SELECT *, (turn % 3 + 1)::DOUBLE AS weight, [0.0, 0.5, -0.5][(turn % 3 + 1)::INT]::DOUBLE AS tilt, source_size * 3 AS room FROM per),
filled AS (SELECT *, (sum(source_size) OVER () - coalesce(sum(room) OVER (ORDER BY room / weight, turn ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::DOUBLE
  / sum(weight) OVER (ORDER BY room / weight, turn ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM weighed),
best AS (SELECT level AS chosen FROM filled WHERE level * weight <= room ORDER BY room / weight, turn LIMIT 1),
goal AS (SELECT source, source_size, tilt, least(room::DOUBLE, chosen * weight) AS target FROM filled, best),
streamed AS (SELECT docs.*, source_size, tilt, target, (sum(size) OVER (PARTITION BY docs.source ORDER BY place, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW))::BIGINT - size AS before
  FROM docs JOIN goal ON docs.source IS NOT DISTINCT FROM goal.source),
taken AS (SELECT *, CASE WHEN size = 0 THEN 0 ELSE greatest(0, least(3, floor((target - (before + size / 2.0)) / source_size) + 1))::BIGINT END AS copies FROM streamed),
shares AS (SELECT *, least(1.0, (before + size / 2.0) / target) AS first, least(1.0, ((copies - 1) * source_size + before + size / 2.0) / target) AS last FROM taken),
placed AS (SELECT *, CASE WHEN tilt = 0 THEN first ELSE (sqrt((1 - tilt) * (1 - tilt) + 4 * tilt * first) - (1 - tilt)) / (2 * tilt) END AS p,
  CASE WHEN tilt = 0 THEN last ELSE (sqrt((1 - tilt) * (1 - tilt) + 4 * tilt * last) - (1 - tilt)) / (2 * tilt) END AS q FROM shares WHERE copies > 0)
SELECT t.doc_id, t.size, t.source_size, t.target, t.copies * t.size AS taken, round(p.p, 6) AS first_position, round(p.q, 6) AS last_position
FROM taken AS t LEFT JOIN placed AS p ON t.doc_id = p.doc_id AND t.before = p.before AND t.source IS NOT DISTINCT FROM p.source
"""

"""Line dedup: normalised lines are hashed and counted by distinct document; frequent ones stay in one document only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACES, Scratch, ascii_lower, text_or_empty


def line_key(line: Column) -> Column:
    return ascii_lower(F.trim(line, F.lit(SPACES)))


def _code(key: Column) -> Column:
    """128 bits that stand for a key."""
    return F.struct(F.xxhash64(key).alias("h1"), F.xxhash64(F.lit(7), key).alias("h2"))


def _text_key() -> Column:
    """What tells texts of one doc_id apart."""
    return F.xxhash64(text_or_empty())


def dropped_lines(docs: DataFrame, min_chars: int = 20, min_docs: int = 3) -> DataFrame:
    """doc_id, h (the text's hash), gone: the places, from 0, of the lines that the text loses."""
    lines = docs.where("doc_id IS NOT NULL").select("doc_id", _text_key().alias("h"), F.posexplode(F.split(text_or_empty(), "\n")).alias("i", "line")).withColumn("k", line_key(F.col("line")))
    held = lines.where(F.length("k") >= min_chars).select("doc_id", "h", "i", _code(F.col("k")).alias("code")).select("doc_id", "h", "i", "code.*")
    # A document counts once for a line: its map side keeps one row of each.
    often = held.select("h1", "h2", "doc_id").distinct().groupBy("h1", "h2").agg(F.count("*").alias("n"), F.max("doc_id").alias("keeper")).where(F.col("n") >= min_docs).drop("n")
    # Staged, so that the join's sides are plain exchanges (or one is small by its files): Spark can split a hot line.
    often = Scratch(docs.sparkSession, "lines").stage(often, "often")
    lost = held.join(often, ["h1", "h2"]).where(F.col("doc_id") != F.col("keeper"))
    return lost.groupBy("doc_id", "h").agg(F.collect_set("i").alias("gone"))


def without(lines: Column, gone: Column) -> Column:
    """Lines but those at the places in gone, in their order: places are subtracted as sets, in linear time."""
    places = F.sequence(F.lit(0), F.size(lines) - 1)
    return F.when(gone.isNull(), lines).otherwise(F.transform(F.array_except(places, gone), lambda i: F.get(lines, i)))


def deduped(docs: DataFrame, min_chars: int = 20, min_docs: int = 3) -> DataFrame:
    """d (a row of docs, whatever its columns), lines and kept (arrays), for each row."""
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("d"))
    gone = dropped_lines(own.select("doc_id", "text"), min_chars, min_docs)
    out = own.select("doc_id", _text_key().alias("h"), "d").join(gone, ["doc_id", "h"], "left")
    out = out.select("d", "gone", F.split(text_or_empty(F.col("d.text").cast("string")), "\n").alias("lines"))
    return out.select("d", "lines", without(F.col("lines"), F.col("gone")).alias("kept"))


def line_dedup(docs: DataFrame, min_chars: int = 20, min_docs: int = 3) -> DataFrame:
    """Drop every line whose key (stripped, A-Z lowered) has min_chars and is in min_docs documents, but in the last one.

    Returns doc_id, n_lines (before), n_dropped, kept (lines joined by line feeds), a row for each row of docs. A null
    text is one empty line. A row without doc_id neither counts nor loses lines. A repeated doc_id counts as one
    document. Other columns of docs are ignored. An empty table gives no rows.
    """
    out = deduped(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), min_chars, min_docs)
    n = F.size("lines").cast("long")
    return out.select("d.doc_id", n.alias("n_lines"), (n - F.size("kept")).alias("n_dropped"), F.array_join("kept", "\n").alias("kept"))


LINE_DEDUP_SQL = """
WITH split AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS parts FROM documents),
lines AS (SELECT doc_id, unnest(parts) AS line, unnest(range(len(parts))) AS i FROM split),
keyed AS (SELECT *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
  'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k FROM lines),
often AS (SELECT k, max(doc_id) AS keeper FROM keyed WHERE length(k) >= 20 GROUP BY k HAVING count(DISTINCT doc_id) >= 3),
judged AS (SELECT keyed.*, keeper IS NOT NULL AND keeper <> doc_id AS gone FROM keyed LEFT JOIN often USING (k))
SELECT doc_id, count(*)::BIGINT AS n_lines, sum(gone::INT)::BIGINT AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (NOT gone), '')) AS kept_sha256
FROM judged GROUP BY doc_id
"""

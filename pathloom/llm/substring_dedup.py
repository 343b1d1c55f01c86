"""Substring dedup over words: super-k-mer partitioning, with windows counted exactly by sorting in each bucket."""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, freeing, text_chunks
from .segments import Plan, covered, covered_units, word_units


def sort_windows(rows, plan: Plan):
    """(doc_id, begin, n) runs of windows that another row's document with a smaller doc_id also has."""
    windows = []
    for i, (doc, _, packed) in enumerate(rows):
        at = [0, *(k + 1 for k, c in enumerate(packed) if c == 32), len(packed) + 1]
        windows += [(packed[at[j] : at[j + plan.span] - 1], doc, i, j) for j in range(len(at) - plan.span)]
    windows.sort()
    hits: dict[int, list[int]] = {}
    last = first = None
    for text, doc, i, j in windows:
        if text != last:
            last, first = text, doc
        elif doc > first:
            hits.setdefault(i, []).append(j)
    for i, found in hits.items():
        yield from ((rows[i][0], rows[i][1] + j, 1) for j in found)


def word_plan(window: int = 50, gram: int = 8) -> Plan:
    return Plan("words", word_units, window, min(gram, window), False, sort_windows)


def _kept(window: int):
    def run(batches):
        import pyarrow as pa

        for batch in text_chunks(batches):
            out = []
            for text, runs in zip(batch.column("text").to_pylist(), batch.column("runs").to_pylist(), strict=True):
                ws = (text or "").encode().split()
                kept, gone = ws, 0
                if runs:
                    mask = covered_units(((r["begin"], r["n"]) for r in runs), len(ws), window)
                    kept, gone = [w for w, m in zip(ws, mask.tolist(), strict=True) if not m], int(mask.sum())
                out.append((len(ws), gone, b" ".join(kept).decode()))
            n, gone, kept = zip(*out, strict=True)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(kept, pa.string())], names=["doc_id", "n_words", "n_removed", "kept"])

    return run


def substring_dedup(docs: DataFrame, window: int = 50, gram: int = 8) -> DataFrame:
    """Remove the words of every `window`-word string that also starts in a document with a smaller doc_id.

    Returns doc_id, n_words, n_removed, kept (words joined by one space), a row for each row of docs. Null or empty
    texts have no words. A row without doc_id keeps all words and removes nothing elsewhere. Repeated rows get equal
    results; a doc_id is expected to name one text. Other columns of docs are ignored. An empty table gives no rows.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    runs = covered(docs, word_plan(window, gram), Scratch(docs.sparkSession, "substring"))
    return docs.join(runs, "doc_id", "left").select("doc_id", "text", "runs").mapInArrow(freeing(_kept(window)), "doc_id long, n_words long, n_removed long, kept string")


def digest(kept: DataFrame, column: str) -> DataFrame:
    return kept.withColumn("kept_sha256", F.sha2(F.col(column), 256)).drop(column)


def kept_by_brute_force(rows: list[tuple[int, str | None]], window: int = 50) -> dict[int, tuple[int, int, str]]:
    """For tests: the same by comparing every window."""
    first: dict[tuple[str, ...], int] = {}
    split = {d: [w.decode() for w in (t or "").encode().split()] for d, t in rows}
    for d in sorted(split):
        for i in range(len(split[d]) - window + 1):
            first.setdefault(tuple(split[d][i : i + window]), d)
    out = {}
    for d, ws in split.items():
        gone = {k for i in range(len(ws) - window + 1) if first[tuple(ws[i : i + window])] < d for k in range(i, i + window)}
        kept = " ".join(w for k, w in enumerate(ws) if k not in gone)
        out[d] = (len(ws), len(gone), hashlib.sha256(kept.encode()).hexdigest())
    return out


SUBSTRING_SQL = r"""
WITH split AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents),
words AS (SELECT doc_id, unnest(ws) AS w, unnest(range(len(ws))) AS i FROM split),
framed AS (SELECT doc_id, w, i, md5(string_agg(w, ' ') OVER f) AS h, count(*) OVER f AS n FROM words WINDOW f AS (PARTITION BY doc_id ORDER BY i ROWS BETWEEN CURRENT ROW AND 49 FOLLOWING)),
firsts AS (SELECT h, min(doc_id) AS first FROM framed WHERE n = 50 GROUP BY h),
hit AS (SELECT doc_id, w, i, n = 50 AND first < doc_id AS again FROM framed LEFT JOIN firsts USING (h)),
judged AS (SELECT doc_id, w, i, coalesce(bool_or(again) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN 49 PRECEDING AND CURRENT ROW), false) AS gone FROM hit),
kept AS (SELECT doc_id, count(*) AS n_words, sum(gone::INT)::BIGINT AS n_removed, string_agg(w, ' ' ORDER BY i) FILTER (NOT gone) AS kept FROM judged GROUP BY doc_id)
SELECT doc_id, coalesce(n_words, 0) AS n_words, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM split LEFT JOIN kept USING (doc_id)
"""

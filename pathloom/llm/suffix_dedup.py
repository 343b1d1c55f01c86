"""Suffix-array dedup over bytes by the difference-cover algorithm.

Suffixes that can share a 100-byte prefix have the same minimiser, so they are dealt to executors by minimiser and
need not be ordered across buckets. Each block of whole buckets is suffix-sorted by the difference cover {1, 2} modulo
3: sampled triples are sorted and named, the names recurse, the remaining suffixes are merged in by (byte, rank of the
next), and neighbours in the suffix array are compared over 100 bytes.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, freeing, text_chunks
from .segments import Plan, Prefix, byte_hashes, byte_units, covered, covered_units, grouped_runs


def _dense(keys: np.ndarray) -> tuple[np.ndarray, int]:
    """Names of keys, from 1, in their order, and how many there are."""
    order = np.argsort(keys)
    own = keys[order]
    names = np.empty(len(keys), dtype=np.int64)
    names[order] = np.cumsum(np.concatenate([[1], own[1:] != own[:-1]]))
    return names, int(names[order[-1]])


def _keys(columns: list[np.ndarray], bits: int) -> np.ndarray:
    """One number for each row of columns of `bits` bits at most, in the order of the rows."""
    if len(columns) * bits > 63:
        order = np.lexsort(columns[::-1])
        new = np.any([c[order][1:] != c[order][:-1] for c in columns], axis=0)
        out = np.empty(len(order), dtype=np.int64)
        out[order] = np.cumsum(np.concatenate([[1], new]))
        return out
    out = columns[0]
    for c in columns[1:]:
        out = (out << bits) | c
    return out


def suffix_array(text: np.ndarray, alphabet: int) -> np.ndarray:
    """Starts of the suffixes of text (numbers from 1 to alphabet - 1) in lexical order.

    Orders are found by sorting single machine words, into which triples and (number, rank) pairs are packed.
    """
    n = len(text)
    if n < 3:
        return np.array(sorted(range(n), key=lambda i: text[i:].tolist()), dtype=np.int64)
    padded = np.concatenate([text.astype(np.int64), np.zeros(4, dtype=np.int64)])
    ones = np.arange(1, n + (n % 3 == 1), 3)  # an all-padding triple parts the two halves where n is 1 modulo 3
    twos = np.arange(2, n, 3)
    sample = np.concatenate([ones, twos])
    bits = int(alphabet - 1).bit_length()
    names, distinct = _dense(_keys([padded[sample + k] for k in range(3)], bits))
    if distinct < len(sample):
        order = suffix_array(names, distinct + 1)
    else:
        order = np.argsort(names)
    rank = np.zeros(n + 4, dtype=np.int64)
    rank[sample[order]] = np.arange(1, len(sample) + 1)
    sampled = sample[order]
    sampled = sampled[sampled < n]
    wide = max(bits, int(len(sample)).bit_length())
    zeros = np.arange(0, n, 3)
    zeros = zeros[np.argsort(_keys([padded[zeros], rank[zeros + 1]], wide))]
    # Merge: where each remaining suffix stands among the sampled ones, by (number, rank) or (number, number, rank).
    place = np.zeros(len(zeros), dtype=np.int64)
    for kind in (1, 2):
        own = sampled[sampled % 3 == kind]
        both = np.concatenate([own, zeros])
        keys = _keys([*(padded[both + k] for k in range(kind)), rank[both + kind]], wide)
        place += np.searchsorted(keys[: len(own)], keys[len(own) :])
    out = np.empty(n, dtype=np.int64)
    slots = place + np.arange(len(zeros))
    out[slots] = zeros
    rest = np.ones(n, dtype=bool)
    rest[slots] = False
    out[rest] = sampled
    return out


def same_prefix(text: np.ndarray, order: np.ndarray, length: int) -> np.ndarray:
    """For each place after the first of a suffix array: whether it shares `length` bytes with the place before."""
    padded = np.concatenate([text, np.zeros(length + 8, dtype=text.dtype)]).astype(np.uint64)
    block = np.zeros(len(text) + length, dtype=np.uint64)
    for k in range(6):  # six numbers below 1024 to a machine word
        block |= padded[k : k + len(block)] << np.uint64(10 * k)
    alive = np.arange(len(order) - 1)
    for shift in [*range(0, length - 6, 6), length - 6]:
        alive = alive[block[order[alive] + shift] == block[order[alive + 1] + shift]]
    same = np.zeros(len(order) - 1, dtype=bool)
    same[alive] = True
    return same


def _shared_stretches(joined: np.ndarray, sizes: np.ndarray, span: int) -> tuple[np.ndarray, np.ndarray]:
    """(begin, end) of the stretches of strings, end to end, that windows with another of the same hash cover.

    A window whose hash is its own equals no other, so suffixes elsewhere need no sorting.
    """
    hashes = Prefix(byte_hashes[joined]).rolling(span)
    ends = np.cumsum(sizes)
    room = np.repeat(ends, sizes)[: len(hashes)] - np.arange(len(hashes)) >= span
    places = np.flatnonzero(room)
    order = np.argsort(hashes[places])
    own = hashes[places[order]]
    same = own[1:] == own[:-1]
    if not same.any():
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
    twice = np.concatenate([[False], same]) | np.concatenate([same, [False]])
    starts = np.sort(places[order[twice]])
    string = np.searchsorted(ends, starts, side="right")
    new = np.flatnonzero(np.concatenate([[True], (np.diff(starts) > span) | (np.diff(string) > 0)]))
    return starts[new], starts[np.concatenate([new[1:], [len(starts)]]) - 1] + span


def sort_suffixes(rows, plan: Plan):
    """(doc_id, begin, n) runs of windows that also start earlier, among the packed strings of whole buckets."""
    span, lengths = plan.span, np.array([len(p) for *_, p in rows])
    joined = np.frombuffer(b"".join(p for *_, p in rows), dtype=np.uint8)
    begin, end = _shared_stretches(joined, lengths, span)
    if not len(begin):
        return
    sizes = end - begin
    text = np.ones(int(sizes.sum()) + len(sizes), dtype=np.int64)  # 1 parts the stretches; bytes are 2 to 257
    at = np.cumsum(sizes + 1) - sizes - 1
    owner = np.repeat(np.arange(len(sizes)), sizes + 1)
    inside = np.ones(len(text), dtype=bool)
    inside[at + sizes] = False
    place = begin[owner] + np.arange(len(text)) - at[owner]  # in the strings, end to end
    text[inside] = joined[place[inside]].astype(np.int64) + 2
    order = suffix_array(text, 258)
    whole = (order - at[owner[order]]) <= sizes[owner[order]] - span
    group = np.concatenate([[0], np.cumsum(~same_prefix(text, order, span))])
    order, group = order[whole], group[whole]
    docs, code = np.unique(np.array([d for d, *_ in rows], dtype=np.int64), return_inverse=True)
    begins = np.array([b for _, b, _ in rows], dtype=np.int64) - (np.cumsum(lengths) - lengths)
    string = np.searchsorted(np.cumsum(lengths), place[order], side="right")
    when = code[string] * (1 << 40) + begins[string] + place[order]
    new = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
    least = np.repeat(np.minimum.reduceat(when, new), np.diff(np.concatenate([new, [len(group)]])))
    for k, n in grouped_runs(np.unique(when[when > least])):
        yield int(docs[k >> 40]), int(k & ((1 << 40) - 1)), n


def byte_plan(window: int = 100, gram: int = 32) -> Plan:
    return Plan("bytes", byte_units, window, min(gram, window), True, sort_suffixes)


def _kept(window: int):
    def run(batches):
        import pyarrow as pa

        for batch in text_chunks(batches):
            out = []
            for text, runs in zip(batch.column("text").to_pylist(), batch.column("runs").to_pylist(), strict=True):
                raw = (text or "").encode()
                if not runs:
                    out.append((len(raw), 0, 0, raw))
                    continue
                mask = covered_units(((r["begin"], r["n"]) for r in runs), len(raw), window)
                spans = int(mask[0]) + int(np.count_nonzero(mask[1:] & ~mask[:-1]))
                out.append((len(raw), int(mask.sum()), spans, np.frombuffer(raw, dtype=np.uint8)[~mask].tobytes()))
            n, gone, spans, kept = zip(*out, strict=True)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(x, pa.int64()) for x in (n, gone, spans)), pa.array(kept, pa.binary())], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept"])

    return run


def suffix_dedup(docs: DataFrame, window: int = 100, gram: int = 32) -> DataFrame:
    """Remove every byte of a `window`-byte string that also starts earlier: in a smaller doc_id, or before in its own.

    Returns doc_id, n_bytes, n_removed, n_spans (maximal removed runs), kept (bytes), a row for each row of docs. Null
    texts are empty. A row without doc_id keeps all bytes and removes nothing elsewhere. Repeated rows get equal
    results; a doc_id is expected to name one text. Other columns of docs are ignored. An empty table gives no rows.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    runs = covered(docs, byte_plan(window, gram), Scratch(docs.sparkSession, "suffix"))
    return docs.join(runs, "doc_id", "left").select("doc_id", "text", "runs").mapInArrow(freeing(_kept(window)), "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary")


def kept_by_brute_force(rows: list[tuple[int, str | None]], window: int = 100) -> dict[int, tuple[int, int, int, str]]:
    """For tests: the same by a dictionary of all strings."""
    seen: set[bytes] = set()
    out = {}
    for d, t in sorted(rows):
        raw = (t or "").encode()
        gone: set[int] = set()
        for i in range(len(raw) - window + 1):
            if (w := raw[i : i + window]) in seen:
                gone.update(range(i, i + window))
            seen.add(w)
        spans = sum(1 for k in gone if k - 1 not in gone)
        out[d] = (len(raw), len(gone), spans, hashlib.sha256(bytes(b for k, b in enumerate(raw) if k not in gone)).hexdigest())
    return out


SUFFIX_SQL = r"""
WITH raw AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS x FROM documents),
bytes AS (SELECT doc_id, i, b, md5(string_agg(b, '') OVER f) AS h, count(*) OVER f = 100 AS whole FROM (SELECT doc_id, unnest(list) AS b, unnest(range(len(list))) AS i FROM (SELECT doc_id, regexp_extract_all(x, '..') AS list FROM raw)) WINDOW f AS (PARTITION BY doc_id ORDER BY i ROWS BETWEEN CURRENT ROW AND 99 FOLLOWING)),
firsts AS (SELECT h, min((doc_id, i)) AS first FROM bytes WHERE whole GROUP BY h),
hit AS (SELECT doc_id, i, b, whole AND first < (doc_id, i) AS again FROM bytes LEFT JOIN firsts USING (h)),
judged AS (SELECT doc_id, i, b, coalesce(bool_or(again) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN 99 PRECEDING AND CURRENT ROW), false) AS gone FROM hit),
runs AS (SELECT *, gone AND NOT coalesce(lag(gone) OVER (PARTITION BY doc_id ORDER BY i), false) AS begins FROM judged),
kept AS (SELECT doc_id, count(*) AS n_bytes, sum(gone::INT)::BIGINT AS n_removed, sum(begins::INT)::BIGINT AS n_spans, string_agg(b, '' ORDER BY i) FILTER (NOT gone) AS kept FROM runs GROUP BY doc_id)
SELECT doc_id, coalesce(n_bytes, 0) AS n_bytes, coalesce(n_removed, 0) AS n_removed, coalesce(n_spans, 0) AS n_spans, sha256(unhex(coalesce(kept, ''))) AS kept_sha256 FROM raw LEFT JOIN kept USING (doc_id)
"""

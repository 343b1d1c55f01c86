"""Minimiser segments (super-k-mers) and the plan that finds repeated windows with them.

A window is `span` consecutive units (words or bytes). Its minimiser is the smallest hash of the `gram`-unit strings
in it; consecutive windows with one minimiser form a segment. Equal windows have equal minimisers, so

1. minimisers that occur once in the corpus are dropped after a pre-aggregated count of (minimiser, document);
2. segments of the rest are keyed by their content: every segment equal to an earlier one is covered as a whole;
3. of distinct segments that share a minimiser, the first occurrences travel as packed strings to the minimiser's
   bucket, where a sorter finds the equal windows of different segments;
4. a minimiser with more than HOT distinct segments is dealt anew by the windows' own 128-bit fingerprints, so that no
   bucket grows with the corpus.

Steps are staged in the shared folder; a lost executor repeats only its own tasks.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, freeing, text_chunks

#: More distinct segments of one minimiser than this are dealt by window fingerprint.
HOT = 2000

U = np.uint64
BASE, BASE2 = U(0x9E3779B97F4A7C15), U(0xD6E8FEB86659FD93)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift and multiply)."""
    x = (x ^ (x >> U(32))) * U(0xD6E8FEB86659FD93)
    x = (x ^ (x >> U(32))) * U(0xD6E8FEB86659FD93)
    return x ^ (x >> U(32))


_powers: dict[tuple[int, int], np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """base**i modulo 2**64 for i below n at least."""
    kept = _powers.get((base, 0))
    if kept is None or len(kept) < n:
        steps = np.full(max(n, 1 << 16), base, dtype=U)
        steps[0] = 1
        _powers[base, 0] = kept = np.multiply.accumulate(steps)
    return kept


def inverse(base: U) -> int:
    return pow(int(base), -1, 1 << 64)


class Prefix:
    """Hashes of any stretch of units in constant time each, from prefix sums."""

    def __init__(self, units: np.ndarray, base: U = BASE):
        n = len(units)
        self.sums = np.zeros(n + 1, dtype=U)
        np.cumsum(units * powers(int(base), n)[:n], out=self.sums[1:])
        self.back = powers(inverse(base), n + 1)

    def of(self, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((self.sums[end] - self.sums[begin]) * self.back[begin] + (end - begin).astype(U))

    def rolling(self, size: int) -> np.ndarray:
        n = len(self.sums) - size
        return mix((self.sums[size:] - self.sums[:n]) * self.back[:n]) if n > 0 else np.zeros(0, dtype=U)


def sliding_min(x: np.ndarray, size: int) -> np.ndarray:
    have = 1
    while have < size:
        step = min(have, size - have)
        x = np.minimum(x[:-step], x[step:])
        have += step
    return x


@dataclass
class Units:
    """Units of a chunk of documents, end to end. at: where each document begins, and the end of the last."""

    hashes: np.ndarray
    at: np.ndarray
    packed: Callable[[int, int], bytes]  # the bytes of units begin to end (exclusive)


byte_hashes = mix(np.arange(1, 257, dtype=U) * U(0xA0761D6478BD642F))


def byte_units(texts: list[bytes]) -> Units:
    joined = b"".join(texts)
    at = np.concatenate([[0], np.cumsum([len(t) for t in texts], dtype=np.int64)])
    return Units(byte_hashes[np.frombuffer(joined, dtype=np.uint8)], at, lambda b, e: joined[b:e])


_is_space = np.zeros(256, dtype=bool)
_is_space[[32, *range(9, 14)]] = True


#: Bytes of text that are split into words and hashed at a time.
PIECE = 1_000_000


def _pieces(texts: list[bytes]) -> Iterator[list[bytes]]:
    """Stretches of texts of about PIECE bytes, one text at least; one empty stretch if there are no texts."""
    begin = total = 0
    for i, t in enumerate(texts):
        if i > begin and total + len(t) > PIECE:
            yield texts[begin:i]
            begin, total = i, 0
        total += len(t)
    yield texts[begin:]


def word_units(texts: list[bytes]) -> Units:
    """Words between bytes of \\x20 and \\x09 to \\x0D; packed with one space between them."""
    joined, offset, parts = b"\n".join(texts), 0, []
    for piece in _pieces(texts):
        n = sum(map(len, piece)) + len(piece)
        raw = np.frombuffer(joined, dtype=np.uint8, count=max(min(n, len(joined) - offset), 0), offset=min(offset, len(joined)))
        edges = np.diff(np.concatenate([[True], _is_space[raw], [True]]).astype(np.int8))
        begins, ends = np.flatnonzero(edges == -1), np.flatnonzero(edges == 1)
        hashes = Prefix(byte_hashes[raw]).of(begins, ends) if len(begins) else np.zeros(0, dtype=U)
        parts.append((hashes, begins + offset, ends + offset))
        offset += n
    hashes, begins, ends = (np.concatenate(x) for x in zip(*parts, strict=True))
    sizes = np.array([len(t) for t in texts], dtype=np.int64)
    at = np.concatenate([[0], np.searchsorted(begins, np.cumsum(sizes + 1) - 1)]).astype(np.int64)
    return Units(hashes, at, lambda b, e: b" ".join(joined[begins[b] : ends[e - 1]].split()))


def cut(units: Units, span: int, gram: int) -> tuple[np.ndarray, ...]:
    """Segments: document's index, first window's unit in the chunk, number of windows, minimiser, content hash."""
    none = np.zeros(0, dtype=np.int64)
    if len(units.hashes) < span:
        return none, none, none, none, none
    prefix = Prefix(units.hashes)
    # The leftmost smallest gram by the upper half of its hash; its place breaks ties, so that a gram that comes again
    # begins a segment of its own.
    grams = prefix.rolling(gram)
    least = sliding_min((grams & ~U(0xFFFFFFFF)) | np.arange(len(grams), dtype=U), span - gram + 1)
    doc = np.repeat(np.arange(len(units.at) - 1), np.diff(units.at))
    at = np.flatnonzero(doc[: len(least)] == doc[span - 1 :])
    if not len(at):
        return none, none, none, none, none
    least = (least[at] & U(0xFFFFFFFF)).astype(np.int64)
    new = np.flatnonzero(np.concatenate([[True], (np.diff(at) != 1) | (least[1:] != least[:-1])]))
    begin, count = at[new], np.diff(np.concatenate([new, [len(at)]]))
    content = prefix.of(begin, begin + count + span - 1)
    return doc[begin], begin, count, grams[least[new]].view(np.int64), content.view(np.int64)


def _encoded(batch) -> list[bytes]:
    import pyarrow as pa

    return [t or b"" for t in batch.column("text").cast(pa.binary()).to_pylist()]


@dataclass
class Plan:
    """What differs between words and bytes."""

    name: str
    units: Callable[[list[bytes]], Units]
    span: int
    gram: int
    within: bool  # an earlier start in the same document counts too
    sorter: Callable[[list[tuple[int, int, bytes]], "Plan"], Iterator[tuple[int, int, int]]]


def _minimisers(plan: Plan):
    def run(batches):
        import pyarrow as pa

        for batch in text_chunks(batches):
            ids = batch.column("doc_id").to_numpy(zero_copy_only=False)
            doc, _, _, mini, _ = cut(plan.units(_encoded(batch)), plan.span, plan.gram)
            order = np.lexsort((mini, doc))
            doc, mini = doc[order], mini[order]
            first = np.ones(len(doc), dtype=bool)
            first[1:] = (doc[1:] != doc[:-1]) | (mini[1:] != mini[:-1])
            at = np.flatnonzero(first)
            times = np.diff(np.concatenate([at, [len(doc)]]))
            yield pa.RecordBatch.from_arrays([pa.array(mini[at]), pa.array(ids[doc[at]].astype(np.int64)), pa.array(times > 1)], names=["mini", "doc_id", "again"])

    return run


def _segments(plan: Plan):
    def run(batches):
        import pyarrow as pa

        for batch in text_chunks(batches):
            ids = batch.column("doc_id").to_numpy(zero_copy_only=False).astype(np.int64)
            units = plan.units(_encoded(batch))
            doc, begin, count, mini, content = cut(units, plan.span, plan.gram)
            lists = batch.column("minis")
            wanted_doc = np.repeat(np.arange(batch.num_rows), np.diff(lists.offsets.to_numpy()))
            wanted = lists.flatten().to_numpy(zero_copy_only=False)
            pairs = np.concatenate([mix(wanted.view(U)) + wanted_doc.astype(U), mix(mini.view(U)) + doc.astype(U)])
            _, codes = np.unique(pairs, return_inverse=True)
            keep = np.flatnonzero(np.isin(codes[len(wanted) :], codes[: len(wanted)]))
            doc, begin, count, mini, content = (x[keep] for x in (doc, begin, count, mini, content))
            yield pa.RecordBatch.from_arrays(
                [pa.array(mini), pa.array(content), pa.array(ids[doc]), pa.array((begin - units.at[doc]).astype(np.int32)), pa.array(count.astype(np.int32))],
                names=["mini", "content", "doc_id", "begin", "n"],
            )

    return run


def _packed(plan: Plan):
    """The packed strings of chosen segments, cut from their documents."""

    def run(batches):
        import pyarrow as pa

        for batch in text_chunks(batches):
            units = plan.units(_encoded(batch))
            rows = []
            for doc, at, chosen in zip(batch.column("doc_id").to_pylist(), units.at.tolist(), batch.column("chosen").to_pylist(), strict=False):
                rows += [(c["mini"], c["hot"], doc, c["begin"], units.packed(at + c["begin"], at + c["begin"] + c["n"] + plan.span - 1)) for c in chosen]
            for i in range(0, len(rows), 50_000):
                columns = zip(*rows[i : i + 50_000], strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(columns, (pa.int64(), pa.bool_(), pa.int64(), pa.int32(), pa.binary()), strict=True)], names=["mini", "hot", "doc_id", "begin", "packed"])

    return run


def _buckets(plan: Plan, most: int = 1_500_000):
    """Rows come sorted by minimiser; whole minimisers are gathered until there are `most` bytes, then sorted."""

    def run(batches):
        import pyarrow as pa

        def flush(rows):
            found = list(plan.sorter(rows, plan))
            columns = list(zip(*found, strict=True)) or [(), (), ()]
            return pa.RecordBatch.from_arrays([pa.array(columns[0], pa.int64()), pa.array(columns[1], pa.int32()), pa.array(columns[2], pa.int32())], names=["doc_id", "begin", "n"])

        held, size, last = [], 0, None
        for batch in batches:
            for mini, *row in zip(*(batch.column(c).to_pylist() for c in ("mini", "doc_id", "begin", "packed")), strict=True):
                if mini != last and size > most:
                    yield flush(held)
                    held, size = [], 0
                last = mini
                held.append(tuple(row))
                size += len(row[-1])
        if held:
            yield flush(held)

    return run


def _fingerprints(plan: Plan):
    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for i in range(0, batch.num_rows, 2000):
                part = batch.slice(i, 2000)
                units = plan.units(part.column("packed").to_pylist())
                windows = np.diff(units.at) - plan.span + 1
                row = np.repeat(np.arange(len(windows)), windows)
                offset = np.arange(len(row)) - np.repeat(np.cumsum(windows) - windows, windows)
                begin = units.at[row] + offset
                hashes = [Prefix(units.hashes, base).of(begin, begin + plan.span).view(np.int64) for base in (BASE, BASE2)]
                yield pa.RecordBatch.from_arrays(
                    [*map(pa.array, hashes), pa.array(part.column("doc_id").to_numpy(zero_copy_only=False)[row]), pa.array((part.column("begin").to_numpy(zero_copy_only=False)[row] + offset).astype(np.int32))],
                    names=["f1", "f2", "doc_id", "begin"],
                )

    return run


def covered(docs: DataFrame, plan: Plan, scratch: Scratch) -> DataFrame:
    """doc_id, runs: array of (begin, n), the windows of each document that also start earlier."""
    docs = docs.select("doc_id", "text").where("doc_id IS NOT NULL AND text IS NOT NULL")
    seen = docs.mapInArrow(freeing(_minimisers(plan)), "mini long, doc_id long, again boolean")
    shared = seen.groupBy("mini").agg(F.min("doc_id").alias("a"), F.max("doc_id").alias("b"), F.max("again").alias("again"))
    shared = shared.where(F.col("a") < F.col("b") if not plan.within else (F.col("a") < F.col("b")) | F.col("again")).select("mini")
    wanted = scratch.stage(seen.select("mini", "doc_id").join(shared, "mini").groupBy("doc_id").agg(F.collect_set("mini").alias("minis")), "wanted")
    found = scratch.stage(docs.join(wanted, "doc_id").mapInArrow(freeing(_segments(plan)), "mini long, content long, doc_id long, begin int, n int"), "segments")
    scratch.drop("wanted")
    key = ["mini", "content", "n"]
    firsts = scratch.stage(found.groupBy(*key).agg(F.min(F.struct("doc_id", "begin")).alias("first")), "firsts")
    kinds = firsts.groupBy("mini").agg(F.count("*").alias("kinds")).where("kinds > 1")
    first = F.col("first")
    later = (F.col("doc_id") > first["doc_id"]) | ((F.col("doc_id") == first["doc_id"]) & (F.col("begin") > first["begin"])) if plan.within else F.col("doc_id") > first["doc_id"]
    whole = found.join(firsts, key).where(later).select("doc_id", "begin", "n")
    several = firsts.join(kinds, "mini").withColumn("hot", F.col("kinds") > HOT)
    if plan.within:
        several = several.select(first["doc_id"].alias("doc_id"), "mini", "hot", first["begin"].alias("begin"), "n")
    else:
        several = found.join(several, key).where(F.col("doc_id") == first["doc_id"]).select("doc_id", "mini", "hot", "begin", "n")
    chosen = scratch.stage(several.groupBy("doc_id").agg(F.collect_list(F.struct("mini", "hot", "begin", "n")).alias("chosen")), "chosen")
    strings = scratch.stage(docs.join(chosen, "doc_id").mapInArrow(freeing(_packed(plan)), "mini long, hot boolean, doc_id long, begin int, packed binary"), "strings")
    scratch.drop("chosen")
    partial = strings.where("NOT hot").select("mini", "doc_id", "begin", "packed").repartition("mini").sortWithinPartitions("mini").mapInArrow(freeing(_buckets(plan)), "doc_id long, begin int, n int")
    windows = strings.where("hot").select("doc_id", "begin", "packed").mapInArrow(freeing(_fingerprints(plan)), "f1 long, f2 long, doc_id long, begin int")
    earliest = windows.groupBy("f1", "f2").agg(F.min(F.struct("doc_id", "begin")).alias("first"))
    hot = windows.join(earliest, ["f1", "f2"]).where(later).select("doc_id", "begin", F.lit(1).alias("n"))
    runs = whole.unionByName(partial).unionByName(hot).groupBy("doc_id").agg(F.collect_list(F.struct("begin", "n")).alias("runs"))
    runs = scratch.stage(runs, "runs")
    for name in ("segments", "firsts", "strings"):
        scratch.drop(name)
    return runs


def covered_units(runs, n_units: int, span: int) -> np.ndarray:
    """Units covered by the windows of (begin, n) runs."""
    edges = np.zeros(n_units + 1, dtype=np.int32)
    for begin, n in runs:
        edges[min(begin, n_units)] += 1
        edges[min(begin + n + span - 1, n_units)] -= 1
    return np.cumsum(edges[:-1]) > 0


def grouped_runs(starts: np.ndarray) -> Iterator[tuple[int, int]]:
    """(begin, n) of each stretch of consecutive numbers in a sorted array."""
    if len(starts):
        new = np.flatnonzero(np.concatenate([[True], np.diff(starts) != 1]))
        yield from zip(starts[new].tolist(), np.diff(np.concatenate([new, [len(starts)]])).tolist(), strict=True)

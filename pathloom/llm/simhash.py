"""SimHash near-dedup with anchor-point covering.

64-bit fingerprints are split into blocks such that of two fingerprints that differ in at most 4 bits, some block (or
some group of blocks, where there are many fingerprints) differs in at most 1. In each block the anchors are a covering
code of radius 1: the perfect (15, 11) Hamming code on 15 bits, all words on the others. A fingerprint is at home at its
nearest anchor and is replicated to every anchor within radius 1 + 1; linked fingerprints thus meet at the home of
either, where they are compared.

Only distinct fingerprints take part. Anchors with more than HOT fingerprints are compared in pairs of parts; each
comparison gives a spanning forest of what it links, not all pairs.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, freeing, text_chunks
from .components import components

NEAR = 4

#: An anchor's fingerprints are compared in parts of about this many.
HOT = 2000

#: (Fingerprints up to which it holds, blocks, blocks taken together). Of 4 differing bits, the three blocks' least has 1 at
#: most, as have the two least of five and the three least of six. Wider groups have more anchors (2^17, 2^21 and 2^28
#: each), so that an anchor's fingerprints do not grow with the corpus.
LAYOUTS = ((1 << 22, 3, 1), (1 << 27, 5, 2), (1 << 62, 6, 3))

U = np.uint64
_lower = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def fingerprint(text: bytes, shingle: int = 4) -> int:
    import xxhash

    ws = text.translate(_lower).split()
    if not ws:
        return 0
    joined = b" ".join(ws)
    if len(ws) <= shingle:
        return xxhash.xxh64_intdigest(joined, 42)  # one hash: a bit is set in over half of it if it is set
    begins = np.concatenate([[0], np.cumsum(np.fromiter(map(len, ws), dtype=np.int64, count=len(ws)) + 1)])
    digest = xxhash.xxh64_intdigest
    hashes = np.array([digest(joined[b:e], 42) for b, e in zip(begins[:-shingle].tolist(), (begins[shingle:] - 1).tolist(), strict=True)], dtype=U)
    ones = np.zeros(64, dtype=np.int64)
    for i in range(0, len(hashes), 1 << 16):
        ones += np.unpackbits(hashes[i : i + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view(U)[0])


def fingerprints(docs: DataFrame, shingle: int = 4) -> DataFrame:
    """doc_id, fp (the fingerprint's bits as a signed number); null texts are empty, texts without words give 0."""

    def run(batches):
        import pyarrow as pa

        for batch in text_chunks(batches):
            fps = np.array([fingerprint((t or "").encode(), shingle) for t in batch.column("text").to_pylist()], dtype=U)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(fps.view(np.int64))], names=["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(freeing(run), "doc_id long, fp long")


_columns = np.arange(1, 16, dtype=np.int64)  # parity checks of the Hamming code: bit i has the syndrome i + 1


def _syndrome(x: np.ndarray) -> np.ndarray:
    s = np.zeros_like(x)
    for i in range(15):
        s ^= np.where((x >> i) & 1, _columns[i], 0)
    return s


def _within(width: int) -> list[np.ndarray]:
    """Flips of at most 2 bits of a block, as masks."""
    ones = [1 << i for i in range(width)]
    return [np.array(m, dtype=np.int64) for m in ([0], ones, [a | b for a, b in combinations(ones, 2)])]


def layout(n: int) -> list[list[tuple[int, int]]]:
    """The groups of blocks (shift, width) for n fingerprints."""
    blocks, together = next((b, t) for most, b, t in LAYOUTS if n <= most)
    edges = [64 * k // blocks for k in range(blocks + 1)]
    return [list(c) for c in combinations([(b, e - b) for b, e in zip(edges, edges[1:], strict=False)], together)]


def anchors(fps: np.ndarray, groups: list[list[tuple[int, int]]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows (fingerprint's index, anchor's key, home?) of fingerprints (64-bit words)."""
    out, many = [], len(groups)
    for k, group in enumerate(groups):
        block, total = np.zeros(len(fps), dtype=np.int64), 0
        for shift, width in group:
            block |= ((fps >> U(shift)) & U((1 << width) - 1)).astype(np.int64) << total
            total += width
        syndrome = _syndrome(block & 0x7FFF)
        nearest = block ^ np.where(syndrome > 0, 1 << np.maximum(syndrome - 1, 0), 0)
        home = np.arange(len(fps))
        out.append((home, nearest * many + k, np.ones(len(fps), dtype=bool)))
        for flips in _within(total):
            # Flips that lead to a code word: their syndrome cancels the block's.
            by = _syndrome(flips & 0x7FFF)
            order = np.argsort(by, kind="stable")
            first = np.searchsorted(by[order], np.arange(17))
            times = np.diff(first)[syndrome]
            row = np.repeat(home, times)
            offset = np.arange(len(row)) - np.repeat(np.cumsum(times) - times, times)
            key = block[row] ^ flips[order[first[syndrome[row]] + offset]]
            far = key != nearest[row]
            out.append((row[far], key[far] * many + k, np.zeros(int(far.sum()), dtype=bool)))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def _replicate(sources: list[str], carried: list[str], groups: list[list[tuple[int, int]]]):
    """A row for each anchor that the fingerprints in `sources` are replicated to, with the columns `carried`."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            columns = {c: batch.column(c).to_numpy(zero_copy_only=False) for c in {*sources, *carried}}
            for i in range(0, batch.num_rows, 10_000):
                for k, source in enumerate(sources):
                    row, key, home = anchors(columns[source][i : i + 10_000].view(U), groups)
                    yield pa.RecordBatch.from_arrays([pa.array(key * len(sources) + k), *(pa.array(columns[c][i : i + 10_000][row]) for c in carried), pa.array(home)], names=["anchor", *carried, "home"])

    return run


def _far(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Differing bits of rows of 64-bit words."""
    return np.bitwise_count(a ^ b).sum(axis=-1, dtype=np.int64)


def forest(words: np.ndarray, home: np.ndarray, near: int) -> list[tuple[int, int]]:
    """Links that connect what (home, any) pairs within `near` bits connect: each node is reached once."""
    left, out = np.ones(len(words), dtype=bool), []
    while len(roots := np.flatnonzero(left & home)):
        front = roots[:1]
        left[front] = False
        while len(front):
            reached = []
            for i in front.tolist():
                rest = np.flatnonzero(left)
                rest = rest if home[i] else rest[home[rest]]
                hit = rest[_far(words[rest], words[i]) <= near]
                left[hit] = False
                out += [(i, j) for j in hit.tolist()]
                reached.append(hit)
            front = np.concatenate(reached)
    return out


def forests(words: np.ndarray, home: np.ndarray, nears: tuple[int, ...]) -> list[tuple[int, int]]:
    """The forest of the first threshold, and from each wider one what links trees that are apart."""
    out: list[tuple[int, int]] = []
    tree = np.arange(len(words))
    for near in nears:
        new = [(i, j) for i, j in forest(words, home, near) if tree[i] != tree[j]]
        out += new
        if near != nears[-1]:
            for i, j in new:  # a forest's links come from the root outwards
                tree[j] = tree[i]
    return out


#: Anchors of up to so many fingerprints give all their links.
SMALL = 64


def _compare(name: str, words: list[str], nears: tuple[int, ...]):
    """Batches sorted by (anchor, part, other) to links between what `name` names, by their `words`.

    A large anchor gives spanning forests only; nears are its thresholds, the last the widest.
    """

    def run(batches):
        import pyarrow as pa

        def links(names, prints, home, group):
            at = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
            sizes = np.diff(np.concatenate([at, [len(group)]]))
            small = np.repeat(sizes <= SMALL, sizes)
            rows = np.flatnonzero(home & small)
            which = np.searchsorted(at, rows, side="right") - 1
            found = [np.zeros((0, 2), dtype=np.int64)]
            for i in range(0, len(rows), 10_000):
                r, w = rows[i : i + 10_000], which[i : i + 10_000]
                a = np.repeat(r, sizes[w])
                b = np.arange(len(a)) - np.repeat(np.cumsum(sizes[w]) - sizes[w], sizes[w]) + np.repeat(at[w], sizes[w])
                hit = (a != b) & (_far(prints[a], prints[b]) <= nears[-1])
                found.append(np.stack([a[hit], b[hit]], axis=1))
            for k in np.flatnonzero(sizes > SMALL):
                s = slice(at[k], at[k] + sizes[k])
                found.append(np.array(forests(prints[s], home[s], nears), dtype=np.int64).reshape(-1, 2) + at[k])
            pairs = np.concatenate(found)
            a, b = names[pairs[:, 0]], names[pairs[:, 1]]
            pairs = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)], axis=1), axis=0)
            return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["a", "b"])

        numbers = lambda batch, c: batch.column(c).to_numpy(zero_copy_only=False)
        held = None
        for batch in batches:
            codes = np.stack([numbers(batch, c).astype(np.int64) for c in ("anchor", "part", "other")])
            new = [codes, numbers(batch, name), np.stack([numbers(batch, w).view(U) for w in words]), numbers(batch, "home").astype(bool)]
            held = new if held is None else [np.concatenate([x, y], axis=-1) for x, y in zip(held, new, strict=True)]
            group = np.concatenate([[0], np.cumsum(np.any(held[0][:, 1:] != held[0][:, :-1], axis=0))])
            n = int(np.searchsorted(group, group[-1]))  # the last group may go on
            if n > 50_000:
                yield links(held[1][:n], np.ascontiguousarray(held[2][:, :n].T), held[3][:n], group[:n])
                held = [x[..., n:] for x in held]
        if held is not None and held[0].shape[1]:
            group = np.concatenate([[0], np.cumsum(np.any(held[0][:, 1:] != held[0][:, :-1], axis=0))])
            yield links(held[1], np.ascontiguousarray(held[2].T), held[3], group)

    return run


def linked(rows: DataFrame, n: int, name: str, sources: list[str], words: list[str], nears: tuple[int, ...]) -> DataFrame:
    """Links (a, b) of `name` between the n rows at most whose `words` differ in nears[-1] bits at most and whose `sources`
    meet at an anchor; those of a large anchor may be a spanning forest."""
    carried = list(dict.fromkeys([name, *words]))
    rows = rows.mapInArrow(freeing(_replicate(sources, carried, layout(n))), f"anchor long, {', '.join(f'{c} long' for c in carried)}, home boolean")
    parts = rows.groupBy("anchor").agg(F.count("*").alias("n")).where(F.col("n") > HOT).select("anchor", F.ceil(F.col("n") / HOT).alias("k"))
    rows = rows.join(parts, "anchor", "left")
    own = F.pmod(F.xxhash64(name), F.col("k"))
    # Part p meets part q in the comparison (min, max); an anchor in one part has the comparison (0, 0).
    meet = F.when(F.col("k").isNull(), F.array(F.struct(F.lit(0).alias("part"), F.lit(0).alias("other")))).otherwise(
        F.transform(F.sequence(F.lit(0).cast("long"), F.col("k") - 1), lambda q: F.struct(F.least(own, q).cast("int").alias("part"), F.greatest(own, q).cast("int").alias("other")))
    )
    rows = rows.select("anchor", *carried, "home", F.explode(meet).alias("m")).select("anchor", "m.part", "m.other", *carried, "home")
    dealt = rows.repartition("anchor", "part", "other").sortWithinPartitions("anchor", "part", "other")
    return dealt.mapInArrow(freeing(_compare(name, words, nears)), "a long, b long").distinct()


def simhash_components(docs: DataFrame, shingle: int = 4, near: int = NEAR) -> DataFrame:
    """doc_id, fp, component_id: the smallest doc_id that links of at most `near` differing bits reach.

    A row for each row of docs, repeated rows included. Null and empty texts have fingerprint 0 and are linked like any
    other; a null doc_id is never a component_id unless its component has no other. Other columns are ignored. An empty
    table gives no rows.
    """
    scratch = Scratch(docs.sparkSession, "simhash")
    fps = scratch.stage(fingerprints(docs, shingle), "fingerprints")
    firsts = scratch.stage(fps.groupBy("fp").agg(F.min("doc_id").alias("first")), "firsts")
    if near > NEAR:
        raise ValueError(f"the anchors cover up to {NEAR} bits")
    roots = components(linked(firsts, firsts.count(), "fp", ["fp"], ["fp"], (near,)), scratch)
    classes = firsts.join(roots, firsts["fp"] == roots["node"], "left").select(firsts["fp"], F.coalesce("root", firsts["fp"]).alias("root"), "first")
    least = classes.groupBy("root").agg(F.min("first").alias("component_id"))
    return fps.join(classes.select("fp", "root").join(least, "root").select("fp", "component_id"), "fp").select("doc_id", "fp", "component_id")

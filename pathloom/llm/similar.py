"""Near-dedup by SimHash of documents whose sets of word shingles have 4/5 of their union in common.

At that similarity a fingerprint of 5-word shingles differs in about a seventh of its bits, too many for anchors to cover.
A changed word touches five of these shingles but two pairs of words, so the fingerprints that meet at anchors are those of
pairs of words: SKETCHES of 64 bits each, every block of which brings documents together that differ in one of its bits at
most. What meets is compared by 128 bits of fingerprint of the 5-word shingles, with room for their spread, and each link
is then decided by the whole sets.

Fingerprints miss some pairs, so an exact search follows for what they leave apart. Of two sets alike by SHARE each has a
common shingle among its first n - ceil(SHARE * n) + 1 in any order that both follow; the order is by how many documents
hold a shingle, rarest first, so shingles of one document fill most of these places and bring nothing together. Sets of
different components that meet at another one, and that the places of what they share do not rule out, are compared whole.

Shingles and sets are known by 64-bit hashes.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, freeing, text_chunks
from .components import components
from .segments import Prefix, mix, word_units
from .simhash import HOT, U, _lower, linked

#: The least similarity, SHARE[0] / SHARE[1].
SHARE = (4, 5)
#: Fingerprints of pairs of words that meet at anchors, and of shingles that are compared, 64 bits each.
SKETCHES, PRINTS = 2, 2
#: Differing bits of 128: documents at the least similarity differ in 19 +- 4, others in 64 +- 6. Large groups are first linked
#: by the smaller number, which few pairs below the similarity have.
NEAR, WIDE = 20, 32
#: Slots that hashes of linked sets fall in; only texts in one of them send their sets on.
SLOTS = 1 << 20
#: Shingles that one task counts at a time, about.
COUNTED = 2_000_000
#: Bytes of a batch, to Python and from it, about: rows hold whole sets or a bucket's shingles, so a bound in rows is none.
BATCH = 4_000_000


def shingle_sets(texts: list[bytes], shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes of the distinct shingles of each text, sorted text by text; where each text's begin). A text of fewer words
    is a shingle as a whole."""
    units = word_units([t.translate(_lower) for t in texts])
    prefix, n = Prefix(units.hashes), np.diff(units.at)
    width = np.minimum(n, shingle)
    count = n - width + 1
    doc = np.repeat(np.arange(len(texts)), count)
    begin = np.arange(len(doc)) - np.repeat(np.cumsum(count) - count, count) + units.at[doc]
    hashes = prefix.of(begin, begin + width[doc]) if len(units.hashes) else np.zeros(len(doc), dtype=U)
    order = np.argsort(hashes)
    order = order[np.argsort(doc[order].astype(np.min_scalar_type(len(texts))), kind="stable")]
    hashes, doc = hashes[order], doc[order]
    new = np.concatenate([[True], (hashes[1:] != hashes[:-1]) | (doc[1:] != doc[:-1])]) if len(doc) else np.zeros(0, dtype=bool)
    return hashes[new], np.searchsorted(doc[new], np.arange(len(texts) + 1))


def prints(hashes: np.ndarray, at: np.ndarray, n: int) -> list[np.ndarray]:
    """n fingerprints of 64 bits for each text of sets of hashes: a bit is 1 if set in over half of them."""
    sizes, out = np.diff(at), []
    for k in range(n):
        bits = np.zeros((len(sizes), 64), dtype=np.int64)
        own = mix(hashes + U((k + 1) * 0x9E3779B97F4A7C15 % (1 << 64)))
        step = 1 << 17
        for i in range(0, len(own), step):  # the texts that a stretch of hashes belongs to
            first, last = np.searchsorted(at, i, side="right") - 1, np.searchsorted(at, min(i + step, len(own)), side="left")
            begins = np.maximum(at[first:last], i) - i
            bits[first:last] += np.add.reduceat(np.unpackbits(own[i : i + step].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"), begins, axis=0, dtype=np.int32)
        out.append(np.packbits(2 * bits > sizes[:, None], axis=1, bitorder="little").view(U).ravel())
    return out


def set_ids(hashes: np.ndarray, at: np.ndarray) -> np.ndarray:
    """A hash of each set."""
    sums = np.add.reduceat(mix(hashes ^ U(0xA0761D6478BD642F)), at[:-1]) if len(at) > 1 else np.zeros(0, dtype=U)
    return mix(sums + np.diff(at).astype(U)).view(np.int64)


def alike(a: np.ndarray, b: np.ndarray) -> bool:
    """Whether sorted sets of distinct hashes have SHARE of their union in common."""
    if SHARE[1] * min(len(a), len(b)) < SHARE[0] * max(len(a), len(b)):
        return False
    few, many = (a, b) if len(a) <= len(b) else (b, a)
    both = int((many[np.minimum(np.searchsorted(many, few), len(many) - 1)] == few).sum())
    return SHARE[1] * both >= SHARE[0] * (len(a) + len(b) - both)


def first_places(sizes: np.ndarray) -> np.ndarray:
    """How many shingles of sets of these sizes, in any order, hold one in common with each set that is alike."""
    return sizes - -(-SHARE[0] * sizes // SHARE[1]) + 1


def _over(docs: DataFrame, schema: str, make, most: int = 2_000_000) -> DataFrame:
    """make(doc_ids, texts as bytes) of chunks of docs: a record batch or None."""

    def run(batches):
        import pyarrow as pa

        for batch in text_chunks(batches, most=most):
            out = make(batch.column("doc_id"), [t or b"" for t in batch.column("text").cast(pa.binary()).to_pylist()])
            if out is not None:
                yield out

    return docs.mapInArrow(freeing(run), schema)


SKETCH, PRINT = [f"s{k}" for k in range(SKETCHES)], [f"p{k}" for k in range(PRINTS)]


def _fingerprints(shingle: int):
    def make(doc_ids, texts):
        import pyarrow as pa

        own, pairs = shingle_sets(texts, shingle), shingle_sets(texts, 2)
        words = [pa.array(x.view(np.int64)) for x in (*prints(*pairs, SKETCHES), *prints(*own, PRINTS))]
        return pa.RecordBatch.from_arrays([doc_ids, pa.array(set_ids(*own)), pa.array(np.diff(own[1])), *words], names=["doc_id", "sid", "n", *SKETCH, *PRINT])

    return make


def _sets(shingle: int, wanted: np.ndarray):
    def make(doc_ids, texts):
        import pyarrow as pa

        hashes, at = shingle_sets(texts, shingle)
        ids = set_ids(hashes, at)
        _, first = np.unique(ids, return_index=True)
        first = first[wanted[ids[first] % len(wanted)]]
        return pa.RecordBatch.from_arrays([pa.array(ids[first]), pa.array([hashes[at[k] : at[k + 1]].tobytes() for k in first.tolist()], pa.binary())], names=["sid", "own"]) if len(first) else None

    return make


def _verified(batches):
    import pyarrow as pa

    for batch in batches:
        a, b = (batch.column(k).to_pylist() for k in ("sa", "sb"))
        hit = [alike(np.frombuffer(x, dtype=U), np.frombuffer(y, dtype=U)) for x, y in zip(a, b, strict=True)]
        yield batch.select(["a", "b"]).filter(pa.array(hit, pa.bool_()))


def _dealt(shingle: int, buckets: int):
    """Rows (bucket, chunk, listed, shingles, owners) of a chunk's distinct sets: the shingles of each bucket with the places
    of their sets in the chunk, and one listed row with the sets' ids and sizes."""
    state = {}

    def make(doc_ids, texts):
        import pyarrow as pa
        from pyspark import TaskContext

        hashes, at = shingle_sets(texts, shingle)
        ids = set_ids(hashes, at)
        new = np.zeros(len(ids), dtype=bool)
        new[np.unique(ids, return_index=True)[1]] = True
        sizes = np.diff(at)
        hashes, ids, sizes = hashes[np.repeat(new, sizes)], ids[new], sizes[new]
        owner = np.repeat(np.arange(len(ids), dtype=np.min_scalar_type(len(ids))), sizes)
        turn = state["turn"] = state.get("turn", -1) + 1
        chunk = (TaskContext.get().partitionId() << 32) + turn
        bucket = (mix(hashes) % U(buckets)).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        hashes, owner, cut = hashes[order], owner[order], np.searchsorted(bucket[order], np.arange(buckets + 1))
        full = np.flatnonzero(np.diff(cut)).tolist()
        part = lambda x: [x[cut[k] : cut[k + 1]].tobytes() for k in full]
        rows = [
            [chunk % buckets, *full], [chunk] * (len(full) + 1), [True] + [False] * len(full),
            pa.array([ids.tobytes(), *part(hashes)], pa.binary()), pa.array([sizes.astype(np.int64).tobytes(), *part(owner)], pa.binary()),
        ]
        return pa.RecordBatch.from_arrays([pa.array(x) if isinstance(x, list) else x for x in rows], names=["bucket", "chunk", "listed", "shingles", "owners"])

    return make


def _grouped(batches, key: str):
    """Batches sorted by key to a dictionary of column lists for each of its values."""
    held: dict[str, list] = {}
    for batch in batches:
        new = {c: batch.column(c).to_pylist() for c in batch.schema.names}
        keys = np.array(new[key], dtype=np.int64)
        cut = [0, *(np.flatnonzero(keys[1:] != keys[:-1]) + 1).tolist(), len(keys)]
        for i, j in zip(cut, cut[1:], strict=False):
            if i == j:
                continue
            if held and held[key][0] != new[key][i]:
                yield held
                held = {}
            held = {c: held.get(c, []) + x[i:j] for c, x in new.items()}
    if held:
        yield held


def _owners(owners: bytes, n: int) -> np.ndarray:
    """The places of n shingles' sets, in numbers as wide as they were written."""
    return np.frombuffer(owners, dtype=f"u{len(owners) // n}").astype(np.int64)


def _counted(hashes: np.ndarray) -> np.ndarray:
    """How often each of the hashes comes among them; they are sorted an eighth at a time."""
    counts, part = np.empty(len(hashes), dtype=np.uint32), hashes.view(np.uint8)[7::8] >> 5
    for k in range(8):
        order = np.flatnonzero(part == k)
        order = order[np.argsort(hashes[order])]
        ordered = hashes[order]
        begin = np.flatnonzero(np.concatenate([[True], ordered[1:] != ordered[:-1]])) if len(ordered) else order
        times = np.diff(np.concatenate([begin, [len(ordered)]]))
        counts[order] = np.repeat(times, times)
    return counts


def _shared(batches):
    """Batches sorted by bucket to rows (chunk, listed, shingles, owners, counts) of the shingles that come more than once."""
    import pyarrow as pa

    names = ["chunk", "listed", "shingles", "owners", "counts"]
    types = [pa.int64(), pa.bool_(), pa.binary(), pa.binary(), pa.binary()]

    def rows_of(g):
        for c, lead, s, o in zip(g["chunk"], g["listed"], g["shingles"], g["owners"], strict=True):
            if lead:
                yield c, True, s, o, b""
        rows = [k for k, lead in enumerate(g["listed"]) if not lead]
        if rows:
            at = np.concatenate([[0], np.cumsum([len(g["shingles"][k]) // 8 for k in rows])])
            hashes = np.empty(at[-1], dtype=U)
            for k, i, j in zip(rows, at, at[1:], strict=False):
                hashes[i:j] = np.frombuffer(g["shingles"][k], dtype=U)
                g["shingles"][k] = None  # the bytes go as they are read
            counts = _counted(hashes)
            for k, i, j in zip(rows, at, at[1:], strict=False):
                if len(hit := np.flatnonzero(counts[i:j] > 1)):
                    owner = _owners(g["owners"][k], j - i)[hit].astype(np.uint32)
                    yield g["chunk"][k], False, hashes[i:j][hit].tobytes(), owner.tobytes(), counts[i:j][hit].tobytes()

    def batch(rows):
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)

    for g in _grouped(batches, "bucket"):
        out, size = [], 0
        for row in rows_of(g):
            out.append(row)
            size += sum(map(len, row[2:]))
            if size > BATCH:
                yield batch(out)
                out, size = [], 0
        if out:
            yield batch(out)


def _first(batches):
    """Batches sorted by chunk to rows (shingle, sid, place, n): what each set has at its first places that others may share."""
    import pyarrow as pa

    for g in _grouped(batches, "chunk"):
        lead = g["listed"].index(True)
        ids, sizes = np.frombuffer(g["shingles"][lead], dtype=np.int64), np.frombuffer(g["owners"][lead], dtype=np.int64)
        rows = [k for k, x in enumerate(g["listed"]) if not x]
        if not rows:
            continue
        hashes, owner, counts = (np.concatenate([np.frombuffer(g[c][k], dtype=t) for k in rows]) for c, t in (("shingles", U), ("owners", np.uint32), ("counts", np.uint32)))
        order = np.lexsort((hashes, counts, owner))
        hashes, owner = hashes[order], owner[order].astype(np.int64)
        many = np.bincount(owner, minlength=len(ids))
        place = np.arange(len(owner)) - (np.cumsum(many) - many)[owner] + (sizes - many)[owner]
        hit = place < first_places(sizes)[owner]
        columns = [hashes[hit].view(np.int64), ids[owner[hit]], place[hit], sizes[owner[hit]]]
        yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["shingle", "sid", "place", "n"])


def left_apart(docs: DataFrame, classes: DataFrame, shingles: int, shingle: int, scratch: Scratch) -> DataFrame:
    """Pairs (a, b) of sets in different classes (sid, root) that may be alike by SHARE; none that is alike is left out.

    shingles: how many the sets have in all.
    """
    buckets = shingles // COUNTED + 1
    dealt = _over(docs, "bucket long, chunk long, listed boolean, shingles binary, owners binary", _dealt(shingle, buckets), 4_000_000)
    dealt = dealt.repartition("bucket").sortWithinPartitions("bucket")
    shared = dealt.mapInArrow(freeing(_shared), "chunk long, listed boolean, shingles binary, owners binary, counts binary")
    found = shared.repartition("chunk").sortWithinPartitions("chunk").mapInArrow(freeing(_first), "shingle long, sid long, place long, n long")
    first = scratch.stage(found.dropDuplicates(["shingle", "sid"]).join(classes.select("sid", "root"), "sid"), "first")
    several = first.groupBy("shingle").agg(F.count("*").alias("many"), F.min("root").alias("least"), F.max("root").alias("most")).where("least < most")
    parts = F.ceil(F.col("many") / HOT)
    rows = first.join(several.select("shingle", parts.alias("k")), "shingle").withColumn("own", F.pmod(F.xxhash64("sid"), F.col("k")))
    # Part p of a shingle's sets meets part q in the comparison (min, max).
    meet = F.transform(F.sequence(F.lit(0).cast("long"), F.col("k") - 1), lambda q: F.struct(F.least("own", q).alias("low"), F.greatest("own", q).alias("high")))
    rows = rows.withColumn("m", F.explode(meet)).select("shingle", "m.low", "m.high", "own", "sid", "root", "place", "n")
    a, b = (rows.select("shingle", "low", "high", *(F.col(c).alias(f"{c}_{x}") for c in ("own", "sid", "root", "place", "n"))) for x in "ab")
    both = a.join(b, ["shingle", "low", "high"]).where("sid_a < sid_b AND root_a <> root_b AND (low = high OR own_a <> own_b)")
    both = both.where(SHARE[1] * F.least("n_a", "n_b") >= SHARE[0] * F.greatest("n_a", "n_b"))
    pairs = both.groupBy("sid_a", "sid_b").agg(F.count("*").alias("met"), *(F.max(f"{c}_{x}").alias(f"{c}_{x}") for c in ("place", "n") for x in "ab"))
    # All that two sets share up to the last place where they met is known; after it, at most the rest of the smaller.
    most = F.col("met") + F.least(F.col("n_a") - 1 - F.col("place_a"), F.col("n_b") - 1 - F.col("place_b"))
    return pairs.where((SHARE[0] + SHARE[1]) * most >= SHARE[0] * (F.col("n_a") + F.col("n_b"))).select(F.col("sid_a").alias("a"), F.col("sid_b").alias("b"))


def _alike_pairs(docs: DataFrame, met: DataFrame, shingle: int, scratch: Scratch, name: str) -> DataFrame:
    """The pairs (a, b) of met, of ids of sets, that are alike by SHARE."""
    wanted = np.zeros(SLOTS, dtype=bool)
    slot = lambda c: F.pmod(F.col(c), F.lit(SLOTS)).alias("slot")
    wanted[[r["slot"] for r in met.select(slot("a")).union(met.select(slot("b"))).distinct().collect()]] = True  # SLOTS rows at most
    if not wanted.any():
        return docs.sparkSession.createDataFrame([], "a long, b long")
    sets = scratch.stage(_over(docs, "sid long, own binary", _sets(shingle, wanted)).dropDuplicates(["sid"]), f"{name}_sets")
    both = met.join(sets.select(F.col("sid").alias("a"), F.col("own").alias("sa")), "a").join(sets.select(F.col("sid").alias("b"), F.col("own").alias("sb")), "b")
    links = scratch.stage(both.select("a", "b", "sa", "sb").mapInArrow(freeing(_verified), "a long, b long"), name)
    scratch.drop(f"{name}_sets")
    return links


def similar_components(docs: DataFrame, shingle: int = 5) -> DataFrame:
    """doc_id, component_id: the smallest doc_id that links of documents alike by SHARE of their shingles reach.

    A row for each row of docs. Null and empty texts are alike; a null doc_id is never a component_id unless its component
    has no other. Other columns are ignored. An empty table gives no rows.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "similar", BATCH)
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    words = ", ".join(f"{c} long" for c in (*SKETCH, *PRINT))
    ids = scratch.stage(_over(docs, f"doc_id long, sid long, n long, {words}", _fingerprints(shingle)), "ids")
    kinds = scratch.stage(ids.groupBy("sid").agg(F.min("doc_id").alias("first"), *(F.min(c).alias(c) for c in ("n", *SKETCH, *PRINT))), "kinds")
    many, shingles = kinds.agg(F.count("*"), F.coalesce(F.sum("n"), F.lit(0))).first()
    met = scratch.stage(linked(kinds.select("sid", *SKETCH, *PRINT), many, "sid", SKETCH, PRINT, (NEAR, WIDE)), "met")
    links = _alike_pairs(docs, met, shingle, scratch, "links")
    scratch.drop("met")

    def of(roots: DataFrame) -> DataFrame:
        return kinds.join(roots, kinds["sid"] == roots["node"], "left").select("sid", F.coalesce("root", "sid").alias("root"), "first")

    classes = of(components(links, scratch))
    apart = scratch.stage(left_apart(docs, classes, shingles, shingle, scratch), "apart")
    scratch.drop("first")
    more = _alike_pairs(docs, apart, shingle, scratch, "more")
    if not more.isEmpty():
        classes = of(components(links.unionByName(more), scratch, "wider"))
    least = classes.groupBy("root").agg(F.min("first").alias("component_id"))
    return ids.select("doc_id", "sid").join(classes.select("sid", "root").join(least, "root").select("sid", "component_id"), "sid").select("doc_id", "component_id")


def similar_dedup(docs: DataFrame, shingle: int = 5) -> DataFrame:
    """The rows of docs with one document for each component, that of the smallest doc_id; its repeated rows stay.

    Rows without doc_id stay, all of them, where one of them has no other document in its component. Columns of docs may
    have any names.
    """
    found = similar_components(docs, shingle)
    kept = found.where(F.col("doc_id").eqNullSafe(F.col("component_id"))).select("doc_id").distinct()
    return docs.alias("d").join(kept.alias("k"), F.col("d.doc_id").eqNullSafe(F.col("k.doc_id")), "left_semi")

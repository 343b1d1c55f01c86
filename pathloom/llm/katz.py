"""Katz backoff language model of any order, with Good-Turing discounts and exactly normalised backoff weights.

A task packs its texts into blocks of about BLOCK bytes, staged once. Level by level, from single words up, each block
sends its distinct n-grams, packed and dealt by context, to buckets. A bucket counts them over the training documents,
sums up its contexts, and tells every block what it asked for: the counts, and what the backoff weights of contexts with
an unseen n-gram are made of. Discounts follow from counts of counts once all buckets are done, so the block itself
turns both into probabilities, which the next level's questions carry as the lower-order distribution: the recursion of
the definition, over arrays of tokens. Counts and answers are tables in the shared folder, partitioned by level, so a
lost executor repeats its own tasks only.

A context of more than SPLIT tokens is split over several buckets, each of which sums up its part; the sums meet in a
table of MOST_SPLIT contexts at most, whatever the input.

N-grams and contexts are known by 64-bit hashes, of which 48 bits travel (beside the bucket, which all of them choose). Probabilities of lower orders are rounded to 32-bit
floats, in sums and in use alike. An unseen word has the mass of the unigram discounts. A context in which no count is
discounted backs off with the mass of half an occurrence.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, freeing, freeing_group, freeing_groups, text_chunks, text_or_empty
from .segments import mix, word_units
from .simhash import _lower

#: Bytes of text in a block, about; a longer text is a block of its own.
BLOCK = 3_000_000
#: Tokens after a context from which on it is split: SPLIT, or where that gave more than MOST_SPLIT contexts, as many as give so many.
SPLIT, MOST_SPLIT = 160_000, 1_000_000
#: Counts up to this one are discounted.
DISCOUNTED = 5
#: Passes over the blocks that ask for n-grams of a level, each for its share of the buckets; the last holds for higher ones.
PASSES = (1, 2, 4)

U = np.uint64
START, END = U(1), U(2)
_PAIR, _PART = U(0x9E3779B97F4A7C15), U(0xC2B2AE3D27D4EB4F)


# ---- blocks and their tokens

def _blocks(batches):
    """Rows of texts packed together: block, ids, held_out and sizes of the texts, payload."""
    import pyarrow as pa
    from pyspark import TaskContext

    task, turn = TaskContext.get().partitionId(), 0
    codec = pa.Codec("zstd", 1)

    def packed(held):
        ids, out, texts = ([x for part in held for x in part[k]] for k in range(3))
        row = ((task << 24) + turn, ids, out, [len(t) for t in texts], codec.compress(b"".join(texts), asbytes=True))
        kinds = (pa.int64(), pa.list_(pa.int64()), pa.list_(pa.bool_()), pa.list_(pa.int64()), pa.binary())
        return pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in zip(row, kinds, strict=True)], names=["block", "ids", "held_out", "sizes", "payload"])

    held, total = [], 0
    for batch in text_chunks(batches):
        texts = [t or b"" for t in batch.column("text").cast(pa.binary()).to_pylist()]
        held.append((batch.column("doc_id").to_pylist(), batch.column("held_out").to_pylist(), texts))
        total += sum(map(len, texts))
        if total >= BLOCK:
            yield packed(held)
            held, total, turn = [], 0, turn + 1
    if held:
        yield packed(held)


def _texts(sizes: list[int], payload: bytes) -> list[bytes]:
    import pyarrow as pa

    joined = pa.Codec("zstd").decompress(payload, sum(sizes), asbytes=True) if any(sizes) else b""
    ends = np.cumsum(sizes).tolist()
    return [joined[e - n : e] for e, n in zip(ends, sizes, strict=True)]


def _hashes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the tokens of texts, each document's end included, and how many each document has."""
    units = word_units([t.translate(_lower) for t in texts])
    sizes = np.diff(units.at) + 1
    word = np.full(int(sizes.sum()), END, dtype=U)
    inside = np.ones(len(word), dtype=bool)
    inside[np.cumsum(sizes) - 1] = False
    word[inside] = units.hashes
    return word, sizes


class Tokens:
    """The tokens of a block: their hashes, whether they are in training documents, and n-grams level by level."""

    def __init__(self, sizes: list[int], payload: bytes, held_out: list[bool]):
        self.word, self.sizes = _hashes(_texts(sizes, payload))
        self.train = np.repeat(~np.array(held_out, dtype=bool), self.sizes)
        self.first = np.cumsum(self.sizes) - self.sizes

    def before(self, x: np.ndarray, at_start) -> np.ndarray:
        """For each token, x of the token before it; at_start for a document's first."""
        out = np.empty_like(x)
        out[1:] = x[:-1]
        out[self.first] = at_start
        return out

    def grams(self, lower: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
        """(n-gram, context) of each token, from the n-grams of the order below."""
        context = np.zeros(len(self.word), dtype=U) if lower is None else self.before(lower, START)
        return mix(context * _PAIR + self.word), context

    def per_document(self, x: np.ndarray) -> np.ndarray:
        return np.bincount(np.repeat(np.arange(len(self.sizes)), self.sizes), weights=x, minlength=len(self.sizes))


# ---- questions

def _stretches(keys: np.ndarray) -> np.ndarray:
    """Where stretches of equal keys begin."""
    return np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, dtype=np.int64)


def _lengths(at: np.ndarray, n: int) -> np.ndarray:
    return np.diff(np.concatenate([at, [n]]))


class Asked:
    """A block's distinct n-grams in the order in which it asks for them: by bucket, context and hash.

    of: each token's place among them; token: a token of each. parts: over how many buckets a token's context is split.
    """

    def __init__(self, gram: np.ndarray, context: np.ndarray, parts: np.ndarray, n_buckets: int):
        order = np.argsort(gram)
        own = gram[order]
        at = _stretches(own)
        token = order[at]
        bucket = ((mix(context[token] + (gram[token] % parts[token]) * _PART) >> U(33)) % U(n_buckets)).astype(np.min_scalar_type(n_buckets))
        # Stable sorts, so that blocks find the same order again wherever they are read.
        by = np.argsort(context[token], kind="stable")
        by = by[np.argsort(bucket[by], kind="stable")]
        place = np.empty(len(by), dtype=np.int64)
        place[by] = np.arange(len(by))
        self.of = np.empty(len(gram), dtype=np.int64)
        self.of[order] = np.repeat(place, _lengths(at, len(own)))
        self.token, self.bucket = token[by], bucket[by]
        self.gram, self.context, self.split = gram[self.token], context[self.token], parts[self.token] > 1
        #: Contexts, bucket by bucket.
        new = self.bucket[1:] != self.bucket[:-1]
        self.runs = np.flatnonzero(np.concatenate([[True], new | (self.context[1:] != self.context[:-1])])) if len(by) else at
        #: (bucket, begin, end) among the n-grams.
        begins = _stretches(self.bucket)
        self.buckets = list(zip(self.bucket[begins].tolist(), begins.tolist(), (begins + _lengths(begins, len(by))).tolist(), strict=True))


def _least_type(x: np.ndarray) -> bytes:
    return x.astype(np.min_scalar_type(int(x.max()) if len(x) else 0)).tobytes()


def _numbers(raw: bytes, n: int) -> np.ndarray:
    """Unsigned numbers written by _least_type."""
    return np.frombuffer(raw, dtype=f"u{len(raw) // n}").astype(np.int64) if n else np.zeros(0, dtype=np.int64)


#: N-grams and contexts travel as 48 bits; buckets tell more of them apart.
SHORT = U((1 << 48) - 1)


def _short(x: np.ndarray) -> bytes:
    return x.view(np.uint8).reshape(-1, 8)[:, :6].tobytes()


def _widened(raw: bytes) -> np.ndarray:
    out = np.zeros((len(raw) // 6, 8), dtype=np.uint8)
    out[:, :6] = np.frombuffer(raw, dtype=np.uint8).reshape(-1, 6)
    return out.view(U).ravel()


def _question_rows(block: int, asked: Asked, times: np.ndarray, low: np.ndarray | None, passes: int, turn: int):
    import pyarrow as pa

    rows = []
    begins, lengths = asked.runs, _lengths(asked.runs, len(asked.gram))
    signed = np.where(asked.split[begins], -lengths, lengths).astype(np.int32) if len(begins) else lengths.astype(np.int32)
    for bucket, b, e in asked.buckets:
        if bucket % passes != turn:
            continue
        r = slice(*np.searchsorted(begins, [b, e]).tolist())
        rows.append((bucket, block, signed[r].tobytes() + _short(asked.context[begins[r]]), _short(asked.gram[b:e]), _least_type(times[b:e]), b"" if low is None else low[b:e][times[b:e] > 0].tobytes()))
    columns = zip(*rows, strict=True) if rows else ((),) * 6
    kinds = (pa.int32(), pa.int64(), pa.binary(), pa.binary(), pa.binary(), pa.binary())
    return pa.table([pa.array(x, t) for x, t in zip(columns, kinds, strict=True)], names=["bucket", "block", "contexts", "grams", "times", "low"])


QUESTIONS = "bucket int, block long, contexts binary, grams binary, times binary, low binary"


# ---- answers

#: Rows to blocks have counts (twice the count, and one more where the context has no discounted count), and the sums of
#: contexts with an unseen n-gram: ones (how many n-grams have each discounted count) and low. Rows of parts of split
#: contexts have no block; rows of counts of counts have these only: tokens, distinct n-grams, and those seen 1, 2, ... times.
ANSWERS = "block long, bucket int, counts binary, ones binary, low binary, sums array<long>"


def _answer(table):
    """A bucket's answers to the blocks that asked it."""
    import pyarrow as pa

    blocks = table.column("block").to_pylist()
    contexts, runs, sizes = [], [], []
    for raw in table.column("contexts").to_pylist():
        n = len(raw) // 10
        runs.append(np.frombuffer(raw, dtype=np.int32, count=n))
        contexts.append(_widened(raw[4 * n :]))
        sizes.append(int(np.abs(runs[-1]).sum()))
    of_run = np.concatenate(runs)
    lengths = np.abs(of_run)
    context = np.repeat(np.concatenate(contexts), lengths)
    split = np.repeat(of_run < 0, lengths)
    gram = _widened(b"".join(table.column("grams").to_pylist()))
    times = np.concatenate([_numbers(t, n) for t, n in zip(table.column("times").to_pylist(), sizes, strict=True)])
    low = np.zeros(len(context), dtype=np.float32)
    if lows := b"".join(table.column("low").to_pylist()):
        low[times > 0] = np.frombuffer(lows, dtype=np.float32)

    key = mix(context * _PAIR + gram)
    del gram
    order = np.argsort(key)
    at = _stretches(key[order])
    of = np.empty(len(key), dtype=np.int64)
    of[order] = np.repeat(np.arange(len(at)), _lengths(at, len(key)))
    del key
    count = np.add.reduceat(times[order], at)
    own, is_split, lower = context[order[at]], split[order[at]], np.maximum.reduceat(low[order], at)
    del order, times, low, context, split

    seen = np.flatnonzero(count)
    seen = seen[np.argsort(own[seen], kind="stable")]
    begins = _stretches(own[seen])
    known = own[seen[begins]]
    if len(seen):
        c = count[seen]
        ones = np.stack([np.add.reduceat((c == r).astype(np.int32), begins, dtype=np.int32) for r in range(1, DISCOUNTED + 1)], axis=1)
        lowsum = np.add.reduceat(lower[seen].astype(np.float64), begins)
    else:
        ones, lowsum = np.zeros((0, DISCOUNTED), dtype=np.int32), np.zeros(0)
    bare = ones.sum(axis=1) == 0
    where = np.minimum(np.searchsorted(known, own), max(len(known) - 1, 0))
    is_known = known[where] == own if len(known) else np.zeros(len(own), dtype=bool)
    code = 2 * count + (bare[where] & is_known & ~is_split if len(known) else 0)

    few = [int(count.sum()), len(seen), *(int(n) for n in np.bincount(count[count <= DISCOUNTED + 1], minlength=DISCOUNTED + 2)[1:])]
    rows = [(None, None, None, None, None, few)]
    apart = is_split[seen[begins]]
    if apart.any():
        rows.append((None, None, known[apart].tobytes(), ones[apart].tobytes(), lowsum[apart].tobytes(), None))
    bucket, end, run_end = table.column("bucket")[0].as_py(), 0, 0
    for block, n, r in zip(blocks, sizes, runs, strict=True):
        mine, begin = of[end : end + n], np.cumsum(np.abs(r)) - np.abs(r)
        unseen = np.add.reduceat((count[mine] == 0).astype(np.int32), begin) > 0
        told = where[mine[begin[unseen & is_known[mine[begin]] & (r > 0)]]]
        rows.append((block, bucket, _least_type(code[mine]), ones[told].tobytes(), lowsum[told].tobytes(), None))
        end += n
    kinds = (pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.list_(pa.int64()))
    return pa.table([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=["block", "bucket", "counts", "ones", "low", "sums"])


def _parts(batches):
    """Rows of (context, how many n-grams have each discounted count, lower-order sum) of split contexts."""
    import pyarrow as pa

    names = ["context", *(f"n{r}" for r in range(1, DISCOUNTED + 1)), "low"]
    for batch in batches:
        for a, b, c in zip(*(batch.column(k).to_pylist() for k in ("counts", "ones", "low")), strict=True):
            ones = np.frombuffer(b, dtype=np.int32).reshape(-1, DISCOUNTED).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(a, dtype=np.int64)), *(pa.array(ones[:, r].copy()) for r in range(DISCOUNTED)), pa.array(np.frombuffer(c, dtype=np.float64))], names=names)


# ---- probabilities

def discounts(few: list[int], top: int = DISCOUNTED) -> list[float]:
    """Katz's ratios for counts 0 to top (few: how many have each count, up to top + 1).

    Where the counts of counts give no ratio between 0 and 1, half an occurrence is taken off.
    """
    out = [0.0]
    share = (top + 1) * few[top + 1] / few[1] if few[1] else 1.0
    for r in range(1, top + 1):
        d = ((r + 1) * few[r + 1] / (r * few[r]) - share) / (1 - share) if few[r] and share < 1 else 0.0
        out.append(d if 0 < d < 1 else (r - 0.5) / r)
    return out


@dataclass(frozen=True)
class Level:
    """Driver-side numbers of an order: what Good-Turing gives, and the sums of split contexts (MOST_SPLIT at most)."""

    tokens: int
    distinct: int
    ratios: np.ndarray  # by count; 1 from DISCOUNTED + 1 on
    split: np.ndarray  # contexts, sorted
    ones: np.ndarray
    low: np.ndarray

    def left(self, ones: np.ndarray) -> np.ndarray:
        """The occurrences that discounts take off contexts, half a one where none is discounted."""
        r = np.arange(1, DISCOUNTED + 1)
        return np.where(ones.sum(axis=1) == 0, 0.5, (ones * (r * (1 - self.ratios[1:-1]))).sum(axis=1))

    def probabilities(self, asked: Asked, answers: list[tuple[int, bytes, bytes, bytes]], total: np.ndarray, lower: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(count, probability) of each token's n-gram; total: its context's count, lower: the lower order's probability."""
        code = np.concatenate([_numbers(a[1], e - b) for a, (_, b, e) in zip(answers, asked.buckets, strict=True)])
        count = code >> 1
        ones = np.concatenate([np.frombuffer(a[2], dtype=np.int32) for a in answers]).reshape(-1, DISCOUNTED)
        low = np.concatenate([np.frombuffer(a[3], dtype=np.float64) for a in answers])
        totals, split = total[asked.token], asked.split
        # The contexts whose sums came are those that are not split, seen in training and followed by an unseen n-gram.
        told = (np.add.reduceat((count == 0).astype(np.int32), asked.runs) > 0) & (totals[asked.runs] > 0) & ~split[asked.runs]
        of_run = np.repeat(np.cumsum(told) - 1, _lengths(asked.runs, len(count)))
        bare = (code & 1).astype(bool)
        left, rest = np.zeros(len(count)), np.ones(len(count))
        back = (count == 0) & (totals > 0)
        near = np.flatnonzero(back & ~split)
        left[near], rest[near] = self.left(ones)[of_run[near]], 1 - low[of_run[near]]
        if (far := np.flatnonzero(split & (totals > 0))).size:
            at = np.searchsorted(self.split, asked.context[far] & SHORT)
            left[far], rest[far] = self.left(self.ones)[at], 1 - self.low[at]
            bare[far] = (self.ones[at] == 0).all(axis=1)
        totals = totals + 0.5 * bare
        with np.errstate(divide="ignore", invalid="ignore"):
            own = count * self.ratios[np.minimum(count, DISCOUNTED + 1)] / totals
            weight = np.where(back, left / totals / np.maximum(rest, 1e-12), 1.0)
        return count[asked.of], np.where(count[asked.of] > 0, own[asked.of], weight[asked.of] * lower)


class Scorer:
    """A block's tokens, taken through the levels that are known."""

    def __init__(self, levels: list[Level], n_buckets: int, row: dict, answers):
        self.levels, self.n_buckets = levels, n_buckets
        self.tokens = t = Tokens(row["sizes"], row["payload"], row["held_out"])
        self.lower = np.ones(len(t.word))
        self.gram = self.counts = self.ends = None
        by_level = {}
        for k, *rest in answers:
            by_level.setdefault(k, []).append(rest)
        for k, level in enumerate(levels):
            asked, total = self.ask(k)
            if k:
                self.lower = self.lower.astype(np.float32).astype(np.float64)
            count, self.lower = level.probabilities(asked, sorted(by_level.get(k, [])), total, self.lower)
            self.gram = t.grams(self.gram)[0]
            if k == 0:
                self.words = count
                ends = count[t.word == END]
                self.ends = int(ends[0]) if len(ends) else 0
            self.counts = count

    def ask(self, k: int) -> tuple[Asked, np.ndarray]:
        """What the block asks for at level k (0: words), and the counts of the tokens' contexts."""
        t = self.tokens
        gram, context = t.grams(self.gram)
        if k == 0:
            total = np.full(len(gram), self.levels[0].tokens if self.levels else 0, dtype=np.int64)
            parts = np.full(len(gram), max(self.n_buckets, 2), dtype=U)
        else:
            total = t.before(self.counts, self.ends)
            parts = U(1) + total.astype(U) // U(max(SPLIT, math.ceil(self.levels[0].tokens / MOST_SPLIT)))
        return Asked(gram, context, parts, self.n_buckets), total

    def questions(self, block: int, passes: int, turn: int):
        k = len(self.levels)
        asked, _ = self.ask(k)
        times = np.bincount(asked.of, weights=self.tokens.train, minlength=len(asked.token)).astype(np.int64)
        return _question_rows(block, asked, times, self.lower[asked.token].astype(np.float32) if k else None, passes, turn)


def _ask(levels: list[Level], n_buckets: int, passes: int, turn: int):
    """Questions of the level after those that are known."""

    def run(blocks, answers):
        row, s = _scorer(levels, n_buckets, blocks, answers)
        return s.questions(row["block"], passes, turn)

    return run


def _ask_words(n_buckets: int, passes: int, turn: int):
    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                yield from Scorer([], n_buckets, row, ()).questions(row["block"], passes, turn).to_batches()

    return run


def _scorer(levels: list[Level], n_buckets: int, blocks, answers) -> tuple[dict, Scorer]:
    row = blocks.to_pylist()[0]
    return row, Scorer(levels, n_buckets, row, zip(*(answers.column(k).to_pylist() for k in ("level", "bucket", "counts", "ones", "low")), strict=True))


def _scores(levels: list[Level], n_buckets: int):
    def run(blocks, answers):
        import pyarrow as pa

        row, s = _scorer(levels, n_buckets, blocks, answers)
        t, n = s.tokens, levels[0].tokens
        base = np.log10((s.words + 1) / (n + levels[0].distinct + 1))
        score = np.log10(np.maximum(s.lower, 1e-300))
        long = lambda x: pa.array(np.asarray(x).astype(np.int64))
        return pa.table(
            [pa.array(row["ids"], pa.int64()), pa.array(row["held_out"], pa.bool_()), long(t.sizes), long(t.per_document(s.words > 0)), long(np.full(len(t.sizes), n)), pa.array(t.per_document(base)), pa.array(t.per_document(score))],
            names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"],
        )

    return run


def katz_scores(docs: DataFrame, order: int = 2) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score and score of every row of docs.

    order: the most words of an n-gram. Learns from the rows whose crc32(doc_id as text) modulo 7 is not 2. Null texts
    are empty and have the end token only; a null doc_id counts as an empty text there and is learned from. Repeated rows
    count and score each. Without training rows every word is unseen, with the probability 1. Other columns are ignored;
    an empty table gives no rows.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "katz")
    doc_id = F.col("doc_id").cast("long")
    held = F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 7 == 2
    docs = docs.select(doc_id.alias("doc_id"), text_or_empty(F.col("text").cast("string")).alias("text"), held.alias("held_out"))
    blocks = scratch.stage(docs.mapInArrow(freeing(_blocks), "block long, ids array<long>, held_out array<boolean>, sizes array<long>, payload binary"), "blocks")
    n_buckets = max(1, blocks.count())
    levels: list[Level] = []
    answers: DataFrame | None = None

    def with_answers(run, schema: str) -> DataFrame:
        return blocks.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(run, schema)

    for k in range(order):
        passes, parts = PASSES[min(k, len(PASSES) - 1)], []
        for turn in range(passes):
            asked = with_answers(freeing_groups(_ask(list(levels), n_buckets, passes, turn)), QUESTIONS) if k else blocks.mapInArrow(freeing(_ask_words(n_buckets, passes, turn)), QUESTIONS)
            parts.append(scratch.stage(asked.groupBy("bucket").applyInArrow(freeing_group(_answer), ANSWERS), f"level{k}_{turn}"))
        told = reduce(DataFrame.unionByName, parts)
        levels.append(_level(told))
        told = told.where("block IS NOT NULL").drop("sums").withColumn("level", F.lit(k))
        answers = told if answers is None else answers.unionByName(told)
    return with_answers(freeing_groups(_scores(levels, n_buckets)), "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def _level(told: DataFrame) -> Level:
    """What all buckets of a level have found together."""
    sums = told.where("sums IS NOT NULL").agg(*(F.sum(F.element_at("sums", k + 1)) for k in range(DISCOUNTED + 3))).first()
    tokens, distinct, *few = (x or 0 for x in sums)
    names = [f"n{r}" for r in range(1, DISCOUNTED + 1)]
    parts = told.where("block IS NULL AND sums IS NULL").select("counts", "ones", "low").mapInArrow(_parts, "context long, " + ", ".join(f"{n} long" for n in names) + ", low double")
    split = parts.groupBy("context").agg(*(F.sum(n).alias(n) for n in names), F.sum("low").alias("low")).toArrow()
    own = split.column("context").to_numpy().view(U)
    order = np.argsort(own)
    ones = np.stack([split.column(n).to_numpy() for n in names], axis=1)
    return Level(tokens, distinct, np.array([*discounts([0, *few]), 1.0]), own[order], ones[order], split.column("low").to_numpy()[order])


def brute_force(rows: list[tuple[int, str | None]], order: int = 2) -> dict[int, tuple]:
    """For tests: the same with dictionaries, from the definitions."""
    import zlib
    from collections import Counter

    lower = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
    docs = {d: [None, *(w.decode() for w in (t or "").translate(lower).encode().split()), "\n"] for d, t in rows}
    held = {d: zlib.crc32(str(d).encode()) % 7 == 2 for d in docs}
    after = lambda ws, i, n: tuple(ws[max(0, i - n) : i])
    follow, ratio = [], []
    for n in range(order):
        counts = Counter((after(ws, i, n), ws[i]) for d, ws in docs.items() if not held[d] for i in range(1, len(ws)))
        of = Counter(counts.values())
        ratio.append([*discounts([of[r] for r in range(DISCOUNTED + 2)]), 1.0])
        by: dict = {}
        for (context, w), c in counts.items():
            by.setdefault(context, {})[w] = c
        follow.append(by)
    known: dict = {}

    def p(n: int, context: tuple, w) -> float:
        """The probability of w after a context of n words at most."""
        if n < 0:
            return 1.0
        if (n, context, w) in known:
            return known[n, context, w]
        shorter = context[1:] if len(context) == n else context
        own = follow[n].get(context, {})
        if not own:
            out = p(n - 1, shorter, w)
        else:
            mass = {x: c * ratio[n][min(c, DISCOUNTED + 1)] for x, c in own.items()}
            bare = min(own.values()) > DISCOUNTED
            total = sum(own.values()) + 0.5 * bare
            if w in own:
                out = mass[w] / total
            else:
                rest = 1 - sum(p(n - 1, shorter, x) for x in own) if n else 1.0
                out = (total - sum(mass.values())) / total / rest * p(n - 1, shorter, w)
        known[n, context, w] = float(np.float32(out)) if n < order - 1 else out
        return known[n, context, w]

    v, n_tokens = len(follow[0].get((), {})), sum(follow[0].get((), {}).values())
    out = {}
    for d, ws in docs.items():
        c = [follow[0].get((), {}).get(w, 0) for w in ws[1:]]
        base = sum(math.log10((x + 1) / (n_tokens + v + 1)) for x in c)
        score = sum(math.log10(p(order - 1, after(ws, i, order - 1), ws[i])) for i in range(1, len(ws)))
        out[d] = (held[d], len(ws) - 1, sum(x > 0 for x in c), n_tokens, base, score)
    return out

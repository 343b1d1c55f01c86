"""Token counts by source, language and tokenizer version as delta-maintained rollups.

A batch of changes (inserts, deletes, revisions) becomes signed sums by key, which are written under the batch's name;
the totals are the sums of all committed batches. A batch is committed by its success marker, which Spark writes last,
and a committed batch is never written again, so repeated and interrupted commits count once.
"""

from __future__ import annotations

import base64
import os
from functools import lru_cache

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import text_chunks, words

KEYS = ["source", "lang", "tokenizer"]
MEASURES = ["docs", "tokens", "chars"]
SCHEMA = "source string, lang string, tokenizer string, docs long, tokens long, chars long"

#: Where the public vocabulary is on every machine, by default; a parameter of byte_pair_counts.
RANKS = "/opt/tokenizers/byte_bpe_50k.tiktoken"

# Fixed value: how this public tokenizer splits a text into pieces.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


@lru_cache(maxsize=4)
def _encoding(ranks: str):
    import tiktoken

    if not os.path.exists(ranks):
        raise FileNotFoundError(f"no vocabulary at {ranks}; every executor needs it there, or at the path given as ranks")
    with open(ranks, "rb") as f:
        table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("ranks", pat_str=PATTERN, mergeable_ranks=table, special_tokens={})


def byte_pair_counts(docs: DataFrame, ranks: str = RANKS, version: str = "byte-bpe-50k/1") -> DataFrame:
    """source, lang, tokenizer, docs (1), tokens, chars of each row of docs; null texts are empty."""

    def run(batches):
        import pyarrow as pa

        encode = _encoding(ranks).encode_ordinary
        for batch in text_chunks(batches):
            texts = batch.column("text").to_pylist()
            # Very long texts are encoded in pieces that end before a space, where no piece of the pattern goes on.
            n = [sum(len(encode(p)) for p in _pieces(t or "")) for t in texts]
            yield pa.RecordBatch.from_arrays([batch.column("source"), batch.column("lang"), pa.array(n, pa.int64()), pa.array([len(t or "") for t in texts], pa.int64())], names=["source", "lang", "tokens", "chars"])

    rows = docs.select(F.col("source").cast("string").alias("source"), F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text")).mapInArrow(run, "source string, lang string, tokens long, chars long")
    return rows.select("source", "lang", F.lit(version).alias("tokenizer"), F.lit(1).cast("long").alias("docs"), "tokens", "chars")


def _pieces(text: str, most: int = 50_000):
    begin = 0
    while len(text) - begin > most:
        end = begin + most
        while end < len(text) and not (text[end] == " " and text[end - 1].isalpha()):
            end += 1
        yield text[begin:end]
        begin = end
    yield text[begin:]


def word_counts(docs: DataFrame, version: str = "words/1") -> DataFrame:
    """As byte_pair_counts, for words between white space."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return docs.select(F.col("source").cast("string").alias("source"), F.col("lang").cast("string").alias("lang"), F.lit(version).alias("tokenizer"), F.lit(1).cast("long").alias("docs"), F.size(words(text)).cast("long").alias("tokens"), F.length(text).cast("long").alias("chars"))


def inserted(counts: DataFrame) -> DataFrame:
    return counts.select(*KEYS, *MEASURES)


def deleted(counts: DataFrame) -> DataFrame:
    return counts.select(*KEYS, *((-F.col(m)).alias(m) for m in MEASURES))


def revised(old: DataFrame, new: DataFrame) -> DataFrame:
    """Documents counted anew: what they counted for goes, what they count for comes."""
    return deleted(old).unionByName(inserted(new))


class Rollup:
    """Totals in a folder that all executors share, with one writer at a time. A batch's name decides whether it is new.

    A compaction lists what it stands for in a table of its own, which holds once the compacted batch is complete: from
    then on the listed batches are committed but no longer summed, whether or not their folders are removed already.
    """

    def __init__(self, spark: SparkSession, folder: str):
        self.spark, self.folder = spark, folder.rstrip("/")

    def _path(self, kind: str, name: str):
        path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{kind}={name}")
        return path, path.getFileSystem(self.spark._jsc.hadoopConfiguration())

    def _complete(self, kind: str, name: str) -> bool:
        path, fs = self._path(kind, name)
        return fs.exists(self.spark._jvm.org.apache.hadoop.fs.Path(path, "_SUCCESS"))

    def _names(self, kind: str) -> list[str]:
        path, fs = self._path(kind, "x")
        top = path.getParent()
        names = [s.getPath().getName() for s in fs.listStatus(top)] if fs.exists(top) else []
        return sorted(n[len(kind) + 1 :] for n in names if n.startswith(f"{kind}="))

    def _drop(self, kind: str, name: str) -> None:
        path, fs = self._path(kind, name)
        fs.delete(path, True)

    def _covered(self) -> set[str]:
        """Names of batches that a complete compaction stands for."""
        paths = [f"{self.folder}/covers={n}" for n in self._names("covers") if self._complete("covers", n) and self._complete("batch", n)]
        return {r["name"] for r in self.spark.read.schema("name string").parquet(*paths).collect()} if paths else set()

    def committed(self, batch: str) -> bool:
        return self._complete("batch", batch) or batch in self._covered()

    def commit(self, batch: str, changes: DataFrame) -> bool:
        """Add signed rows of KEYS and MEASURES under a batch's name; False if it is committed already.

        What an interrupted commit left is overwritten. Sums are partial before the shuffle, so a hot source costs a
        row for each task. Null sources, languages and measures: null is a key of its own, a null measure counts 0.
        """
        if self.committed(batch):
            return False
        sums = changes.groupBy(*KEYS).agg(*(F.coalesce(F.sum(m), F.lit(0)).cast("long").alias(m) for m in MEASURES))
        sums.write.mode("overwrite").parquet(f"{self.folder}/batch={batch}")
        return True

    def batches(self) -> list[str]:
        """The committed batches that totals are the sums of."""
        covered = self._covered()
        return [n for n in self._names("batch") if n not in covered and self._complete("batch", n)]

    def totals(self) -> DataFrame:
        """KEYS and MEASURES over all committed batches; keys whose measures are all zero are absent."""
        paths = [f"{self.folder}/batch={b}" for b in self.batches()]
        rows = self.spark.read.schema(SCHEMA).parquet(*paths) if paths else self.spark.createDataFrame([], SCHEMA)
        out = rows.groupBy(*KEYS).agg(*(F.sum(m).alias(m) for m in MEASURES))
        return out.where(" OR ".join(f"{m} <> 0" for m in MEASURES))

    def compact(self, batch: str) -> bool:
        """Write the totals as one batch of a new name and remove those it stands for; False if there is nothing to do.

        Their names stay committed, so a replay counts nothing. An interrupted compaction leaves the totals as they are.
        """
        old = self.batches()
        if len(old) < 2 or self.committed(batch):
            return False
        covered = self._covered() | set(old)
        self._drop("batch", batch)
        self.spark.createDataFrame([(n,) for n in sorted(covered)], "name string").coalesce(1).write.mode("overwrite").parquet(f"{self.folder}/covers={batch}")
        self.totals().coalesce(1).write.mode("overwrite").parquet(f"{self.folder}/batch={batch}")
        for name in covered:
            self._drop("batch", name)
            self._drop("covers", name)
        return True

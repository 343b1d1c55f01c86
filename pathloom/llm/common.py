"""Pieces that the corpus operators share: word splitting, let-bindings, and tables staged in the shared folder."""

from __future__ import annotations

import uuid
from collections.abc import Iterable
from contextlib import contextmanager, nullcontext

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.staging import file_system, shared_folder

#: Separators between words: space, tab, line feed, vertical tab, form feed, carriage return.
SPACES = " \t\n\x0b\x0c\r"
SPACES_RE = "[\\x20\\x09-\\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_or_empty(col: Column | str = "text") -> Column:
    return F.coalesce(F.col(col) if isinstance(col, str) else col, F.lit(""))


def words(text: Column) -> Column:
    """Array of the words of a non-null text."""
    return F.filter(F.split(text, SPACES_RE), lambda w: w != F.lit(""))


def ascii_lower(text: Column) -> Column:
    return F.translate(text, UPPER, LOWER)


def let(value: Column, body) -> Column:
    """body(value) with value computed once a row: Catalyst would otherwise inline it into every lambda call."""
    return F.element_at(F.transform(F.array(value), body), 1)


def fresh(taken: Iterable[str], *names: str) -> list[str]:
    """The names, each with underscores until it is not taken."""
    taken, out = {t.lower() for t in taken}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def collect_garbage(spark: SparkSession) -> None:
    """Let the context cleaner remove shuffle files of plans that nothing refers to any more."""
    import gc

    gc.collect()
    spark.sparkContext._jvm.System.gc()


#: A runtime setting of Spark: shuffle files of a command's plan go as soon as the command has ended.
FREE_SHUFFLES = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


#: A runtime setting of Spark: bytes of rows in a batch for Python, at most but for one row. Unlimited where it is not set.
BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch"


@contextmanager
def setting(spark: SparkSession, key: str, value: str):
    """The setting holds in the block; the session's own holds again afterwards."""
    own = spark.conf.get(key, None)
    spark.conf.set(key, value)
    try:
        yield
    finally:
        if own is None:
            spark.conf.unset(key)
        else:
            spark.conf.set(key, own)


def freed_shuffles(spark: SparkSession):
    """Commands in the block free their shuffle files at once.

    Garbage collection alone leaves those of the last plan until the next one has run.
    """
    return setting(spark, FREE_SHUFFLES, "true")


class Scratch:
    """Tables written to the shared folder, which cut lineage and survive the loss of executors."""

    def __init__(self, spark: SparkSession, name: str, batch_bytes: int = 0):
        """batch_bytes: of the batches that Python gets where tables are staged, if not 0; Spark's own bound is in rows only."""
        self.spark, self.root, self.paths = spark, f"{shared_folder(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}", {}
        self.batch_bytes = batch_bytes

    def stage(self, df: DataFrame, name: str) -> DataFrame:
        path = f"{self.root}/{name}"
        with freed_shuffles(self.spark), setting(self.spark, BATCH_BYTES, str(self.batch_bytes)) if self.batch_bytes else nullcontext():
            df.write.mode("overwrite").parquet(path)
        self.paths[name] = path
        schema = df.schema
        del df
        collect_garbage(self.spark)
        return self.spark.read.schema(schema).parquet(path)

    def drop(self, name: str) -> None:
        """Remove a staged table that no later plan reads."""
        if path := self.paths.pop(name, None):
            p, fs = file_system(self.spark, path)
            fs.delete(p, True)


def release_memory() -> None:
    """Give freed memory back to the system: Python workers stay for later tasks and would keep what one has needed."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


def freeing(run):
    """A function of record batches that gives freed memory back when a task is done."""

    def out(batches):
        yield from run(batches)
        release_memory()

    return out


def freeing_group(run):
    """The same for a function of one group's table."""

    def out(table):
        done = run(table)
        release_memory()
        return done

    return out


def freeing_groups(run):
    """The same for a function of two cogrouped tables."""

    def out(left, right):
        done = run(left, right)
        release_memory()
        return done

    return out


def text_chunks(batches, column: str = "text", most: int = 4_000_000):
    """Slices of Arrow batches with at most about `most` bytes of text each (one row at least)."""
    import pyarrow.compute as pc

    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_pylist()
        begin = total = 0
        for i, n in enumerate(sizes):
            if i > begin and total + n > most:
                yield batch.slice(begin, i - begin)
                begin, total = i, 0
            total += n
        yield batch.slice(begin)

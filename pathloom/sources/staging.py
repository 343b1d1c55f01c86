"""Tables staged in the shared folder: they cut lineage in loops and survive the loss of executors."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_own_folder: dict[str, str] = {}


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir where the cluster names it; a temporary folder only for local sessions that name none."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if named:
        return named
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    app = spark.sparkContext.applicationId
    if app not in _own_folder:
        _own_folder[app] = tempfile.mkdtemp(prefix="pathloom-")
    return _own_folder[app]


def file_system(spark: SparkSession, path: str):
    """(path, its file system), as the JVM's objects."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p, p.getFileSystem(spark._jsc.hadoopConfiguration())


#: Tables of at most this many rows, and made from inputs of about this many bytes at most, may be kept on the driver.
KEPT_ROWS, KEPT_BYTES = 100_000, 64_000_000


def estimated_bytes(df: DataFrame) -> int:
    """What the optimizer takes for a plan's output: the bytes of its files, multiplied by joins."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


class Stage:
    """Tables of one computation. What no later plan reads can be dropped, or all but some tables at its end."""

    def __init__(self, spark: SparkSession, name: str = "pass"):
        self.spark, self.root, self.n = spark, f"{shared_folder(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}", 0
        self.paths: dict[int, tuple[DataFrame, str | None, int]] = {}

    def has(self, df: DataFrame) -> bool:
        return id(df) in self.paths

    def put(self, df: DataFrame) -> tuple[DataFrame, int]:
        """The written table and its number of rows (from the footers); what this stage made already stays as it is."""
        if self.has(df):
            return df, self.paths[id(df)][2]
        self.n += 1
        path = f"{self.root}/{self.n}"
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        n = out.count()
        self.paths[id(out)] = out, path, n
        return out, n

    def keep(self, df: DataFrame, small: bool = False) -> tuple[DataFrame, int]:
        """As put(), but of a table that is small (the caller says that its inputs are), the rows themselves, in one job.

        A table that turns out larger than KEPT_ROWS is written all the same.
        """
        if small and not self.has(df):
            rows = df.limit(KEPT_ROWS + 1).toArrow()
            if rows.num_rows <= KEPT_ROWS:
                return self.local(rows, df.schema)
        return self.put(df)

    def local(self, rows, schema) -> tuple[DataFrame, int]:
        """An Arrow table of few rows as a table of this stage."""
        out = self.spark.createDataFrame(rows, schema)
        self.paths[id(out)] = out, None, rows.num_rows
        return out, rows.num_rows

    def drop(self, *tables: DataFrame) -> None:
        """Remove tables of this stage; other tables are left alone."""
        for t in tables:
            kept = self.paths.pop(id(t), None)
            if kept and kept[1]:
                p, fs = file_system(self.spark, kept[1])
                fs.delete(p, True)

    def clear(self, keep: tuple[DataFrame, ...] = ()) -> None:
        """Remove all tables that were put but those to keep."""
        self.drop(*(t for k, (t, *_) in list(self.paths.items()) if k not in set(map(id, keep))))

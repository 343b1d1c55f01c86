"""The corpus pipeline: quality rules, line dedup, near-dedup, decontamination and the training order, over documents."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathloom.llm import curriculum, decontamination, line_dedup, quality_rules, similar
from pathloom.llm.common import Scratch, table


def _quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules or the learned decision list reject go."""
    return quality_rules.quality_rules(docs, table(spark, sf_dir, "labels")).where("kept").select(docs.columns)


def _lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts lose their frequent lines; a document that loses all its text goes. n_chars follows the text."""
    out = line_dedup.deduped(docs).where((F.size("kept") == F.size("lines")) | (F.array_join("kept", "\n") != ""))
    text = F.when(F.size("kept") == F.size("lines"), F.col("d.text")).otherwise(F.array_join("kept", "\n"))
    own = {c: F.col(f"d.`{c}`") for c in docs.columns} | {"text": text}
    if "n_chars" in docs.columns:
        own["n_chars"] = F.when(F.size("kept") == F.size("lines"), F.col("d.n_chars")).otherwise(F.length(text)).cast(docs.schema["n_chars"].dataType)
    return out.select(*(own[c].alias(c) for c in docs.columns))


def _near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays: of those linked by a similarity of 4/5 of their 5-word shingles."""
    return similar.similar_dedup(docs, shingle=5)


def _benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    return decontamination.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def _mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row for each copy to train on, range-sorted by its position."""
    return curriculum.curriculum(docs)


STAGES = [("quality rules", _quality), ("line dedup", _lines), ("near-dedup", _near_copies), ("decontamination", _benchmark), ("mix", _mix)]

#: Learned rules and fingerprints have no SQL form; tests compare with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each stage reads what the one before wrote to the shared folder."""
    scratch = Scratch(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = scratch.stage(docs, f"stage{k}")
            scratch.drop(f"stage{k - 1}")
    return docs

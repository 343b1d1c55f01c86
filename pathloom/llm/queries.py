"""The queries opN_ of this subpackage over whole tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import curriculum, decontamination, katz, line_dedup, pii, quality_rules, simhash, substring_dedup, suffix_dedup, token_counts
from .common import Scratch, table


def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.digest(substring_dedup.substring_dedup(table(spark, sf_dir, "documents")), "kept")


def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = quality_rules.quality_rules(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "labels"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return katz.katz_scores(table(spark, sf_dir, "documents"))


def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = pii.personal_data(table(spark, sf_dir, "documents"))
    return out.withColumn("base_sha256", F.sha2("base", 256)).drop("base")


def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.digest(line_dedup.line_dedup(table(spark, sf_dir, "documents")), "kept")


def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = simhash.simhash_components(table(spark, sf_dir, "documents"))
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def _rolled(spark: SparkSession, sf_dir: str, name: str, counts) -> DataFrame:
    """The totals after a load, its replay, a source's deletion, its return, and a revision of long texts: to the first
    half of their characters, and then of these to the whole again for the texts of even doc_id."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "source", "lang", "text")
    rollup = token_counts.Rollup(spark, Scratch(spark, name).root)
    one = docs.where(F.col("source") == docs.agg(F.min("source")).first()[0])
    long = docs.where(F.length("text") > LONG_TEXT)
    half = lambda d: d.withColumn("text", F.expr("substring(text, 1, CAST(length(text) / 2 AS INT))"))
    even = long.where("doc_id % 2 = 0")
    batches = {
        "load": lambda: token_counts.inserted(counts(docs)), "delete": lambda: token_counts.deleted(counts(one)), "return": lambda: token_counts.inserted(counts(one)),
        "revise": lambda: token_counts.revised(counts(long), counts(half(long))), "restore": lambda: token_counts.revised(counts(half(even)), counts(even)),
    }
    for batch in ("load", "load", "delete", "return", "delete", "revise", "restore", "revise"):
        rollup.commit(batch, batches[batch]())
    rollup.compact("all")
    return rollup.totals()


#: Characters from which on a text's count is revised.
LONG_TEXT = 4000


def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Byte-pair and word counts, each through all kinds of batches."""
    return _rolled(spark, sf_dir, "rollup", token_counts.byte_pair_counts).unionByName(_rolled(spark, sf_dir, "words", token_counts.word_counts))


def rollup_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The word counts of op8 alone, which SQL can give, too."""
    return _rolled(spark, sf_dir, "words", token_counts.word_counts)


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = curriculum.mixed(table(spark, sf_dir, "documents").select("doc_id", "text", "source"))
    taken = (F.col("copies") * F.col("size")).alias("taken")
    return out.select("doc_id", "size", "source_size", "target", taken, F.round("first_position", 6).alias("first_position"), F.round("last_position", 6).alias("last_position"))


def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.digest(suffix_dedup.suffix_dedup(table(spark, sf_dir, "documents")), "kept")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_substring_dedup": op1,
    "op2_quality_rules": op2,
    "op3_decontamination": op3,
    "op4_katz_backoff": op4,
    "op5_personal_data": op5,
    "op6_line_dedup": op6,
    "op7_simhash": op7,
    "op8_token_counts": op8,
    "op9_curriculum_mix": op9,
    "op10_suffix_dedup": op10,
    "pipeline": pipeline,
    "rollup_words": rollup_words,
}

SQL: dict[str, str] = {
    "op1_substring_dedup": substring_dedup.SUBSTRING_SQL,
    "op10_suffix_dedup": suffix_dedup.SUFFIX_SQL,
    "op6_line_dedup": line_dedup.LINE_DEDUP_SQL,
    "op9_curriculum_mix": curriculum.MIX_SQL,
    "rollup_words": f"""
WITH counted AS (SELECT *, len(list_filter(regexp_split_to_array(coalesce(now, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> ''))::BIGINT AS n
  FROM (SELECT source, lang, CASE WHEN length(text) > {LONG_TEXT} AND doc_id % 2 <> 0 THEN substr(text, 1, (length(text) // 2)::BIGINT) ELSE text END AS now FROM documents))
SELECT source, lang, 'words/1' AS tokenizer, count(*) AS docs, sum(n)::BIGINT AS tokens, sum(coalesce(length(now), 0))::BIGINT AS chars FROM counted GROUP BY source, lang""",
}

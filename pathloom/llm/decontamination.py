"""Benchmark decontamination by template canonicalisation.

Numbers, units and names become typed placeholders. Windows of template tokens of the documents meet those of the
benchmark in a hash join; runs of matched windows on one alignment count if the slots fill consistently, i.e. what the
benchmark repeats is repeated alike in the document. Copies with other numbers or names are caught, too. Windows that are mostly
slots, and items shorter than a window, are searched as they are filled.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACES_RE, Scratch, let, text_or_empty

NUMBER, UNIT, NAME = "\ue000", "\ue001", "\ue002"  # private-use characters

# Units that may follow a number.
UNITS = "km|kilometers|kilometres|m|meters|metres|cm|mm|miles|mile|feet|ft|inches|kg|kilograms|g|grams|mg|lb|lbs|pounds|tons|l|liters|litres|ml|hours|hour|h|minutes|minute|min|seconds|second|s|days|day|weeks|months|years|year|percent|dollars|euros|cents|degrees|kw|kwh|mb|gb|tb"

WINDOW, LITERALS, RUN = 8, 4, 5
EXACT = "exact"  # tells codes of fillers from codes of templates

#: Benchmark windows that are broadcast at most; beyond, Spark joins by shuffle.
BROADCAST_WINDOWS = 200_000

#: Slots that ids of matched documents hash to; at most so many are broadcast, whatever the input.
SLOTS = 1 << 20


def plain(text: Column) -> Column:
    """Text without tokens of punctuation alone, so that template and text have the same tokens."""
    return F.regexp_replace(text, r"(?<!\S)[^\p{L}\p{N}\s]+(?!\S)", " ")


def template(text: Column) -> Column:
    t = F.regexp_replace(text, r"(?<![\p{L}\p{N}])[0-9]+(?:[.,:/][0-9]+)*", NUMBER)
    t = F.regexp_replace(t, rf"(?<={NUMBER} ?)(?:{UNITS})(?![\p{{L}}\p{{N}}])", UNIT)
    t = F.regexp_replace(t, rf"(?<=[^.!?:\s{NUMBER}] )\p{{Lu}}\p{{L}}*", NAME)
    return F.lower(F.regexp_replace(t, rf"[^\p{{L}}\p{{N}}\s{NUMBER}{UNIT}{NAME}]+", ""))


def tokens(text: Column) -> Column:
    return F.filter(F.split(text, SPACES_RE), lambda w: w != F.lit(""))


def _codes(toks: Column) -> Column:
    """Codes of the windows of an array of tokens, in order; none if it is shorter."""
    hashed = F.transform(toks, lambda w: F.xxhash64(w))
    window = lambda hs: F.transform(F.sequence(F.lit(1), F.size(hs) - WINDOW + 1), lambda i: F.xxhash64(*(F.element_at(hs, (i + k).cast("int")) for k in range(WINDOW))))
    return F.when(F.size(toks) >= WINDOW, let(hashed, window))


def _exact_code(fillers: list[Column]) -> Column:
    return F.xxhash64(F.lit(EXACT), *fillers)


def _exact_codes(raw: Column, widths: list[int]) -> Column:
    """(place, code) of the windows of each width of an array of fillers."""

    def of(width: int) -> Column:
        at = F.when(F.size(raw) >= width, F.sequence(F.lit(0), F.size(raw) - width)).otherwise(F.array().cast("array<int>"))
        return F.transform(at, lambda i: F.struct(i.alias("place"), _exact_code([F.element_at(raw, (i + k + 1).cast("int")) for k in range(width)]).alias("code")))

    return F.concat(*map(of, widths))


def _fillers(text: Column) -> Column:
    """Tokens of a plain text in lower case without punctuation at their ends, one for each token of its template."""
    return tokens(F.lower(F.regexp_replace(text, r"(?<!\S)[^\p{L}\p{N}\s]+|[^\p{L}\p{N}\s]+(?!\S)", "")))


def _is_slot(token: Column) -> Column:
    return token.rlike(f"[{NUMBER}{UNIT}{NAME}]")


def _consistent(windows: str) -> Column:
    """The windows of an alignment without those that hold a filler which the alignment fills in more than one way."""
    pairs = F.array_distinct(F.flatten(F.transform(windows, lambda w: w["pairs"])))
    twice = lambda ofs: F.filter(ofs, lambda x, i: F.array_position(ofs, x) != i + 1)
    clashing = let(F.transform(pairs, lambda p: p["of"]), twice)
    return let(clashing, lambda bad: F.filter(windows, lambda w: ~F.arrays_overlap(F.transform(w["pairs"], lambda p: p["of"]), bad)))


def benchmark_windows(benchmark: DataFrame) -> DataFrame:
    """item_id, at (place of the window), code, width, exact (by its fillers?), slots (places in the window), filled (the
    item's tokens), n_windows, n_templates (those that are not exact)."""
    text = plain(text_or_empty(F.col("text").cast("string")))
    rows = benchmark.where("item_id IS NOT NULL").select("item_id", tokens(template(text)).alias("t"), _fillers(text).alias("raw")).where(F.size("t") > 0)
    codes = F.when(F.size("t") >= WINDOW, _codes(F.col("t"))).otherwise(F.array(F.lit(0).cast("long")))
    rows = rows.select("item_id", "t", "raw", F.posexplode(codes).alias("at", "code"))
    rows = rows.select("item_id", "at", "code", F.slice("raw", F.col("at") + 1, WINDOW).alias("filled"), F.transform(F.slice("t", F.col("at") + 1, WINDOW), _is_slot).alias("slots"))
    rows = rows.withColumn("width", F.size("filled")).withColumn("exact", (F.size("filled") < WINDOW) | (F.size(F.filter("slots", lambda s: ~s)) < LITERALS))
    code = F.col("code")
    for width in range(1, WINDOW + 1):
        code = F.when(F.col("exact") & (F.col("width") == width), _exact_code([F.get("filled", F.lit(k)) for k in range(width)])).otherwise(code)
    rows = rows.withColumn("code", code)
    sizes = rows.groupBy("item_id").agg(F.count("*").alias("n_windows"), F.sum((~F.col("exact")).cast("long")).alias("n_templates"))
    return rows.join(sizes, "item_id")


def contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, item_id, n_matched (the item's windows found), n_windows, for each document that holds a benchmark item.

    An item is held if RUN of its windows (all, if it has fewer), that is 12 tokens in a row, match. A window does not count
    where it holds a filler that its alignment fills in more than one way. Rows without doc_id or item_id, null and empty
    texts match nothing; repeated rows give one row. Other columns are ignored.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "decontamination")
    own = scratch.stage(benchmark_windows(benchmark).dropDuplicates(["item_id", "at", "code"]), "benchmark")
    docs = docs.where("doc_id IS NOT NULL").select("doc_id", plain(text_or_empty(F.col("text").cast("string"))).alias("text"))
    few = own.limit(BROADCAST_WINDOWS + 1).count() <= BROADCAST_WINDOWS
    wanted = own.select("code").distinct()
    widths = [r["width"] for r in own.where("exact").select("width").distinct().collect()]
    found = docs.select("doc_id", tokens(template(F.col("text"))).alias("t")).select("doc_id", F.posexplode(_codes(F.col("t"))).alias("place", "code"))
    if widths:
        filled = docs.select("doc_id", _fillers(F.col("text")).alias("raw"))
        found = found.unionByName(filled.select("doc_id", F.inline(_exact_codes(F.col("raw"), sorted(widths)))))
    hits = found.join(F.broadcast(wanted) if few else wanted, "code").groupBy("doc_id").agg(F.collect_set(F.struct("place", "code")).alias("hits"))
    hits = scratch.stage(hits, "hits")
    # Only matched documents are read for their tokens; each window goes on with its own eight.
    # Texts whose ids hash to no matched slot stay out of the join's shuffle.
    slot = F.pmod(F.xxhash64("doc_id"), F.lit(SLOTS)).cast("int").alias("slot")
    near = docs.select("*", slot).join(F.broadcast(hits.select(slot).distinct()), "slot", "left_semi").drop("slot")
    raw = near.join(hits, "doc_id").select("doc_id", _fillers(F.col("text")).alias("raw"), "hits").dropDuplicates(["doc_id"])
    piece = lambda h: F.struct(h["place"].alias("place"), h["code"].alias("code"), F.slice(F.col("raw"), h["place"] + 1, F.lit(WINDOW)).alias("words"))
    pieces = raw.select("doc_id", F.explode(F.transform("hits", piece)).alias("h")).select("doc_id", "h.*")
    matched = pieces.join(F.broadcast(own) if few else own, "code")
    pairs = F.zip_with(F.zip_with("filled", "slots", lambda f, s: F.when(s, f)), F.slice("words", F.lit(1), F.col("width")), lambda f, w: F.when(f.isNotNull(), F.struct(f.alias("of"), w.alias("by"))))
    matched = matched.select("doc_id", "item_id", "n_windows", "n_templates", "at", "exact", (F.col("place") - F.col("at")).alias("shift"), F.filter(pairs, lambda p: p.isNotNull()).alias("pairs"))
    sizes = [F.first(n).alias(n) for n in ("n_windows", "n_templates")]
    aligned = matched.groupBy("doc_id", "item_id", "shift").agg(*sizes, F.collect_set(F.struct("at", "exact", "pairs")).alias("windows"))
    held = aligned.select("doc_id", "item_id", "n_windows", "n_templates", F.transform(_consistent("windows"), lambda w: F.struct(w["at"].alias("at"), w["exact"].alias("exact"))).alias("ats"))
    held = held.groupBy("doc_id", "item_id").agg(*sizes, F.array_distinct(F.flatten(F.collect_list("ats"))).alias("ats"))
    held = held.withColumn("n_matched", F.size("ats").cast("long")).withColumn("n_alike", F.size(F.filter("ats", lambda w: ~w["exact"])))
    by_template = (F.col("n_templates") > 0) & (F.col("n_alike") >= F.least(F.lit(RUN), F.col("n_templates")))
    return held.where((F.col("n_matched") >= F.least(F.lit(RUN), F.col("n_windows"))) | by_template).select("doc_id", "item_id", "n_matched", "n_windows")


def decontaminate(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of docs that hold no benchmark item, unchanged, whatever their columns; rows without doc_id stay."""
    hit = contaminated(docs, benchmark).select("doc_id").distinct()
    return docs.alias("d").join(hit.alias("h"), F.col("d.doc_id") == F.col("h.doc_id"), "left_anti")

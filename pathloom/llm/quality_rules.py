"""Quality rules: a decision list learned by sequential covering from labelled statistics, as Spark conditional columns."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import LOWER, SPACES, UPPER, Scratch, fresh, let, text_or_empty, words

SYMBOLS = "#*$%&|<>"

#: Labelled documents that learning reads at most, the first by hash of doc_id.
SAMPLE = 20_000


def _repeat_words(ws: Column) -> Column:
    """Words inside 5-word windows that occur twice or more in the array, the first occurrence included."""

    def gathered(codes: Column) -> Column:
        placed = F.sort_array(F.zip_with(codes, F.sequence(F.lit(0), F.size(codes) - 1), lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        return let(placed, lambda s: let(F.zip_with(F.slice(s, 1, F.size(s) - 1), F.slice(s, 2, F.size(s) - 1), lambda a, b: a["h"] == b["h"]), lambda same: covered(s, same)))

    def covered(s: Column, same: Column) -> Column:
        no = F.array(F.lit(False))
        either = F.zip_with(F.concat(same, no), F.concat(no, same), lambda a, b: a | b)
        at = F.sort_array(F.filter(F.zip_with(s, either, lambda x, e: F.when(e, x["i"])), lambda i: i.isNotNull()))
        return let(at, lambda p: F.aggregate(F.zip_with(p, F.slice(p, 2, F.greatest(F.size(p), F.lit(1))), lambda a, b: F.least(F.lit(5), F.coalesce(b - a, F.lit(5)))), F.lit(0), lambda x, y: x + y))

    codes = F.transform(F.sequence(F.lit(1), F.size(ws) - 4), lambda i: F.xxhash64(*(F.element_at(ws, (i + k).cast("int")) for k in range(5))))
    return F.when(F.size(ws) < 6, F.lit(0)).otherwise(let(codes, lambda c: F.when(F.size(F.array_distinct(c)) == F.size(c), F.lit(0)).otherwise(gathered(c))))


def statistics(docs: DataFrame) -> DataFrame:
    """The columns of docs and n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, and the features f_*."""
    text = text_or_empty(F.col("text").cast("string"))
    count = lambda chars: F.length(text) - F.length(F.translate(text, chars, ""))
    ws, lines, n_lines, upper, lower, marks, digits = own = fresh(docs.columns, "_words", "_lines", "_n_lines", "_upper", "_lower", "_marks", "_digits")
    rows = docs.withColumn(ws, words(text)).withColumn(lines, F.filter(F.split(text, "\n"), lambda x: F.trim(x, F.lit(SPACES)) != ""))
    whole = {
        "n_words": F.size(ws), "word_chars": F.length(F.translate(text, SPACES, "")), "n_symbols": count(SYMBOLS),
        "n_dup_lines": F.size(lines) - F.size(F.array_distinct(lines)), "n_repeat_words": let(F.col(ws), _repeat_words),
    }
    rows = rows.withColumns({k: v.cast("long") for k, v in whole.items()} | {n_lines: F.size(lines), upper: count(UPPER), lower: count(LOWER), marks: count("!?"), digits: count("0123456789")})
    per_word = lambda c: F.col(c) / F.greatest(F.col("n_words"), F.lit(1))
    features = {
        "f_words": F.col("n_words").cast("double"), "f_chars": per_word("word_chars"), "f_symbols": per_word("n_symbols"), "f_repeats": per_word("n_repeat_words"), "f_marks": per_word(marks), "f_digits": per_word(digits),
        "f_dup_lines": F.col("n_dup_lines") / F.greatest(F.col(n_lines), F.lit(1)), "f_upper": F.col(upper) / F.greatest(F.col(upper) + F.col(lower), F.lit(1)),
    }
    return rows.withColumns(features).drop(*own)


FEATURES = ("f_words", "f_chars", "f_symbols", "f_repeats", "f_marks", "f_digits", "f_dup_lines", "f_upper")


@dataclass(frozen=True)
class Condition:
    feature: str
    above: bool
    threshold: float

    def column(self) -> Column:
        return F.col(self.feature) > self.threshold if self.above else F.col(self.feature) <= self.threshold

    def __str__(self) -> str:
        return f"{self.feature} {'>' if self.above else '<='} {self.threshold:.6g}"


@dataclass(frozen=True)
class DecisionList:
    """Rules in order; a document that a rule's conditions all fit is rejected, what no rule fits is kept."""

    rules: tuple[tuple[Condition, ...], ...]

    def kept(self) -> Column:
        verdict = None
        for rule in self.rules:
            fits = rule[0].column()
            for c in rule[1:]:
                fits &= c.column()
            verdict = F.when(fits, False) if verdict is None else verdict.when(fits, False)
        return F.lit(True) if verdict is None else verdict.otherwise(True)

    def __str__(self) -> str:
        return "\n".join(f"reject if {' and '.join(map(str, r))}" for r in self.rules) + "\nkeep"


def _fits(conditions: list[tuple[int, bool, int]]) -> Column:
    out = F.lit(True)
    for f, above, b in conditions:
        bin_ = F.element_at("bins", f + 1)
        out &= bin_ > b if above else bin_ <= b
    return out


def learn(labelled: DataFrame, max_rules: int = 8, max_conditions: int = 3, precision: float = 0.9, least: int = 5) -> DecisionList:
    """A decision list from rows of (bad boolean, held_out boolean, x: the features, bins: x by the cuts, cuts).

    Sequential covering: a rule grows on two thirds of the uncovered rows by the condition of largest information
    gain, is pruned to the prefix of best worth on the other third, and joins the list while its precision there holds.
    Each step is one grouped count of at most features * bins rows. Thresholds end up half-way between the values on
    either side.
    """
    cuts = labelled.first()
    if cuts is None:
        return DecisionList(())
    cuts, rules, covered = cuts["cuts"], [], F.lit(False)
    for _ in range(max_rules):
        rest, grown = labelled.where(~covered), []
        while len(grown) < max_conditions:
            counts = rest.where(~F.col("held_out") & _fits(grown)).select("bad", F.posexplode("bins").alias("f", "b")).groupBy("f", "b").agg(F.sum(F.col("bad").cast("long")).alias("p"), F.sum((~F.col("bad")).cast("long")).alias("n")).collect()
            p0, n0 = (sum(r[k] for r in counts if r["f"] == 0) for k in ("p", "n"))
            if p0 < least or n0 == 0:
                break
            best = (0.0,)
            for f in range(len(cuts)):
                for b in range(len(cuts[f])):
                    below = [sum(r[k] for r in counts if r["f"] == f and r["b"] <= b) for k in ("p", "n")]
                    for above, (p, n) in ((False, below), (True, (p0 - below[0], n0 - below[1]))):
                        if p >= least and (gain := p * (math.log2(p / (p + n)) - math.log2(p0 / (p0 + n0)))) > best[0]:
                            best = (gain, f, above, b)
            if len(best) == 1:
                break
            grown.append(best[1:])
        if not grown:
            break
        sums = [F.sum((F.col("bad") == bad).cast("long") * _fits(grown[: k + 1]).cast("long")) for k in range(len(grown)) for bad in (True, False)]
        held = rest.where("held_out").select(sums).first()
        worth = [((held[2 * k] or 0), (held[2 * k + 1] or 0)) for k in range(len(grown))]
        k = max(range(len(grown)), key=lambda k: (worth[k][0] - worth[k][1]) / (sum(worth[k]) or 1))
        if worth[k][0] < least / 2 or worth[k][0] < precision * sum(worth[k]):
            break
        rule = grown[: k + 1]
        ends = rest.select([e for f, _, b in rule for e in (F.max(F.when(F.element_at("bins", f + 1) <= b, F.col("x")[f])), F.min(F.when(F.element_at("bins", f + 1) > b, F.col("x")[f])))]).first()
        middles = [cuts[f][b] if ends[2 * i] is None or ends[2 * i + 1] is None else (ends[2 * i] + ends[2 * i + 1]) / 2 for i, (f, _, b) in enumerate(rule)]
        rules.append(tuple(Condition(FEATURES[f], above, m) for (f, above, _), m in zip(rule, middles, strict=True)))
        covered |= _fits(rule)
    return DecisionList(tuple(rules))


def base_failed() -> Column:
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


def labelled_statistics(docs: DataFrame, labels: DataFrame, scratch: Scratch, sample: int = SAMPLE, bins: int = 24) -> DataFrame:
    """The bounded sample that learn() reads, staged: at most `sample` labelled documents, the first by hash, but those
    that the base rules reject anyway."""
    order = F.md5(F.col("doc_id").cast("string"))
    chosen = labels.where("doc_id IS NOT NULL AND quality IS NOT NULL").select("doc_id", (F.col("quality") == 0).alias("bad")).dropDuplicates(["doc_id"]).orderBy(order, "doc_id").limit(sample)
    rows = statistics(docs.select("doc_id", "text").join(chosen, "doc_id")).where(~base_failed()).select("doc_id", "bad", F.array(*FEATURES).alias("x"))
    rows = scratch.stage(rows, "labelled").coalesce(1)
    marks = [k / (bins + 1) for k in range(1, bins + 1)]
    cuts = rows.agg(*(F.percentile(F.col("x")[i], F.array(*map(F.lit, marks))).alias(f) for i, f in enumerate(FEATURES))).first()
    cuts = [sorted(set(cuts[f] or ())) for f in FEATURES]
    typed = F.array(*(F.array(*map(F.lit, c)) if c else F.array().cast("array<double>") for c in cuts))
    binned = F.zip_with("x", typed, lambda v, own: F.size(F.filter(own, lambda c: c < v)))
    held = F.conv(F.substring(F.md5(F.concat(F.lit("held"), F.col("doc_id").cast("string"))), 1, 8), 16, 10).cast("long") % 3 == 0
    return scratch.stage(rows.select("bad", "x", held.alias("held_out"), binned.alias("bins"), typed.alias("cuts")), "binned").coalesce(1)


def quality_rules(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """The columns of docs, the statistics, base_failed and kept (false if base_failed, else the decision list's verdict).

    One row for each row of docs. Null and empty texts have no words and fail the base rules. Labels without doc_id or
    quality are left out, of repeated labels one counts; without labels the list is empty and keeps all. Columns of
    docs named like a statistic are replaced.
    """
    scratch = Scratch(docs.sparkSession, "quality")
    rules = learn(labelled_statistics(docs, labels, scratch, sample))
    return statistics(docs).withColumn("base_failed", base_failed()).withColumn("kept", ~F.col("base_failed") & rules.kept())

"""Personal data: exact base patterns, and a semi-Markov conditional random field that adds what they miss.

The field scores whole candidate segments (up to LONGEST tokens, or one token of other text) of the windows around
digits and @ signs. Boundaries and kinds are chosen together by bounded-segment dynamic programming. It is trained
here by gradient ascent on the conditional likelihood (forward-backward over segments), from windows of a bounded
sample of documents whose base spans are the labels, with the spans' formats varied so that other ways of writing are
learned, too.
"""

from __future__ import annotations

import bisect
import math
import random
import re

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_chunks

KINDS = ("email", "ip", "card", "phone")

#: Documents with base spans that training reads at most, the first by hash of doc_id.
SAMPLE = 400
LONGEST = 6
REACH = 3  # tokens of other text around a digit or @ sign

_local = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_domain = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_ip = re.compile(r"(?<![0-9])[0-9]+(?:\.[0-9]+){3}")
_card = re.compile(r"[0-9](?:[ -]?[0-9])+")
_phone = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_token = re.compile(r"[^\s]+")
_trigger = re.compile(r"[0-9@]")
_digits = re.compile(r"[^0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if k % 2 == 0 else (2 * d - 9 if d > 4 else 2 * d)
    return total % 10 == 0


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """(kind, start, end) of the base patterns, by kind, then start."""
    out, last, at = [], 0, text.find("@")
    while at >= 0:
        begin = at
        while begin > last and text[begin - 1] in _local:
            begin -= 1
        if begin < at and (m := _domain.match(text, at + 1)):
            out.append(("email", begin, m.end()))
            last = m.end()
        at = text.find("@", max(at + 1, last))
    if _trigger.search(text):
        out += [("ip", m.start(), m.end()) for m in _ip.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m.group().split("."))]
        out += [("card", m.start(), m.end()) for m in _card.finditer(text) if m.end() - m.start() >= 16 and 16 <= len(d := _digits.sub("", m.group())) <= 19 and luhn(d)]
        out += [("phone", m.start(), m.end()) for m in _phone.finditer(text) if 8 <= len(_digits.sub("", m.group())) <= 15]
    return out


def windows(text: str) -> list[list[tuple[int, int]]]:
    """Tokens (start, end) of the stretches within REACH tokens of one with a digit or @; empty for most texts."""
    if not _trigger.search(text):
        return []
    tokens = [m.span() for m in _token.finditer(text)]
    hot = [i for i, (a, b) in enumerate(tokens) if _trigger.search(text, a, b)]
    out: list[list[tuple[int, int]]] = []
    last = -1
    for i in hot:
        begin, end = max(i - REACH, 0), min(i + REACH + 1, len(tokens))
        if out and begin <= last:
            out[-1] += tokens[last:end]
        else:
            out.append(tokens[begin:end])
        last = max(last, end)
    return out


_edges = "\"'.,;:!?<>[]{}|*&#$%="


def trimmed(text: str, a: int, b: int) -> tuple[int, int]:
    """The span without punctuation at its ends, except a leading + or (."""
    while a < b and text[a] in _edges:
        a += 1
    while b > a and text[b - 1] in _edges:
        b -= 1
    return a, b


def features(text: str, a: int, b: int, n_tokens: int) -> tuple[str, ...]:
    """Whole-segment features of text[a:b]."""
    s = text[a:b]
    digits = _digits.sub("", s)
    letters = sum(c.isalpha() for c in s)
    parts = s.split(".")
    quad = len(parts) == 4 and all(p.isdigit() and len(p) <= 3 for p in parts)
    out = ["bias", f"n{n_tokens}", f"d{min(len(digits), 20)}", f"l{min(letters, 3)}", f"@{s.count('@')}", f".{min(s.count('.'), 4)}"]
    out += [name for name, holds in (
        ("plus", s[:1] == "+"), ("paren", "(" in s and ")" in s), ("dash", "-" in s), ("quad", quad), ("octets", quad and all(int(p) <= 255 for p in parts)),
        ("luhn", 16 <= len(digits) <= 19 and not letters and luhn(digits)), ("grouped", bool(re.fullmatch(r"\(?[0-9]{3}\)?[ .-]+[0-9]{3}[ .-]+[0-9]{4}", s))), ("fours", bool(re.fullmatch(r"[0-9]{4}(?:[ .-][0-9]{4}){3}", s))),
        ("address", bool(re.fullmatch(r"[\w.%+-]+@[\w-]+(?:\.[\w-]+)+", s))), ("spelled", bool(re.fullmatch(r"[\w.%+-]+ ?[(\[]?@[)\]]? ?[\w-]+(?: ?[(\[]?(?:\.|dot)[)\]]? ?[\w-]+)+", s))),
        ("odd", any(not (c.isalnum() or c in "@.+-()_%[] ") for c in s)), ("open", s.count("(") != s.count(")") or s.count("[") != s.count("]")), ("starts", s[:1].isalpha() and len(s.split()[0]) > 1 and not _trigger.search(s.split()[0])), ("ends", bool(s) and not _trigger.search(s.split()[-1]) and "." not in s.split()[-1]),
    ) if holds]
    return tuple(out)


OTHER = "other"
_plain = ("bias",)


_plain_digits = re.compile(r"[0-9 ./_-]+")
_dialled = re.compile(r"[+(]?[0-9(][0-9 ()./-]*[0-9]")
_dots = re.compile(r"\[\.\]|\(\.\)")


def possible(s: str) -> list[str]:
    """The kinds that a segment can be of at all; the field chooses among these and other text."""
    digits, out = _digits.sub("", s), []
    if "@" in s and "." in s[s.index("@") :] or "@" in s and " dot " in s[s.index("@") :]:
        out.append("email")
    parts = _dots.sub(".", s).split(".")
    if len(parts) == 4 and all(p.isascii() and p.isdigit() and int(p) <= 255 for p in parts):
        out.append("ip")
    if 13 <= len(digits) <= 19 and _plain_digits.fullmatch(s) and luhn(digits):
        out.append("card")
    if 7 <= len(digits) <= 15 and _dialled.fullmatch(s):
        out.append("phone")
    return out


def _segments(text: str, tokens: list[tuple[int, int]]):
    """(first token, one past the last, kind, features, span) of all candidate segments."""
    for i in range(len(tokens)):
        own = text[tokens[i][0] : tokens[i][1]]
        yield i, i + 1, OTHER, ("digits" if _trigger.search(own) else "bias",), None
        for j in range(i + 1, min(i + LONGEST, len(tokens)) + 1):
            a, b = trimmed(text, tokens[i][0], tokens[j - 1][1])
            if b - a < 6 or not _trigger.search(text, a, b):
                continue
            if kinds := possible(text[a:b]):
                own = features(text, a, b, j - i)
                for kind in kinds:
                    yield i, j, kind, own, (a, b)


class Field:
    """Weights by (kind, feature)."""

    def __init__(self, weights: dict[tuple[str, str], float] | None = None):
        self.weights = weights or {}

    def score(self, kind: str, own: tuple[str, ...]) -> float:
        w = self.weights
        return sum(w.get((kind, f), 0.0) for f in own)

    def decode(self, text: str, tokens: list[tuple[int, int]]) -> list[tuple[str, int, int]]:
        """The best segmentation's spans (segmental Viterbi)."""
        n = len(tokens)
        best, back = [0.0] + [-math.inf] * n, [None] * (n + 1)
        for i, j, kind, own, span in _segments(text, tokens):  # comes in order of i, so best[i] is final
            if (s := best[i] + self.score(kind, own)) > best[j]:
                best[j], back[j] = s, (i, kind, span)
        out, j = [], n
        while j > 0:
            i, kind, span = back[j]
            if kind != OTHER:
                out.append((kind, *span))
            j = i
        return out[::-1]

    def train(self, examples: list[tuple[str, list[tuple[int, int]], list[tuple[str, int, int]]]], rounds: int = 12, rate: float = 0.3, decay: float = 1e-3) -> Field:
        """Stochastic gradient ascent on the log-likelihood of the labelled segmentations."""
        held = []
        for text, tokens, spans in examples:
            every = list(_segments(text, tokens))
            want = set(spans)
            gold = [k for k, (i, j, kind, _, span) in enumerate(every) if kind != OTHER and (kind, *span) in want]
            taken = {t for k in gold for t in range(every[k][0], every[k][1])}
            if len(taken) != sum(every[k][1] - every[k][0] for k in gold) or len(gold) != len(want):
                continue  # a label that no segmentation has
            gold += [k for k, s in enumerate(every) if s[2] == OTHER and s[0] not in taken]
            held.append((len(tokens), every, gold))
        rng = random.Random(7)
        for turn in range(rounds):
            rng.shuffle(held)
            step = rate / (1 + turn / 4)
            for n, every, gold in held:
                scores = [self.score(kind, own) for _, _, kind, own, _ in every]
                forward, backward = [0.0] + [-math.inf] * n, [-math.inf] * n + [0.0]
                for (i, j, *_), s in zip(every, scores, strict=True):
                    forward[j] = np.logaddexp(forward[j], forward[i] + s)
                for (i, j, *_), s in zip(reversed(every), reversed(scores), strict=True):
                    backward[i] = np.logaddexp(backward[i], backward[j] + s)
                chosen = set(gold)
                for k, ((i, j, kind, own, _), s) in enumerate(zip(every, scores, strict=True)):
                    g = (k in chosen) - math.exp(min(0.0, forward[i] + s + backward[j] - forward[n]))
                    if abs(g) > 1e-4:
                        for f in own:
                            old = self.weights.get((kind, f), 0.0)
                            self.weights[kind, f] = old + step * (g - decay * old)
        return self


def varied(rng: random.Random, text: str, tokens, spans):
    """A labelled window with its spans written another way; other digits stay other text."""
    base = tokens[0][0]
    out, labels, at = "", [], base
    for kind, a, b in sorted(spans, key=lambda s: s[1]):
        s, d = text[a:b], _digits.sub("", text[a:b])
        if kind == "phone" and len(d) >= 10:
            d = d[-10:]
            s = rng.choice([f"({d[:3]}) {d[3:6]}-{d[6:]}", f"{d[:3]}-{d[3:6]}-{d[6:]}", f"{d[:3]}.{d[3:6]}.{d[6:]}", f"{d[:3]} {d[3:6]} {d[6:]}"])
        elif kind == "card" and len(d) == 16:
            s = rng.choice([" ", "-", "."]).join(d[k : k + 4] for k in range(0, 16, 4))
        elif kind == "email":
            s = rng.choice([s.replace("@", " @ "), s.replace("@", " (@) "), s.replace("@", "[@]"), s])
        out += text[at:a]
        labels.append((kind, len(out), len(out) + len(s)))
        out, at = out + s, b
    out += text[at : tokens[-1][1]]
    return out, [m.span() for m in _token.finditer(out)], labels


def negatives(rng: random.Random) -> tuple[str, list[tuple[int, int]], list]:
    """Numbers that are no personal data: dates, versions, amounts, years, hashes."""
    n = lambda k: "".join(rng.choice("0123456789") for _ in range(k))
    s = rng.choice([f"20{n(2)}-{n(2)}-{n(2)}", f"v{n(1)}.{n(1)}.{n(1)}", f"{n(3)},{n(3)}.{n(2)}", f"19{n(2)}", f"{n(5)}", f'"{"".join(rng.choice("0123456789abcdef") for _ in range(40))}"', f"{n(1)}.{n(1)}", f"{n(2)}:{n(2)}:{n(2)}", f"{n(8)}", f"{n(1)}.{n(2)}.{n(4)}", "@", f"@user{n(2)}"])
    text = f"of the {s} and then"
    return text, [m.span() for m in _token.finditer(text)], []


#: Tokens of a window that training reads at most, and windows it reads for each document of the sample, on average.
TRAINED_TOKENS, TRAINED_WINDOWS = 40, 4


def _labelled(batches):
    """The windows of documents that hold base spans: text from their first token to their last, and the spans in it."""
    import pyarrow as pa

    for batch in text_chunks(batches):
        rows = []
        for h, d, text in zip(*(batch.column(c).to_pylist() for c in ("h", "doc_id", "text")), strict=True):
            base = base_spans(text)
            for k, tokens in enumerate(windows(text)):
                begin, end = tokens[0][0], tokens[-1][1]
                spans = [(kind, a - begin, b - begin) for kind, a, b in base if a >= begin and b <= end]
                if spans and len(tokens) <= TRAINED_TOKENS:
                    rows.append((h, d, k, text[begin:end], ",".join(f"{x}:{a}:{b}" for x, a, b in spans)))
        columns = zip(*rows, strict=True) if rows else ((),) * 5
        kinds = (pa.int64(), pa.int64(), pa.int32(), pa.string(), pa.string())
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=["h", "doc_id", "k", "window", "spans"])


def trained(docs: DataFrame, sample: int = SAMPLE) -> Field:
    """A field trained on the labelled windows of at most `sample` documents with base spans, the first by hash of doc_id.

    Of their windows, those of TRAINED_TOKENS tokens at most are read, TRAINED_WINDOWS * sample in all at most, each as it
    is and once more with its spans written another way.
    """
    marked = docs.where("doc_id IS NOT NULL").where(F.col("text").rlike(r"@[A-Za-z0-9-]+\.[A-Za-z0-9]|[0-9]{2}\.[0-9]+\.[0-9]+\.[0-9]|[0-9]{16}|\+[0-9] ?\(?[0-9]{3}"))
    marked = marked.select(F.xxhash64("doc_id").alias("h"), "doc_id")
    # Hashes under a bound that about twice the sample has: else each task would send `sample` ids to the one that sorts.
    share = 2 * sample / max(marked.count(), 1)
    while True:
        under = marked if share >= 1 else marked.where(F.col("h") < -(1 << 63) + int(share * (1 << 64)))
        ids = [r["doc_id"] for r in under.orderBy("h", "doc_id").limit(sample).collect()]
        if len(ids) >= sample or share >= 1:
            break
        share *= 4
    chosen = docs.where(F.col("doc_id").isin(sorted(set(ids)))).select(F.xxhash64("doc_id").alias("h"), "doc_id", F.coalesce("text", F.lit("")).alias("text"))
    rows = chosen.mapInArrow(_labelled, "h long, doc_id long, k int, window string, spans string").orderBy("h", "doc_id", "k", "window").limit(TRAINED_WINDOWS * sample).collect()
    rng, examples = random.Random(11), []
    for r in rows:
        text, tokens = r["window"], [m.span() for m in _token.finditer(r["window"])]
        spans = [(x, int(a), int(b)) for x, a, b in (y.split(":") for y in r["spans"].split(","))]
        examples.append((text, tokens, spans))
        examples.append(varied(rng, text, tokens, spans))
    examples += [negatives(rng) for _ in range(max(40, len(examples) // 6))]
    return Field().train(examples)


def _joined(spans) -> list[tuple[int, int]]:
    """Spans that overlap, of several kinds, as one; sorted."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a < out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def all_spans(field: Field, text: str) -> tuple[list[tuple[str, int, int]], list[tuple[str, int, int]]]:
    """Base spans, and all spans: the base ones and those of the field that overlap none; by kind, then start."""
    base = base_spans(text)
    every, used = list(base), _joined((a, b) for _, a, b in base)
    ends = [y for _, y in used]
    for tokens in windows(text):
        for kind, a, b in field.decode(text, tokens):
            if not any(x < b and a < y for x, y in used[bisect.bisect_left(ends, a + 1) : bisect.bisect_left(used, (b, 0))]):
                every.append((kind, a, b))
    return base, every


def joined(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in sorted(spans, key=lambda s: (KINDS.index(s[0]), s[1], s[2])))


def personal_data(docs: DataFrame, sample: int = SAMPLE, field: Field | None = None) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone (base counts), base, spans (kind:start:end, comma-joined), for every row.

    Null and empty texts have no spans. Repeated rows get equal results. Training reads a bounded sample of documents
    with base spans, scoring every whole text. Other columns are ignored; an empty table gives no rows.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    field = field or trained(docs, sample)
    weights = field.weights

    def run(batches):
        import pyarrow as pa

        own = Field(weights)
        for batch in text_chunks(batches):
            rows = []
            for text in batch.column("text").to_pylist():
                base, every = all_spans(own, text or "")
                rows.append((*(sum(k == kind for k, *_ in base) for kind in KINDS), joined(base), joined(every)))
            *counts, base, every = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(c, pa.int64()) for c in counts), pa.array(base, pa.string()), pa.array(every, pa.string())], names=["doc_id", *(f"n_{k}" for k in KINDS), "base", "spans"])

    return docs.mapInArrow(run, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base string, spans string")

"""Corpus operators against brute-force versions, and their edge cases: nulls, empty and repeated rows, other columns."""

import hashlib
import random
import re
import tracemalloc
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from pathloom.llm import curriculum, decontamination, katz, line_dedup, pii, quality_rules, segments, similar, simhash, substring_dedup, suffix_dedup, token_counts
from pathloom.llm.components import components
from pathloom.llm.common import Scratch

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
EXTRA = SCHEMA + ", kept string, mini long, size long, fp long, block int"


def docs(spark, rows, schema=EXTRA):
    """Rows (doc_id, text), with columns whose names clash with the operators' own."""
    return spark.createDataFrame([(d, t, "en", None if d is None else f"s{d % 3}", len(t or ""), "x", 1, 2, 3, 4)[: len(schema.split(","))] for d, t in rows], schema)


def prose(rng, n):
    return " ".join(rng.choice(["of", "the", "and"]) if rng.random() < 0.3 else "".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 7))) for _ in range(n))


@pytest.fixture(scope="module")
def corpus():
    rng = random.Random(1)
    passage = prose(rng, 120)
    rows = [(k, prose(rng, rng.randint(5, 200))) for k in range(30)]
    rows += [(30 + k, f"{prose(rng, 20)} {passage} {prose(rng, 15)}") for k in range(6)]
    rows += [(40 + k, rows[3][1]) for k in range(4)]
    rows += [(50 + k, " ".join(w if rng.random() > 0.02 else "zz" for w in passage.split() * 2)) for k in range(5)]
    return rows + [(60, None), (61, ""), (62, "a" * 700), (63, "é ü " * 150), (64, "\n \t")]


@pytest.fixture(params=[2000, 1])
def hot(request, monkeypatch):
    monkeypatch.setattr(segments, "HOT", request.param)


def test_substrings(spark, corpus, hot):
    got = substring_dedup.digest(substring_dedup.substring_dedup(docs(spark, [*corpus, (None, corpus[31][1]), corpus[31]])), "kept").collect()
    want = substring_dedup.kept_by_brute_force(corpus)
    for r in got:
        if r["doc_id"] is not None:
            assert (r["n_words"], r["n_removed"], r["kept_sha256"]) == want[r["doc_id"]], r["doc_id"]
        else:
            assert r["n_removed"] == 0
    assert len(got) == len(corpus) + 2


def test_suffixes(spark, corpus, hot):
    got = {r["doc_id"]: tuple(r)[1:] for r in substring_dedup.digest(suffix_dedup.suffix_dedup(docs(spark, corpus)), "kept").collect()}
    assert got == suffix_dedup.kept_by_brute_force(corpus)


def test_suffix_array():
    import numpy as np

    rng = np.random.default_rng(2)
    for n in [*range(30), 400]:
        t = rng.integers(1, 4, n)
        assert suffix_dedup.suffix_array(t, 5).tolist() == sorted(range(n), key=lambda i: t[i:].tolist())


def test_lines(spark):
    line = "The same long footer line"
    rows = [(k, f"own {k} text that is only here {k}\n  {line.upper() if k % 2 else line}\t\nshort") for k in range(4)] + [(9, None), (10, ""), (None, line)]
    got = {r["doc_id"]: (r["n_lines"], r["n_dropped"], r["kept"]) for r in line_dedup.line_dedup(docs(spark, [*rows, rows[0]])).collect()}
    assert got[3] == (3, 0, rows[3][1]) and got[0] == (3, 1, "own 0 text that is only here 0\nshort")
    assert got[9] == (1, 0, "") == got[10] and got[None] == (1, 0, line)


def test_quality(spark):
    rng = random.Random(4)
    rows = [(k, prose(rng, 40) if k % 4 else " ".join(w + "###" for w in prose(rng, 40).split())) for k in range(200)]
    labels = spark.createDataFrame([*((k, int(k % 4 > 0), 0) for k in range(150)), (None, 1, 0), (3, None, 0)], "doc_id long, quality int, toxic int")
    out = {r["doc_id"]: r for r in quality_rules.quality_rules(docs(spark, [*rows, (300, None), (301, "a b c d e f g " * 8)]), labels).collect()}
    assert all(out[k]["kept"] == (k % 4 > 0) for k in range(200))
    assert out[300]["n_words"] == 0 and out[300]["base_failed"] and out[301]["n_repeat_words"] == 56 and not out[301]["kept"]
    none = quality_rules.quality_rules(docs(spark, rows[:8]), labels.limit(0))
    assert none.where("kept").count() == 8 and none.columns[:5] == ["doc_id", "text", "lang", "source", "n_chars"]


def test_base_statistics_by_brute_force(spark):
    rng = random.Random(9)
    texts = [*spark_texts(), None, "", " ", "a", "\n\n", "x y z w v x y z w v", "a b c d e f " * 5]
    texts += ["".join(rng.choice(["a", "b", "c", " ", " ", "\n", "\t", "#", "|", "é", "\x0b", "\x1c"]) for _ in range(rng.randint(0, 80))) for _ in range(300)]
    out = {r["doc_id"]: r for r in quality_rules.statistics(docs(spark, list(enumerate(texts)))).withColumn("failed", quality_rules.base_failed()).collect()}
    for k, text in enumerate(texts):
        ws = re.findall("[^\\x20\\x09-\\x0D]+", text or "")
        lines = [x for x in (text or "").split("\n") if re.search("[^\\x20\\x09-\\x0D]", x)]
        five = [tuple(ws[i : i + 5]) for i in range(len(ws) - 4)]
        repeated = {i + j for i, w in enumerate(five) if five.count(w) > 1 for j in range(5)} if len(five) < 500 else None
        if repeated is None:
            counts = {}
            for w in five:
                counts[w] = counts.get(w, 0) + 1
            repeated = {i + j for i, w in enumerate(five) if counts[w] > 1 for j in range(5)}
        want = (len(ws), sum(map(len, ws)), sum(c in "#*$%&|<>" for c in text or ""), len(lines) - len(set(lines)), len(repeated))
        r = out[k]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == want, text
        assert r["failed"] == (want[0] < 10 or 100 * want[4] > 20 * want[0])


def test_columns_with_clashing_names(spark):
    """Names that operators use inside are a caller's columns here: they stay as they are."""
    own = ["_s", "_st", "_s1", "_size", "_order", "_w", "_words", "_lines", "_upper", "_lower", "_hit", "_kept", "_doc", "_gone", "gone", "h", "d", "k", "lines", "h1", "code", "sid", "slot", "source_"]
    line = "The same long footer line"
    rows = [(k, f"own text {k} a b c d e f g h i\n{line}") for k in range(5)]
    table = docs(spark, rows, SCHEMA).withColumns({c: F.lit(f"own {c}") for c in own})
    labels = spark.createDataFrame([(0, 1, 0)], "doc_id long, quality int, toxic int")
    bench = spark.createDataFrame([(0, "nothing of this item is in any of the texts of the table at all")], "item_id long, text string")
    import corpus_pipeline

    outs = [curriculum.mixed(table), curriculum.curriculum(table), decontamination.decontaminate(table, bench), similar.similar_dedup(table), quality_rules.quality_rules(table, labels), corpus_pipeline._lines(spark, table, "")]
    for out in outs:
        got = out.collect()
        assert got and all(r[c] == f"own {c}" for r in got for c in own)
    assert all(op(table).count() == 5 for op in (line_dedup.line_dedup, substring_dedup.substring_dedup, suffix_dedup.suffix_dedup, katz.katz_scores, simhash.simhash_components))


def test_lines_of_one_id_with_several_texts(spark):
    line = "The same long footer line"
    rows = [(1, f"{line}\na"), (1, f"b\n{line}"), (2, line), (3, f"c\n{line}\n{line}"), (3, None)]
    got = sorted((r["doc_id"], r["n_lines"], r["n_dropped"], r["kept"]) for r in line_dedup.line_dedup(docs(spark, rows)).collect())
    assert got == [(1, 2, 1, "a"), (1, 2, 1, "b"), (2, 1, 1, ""), (3, 1, 0, ""), (3, 3, 0, f"c\n{line}\n{line}")]


def test_rolled_up_tables(spark):
    """The query's totals, counted anew from what its batches leave."""
    import pyarrow.parquet as pq
    from collections import Counter

    from pathloom.llm import queries

    encoding = token_counts._encoding(token_counts.RANKS)
    want = Counter()
    for r in pq.read_table("/root/testdata/sf0.001/documents.parquet").to_pylist():
        text = r["text"] or ""
        now = text[: len(text) // 2] if len(text) > queries.LONG_TEXT and r["doc_id"] % 2 else text
        for version, n in (("byte-bpe-50k/1", len(encoding.encode_ordinary(now))), ("words/1", len(re.findall("[^\\x20\\x09-\\x0D]+", now)))):
            for measure, x in (("docs", 1), ("tokens", n), ("chars", len(now))):
                want[r["source"], r["lang"], version, measure] += x
    got = {(r["source"], r["lang"], r["tokenizer"], m): r[m] for r in queries.op8(spark, "/root/testdata/sf0.001").collect() for m in token_counts.MEASURES}
    assert {k: v for k, v in got.items() if v} == {k: v for k, v in want.items() if v}


def test_templates(spark):
    item = "A train with 12 wagons leaves Boston at noon and each of the 12 wagons holds 40 quiet people who read"
    other = "A train with 17 wagons leaves Denver at noon and each of the 17 wagons holds 55 quiet people who read"
    clash = "A train with 17 wagons leaves Denver at noon and each of the 99 wagons holds 12 quiet people who read"
    rows = [(1, f"x y z. {item} . more"), (2, f"then {other}, so"), (3, "nothing of this is in the list at all, not even a bit of it"), (4, None), (None, item), (5, clash)]
    bench = spark.createDataFrame([(0, item), (1, None), (None, item), (2, "too short")], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in decontamination.contaminated(docs(spark, [*rows, rows[0]]), bench).collect()}
    assert {(1, 0), (2, 0)} <= got and not {d for d, _ in got} & {3, 4, None}
    left = decontamination.decontaminate(docs(spark, rows), bench)
    assert {r["doc_id"] for r in left.collect()} == {3, 4, 5, None} - {d for d, _ in got} and left.columns == docs(spark, rows).columns
    assert decontamination.contaminated(docs(spark, rows), bench.limit(0)).count() == 0


def test_clashing_slots(spark):
    item = "A train with 12 wagons leaves Boston at noon and each of the 12 wagons holds 40 quiet people who read"
    alike = "A train with 17, wagons leaves DENVER at noon and each of the 17 wagons holds 12 quiet people who read"
    clash = "A train with 17 wagons leaves Denver at noon and each of the 99 wagons holds 12 quiet people who read"
    bench = spark.createDataFrame([(0, item)], "item_id long, text string")
    got = decontamination.contaminated(docs(spark, [(1, alike), (2, clash), (3, item)]), bench)
    assert sorted(r["doc_id"] for r in got.collect()) == [1, 3]
    assert [r["doc_id"] for r in decontamination.decontaminate(docs(spark, [(2, clash)]), bench).collect()] == [2]


def test_items_of_slots(spark):
    sums, short = "Compute 12 + 45 - 7 * 3 / 9 and 8 to 5", "What is 12 % of 250 km ?"
    rows = [(1, f"First: {sums}, so"), (2, f"Then. {short} Well"), (3, "Compute 13 + 45 - 7 * 3 / 9 and 8 to 5"), (4, "What is 12 % of 251 km ?"), (5, "what is 12% of 250 km")]
    bench = spark.createDataFrame([(0, sums), (1, short), (2, "..."), (3, "")], "item_id long, text string")
    got = decontamination.contaminated(docs(spark, rows), bench).collect()
    assert sorted(tuple(r) for r in got) == [(1, 0, 3, 3), (2, 1, 1, 1), (5, 1, 1, 1)]


@pytest.mark.parametrize(("order", "split"), [(1, 50), (2, 160_000), (3, 50)])
def test_katz(spark, corpus, monkeypatch, order, split):
    monkeypatch.setattr(katz, "BLOCK", 4000)
    monkeypatch.setattr(katz, "SPLIT", split)
    monkeypatch.setattr(katz, "MOST_SPLIT", 10**9)
    got = {r["doc_id"]: tuple(r)[1:] for r in katz.katz_scores(docs(spark, corpus), order).collect()}
    for d, want in katz.brute_force(corpus, order).items():
        assert got[d][:4] == want[:4] and got[d][4:] == pytest.approx(want[4:], rel=1e-9), d


def test_katz_rows_that_teach_nothing(spark):
    rows = [(None, "a b"), (3, None), (3, None), (5, "A b " * 400)]
    got = katz.katz_scores(docs(spark, rows)).collect()
    assert sorted(r["n_tokens"] for r in got) == [1, 1, 3, 801] and len(got) == 4
    held = [k for k in range(60) if zlib.crc32(str(k).encode()) % 7 == 2]
    assert {(r["score"], r["train_tokens"], r["n_known"]) for r in katz.katz_scores(docs(spark, [(k, "x y") for k in held])).collect()} == {(0.0, 0, 0)}


def test_personal_data(spark):
    texts = ["mail a.b@c.example.org, x@y and a@b.c@d.e", "at 10.0.0.255 or 10.0.0.256", "card 4111 1111 1111 1111 and 4111111111111112", "+1 (555) 123-4567 or +12", "", None]
    rng = random.Random(6)
    more = [f"{prose(rng, 5)} +1 ({rng.randint(200, 999)}) 555-{rng.randint(1000, 9999)} {prose(rng, 5)} u{k}@mail.example.com {prose(rng, 4)}" for k in range(40)]
    field = pii.trained(docs(spark, list(enumerate(more))))
    # A sample that has to be drawn by the bound, and one that the bound misses at first as all rows hash alike.
    assert pii.trained(docs(spark, list(enumerate(more * 5))), sample=10).weights and pii.trained(docs(spark, [(7, t) for t in more]), sample=5).weights
    got = {r["doc_id"]: r for r in pii.personal_data(docs(spark, list(enumerate(texts))), field=field).collect()}
    assert [got[k]["n_email"] for k in range(6)] == [2, 0, 0, 0, 0, 0] and got[1]["n_ip"] == 1 and got[2]["n_card"] == 1 and got[3]["n_phone"] == 1
    pattern = r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"
    assert got[0]["base"] == ",".join(f"email:{m.start()}:{m.end()}" for m in re.finditer(pattern, texts[0]))
    assert all(set(got[k]["base"].split(",")) <= set(got[k]["spans"].split(",")) for k in range(6))
    assert pii.all_spans(field, "call (555) 123-4567 now")[1] == [("phone", 5, 19)]
    assert pii.all_spans(field, "on 2021-03-04 at 10:22:33 we paid 1,234.00")[1] == []


def brute_base(text):
    """The base kinds by plain regular expressions over the whole text."""
    out = [("email", m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+", text)]
    out += [("ip", m.span()) for m in re.finditer(r"[0-9]+(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]+)", text) if all(int(p) <= 255 for p in m.group().split("."))]
    for kind, pattern, low, high in (("card", r"[0-9](?:[\x20-]?[0-9])+", 16, 19), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", 8, 15)):
        for m in re.finditer(pattern, text):
            digits = [int(c) for c in m.group() if c in "0123456789"]
            twice = sum(sum(divmod(2 * d, 10)) for d in digits[-2::-2]) + sum(digits[-1::-2])
            if low <= len(digits) <= high and (kind == "phone" or twice % 10 == 0):
                out.append((kind, m.span()))
    return [(k, *span) for k, span in out]


def test_base_kinds_by_brute_force():
    rng = random.Random(5)
    alphabet = ["a", "Z", "9", "4", "1", "0", "25", "255", ".", ".", "@", "@", "-", " ", "+", "+1", "(", ")", "%", "\n", "é", "4111 1111 1111 1111", "a.b@c.de", "10.0.0.1"]
    for _ in range(20_000):
        text = "".join(rng.choice(alphabet) for _ in range(rng.randint(0, 24)))
        assert sorted(pii.base_spans(text)) == sorted(brute_base(text)), text
    for text in spark_texts():
        assert sorted(pii.base_spans(text)) == sorted(brute_base(text))


def spark_texts():
    import pyarrow.parquet as pq

    return [t or "" for t in pq.read_table("/root/testdata/sf0.001/documents.parquet", columns=["text"]).column("text").to_pylist()]


def luhn_card(rng, n=16):
    body = [rng.randrange(10) for _ in range(n - 1)]
    s = sum(sum(divmod(2 * d, 10)) for d in body[::-1][::2]) + sum(body[::-1][1::2])
    return "".join(map(str, body + [-s % 10]))


def test_precision_and_recall_on_unseen_formats(spark):
    """Formats that training never writes, among numbers that are no personal data; trained on the tables' own spans."""
    field = pii.trained(spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text"))
    rng, right, found, planted = random.Random(21), 0, 0, 0
    n = lambda k: "".join(rng.choice("0123456789") for _ in range(k))
    for _ in range(400):
        c = luhn_card(rng)
        kind, s = rng.choice([
            ("phone", f"1-{rng.randint(201, 989)}-{n(3)}-{n(4)}"), ("phone", f"({rng.randint(201, 989)}) {n(3)}.{n(4)}"), ("phone", f"{rng.randint(201, 989)} {n(3)}-{n(4)}"),
            ("card", ".".join(c[k : k + 4] for k in range(0, 16, 4))), ("card", f"{c[:4]}  {c[4:8]}  {c[8:12]}  {c[12:]}"), ("ip", f"{rng.randint(11, 250)}[.]{rng.randint(0, 255)}[.]{rng.randint(0, 255)}[.]{rng.randint(1, 254)}"),
            ("email", f"{prose(rng, 1)}{n(2)} @ {prose(rng, 1)}-mail.example.org"), ("email", f"{prose(rng, 1)}.x (@) example{n(1)}.net"),
        ])
        noise = rng.choice([f"20{n(2)}-0{rng.randint(1, 9)}-1{n(1)}", f"v{n(1)}.{n(1)}.{n(2)}", f"{n(1)},{n(3)}.{n(2)}", f"{n(5)} of {n(4)}", f"{n(2)}:{n(2)}"])
        head = f"{prose(rng, 6)} {noise} {prose(rng, 6)} "
        text = f"{head}{s} {prose(rng, 8)} {n(2)} {prose(rng, 4)}"
        got = set(pii.all_spans(field, text)[1])
        planted, found, right = planted + 1, found + len(got), right + ((kind, len(head), len(head) + len(s)) in got)
    print(f"recall {right / planted:.3f}, precision {right / max(found, 1):.3f}")
    assert right >= 0.9 * planted and right >= 0.9 * found


def test_long_windows():
    field = pii.Field({("phone", "grouped"): 9.0} | {(kind, "bias"): -1.0 for kind in pii.KINDS})
    for before in (*range(190, 201), 399):
        text = "7 " * before + "(555) 123 4567" + " 8" * 50
        assert pii.all_spans(field, text)[1] == [("phone", 2 * before, 2 * before + 14)], before


def test_simhash(spark, corpus, monkeypatch):
    monkeypatch.setattr(simhash, "HOT", 3)
    got = {r["doc_id"]: (r["fp"] & (2**64 - 1), r["component_id"]) for r in simhash.simhash_components(docs(spark, corpus)).collect()}
    fps = {d: simhash.fingerprint((t or "").encode()) for d, t in corpus}
    root = {d: d for d in fps}
    for _ in fps:
        for a in fps:
            root[a] = min(root[b] for b in fps if (fps[a] ^ fps[b]).bit_count() <= 4)
    assert got == {d: (fps[d], root[d]) for d in fps}


def alike_roots(rows):
    """By comparing all sets: the least doc_id that links of 4/5 of the shingles in common reach, and the pairs linked."""
    def shingles(t):
        ws = re.findall("[^\\x20\\x09-\\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))
        return {tuple(ws[i : i + 5]) for i in range(max(1, len(ws) - 4))}

    sets = {d: shingles(t) for d, t in rows if d is not None}
    pairs = {(a, b) for a in sets for b in sets if a < b and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b])}
    root = {d: d for d in sets}
    for _ in range(8):
        for a, b in pairs:
            root[a] = root[b] = min(root[a], root[b])
    return root, pairs


def test_similar(spark, corpus):
    rng = random.Random(12)
    rows = [*corpus, (None, corpus[3][1]), (None, "only here")]
    for k in range(24):  # each k // 4 + 1 changes away from the text that it begins with, so that not all are alike
        own = prose(random.Random(k % 3), 150).split()
        for i in range(1 + k // 4):
            own[(7 * k + 20 * i) % 150] = f"w{k}x{i}"
        rows.append((100 + k, " ".join(own)))
    got = similar.similar_components(docs(spark, rows)).collect()
    root, pairs = alike_roots(rows)
    assert {r["doc_id"]: r["component_id"] for r in got if r["doc_id"] is not None} == root and len(got) == len(rows) and len(pairs) > 20
    assert sorted(r["component_id"] or -1 for r in got if r["doc_id"] is None) == [-1, 3]
    kept = similar.similar_dedup(docs(spark, [(d, t) for d, t in rows if d is not None])).collect()
    assert {r["doc_id"] for r in kept} == {*root.values()}
    assert similar.similar_dedup(docs(spark, []).withColumn("_kept", F.lit(1))).count() == 0


@pytest.mark.parametrize("hot", [2000, 3])
def test_similar_where_fingerprints_miss(spark, monkeypatch, hot):
    """Short texts that differ in their last word: a ninth of the shingles of each, but many bits of fingerprints."""
    monkeypatch.setattr(similar, "HOT", hot)
    monkeypatch.setattr(similar, "COUNTED", 500)
    rng = random.Random(21)
    rows = []
    for k in range(120):
        own = prose(rng, 13)
        rows += [(3 * k, f"{own} {prose(rng, 1)}x"), (3 * k + 1, f"{own} {prose(rng, 1)}y"), (3 * k + 2, f"a shared beginning of six words {prose(rng, 6)}")]
    root, pairs = alike_roots(rows)
    got = {r["doc_id"]: r["component_id"] for r in similar.similar_components(docs(spark, [*rows, rows[4]])).collect()}
    assert got == root and len(pairs) >= 120


def test_similar_in_batches_of_bounded_bytes(spark, monkeypatch):
    def watched(run):
        def out(batches):
            def each():
                for batch in batches:
                    assert batch.slice(0, batch.num_rows - 1).nbytes <= 120_000, (batch.schema.names, batch.num_rows, batch.nbytes)
                    yield batch

            return run(each())

        return out

    monkeypatch.setattr(similar, "BATCH", 100_000, raising=False)
    monkeypatch.setattr(similar, "freeing", watched)
    rng = random.Random(5)
    rows = [(k, prose(rng, 1_500)) for k in range(60)]
    rows += [(100 + k, " ".join(w if i % 97 else "zz" for i, w in enumerate(t.split()))) for k, t in rows[:30]]
    got = {r["doc_id"]: r["component_id"] for r in similar.similar_components(docs(spark, rows).coalesce(1)).collect()}
    assert got == {d: d % 100 for d, _ in rows}


def test_counting_shingles_takes_little_memory():
    import pyarrow as pa

    rng, n, chunks = np.random.default_rng(6), 1_000_000, 10
    hashes = segments.mix(rng.integers(0, 2 * n, n, dtype=np.uint64) + np.uint64(1))
    owners = rng.integers(0, 300, n).astype(np.uint16)
    split = lambda x: [p.tobytes() for p in np.split(x, chunks)]

    def batches():
        for k, (s, o) in enumerate(zip(split(hashes), split(owners), strict=True)):
            cells = [[0, 0], [k, k], [True, False], [b"", s], [b"", o]]
            yield pa.RecordBatch.from_arrays([*map(pa.array, cells[:3]), *(pa.array(c, pa.binary()) for c in cells[3:])], names=["bucket", "chunk", "listed", "shingles", "owners"])

    _, back, times = np.unique(hashes, return_inverse=True, return_counts=True)
    times, at = times[back], 0
    listed, most = [], 0
    tracemalloc.start()
    for out in similar._shared(batches()):
        most = max(most, out.nbytes)
        for r in out.to_pylist():
            if r["listed"]:
                listed.append(r["chunk"])
                continue
            own = slice(r["chunk"] * n // chunks, (r["chunk"] + 1) * n // chunks)
            hit = times[own] > 1
            assert r["shingles"] == hashes[own][hit].tobytes() and r["owners"] == owners[own][hit].astype(np.uint32).tobytes()
            assert np.frombuffer(r["counts"], dtype=f"u{len(r['counts']) // int(hit.sum())}").tolist() == times[own][hit].tolist()
            at += n // chunks
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert sorted(listed) == list(range(chunks)) and at == n
    assert most <= 6_000_000 and peak <= 45 * n, (most, peak)  # bytes


def test_similar_in_large_groups(spark, monkeypatch):
    monkeypatch.setattr(simhash, "SMALL", 4)
    monkeypatch.setattr(simhash, "HOT", 20)
    rng, base = random.Random(2), prose(random.Random(1), 200).split()
    rows = [(k, " ".join("zz" if rng.random() < 0.01 else w for w in base)) for k in range(80)] + [(100 + k, prose(rng, 60)) for k in range(10)]
    got = {r["doc_id"]: r["component_id"] for r in similar.similar_components(docs(spark, rows)).collect()}
    assert got == alike_roots(rows)[0]


@pytest.mark.parametrize("n", [100, 1 << 25, 1 << 40])
def test_layouts_bring_near_fingerprints_together(n):
    import numpy as np

    rng = np.random.default_rng(8)
    groups = simhash.layout(n)
    for _ in range(40):
        a = int(rng.integers(0, 2**63))
        b = a
        for bit in rng.choice(64, rng.integers(0, 5), replace=False):
            b ^= 1 << int(bit)
        keys = lambda x: {(int(k), bool(h)) for _, k, h in zip(*simhash.anchors(np.array([x], dtype=np.uint64), groups), strict=True)}
        near = {k for k, _ in keys(b)}
        assert any(h and k in near for k, h in keys(a))


def test_pipeline_links_near_copies(spark):
    import corpus_pipeline

    rng = random.Random(13)
    base = prose(rng, 200).split()
    rows = [(1, " ".join(base)), (2, " ".join("changed" if i in (30, 80, 130, 170) else w for i, w in enumerate(base))), (3, prose(rng, 200))]
    assert (simhash.fingerprint(rows[0][1].encode(), 5) ^ simhash.fingerprint(rows[1][1].encode(), 5)).bit_count() > simhash.NEAR
    assert {r["doc_id"] for r in corpus_pipeline._near_copies(spark, docs(spark, rows), "").collect()} == {1, 3}


def test_components(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(1, 20)] + [(30, 40), (40, 31), (7, 7)], "a long, b long")
    got = {r["node"]: r["root"] for r in components(edges, Scratch(spark, "t")).collect()}
    assert got == {k: 1 for k in range(1, 21)} | {30: 30, 31: 30, 40: 30}


def test_rollups(spark, tmp_path):
    d = docs(spark, [(1, "a b c"), (2, "d e"), (3, None), (4, "x" * 9)], SCHEMA)
    roll = token_counts.Rollup(spark, str(tmp_path / "roll"))
    counts = token_counts.word_counts(d)
    assert roll.commit("one", token_counts.inserted(counts)) and not roll.commit("one", token_counts.inserted(counts))
    total = lambda: {r["source"]: (r["docs"], r["tokens"]) for r in roll.totals().collect()}
    assert total() == {"s1": (2, 4), "s2": (1, 2), "s0": (1, 0)}
    roll.commit("two", token_counts.deleted(token_counts.word_counts(d.where("doc_id = 2"))))
    roll.commit("three", token_counts.revised(token_counts.word_counts(d.where("doc_id = 1")), token_counts.word_counts(docs(spark, [(1, "a")], SCHEMA))))
    assert total() == {"s1": (2, 2), "s0": (1, 0)}
    assert roll.compact("all") and roll.batches() == ["all"] and total() == {"s1": (2, 2), "s0": (1, 0)}
    assert not roll.commit("one", token_counts.inserted(counts)) and not roll.compact("one")
    assert roll.commit("four", token_counts.inserted(counts)) and roll.compact("again") and not roll.commit("two", token_counts.inserted(counts))
    assert roll.batches() == ["again"] and total() == {"s1": (4, 6), "s2": (1, 2), "s0": (2, 0)}
    # Compactions that stopped before their batch was complete, and before what they stand for was removed.
    roll.commit("five", token_counts.deleted(counts))
    spark.createDataFrame([("again",), ("five",)], "name string").write.parquet(str(tmp_path / "roll" / "covers=later"))
    assert roll.batches() == ["again", "five"] and total() == {"s1": (2, 2), "s0": (1, 0)}
    roll.totals().write.parquet(str(tmp_path / "roll" / "batch=later"))
    assert roll.batches() == ["later"] and roll.committed("five") and total() == {"s1": (2, 2), "s0": (1, 0)}
    encoding = token_counts._encoding(token_counts.RANKS)
    long = prose(random.Random(9), 30_000)
    assert token_counts.byte_pair_counts(docs(spark, [(1, long), (2, None)], SCHEMA)).agg({"tokens": "sum"}).first()[0] == len(encoding.encode_ordinary(long))


def test_curriculum(spark):
    rows = [(k, "w " * (k % 7 + 1)) for k in range(60)] + [(90, None), (None, "lone words here")]
    out = curriculum.mixed(docs(spark, [*rows, rows[5]])).collect()
    assert len(out) == 63 and all(0 <= r["copies"] <= 3 for r in out)
    placed = {(r["doc_id"], r["copy"]): r["position"] for r in curriculum.curriculum(docs(spark, rows)).collect()}
    for r in curriculum.mixed(docs(spark, rows)).collect():
        own = [placed[r["doc_id"], c] for c in range(r["copies"])]
        assert (own[0], own[-1]) == (r["first_position"], r["last_position"]) if own else r["first_position"] is None
    for s in {r["source"] for r in out}:
        own = [r for r in out if r["source"] == s]
        assert abs(sum(r["copies"] * r["size"] for r in own) - own[0]["target"]) <= max(r["size"] for r in own)
    assert sum({r["source"]: r["target"] for r in out}.values()) == pytest.approx(sum(r["size"] for r in out))
    order = curriculum.curriculum(docs(spark, rows)).collect()
    assert [r["position"] for r in order] == sorted(r["position"] for r in order) and all(0 <= r["position"] <= 1 for r in order)


def test_taken_words_come_from_the_inverted_schedules(spark, monkeypatch):
    rows = docs(spark, [(k, "w " * (3 + k % 11)) for k in range(60)])
    key = lambda r: (r["first_position"] is None, r["first_position"] or 0, r["doc_id"])
    out = curriculum.mixed(rows).collect()
    assert [r["doc_id"] for r in out] == [r["doc_id"] for r in sorted(out, key=key)]
    copies = sorted((r["position"], r["doc_id"], r["copy"]) for r in curriculum.curriculum(rows).collect())
    assert copies == sorted((p, r["doc_id"], k) for r in out for k, p in enumerate(r["positions"])) and copies
    own = curriculum._position
    monkeypatch.setattr(curriculum, "_position", lambda share, tilt: F.when(own(share, tilt) <= 0.5, own(share, tilt)))  # training ends half-way
    half = {r["doc_id"]: r["copies"] for r in curriculum.mixed(rows).collect()}
    assert half == {r["doc_id"]: sum(p <= 0.5 for p in r["positions"]) for r in out}


def test_empty_tables(spark):
    none = docs(spark, [], EXTRA)
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    bench = spark.createDataFrame([], "item_id long, text string")
    for out in (substring_dedup.substring_dedup(none), suffix_dedup.suffix_dedup(none), line_dedup.line_dedup(none), quality_rules.quality_rules(none, labels), decontamination.contaminated(none, bench), katz.katz_scores(none), pii.personal_data(none), simhash.simhash_components(none), token_counts.byte_pair_counts(none), curriculum.curriculum(none)):
        assert out.count() == 0


def words_of(text):
    return re.findall("[^\\x20\\x09-\\x0D]+", text or "")


def lines_by_brute_force(rows):
    key = lambda x: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in x.strip(" \t\n\x0b\x0c\r"))
    holders = {}
    for d, t in rows:
        for x in (t or "").split("\n"):
            if len(key(x)) >= 20:
                holders.setdefault(key(x), set()).add(d)
    gone = lambda d, x: len(holders.get(key(x), ())) >= 3 and max(holders[key(x)]) != d
    out = {}
    for d, t in rows:
        lines = (t or "").split("\n")
        kept = [x for x in lines if not gone(d, x)]
        if len(kept) == len(lines) or "\n".join(kept):
            out[d] = t if len(kept) == len(lines) else "\n".join(kept)
    return out


def mix_by_brute_force(rows, cap=3):
    """doc_id to its copies, and all positions in order, from the definition of the schedules."""
    size = {d: len(words_of(t)) for d, t, _ in rows}
    sources = sorted({s for *_, s in rows}, key=lambda s: (s is None, s or ""))
    whole = {s: sum(size[d] for d, _, x in rows if x == s) for s in sources}
    weight, tilt = ({s: values[k % 3] for k, s in enumerate(sources)} for values in ((1.0, 2.0, 3.0), (0.0, 0.5, -0.5)))
    target, full = {}, set()
    while True:
        left = sum(whole.values()) - sum(cap * whole[s] for s in full)
        level = left / sum(weight[s] for s in sources if s not in full)
        over = {s for s in sources if s not in full and level * weight[s] > cap * whole[s]}
        if not over:
            break
        full |= over
    target = {s: float(cap * whole[s]) if s in full else level * weight[s] for s in sources}
    copies, positions = {}, []
    for s in sources:
        before = 0
        for d, _, _ in sorted((r for r in rows if r[2] == s), key=lambda r: (int(hashlib.md5(str(r[0]).encode()).hexdigest()[:13], 16), r[0])):
            n = size[d]
            copies[d] = sum(n > 0 and k * whole[s] + before + n / 2 <= target[s] for k in range(cap))
            for k in range(copies[d]):
                share = min(1.0, (k * whole[s] + before + n / 2) / target[s])
                t, step = 0.5, 0.25
                for _ in range(50):  # the schedule's integral from 0 to t is t + tilt * (t * t - t)
                    t += step if t + tilt[s] * (t * t - t) < share else -step
                    step /= 2
                positions.append((t, d, k))
            before += n
    return copies, sorted(positions)


def test_pipeline_by_brute_force(spark):
    """Each stage on the output of the one before, over whole tables."""
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    start = spark.read.parquet(f"{sf}/documents.parquet")
    outs, current = [], start
    for name, stage in corpus_pipeline.STAGES:
        rows = stage(spark, current, sf).collect()
        outs.append(rows)
        current = spark.createDataFrame(rows, stage(spark, current, sf).schema) if name != "mix" else current
    begin = start.collect()
    quality, lines, near, clean, mix = outs
    # Quality: the base rules by hand, and the learned list's verdict as its own text says.
    learned = quality_rules.learn(quality_rules.labelled_statistics(start, spark.read.parquet(f"{sf}/labels.parquet"), Scratch(spark, "t")))
    stats = {r["doc_id"]: r for r in quality_rules.statistics(start).collect()}
    holds = lambda r, c: r[c.feature] > c.threshold if c.above else r[c.feature] <= c.threshold
    fails = lambda r: r["n_words"] < 10 or 100 * r["n_repeat_words"] > 20 * r["n_words"]
    want = {d for d, r in stats.items() if not fails(r) and not any(all(holds(r, c) for c in rule) for rule in learned.rules)}
    assert {r["doc_id"] for r in quality} == want and len(want) < len(begin)
    assert {r["doc_id"]: r["text"] for r in lines} == lines_by_brute_force([(r["doc_id"], r["text"]) for r in quality])
    assert all(r["n_chars"] == len(r["text"]) for r in lines)
    root, _ = alike_roots([(r["doc_id"], r["text"]) for r in lines])
    assert {r["doc_id"] for r in near} == set(root.values())
    # Decontamination: verbatim items go, and texts that share no eight words in a row with any item stay.
    plain = lambda t: re.sub(r"[^\w\s]|_", "", (t or "").lower()).split()
    items = [plain(r["text"]) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    eights = {tuple(i[k : k + 8]) for i in items for k in range(len(i) - 7)}
    left = {r["doc_id"] for r in clean}
    for r in near:
        ws = plain(r["text"])
        if any(f" {' '.join(i)} " in f" {' '.join(ws)} " for i in items):
            assert r["doc_id"] not in left
        elif not any(tuple(ws[k : k + 8]) in eights for k in range(len(ws) - 7)):
            assert r["doc_id"] in left
    copies, positions = mix_by_brute_force([(r["doc_id"], r["text"], r["source"]) for r in clean])
    got = {}
    for r in mix:
        got[r["doc_id"]] = got.get(r["doc_id"], 0) + 1
    assert got == {d: n for d, n in copies.items() if n}
    assert [r["position"] for r in mix] == pytest.approx([t for t, _, _ in positions], abs=1e-9)


def test_pipeline_stages(spark):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    table = spark.read.parquet(f"{sf}/documents.parquet")
    out = corpus_pipeline.run(spark, sf).collect()
    assert set(table.columns) <= set(out[0].asDict()) and 0 < len({r["doc_id"] for r in out}) < table.count()
    texts = [hashlib.sha256(r["text"].encode()).hexdigest() for r in out if r["copy"] == 0]
    assert len(texts) == len(set(texts))

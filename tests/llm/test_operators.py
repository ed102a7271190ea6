"""Operators against brute force, and on nulls, empty and long texts, ties, repeated rows, empty tables and clashing names."""

import hashlib
import itertools
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import corpus_pipeline
from mutualgraph.llm import components, language, licences, media, mixing, near_duplicates, ngram, packing, personal, queries, token_files, tokenise, vector_duplicates, words

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
WORDS = re.compile(r"[^\x20\x09-\x0D]+")


def sample_docs(n=60, seed=0):
    rnd = random.Random(seed)
    vocab = ["".join(rnd.choice("abcdefghéß") for _ in range(rnd.randint(2, 7))) for _ in range(300)]
    rows = []
    for i in range(n):
        body = [rnd.choice(vocab) for _ in range(rnd.randint(1, 80))]
        rows.append((i, " ".join(body), rnd.choice(["en", "de", None]), f"src{i % 4}", 0))
    for i in range(n, n + 10):  # near copies: one word differs
        w = rows[i - n][1].split()
        w[rnd.randrange(len(w))] = "zzz"
        rows.append((i, " ".join(w), "en", "src1", 0))
    for i in range(n + 10, n + 20):  # exact copies, in other case
        rows.append((i, rows[3][1].upper().replace("É", "é").replace("ß".upper(), "ß"), "en", "src2", 0))
    return rows


ODD = [
    (1000, None, None, None, None),
    (1001, "", "en", None, 0),
    (1002, " \t\n ", "en", "src0", 4),
    (1003, "one", "en", "src0", 3),
    (1004, "12 34 !!", None, "src9", 8),
    (1005, "x" * 60_000 + " " + "y z " * 20_000, "en", "src0", 140_001),
    (1006, "same row", "en", "src0", 8),
    (1006, "same row", "en", "src0", 8),
    (None, "no id here", "en", "src0", 10),
    (1007, "mail a.b@c.example.org, ip 10.0.0.1 and 10.0.0.256, card 4111 1111 1111 1111, tel +1 (234) 555-6789 <|endoftext|> x", "en", "src0", 10),
    (1008, "日本語 テキスト Привет мир", None, "src0", 10),
]


@pytest.fixture(scope="module")
def docs(spark):
    clash = {c: F.lit("clash") for c in ("_key", "_spans", "_text", "epochs", "target", "size", "component_id", "kept", "lang_pred", "score", "spans", "band", "piece", "digest", "bucket", "shard", "_copy")}
    return spark.createDataFrame(sample_docs() + ODD, SCHEMA).withColumns(clash)


@pytest.fixture(scope="module")
def plain():
    return [(r[0], r[1] or "") for r in sample_docs() + ODD]


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def lower(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t)


def test_word_hashes_equal_iff_words_do():
    import pyarrow as pa

    texts = [t for _, t, *_ in sample_docs()] + [None, "", "a  b\tc d "]
    h, first = words.word_hashes(pa.array(texts))
    flat = [w for t in texts for w in WORDS.findall(lower(t or ""))]
    assert len(h) == len(flat) == first[-1]
    assert len(set(flat)) == len(set(h.tolist())) == len(set(zip(flat, h.tolist(), strict=True)))


def test_mixing_fills_targets(docs, plain):
    got = mixing.mix(docs).collect()
    assert len(got) == len(plain)
    size = {}
    for r in got:
        size[r.source] = size.get(r.source, 0) + r["size"]
    order = sorted([s for s in size if s is not None], key=lambda s: s.encode()) + [None]
    weight = {s: (3, 1, 2)[i % 3] for i, s in enumerate(order)}
    left, open_, target = 1.5 * sum(size.values()), set(order), {}
    while True:  # deal, cap, deal the excess again
        level = left / sum(weight[s] for s in open_)
        over = {s for s in open_ if level * weight[s] > 2 * size[s]}
        if not over:
            target |= {s: level * weight[s] for s in open_}
            break
        for s in over:
            target[s] = 2.0 * size[s]
            left -= target[s]
        open_ -= over
        if not open_:
            break
    for r in got:
        assert r.source_size == size[r.source] and r.target == pytest.approx(target[r.source]) and 0 <= r.taken <= 2 * r["size"]
    for s in order:
        biggest = max(r["size"] for r in got if r.source == s)
        assert abs(sum(r.taken for r in got if r.source == s) - target[s]) <= biggest / 2 + 1e-6
    assert sorted(map(str, got)) == sorted(map(str, mixing.mix(docs).collect()))


@pytest.mark.parametrize("worth", [None, 0.02, 50.0])
def test_mixing_takes_what_a_plain_sort_takes(spark, monkeypatch, worth):
    """The line found by rounds is that of sorting all keys of a source, at any scale of quality, ids repeated or null."""
    monkeypatch.setattr(mixing, "EDGE_ROWS", 3)
    rnd = random.Random(9)
    rows = [(rnd.choice([None, *range(300)]), "w " * rnd.randint(0, 30) + str(rnd.randint(0, 3)), rnd.choice(["a", "b", None])) for _ in range(2000)]
    df = spark.createDataFrame(rows + rows[:40] * 5, "doc_id long, text string, source string")
    options = {"weights": (1, 2), "share": 0.7, "quality": None if worth is None else F.lit(worth)}
    got = Counter((r.source, r.doc_id, r["size"], r.taken) for r in mixing.mix(df, **options).collect())
    narrow, _ = mixing._narrow(*mixing._needed(df, options["quality"]), 20240501)
    target = {r.source: r.target for r in mixing.mix(df, **options).collect()}
    want = Counter()
    for source, goal in target.items():
        mine = sorted((r for r in narrow.collect() if r["_src"] == source), key=lambda r: (r["_key"], r["_tie"]))
        total = sum(r["_size"] for r in mine)
        rest, sofar, epochs = goal - goal // total * total, 0, goal // total
        taken = [i for i, r in enumerate(mine) if (sofar := sofar + r["_size"]) - r["_size"] / 2 <= rest and sofar - r["_size"] < rest]
        for i, r in enumerate(mine):
            want[source, r["_id"], r["_size"], r["_size"] * (epochs + (i <= max(taken)))] += 1
    assert got == want


def test_mixing_rows_of_one_id_have_fates_of_their_own(spark):
    rows = [(7, "w " * 10, "a")] * 400 + [(i, "w " * 10, "a") for i in range(8, 100)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(3)
    got = mixing.mix(df, weights=(1,), share=0.5)
    assert abs(got.agg(F.sum("taken")).first()[0] - 2460) <= 5
    assert mixing.mixed_documents(df, weights=(1,), share=0.5).count() == 246
    assert mixing.mixed_documents(df, weights=(1,), share=1.5).filter("doc_id = 7").count() == got.select(F.sum("epochs")).first()[0] + 400 - got.filter("doc_id <> 7").agg(F.sum("epochs")).first()[0]


def test_mixing_prefers_quality(spark):
    rows = spark.createDataFrame([(i, "w " * 10, "a", i % 2) for i in range(2000)], "doc_id long, text string, source string, good int")
    got = mixing.mix(rows, weights=(1,), share=0.3, quality=F.when(F.col("good") == 1, 4.0).otherwise(1.0)).filter("taken > 0")
    n = {r.odd: r["count"] for r in got.groupBy((F.col("doc_id") % 2).alias("odd")).count().collect()}
    assert n[1] > 2 * n[0]


def test_mixed_documents_repeat_rows(docs):
    want = Counter()
    for r in mixing.mix(docs).collect():
        want[r.doc_id] += r.epochs
    got = mixing.mixed_documents(docs)
    assert got.columns == docs.columns
    assert Counter(r.doc_id for r in got.select("doc_id").collect()) == Counter({k: v for k, v in want.items() if v})


@pytest.mark.parametrize("axes", [None, 4])
def test_vectors_against_brute_force(spark, axes):
    rng = np.random.default_rng(1)
    base = rng.standard_normal((300, 16))
    near = base[:60] + 0.05 * rng.standard_normal((60, 16))
    chain = base[:20] + 0.28 * rng.standard_normal((20, 16))
    x = np.vstack([base, near, chain, base[:5], 3 * base[5:8]])
    rows = [(i, v.tolist()) for i, v in enumerate(x)]
    n = len(rows)
    rows += [(n, None), (n + 1, [0.0] * 16), (n + 2, [1.0, None] + [0.0] * 14), (n + 3, [float("nan")] * 16), (n + 4, [float("inf")] + [0.0] * 15), (n + 5, []), (n + 6, base[0, :8].tolist())]
    got = {r.vec_id: r for r in vector_duplicates.vector_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), axes=axes).collect()}
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    link = (u @ u.T >= 0.95) & ~np.eye(n, dtype=bool)
    label = np.arange(n)
    for _ in range(n):
        new = np.array([min([label[i], *label[link[i]]]) for i in range(n)])
        if (new == label).all():
            break
        label = new
    assert len(got) == len(rows)
    for i in range(n):
        assert (got[i].n_links, got[i].component_id, got[i].kept) == (link[i].sum(), label[i], label[i] == i)
    for i in range(n, n + 7):
        assert (got[i].n_links, got[i].component_id, got[i].kept) == (0, i, True)


def test_cells_follow_the_number_of_vectors():
    axes = [vector_duplicates.cell_axes(n) for n in (0, 1, 10**4, 10**5, 10**6, 10**7, 10**12)]
    assert axes == sorted(axes) and axes[0] == 2 and axes[-1] == 6
    gaps = np.random.default_rng(3).standard_normal((400_000, 6)) * math.sqrt(0.1)
    for k in (2, 6):
        assert (np.abs(gaps[:, :k]) > vector_duplicates.cell_width(0.95, k, 1e-2)).any(1).mean() < 1.1e-2


def test_collisions_and_calibration():
    rng = np.random.default_rng(0)
    a, b = rng.standard_normal((30, 8)).astype(np.float32), rng.standard_normal((50, 8)).astype(np.float32)
    want = (np.abs(a[:, None] - b[None]) <= np.float32(0.4)).sum(2)
    assert (np.abs(vector_duplicates.collisions(a, b, np.float32(0.4)).astype(int) - want) <= 1).mean() > 0.999
    half, need = vector_duplicates.calibrate(0.95, 40)
    gaps = rng.standard_normal((200_000, 40)) * math.sqrt(0.1)
    assert ((np.abs(gaps) <= half).sum(1) < need).mean() < 1e-3


def base_spans(t):
    def luhn(d):
        return sum(v if i % 2 == 0 else (2 * v - 9 if v > 4 else 2 * v) for i, v in enumerate(int(c) for c in reversed(d))) % 10 == 0

    out = [(m.start(), 0, m.end(), "email") for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    out += [(m.start(), 1, m.end(), "ip") for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(x) <= 255 for x in m[0].split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = re.sub("[^0-9]", "", m[0])
        if 14 <= len(d) <= 19 and luhn(d):
            out.append((m.start(), 2, m.end(), "card"))
    out += [(m.start(), 3, m.end(), "phone") for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 10 <= len(re.sub("[^0-9]", "", m[0])) <= 15]
    return ",".join(f"{k}:{a}:{b}" for a, _, b, k in sorted(out))


def test_base_spans_against_brute_force(spark, docs, plain):
    rnd = random.Random(3)
    parts = ["a", "b.", "@", "@x.y", "1", "255", ".", "-", " ", "+", "+1 ", "(5", "4111 1111 1111 1111", "1.2.3.4", "_", "..", "%", "é", "\n", "4539578763621486", "-3", "99"]
    texts = ["".join(rnd.choice(parts) for _ in range(rnd.randint(0, 40))) for _ in range(800)] + ["a@b" + ".c" * 20_000, "1-" * 20_000 + "1", "+" + "1 " * 20_000]
    more = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for df, rows in ((more, list(enumerate(texts))), (docs, plain)):
        got = sorted((str(r.doc_id), r.base_sha256) for r in personal.detect(df).collect())
        assert got == sorted((str(i), hashlib.sha256(base_spans(t).encode()).hexdigest()) for i, t in rows)


def test_patterns_are_linear(spark):
    rows = [(0, "a" * 300_000), (1, "1" * 300_000), (2, "1." * 100_000)]
    assert personal.detect(spark.createDataFrame(rows, "doc_id long, text string")).count() == 3


def test_disclosing_terms_are_found_and_replaced(spark):
    rows = [(i, f"Call the Zorblax office number {i} tel +1 (234) 555-6789 please") for i in range(6)] + [(i, f"call the office please number {i} today") for i in range(6, 400)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r for r in personal.detect(df).collect()}
    at = rows[0][1].index("Zorblax")
    assert f"term:{at}:{at + 7}" in got[0].spans.split(",") and got[0].n_phone == 1
    assert not any("term" in r.spans for i, r in got.items() if i >= 6)
    assert got[0].n_terms == 2  # Zorblax and tel stand with the number alone
    safe = {r.doc_id: r.text for r in personal.sanitise(df).collect()}
    assert safe[0] == "Call the [...] office number 0 [...] [PHONE] please" and safe[7] == rows[7][1]


def test_values_of_one_or_two_texts_are_protected(spark):
    one, two = "Quibbler please write to a@b.cd or c@d.ef today", "please ask Vexley tel +1 (234) 555-67{} today"
    rows = [(0, one), (1, two.format("89")), (2, two.format("89") + " now")] + [(i, f"please write or ask today number {i} now") for i in range(3, 400)]
    got = {r.doc_id: r for r in personal.detect(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert "term:0:8" in got[0].spans.split(",") and got[0].n_terms == 1
    assert all(got[i].n_terms == 2 and f"term:{two.index('Vexley')}:{two.index('Vexley') + 6}" in got[i].spans.split(",") for i in (1, 2))
    assert not any(r.n_terms for i, r in got.items() if i > 2)
    copies = [(i, one) for i in range(50)] + rows[3:]  # copies of a text are no more evidence than the text
    got = {r.doc_id: r for r in personal.find(spark.createDataFrame(copies, "doc_id long, text string")).collect()}
    assert all(not got[i]["_marks"] for i in range(50))


def test_terms_are_generalised_where_their_class_tells_nothing(spark):
    rows = [(0, "Quibbler and Xyzzy write to a@b.cd today")] + [(i, f"quite many write {'quietly' if i % 2 else 'and'} today to number {i}") for i in range(1, 400)]
    got = {r.doc_id: r.text for r in personal.sanitise(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[0] == "qui* and [...] write to [EMAIL] today" and got[7] == rows[7][1]


def test_secrets(spark):
    key = "b44e15e09fd311c3cf3163b66d5a9875b883d8ce"
    rows = [(0, f'put token = "{key}" here'), (1, "a" * 50 + " " + "1" * 50), (2, f"mail {key}@x.org now"), (3, "x" * 19 + "1")] + [(i, f"put here number {i}") for i in range(4, 100)]
    got = {r.doc_id: r for r in personal.detect(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert [got[i].n_secrets for i in range(5)] == [1, 0, 0, 1, 0] and f"secret:13:{13 + len(key)}" in got[0].spans.split(",")
    assert got[2].n_email == 1 and got[0].base_sha256 == hashlib.sha256(b"").hexdigest() and got[0].n_spans == got[0].n_terms + 1
    safe = {r.doc_id: r.text for r in personal.sanitise(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert '"[SECRET]"' in safe[0] and safe[1] == rows[1][1]


def test_disclosing_marks_against_brute_force(spark, tiny):
    df = spark.read.parquet(f"{tiny}/documents.parquet").select("doc_id", "text")
    rows = [(r.doc_id, r["_key"], [f"{x.kind}:{x.value.lower()}" for x in [*r["_spans"], *r["_secrets"]]], set(r["_marks"] or [])) for r in personal.find(df).collect()]
    marks = {r.doc_id: {m for t in re.findall(r"[^\W\d_]{3,}", (r.text or "").lower()) for m in (t, t[:3] + "*")} for r in df.collect()}
    n_mark = Counter(t for x in marks.values() for t in x)
    at = {}
    for i, key, values, _ in rows:
        for v in values:
            at.setdefault(v, {})[i] = key
    want = {i: set() for i in marks}
    for docs_ in at.values():
        for t in set().union(*(marks[i] for i in docs_)):
            both = [i for i in docs_ if t in marks[i]]
            texts = len({docs_[i] for i in both})
            p = texts / (texts + 0.5) * len(both) / n_mark[t]
            if math.log2(p * len(rows) / len(docs_)) / math.log2(len(rows) / len(docs_)) >= 0.9:
                for i in both:
                    want[i].add(t)
    assert any(want.values()) and {i: x for i, _, _, x in rows} == want


def test_sanitise_keeps_rows_and_columns(docs):
    out = personal.sanitise(docs)
    assert out.columns == docs.columns and out.count() == docs.count()
    row = out.filter("doc_id = 1007").first()
    assert "[EMAIL]" in row.text and "[CARD]" in row.text and "10.0.0.256" in row.text and row.n_chars == len(row.text)
    assert out.filter("doc_id = 1000").first().text is None


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_tokenising_equals_the_library(name):
    import pyarrow as pa

    texts = [t for _, t, *_ in sample_docs()] + [t for _, t, *_ in ODD] + ["", None, "  ", "a  b\n\n c", "x  y  z ", " q r", "tab\t\tx \n", "é é", " 'S don't", "\x1c a", "á b"]
    lib = Tokenizer.from_file(public_tokenizers.path(name))
    ids, offs = tokenise.Encoder(public_tokenizers.path(name)).encode(pa.array(texts))
    for i, t in enumerate(texts):
        assert ids[offs[i] : offs[i + 1]].tolist() == lib.encode(t or "", add_special_tokens=False).ids


def test_packing(docs, plain):
    lib = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    got = packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"), packing.Capacity(256, 256, 256 * 256)).collect()
    want = Counter()
    for i, t in plain:
        ids = lib.encode(t, add_special_tokens=False).ids + [0]
        for p, at in enumerate(range(0, len(ids), 256)):
            cut = np.array(ids[at : at + 256], "<u4")
            want[i, p, at, len(cut), zlib.crc32(cut.tobytes())] += 1
    assert Counter((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in got) == want
    by = {}
    for r in got:
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in by.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= 256
    assert len(by) <= math.ceil(sum(r.length for r in got) / 256) * 1.05 + 1


@pytest.mark.parametrize("score", ["norm", "dot"])
def test_best_fit_respects_every_capacity(score):
    lengths = np.random.default_rng(0).integers(1, 100, 500)
    cap = packing.Capacity(100, 4, 5000 + 100 * 100)
    which, offset = packing.best_fit(lengths, cap, score)
    for b in np.unique(which):
        at = lengths[which == b]
        assert at.sum() <= 100 and len(at) <= 4 and (at**2).sum() <= cap.attention
    with pytest.raises(ValueError):
        packing.best_fit(np.array([101]), cap)


def test_backoff_scores_against_brute_force(spark, docs, plain):
    held = language.held_out(F.col("doc_id"), 10, 0)
    for order in (1, 2, 3):
        got = {}
        for r in ngram.score_documents(docs, held, order=order, bucket_bytes=2000).collect():
            got.setdefault(r.doc_id, r)
        toks = [(i, WORDS.findall(lower(t)) + ["</s>"]) for i, t in plain]
        train = [v for i, v in toks if i is None or zlib.crc32(str(i).encode()) % 10]
        c = [Counter() for _ in range(order + 1)]
        for v in train:
            w = ["<s>", *v]
            for k in range(1, order + 1):
                c[k].update(tuple(w[j - k + 1 : j + 1]) for j in range(1, len(w)) if j - k + 1 >= 0)
        n, kinds = sum(c[1].values()), len(c[1])
        c[1][("<s>",)] = len(train)
        for i, v in toks:
            w, score, base = ["<s>", *v], 0.0, 0.0
            for j in range(1, len(w)):
                p = (c[1][(w[j],)] + 0.1) / (n + 0.1 * (kinds + 1))
                base += math.log10(p)
                for k in range(2, order + 1):
                    if j - k + 1 < 0:
                        break
                    h = c[k - 1][tuple(w[j - k + 1 : j])]
                    if h:
                        p = (c[k][tuple(w[j - k + 1 : j + 1])] + 4 * p) / (h + 4)
                score += math.log10(p)
            r = got[i]
            assert r.train_tokens == n and r.n_tokens == len(v) and r.n_known == sum(c[1][(x,)] > 0 for x in v)
            assert r.base_score == pytest.approx(base, rel=1e-9, abs=1e-9) and r.score == pytest.approx(score, rel=1e-9, abs=1e-9)


def test_language_on_held_out_rows(spark, small):
    d = spark.read.parquet(f"{small}/documents.parquet")
    got = queries.op6_language_spans(spark, small).join(d.select("doc_id", "lang"), "doc_id").filter("held_out").collect()
    assert np.mean([r.lang == r.lang_pred for r in got]) > 0.97 and all(0 <= r.score <= 1 for r in got)


def test_language_predictions_against_brute_force(spark, tiny):
    """Every prediction and score, from counts to Viterbi, in plain Python."""
    d = spark.read.parquet(f"{tiny}/documents.parquet").collect()
    train = [r for r in d if zlib.crc32(str(r.doc_id).encode()) % 4 != 2 and r.lang is not None and r.text is not None]
    langs = sorted({r.lang for r in train})

    def windows(t):
        b = bytes(32 if c in b" \t\n\v\f\r" else c + 32 if 65 <= c <= 90 else c for c in t.encode())
        p = b"  " + b
        return [((p[i + 2] * 0x9E3779B1 ^ p[i + 1] * 0x85EBCA77 ^ p[i] * 0xC2B2AE3D) & 0xFFFFFFFF) >> 16 for i in range(len(b))]

    def script(c):
        return next((s for s, lo, hi in language.SCRIPT_RANGES if lo <= ord(c) <= hi), "none" if ord(c) < 0xC0 or ord(c) in (0xD7, 0xF7) else "other")

    seen, letters = {k: Counter() for k in langs}, {k: Counter() for k in langs}
    for r in train:
        seen[r.lang].update(windows(r.text))
        letters[r.lang].update(s for s in map(script, r.text) if s != "none")
    size = {k: sum(seen[k].values()) + 0.5 * 65536 for k in langs}
    logs = {c: [math.log((seen[k][c] + 0.5) / size[k]) for k in langs] for c in set().union(*seen.values())}
    none = [math.log(0.5 / size[k]) for k in langs]
    got = {r.doc_id: r for r in queries.op6_language_spans(spark, tiny).collect()}
    sample = [r for r in d if r.text and len(r.text) < 6000][:120]
    for r in sample:
        words, at = list(WORDS.finditer(r.text)), windows(r.text)
        place = [len(r.text[: m.start()].encode()) for m in words] + [len(at)]
        value, back, weight = [0.0] * len(langs), [], []
        for i, m in enumerate(words):
            in_word = Counter(s for s in map(script, m[0]) if s != "none")
            weight.append(sum(in_word.values()))
            gain = [0.0] * len(langs)
            if in_word:
                for c in at[place[i] : place[i + 1]]:
                    row = logs.get(c, none)
                    mean = sum(row) / len(langs)
                    gain = [g + x - mean for g, x in zip(gain, row, strict=True)]
                main = max(in_word, key=lambda s: (in_word[s], -language.SCRIPTS.index(s)))
                may = [letters[k][main] / max(sum(letters[k].values()), 1) >= 0.01 for k in langs]
                gain = [g if ok or not any(may) else -1e3 for g, ok in zip(gain, may, strict=True)]
            best = max(range(len(langs)), key=lambda k: (value[k], -k))
            step = [k if i == 0 or value[k] >= value[best] - 8.0 else best for k in range(len(langs))]
            value = [(value[k] if step[k] == k else value[best] - 8.0) + gain[k] for k in range(len(langs))]
            back.append(step)
        votes, now = [0] * len(langs), max(range(len(langs)), key=lambda k: (value[k], -k))
        for i in range(len(words) - 1, -1, -1):
            votes[now] += weight[i]
            now = back[i][now]
        if not any(c.isalpha() for c in r.text):
            assert (got[r.doc_id].lang_pred, got[r.doc_id].score) == ("und", 0)
        else:
            assert got[r.doc_id].lang_pred == langs[votes.index(max(votes))] and got[r.doc_id].score == pytest.approx(max(votes) / sum(votes))


def test_scripts_of_code_points():
    text = "aß ếạ Ж ω א ع अ ก ქ 한 か 漢 ሀ Ꭰ \u2014 ! 7 \U0001f600 \U00020000 \ua500"
    raw = np.frombuffer(text.encode(), np.uint8)
    names = [*language.SCRIPTS, "none"]
    at = np.flatnonzero((raw & 0xC0) != 0x80)
    got = [names[k] for k in language.scripts_of(raw)[at]]
    want = "latin latin none latin latin none cyrillic none greek none hebrew none arabic none devanagari none thai none georgian none hangul none kana none han none ethiopic none cherokee none none none none none none none none none han none other"
    assert got == want.split() and (np.delete(language.scripts_of(raw), at) == language.NO_SCRIPT).all()


def test_too_many_languages_are_an_error(spark):
    rows = spark.createDataFrame([(i, "text", f"l{i}") for i in range(9)], "doc_id long, text string, lang string")
    with pytest.raises(ValueError, match="languages"):
        language.fit(rows, most_languages=8)


def test_language_spans_and_odd_rows(spark, docs, empty):
    rng = random.Random(1)
    make = lambda alphabet, n: " ".join("".join(rng.choice(alphabet) for _ in range(rng.randint(3, 8))) for _ in range(n))
    train = spark.createDataFrame([(i, make("abcd" if i % 2 else "wxyz", 50), "one" if i % 2 else "two") for i in range(200)] + [(900, "слово дело тело " * 20, "three")], "doc_id long, text string, lang string")
    model = language.fit(train)
    mixed = spark.createDataFrame([(1, make("abcd", 30) + " " + make("wxyz", 10) + " слово дело"), (2, "дело 123")], "doc_id long, text string")
    rows = {r.doc_id: r for r in language.identify(mixed, model, with_spans=True).collect()}
    assert rows[1].lang_pred == "one" and [s.split(":")[0] for s in rows[1].spans.split(",")] == ["one", "two", "three"]
    assert rows[2].lang_pred == "three"
    odd = {r.doc_id: r for r in language.identify(docs, model).collect()}
    assert all(odd[i].lang_pred == "und" and odd[i].score == 0 for i in (1000, 1001, 1002, 1004))
    assert odd[1008].lang_pred in model.languages
    assert language.identify(docs, language.fit(empty)).filter("lang_pred <> 'und'").count() == 0


def test_viterbi_against_all_paths():
    g = np.random.default_rng(0).standard_normal((7, 3)).astype(np.float32)
    got = language._viterbi(g, np.array([0, 4, 4, 7]), 0.7)
    for lo, hi in ((0, 4), (4, 7)):
        worth = lambda p, lo=lo: sum(g[lo + i, k] for i, k in enumerate(p)) - 0.7 * sum(a != b for a, b in zip(p, p[1:], strict=False))
        best = max(itertools.product(range(3), repeat=hi - lo), key=worth)
        assert worth(tuple(got[lo:hi])) == pytest.approx(worth(best))


def test_token_codes_round_trip():
    v = np.array([0, 255, 256, 65535, 65536, 2**24 - 1, 2**24, 2**32 - 1, 7], np.uint32)
    for n in range(len(v) + 1):
        control, data = token_files.pack_codes(v[:n])
        assert len(control) == -(-n // 4) and (token_files.unpack_codes(control, data, n) == v[:n]).all()


def test_token_files_round_trip(docs, plain, monkeypatch):
    lib = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    got = sorted(token_files.token_shard_roundtrip(docs, public_tokenizers.path("byte_bpe_50k.json")).collect(), key=lambda r: r.start)
    at = 0
    want = Counter((i, zlib.crc32(np.array(lib.encode(t, add_special_tokens=False).ids + [0], "<u4").tobytes())) for i, t in plain)
    assert [r.doc_id for r in got] == sorted([r.doc_id for r in got], key=lambda x: (x is not None, x or 0))
    for r in got:
        assert r.start == at
        at += r.n_tokens
    assert Counter((r.doc_id, r.ids_crc32) for r in got) == want


def components_of(sets, percent):
    label = {i: i for i in sets}

    def top(i):
        while label[i] != i:
            i = label[i]
        return i

    for a, b in itertools.combinations(sets, 2):
        if sets[a] and sets[b]:
            common = len(sets[a] & sets[b])
            if 100 * common >= percent * (len(sets[a]) + len(sets[b]) - common) and top(a) != top(b):
                x, y = sorted((top(a), top(b)))
                label[y] = x
    return {i: top(i) for i in sets}


def shingle_set(t, width):
    w = WORDS.findall(lower(t))
    return frozenset(tuple(w[i : i + width]) for i in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)] if w else [])


@pytest.mark.parametrize(("width", "percent"), [(3, 85), (5, 80), (1, 60)])
def test_near_duplicates_against_brute_force(docs, plain, width, percent):
    got = near_duplicates.near_duplicates(docs, width=width, percent=percent).filter("doc_id is not null").collect()
    sets = {i: shingle_set(t, width) for i, t in plain if i is not None}
    want = components_of(sets, percent)
    assert len(got) == len(plain) - 1
    for r in got:
        assert (r.n_shingles, r.component_id, r.kept) == (len(sets[r.doc_id]), want[r.doc_id], want[r.doc_id] == r.doc_id)


def test_near_duplicates_with_null_and_shared_ids(spark):
    a, b, c, d, e = (" ".join(f"{x}{i}" for i in range(60)) for x in "abcde")
    rows = [(None, a), (None, b), (None, b), (7, c), (7, d), (8, d + " more"), (3, e), (9, e + " more"), (9, a + " more"), (5, ""), (5, None), (None, " ")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = Counter((r.doc_id, r.text) for r in near_duplicates.without_near_duplicates(df).collect())
    want = Counter([(9, a + " more"), (None, b), (7, c), (7, d), (3, e), (5, ""), (5, None), (None, " ")])
    assert got == want
    found = Counter((r.doc_id, r.component_id, r.kept) for r in near_duplicates.near_duplicates(df).filter("n_shingles > 0").collect())
    assert found == Counter([(None, 9, False), (None, None, True), (None, None, True), (7, 7, True), (7, 7, True), (8, 7, False), (3, 3, True), (9, 3, False), (9, 9, True)])


def test_bands_split_over_components_are_compared(spark):
    """Many documents that share bands with a pivot they aren't like: links among them must be found across blocks."""
    rnd = random.Random(5)
    base = [f"w{i}" for i in range(120)]
    rows = []
    for i in range(300):
        w = list(base)
        for _ in range(rnd.randint(2, 26)):
            w[rnd.randrange(len(w))] = f"r{rnd.randrange(40)}"
        rows.append((i, " ".join(w)))
    old, near_duplicates.BLOCK = near_duplicates.BLOCK, 32
    try:
        got = near_duplicates.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), width=1, percent=85).collect()
    finally:
        near_duplicates.BLOCK = old
    want = components_of({i: shingle_set(t, 1) for i, t in rows}, 85)
    assert {r.doc_id: r.component_id for r in got} == want


def test_super_minhash_has_lower_variance():
    rng = np.random.default_rng(0)
    gaps = {}
    for n in (20, 100):
        err = []
        for _ in range(300):
            u = rng.integers(0, 2**63, 2 * n).astype(np.uint64)
            k = n // 2
            s = near_duplicates.super_minhash(np.concatenate([u[:n], u[n - k : 2 * n - k]]), np.array([0, n, 2 * n]), 144)
            err.append((s[0] == s[1]).mean() - k / (2 * n - k))
        j = k / (2 * n - k)
        gaps[n] = np.var(err) / (j * (1 - j) / 144)
        assert abs(np.mean(err)) < 0.01
    assert gaps[20] < 0.8 and gaps[100] < 1.0


def test_components_of_chains(spark):
    edges = [(i, i + 1) for i in range(100, 300)] + [(5, 900), (900, 7), (7, 7)] + [(2000, i) for i in range(2001, 2100)]
    got = {r.node: r.component for r in components.connected_components(spark.createDataFrame(edges, "a long, b long").repartition(7)).collect()}
    assert all(got[i] == 100 for i in range(100, 301)) and got[900] == got[7] == got[5] == 5 and got[2050] == 2000


def plain_canonical(t):
    t = lower(t)
    t = "\n".join(" " if re.match(r"[^a-z0-9\n]*(copyright|\(c\)|©)", x) else x for x in t.split("\n"))
    for a, b in licences.SPELLINGS:
        t = t.replace(a, b)
    return re.sub("[^a-z0-9]+", " ", t).strip()


@pytest.mark.parametrize("most_known", [licences.MOST_KNOWN, 0])
def test_licences_against_brute_force(spark, docs, most_known):
    rnd = random.Random(4)
    british = [("license", "licence"), ("License", "Licence"), ("acknowledgment", "acknowledgement"), ("organization", "organisation"), ("authorization", "authorisation"), ("and", "&")]
    rows = [(i, r.text) for i, r in enumerate(docs.select("text").collect())]
    for licence, text in licences.KNOWN:
        for style in range(3):
            t = text.upper() if style == 1 else text
            if style == 2:
                for a, b in british[:3]:
                    t = t.replace(a, b)
            t = re.sub(" ", lambda m: rnd.choice([" ", "  ", "\t", " - "]) if style else " ", t)
            rows.append((len(rows), f"Copyright 20{style}0 the holder\n{t}\n"))
            rows.append((len(rows), f"words before\n{t}\nand after\n{t}"))
    rows.append((len(rows), "x " * 1_500_000 + "\nAll rights reserved."))
    got = {r.doc_id: r for r in licences.scan(spark.createDataFrame(rows, "doc_id long, text string"), most_known=most_known).collect()}
    known = {}
    for licence, text in sorted(licences.KNOWN, reverse=True):
        known[plain_canonical(text)] = licence
    assert len(got) == len(rows) and len({i for i, _ in licences.KNOWN if len(_) > 150}) >= 15
    for i, t in rows:
        whole = known.get(plain_canonical(t)) if t is not None else None
        lines = [known[c] for c in map(plain_canonical, (t or "").split("\n")) if c in known]
        assert (got[i].whole_licence, got[i].n_licence_lines, got[i].licences) == (whole, len(lines), ",".join(sorted({*lines, *([whole] if whole else [])}))), t[:200]
    assert sum(r.whole_licence is not None for r in got.values()) == 3 * len(licences.KNOWN)


def test_licences_edges(spark, docs):
    mit = next(t for i, t in licences.KNOWN if i == "MIT" and len(t) > 100)
    rows = [(1, "Copyright (c) 2020 Somebody\n" + mit.upper().replace(",", " ,").replace(".", ".\n")), (2, "text\nReleased under the MIT licence!\nmore\nLicensed under CC BY 4.0"), (3, None), (4, "***"), (5, "nothing"), (2, "same id")]
    got = {r.doc_id: r for r in licences.scan(spark.createDataFrame(rows[:5], "doc_id long, text string")).collect()}
    assert got[1].whole_licence == "MIT" and got[2].whole_licence is None and got[2].licences == "CC-BY-4.0,MIT" and got[2].n_licence_lines == 2
    assert got[3].digest is None and all(got[i].licences == "" for i in (3, 4, 5))
    assert licences.scan(spark.createDataFrame(rows, "doc_id long, text string")).count() == 6 and licences.scan(docs, known=[]).count() == docs.count()


def test_licence_lines_are_normalised_before_any_filter(spark):
    lines = ["All  rights reserved", "All rights\treserved", "All Rights-Reserved", "All rights, reserved.", "all rights" + " " * 9000 + "reserved\r", "\u2028All * rights -- reserved"]
    rows = [(i, f"first\n{x}\nlast") for i, x in enumerate(lines)] + [(90, "\n".join(lines)), (91, "Copyright 2020 x\r\nAll\nrights reserved"), (92, "(c) x all rights reserved\n")]
    got = {r.doc_id: r for r in licences.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all(got[i].n_licence_lines == 1 and got[i].licences == "proprietary" for i in range(len(lines))) and got[90].n_licence_lines == len(lines)
    assert got[91].n_licence_lines == 0 and got[91].whole_licence == "proprietary" and got[92].licences == ""


def plain_resize(g, height, width):
    fine = np.repeat(np.repeat(g.astype(float), height, 0), width, 1)
    return fine.reshape(height, len(g), width, g.shape[1]).mean((1, 3))


def test_media_round_trip(docs, plain):
    got = media.media_roundtrip(docs).collect()
    want = Counter()
    for i, t in plain:
        raw = t.encode()
        p = raw + bytes(-len(raw) % 64 if raw else 64)
        grid = np.frombuffer(p, np.uint8).reshape(-1, 64)
        if len(grid) > 400:
            continue
        stored = b"P5\n64 %d\n255\n" % len(grid) + p if len(grid) % 2 == 0 else media.encode_bmp(grid)
        small = plain_resize(grid, 8, 9)
        bits = "".join("1" if x else "0" for x in (small[:, 1:] > small[:, :-1] + 1e-9).ravel())
        tile = np.clip(np.rint(plain_resize(grid, 16, 16).round(9)), 0, 255).astype(np.uint8)
        want[i, len(raw), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]), len(stored), hashlib.sha256(stored).hexdigest(), f"{int(bits, 2):016x}", zlib.crc32(tile)] += 1
    assert len(got) == len(plain) and Counter(tuple(r) for r in got if r.payload_bytes <= 400 * 64) == want


def test_image_formats():
    rng = np.random.default_rng(0)
    g = rng.integers(0, 256, (5, 7)).astype(np.uint8)
    rgb = rng.integers(0, 256, (3, 5, 3)).astype(np.uint8)
    assert (media.decode_image(media.encode_pgm(g)) == g).all() and (media.decode_image(media.encode_bmp(g)) == g).all()
    assert (media.decode_image(b"P6 # note\n5 3 255\n" + rgb.tobytes()) == rgb).all()
    assert (media.decode_image(b"P2\n2 2\n9\n1 2\n3 4") == [[1, 2], [3, 4]]).all()
    assert (media.decode_image(b"P1\n3 1\n101") == [[0, 255, 0]]).all() and (media.decode_image(b"P4\n3 1\n\xa0") == [[0, 255, 0]]).all()
    bgr = b"".join(row[:, ::-1].tobytes() + b"\0" for row in rgb[::-1])
    head = b"BM" + (54 + len(bgr)).to_bytes(4, "little") + bytes(4) + (54).to_bytes(4, "little") + (40).to_bytes(4, "little") + (5).to_bytes(4, "little") + (3).to_bytes(4, "little") + (1).to_bytes(2, "little") + (24).to_bytes(2, "little") + bytes(24)
    assert (media.decode_image(head + bgr) == rgb).all()
    with pytest.raises(ValueError):
        media.decode_image(b"GIF89a")


def test_area_resize_against_brute_force(monkeypatch):
    g = np.random.default_rng(0).integers(0, 256, (6, 9)).astype(float)
    for strip in (1, 20, 1 << 18):
        monkeypatch.setattr(media, "STRIP", strip)
        assert np.allclose(media.area_resize(g, 4, 5), plain_resize(g, 4, 5)) and np.allclose(media.area_resize(g, 6, 9), g)
        assert np.allclose(media.area_resize(g, 13, 20), plain_resize(g, 13, 20)) and np.allclose(media.area_resize(g[:1], 3, 2), plain_resize(g[:1], 3, 2))


def test_tiles_keep_every_row(spark, docs, monkeypatch):
    monkeypatch.setattr(media, "TILES", 7)
    images = media.text_media(docs)
    bad = spark.createDataFrame([(1, 3, b"GIF89a"), (2, None, None), (3, 1, b"P5\n9 9\n255\nx"), (4, 1, b"BM")], "doc_id long, n_bytes long, media binary")
    index = media.write_tiles(images.union(bad))
    rows = index.collect()
    assert len(rows) == docs.count() + 4 and sum(r.path is None and r.row is None and r.feature is None for r in rows) == 4
    assert len({(r.path, r.row) for r in rows}) == docs.count() + 1 and max(r.row or 0 for r in rows) < 7
    one = next(r for r in rows if r.path)
    got = np.load(one.path.removeprefix("file://"))[one.row]
    assert got.shape == (16, 16) and got.dtype == np.uint8
    assert sum(r.tile_crc32 is None for r in media.read_tiles(index).collect()) == 4


def test_empty_tables(spark, empty):
    t = public_tokenizers.path("byte_bpe_50k.json")
    for df in (mixing.mix(empty), mixing.mixed_documents(empty), personal.detect(empty), personal.sanitise(empty), packing.pack(empty, t), ngram.score_documents(empty, F.lit(False)), language.identify(empty, language.fit(empty)), token_files.token_shard_roundtrip(empty, t), near_duplicates.near_duplicates(empty), near_duplicates.without_near_duplicates(empty), licences.scan(empty), media.media_roundtrip(empty), vector_duplicates.vector_duplicates(spark.createDataFrame([], "vec_id long, embedding array<float>"))):
        assert df.count() == 0


def test_pipeline_stages(spark, docs, tiny):
    now = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, now, tiny)
        assert out.columns == docs.columns, name
        now = spark.createDataFrame(out.collect(), docs.schema)
        ids = {r.doc_id for r in now.select("doc_id").collect()}
        if name == "language":
            assert not ids & {1000, 1001, 1002, 1004} and 1008 in ids
        if name == "near duplicates":
            assert now.filter("doc_id = 1006").count() == 1
    packed = corpus_pipeline.STAGES[-1][1](spark, now, tiny)
    assert Counter(r.doc_id for r in packed.filter("piece = 0").collect()) == Counter(r.doc_id for r in now.collect())
    assert corpus_pipeline.run(spark, tiny).count() > 0


def test_pipeline_stages_against_brute_force(spark, tiny):
    """What each stage keeps and makes of the whole table, in plain Python."""
    now = spark.read.parquet(f"{tiny}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    before = {r.doc_id: r for r in now.collect()}

    out = stages["language"](spark, now, tiny)
    got = {r.doc_id: r for r in out.collect()}
    assert set(got) == {i for i, r in before.items() if any(c.isalpha() for c in r.text or "")}
    known = {r.doc_id: r.lang_pred for r in language.identify(now, language.fit(now)).collect()}
    assert all(r.lang == known[i] and r.text == before[i].text for i, r in got.items())

    now, before = spark.createDataFrame(list(got.values()), now.schema), got
    got = {r.doc_id: r for r in stages["near duplicates"](spark, now, tiny).collect()}
    want = components_of({i: shingle_set(r.text, 5) for i, r in before.items()}, 80)
    assert set(got) == {i for i, c in want.items() if i == c} and all(got[i] == before[i] for i in got)

    now, before = spark.createDataFrame(list(got.values()), now.schema), got
    found = {r.doc_id: r for r in personal.find(now).collect()}
    got = {r.doc_id: r for r in stages["personal data"](spark, now, tiny).collect()}
    assert set(got) == set(before)
    for i, r in before.items():
        marks, at, safe = set(found[i]["_marks"] or []), 0, ""
        spans = [(int(a), int(b), k) for k, a, b in (x.split(":") for x in base_spans(r.text).split(",") if x)]
        base = list(spans)
        secrets = [(m.start(), m.end(), "secret") for m in re.finditer("[A-Za-z0-9+/_-]{20,}", r.text) if re.search("[0-9]", m[0]) and re.search("[A-Za-z]", m[0]) and not any(a < m.end() and b > m.start() for a, b, _ in base)]
        spans += secrets
        spans += [(m.start(), m.end(), m[0].lower()) for m in re.finditer(r"[^\W\d_]{3,}", r.text) if m[0].lower() in marks and not any(a < m.end() and b > m.start() for a, b, _ in base + secrets)]
        rank = {k: n for n, k in enumerate(personal.KINDS)}
        for a, b, kind in sorted(spans, key=lambda x: (x[0], rank.get(x[2], 4))):
            if a >= at:
                safe += r.text[at:a] + (f"[{kind.upper()}]" if kind in rank else "[...]" if kind[:3] + "*" in marks else kind[:3] + "*")
                at = b
            at = max(at, b)
        assert got[i].text == safe + r.text[at:], i

    now = spark.createDataFrame(list(got.values()), now.schema)
    times = {r.doc_id: r.epochs for r in mixing.mix(now).collect()}
    mixed = stages["source mix"](spark, now, tiny).collect()
    assert Counter(r.doc_id for r in mixed) == Counter({i: n for i, n in times.items() if n}) and all(r == got[r.doc_id] for r in mixed)

    lib = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    want = Counter()
    for r in mixed:
        ids = lib.encode(r.text, add_special_tokens=False).ids + [0]
        for p, at in enumerate(range(0, len(ids), 2048)):
            want[r.doc_id, p, at, zlib.crc32(np.array(ids[at : at + 2048], "<u4").tobytes())] += 1
    packed = stages["packing"](spark, spark.createDataFrame(mixed, now.schema), tiny).collect()
    assert Counter((r.doc_id, r.piece, r.start, r.ids_crc32) for r in packed) == want
    assert len({r.sequence_id for r in packed}) <= math.ceil(sum(r.length for r in packed) / 2048) + 1


def test_pipeline_on_an_empty_table_and_on_one_text_of_megabytes(spark, empty, tmp_path):
    rnd = random.Random(2)
    long = " ".join("".join(rnd.choice("abcdefgh") for _ in range(rnd.randint(2, 9))) for _ in range(600_000))
    for name, df in (("none", empty), ("long", spark.createDataFrame([(1, long, "en", "a", len(long)), (2, None, "en", None, None)], SCHEMA))):
        (tmp_path / name).mkdir()
        df.write.parquet(str(tmp_path / name / "documents.parquet"))
        got = corpus_pipeline.run(spark, str(tmp_path / name)).select("doc_id", "length").collect()
        assert (not got) if name == "none" else {r.doc_id for r in got} == {1} and sum(r.length for r in got) > 600_000


def test_vectors_repeated_null_ids_clashes_and_ties(spark):
    """Rows count one by one, also equal ones; a null vec_id links but names nothing; a cosine of the threshold links."""
    a, b = [1.0, 0.0, 0.0], [0.95, math.sqrt(1 - 0.95**2), 0.0]
    c = [0.95, 0.0, -math.sqrt(1 - 0.9499999**2)]  # just below 0.95 from a
    rows = [(5, a), (5, a), (3, [2.0, 0.0, 0.0]), (None, [0.0, 1.0, 0.0]), (None, [0.0, 3.0, 0.0]), (9, c)]
    clash = {x: F.lit("clash") for x in ("dim", "rep", "unit", "n", "line", "cell", "_node", "node", "component")}
    got = Counter((r.vec_id, r.n_links, r.component_id, r.kept) for r in vector_duplicates.vector_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumns(clash)).collect())
    assert got == Counter({(5, 2, 3, False): 2, (3, 2, 3, True): 1, (None, 1, None, True): 2, (9, 0, 9, True): 1})
    tie = vector_duplicates.vector_duplicates(spark.createDataFrame([(1, [1.0, 0.0]), (2, [19.0, math.sqrt(39.0)])], "vec_id long, embedding array<double>")).collect()
    assert all(r.n_links == (19 / 20 >= 0.95) for r in tie)


def test_vectors_near_the_threshold_are_found(spark):
    """Recall on planted pairs of cosine 0.95 to 0.97 among many vectors."""
    rng = np.random.default_rng(8)
    n, dim, planted = 12_000, 64, 1500
    x = rng.standard_normal((n, dim))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    y = rng.standard_normal((planted, dim))
    y -= (y * x[:planted]).sum(1, keepdims=True) * x[:planted]
    y /= np.linalg.norm(y, axis=1, keepdims=True)
    cos = rng.uniform(0.9501, 0.97, planted)[:, None]
    both = np.vstack([x, cos * x[:planted] + np.sqrt(1 - cos**2) * y])
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(both)], "vec_id long, embedding array<double>")
    got = {r.vec_id: r.n_links for r in vector_duplicates.vector_duplicates(rows).filter(f"vec_id >= {n}").collect()}
    assert np.mean([got[n + i] >= 1 for i in range(planted)]) > 0.999

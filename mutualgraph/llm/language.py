"""Language identification: script ranges narrow candidates, then Viterbi with a switching penalty labels spans of words."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import join_small, ship, store
from .words import LOWER, SPACE, flatten, released, slices, spans

CELLS = 1 << 16

#: Code points by script (fixed values: each row is script, first, last), ascending.
SCRIPT_RANGES = [
    ("latin", 0x41, 0x5A), ("latin", 0x61, 0x7A), ("latin", 0xAA, 0xAA), ("latin", 0xBA, 0xBA), ("latin", 0xC0, 0xD6), ("latin", 0xD8, 0xF6), ("latin", 0xF8, 0x2B8),
    ("greek", 0x370, 0x3FF), ("cyrillic", 0x400, 0x52F), ("armenian", 0x531, 0x587), ("hebrew", 0x5D0, 0x5F4), ("arabic", 0x620, 0x6FF), ("syriac", 0x700, 0x74F),
    ("arabic", 0x750, 0x77F), ("thaana", 0x780, 0x7BF), ("arabic", 0x8A0, 0x8FF), ("devanagari", 0x900, 0x97F), ("bengali", 0x980, 0x9FF), ("gurmukhi", 0xA00, 0xA7F),
    ("gujarati", 0xA80, 0xAFF), ("oriya", 0xB00, 0xB7F), ("tamil", 0xB80, 0xBFF), ("telugu", 0xC00, 0xC7F), ("kannada", 0xC80, 0xCFF), ("malayalam", 0xD00, 0xD7F),
    ("sinhala", 0xD80, 0xDFF), ("thai", 0xE00, 0xE7F), ("lao", 0xE80, 0xEFF), ("tibetan", 0xF00, 0xFFF), ("myanmar", 0x1000, 0x109F), ("georgian", 0x10A0, 0x10FF),
    ("hangul", 0x1100, 0x11FF), ("ethiopic", 0x1200, 0x139F), ("cherokee", 0x13A0, 0x13FF), ("khmer", 0x1780, 0x17FF), ("mongolian", 0x1800, 0x18AF),
    ("latin", 0x1D00, 0x1DBF), ("latin", 0x1E00, 0x1EFF), ("greek", 0x1F00, 0x1FFF), ("none", 0x2000, 0x2BFF), ("latin", 0x2C60, 0x2C7F), ("georgian", 0x2D00, 0x2D2F),
    ("ethiopic", 0x2D80, 0x2DDF), ("cyrillic", 0x2DE0, 0x2DFF), ("han", 0x2E80, 0x2FDF), ("none", 0x3000, 0x3004), ("han", 0x3005, 0x3007), ("none", 0x3008, 0x303F), ("kana", 0x3040, 0x30FF),
    ("bopomofo", 0x3100, 0x312F), ("hangul", 0x3130, 0x318F), ("kana", 0x31F0, 0x31FF), ("none", 0x3200, 0x33FF), ("han", 0x3400, 0x4DBF), ("han", 0x4E00, 0x9FFF),
    ("cyrillic", 0xA640, 0xA69F), ("latin", 0xA720, 0xA7FF), ("latin", 0xAB30, 0xAB6F), ("cherokee", 0xAB70, 0xABBF), ("hangul", 0xAC00, 0xD7FF), ("none", 0xE000, 0xF8FF),
    ("han", 0xF900, 0xFAFF), ("latin", 0xFB00, 0xFB06), ("armenian", 0xFB13, 0xFB17), ("hebrew", 0xFB1D, 0xFB4F), ("arabic", 0xFB50, 0xFDFF), ("none", 0xFE00, 0xFE6F),
    ("arabic", 0xFE70, 0xFEFE), ("none", 0xFEFF, 0xFF20), ("latin", 0xFF21, 0xFF3A), ("latin", 0xFF41, 0xFF5A), ("kana", 0xFF66, 0xFF9F), ("hangul", 0xFFA0, 0xFFDC), ("none", 0xFFE0, 0xFFFF),
    ("none", 0x1F000, 0x1FAFF), ("han", 0x20000, 0x323AF), ("none", 0xE0000, 0x10FFFF),
]
#: Scripts, then "other" (letters of none of them).
SCRIPTS = [*dict.fromkeys(s for s, _, _ in SCRIPT_RANGES if s != "none"), "other"]
NO_SCRIPT = len(SCRIPTS)
_FIRST = np.array([lo for _, lo, _ in SCRIPT_RANGES])
_LAST = np.array([hi for _, _, hi in SCRIPT_RANGES])
_CODE = np.array([NO_SCRIPT if s == "none" else SCRIPTS.index(s) for s, _, _ in SCRIPT_RANGES], np.uint8)


def code_scripts(points: np.ndarray) -> np.ndarray:
    """Script of each code point; below 0xC0 what isn't listed has none, above it is "other"."""
    at = np.maximum(np.searchsorted(_FIRST, points, "right") - 1, 0)
    listed = (points >= _FIRST[at]) & (points <= _LAST[at])
    other = np.where((points < 0xC0) | (points == 0xD7) | (points == 0xF7), NO_SCRIPT, NO_SCRIPT - 1)
    return np.where(listed, _CODE[at], other).astype(np.uint8)


_ASCII = np.concatenate([code_scripts(np.arange(128)), np.full(128, NO_SCRIPT, np.uint8)])


def scripts_of(raw: np.ndarray) -> np.ndarray:
    """Script of the character that begins at each byte of UTF-8; bytes within a character have none."""
    out = _ASCII[raw]
    at = np.flatnonzero(raw >= 0xC2)
    if len(at):
        lead = raw[at].astype(np.int64)
        more = 1 + (lead >= 0xE0) + (lead >= 0xF0)
        point = lead & (0x3F >> more)
        for k in (1, 2, 3):
            here = more >= k
            point[here] = point[here] << 6 | raw[np.minimum(at[here] + k, len(raw) - 1)] & 0x3F
        out[at] = code_scripts(point)
    return out


@dataclass
class Model:
    languages: list[str]
    gain: np.ndarray  # CELLS x languages: log probability of a three-byte window, less its mean over languages
    allowed: np.ndarray  # scripts + 1 x languages


def _cells(raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Cell of the three bytes that end at each byte; white space and text edges are one byte value."""
    b = np.where(SPACE[raw], np.uint8(32), LOWER[raw]).astype(np.uint32)
    one, two = np.empty_like(b), np.empty_like(b)
    one[1:], two[2:] = b[:-1], b[:-2]
    one[:1] = 32
    two[:2] = 32
    starts = offsets[:-1][offsets[:-1] < len(b)]
    one[starts] = 32
    two[starts] = 32
    later = starts[starts + 1 < len(b)] + 1
    two[later] = 32
    return ((b * np.uint32(0x9E3779B1) ^ one * np.uint32(0x85EBCA77) ^ two * np.uint32(0xC2B2AE3D)) >> np.uint32(16)) & np.uint32(CELLS - 1)


def fit(labelled: DataFrame, rows_per_language: int = 800, most_languages: int = 2000, smoothing: float = 0.5) -> Model:
    """From labelled rows (doc_id, text, lang); rows without text or language teach nothing, repeated rows as often as they
    stand, an empty table gives a model without languages.

    Of each language about `rows_per_language` rows, chosen by a hash of doc_id below a share of its count, are learned
    from, whole: that sample is the bound. Windows are counted where the rows are; the driver gets CELLS numbers a language
    at most. More than `most_languages` raise an error: the model takes 256 KB each.
    """
    ship(labelled.sparkSession)
    rows = labelled.select(F.xxhash64("doc_id", F.lit(99)).alias("_draw"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang")).filter("lang is not null and text is not null")
    counts = store(rows.groupBy("lang").agg(F.count("*").alias("_n")), "languages")
    languages = [r["lang"] for r in counts.select("lang").limit(most_languages + 1).collect()]
    if len(languages) > most_languages:
        raise ValueError(f"more than {most_languages} languages: is lang a label?")
    languages.sort()
    draw = F.shiftrightunsigned("_draw", 11) / F.lit(float(1 << 53))
    sample = join_small(rows, counts, "lang", "inner", len(languages)).filter(draw < float(rows_per_language) / F.col("_n")).select("lang", "text")

    def count(batches):
        for b in batches:
            for part in slices(b, "text"):
                names = np.array(part.column("lang").to_pylist())
                for lang in np.unique(names).tolist():
                    raw, offs = flatten(part.column("text").filter(pa.array(names == lang)))
                    seen = np.concatenate([np.bincount(_cells(raw, offs), minlength=CELLS), np.bincount(scripts_of(raw), minlength=NO_SCRIPT + 1)])
                    at = np.flatnonzero(seen)
                    yield pa.RecordBatch.from_pydict({"lang": pa.array([lang] * len(at), pa.string()), "cell": pa.array(at, pa.int32()), "n": pa.array(seen[at], pa.int64())})

    got = sample.mapInArrow(released(count), "lang string, cell int, n long").groupBy("lang", "cell").agg(F.sum("n").alias("n")).toArrow()
    seen = np.zeros((CELLS + NO_SCRIPT + 1, len(languages)))
    if got.num_rows:
        place = {lang: k for k, lang in enumerate(languages)}
        seen[got.column("cell").to_numpy(), [place[x] for x in got.column("lang").to_pylist()]] = got.column("n").to_numpy()
    cells, scripts = seen[:CELLS], seen[CELLS:]
    logs = np.log((cells + smoothing) / (cells.sum(0) + smoothing * CELLS))
    letters = np.maximum(scripts[:-1].sum(0), 1)
    allowed = scripts / letters >= 0.01
    allowed[-1] = True
    return Model(languages, (logs - logs.mean(1, keepdims=True)).astype(np.float32) if languages else np.zeros((CELLS, 0), np.float32), allowed)


def label_words(model: Model, column, penalty: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Language index of each word, its letters (weight), and each row's first word index."""
    raw, offs = flatten(column)
    starts, _, first = spans(raw, offs)
    n, kinds = len(starts), len(model.languages)
    if n == 0:
        return np.zeros(0, np.int64), np.zeros(0), first
    cells = _cells(raw, offs)
    gains = np.empty((n, kinds), np.float32)
    for k in range(kinds):
        gains[:, k] = np.add.reduceat(model.gain[cells, k], starts)  # a word and the white space after it
    script = scripts_of(raw)
    letters, most, main = np.zeros(n, np.int64), np.zeros(n, np.int32), np.full(n, NO_SCRIPT)
    for s in np.flatnonzero(np.bincount(script, minlength=NO_SCRIPT + 1)[:NO_SCRIPT]).tolist():  # scripts that occur
        has = np.add.reduceat(script == s, starts, dtype=np.int32)
        letters += has
        main[has > most] = s
        most = np.maximum(most, has)
    may = model.allowed[main]
    may |= ~may.any(1, keepdims=True)
    gains[~may] = -1e3
    gains[letters == 0] = 0  # digits and marks follow their neighbours
    return _viterbi(gains, first, penalty), letters, first


def _viterbi(gains: np.ndarray, first: np.ndarray, penalty: float) -> np.ndarray:
    """All rows in step: at each word, stay in a language or pay the penalty and come from the best one."""
    n, kinds = gains.shape
    length = np.diff(first)
    order = np.argsort(-length, kind="stable")
    head, length = first[:-1][order], length[order]
    active = np.searchsorted(-length, -np.arange(length[0] if len(length) else 0), "left")  # rows longer than each step
    back = np.zeros((n, kinds), np.uint16)
    own = np.arange(kinds, dtype=np.uint16)
    value = np.zeros((len(order), kinds))
    for t, m in enumerate(active.tolist()):
        at = head[:m] + t
        v = value[:m]
        best = v.argmax(1)
        switch = v[np.arange(m), best] - penalty
        stay = v >= switch[:, None]
        back[at] = np.where(stay, own, best[:, None].astype(np.uint16)) if t else own
        value[:m] = (np.where(stay, v, switch[:, None]) if t else v) + gains[at]
    out = np.zeros(n, np.int64)
    now = value.argmax(1)
    for t in range(len(active) - 1, -1, -1):
        m = active[t]
        at = head[:m] + t
        out[at] = now[:m]
        now[:m] = back[at, now[:m]]
    return out


def identify(docs: DataFrame, model: Model, penalty: float = 8.0, with_spans: bool = False) -> DataFrame:
    """docs with lang_pred, score and n_spans (and spans: "language:first word:end word", comma-joined).

    lang_pred is the language with most letters in its spans, score its share of letters; ties go to the language first
    in order. Null text, or text without any letter (Unicode category L), gives "und" and 0. Columns of docs with these
    names are replaced, others kept whatever their names; repeated rows and null doc_ids are rows as any; an empty table
    gives an empty one. Any text length; nothing is cut.
    """
    spark = docs.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(model)  # 65,536 cells a language, whatever the data's size
    names = ["lang_pred", "score", "n_spans"] + ["spans"] * with_spans
    base = docs.drop(*names).withColumn("_mg_letter", F.coalesce(F.col("text").rlike(r"\p{L}"), F.lit(False)))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in base.drop("_mg_letter").schema.fields) + ", lang_pred string, score double, n_spans long" + ", spans string" * with_spans

    def run(batches):
        known = shared.value
        kinds = len(known.languages)
        for b in batches:
            for part in slices(b, "text", 3 << 20):
                rows = part.num_rows
                letter = part.column("_mg_letter").to_numpy(zero_copy_only=False)
                if kinds:
                    label, weight, first = label_words(known, part.column("text"), penalty)
                    row = np.repeat(np.arange(rows), np.diff(first))
                    votes = np.bincount(row * kinds + label, weights=weight, minlength=rows * kinds).reshape(rows, kinds)
                    top, total = votes.argmax(1), votes.sum(1)
                    score = np.where(letter & (total > 0), votes.max(1) / np.maximum(total, 1), 0.0)
                    new = np.ones(len(label), bool)
                    new[1:] = (label[1:] != label[:-1]) | (row[1:] != row[:-1])
                    count = np.bincount(row[new], minlength=rows)
                    pred = [known.languages[k] if ok else "und" for k, ok in zip(top.tolist(), letter.tolist(), strict=True)]
                else:
                    pred, score, count = ["und"] * rows, np.zeros(rows), np.zeros(rows, np.int64)
                cols = [part.column(i) for i in range(part.num_columns - 1)] + [pa.array(pred, pa.string()), pa.array(score, pa.float64()), pa.array(count, pa.int64())]
                if with_spans:
                    texts = [[] for _ in range(rows)]
                    if kinds:
                        at = np.flatnonzero(new)
                        stop = np.append(at[1:], len(label))
                        for i, j in zip(at.tolist(), stop.tolist(), strict=True):
                            r = int(row[i])
                            texts[r].append(f"{known.languages[label[i]]}:{i - first[r]}:{j - first[r]}")
                    cols.append(pa.array([",".join(x) for x in texts], pa.string()))
                yield pa.RecordBatch.from_arrays(cols, names=[f.name for f in part.schema][:-1] + names)

    return base.mapInArrow(released(run), schema)


def held_out(doc_id, parts: int = 4, part: int = 2):
    """Whether crc32 of doc_id as text leaves `part` when divided by `parts`; a null doc_id isn't held out."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % parts == part, F.lit(False))

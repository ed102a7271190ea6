"""Language-model scoring by a weighted backoff automaton over smoothed n-grams of the whole corpus.

Smoothing: P1(w) = (c(w) + 0.1) / (N + 0.1 (V + 1)); P(w | h) = (c(h w) + m P(w | shorter h)) / (c(h) + m), a Dirichlet
prior of mass m on the shorter context. As an automaton: a state is a context that was seen, an arc of weight
log P(w | h) leaves it for each word seen after it, and where there is none its failure arc, of weight
log m / (c(h) + m), leads to the shorter context; the root has an arc for every word.

Corpus counts stay distributed. Documents fall into buckets of bounded text; a bucket sends each of its distinct n-grams
once, as sorted 64-bit hashes cut into shards by range; a shard adds the buckets' counts and answers each bucket in the
order it asked; a bucket then holds just the part of the automaton that its own documents can reach.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship, store
from .words import mix64, released, word_hashes

END, START = np.uint64(0x5851F42D4C957F2D), np.uint64(0x14057B7EF767814F)
_STEP = np.uint64(0xD1342543DE82EF95)


def tokens(column) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of each row's words and its end token, and row offsets."""
    words, first = word_hashes(column)
    rows = len(first) - 1
    offs = first + np.arange(rows + 1)
    out = np.full(len(words) + rows, END, np.uint64)
    keep = np.ones(len(out), bool)
    keep[offs[1:] - 1] = False
    out[keep] = words
    return out, offs


def grams(toks: np.ndarray, offs: np.ndarray, order: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each k up to order: hashes of the k-grams that end at each token, and where there is one. A row begins with
    one start symbol, which only longer grams hold."""
    place = np.arange(len(toks)) - np.repeat(offs[:-1], np.diff(offs))
    out = []
    for k in range(1, order + 1):
        h = np.full(len(toks), k, np.uint64)
        for back in range(k - 1, -1, -1):
            part = np.full(len(toks), START, np.uint64)
            if back < len(toks):
                part[back:] = toks[: len(toks) - back]
            part[place < back] = START
            h = mix64(h * _STEP + part)
        out.append((h, place >= k - 2))
    return out


def distinct(h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct values, and each value's place among them."""
    code, found = pd.factorize(h)
    order = np.argsort(found, kind="stable")
    rank = np.empty(len(order), np.int64)
    rank[order] = np.arange(len(order))
    return found[order], rank[code]


class Automaton:
    """The states and arcs that some rows reach: for each token and context depth, its arc and the failure arc beside it."""

    def __init__(self, counts: list[np.ndarray], histories: list[np.ndarray], exists: list[np.ndarray], total: int, kinds: int, mass: float):
        self.known = counts[0] > 0
        lower = (counts[0] + 0.1) / (total + 0.1 * (kinds + 1))
        self.root = np.log10(lower)
        self.arc, self.fail, self.has_state, self.has_arc = [], [], [], []
        for count, history, real in zip(counts[1:], histories, exists, strict=True):
            seen = real & (history > 0)
            full = (count + mass * lower) / (history + mass)
            lower = np.where(seen, full, lower)
            self.arc.append(np.log10(lower))
            self.fail.append(np.log10(mass / (history + mass)))
            self.has_state.append(seen)
            self.has_arc.append(seen & (count > 0))

    def traverse(self, offs: np.ndarray) -> np.ndarray:
        """log10 probability of each row: all rows in step, left to right, each carrying its state's depth."""
        length = np.diff(offs)
        order = np.argsort(-length, kind="stable")
        head, length = offs[:-1][order], length[order]
        score, state = np.zeros(len(order)), np.full(len(order), 1 if self.arc else 0)
        for t, m in enumerate(np.searchsorted(-length, -np.arange(length[0] if len(length) else 0), "left").tolist()):
            at = head[:m] + t
            depth, gain, open_ = state[:m], np.zeros(m), np.ones(m, bool)
            reached = np.zeros(m, np.int64)
            for k in range(len(self.arc), 0, -1):
                here = open_ & (depth >= k) & self.has_state[k - 1][at]
                take = here & self.has_arc[k - 1][at]
                gain += np.where(take, self.arc[k - 1][at], np.where(here, self.fail[k - 1][at], 0.0))
                reached[take] = k
                open_ &= ~take
            gain += np.where(open_, self.root[at], 0.0)
            score[:m] += gain
            state[:m] = np.minimum(reached + 1, len(self.arc))
        out = np.empty(len(order))
        out[order] = score
        return out


def score_documents(docs: DataFrame, held_out, order: int = 2, mass: float = 4.0, bucket_bytes: int = 12 << 20) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score. Rows where `held_out` (a boolean column
    expression) is true aren't learned from. Null text is empty (one token, the end); repeated rows count as often as
    they occur; an empty table gives an empty one; other columns are ignored."""
    spark = docs.sparkSession
    ship(spark)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.coalesce(held_out, F.lit(False)).alias("held_out"))
    size, learned = rows.agg(F.sum(F.octet_length("text")), F.sum((~F.col("held_out")).cast("long"))).first()
    buckets = max(1, -(-(size or 0) // bucket_bytes))
    shards = buckets
    dealt = rows.withColumn("bucket", F.pmod(F.xxhash64("doc_id", F.xxhash64("text")), F.lit(buckets)).cast("int")).repartitionById(buckets, "bucket")

    def ask(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        toks, offs = tokens(table.column("text"))
        train = np.repeat(~table.column("held_out").to_numpy(zero_copy_only=False), np.diff(offs))
        bucket = table.column("bucket")[0].as_py()
        out = []
        for k, (h, real) in enumerate(grams(toks, offs, order), 1):
            found, place = distinct(h[real])
            count = np.bincount(place[train[real]], minlength=len(found))
            cut = _cuts(found, shards)
            for s in np.flatnonzero(np.diff(cut)).tolist():
                out.append((bucket, k, s, found[cut[s] : cut[s + 1]].tobytes(), _thin(count[cut[s] : cut[s + 1]])))
        return _table(out)

    def answer(table: pa.Table) -> pa.Table:
        out, shard = [], table.column("shard")[0].as_py()
        kinds = table.column("k").to_numpy()
        for k in np.unique(kinds):
            part = table.filter(pa.array(kinds == k))
            asked = [np.frombuffer(x, np.uint64) for x in part.column("grams").to_pylist()]
            found, place = distinct(np.concatenate(asked))
            total = np.bincount(place, weights=np.concatenate([_thick(x) for x in part.column("counts").to_pylist()]), minlength=len(found)).astype(np.int64)
            at = 0
            for bucket, x in zip(part.column("bucket").to_pylist(), asked, strict=True):
                out.append((bucket, k, shard, b"", _thin(total[place[at : at + len(x)]])))
                at += len(x)
            out.append((-1, k, shard, b"", b"", int(total.sum()), int((total > 0).sum())))
        return _table(out)

    # A bucket, and a shard, is a partition of its own.
    message = "bucket int, k int, shard int, grams binary, counts binary, total long, kinds long"
    asked = dealt.groupBy("bucket").applyInArrow(released(ask), message).repartitionById(shards, "shard")
    answers = store(asked.groupBy("shard").applyInArrow(released(answer), message), "ngram-counts")
    total, kinds = (int(x or 0) for x in answers.filter("bucket = -1 and k = 1").agg(F.sum("total"), F.sum("kinds")).first())
    learned = int(learned or 0)

    def score(docs_: pa.Table, told: pa.Table) -> pa.Table:
        docs_ = docs_.combine_chunks()
        toks, offs = tokens(docs_.column("text"))
        parts = sorted(zip(told.column("k").to_pylist(), told.column("shard").to_pylist(), told.column("counts").to_pylist(), strict=True), key=lambda x: x[:2])
        counts, exists = [], []
        for k, (h, real) in enumerate(grams(toks, offs, order), 1):
            found, place = distinct(h[real])
            known = np.concatenate([_thick(c) for kk, _, c in parts if kk == k])
            each = np.zeros(len(toks), np.int64)
            each[real] = known[place]
            counts.append(each)
            exists.append(real)
        histories = []
        for k in range(2, order + 1):
            before = np.zeros(len(toks), np.int64)
            before[1:] = counts[k - 2][:-1]
            starts = offs[:-1]
            before[starts] = learned if k == 2 else 0
            histories.append(before)
        machine = Automaton(counts, histories, exists[1:], total, kinds, mass)
        row = np.repeat(np.arange(len(offs) - 1), np.diff(offs))
        n = len(offs) - 1
        return pa.table({
            "doc_id": docs_.column("doc_id"),
            "held_out": docs_.column("held_out"),
            "n_tokens": pa.array(np.diff(offs), pa.int64()),
            "n_known": pa.array(np.bincount(row, weights=machine.known, minlength=n).astype(np.int64)),
            "train_tokens": pa.array(np.full(n, total, np.int64)),
            "base_score": pa.array(np.bincount(row, weights=machine.root, minlength=n)),
            "score": pa.array(machine.traverse(offs)),
        })

    mine = answers.filter("bucket >= 0").select("bucket", "k", "shard", "counts").repartitionById(buckets, "bucket")
    result = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    return dealt.groupBy("bucket").cogroup(mine.groupBy("bucket")).applyInArrow(released(score), result)


def _cuts(found: np.ndarray, shards: int) -> np.ndarray:
    edges = np.array([(s << 64) // shards for s in range(1, shards)], np.uint64)
    return np.concatenate([[0], np.searchsorted(found, edges), [len(found)]])


def _thin(counts: np.ndarray) -> bytes:
    """Counts in the fewest of 1, 2, 4 or 8 bytes that hold the largest; the first byte says which."""
    top = int(counts.max()) if len(counts) else 0
    width = 1 if top < 1 << 8 else 2 if top < 1 << 16 else 4 if top < 1 << 32 else 8
    return bytes([width]) + counts.astype(f"<u{width}").tobytes()


def _thick(data: bytes) -> np.ndarray:
    return np.frombuffer(data, f"<u{data[0]}", offset=1).astype(np.int64)


def _table(rows: list[tuple]) -> pa.Table:
    """Messages; the last two numbers, the total and the kinds of a shard's n-grams, are null but where it tells them."""
    kinds = {"bucket": pa.int32(), "k": pa.int32(), "shard": pa.int32(), "grams": pa.binary(), "counts": pa.binary(), "total": pa.int64(), "kinds": pa.int64()}
    cols = list(zip(*((*r, None, None)[:7] for r in rows), strict=True)) if rows else [[] for _ in kinds]
    return pa.table({n: pa.array(c, t) for (n, t), c in zip(kinds.items(), cols, strict=True)})


_SQL_CRC = """xor(list_reduce(list_prepend(4294967295::BIGINT, list_transform(string_split(doc_id::VARCHAR, ''), lambda x: ascii(x)::BIGINT)),
  lambda c, b: list_reduce(list_prepend(xor(c, b), range(8)), lambda a, i: xor(a >> 1, 3988292384 * (a & 1)))), 4294967295)"""

#: The rows of op5's query over documents at order 2 and mass 4, scores to six places, for doc_ids that differ.
ORACLE = rf"""
WITH docs AS (
  SELECT doc_id, coalesce({_SQL_CRC} % 10 = 0, false) AS held_out,
    list_append(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^ 	-
]+'), ' ') AS w FROM documents),
toks AS MATERIALIZED (SELECT doc_id, held_out, unnest(list_prepend('  ', w[:-2])) AS h, unnest(w) AS t FROM docs),
one AS (SELECT t, count(*) AS c FROM toks WHERE NOT held_out GROUP BY t),
two AS (SELECT h, t, count(*) AS c2 FROM toks WHERE NOT held_out GROUP BY h, t),
before AS (SELECT t AS h, c AS ch FROM one WHERE t <> ' ' UNION ALL SELECT '  ', count(*) FROM docs WHERE NOT held_out),
whole AS (SELECT coalesce(sum(c), 0)::BIGINT AS n, count(*) AS v FROM one),
scored AS (
  SELECT doc_id, held_out, n, coalesce(c, 0) AS c, coalesce(ch, 0) AS ch, coalesce(c2, 0) AS c2, (coalesce(c, 0) + 0.1::DOUBLE) / (n + 0.1::DOUBLE * (v + 1)) AS p
  FROM toks LEFT JOIN one USING (t) LEFT JOIN two USING (h, t) LEFT JOIN before USING (h), whole)
SELECT doc_id, held_out, n_tokens, n_known, train_tokens, round(b, 6) AS base_score, round(m, 6) AS score, round(m / n_tokens, 6) AS mean_score, round((m - b) / n_tokens, 6) AS mean_gain
FROM (
  SELECT doc_id, held_out, count(*) AS n_tokens, count(*) FILTER (c > 0) AS n_known, any_value(n) AS train_tokens,
    sum(log10(p)) AS b, sum(log10(CASE WHEN ch > 0 THEN (c2 + 4 * p) / (ch + 4) ELSE p END)) AS m
  FROM scored GROUP BY doc_id, held_out)
"""

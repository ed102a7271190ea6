"""Vector best-fit packing of token pieces into sequences under token, document-count and attention-cost capacities."""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import partitions_for, ship, store
from .token_files import with_end
from .tokenise import encoder
from .words import released, slices


@dataclass(frozen=True)
class Capacity:
    """Of one sequence. attention: the sum of squared piece lengths. The defaults bind on tokens alone."""

    tokens: int = 2048
    documents: int = 2048
    attention: int = 2048 * 2048

    def vector(self) -> np.ndarray:
        return np.array([self.tokens, self.documents, self.attention], float)


def best_fit(lengths: np.ndarray, capacity: Capacity, score: str = "norm", weights=(1.0, 0.05, 0.1)) -> tuple[np.ndarray, np.ndarray]:
    """Bin and offset of each piece. Longest first; of the bins that can take it under every capacity, the one with the
    least weighted norm of what stays free ("norm"), or the greatest weighted dot product of need and free ("dot").
    Ties go to the oldest bin. Raises if a piece can't fit in an empty bin."""
    cap, w = capacity.vector(), np.asarray(weights, float)
    n = len(lengths)
    which, offset = np.zeros(n, np.int64), np.zeros(n, np.int64)
    order = np.argsort(-lengths, kind="stable")
    least = int(lengths.min()) if n else 0
    free = np.empty((max(16, n), 3))
    label, opened, live = np.zeros(max(16, n), np.int64), 0, 0
    for step, i in enumerate(order.tolist()):
        size = float(lengths[i])
        need = np.array([size, 1.0, size * size])
        if (need > cap).any():
            raise ValueError(f"a piece of {int(size)} tokens exceeds an empty sequence's capacity")
        if step % 512 == 511:  # bins that no later piece fits in
            keep = np.flatnonzero((free[:live, 0] >= least) & (free[:live, 1] >= 1))
            free[: len(keep)], label[: len(keep)], live = free[keep], label[keep], len(keep)
        open_ = free[:live]
        fit = np.flatnonzero((open_[:, 0] >= need[0]) & (open_[:, 1] >= 1) & (open_[:, 2] >= need[2]))
        if len(fit):
            if score == "dot":
                k = fit[int(np.argmax((open_[fit] / cap * (need / cap)) @ w))]
            else:
                k = fit[int(np.argmin((((open_[fit] - need) / cap) ** 2) @ w))]
        else:
            k = live
            free[k], label[k] = cap, opened
            live, opened = live + 1, opened + 1
        which[i], offset[i] = label[k], int(cap[0] - free[k, 0])
        free[k] -= need
    return which, offset


def token_pieces(docs: DataFrame, tokenizer_path: str, size: int, end_id: int = 0, with_ids: bool = False) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 (and ids): each document's ids and end_id, cut every `size` ids."""
    ship(docs.sparkSession)

    def cut(batches):
        enc = encoder(tokenizer_path)
        for b in batches:
            for part in slices(b, "text"):
                ids, offs = with_end(*enc.encode(part.column("text")), end_id)
                lengths = np.diff(offs)
                pieces = -(-lengths // size)
                row = np.repeat(np.arange(len(lengths)), pieces)
                piece = np.arange(len(row)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
                start = piece * size
                n = np.minimum(size, lengths[row] - start)
                at = offs[row] + start
                raw = ids.astype("<u4")
                cols = {
                    "doc_id": part.column("doc_id").take(pa.array(row)),
                    "piece": pa.array(piece, pa.int32()),
                    "start": pa.array(start, pa.int64()),
                    "length": pa.array(n, pa.int64()),
                    "ids_crc32": pa.array([zlib.crc32(raw[a : a + m]) for a, m in zip(at.tolist(), n.tolist(), strict=True)], pa.int64()),
                }
                if with_ids:
                    cols["ids"] = pa.array([ids[a : a + m].astype(np.int32) for a, m in zip(at.tolist(), n.tolist(), strict=True)], pa.list_(pa.int32()))
                yield pa.RecordBatch.from_pydict(cols)

    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * with_ids
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(released(cut), schema)


def pack(docs: DataFrame, tokenizer_path: str, capacity: Capacity = Capacity(), score: str = "norm", end_id: int = 0, chunk: int = 16384, with_ids: bool = False) -> DataFrame:
    """Pieces of all documents with sequence_id and offset. Null texts are empty (one id, the end); repeated rows and null
    doc_ids have pieces of their own; any text length; an empty table gives an empty one; other columns are ignored.

    Pieces are dealt evenly, without a key, and each chunk of at most `chunk` pieces is packed in one task, so no group
    is gathered and memory is bounded; each chunk wastes less than one sequence. Sequence ids are unique, not dense.
    """
    spark = docs.sparkSession
    stored = store(token_pieces(docs, tokenizer_path, capacity.tokens, end_id, with_ids), "pieces")
    parts = partitions_for(spark, stored.count(), chunk)

    def fill(batches):
        base, used = TaskContext.get().partitionId() << 40, 0
        table = []
        for b in batches:
            table.append(b)
            if sum(x.num_rows for x in table) >= chunk:
                out, used = settle(table, base, used)
                yield out
                table = []
        if table:
            out, used = settle(table, base, used)
            yield out

    def settle(table, base, used):
        t = pa.Table.from_batches(table).combine_chunks()
        lengths = t.column("length").to_numpy()
        which, offset = best_fit(lengths, capacity, score)
        t = t.append_column("sequence_id", pa.array(base + used + which)).append_column("offset", pa.array(offset))
        return t.to_batches()[0], used + (int(which.max()) + 1 if len(which) else 0)

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in stored.schema.fields) + ", sequence_id long, offset long"
    return stored.repartition(parts).mapInArrow(released(fill), schema)

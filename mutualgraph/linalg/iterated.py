"""Block iteration on D^-1 S whose vectors stay packed by blocks of users: a round is one product, which also forms the small
Gram matrices of its rows, and a sum of those. Rows here are z = D^-1/2 x of the rows x that D^-1/2 S D^-1/2 acts on, so that
degrees are needed where rows are made only."""

from __future__ import annotations

import pickle

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import drop_stored, free, store
from .blocks import TASKS, lists, matrix, sums

#: Products of a round of a filter, from the second on. The spectrum lies above LEAST.
DEGREE, LEAST = 8, -1.05


def dealt(rows: DataFrame, blocks: int) -> DataFrame:
    """Rows with the block q of their user_id, those of a block together."""
    q = F.pmod(F.xxhash64("user_id"), F.lit(blocks)).cast("int").alias("q")
    return rows.select(q, *rows.columns).repartition(min(TASKS, blocks), "q")


def packed(rows: DataFrame, blocks: int) -> DataFrame:
    """q, own (users ascending and their d), x (their rows): of rows (user_id, d, vec), stored."""

    def run(table: pa.Table) -> pa.Table:
        ids, d = (table.column(c).to_numpy() for c in ("user_id", "d"))
        order = np.argsort(ids)
        return _state(table.column("q")[0].as_py(), ids[order], d[order], matrix(table.column("vec"))[order])

    return store(dealt(rows.select("user_id", "d", "vec"), blocks).groupBy("q").applyInArrow(run, _STATE), "state", large_rows=True)


_STATE = "q int, own binary, x binary, g array<double>"


def _state(q: int, ids: np.ndarray, d: np.ndarray, x: np.ndarray, g: np.ndarray | None = None) -> pa.Table:
    own, rows = pickle.dumps((ids, d), 5), np.ascontiguousarray(x, dtype=np.float64).tobytes()
    return pa.table({"q": pa.array([q], pa.int32()), "own": pa.array([own], pa.binary()), "x": pa.array([rows], pa.binary()), "g": lists(np.zeros((1, 0)) if g is None else g.reshape(1, -1))})


def unpacked(own, x) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Users, degrees and rows of a block, as a task reads it."""
    ids, d = pickle.loads(own.as_buffer())
    return ids, d, np.frombuffer(x.as_buffer(), np.float64).reshape(len(ids), -1)


def part(q: int, ids: np.ndarray, rows: np.ndarray) -> pa.RecordBatch:
    """A partial sum of S z at some users of block q."""
    return pa.RecordBatch.from_pydict({"q": pa.array([q], pa.int32()), "part": pa.array([pickle.dumps((ids, np.ascontiguousarray(rows)), 5)], pa.binary())})


#: What partial sums are.
PART = "q int, part binary"


def moved(state: DataFrame, parts: DataFrame, blocks: int, shift: float, turn: np.ndarray) -> DataFrame:
    """The state of (D^-1 S - shift) z times turn, stored; g: z'D z, z'S z and z'S D^-1 S z of the block (z before it)."""

    def run(table: pa.Table) -> pa.Table:
        mine = table.column("own").is_valid().to_numpy()
        at = int(np.flatnonzero(mine)[0])
        ids, d, z = unpacked(table.column("own")[at], table.column("x")[at])
        s = np.zeros_like(z)
        for r in np.flatnonzero(~mine):
            users, rows = pickle.loads(table.column("part")[int(r)].as_buffer())
            s[np.searchsorted(ids, users)] += rows
        sd = s / d[:, None]
        g = np.stack([z.T @ (z * d[:, None]), z.T @ s, s.T @ sd])
        return _state(table.column("q")[0].as_py(), ids, d, (sd - shift * z) @ turn, g)

    none = F.lit(None).cast("binary")
    both = state.select("q", "own", "x", none.alias("part")).union(parts.select("q", none, none, "part"))
    return store(both.repartition(min(TASKS, blocks), "q").groupBy("q").applyInArrow(run, _STATE), "state", large_rows=True)


def parts_of(rows: DataFrame, blocks: int, state: DataFrame) -> DataFrame:
    """Partial sums of S z, given as rows (user_id, vec), of the users that a state has."""

    def run(table: pa.Table) -> pa.Table:
        ids, got = table.column("user_id").to_numpy(), matrix(table.column("vec"))
        return pa.Table.from_batches([part(table.column("q")[0].as_py(), ids, got)])

    known = rows_of(state).select("user_id")
    return dealt(rows.select("user_id", "vec").join(known, "user_id", "left_semi"), blocks).groupBy("q").applyInArrow(run, PART)


def rows_of(state: DataFrame, turn: np.ndarray | None = None) -> DataFrame:
    """user_id, d, vec: rows, or rows times turn."""

    def run(batches):
        for b in batches:
            for r in range(b.num_rows):
                ids, d, z = unpacked(b.column("own")[r], b.column("x")[r])
                z = z if turn is None else z @ turn
                for s in range(0, len(ids), 1 << 14):
                    e = s + (1 << 14)
                    yield pa.RecordBatch.from_pydict({"user_id": pa.array(ids[s:e]), "d": pa.array(d[s:e]), "vec": lists(z[s:e])})

    return state.select("own", "x").mapInArrow(run, "user_id long, d double, vec array<double>")


def _filter(degree: int, top: float) -> list[float]:
    """Zeros of the Chebyshev polynomial on LEAST..top, each far from those before it (Leja's order)."""
    middle, half = (top + LEAST) / 2, (top - LEAST) / 2
    left = list(middle + half * np.cos((np.arange(degree) + 0.5) * np.pi / degree))
    out = [left.pop()]
    while left:
        out.append(left.pop(int(np.argmax([np.sum(np.log(np.abs(v - np.array(out)))) for v in left]))))
    return out


def _ritz(ww: np.ndarray, ws: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Values, falling, and vectors v with v'(ww)v = I and v'(ws)v diagonal."""
    w, v = np.linalg.eigh((ww + ww.T) / 2)
    root = v[:, w > 1e-12 * w[-1]] / np.sqrt(w[w > 1e-12 * w[-1]])
    m = root.T @ ws @ root
    w, v = np.linalg.eigh((m + m.T) / 2)
    return w[::-1], root @ v[:, ::-1]


def largest(operator, k: int, start: DataFrame, rounds: int = 150, tol: float = 1e-9) -> DataFrame:
    """user_id, d, vec: z of the k largest eigenvectors of D^-1 S, vec'D vec = I. operator: blocks, and parts(state): the partial
    sums of S z. start: rows (user_id, d, vec) of a block wider than k.

    Products are the factors of Chebyshev filters on what lies below the block's least value, so that far fewer are needed than
    of one factor all the time. More values than the block has may lie as high as its least one, and then what remains to be
    damped is lower: its mean distance is what the rows' residuals against the values of now were over by how far the values rose. Ends when the sum of the k values settled in two
    products on end.
    """
    state = packed(start, operator.blocks)
    width = matrix(start.select("vec").limit(1).toArrow().column("vec")).shape[1]
    turn, shifts, before, settled, top, gap = np.eye(width), _filter(DEGREE // 2, 0.0), -np.inf, 0, 0.0, 0.0
    for n in range(rounds):
        if not shifts:
            shifts = _filter(DEGREE, top)
        shift = shifts.pop(0)
        new = moved(state, operator.parts(state), operator.blocks, shift, turn)
        ww, ws, ss = sums(new, ["g"], lambda c: {"g": c["g"].sum(0)[None]})["g"].reshape(3, width if n == 0 else len(turn), -1)
        last = state, ww, ws
        values, vectors = _ritz(ww, ws)
        now = values[:k].sum()
        settled = settled + 1 if abs(now - before) <= tol * max(abs(now), 1.0) else 0
        if n == rounds - 1 or settled == 2:
            break
        before = now
        if not shifts:  # the next filter's range
            lies = float((square - 2 * values[:k] * began + values[:k] ** 2).sum()), float((values[:k] - began).sum())
            gap = lies[0] / lies[1] if lies[1] > tol else gap
            top = max(min(float(values[-1]), float(values[:k][-1]) - gap / 2), -1.0)
        if n == 0 or not shifts:
            began, square = values[:k], np.einsum("ij,ik,kj->j", vectors[:, :k], ss, vectors[:, :k])
        gram = ss - shift * (ws + ws.T) + shift * shift * ww
        gram = turn.T @ gram @ turn  # of the new rows
        w, v = np.linalg.eigh((gram + gram.T) / 2)
        keep = w > 1e-14 * w[-1]
        turn = v[:, keep] / np.sqrt(w[keep])
        drop_stored(state)
        state = new
        free(state.sparkSession)
    out = store(rows_of(last[0], vectors[:, :k]), "eigenvectors")
    drop_stored(state)
    if new is not state:
        drop_stored(new)
    return out

"""Products of sparse tables with rows of short vectors, and Gram matrices of such rows; users never leave the cluster."""

from __future__ import annotations

import pickle
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import Passing, ship, store

#: Rows that a task adds up before it passes partial sums on.
HELD_ROWS = 200_000
#: Packed entries: users of a block of rows and of a block of sources, and entries of a piece, at most (about); blocks of rows
#: that a task meets together, entries multiplied at once, rows of a batch of results, and tasks that pack at most.
BLOCK_ROWS, SIDE_ROWS, PIECE = 1 << 15, 1 << 17, 1 << 20
TOGETHER, AT_ONCE, SENT_ROWS, TASKS = 6, 1 << 13, 1 << 13, 4096
#: Blocks of rows of a state that a task meets together.
FAR_TOGETHER = 16


def matrix(column) -> np.ndarray:
    """Rows of a list column, all of one length, as an array. Null rows are zero."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if len(column) == column.null_count:
        return np.zeros((len(column), 0))
    flat = column.flatten().to_numpy(zero_copy_only=False)
    k = len(flat) // (len(column) - column.null_count)
    if not column.null_count:
        return flat.reshape(-1, k)
    out = np.zeros((len(column), k))
    out[column.is_valid().to_numpy(zero_copy_only=False)] = flat.reshape(-1, k)
    return out


def lists(a: np.ndarray) -> pa.Array:
    a = np.ascontiguousarray(a, dtype=np.float64)
    return pa.ListArray.from_arrays(pa.array(np.arange(len(a) + 1) * a.shape[1], pa.int32()), pa.array(a.reshape(-1)))


def _summed(keys: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(keys, kind="stable")
    keys, rows = keys[order], rows[order]
    at = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
    return keys[at], np.add.reduceat(rows, at, axis=0)


def add_rows(rows: DataFrame, summed: bool = False) -> DataFrame:
    """user_id, vec: the sum of rows that share a user_id. Tasks add up their own rows before (unless they are `summed`) and
    after the shuffle."""
    ship(rows.sparkSession)

    def run(batches):
        keys, vecs, n = [], [], 0
        for b in batches:
            if not b.num_rows:
                continue
            keys.append(b.column("user_id").to_numpy())
            vecs.append(matrix(b.column("vec")))
            n += b.num_rows
            if n > HELD_ROWS:
                k, v = _summed(np.concatenate(keys), np.concatenate(vecs))
                keys, vecs, n = [k], [v], len(k)
                if n > HELD_ROWS // 2:
                    yield from _out(k, v)
                    keys, vecs, n = [], [], 0
        if keys:
            yield from _out(*_summed(np.concatenate(keys), np.concatenate(vecs)))

    def _out(k, v):
        yield pa.RecordBatch.from_pydict({"user_id": pa.array(k), "vec": lists(v)})

    kind = "user_id long, vec array<double>"
    first = rows.select("user_id", "vec")
    first = first if summed else first.mapInArrow(run, kind)

    def last(batches):
        keys, vecs = [], []
        for b in batches:
            if b.num_rows:
                keys.append(b.column("user_id").to_numpy())
                vecs.append(matrix(b.column("vec")))
        if keys:
            yield from _out(*_summed(np.concatenate(keys), np.concatenate(vecs)))

    return first.repartition("user_id").mapInArrow(last, kind)


def spmm(entries: DataFrame, rows: DataFrame) -> DataFrame:
    """user_id, vec: entries (src, dst, w) times rows (user_id, vec), by one join on dst and one sum by src."""
    ship(rows.sparkSession)

    def scaled(batches):
        for b in batches:
            if b.num_rows:
                k, v = _summed(b.column("src").to_numpy(), b.column("w").to_numpy()[:, None] * matrix(b.column("vec")))
                yield pa.RecordBatch.from_pydict({"user_id": pa.array(k), "vec": lists(v)})

    joined = entries.join(rows.select(F.col("user_id").alias("dst"), "vec"), "dst").select("src", "w", "vec")
    return add_rows(joined.mapInArrow(scaled, "user_id long, vec array<double>"))


def _small(a: np.ndarray) -> np.ndarray:
    return a.astype(np.min_scalar_type(int(a.max())))


def _gaps(ids: np.ndarray) -> tuple[int, np.ndarray]:
    """Ascending numbers as the first one and what each adds."""
    return int(ids[0]), _small(np.diff(ids, prepend=ids[0]))


def _piece(table: pa.Table) -> pa.Table:
    """One row of a piece: its sources and targets ascending, how many entries each source has, their targets' places and
    weights (one number if all are equal), and each source's own block of rows."""
    src, dst, w = (table.column(c).to_numpy() for c in ("src", "dst", "w"))
    order = np.argsort(src, kind="stable")
    ids, first, many = np.unique(src[order], return_index=True, return_counts=True)
    block = table.column("b").to_numpy()[order][first]
    others, to = np.unique(dst[order], return_inverse=True)
    w = w[order] if w.min() != w.max() else w[:1].copy()
    data = pickle.dumps((*_gaps(ids), *_gaps(others), _small(many), _small(to), w, _small(block)), 5)
    return pa.table({"p": table.column("p")[:1], "q": table.column("q")[:1], "data": pa.array([data], pa.binary())})


def _multiplied(piece: tuple, users: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A piece's sources, and its entries times rows of users; users without a row are zero."""
    (one, gaps, two, others, many, to, w, _) = piece
    ids, others = one + np.cumsum(gaps, dtype=np.int64), two + np.cumsum(others, dtype=np.int64)
    at = np.minimum(np.searchsorted(users, others), len(users) - 1)
    x = np.where((users[at] == others)[:, None], rows[at], 0.0)
    ends, s = np.cumsum(many, dtype=np.int64), 0
    first, out = ends - many, np.empty((len(ids), rows.shape[1]))
    while s < len(ids):
        e = max(s + 1, int(np.searchsorted(ends, first[s] + AT_ONCE, "right")))
        a, b = first[s], ends[e - 1]
        part = np.take(x, to[a:b], axis=0)
        part *= w if len(w) == 1 else w[a:b, None]
        out[s:e] = np.add.reduceat(part, first[s:e] - a, axis=0)
        s = e
    return ids, out


class PackedEntries:
    """Entries (src, dst, w), packed in pieces by blocks of sources (p) and of targets (q) and stored once, for any number of
    products. A product packs its rows by q, and each piece meets its block of rows in Spark's product of the two stored
    tables: entries are not shuffled again, and a task sums what its pieces give to a source before anything is shuffled.
    """

    def __init__(self, entries: DataFrame, users: int, count: int):
        ship(entries.sparkSession)
        self.blocks = max(1, -(-users // BLOCK_ROWS))
        self.sides = max(1, -(-users // SIDE_ROWS), -(-count // (PIECE * self.blocks)))
        at = lambda c, n: F.pmod(F.xxhash64(c), F.lit(n)).cast("int")
        dealt = entries.select(at("src", self.sides).alias("p"), at("dst", self.blocks).alias("q"), at("src", self.blocks).alias("b"), F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), F.col("w").cast("double").alias("w")).na.drop()
        # All pieces of a block of sources are in one file, so that a task sums many of them.
        self.table = store(dealt.repartition(min(TASKS, 4 * self.sides), "p").groupBy("p", "q").applyInArrow(_piece, "p int, q int, data binary"), "pieces", large_rows=True)
        self.passing = Passing()

    def times(self, rows: DataFrame) -> DataFrame:
        """user_id, vec: entries times rows (user_id, vec). To be read before the product after the next one is asked for:
        then the packed rows are dropped."""

        def packed(table: pa.Table) -> pa.Table:
            one = pickle.dumps(_summed(table.column("user_id").to_numpy(), matrix(table.column("vec"))), 5)
            return pa.table({"q": table.column("q")[:1], "x": pa.array([one], pa.binary())})

        def run(batches):
            p, ids, total = None, [], []
            for b in batches:
                for r in range(b.num_rows):
                    side = b.column("p")[r].as_py()
                    if side != p or sum(map(len, ids)) > HELD_ROWS:
                        yield from out(ids, total)
                        p, ids, total = side, [], []
                    got = _multiplied(pickle.loads(b.column("data")[r].as_buffer()), *pickle.loads(b.column("x")[r].as_buffer()))
                    ids.append(got[0])
                    total.append(got[1])
                    if len(ids) > 1:
                        ids, total = ([a] for a in _summed(np.concatenate(ids), np.concatenate(total)))
            yield from out(ids, total)

        def out(ids, total):
            if ids:
                k, v = _summed(np.concatenate(ids), np.concatenate(total))
                for at in range(0, len(k), SENT_ROWS):
                    yield pa.RecordBatch.from_pydict({"user_id": pa.array(k[at : at + SENT_ROWS]), "vec": lists(v[at : at + SENT_ROWS])})

        q = F.pmod(F.xxhash64("user_id"), F.lit(self.blocks)).cast("int").alias("q")
        dealt = rows.select(q, F.col("user_id").cast("long").alias("user_id"), "vec").filter("vec is not null").repartition(min(TASKS, self.blocks), "q")
        x = self.passing.keep(store(dealt.groupBy("q").applyInArrow(packed, "q int, x binary"), "rows", large_rows=True))
        few = max(1, -(-self.blocks // TOGETHER))
        met = self.table.hint("shuffle_replicate_nl").join(x.coalesce(few), "q")
        return add_rows(met.select("p", "data", "x").mapInArrow(run, "user_id long, vec array<double>"), summed=True)


    def parts(self, state: DataFrame) -> DataFrame:
        """Partial sums of entries times the rows of a state (linalg/iterated), by the blocks that the state has."""
        from .iterated import PART, part, unpacked

        def run(batches):
            p, held = None, None
            for b in batches:
                for r in range(b.num_rows):
                    side = b.column("p")[r].as_py()
                    if side != p and held is not None:
                        yield from out(*held)
                        held = None
                    p, piece = side, pickle.loads(b.column("data")[r].as_buffer())
                    users, _, x = unpacked(b.column("own")[r], b.column("x")[r])
                    ids, got = _multiplied(piece, users, x)
                    held = (ids, piece[7], got) if held is None else _added(held, ids, piece[7], got)
            if held is not None:
                yield from out(*held)

        def out(ids, block, total):
            for q in np.unique(block).tolist():
                at = block == q
                yield part(q, ids[at], total[at])

        few = max(1, -(-self.blocks // FAR_TOGETHER))
        met = self.table.hint("shuffle_replicate_nl").join(state.select("q", "own", "x").coalesce(few), "q")
        return met.select("p", "data", "own", "x").mapInArrow(run, PART)


def _added(held: tuple, ids: np.ndarray, block: np.ndarray, rows: np.ndarray) -> tuple:
    """Users ascending, their blocks and sums, and some more of them."""
    mine, blocks, total = held
    at = np.minimum(np.searchsorted(mine, ids), len(mine) - 1)
    new = mine[at] != ids
    if new.any():
        all_ = np.concatenate([mine, ids[new]])
        order = np.argsort(all_, kind="stable")
        mine, blocks = all_[order], np.concatenate([blocks, block[new]])[order]
        total = np.concatenate([total, np.zeros((int(new.sum()), total.shape[1]))])[order]
        at = np.searchsorted(mine, ids)
    total[at] += rows
    return mine, blocks, total


def sums(df: DataFrame, columns: list[str], parts: Callable[[dict[str, np.ndarray]], dict[str, np.ndarray]]) -> dict[str, np.ndarray]:
    """Small matrices that add up over rows: parts({column: array}) of each batch, summed by task, then by entry on the
    cluster; only the totals reach the driver."""
    ship(df.sparkSession)

    def run(batches):
        total: dict[str, np.ndarray] = {}
        for b in batches:
            if not b.num_rows:
                continue
            cols = {c: matrix(b.column(c)) if pa.types.is_list(b.schema.field(c).type) else b.column(c).to_numpy(zero_copy_only=False) for c in columns}
            for name, m in parts(cols).items():
                total[name] = total[name] + m if name in total else m
        for name, m in total.items():
            m = np.atleast_2d(m)
            i, j = np.indices(m.shape)
            yield pa.RecordBatch.from_pydict({"name": pa.array([name] * m.size), "i": pa.array(i.ravel(), pa.int32()), "j": pa.array(j.ravel(), pa.int32()), "v": pa.array(m.ravel().astype(float))})

    got = df.select(*columns).mapInArrow(run, "name string, i int, j int, v double").groupBy("name", "i", "j").agg(F.sum("v").alias("v")).toArrow()
    out: dict[str, np.ndarray] = {}
    names = got.column("name").to_numpy(zero_copy_only=False)
    i, j, v = (got.column(c).to_numpy() for c in ("i", "j", "v"))
    for name in dict.fromkeys(names.tolist()):
        at = names == name
        m = np.zeros((i[at].max() + 1, j[at].max() + 1))
        m[i[at], j[at]] = v[at]
        out[name] = m
    return out


def map_rows(df: DataFrame, columns: list[str], made: Callable[[dict[str, np.ndarray]], dict[str, np.ndarray]], schema: str, keep: tuple[str, ...] = ("user_id",)) -> DataFrame:
    """New array columns of each row: made({column: array}) of each batch; `keep` are passed through. schema covers both."""
    ship(df.sparkSession)

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            cols = {c: matrix(b.column(c)) if pa.types.is_list(b.schema.field(c).type) else b.column(c).to_numpy(zero_copy_only=False) for c in columns}
            new = {n: lists(a) if a.ndim == 2 else pa.array(a) for n, a in made(cols).items()}
            yield pa.RecordBatch.from_pydict({c: b.column(c) for c in keep} | new)

    return df.select(*dict.fromkeys([*keep, *columns])).mapInArrow(run, schema)

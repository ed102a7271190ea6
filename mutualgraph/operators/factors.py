"""Products with pair closeness of a network whose users share much, without a pair: by terms that have factors.

A path's part is counts over the sum of both users' totals. 1 / (a + b) is a sum of products f_m(a) f_m(b), up to the last bit of a
double, of as few terms as the logarithm of the totals' range asks for, and counts are incidence times incidence. So a term's
product is two products with incidence; a task takes some terms of a path for all users.
"""

from __future__ import annotations

import pickle

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..linalg.blocks import add_rows, lists, matrix
from ..linalg.iterated import PART, packed, part, unpacked
from ..storage import Passing, ship, store

#: Rows of a path's incidence that one task may hold, and tasks that share the terms of a path (social ones have more work).
MOST_ENTRIES, SHARES = 40_000_000, {1: 1, 2: 4, 3: 3, 4: 3, 5: 2, 6: 2, 7: 2}
#: Numbers gathered at once, about.
AT_ONCE = 1 << 17
#: What is left of 1 / (a + b), relative to it.
LEFT = 1e-16


def nodes(low: float, high: float) -> np.ndarray:
    """x_m such that the terms of them leave LEFT of 1 / (a + b) for all a, b in low..high: each where most was left."""
    grid, left, out = np.geomspace(low, high, 2000), np.ones(2000), []
    while (left.max() ** 2 > LEFT or not out) and len(out) < 200:
        x = grid[int(left.argmax())]
        out.append(x)
        left *= np.abs((grid - x) / (grid + x))
    return np.array(out)


def terms(a: np.ndarray, x: np.ndarray) -> np.ndarray:
    """f_m(a) by rows m: sqrt(2 x_m) / (a + x_m) times (a - x_j) / (a + x_j) of all j before m; 0 where a is 0."""
    out, rest = np.empty((len(x), len(a))), (a > 0).astype(float)
    for m, v in enumerate(x):
        out[m] = rest * np.sqrt(2 * v) / (a + v)
        rest = rest * (a - v) / (a + v)
    return out


def _least(a: np.ndarray) -> np.ndarray:
    return a.astype(np.min_scalar_type(int(a.max()))) if len(a) else a


class Sparse:
    """Entries by row, for products with short vectors. order: entries of a row are together."""

    def __init__(self, row: np.ndarray, column: np.ndarray, value: np.ndarray, n: int):
        order = np.argsort(row, kind="stable")
        many = np.bincount(row, minlength=n)
        self.n, self.rows, self.many = n, np.flatnonzero(many).astype(np.int32), many[many > 0].astype(np.int32)
        # Small types: a task's JVM holds copies of what is stored here.
        self.column = _least(column[order])
        self.value = None if (value == 1).all() else _least(value[order]) if value.dtype.kind == "i" else value[order]

    def times(self, v: np.ndarray) -> np.ndarray:
        out, s = np.zeros((self.n, v.shape[1])), 0
        ends = np.cumsum(self.many, dtype=np.int64)
        first, step = ends - self.many, max(1, AT_ONCE // v.shape[1])
        while s < len(ends):
            e = max(s + 1, int(np.searchsorted(ends, first[s] + step, "right")))
            a, b = first[s], ends[e - 1]
            got = np.take(v, self.column[a:b], axis=0)
            if self.value is not None:
                got *= self.value[a:b, None]
            out[self.rows[s:e]] = np.add.reduceat(got, first[s:e] - a, axis=0)
            s = e
        return out


def _term(table: pa.Table) -> pa.Table:
    """One row of a path: its users ascending, their totals, closed walks, and entries both ways."""
    path = table.column("path")[0].as_py()
    has = table.column("attr").is_valid().to_numpy()
    users, cnt = table.column("user_id").to_numpy(), table.column("cnt").to_numpy()
    other = table.column("attr").filter(pa.array(has)).to_numpy()
    ids, names = np.unique(users), np.unique(other)
    if path <= 2:
        ids = names = np.union1d(ids, names)
    n, at = len(names), np.searchsorted(names, other).astype(np.int32)
    row = np.searchsorted(ids, users[has]).astype(np.int32)
    o = np.zeros(len(ids))
    o[np.searchsorted(ids, users[~has])] = cnt[~has]
    del other, users
    there, back = Sparse(row, at, cnt[has], len(ids)), Sparse(at, row, cnt[has], n)
    if path == 2:
        key = row.astype(np.int64) * n + at
        closed = 2.0 * np.bincount(row[np.isin(key, at.astype(np.int64) * n + row)], minlength=len(ids))
    else:
        closed = np.bincount(row, weights=cnt[has].astype(float) ** 2, minlength=len(ids))
    data = pickle.dumps((ids, o, closed, there, back), 5)
    return pa.table({"path": pa.array([path], pa.int32()), "data": pa.array([data], pa.binary())})


def _path_times(path: int, share: int, term: tuple, x: np.ndarray, weight: float) -> np.ndarray:
    """A share of a path's closeness times rows of its users."""
    ids, o, closed, there, back = term
    live = o > 0
    if path == 1:
        def over(m):  # entries over the sum of both users' totals
            row = np.repeat(m.rows, m.many)
            return Sparse(row, m.column, 1.0 / (o[row] + o[m.column]) * (row != m.column), m.n)
        return weight * sum(over(m).times(x) for m in (there, back))
    both = (lambda v: there.times(there.times(v)) + back.times(back.times(v))) if path == 2 else (lambda v: there.times(back.times(v)))
    out, weight = np.zeros_like(x), weight if path == 2 else 2 * weight
    if not live.any():
        return out
    f = terms(o, nodes(o[live].min(), o[live].max()))
    for m in range(share, len(f), SHARES[path]):
        out += f[m][:, None] * both(f[m][:, None] * x)
    if share == 0:
        inverse = np.divide(1.0, o, out=np.zeros_like(o), where=live)
        if path == 2 and not live.all():
            none = (~live).astype(float)[:, None]
            out += none * both(inverse[:, None] * x) + inverse[:, None] * both(none * x)
        out -= (closed * inverse / 2)[:, None] * x
    return weight * out


class Terms:
    """have: path (3 to 7), user_id, attr, cnt; marginals: user_id, path, o. Stored once for any number of products."""

    def __init__(self, have: DataFrame, marginals: DataFrame, mix: dict[int, float], users: DataFrame):
        ship(have.sparkSession)
        self.mix, self.users, self.passing = mix, users, Passing()
        number = F.when(F.col("path") <= 4, F.col("attr").cast("long")).otherwise(F.xxhash64("attr"))
        rows = have.filter("user_id is not null and attr is not null").select("path", "user_id", number.alias("attr"), F.col("cnt").cast("long").alias("cnt"))
        all_ = rows.filter(F.col("path").isin([p for p in mix if p > 2]))
        for p in (p for p in mix if p <= 2):  # links, as path 3 has them
            all_ = all_.union(rows.filter("path = 3").select(F.lit(p).alias("path"), "user_id", "attr", "cnt"))
        none = F.lit(None).cast("long")
        all_ = all_.union(marginals.select("path", "user_id", none.alias("attr"), F.col("o").cast("long").alias("cnt")))
        shares = F.element_at(F.create_map(*[F.lit(v) for p in SHARES.items() for v in p]), F.col("path"))
        each = store(all_.repartition("path").groupBy("path").applyInArrow(_term, "path int, data binary"), "paths", large_rows=True)
        self.table = store(each.select("path", F.explode(F.sequence(F.lit(0), shares - 1)).alias("share"), "data").repartitionByRange(sum(SHARES[p] for p in mix), "path", "share"), "terms", large_rows=True)

    def parts(self, state: DataFrame) -> DataFrame:
        """Partial sums of closeness times the rows of a state (linalg/iterated)."""
        mix = self.mix

        def whole(table: pa.Table) -> pa.Table:
            got = [unpacked(table.column("own")[r], table.column("x")[r]) for r in range(table.num_rows)]
            ids, x = np.concatenate([g[0] for g in got]), np.concatenate([g[2] for g in got])
            q = np.repeat(table.column("q").to_numpy(), [len(g[0]) for g in got])
            order = np.argsort(ids)
            return pa.table({"rows": pa.array([pickle.dumps((ids[order], q[order], x[order]), 5)], pa.binary())})

        one = state.select("q", "own", "x").groupBy(F.lit(0).alias("all")).applyInArrow(whole, "rows binary")
        one = self.passing.keep(store(one, "whole", large_rows=True))

        def run(batches):
            for b in batches:
                for r in range(b.num_rows):
                    ids, q, x = pickle.loads(b.column("rows")[r].as_buffer())
                    term = pickle.loads(b.column("data")[r].as_buffer())
                    path, users = b.column("path")[r].as_py(), term[0]
                    at = np.minimum(np.searchsorted(ids, users), len(ids) - 1)
                    known = ids[at] == users
                    got = _path_times(path, b.column("share")[r].as_py(), term, np.where(known[:, None], x[at], 0.0), mix[path])[known]
                    users, of = users[known], q[at[known]]
                    for p in np.unique(of).tolist():
                        yield part(p, users[of == p], got[of == p])

        return self.table.hint("shuffle_replicate_nl").crossJoin(one.coalesce(1)).select("path", "share", "data", "rows").mapInArrow(run, PART)

    def times(self, rows: DataFrame) -> DataFrame:
        """user_id, vec: closeness times rows (user_id, vec). Users without rows have zeros."""
        width = len(rows.select("vec").first()[0])
        each = self.users.join(rows.select("user_id", "vec"), "user_id", "left").select("user_id", F.lit(1.0).alias("d"), F.coalesce("vec", F.array_repeat(F.lit(0.0), width)).alias("vec"))
        state = self.passing.keep(packed(each, 1))

        def run(batches):
            for b in batches:
                for r in range(b.num_rows):
                    ids, got = pickle.loads(b.column("part")[r].as_buffer())
                    for s in range(0, len(ids), 1 << 14):
                        yield pa.RecordBatch.from_pydict({"user_id": pa.array(ids[s : s + (1 << 14)]), "vec": lists(got[s : s + (1 << 14)])})

        return add_rows(self.parts(state).mapInArrow(run, "user_id long, vec array<double>"))

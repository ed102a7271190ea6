"""Counts and closeness of all pairs of users by blocks of users: a task crosses two blocks and forms their pairs as a dense
matrix, complete over all attributes and paths, so pairs are never shuffled, summed by key or stored.

What a block's users have is packed into one row. Tasks get the rows of two blocks from Spark's own product of the stored
table with itself, which reads it again rather than shuffling copies of it.
"""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..linalg.blocks import add_rows, matrix
from ..storage import Passing, ship, store

#: Attributes multiplied at once, pairs expanded at once, cells worked on at once, and tasks that pack at most. Cells in work
#: and their batch of results stay in a core's cache.
COLUMNS, PAIRS, CELLS, TASKS = 4096, 1 << 21, 1 << 16, 4096
#: A product of `cells` times attributes is dense up to so many multiplications for each pair that shares an attribute: as
#: many as single precision does in the time that a pair takes in `_sparse` (measured: 0.02 and 20 ns).
DENSE_COST = 1000
#: Kinds of what users have on either end of a link: whom they follow (the middle of path 3), who follows them (of path 4).
OUT, IN = 3, 4

#: A matrix of counts: dense, or the places (row * columns + column) and values that aren't zero, or nothing.
Counts = np.ndarray | tuple[np.ndarray, np.ndarray] | None


def _small(a: np.ndarray) -> np.ndarray:
    return a.astype(np.min_scalar_type(int(a.max()) if len(a) else 0)) if not len(a) or a.min() >= 0 else a


def _packed(table: pa.Table) -> pa.Table:
    """One row of a block: its users ascending; what they have by kind (names, row, code, count); and by path the
    counts from and to each."""
    users = table.column("user_id").to_numpy()
    ids, row = np.unique(users, return_inverse=True)
    path = table.column("path").to_numpy()
    has = table.column("attr").is_valid().to_numpy(zero_copy_only=False)
    cnt, more = (table.column(c).to_numpy() for c in ("cnt", "more"))
    kinds, out, into = {}, {}, {}
    for p in np.unique(path[has]).tolist():
        at = has & (path == p)
        attr = table.column("attr").filter(pa.array(at)).combine_chunks().dictionary_encode()
        kinds[p] = (attr.dictionary, _small(row[at]), _small(attr.indices.to_numpy()), _small(cnt[at]))
    for p in np.unique(path[~has]).tolist():
        at = ~has & (path == p)
        out[p], into[p] = np.zeros(len(ids)), np.zeros(len(ids))
        out[p][row[at]], into[p][row[at]] = cnt[at], more[at]
    return pa.table({"block": table.column("block")[:1], "data": pa.array([pickle.dumps((ids, kinds, out, into), 5)], pa.binary())})


class Block:
    """A block as a task reads it."""

    def __init__(self, data: bytes, x: bytes | None = None):
        self.ids, self.kinds, self.out, self.into = pickle.loads(data)
        self.x = None
        if x is not None:
            users, rows = pickle.loads(x)
            self.x = np.zeros((len(self.ids), rows.shape[1]))
            at = np.minimum(np.searchsorted(self.ids, users), max(len(self.ids) - 1, 0))
            known = self.ids[at] == users if len(self.ids) else np.zeros(len(users), bool)
            self.x[at[known]] = rows[known]

    def themselves(self):
        n = np.arange(len(self.ids))
        return pa.array(self.ids).cast(pa.string()), n, n, np.ones(len(n), np.uint8)


def product(a, b, shape: tuple[int, int]) -> Counts:
    """Over attributes that both have, the product of the counts of a's and of b's users. Sums stay exact below 2^53."""
    if a is None or b is None or not len(a[1]) or not len(b[1]):
        return None
    (names, r1, c1, v1), (others, r2, c2, v2) = a, b
    to = pc.fill_null(pc.index_in(others.cast(names.type), value_set=names), -1).to_numpy()
    c2 = to[c2]
    f1, f2 = np.bincount(c1, minlength=len(names)), np.bincount(c2[c2 >= 0], minlength=len(names))
    common = (f1 > 0) & (f2 > 0)
    pairs, kinds = float(f1.astype(float) @ f2), int(common.sum())
    if not kinds:
        return None
    number = np.where(common, np.cumsum(common) - 1, -1)
    c1, c2 = number[c1], np.where(c2 >= 0, number[c2], -1)
    r1, c1, v1 = (x[c1 >= 0] for x in (r1, c1, v1))
    r2, c2, v2 = (x[c2 >= 0] for x in (r2, c2, v2))
    if float(shape[0]) * shape[1] * kinds <= DENSE_COST * pairs:
        return _dense((r1, c1, v1), (r2, c2, v2), shape, kinds)
    return _sparse((r1, c1, v1), (r2, c2, v2), shape, kinds)


def _dense(a, b, shape: tuple[int, int], kinds: int) -> np.ndarray:
    most = float(np.bincount(a[0], weights=a[2]).max()) * float(b[2].max())
    kind = np.float32 if most < 1 << 24 else np.float64  # single precision holds these sums exactly
    total = None
    for start in range(0, kinds, COLUMNS):
        end, sides = min(kinds, start + COLUMNS), []
        for (r, c, v), n in ((a, shape[0]), (b, shape[1])):
            at = slice(None) if kinds <= COLUMNS else (c >= start) & (c < end)
            m = np.zeros((n, end - start), kind)
            m[r[at], c[at] - start] = v[at]
            sides.append(m)
        got = sides[0] @ sides[1].T
        total = got if total is None else np.add(total, got, out=total)
    return total


def _sparse(a, b, shape: tuple[int, int], kinds: int) -> Counts:
    """Every pair of entries that share an attribute, some at a time."""
    (r1, c1, v1), (r2, c2, v2) = a, b
    order = np.argsort(c2, kind="stable")
    r2, v2 = r2[order].astype(np.int64), v2[order].astype(np.float64)
    first = np.searchsorted(c2[order], np.arange(kinds + 1))
    fan, r1 = np.diff(first)[c1], r1.astype(np.int64)
    upto = np.concatenate([[0], np.cumsum(fan)])
    few = upto[-1] < shape[0] * shape[1] // 16
    total, places, values, s = None if few else np.zeros(shape[0] * shape[1]), [], [], 0
    while s < len(c1):
        e = max(s + 1, min(len(c1), int(np.searchsorted(upto, upto[s] + PAIRS, "right")) - 1))
        many, ends = fan[s:e], np.cumsum(fan[s:e])
        at = np.repeat(first[c1[s:e]] - (ends - many), many) + np.arange(int(ends[-1]))
        place = np.repeat(r1[s:e] * shape[1], many) + r2[at]
        value = np.repeat(v1[s:e].astype(np.float64), many) * v2[at]
        if few:
            places.append(place)
            values.append(value)
        else:
            total += np.bincount(place, weights=value, minlength=len(total))
        s = e
    return _summed(np.concatenate(places), np.concatenate(values)) if few else total.reshape(shape)


def _summed(place: np.ndarray, value: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    places, at = np.unique(place, return_inverse=True)
    return places, np.bincount(at, weights=value)


def _whole(c: Counts, shape: tuple[int, int]) -> np.ndarray:
    if isinstance(c, np.ndarray):
        return c
    out = np.zeros(shape[0] * shape[1])
    if c is not None:
        out[c[0]] = c[1]
    return out.reshape(shape)


def _plus(a: Counts, b: Counts, shape: tuple[int, int]) -> Counts:
    if a is None or b is None:
        return a if b is None else b
    if isinstance(a, tuple) and isinstance(b, tuple):
        return _summed(np.concatenate([a[0], b[0]]), np.concatenate([a[1], b[1]]))
    return _whole(a, shape) + _whole(b, shape)


def counts(a: Block, b: Block, path: int, same: bool, self_paths: bool, twice: bool = True) -> Counts:
    """Counts of a path between a's and b's users, both ways together; one way of a symmetric path without `twice`."""
    shape = len(a.ids), len(b.ids)
    if path == 1:
        got = _plus(product(a.kinds.get(OUT), b.themselves(), shape), product(a.themselves(), b.kinds.get(OUT), shape), shape)
    elif path == 2:
        got = _plus(product(a.kinds.get(OUT), b.kinds.get(IN), shape), product(a.kinds.get(IN), b.kinds.get(OUT), shape), shape)
    else:
        got = product(a.kinds.get(path), b.kinds.get(path), shape)
        if twice and got is not None:
            got = 2 * got if isinstance(got, np.ndarray) else (got[0], 2 * got[1])
    if same and not self_paths and got is not None:
        if isinstance(got, np.ndarray):
            np.fill_diagonal(got, 0)
        else:
            keep = got[0] // shape[1] != got[0] % shape[1]
            got = got[0][keep], got[1][keep]
    return got


def _strips(shape: tuple[int, int]) -> Iterator[slice]:
    """Rows of a matrix, some cells at a time."""
    step = max(1, CELLS // max(1, shape[1]))
    return (slice(r, min(r + step, shape[0])) for r in range(0, shape[0], step))


def _add_shares(out: np.ndarray, got: Counts, weight: float, one: np.ndarray | None, two: np.ndarray | None) -> None:
    """out += weight * counts over one (a number a row) plus two (a number a column). A count that isn't 0 has 1 at least below it."""
    if isinstance(got, tuple):
        at, value = got
        i, j = at // out.shape[1], at % out.shape[1]
        below = (0 if one is None else one[i]) + (0 if two is None else two[j])
        out.reshape(-1)[at] += weight * value / below
        return
    one, two = (None if x is None else np.maximum(x, least) for x, least in ((one, two is None), (two, one is None)))
    bare = one is not None and two is not None and len(one) and len(two) and one.min() + two.min() < 1
    for s in _strips(out.shape):
        value = np.multiply(got[s], weight, dtype=np.float64)
        if two is None:
            value /= one[s, None]
        elif one is None:
            value /= two
        else:
            below = one[s, None] + two
            value /= np.maximum(below, 1, out=below) if bare else below
        out[s] += value


def scores(a: Block, b: Block, mix: dict[int, float], form: str, same: bool, self_paths: bool) -> tuple[np.ndarray, np.ndarray]:
    """Closeness of a's to b's users, and of b's to a's (turned, so that both have a's users as rows). form: pair, matrix,
    or symmetric (the mean of a matrix and its transpose)."""
    shape = len(a.ids), len(b.ids)
    forth = np.zeros(shape)
    back = forth if form != "matrix" else np.zeros(shape)
    for path, weight in mix.items():
        got = counts(a, b, path, same, self_paths, twice=False)
        if got is None:
            continue
        weight = weight if path <= 2 else 2 * weight  # both ways of a symmetric path
        if form == "pair":
            _add_shares(forth, got, weight, a.out[path], b.out[path])
        else:
            _add_shares(forth, got, weight, a.out[path] + a.into[path], None)
            _add_shares(back, got, weight, None, b.out[path] + b.into[path])
    if form == "symmetric":
        forth /= 2
    return forth, back


def _cells(a: Block, b: Block, got: Counts) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Users of a, of b, and what isn't 0 between them, some cells at a time."""
    n = len(b.ids)
    if isinstance(got, tuple):
        for r in range(0, len(got[0]), CELLS):
            at, value = got[0][r : r + CELLS], got[1][r : r + CELLS]
            yield a.ids[at // n], b.ids[at % n], value
        return
    for s in _strips(got.shape) if got is not None else ():
        part = np.ascontiguousarray(got[s])
        if part.all():
            yield np.repeat(a.ids[s], n), np.tile(b.ids, len(part)), part.reshape(-1)
        else:
            i, j = np.nonzero(part)
            yield a.ids[s][i], b.ids[j], part[i, j]


def _rows(src: np.ndarray, dst: np.ndarray, value: np.ndarray, name: str, kind: pa.DataType, **more) -> Iterator[pa.RecordBatch]:
    if len(src):
        part = {"src": pa.array(src), "dst": pa.array(dst)} | {k: pa.array(np.full(len(src), v, np.int32)) for k, v in more.items()}
        yield pa.RecordBatch.from_pydict(part | {name: pa.array(value.astype(kind.to_pandas_dtype(), copy=False), kind)})


class Blocks:
    """Users by blocks of about `size`, packed and stored. have: path (of a symmetric one: 3 to 7), user_id, attr, cnt.
    marginals: user_id, path, o, i, for closeness."""

    def __init__(self, have: DataFrame, users: int, size: int, marginals: DataFrame | None = None):
        self.spark = have.sparkSession
        ship(self.spark)
        self.count = max(1, -(-users // size), min(6, -(-users // 128)))
        rows = have.select("path", "user_id", F.col("attr").cast("string").alias("attr"), F.col("cnt").cast("long").alias("cnt"), F.lit(0).cast("long").alias("more"))
        rows = rows.filter("user_id is not null and attr is not null")
        if marginals is not None:
            none = F.lit(None).cast("string")
            rows = rows.union(marginals.select("path", "user_id", none.alias("attr"), F.col("o").cast("long").alias("cnt"), F.col("i").cast("long").alias("more")))
        self.table = store(self._dealt(rows).groupBy("block").applyInArrow(_packed, "block int, data binary"), "blocks")
        self.passing = Passing()

    def _dealt(self, rows: DataFrame) -> DataFrame:
        at = F.pmod(F.xxhash64("user_id"), F.lit(self.count)).cast("int")
        return rows.select(at.alias("block"), *rows.columns).repartition(min(TASKS, self.count), "block")

    def _with(self, rows: DataFrame) -> DataFrame:
        """Blocks beside rows (user_id, vec) of their users, stored: a product of tables needs its parts as files. What the
        product before the last one wrote is dropped."""

        def packed(table: pa.Table) -> pa.Table:
            one = pickle.dumps((table.column("user_id").to_numpy(), matrix(table.column("vec"))), 5)
            return pa.table({"block": table.column("block")[:1], "x": pa.array([one], pa.binary())})

        x = self._dealt(rows.select("user_id", "vec")).groupBy("block").applyInArrow(packed, "block int, x binary")
        return self.passing.keep(store(self.table.join(x, "block", "left").repartition(min(TASKS, self.count), "block"), "blocks"))

    def cross(self, work: Callable[[Block, Block, bool], Iterator], schema: str, table: DataFrame | None = None, last: Callable[[], Iterator] | None = None) -> DataFrame:
        """work(a, b, whether they are the same) of each unordered pair of blocks, in tasks; then last() of each task."""
        table = self.table if table is None else table
        x = F.col("x") if "x" in table.columns else F.lit(None).cast("binary")
        a = table.select(F.col("block").alias("a"), F.col("data").alias("da"), x.alias("xa"))
        b = table.select(F.col("block").alias("b"), F.col("data").alias("db"), x.alias("xb"))

        def run(batches):
            for batch in batches:
                for r in range(batch.num_rows):
                    one, two = (Block(batch.column("d" + s)[r].as_py(), batch.column("x" + s)[r].as_py()) for s in "ab")
                    yield from work(one, two, batch.column("a")[r].as_py() == batch.column("b")[r].as_py())
            if last is not None:
                yield from last()

        return a.hint("shuffle_replicate_nl").join(b, F.col("a") <= F.col("b")).mapInArrow(run, schema)

    def counts(self, paths: list[int], half: bool = False, self_paths: bool = False, with_path: bool = True) -> DataFrame:
        """src, dst, path, cnt of symmetric paths, each pair of a path once. half: only src <= dst."""

        def work(a, b, same):
            for path in paths:
                more = {"path": path} if with_path else {}
                for src, dst, got in _cells(a, b, counts(a, b, path, same, self_paths, twice=False)):
                    if half and same:
                        keep = src <= dst
                        src, dst, got = src[keep], dst[keep], got[keep]
                    elif half:
                        src, dst = np.minimum(src, dst), np.maximum(src, dst)
                    yield from _rows(src, dst, got, "cnt", pa.int64(), **more)
                    if not half and not same:
                        yield from _rows(dst, src, got, "cnt", pa.int64(), **more)

        return self.cross(work, f"src long, dst long, {'path int, ' if with_path else ''}cnt long")

    def closeness(self, mix: dict[int, float], form: str, self_paths: bool = False, digits: int | None = None) -> DataFrame:
        """src, dst, s of all pairs with closeness. digits: s is rounded to so many, halves up, as the rows are made."""

        def rounded(s):
            return s if digits is None else np.floor(s * 10.0**digits + 0.5) / 10.0**digits

        def work(a, b, same):
            forth, back = scores(a, b, mix, form, same, self_paths)
            for src, dst, s in _cells(a, b, forth):
                s = rounded(s)
                yield from _rows(src, dst, s, "s", pa.float64())
                if back is forth and not same:
                    yield from _rows(dst, src, s, "s", pa.float64())
            if back is not forth and not same:
                for src, dst, s in _cells(a, b, back):
                    yield from _rows(dst, src, rounded(s), "s", pa.float64())

        return self.cross(work, "src long, dst long, s double")

    def times(self, mix: dict[int, float], form: str, rows: DataFrame, squares: bool = False) -> DataFrame:
        """user_id, vec: closeness times rows (user_id, vec), of users in blocks. squares: one number more, the squared
        length of the user's row of closeness."""
        held: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        table = self._with(rows)
        one = table.filter("x is not null").select("x").head()  # a block's rows: their width is that of all
        width = pickle.loads(one["x"])[1].shape[1] if one else 0

        def add(block, other, s):
            got = s @ other.x
            if squares:
                got = np.hstack([got, np.einsum("ij,ij->i", s, s)[:, None]])
            key = int(block.ids[0])
            if key in held:
                held[key][1][:] += got
            else:
                held[key] = block.ids, got

        def work(a, b, same):
            if not squares and a.x is None and b.x is None:
                return
            a.x, b.x = (v.x if v.x is not None else np.zeros((len(v.ids), width)) for v in (a, b))
            forth, back = scores(a, b, mix, form, same, False)
            add(a, b, forth)
            if not same:
                add(b, a, back.T)
            yield from ()

        def last():
            for ids, got in held.values():
                flat = pa.array(np.ascontiguousarray(got).reshape(-1))
                yield pa.RecordBatch.from_pydict({"user_id": pa.array(ids), "vec": pa.ListArray.from_arrays(pa.array(np.arange(len(ids) + 1) * got.shape[1], pa.int32()), flat)})

        return add_rows(self.cross(work, "user_id long, vec array<double>", table, last))

    def inside(self, mix: dict[int, float], form: str, labels: DataFrame) -> DataFrame:
        """path, mass: the similarity by each path between users of one cluster (user_id, cluster)."""
        one = {p: 0.0 for p in mix}
        rows = labels.select("user_id", F.array(F.col("cluster").cast("double") + 1.0).alias("vec"))

        def work(a, b, same):
            if a.x is not None and b.x is not None:
                within = ((a.x == b.x.T) & (a.x > 0)).astype(np.float64)
                for p in mix:
                    forth, back = scores(a, b, {p: 1.0}, form, same, False)
                    one[p] += float(np.vdot(forth, within) + (0.0 if same else np.vdot(back, within)))
            yield from ()

        def last():
            yield pa.RecordBatch.from_pydict({"path": pa.array(list(one), pa.int32()), "mass": pa.array(list(one.values()), pa.float64())})

        return self.cross(work, "path int, mass double", self._with(rows), last).groupBy("path").agg(F.sum("mass").alias("mass"))

    def linked(self, mix: dict[int, float]) -> DataFrame:
        """pairs, direct: ordered pairs with closeness, and those of them with a link one way at least."""
        seen = [0, 0]

        def work(a, b, same):
            shape = len(a.ids), len(b.ids)
            s = np.zeros(shape[0] * shape[1], bool)  # counts are above 0 where closeness is
            for path in mix:
                got = counts(a, b, path, same, False, twice=False)
                if isinstance(got, tuple):
                    s[got[0]] = True
                elif got is not None:
                    s |= got.reshape(-1) > 0
            link = counts(a, b, 1, same, False)
            direct = s[link[0]] if isinstance(link, tuple) else s[link.reshape(-1) > 0] if link is not None else s[:0]
            both = 1 if same else 2
            seen[0] += both * int(s.sum())
            seen[1] += both * int(direct.sum())
            yield from ()

        def last():
            yield pa.RecordBatch.from_pydict({"pairs": pa.array(seen[:1], pa.int64()), "direct": pa.array(seen[1:], pa.int64())})

        return self.cross(work, "pairs long, direct long", None, last).agg(F.coalesce(F.sum("pairs"), F.lit(0)).alias("pairs"), F.coalesce(F.sum("direct"), F.lit(0)).alias("direct"))

    def closest(self, mix: dict[int, float], top: int, digits: int) -> DataFrame:
        """src, dst, s (pair form): at least each user's `top` closest of each task by s rounded to `digits`, ties by dst;
        twice as many are kept, so that how a last digit is rounded decides nothing here."""
        keep, scale = 2 * top, 10.0**digits
        held: dict[int, tuple] = {}

        def key(s):
            return np.floor(s * scale + 0.5).astype(np.int64)

        def add(block, other, s):
            """held: by block its users, the least closeness that can still matter to each, and rows (row, key, dst, s)."""
            ids, least, rows = held.get(int(block.ids[0]), (block.ids, np.zeros(len(s)), None))
            for part in _strips(s.shape):
                strip = np.ascontiguousarray(s[part])
                if rows is None and strip.shape[1] > 4 * keep:  # nothing held yet: the strip's own say what matters
                    low = np.partition(strip, strip.shape[1] - keep, axis=1)[:, strip.shape[1] - keep]
                    least[part] = np.maximum((key(low) - 1) / scale, 0)
                i, j = np.nonzero((strip > 0) & (strip >= least[part, None]))
                value = strip[i, j]
                parts.append((i + part.start, key(value), other.ids[j], value))
            new = [np.concatenate(x) for x in zip(*([rows] if rows is not None else []), *parts, strict=True)]
            parts.clear()
            order = np.lexsort((new[2], -new[1], new[0]))
            new = [x[order] for x in new]
            first = np.searchsorted(new[0], np.arange(len(ids)))
            new = [x[(np.arange(len(order)) - first[new[0]]) < keep] for x in new]
            many = np.bincount(new[0], minlength=len(ids))
            full = many == keep
            least[full] = np.maximum((new[1][np.cumsum(many)[full] - 1] - 1) / scale, 0)
            held[int(block.ids[0])] = ids, least, new

        parts: list[tuple] = []

        def work(a, b, same):
            s = scores(a, b, mix, "pair", same, False)[0]
            add(a, b, s)
            if not same:
                add(b, a, s.T)
            yield from ()

        def last():
            for ids, _, (row, _, dst, s) in held.values():
                yield from _rows(ids[row], dst, s, "s", pa.float64())

        return self.cross(work, "src long, dst long, s double", None, last)

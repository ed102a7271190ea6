"""Near-duplicate vectors by collision counting on sorted one-dimensional projections, verified in double precision."""

from __future__ import annotations

import hashlib
import math
from statistics import NormalDist

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import join_small, ship, store
from .components import connected_components, roots
from .words import released

#: Vectors of a block, about; two blocks are compared in one task: a few dozen MB, and each vector goes to few tasks.
BLOCK = 8192
#: Vectors whose collisions with as many others are counted at once.
TILE = 1024
#: Projections that cells may use.
AXES = range(2, 7)


def calibrate(cosine: float, projections: int, width: float = 1.45, miss: float = 1e-5) -> tuple[float, int]:
    """Half-width of a window on a Gaussian projection of unit vectors, and the collisions a pair needs.

    A pair at the threshold lies sqrt(2 - 2 cosine) apart, so its projections differ by a Gaussian of that deviation; the
    window takes `width` deviations. The count is the largest that such a pair misses with probability at most `miss`
    (binomial); nearer pairs miss less.
    """
    p = math.erf(width / math.sqrt(2))
    total, need = 0.0, 0
    for k in range(projections + 1):
        total += math.comb(projections, k) * p**k * (1 - p) ** (projections - k)
        if total > miss:
            break
        need = k + 1
    return width * math.sqrt(2 - 2 * cosine), need


def projection(dim: int, count: int) -> np.ndarray:
    """Random directions, all of length sqrt(dim): projections of unit vectors then have a deviation of 1."""
    lines = np.random.default_rng(1000003 * dim + count).standard_normal((dim, count))
    return lines * (math.sqrt(dim) / np.linalg.norm(lines, axis=0))


def cell_axes(classes: int) -> int:
    """How many projections make up a cell: one more for each fourfold number of different vectors, so that cells of
    ordinary density keep to a few blocks. Each leaves about 0.6 of the pairs to compare."""
    return min(max(AXES.start, AXES.start + math.floor(math.log(max(classes, 1) / (2 * BLOCK), 4))), AXES.stop - 1)


def cell_width(cosine: float, axes: int, miss: float) -> float:
    """So wide that a pair at the threshold lies in one cell or two neighbours, on all axes, but for a chance of `miss`."""
    return -NormalDist().inv_cdf(miss / (2 * axes)) * math.sqrt(2 - 2 * cosine)


def collisions(left: np.ndarray, right: np.ndarray, half: float) -> np.ndarray:
    """For each pair of rows, in how many columns the right value lies in the window around the left one. Each column of
    `right` is sorted once; a query's window is then a range of ranks."""
    counts = np.zeros((len(left), len(right)), np.uint8)
    for k in range(left.shape[1]):
        order = np.argsort(right[:, k], kind="stable")
        rank = np.empty(len(right), np.uint16)
        rank[order] = np.arange(len(right), dtype=np.uint16)
        line = right[order, k]
        lo = np.searchsorted(line, left[:, k] - half, "left").astype(np.uint16)
        size = np.searchsorted(line, left[:, k] + half, "right").astype(np.uint16) - lo
        counts += (rank[None, :] - lo[:, None]) < size[:, None]  # unsigned: below lo wraps round
    return counts


def _read(vectors: DataFrame, projections: int) -> DataFrame:
    """vec_id, dim (0 if it can't link), h1, h2 (digest of the vector), line (its first projections) and unit."""

    def run(batches):
        lines = {}
        for b in batches:
            ids, out = b.column("vec_id"), []
            for v in b.column("v").to_pylist():
                x = np.array(v, np.float64) if v and None not in v else np.zeros(0)
                top = np.abs(x).max() if len(x) and np.isfinite(x).all() else 0.0
                if top == 0:
                    out.append((0, 0, 0, [], b""))
                    continue
                x = x + 0.0
                digest = np.frombuffer(hashlib.md5(x.tobytes()).digest(), np.int64)
                unit = x / top
                unit = unit / np.sqrt(unit @ unit)
                if len(x) not in lines:
                    lines[len(x)] = projection(len(x), projections)[:, : AXES.stop - 1]
                out.append((len(x), int(digest[0]), int(digest[1]), (unit @ lines[len(x)]).tolist(), unit.tobytes()))
            cols = list(zip(*out, strict=True)) if out else [[]] * 5
            kinds = (pa.int32(), pa.int64(), pa.int64(), pa.list_(pa.float64()), pa.binary())
            yield pa.RecordBatch.from_arrays([ids, *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], names=["vec_id", "dim", "h1", "h2", "line", "unit"])

    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v"))
    return rows.mapInArrow(released(run), "vec_id long, dim int, h1 long, h2 long, line array<double>, unit binary")


def vector_duplicates(vectors: DataFrame, cosine: float = 0.95, projections: int = 40, cell_miss: float = 1.3e-4, axes: int | None = None, small: int = 1_000_000) -> DataFrame:
    """vec_id, n_links, component_id, kept for each row of vectors (vec_id, embedding).

    Vectors that are null, empty, zero, or hold null or non-finite components link with nothing; vectors of different
    lengths too. Equal vectors form a class and are compared once. The first projections (two to six, by `cell_axes`, or
    `axes`) put classes into cells so wide that a pair at the threshold lies in one cell or two neighbours but for a
    chance of `cell_miss`; cells are cut into blocks of about BLOCK, and each pair of neighbouring blocks counts collisions
    over all projections, checks pairs that reach the calibrated count by cosine in double precision, and returns
    each vector's number of links and a spanning forest of them, never the pairs. A cosine equal to the threshold links.
    Repeated rows are vectors of their own; component_id is the smallest vec_id reachable, null if none there has one; an
    empty table gives an empty one; other columns, whatever their names, are ignored.
    """
    ship(vectors.sparkSession)
    half, need = calibrate(cosine, projections)
    read = store(_read(vectors, projections), "vectors")
    good = read.filter("dim > 0")
    # Classes have numbers of their own: vec_ids, which may be null or shared by different vectors, only name the outcome.
    grouped = good.groupBy("dim", "h1", "h2").agg(F.min("vec_id").alias("least"), F.count("*").alias("n"), F.first("line").alias("line"), F.first("unit").alias("unit"))
    classes = store(grouped.withColumn("rep", F.monotonically_increasing_id()), "classes")
    axes = min(projections, axes or cell_axes(classes.count()))
    width = cell_width(cosine, axes, cell_miss)
    in_cells = classes.withColumn("cell", F.transform(F.slice("line", 1, axes), lambda x: F.floor(x / width).cast("int"))).drop("line")

    # One row a cell: the projections of unit vectors lie within a few deviations, so cells don't grow with the data.
    cells = store(in_cells.groupBy("dim", "cell").agg(F.count("*").alias("m")).withColumn("subs", F.ceil(F.col("m") / BLOCK).cast("int")).drop("m"), "cells")
    n_cells = cells.count()
    near = cells.withColumn("to", F.array().cast("array<int>"))
    for k in range(axes):  # a neighbour's cell, axis by axis
        near = near.withColumn("step", F.explode(F.array(F.lit(-1), F.lit(0), F.lit(1)))).withColumn("to", F.array_append("to", F.col("cell")[k] + F.col("step"))).drop("step")
    other = cells.select(F.col("dim").alias("odim"), F.col("cell").alias("ocell"), F.col("subs").alias("osubs"))
    near = near.filter(F.col("cell") <= F.col("to")).join(other, (F.col("dim") == F.col("odim")) & (F.col("to") == F.col("ocell")))
    grid = near.withColumn("sub", F.explode(F.sequence(F.lit(0), F.col("subs") - 1))).withColumn("osub", F.explode(F.sequence(F.lit(0), F.col("osubs") - 1)))
    mine, theirs = F.struct("cell", "sub"), F.struct(F.col("ocell"), F.col("osub"))
    grid = grid.filter(mine <= theirs).select("dim", F.xxhash64("dim", "cell", "sub", "ocell", "osub").alias("task"), "cell", "sub", "ocell", "osub")
    ends = grid.select("dim", "cell", "sub", "task", F.lit(0).alias("side")).union(grid.filter(mine != theirs).select("dim", "ocell", "osub", "task", F.lit(1)))
    ends = store(ends.groupBy("dim", "cell", "sub").agg(F.collect_list(F.struct("task", "side")).alias("tasks")), "block-pairs")

    placed = join_small(in_cells, cells, ["dim", "cell"], "inner", n_cells, small).withColumn("sub", F.pmod(F.xxhash64("rep"), F.col("subs")).cast("int"))
    dealt = join_small(placed, ends, ["dim", "cell", "sub"], "inner", ends.count(), small // 10).select(F.explode("tasks").alias("t"), "rep", "n", "unit", "dim").select("t.task", "t.side", "rep", "n", "unit", "dim")

    def compare(t: pa.Table) -> pa.Table:
        side, rep, n = (t.column(c).to_numpy() for c in ("side", "rep", "n"))
        dim = t.column("dim")[0].as_py()
        unit = np.frombuffer(b"".join(t.column("unit").to_pylist()), np.float64).reshape(-1, dim)
        order = np.argsort(rep, kind="stable")
        side, rep, n, unit = side[order], rep[order], n[order], unit[order]
        line = (unit @ projection(dim, projections)).astype(np.float32)
        own = not (side == 1).any()
        a = np.flatnonzero(side == 0)
        b = a if own else np.flatnonzero(side == 1)
        degree, left, right = np.zeros(len(rep), np.int64), [], []
        for lo in range(0, len(a), TILE):
            for so in range(0, len(b), TILE):
                x, y = a[lo : lo + TILE], b[so : so + TILE]
                i, j = np.nonzero(collisions(line[x], line[y], np.float32(half)) >= need)
                if own:
                    i, j = i[x[i] < y[j]], j[x[i] < y[j]]
                for k in range(0, len(i), 1 << 16):
                    p, q = x[i[k : k + (1 << 16)]], y[j[k : k + (1 << 16)]]
                    ok = np.einsum("ij,ij->i", unit[p], unit[q]) >= cosine
                    p, q = p[ok], q[ok]
                    np.add.at(degree, p, n[q])
                    np.add.at(degree, q, n[p])
                    if len(p):
                        nodes, low = roots(np.concatenate([p, *left]), np.concatenate([q, *right]))
                        left, right = [nodes[nodes != low]], [low[nodes != low]]
        some = np.flatnonzero(degree)
        p, q = (np.concatenate(s) if s else np.zeros(0, np.int64) for s in (left, right))
        return pa.table({
            "edge": pa.array(np.repeat([False, True], [len(some), len(p)])),
            "a": pa.array(np.concatenate([rep[some], rep[p]])),
            "b": pa.array(np.concatenate([degree[some], rep[q]])),
        })

    found = store(dealt.groupBy("task").applyInArrow(released(compare), "edge boolean, a long, b long"), "links")
    degree = found.filter("not edge").groupBy(F.col("a").alias("_node")).agg(F.sum("b").alias("_degree"))
    label = store(connected_components(found.filter("edge").select("a", "b")), "labels")
    ids = classes.select("dim", "h1", "h2", "rep", "least", "n")
    first = label.join(ids, F.col("rep") == F.col("node")).groupBy("component").agg(F.min("least").alias("first"))
    named = label.join(first, "component").select("node", "first", F.lit(True).alias("linked"))
    of = ids.join(degree, F.col("rep") == F.col("_node"), "left").join(named, F.col("rep") == F.col("node"), "left")
    name = F.when(F.col("linked"), F.col("first")).otherwise(F.col("least"))
    of = of.select(F.col("dim").alias("_d"), F.col("h1").alias("_h1"), F.col("h2").alias("_h2"), (F.col("n") - 1 + F.coalesce("_degree", F.lit(0))).alias("n_links"), name.alias("component_id"))
    out = good.join(of, (F.col("dim") == F.col("_d")) & (F.col("h1") == F.col("_h1")) & (F.col("h2") == F.col("_h2")))
    rows = out.select("vec_id", "n_links", "component_id")
    rows = rows.union(read.filter("dim = 0").select("vec_id", F.lit(0).cast("long"), F.col("vec_id").alias("component_id")))
    return rows.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


#: The same rows by all pairs of vectors, at the defaults, for tables small enough for that.
ORACLE = """
WITH RECURSIVE given AS (SELECT row_number() OVER () AS r, vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings),
good AS (
  SELECT r, vec_id, len(e) AS dim, list_transform(e, lambda x: x / list_max(list_transform(e, lambda y: abs(y)))) AS e FROM given
  WHERE len(e) > 0 AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND list_max(list_transform(e, lambda y: abs(y))) > 0),
normed AS (SELECT r, vec_id, dim, e, sqrt(list_sum(list_transform(e, lambda x: x * x))) AS n FROM good),
links AS MATERIALIZED (
  SELECT a.r, a.vec_id AS a, b.vec_id AS b FROM normed a JOIN normed b ON a.r <> b.r AND a.dim = b.dim
  WHERE list_inner_product(a.e, b.e) / (a.n * b.n) >= 0.95),
reach AS (SELECT a AS node, b AS other FROM links UNION SELECT reach.node, links.b FROM reach JOIN links ON reach.other = links.a),
least_ AS (SELECT node, least(node, min(other)) AS component_id FROM reach GROUP BY node)
SELECT vec_id, (SELECT count(*) FROM links l WHERE l.r = g.r) AS n_links, coalesce(component_id, vec_id) AS component_id, coalesce(component_id, vec_id) = vec_id AS kept
FROM given g LEFT JOIN least_ ON node = vec_id
"""

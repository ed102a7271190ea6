"""Lloyd's rounds on tables, through products of rows with the k centres only."""

from __future__ import annotations

from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..linalg.blocks import matrix, spmm, sums
from ..storage import drop_stored, free, store


class FeatureTable:
    """Sparse rows (user_id, dim, x), stored."""

    def __init__(self, features: DataFrame):
        self.features = store(features.select("user_id", F.col("dim").cast("long").alias("dim"), "x"), "features")

    @cached_property
    def users(self) -> DataFrame:
        """user_id, xx (squared length)."""
        return store(self.features.groupBy("user_id").agg(F.sum(F.col("x") * F.col("x")).alias("xx")), "users")

    def times(self, rows: DataFrame) -> DataFrame:
        """Rows (user_id: a dimension, vec), summed by user with weights x."""
        return spmm(self.features.select(F.col("user_id").alias("src"), F.col("dim").alias("dst"), F.col("x").alias("w")), rows)

    def turned(self, rows: DataFrame) -> DataFrame:
        """Rows (user_id, vec), summed by dimension with weights x."""
        return spmm(self.features.select(F.col("dim").alias("src"), F.col("user_id").alias("dst"), F.col("x").alias("w")), rows)


class SquareTable:
    """Rows of a symmetric matrix that is known by its products alone: times(rows) -> rows. users: user_id, xx (0 where
    squared lengths aren't known; they only choose which row an empty cluster is given). lengths: gives user_id, xx, and is
    asked for them when a cluster is empty."""

    def __init__(self, users: DataFrame, times, lengths=None):
        self.users, self.times, self.turned, self.asked = users, times, times, lengths

    @cached_property
    def lengths(self) -> DataFrame | None:
        return None if self.asked is None else self.asked()


def _unit(k: int, value):
    """A row of k numbers: `value` at the row's cluster, 0 elsewhere."""
    return F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda c: F.when(c == F.col("cluster"), value).otherwise(F.lit(0.0)))


def centroids(rows, labels: DataFrame, k: int) -> DataFrame:
    """user_id (a dimension), vec: the k centres' values there. Stored."""
    size = labels.groupBy("cluster").agg(F.count("*").alias("n"))
    one = labels.join(F.broadcast(size), "cluster").select("user_id", _unit(k, 1 / F.col("n")).alias("vec"))
    return store(rows.turned(one), "centres")


def nearest(rows, centres: DataFrame, k: int) -> DataFrame:
    """user_id, cluster (the nearest centre, the lower on ties) and d2, the squared distance. k numbers reach the driver."""
    norm = sums(centres, ["vec"], lambda c: {"cc": (c["vec"] ** 2).sum(0)[None]}).get("cc")
    cc = F.array(*[F.lit(float(x)) for x in (norm[0] if norm is not None else [0.0] * k)])
    dots = rows.times(centres).withColumnRenamed("vec", "dots")
    far = F.zip_with(F.coalesce("dots", F.array_repeat(F.lit(0.0), k)), cc, lambda x, q: F.round(q - 2 * x, 12))
    all_ = rows.users.join(dots, "user_id", "left").select("user_id", "xx", far.alias("far"))
    return all_.select("user_id", (F.array_position("far", F.array_min("far")) - 1).cast("int").alias("cluster"), (F.array_min("far") + F.col("xx")).alias("d2"))


def step(features: DataFrame, labels: DataFrame) -> DataFrame:
    """user_id, cluster after one round."""
    rows, k = FeatureTable(features), labels.agg(F.max("cluster")).first()[0] + 1
    return nearest(rows, centroids(rows, labels, k), k).select("user_id", "cluster")


def _filled(labels: DataFrame, k: int, rows=None) -> DataFrame:
    """labels with the farthest users moved to clusters that have none (k numbers and at most k ids reach the driver). rows: may
    know squared lengths that d2 lacks yet."""
    used = {r["cluster"] for r in labels.select("cluster").distinct().collect()}
    empty = [c for c in range(k) if c not in used]
    if not empty:
        return labels
    if (lengths := getattr(rows, "lengths", None)) is not None:
        labels = labels.join(lengths, "user_id").select("user_id", "cluster", (F.col("d2") + F.col("xx")).alias("d2"))
    crowded = labels.groupBy("cluster").agg(F.count("*").alias("n")).filter("n > 1").select("cluster")
    far = [r["user_id"] for r in labels.join(F.broadcast(crowded), "cluster", "left_semi").orderBy(F.col("d2").desc(), "user_id").limit(len(empty)).collect()]
    move = labels.sparkSession.createDataFrame(list(zip(far, empty, strict=False)), "user_id long, to int")
    return store(labels.join(F.broadcast(move), "user_id", "left").select("user_id", F.coalesce("to", "cluster").alias("cluster"), F.when(F.col("to").isNull(), F.col("d2")).otherwise(0.0).alias("d2")), "labels")


def lloyd_rows(rows, k: int, rounds: int = 20, seed: int = 0, start: DataFrame | None = None) -> DataFrame:
    """user_id, cluster, d2, stored. Begins with k rows drawn by a hash of user_id, or from labels; stops when nothing
    moves. k is cut to the number of users; an empty cluster is given the farthest user."""
    users = rows.users
    k = min(k, users.count())
    if not k:
        return users.select("user_id", F.lit(0).alias("cluster"), F.lit(0.0).alias("d2"))
    if start is None:
        ids = [r["user_id"] for r in users.orderBy(F.xxhash64("user_id", F.lit(seed)), "user_id").limit(k).select("user_id").collect()]  # k ids
        start = users.sparkSession.createDataFrame([(u, c) for c, u in enumerate(ids)], "user_id long, cluster int")
        start = nearest(rows, centroids(rows, start, k), k)
    labels = _filled(store(start, "labels"), k, rows) if "d2" in start.columns else _filled(store(start.withColumn("d2", F.lit(0.0)), "labels"), k)
    for _ in range(rounds):
        centres = centroids(rows, labels, k)
        new = _filled(store(nearest(rows, centres, k), "labels"), k, rows)
        drop_stored(centres)
        moved = new.join(labels.select("user_id", F.col("cluster").alias("was")), "user_id").filter("cluster <> was").limit(1).count()
        labels = new
        free(labels.sparkSession)
        if not moved:
            break
    return labels


def lloyd(features: DataFrame, k: int, rounds: int = 20, seed: int = 0, start: DataFrame | None = None) -> DataFrame:
    """user_id, cluster of sparse rows (user_id, dim, x); as lloyd_rows."""
    return lloyd_rows(FeatureTable(features), k, rounds, seed, start).select("user_id", "cluster")


class _Labelling:
    """Users' clusters as tasks form them: by the nearest centre (or, without centres, the largest entry), but for some users
    that were given to empty clusters."""

    def __init__(self, centres: np.ndarray | None = None):
        self.centres, self.given = centres, {}

    def of(self, users: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Clusters (the lower on ties) and squared distances."""
        if self.centres is None:
            label, d2 = np.abs(x).argmax(1), np.zeros(len(x))
        else:
            far = np.round((self.centres**2).sum(1) - 2 * (x @ self.centres.T), 12)
            label = far.argmin(1)
            d2 = far[np.arange(len(x)), label] + (x * x).sum(1)
        for user, c in self.given.items():
            label[users == user], d2[users == user] = c, 0.0
        return label, d2


def _totals(rows: DataFrame, k: int, pairs: list) -> list[dict]:
    """Of each (labelling, the one before or None), in one pass: users n and sums of rows s by cluster, users that moved, cost."""

    def parts(c):
        out = {}
        for i, (now, old) in enumerate(pairs):
            label, d2 = now.of(c["user_id"], c["vec"])
            one = np.zeros((len(label), k))
            one[np.arange(len(label)), label] = 1.0
            moved = np.nan if old is None else float((label != old.of(c["user_id"], c["vec"])[0]).sum())
            out |= {f"n{i}": one.sum(0)[None], f"s{i}": one.T @ c["vec"], f"m{i}": np.array([[moved, d2.sum()]])}
        return out

    got = sums(rows, ["user_id", "vec"], parts)
    return [{"n": got[f"n{i}"][0], "s": got[f"s{i}"], "moved": got[f"m{i}"][0, 0], "cost": got[f"m{i}"][0, 1]} for i in range(len(pairs))]


def _farthest(rows: DataFrame, label: _Labelling, n: np.ndarray) -> list[int]:
    """As many users as there are empty clusters, the farthest of clusters of two or more."""
    many = int((n == 0).sum())

    def run(batches):
        for b in batches:
            users = b.column("user_id").to_numpy()
            c, d2 = label.of(users, matrix(b.column("vec")))
            at = np.flatnonzero(n[c] > 1)
            at = at[np.lexsort((users[at], -d2[at]))[:many]]
            yield pa.RecordBatch.from_pydict({"user_id": pa.array(users[at]), "d2": pa.array(d2[at])})

    far = rows.mapInArrow(run, "user_id long, d2 double").orderBy(F.col("d2").desc(), "user_id").limit(many)
    return [r["user_id"] for r in far.collect()]


def dense_clusters(rows: DataFrame, k: int, rounds: int, seed: int = 0) -> DataFrame:
    """user_id, cluster of stored rows (user_id, vec): the better of Lloyd's rounds from each row's largest entry and from k drawn
    rows. As lloyd_rows, but rows are read once a round for both; k centres are what reaches the driver, and labels are formed
    anew from them."""
    drawn = rows.orderBy(F.xxhash64("user_id", F.lit(seed)), "user_id").limit(k).toArrow()
    if not drawn.num_rows:
        return rows.select("user_id", F.lit(0).alias("cluster"))
    k = min(k, drawn.num_rows)

    def filled(label: _Labelling, got: dict, old: _Labelling | None) -> dict:
        if (got["n"] > 0).all():
            return got
        label.given = dict(zip(_farthest(rows, label, got["n"]), np.flatnonzero(got["n"] == 0).tolist(), strict=False))
        return _totals(rows, k, [(label, old)])[0]

    labels = [_Labelling(), _Labelling(matrix(drawn.column("vec")))]
    found = [filled(x, got, None) for x, got in zip(labels, _totals(rows, k, [(x, None) for x in labels]), strict=True)]
    going = [0, 1]
    for _ in range(rounds):
        new = [_Labelling(found[i]["s"] / np.maximum(found[i]["n"], 1.0)[:, None]) for i in going]
        for i, x, got in zip(going, new, _totals(rows, k, [(x, labels[i]) for i, x in zip(going, new, strict=True)]), strict=True):
            labels[i], found[i] = x, filled(x, got, labels[i])
        going = [i for i in going if found[i]["moved"]]
        if not going:
            break
    best = labels[0 if found[0]["cost"] <= found[1]["cost"] else 1]

    def run(batches):
        for b in batches:
            users = b.column("user_id").to_numpy()
            yield pa.RecordBatch.from_pydict({"user_id": pa.array(users), "cluster": pa.array(best.of(users, matrix(b.column("vec")))[0].astype(np.int32))})

    return rows.mapInArrow(run, "user_id long, cluster int")

"""Comparators: normalised cut and K-means of each network alone, and propagation over both with factorisation."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.hetnet import AlignedSet, HetNet
from ..operators.closeness import CrossedCloseness, closeness, symmetric_part
from ..optimize.local import Laplacian, SimilarityRows, assign, indicator, kmeans, orthonormal, spectral
from ..storage import free, store
from .onetask import Prepared, batch, fits

_SCHEMA = [("net", pa.int32()), ("user_id", pa.int64()), ("cluster", pa.int32())]
_TYPES = "net int, user_id long, cluster int"


def social_entries(net: HetNet) -> DataFrame:
    """Links both ways as entries of 1."""
    return net.undirected().select("src", "dst", F.lit(1.0).alias("s"))


def _closeness(net: HetNet, weights, form: str) -> DataFrame:
    S = closeness(net, weights, form)
    return store(symmetric_part(S) if form == "matrix" else S, f"closeness-{net.name}")


def _labelled(users: np.ndarray, lap: Laplacian, label_of_live) -> pa.RecordBatch:
    label = np.full(len(users), -1, np.int64)
    live = lap.degree > 0
    if live.any():
        label[live] = label_of_live(live)
    return batch(_SCHEMA, net=np.zeros(len(users), int), user_id=users, cluster=label)


def _alone(net: HetNet, S, weights, form: str, engine: str, label, tables, name: str) -> DataFrame:
    """user_id, cluster by label(lap, live) in a task, or by tables(S)."""
    if S is None and weights is None:
        S = store(social_entries(net), f"links-{net.name}")
        free(S.sparkSession)
    prepared = None
    if engine == "task" or (engine == "auto" and (S is None or fits(S))):
        prepared = Prepared.of([net], weights or "uniform", form, None if S is None else [S])
    if prepared is None or (engine == "auto" and not prepared.whole):
        crossed = CrossedCloseness.of(net, weights, "symmetric" if form == "matrix" else form) if S is None else None
        return tables(S if S is not None else crossed or _closeness(net, weights, form))
    laplacian = prepared.reader()

    def work(held):
        users, lap = laplacian(held, 0)
        yield _labelled(users, lap, lambda live: label(lap, live))

    return store(prepared.run(work, _TYPES), name).select("user_id", "cluster")


def normalized_cut(net: HetNet, k: int, seed: int = 0, S: DataFrame | None = None, engine: str = "auto", weights=None, form: str = "pair") -> DataFrame:
    """user_id, cluster by the relaxed normalised cut of one network: of its links, of S, or of the closeness by `weights`.
    Every user has a row; isolated ones get -1."""

    def label(lap, live):
        x = spectral(lap, min(k, lap.n), seed)
        return assign(x[live], lap.degree[live], "kmeans_rows", seed)

    def tables(S_):
        from .distributed import spectral_partition

        return spectral_partition(net.users, S_, k, seed)

    return _alone(net, S, weights, form, engine, label, tables, "ncut")


def spectral_check(net: HetNet, k: int, seed: int = 0) -> DataFrame:
    """orthonormal, smallest: whether the relaxed rows of net's links have X'X = I, and cost no more than the indicator rows
    of the partition that they lead to, which meet the same constraint."""
    prepared = Prepared.of([net], "social", "pair", [social_entries(net)])
    laplacian = prepared.reader()

    def work(held):
        _, lap = laplacian(held, 0)
        x, live = spectral(lap, k, seed), np.flatnonzero(lap.degree > 0)
        label = np.zeros(lap.n, np.int64)
        label[live] = assign(x[live], lap.degree[live], "kmeans_rows", seed)
        y = indicator(label, lap.degree, k)
        cost = lambda v: float(np.trace(v.T @ lap(v)))
        yield pa.RecordBatch.from_pydict({"orthonormal": [bool(np.abs(x.T @ x - np.eye(k)).max() < 1e-9)], "smallest": [cost(x) <= cost(y) + 1e-9]})

    return prepared.run(work, "orthonormal boolean, smallest boolean")


def kmeans_rows(net: HetNet, k: int, seed: int = 0, S: DataFrame | None = None, engine: str = "auto", weights=None, form: str = "pair", restarts: int = 3) -> DataFrame:
    """user_id, cluster by K-means on whole rows: of links, of S, or of the closeness by `weights`. Every user has a row;
    isolated ones get -1. `restarts` is the task's; tables start once."""

    def label(lap, live):
        return kmeans(SimilarityRows(lap, np.flatnonzero(live)), k, seed, restarts=restarts)

    def tables(S_):
        from .kmeans import lloyd, lloyd_rows

        if isinstance(S_, CrossedCloseness):
            from .distributed import CrossedOperator

            got = lloyd_rows(CrossedOperator(S_).similarity_rows(), k, seed=seed).select("user_id", "cluster")
            return net.users.join(got, "user_id", "left").select("user_id", F.coalesce("cluster", F.lit(-1)).alias("cluster"))
        got = lloyd(S_.select(F.col("src").alias("user_id"), F.col("dst").alias("dim"), F.col("s").alias("x")), k, seed=seed)
        return net.users.join(got, "user_id", "left").select("user_id", F.coalesce("cluster", F.lit(-1)).alias("cluster"))

    return _alone(net, S, weights, form, engine, label, tables, "kmeans")


def propagation(aligned: AlignedSet, k: list[int], closenesses: list[DataFrame] | None = None, restart: float = 0.15, hops: int = 5, gamma: float = 0.5, seed: int = 0, weights="uniform", form: str = "matrix", rounds: int = 40, engine: str = "auto", prepared: Prepared | None = None) -> list[DataFrame]:
    """Partitions of both networks from user intimacy that spreads within and across them.

    Our reading of an idea that is only sketched: over the users of both networks, a step goes along row-normalised
    closeness, or with probability gamma from an anchor to its counterpart; intimacy is the restart series cut after
    `hops`, its symmetric part is factorised at rank k by orthogonal iteration (only products with it are formed), and
    each network's users are grouped by K-means on their rows of the factor. engine as in mutual_cluster.
    """
    anchors = aligned.anchors[0, 1]
    if engine != "tables" and prepared is None:
        prepared = Prepared.of(aligned.nets[:2], weights, form, closenesses)
    if engine == "tables" or prepared is None or (engine == "auto" and not prepared.whole):
        from .distributed import propagation_tables

        return propagation_tables(aligned, closenesses or [_closeness(n, weights, form) for n in aligned.nets[:2]], k, restart, hops, gamma, seed, rounds)
    laplacian = prepared.reader()
    more = {"a": anchors.select(F.col("u1").alias("a"), F.col("u2").alias("b"), F.lit(1.0).alias("v"))}

    def work(held):
        (ua, la), (ub, lb) = (laplacian(held, i) for i in (0, 1))
        n = len(ua) + len(ub)
        a, b, _ = held["a"]
        ok = np.isin(a, ua) & np.isin(b, ub)
        ia, ib = np.searchsorted(ua, a[ok]), np.searchsorted(ub, b[ok]) + len(ua)
        other = np.full(n, -1)
        other[ia], other[ib] = ib, ia
        at = np.flatnonzero(other >= 0)

        def inner(v, transpose):
            """Row-normalised closeness of both networks times v: D^-1 S = D^-1/2 (normalised S) D^1/2."""
            out = np.empty_like(v)
            for lap, s in ((la, slice(0, len(ua))), (lb, slice(len(ua), n))):
                up = np.sqrt(np.where(lap.degree > 0, lap.degree, 1))[:, None]
                down = lap.root[:, None]
                out[s] = up * lap.times(down * v[s]) if transpose else down * lap.times(up * v[s])
            return out

        stay = np.ones((n, 1))
        stay[at] = 1 - gamma

        def walk(v, transpose=False):
            cross = np.zeros_like(v)
            cross[at] = gamma * v[other[at]]
            return inner(stay * v, True) + cross if transpose else stay * inner(v, False) + cross

        def series(v, transpose):
            total, term = restart * v, v
            for _ in range(hops):
                term = (1 - restart) * walk(term, transpose)
                total = total + restart * term
            return total

        width = min(n, 2 * max(k) + 5)
        q = orthonormal(np.random.default_rng(seed).standard_normal((n, width)))
        for _ in range(rounds):
            q = orthonormal((series(q, False) + series(q, True)) / 2 + q)
        small = q.T @ (series(q, False) + series(q, True)) / 2
        w, v = np.linalg.eigh((small + small.T) / 2)
        factor = q @ v[:, ::-1] * np.sqrt(np.maximum(w[::-1], 0))
        for i, (users, kk, s) in enumerate(((ua, k[0], slice(0, len(ua))), (ub, k[1], slice(len(ua), n)))):
            yield batch(_SCHEMA, net=np.full(len(users), i), user_id=users, cluster=kmeans(factor[s, : max(k)], kk, seed))

    out = store(prepared.run(work, _TYPES, more), "propagation")
    return [out.filter(F.col("net") == i).select("user_id", "cluster") for i in (0, 1)]


def one_hop(S: DataFrame, start: DataFrame, restart: float = 0.15) -> DataFrame:
    """user_id, p after one step of the walk along row-normalised S with restart: start has user_id, p."""
    d = S.groupBy(F.col("src").alias("u")).agg(F.sum("s").alias("d"))
    step = S.join(d, F.col("src") == F.col("u")).join(start, F.col("src") == F.col("user_id")).groupBy("dst").agg(F.sum(F.col("p") * F.col("s") / F.col("d")).alias("q"))
    both = start.join(step, F.col("user_id") == F.col("dst"), "full")
    return both.select(F.coalesce("user_id", "dst").alias("user_id"), (restart * F.coalesce("p", F.lit(0.0)) + (1 - restart) * F.coalesce("q", F.lit(0.0))).alias("p"))

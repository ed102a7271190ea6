"""Connected components of an edge table, by alternating stars; no node, edge or label reaches the driver."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_stored, ship, store
from .words import released


def roots(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes of the edges (a, b), ascending, and the smallest node of each one's component."""
    nodes, index = np.unique(np.concatenate([a, b]), return_inverse=True)
    u, v = index[: len(a)], index[len(a) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[u], label[v])
        np.minimum.at(label, label[u], low)
        np.minimum.at(label, label[v], low)
        new = label[label]
        while (new != new[new]).any():
            new = new[new]
        if (new[u] == new[v]).all() and (new == label).all():
            return nodes, nodes[label]
        label = new


def _contract(batches, most: int = 1 << 21):
    """A task's edges, at most `most` at a time, become one star a component of theirs."""
    held, rows = [], 0

    def stars():
        nodes, low = roots(*(np.concatenate([x.column(c).to_numpy() for x in held]) for c in ("a", "b")))
        keep = nodes != low
        return pa.RecordBatch.from_pydict({"a": pa.array(nodes[keep]), "b": pa.array(low[keep])})

    for batch in batches:
        held.append(batch)
        rows += batch.num_rows
        if rows >= most:
            yield stars()
            held, rows = [], 0
    if rows:
        yield stars()


def connected_components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """node, component (its smallest node) for each node of `edges` (a, b: long; order and repeats don't matter).

    Each task first contracts its own edges; then large stars (a node's larger neighbours move to its smallest one) and
    small stars (a node's smaller neighbours do) alternate on stored tables until nothing moves, which takes a number of
    rounds logarithmic in the longest chain. A hub's rows are partially aggregated and its join is split by Spark.
    """
    spark = edges.sparkSession
    ship(spark)
    now = store(edges.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).filter("a <> b").mapInArrow(released(_contract), "a long, b long"), "edges")
    for _ in range(most_rounds):
        both = now.select("a", "b").union(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = both.join(low, "a").filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()
        down = large.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        least = down.groupBy("a").agg(F.min("b").alias("m"))
        small = down.join(least, "a").select(F.explode(F.array(F.struct("b", "m"), F.struct(F.col("a").alias("b"), "m"))).alias("x"))
        new = store(small.select(F.col("x.b").alias("a"), F.col("x.m").alias("b")).filter("a <> b").distinct(), "edges")
        same = _mark(now) == _mark(new)
        drop_stored(now)
        now = new
        if same:
            break
    else:
        raise RuntimeError("components did not settle")
    labels = now.select(F.col("a").alias("node"), F.col("b").alias("component"))
    return labels.union(now.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())


def _mark(edges: DataFrame):
    return edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(20,0)"))).first()

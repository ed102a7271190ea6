"""Closeness by terms that have factors, block iteration on packed rows, and K-means that reads rows once a round."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from mutualgraph.cluster import distributed, kmeans
from mutualgraph.linalg import blocks, iterated
from mutualgraph.operators import factors
from mutualgraph.operators.closeness import CrossedCloseness
from mutualgraph.sources import networks


def test_terms_of_a_sum():
    """Any totals, from equal ones to a range of 10^8: each 1 / (a + b) to the last bits."""
    for high in (1.0, 3.0, 1e8):
        a = np.geomspace(1.0, high, 300)
        f = factors.terms(a, factors.nodes(1.0, high))
        assert np.abs((f.T @ f) * (a[:, None] + a) - 1).max() < 1e-13 and len(f) < 100


@pytest.mark.parametrize("mix", ["uniform", {2: 0.5, 7: 0.5}, {1: 0.5, 6: 0.5}])
def test_products_by_terms(spark, tiny, mix):
    """As blocks of users give them."""
    net = networks.events_net(spark, tiny).stored()
    crossed = CrossedCloseness.of(net, mix)
    rows = net.users.filter("user_id <> 3").select("user_id", F.array(F.col("user_id") - 7.5, F.lit(1.0)).alias("vec"))
    want, got = ({r["user_id"]: np.array(r["vec"]) for r in x.collect()} for x in (crossed.times(rows), crossed.terms().times(rows)))
    assert len(want) == 15 and all(np.allclose(got.get(u, 0.0), want[u], rtol=1e-12, atol=1e-13) for u in want)


def ring(spark, groups, size):
    """Groups of users that all know each other, one pair of them apart."""
    pairs = [(g * size + a, g * size + b) for g in range(groups) for a in range(size) for b in range(size) if a != b and {a, b} != {0, 1}]
    return spark.createDataFrame(pairs, "src long, dst long").withColumn("s", F.lit(1.0))


def test_more_equal_values_than_the_block_has(spark, monkeypatch):
    """Twenty groups apart have the largest value twenty times: found in far fewer products than 150, rows orthonormal."""
    monkeypatch.setattr(blocks, "BLOCK_ROWS", 16)
    op = distributed.EntryOperator(ring(spark, 20, 6))
    made, before = [], iterated.moved
    monkeypatch.setattr(iterated, "moved", lambda *a: made.append(1) or before(*a))
    rows = {r["user_id"]: r["vec"] for r in distributed.spectral_rows(op, 2).collect()}
    x = np.array([rows[u] for u in sorted(rows)])
    S = np.zeros((120, 120))
    for r in op.S.collect():
        S[r["src"], r["dst"]] = 1.0
    root = 1 / np.sqrt(S.sum(1))
    assert np.abs(x.T @ x - np.eye(2)).max() < 1e-9 and abs(np.trace(x.T @ (root[:, None] * S * root) @ x) - 2) < 1e-8
    assert len(made) <= 25


def test_dense_clusters(spark):
    """As lloyd_rows finds them, from the better start; a cluster that no row is nearest to is given one."""
    rows = spark.createDataFrame([(i, [1.0, 0.001 * i] if i % 2 else [0.001 * i, 1.0]) for i in range(12)], "user_id long, vec array<double>")
    got = {r["user_id"]: r["cluster"] for r in kmeans.dense_clusters(rows, 2, 50).collect()}
    assert len(got) == 12 and len({got[i] for i in range(0, 12, 2)}) == len({got[i] for i in range(1, 12, 2)}) == 1 and got[0] != got[1]
    same = spark.createDataFrame([(i, [1.0, 0.0, 0.0]) for i in range(5)], "user_id long, vec array<double>")
    assert {r["cluster"] for r in kmeans.dense_clusters(same, 3, 50).collect()} == {0, 1, 2}

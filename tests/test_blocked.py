"""Pairs of users by blocks: the same rows as joins give, and none of them shuffled."""

import random
import re

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from mutualgraph.cluster.distributed import CrossedOperator, EntryOperator
from mutualgraph.metrics import quality
from mutualgraph.model.hetnet import HetNet
from mutualgraph.operators import blocked, closeness, metapath, partitions, shared
from mutualgraph.operators.closeness import CrossedCloseness

#: Queries whose rows are pairs of users: they leave the tasks that form them.
PAIRS = [
    "path5_word",
    "path6_time",
    "path7_location",
    "path5_with_self",
    "sim_pair_p5",
    "sim_pair_p6",
    "ancestor_sim_p5",
    "sim_matrix_p5",
    "sim_matrix_p6",
    "closeness_attr_only",
    "closeness_matrix_net2",
    "closeness_pair_net2",
    "sim_matrix_p7",
]


@pytest.fixture(scope="module")
def net(spark):
    """70 users, some with nothing, in blocks of about 12."""
    draw = random.Random(5)
    users = spark.createDataFrame([(u,) for u in range(70)], "user_id long")
    links = {(draw.randrange(60), draw.randrange(60)) for _ in range(150)}
    follow = spark.createDataFrame(sorted((a, b) for a, b in links if a != b), "src long, dst long")
    posts = [(p, draw.randrange(64)) for p in range(400)]
    attributes = {(p, k, f"{k}{draw.randrange(n)}") for p, _ in posts for k, n in (("word", 4), ("word", 4), ("time", 9), ("location", 40))}
    return HetNet("n", users, follow, spark.createDataFrame(posts, "post_id long, user_id long"), spark.createDataFrame(sorted(attributes), "post_id long, kind string, attr string"))


@pytest.fixture
def small_blocks(monkeypatch):
    monkeypatch.setattr(shared, "BLOCK", 12)


def rows(df, *cols, digits=9):
    return sorted(tuple(round(v, digits) if isinstance(v, float) else v for v in r) for r in df.select(*cols).collect())


def both_ways(monkeypatch, make, *cols):
    """Rows by joins, then by blocks."""
    out = []
    for share in (0, 10**9):
        monkeypatch.setattr(shared, "CROSS_SHARE", share)
        out.append(rows(make(), *cols))
    return out


@pytest.mark.parametrize("own", [False, True])
@pytest.mark.parametrize("path", [3, 5, 6, 7])
def test_counts(net, monkeypatch, small_blocks, path, own):
    for half in (False, True):
        joined, crossed = both_ways(monkeypatch, lambda half=half: metapath.path_counts(net, path, own, half), "src", "dst", "cnt")
        assert joined == crossed and joined


@pytest.mark.parametrize("form", ["pair", "matrix"])
@pytest.mark.parametrize("weights", ["uniform", "attribute", {2: 0.5, 5: 0.25, 7: 0.25}])
def test_closeness(net, monkeypatch, small_blocks, weights, form):
    joined, crossed = both_ways(monkeypatch, lambda: closeness.closeness(net, weights, form), "src", "dst", "s")
    assert joined == crossed and joined


def test_similarity(net, monkeypatch, small_blocks):
    for make in (lambda: closeness.path_similarity(net, 5, "matrix", True), lambda: closeness.ancestor_similarity(net, 6)):
        joined, crossed = both_ways(monkeypatch, make, "src", "dst", "s")
        assert joined == crossed and joined


def test_products(net, monkeypatch, small_blocks):
    part = net.users.select("user_id", (F.col("user_id") % 3).cast("int").alias("cluster"))
    monkeypatch.setattr(shared, "CROSS_SHARE", 0)
    S = closeness.closeness(net)
    S = S.sparkSession.createDataFrame(S.collect(), S.schema)
    votes = rows(closeness.vote_weights(net, part, closeness.weights_of()), "path", "weight")
    monkeypatch.setattr(shared, "CROSS_SHARE", 10**9)
    crossed = CrossedCloseness.of(net)
    assert rows(closeness.degrees(S), "user_id", "d") == rows(crossed.degrees(), "user_id", "d")
    assert rows(partitions.cluster_flow(S, part), "c1", "c2", "w", digits=8) == rows(crossed.cluster_flow(part), "c1", "c2", "w", digits=8)
    assert rows(closeness.profile(S, net.follow, net.users), "pairs", "direct", "indirect", "possible") == rows(crossed.profile(), "pairs", "direct", "indirect", "possible")
    assert rows(closeness.sparsify(S.withColumn("s", F.round("s", 9)), 3), "src", "dst", "s") == rows(crossed.closest(3, 9), "src", "dst", "s")
    assert votes == rows(closeness.vote_weights(net, part, closeness.weights_of()), "path", "weight")
    assert rows(quality.ndbi(quality.closeness_features(S), part), "ndbi", digits=6) == rows(quality.ndbi_products(crossed, part), "ndbi", digits=6)


def test_operators_of_large_networks(net, monkeypatch, small_blocks):
    """What the comparators multiply by beyond one task: products formed anew equal those with stored entries."""
    monkeypatch.setattr(shared, "CROSS_SHARE", 0)
    S = closeness.closeness(net)
    entries = EntryOperator(S.sparkSession.createDataFrame(S.collect(), S.schema))
    monkeypatch.setattr(shared, "CROSS_SHARE", 10**9)
    crossed = CrossedOperator(CrossedCloseness.of(net))
    some = net.users.filter("user_id % 9 = 0").select("user_id", F.array(F.col("user_id") % 5 - 2.0, F.lit(1.0)).alias("vec"))
    wide = lambda df: {r["user_id"]: [round(v, 9) for v in r["vec"]] for r in df.collect() if any(r["vec"])}
    assert wide(entries.scaled(some)) == wide(crossed.scaled(some))
    assert rows(entries.similarity_rows().users, "user_id", "xx") == rows(crossed.similarity_rows().users, "user_id", "xx")


@pytest.mark.parametrize("name", PAIRS)
def test_pairs_are_not_shuffled(spark, tiny, name):
    plan = entry.queries()[name](spark, tiny)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" in plan and not re.search(r"Exchange hashpartitioning\((src|dst|a|b)#", plan), plan


def test_heavy_attributes_are_not_copied(spark, monkeypatch):
    """A network in which few share attributes but one attribute is heavy: its pairs come from blocks, too."""
    monkeypatch.setattr(shared, "BLOCK", 16)
    held = shared.held(spark.createDataFrame([(5, u, "x", 1) for u in range(90)] + [(5, 1000 + u, f"y{u}", 1) for u in range(900)], "path int, user_id long, attr string, cnt long"))
    got = shared.shared_counts(held, half=True)
    assert "CartesianProduct" in got._jdf.queryExecution().executedPlan().toString() and got.count() == 90 * 89 // 2


@pytest.mark.parametrize("name", [n for n in PAIRS if "sim" in n or "closeness" in n])
def test_pairs_leave_their_tasks_rounded(spark, tiny, name):
    """Spark rounds a number by its decimal text, which takes longer than all else that a row does."""
    plan = entry.queries()[name](spark, tiny)._jdf.queryExecution().executedPlan().toString()
    assert "round(" not in plan, plan


@pytest.mark.parametrize("kinds, each", [(720, 64), (221, 39)])
def test_common_attributes_are_multiplied(monkeypatch, kinds, each):
    """Two blocks of 1024 users with 64 of 720 attributes each (hours, at sf0.1): a product, not six million pairs one by one."""
    monkeypatch.setattr(blocked, "_sparse", None)
    draw, n = np.random.default_rng(1), 1024
    rows, one = np.repeat(np.arange(n), each), np.concatenate([draw.choice(kinds, each, False) for _ in range(n)])
    side = (pa.array([str(k) for k in range(kinds)]), rows, one, np.ones(len(rows), np.uint8))
    dense = np.zeros((n, kinds))
    dense[rows, one] = 1
    assert (blocked.product(side, side, (n, n)) == dense @ dense.T).all()


def test_closest_over_many_blocks(net, monkeypatch, small_blocks):
    """Fewer are asked for than a block has users, and equal closeness is common: what falls out early stays out."""
    monkeypatch.setattr(shared, "CROSS_SHARE", 0)
    S = closeness.closeness(net, {6: 1.0})
    want = rows(closeness.sparsify(S.withColumn("s", F.round("s", 2)), 1), "src", "dst", "s")
    monkeypatch.setattr(shared, "CROSS_SHARE", 10**9)
    assert want == rows(closeness.CrossedCloseness.of(net, {6: 1.0}).closest(1, 2), "src", "dst", "s")

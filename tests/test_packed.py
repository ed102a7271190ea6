"""Packed entries: the same products as joins give, without a shuffle of entries, and loops that keep no stored table."""

import random

import pytest
from pyspark.sql import functions as F

from mutualgraph import storage
from mutualgraph.cluster import baselines, distributed, onetask
from mutualgraph.linalg import blocks
from mutualgraph.model.hetnet import HetNet
from mutualgraph.operators import closeness


@pytest.fixture
def small_pieces(monkeypatch):
    for name, value in (("BLOCK_ROWS", 8), ("SIDE_ROWS", 16), ("PIECE", 30), ("TOGETHER", 2), ("AT_ONCE", 7), ("SENT_ROWS", 5)):
        monkeypatch.setattr(blocks, name, value)


def links(spark, n=40, many=300, seed=3):
    draw = random.Random(seed)
    found = {(draw.randrange(n), draw.randrange(n)) for _ in range(many)} | {(0, i) for i in range(1, n)}
    return spark.createDataFrame(sorted(x for x in found if x[0] != x[1]), "src long, dst long")


def vectors(df):
    return {r["user_id"]: [round(v, 9) for v in r["vec"]] for r in df.collect()}


@pytest.mark.parametrize("weight", ["1.0", "1.0 + src % 3 + dst / 7"])
def test_products(spark, small_pieces, weight):
    """Blocks of rows without any of the rows, users that have none, equal and different weights, several products."""
    entries = links(spark).withColumn("w", F.expr(weight).cast("double"))
    packed = blocks.PackedEntries(entries, 40, entries.count())
    for rows in (entries.select(F.col("src").alias("user_id")).distinct(), spark.createDataFrame([(3,), (99,)], "user_id long")):
        rows = rows.select("user_id", F.array(F.col("user_id") - 7.5, F.lit(1.0), F.col("user_id") % 4 * 0.5).alias("vec"))
        assert vectors(blocks.spmm(entries, rows)).items() <= vectors(packed.times(rows)).items()
        assert {u for u, v in vectors(packed.times(rows)).items() if any(v)} <= set(vectors(blocks.spmm(entries, rows)))


def test_entries_are_not_shuffled(spark):
    """A product reads the entries where they lie: all that is dealt anew are rows of vectors."""
    both = links(spark)
    S = both.union(both.select("dst", "src")).distinct().withColumn("s", F.lit(1.0))
    op = distributed.EntryOperator(S)
    plan = op.scaled(op.degree.select("user_id", F.array("d").alias("vec")))._jdf.queryExecution().optimizedPlan().toString()
    assert "pieces-" in "".join(op.packed.table.inputFiles()) and " dst#" not in plan, plan


def test_rounds_keep_no_tables(spark, small_pieces):
    """Nine more rounds of orthogonal iteration leave no more stored tables."""
    both = links(spark)
    S = both.union(both.select("dst", "src")).distinct().withColumn("s", F.lit(1.0))
    op = distributed.EntryOperator(S)
    kept = []
    for rounds in (3, 12):
        before = len(storage._stored)
        distributed.spectral_rows(op, 3, rounds=rounds, tol=-1.0)
        kept.append(len(storage._stored) - before)
    assert kept[1] <= kept[0] <= 6, kept


def test_large_networks_are_not_gathered(spark, monkeypatch):
    """Links beyond what a task may gather aren't written for it; the partition by tables is the task's."""
    users = spark.range(12).select(F.col("id").alias("user_id"))
    pairs = [(a, b) for a in range(12) for b in range(12) if a != b and a % 3 == b % 3] + [(0, 1)]
    none = spark.createDataFrame([], "post_id long, user_id long"), spark.createDataFrame([], "post_id long, kind string, attr string")
    net = HetNet("n", users, spark.createDataFrame(pairs, "src long, dst long"), *none)
    groups = lambda rows: {frozenset(r["user_id"] for r in rows if r["cluster"] == c) for c in {r["cluster"] for r in rows}}
    task = groups(baselines.normalized_cut(net, 3).collect())
    monkeypatch.setattr(onetask, "MOST_ROWS", 20)
    before = len(storage._stored)
    tables = groups(baselines.normalized_cut(net, 3).collect())
    assert not any("/gathered-" in path for _, path in storage._stored[before:]) and tables == task and len(task) == 3


def test_products_of_blocks_keep_no_tables(spark, monkeypatch):
    """Closeness formed anew for each product keeps what the two newest products wrote, however many there are."""
    users = spark.range(40).select(F.col("id").alias("user_id"))
    posts = users.select(F.col("user_id").alias("post_id"), "user_id")
    attributes = posts.select("post_id", F.lit("word").alias("kind"), (F.col("post_id") % 2).cast("string").alias("attr"))
    net = HetNet("n", users, spark.createDataFrame([(1, 2), (3, 2)], "src long, dst long"), posts, attributes)
    crossed = closeness.CrossedCloseness.of(net, "attribute")
    one, before = users.select("user_id", F.array(F.lit(1.0)).alias("vec")), len(storage._stored)
    got = [vectors(crossed.times(one)) for _ in range(5)]
    assert len(storage._stored) - before <= 2 and all(g == got[0] for g in got) and len(got[0]) == 40

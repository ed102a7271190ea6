"""Costs of path joins before they run, and what to do about hubs."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.hetnet import HetNet
from ..operators.metapath import KIND_OF


def path_join_rows(net: HetNet) -> DataFrame:
    """net, path, join_rows that the joins of paths 2 to 7 would form, from degrees alone."""
    out_deg = net.follow.groupBy(F.col("src").alias("u")).agg(F.count("*").alias("o"))
    in_deg = net.follow.groupBy(F.col("dst").alias("u")).agg(F.count("*").alias("i"))
    rows = [
        (2, out_deg.join(in_deg, "u").agg(F.sum(F.col("o") * F.col("i")).alias("r"))),
        (3, in_deg.agg(F.sum(F.col("i") * F.col("i")).alias("r"))),
        (4, out_deg.agg(F.sum(F.col("o") * F.col("o")).alias("r"))),
    ]
    for path, kind in KIND_OF.items():
        users = net.user_attributes(kind).groupBy("attr").agg(F.count("*").alias("c"))
        rows.append((path, users.agg(F.sum(F.col("c") * F.col("c")).alias("r"))))
    return reduce(DataFrame.union, [df.select(F.lit(net.name).alias("net"), F.lit(p).alias("path"), F.col("r").alias("join_rows")) for p, df in rows])


def classify_hubs(net: HetNet, kind: str, most_users: int) -> DataFrame:
    """attr, users, hub, lost_rows: attributes with more users than the cap, and the join rows that dropping them saves."""
    users = net.user_attributes(kind).groupBy("attr").agg(F.count("*").alias("users"))
    hub = F.col("users") > most_users
    return users.select("attr", "users", hub.alias("hub"), F.when(hub, F.col("users") * F.col("users")).otherwise(0).alias("lost_rows"))


def without_hubs(net: HetNet, kind: str, most_users: int) -> HetNet:
    """net less attributes of a kind with more users than the cap. This changes closeness: an explicit choice, and
    classify_hubs() says what it costs. The factorised operator needs no cap."""
    hubs = classify_hubs(net, kind, most_users).filter("hub").select(F.lit(kind).alias("kind"), "attr")
    return HetNet(net.name, net.users, net.follow, net.posts, net.attributes.join(hubs, ["kind", "attr"], "left_anti"))

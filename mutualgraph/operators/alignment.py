"""Anchor links: sampling, validation, kinds of alignment, merged accounts."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model.hetnet import AlignedSet, HetNet
from ..storage import store


def anchor_users(net: HetNet, anchors: DataFrame, side: str = "u1") -> DataFrame:
    return net.users.join(anchors.select(F.col(side).alias("user_id")), "user_id", "left_semi")


def non_anchor_users(net: HetNet, anchors: DataFrame, side: str = "u1") -> DataFrame:
    return net.users.join(anchors.select(F.col(side).alias("user_id")), "user_id", "left_anti")


def violations(anchors: DataFrame) -> DataFrame:
    """side, user_id, links of users with more than one anchor link on a side."""
    one = lambda side: anchors.groupBy(F.col(side).alias("user_id")).agg(F.count("*").alias("links")).filter("links > 1").select(F.lit(side).alias("side"), "user_id", "links")
    return one("u1").union(one("u2"))


def alignment_kinds(aligned: AlignedSet) -> DataFrame:
    """first, second, n1, n2, links, kind of each pair: none, partial or full (every user of both has a link)."""
    out = None
    for i, j in aligned.pairs():
        n1, n2, a = (df.agg(F.count("*").alias(c)) for df, c in ((aligned.nets[i].users, "n1"), (aligned.nets[j].users, "n2"), (aligned.anchors[i, j], "links")))
        kind = F.when(F.col("links") == 0, "none").when((F.col("links") == F.col("n1")) & (F.col("links") == F.col("n2")), "full").otherwise("partial")
        row = n1.crossJoin(n2).crossJoin(a).select(F.lit(aligned.nets[i].name).alias("first"), F.lit(aligned.nets[j].name).alias("second"), "n1", "n2", "links", kind.alias("kind"))
        out = row if out is None else out.union(row)
    return out


def sample_anchors(anchors: DataFrame, sigma: float, seed: int = 0) -> DataFrame:
    """The first ceil(sigma x links) anchors by a hash of u1: deterministic, and nested for growing sigma.

    A threshold on the hash, found from counts of its 4096 ranges, selects whole ranges; only the range that the line
    falls into is ordered, so no global sort of anchors happens.
    """
    key = ((F.col("u1") + seed) * 2654435761) % 4294967296
    keyed = anchors.withColumn("_h", key).withColumn("_b", F.floor(key / 1048576).cast("int"))
    sums = keyed.groupBy("_b").agg(F.count("*").alias("_n"))  # at most 4096 rows
    upto = Window.orderBy("_b")
    sums = sums.withColumn("_upto", F.sum("_n").over(upto)).withColumn("_want", F.ceil(F.round(F.sum("_n").over(Window.partitionBy()) * sigma, 9)))
    keyed = keyed.join(F.broadcast(sums), "_b")
    rank = F.row_number().over(Window.partitionBy("_b").orderBy("_h", "u1"))
    edge = keyed.filter((F.col("_upto") > F.col("_want")) & (F.col("_upto") - F.col("_n") < F.col("_want"))).withColumn("_r", rank)
    whole = keyed.filter(F.col("_upto") <= F.col("_want")).select("u1", "u2")
    return whole.union(edge.filter(F.col("_r") <= F.col("_want") - (F.col("_upto") - F.col("_n"))).select("u1", "u2"))


def account_components(links: DataFrame, most_rounds: int = 50) -> DataFrame:
    """user_id, account (smallest id reachable) of accounts (user_a, user_b) of one person: hash-to-min on stored tables."""
    pairs = links.select(F.col("user_a").alias("a"), F.col("user_b").alias("b"))
    edges = store(pairs.union(pairs.select("b", "a")).filter("a <> b").distinct(), "account-links")
    label = store(edges.select("a", F.col("a").alias("m")).distinct(), "accounts")
    for _ in range(most_rounds):
        low = edges.join(label, F.col("b") == label["a"]).groupBy(edges["a"]).agg(F.min("m").alias("o"))
        new = label.join(low, "a").select("a", F.least("m", "o").alias("m"))
        hop = new.select(F.col("a").alias("m"), F.col("m").alias("mm"))
        new = store(new.join(hop, "m").select("a", F.col("mm").alias("m")), "accounts")
        if new.join(label.withColumnRenamed("m", "was"), "a").filter("m <> was").limit(1).count() == 0:
            return new.select(F.col("a").alias("user_id"), F.col("m").alias("account"))
        label = new
    raise RuntimeError("account components did not settle")


def collapse_accounts(net: HetNet, links: DataFrame) -> HetNet:
    """net with linked accounts merged into one virtual account (their smallest id)."""
    to = account_components(links)

    def mapped(df: DataFrame, col: str) -> DataFrame:
        t = to.select(F.col("user_id").alias("_u"), F.col("account").alias("_a"))
        return df.join(t, F.col(col) == F.col("_u"), "left").withColumn(col, F.coalesce("_a", col)).drop("_u", "_a")

    follow = mapped(mapped(net.follow, "src"), "dst").filter("src <> dst").distinct()
    return HetNet(net.name, mapped(net.users, "user_id").distinct(), follow, mapped(net.posts, "user_id"), net.attributes)

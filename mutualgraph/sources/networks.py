"""Networks built on the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model.hetnet import AlignedSet, HetNet


#: Post ids of a line are id * LINES + line: more lines than a text of two gigabytes can have.
LINES = 1 << 31


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def follow_previous(visits: DataFrame, item: str, order: list[str], within: Column | None = None, by_src: bool = False) -> DataFrame:
    """src follows dst, who was the one just before at the same item: visits (user_id, item, order...), distinct links.
    by_src: links are dealt out by src, which a join on src then need not do again."""
    at = Window.partitionBy(item).orderBy(*order)
    prev = visits.withColumn("dst", F.lag("user_id").over(at)).withColumn("_before", F.lag(order[0]).over(at))
    ok = F.col("dst").isNotNull() & (F.col("dst") != F.col("user_id"))
    links = prev.filter(ok if within is None else ok & within).select(F.col("user_id").alias("src"), "dst")
    return (links.repartition("src") if by_src else links).distinct()


def orders_net(spark: SparkSession, sf_dir: str) -> HetNet:
    """Customers; orders are posts, parts words, suppliers locations, days times; a buyer follows a part's buyer before."""
    orders, lines = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    head = orders.select(F.col("o_orderkey").alias("post_id"), F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("at"))
    bought = lines.select(F.col("l_orderkey").alias("post_id"), "l_partkey").repartition("post_id").distinct().join(head, "post_id")  # one shuffle for both
    attr = lambda kind, col: lines.select(F.col("l_orderkey").alias("post_id"), F.lit(kind).alias("kind"), F.col(col).cast("string").alias("attr")).distinct()
    days = head.select("post_id", F.lit("time").alias("kind"), F.date_format("at", "yyyy-MM-dd").alias("attr"))
    return HetNet(
        "net1",
        table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id")),
        follow_previous(bought, "l_partkey", ["at", "post_id"], by_src=True),
        head.select("post_id", "user_id"),
        attr("word", "l_partkey").union(attr("location", "l_suppkey")).union(days),
    )


def events_net(spark: SparkSession, sf_dir: str, gap_seconds: int = 3600) -> HetNet:
    """Event users; events are posts, type and value decile words, k locations, hours times; a user follows the other
    user who was just before at the same k, at most `gap_seconds` ago."""
    e = table(spark, sf_dir, "events").withColumn("k", F.get_json_object("props", "$.k").cast("int")).withColumn("at", F.unix_micros(F.col("ts").cast("timestamp")))
    near = (F.col("at") - F.col("_before")) <= gap_seconds * 1_000_000
    kinds = F.array(
        F.struct(F.lit("word").alias("kind"), F.concat_ws(":", "event_type", F.floor(F.col("value") / 10).cast("string")).alias("attr")),
        F.struct(F.lit("time").alias("kind"), F.date_format("ts", "yyyy-MM-dd HH").alias("attr")),
        F.struct(F.lit("location").alias("kind"), F.col("k").cast("string").alias("attr")),
    )
    return HetNet(
        "net2",
        e.select("user_id").distinct(),
        follow_previous(e, "k", ["at", "event_id"], near),
        e.select(F.col("event_id").alias("post_id"), "user_id"),
        e.select(F.col("event_id").alias("post_id"), F.explode(kinds).alias("x")).select("post_id", "x.kind", "x.attr"),
    )


def key_anchors(spark: SparkSession, sf_dir: str, percent: int = 63) -> DataFrame:
    """u1, u2: equal keys of customers and event users, a fixed slice of them."""
    users = table(spark, sf_dir, "events").select("user_id").distinct()
    keys = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id")).join(users, "user_id", "left_semi")
    return keys.filter((F.col("user_id") * 7919 + 13) % 100 < percent).select(F.col("user_id").alias("u1"), F.col("user_id").alias("u2"))


def aligned_tables(spark: SparkSession, sf_dir: str) -> AlignedSet:
    return AlignedSet([orders_net(spark, sf_dir), events_net(spark, sf_dir)], {(0, 1): key_anchors(spark, sf_dir)})


def tokens(text: Column, least: int = 3) -> Column:
    """Lower-case letter runs of at least `least` characters."""
    return F.regexp_extract_all(F.lower(text), F.lit(rf"\p{{L}}{{{least},}}"), F.lit(0))


def document_view(spark: SparkSession, sf_dir: str, side: int, frequency: tuple[int, float] = (2, 0.05)) -> HetNet:
    """View `side` (0 or 1) of the documents: those whose id leaves other than `side` by 5, lines of that parity as posts,
    letter runs as words (in 2 documents at least and 5 % of them at most), source as location; weak planted follow links."""
    docs = table(spark, sf_dir, "documents").filter(F.col("doc_id") % 5 != side)
    lines = docs.select("doc_id", "source", F.posexplode(F.split("text", "\n")).alias("line", "body")).filter(F.col("line") % 2 == side)
    lines = lines.withColumn("post_id", F.col("doc_id") * LINES + F.col("line"))
    words = lines.select("post_id", "doc_id", F.explode(F.array_distinct(tokens(F.col("body")))).alias("attr"))
    many = docs.agg((F.count("*") * frequency[1]).alias("most"))
    held = words.groupBy("attr").agg(F.countDistinct("doc_id").alias("df")).join(F.broadcast(many)).filter((F.col("df") >= frequency[0]) & (F.col("df") <= F.col("most")))
    words = words.join(held.select("attr"), "attr", "left_semi").select("post_id", F.lit("word").alias("kind"), "attr")
    places = lines.select("post_id", F.lit("location").alias("kind"), F.col("source").alias("attr"))
    n = docs.agg((F.max("doc_id") + 1).alias("n"))
    (a, b), (c, d) = ((31, 7), (17, 3)) if side == 0 else ((37, 11), (13, 5))
    noise = docs.select(F.col("doc_id").alias("src")).join(F.broadcast(n)).select("src", F.explode(F.array((F.col("src") * a + b) % F.col("n"), (F.col("src") * c + d) % F.col("n"))).alias("dst"))
    same = docs.select(F.col("doc_id").alias("src"), F.lead("doc_id").over(Window.partitionBy("lang").orderBy("doc_id")).alias("dst")).filter("dst is not null")
    users = docs.select(F.col("doc_id").alias("user_id"))
    links = same.union(noise).filter("src <> dst").distinct().join(users, F.col("dst") == F.col("user_id"), "left_semi")
    return HetNet("netA" if side == 0 else "netB", users, links, lines.select("post_id", F.col("doc_id").alias("user_id")), words.union(places).distinct())


def aligned_documents(spark: SparkSession, sf_dir: str) -> AlignedSet:
    """The two document views; documents in both are anchors."""
    docs = table(spark, sf_dir, "documents").filter((F.col("doc_id") % 5 != 0) & (F.col("doc_id") % 5 != 1))
    anchors = docs.select(F.col("doc_id").alias("u1"), F.col("doc_id").alias("u2"))
    return AlignedSet([document_view(spark, sf_dir, 0), document_view(spark, sf_dir, 1)], {(0, 1): anchors})


def conversations_net(spark: SparkSession, sf_dir: str) -> HetNet:
    """Conversations as users, turns as posts, letter runs as words, roles as locations; each follows the one before."""
    t = table(spark, sf_dir, "conversations").withColumn("post_id", F.col("conv_id") * LINES + F.col("turn"))
    words = t.select("post_id", F.lit("word").alias("kind"), F.explode(F.array_distinct(tokens(F.col("text")))).alias("attr"))
    roles = t.select("post_id", F.lit("location").alias("kind"), F.col("role").alias("attr"))
    users = t.select(F.col("conv_id").alias("user_id")).distinct()
    follow = users.select(F.col("user_id").alias("src"), (F.col("user_id") - 1).alias("dst")).join(users, F.col("dst") == F.col("user_id"), "left_semi")
    return HetNet("net3", users, follow, t.select("post_id", F.col("conv_id").alias("user_id")), words.union(roles))


def three_networks(spark: SparkSession, sf_dir: str) -> AlignedSet:
    """Orders, events and conversations, aligned by equal keys."""
    two = aligned_tables(spark, sf_dir)
    third = conversations_net(spark, sf_dir)
    keys = third.users.select(F.col("user_id").alias("u2"))
    to = lambda net: net.users.join(keys, F.col("user_id") == F.col("u2")).select(F.col("user_id").alias("u1"), "u2")
    return AlignedSet([*two.nets, third], two.anchors | {(0, 2): to(two.nets[0]), (1, 2): to(two.nets[1])})


def planted_blocks(spark: SparkSession, sf_dir: str) -> int:
    """How many blocks the planted networks have: about ten users of the smaller network each at sf0.01."""
    users = table(spark, sf_dir, "events").agg(F.countDistinct("user_id")).first()[0]
    return int((users / 1.5) ** 0.5)


def planted_networks(spark: SparkSession, sf_dir: str) -> AlignedSet:
    """Customers and event users with known communities, for tests of whole methods: users whose keys leave the same
    remainder by the number of blocks all follow each other, and every second user follows one more at random. Aligned by
    equal keys (a fixed slice). Links grow as users times the block size."""
    blocks = planted_blocks(spark, sf_dir)
    none = spark.createDataFrame([], "post_id long, user_id long"), spark.createDataFrame([], "post_id long, kind string, attr string")
    nets = []
    for name, users in (("net1", table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"))), ("net2", table(spark, sf_dir, "events").select("user_id").distinct())):
        users = users.withColumn("block", F.col("user_id") % blocks)
        other = users.select(F.col("user_id").alias("dst"), "block")
        inside = users.join(other, "block").select(F.col("user_id").alias("src"), "dst")
        count = users.agg((F.max("user_id") + 1).alias("n"))
        noise = users.filter("user_id % 2 = 0").join(F.broadcast(count)).select(F.col("user_id").alias("src"), F.pmod(F.xxhash64("user_id"), F.col("n")).alias("dst"))
        noise = noise.join(other.select("dst"), "dst", "left_semi").select("src", "dst")
        nets.append(HetNet(name, users.select("user_id"), inside.union(noise).filter("src <> dst").distinct(), *none))
    return AlignedSet(nets, {(0, 1): key_anchors(spark, sf_dir)})

"""Networks of users, posts, words, times and locations as tables, and sets of aligned networks."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import store

#: Node kinds of a post's attributes.
ATTRIBUTES = ("word", "time", "location")


@dataclass(frozen=True)
class HetNet:
    """One network. users (user_id), follow (src, dst; distinct, no loops), posts (post_id, user_id) and
    attributes (post_id, kind, attr; distinct, kind one of ATTRIBUTES, any number a post)."""

    name: str
    users: DataFrame
    follow: DataFrame
    posts: DataFrame
    attributes: DataFrame

    def user_attributes(self, kind: str) -> DataFrame:
        """user_id, attr, cnt: posts of each user that have each attribute. Aggregated before any path joins it."""
        of_kind = self.attributes.filter(F.col("kind") == kind).select("post_id", "attr")
        return of_kind.join(self.posts, "post_id").groupBy("user_id", "attr").agg(F.count("*").alias("cnt"))

    def stored(self) -> HetNet:
        """The same with its relations written once, for plans that read them many times."""
        return HetNet(self.name, *(store(df, f"{self.name}-{n}") for n, df in (("users", self.users), ("follow", self.follow), ("posts", self.posts), ("attributes", self.attributes))))

    def linked(self) -> HetNet:
        """The same with its users and links written once, for plans that read no post."""
        return HetNet(self.name, store(self.users, f"{self.name}-users"), store(self.follow, f"{self.name}-follow"), self.posts, self.attributes)

    def undirected(self) -> DataFrame:
        """src, dst of follow links in both directions, distinct; a user's are together, so that sums by src meet them so."""
        return self.follow.union(self.follow.select("dst", "src")).repartition("src").distinct()


@dataclass(frozen=True)
class AlignedSet:
    """Networks and the anchor links (u1, u2) between pairs of them."""

    nets: list[HetNet]
    anchors: dict[tuple[int, int], DataFrame] = field(default_factory=dict)

    def pairs(self) -> list[tuple[int, int]]:
        return [p for p in combinations(range(len(self.nets)), 2) if p in self.anchors]

    def stored(self) -> AlignedSet:
        return AlignedSet([n.stored() for n in self.nets], {p: store(a, "anchors") for p, a in self.anchors.items()})

    def with_anchors(self, pair: tuple[int, int], anchors: DataFrame) -> AlignedSet:
        return AlignedSet(self.nets, self.anchors | {pair: anchors})

    def views(self) -> None:
        """Register every relation as a temporary view: users_0, follow_0, ..., anchors_0_1."""
        for i, net in enumerate(self.nets):
            for name in ("users", "follow", "posts", "attributes"):
                getattr(net, name).createOrReplaceTempView(f"{name}_{i}")
        for (i, j), df in self.anchors.items():
            df.createOrReplaceTempView(f"anchors_{i}_{j}")


def describe(net: HetNet) -> DataFrame:
    """property, value: users, posts, locations, social, write and locate links, posts per user, percent located."""
    located = net.attributes.filter(F.col("kind") == "location")
    counts = [
        net.users.agg(F.count("*").alias("value")).withColumn("property", F.lit("users")),
        net.posts.agg(F.count("*").alias("value")).withColumn("property", F.lit("posts")),
        located.agg(F.countDistinct("attr").alias("value")).withColumn("property", F.lit("locations")),
        net.follow.agg(F.count("*").alias("value")).withColumn("property", F.lit("social links")),
        net.posts.agg(F.count("*").alias("value")).withColumn("property", F.lit("write links")),
        located.agg(F.count("*").alias("value")).withColumn("property", F.lit("locate links")),
        located.agg(F.countDistinct("post_id").alias("value")).withColumn("property", F.lit("located posts")),
    ]
    base = reduce(DataFrame.unionByName, counts).select("property", F.col("value").cast("double").alias("value"))
    get = lambda name: F.max(F.when(F.col("property") == name, F.col("value")))
    rates = base.agg(F.try_divide(get("posts"), get("users")).alias("a"), (100 * F.try_divide(get("located posts"), get("posts"))).alias("b"))
    more = rates.select(F.explode(F.array(F.struct(F.lit("posts per user").alias("property"), F.col("a").alias("value")), F.struct(F.lit("percent of posts located").alias("property"), F.col("b").alias("value")))).alias("r")).select("r.*")
    return base.union(more).withColumn("value", F.round("value", 6))

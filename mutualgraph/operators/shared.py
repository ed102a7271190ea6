"""How often two users share an attribute: light attributes by a join, heavy ones by products of blocks of users."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import store
from .blocked import Blocks

#: An attribute is heavy that one user in so many has: then a dense product costs less than its pairs in a join.
HEAVY_SHARE = 32
#: Users of a block at most (about), and users of a light attribute that a task joins.
BLOCK, PIECE = 1024, 1000
#: Blocks of users are crossed where a join would have a row for every so many pairs of users.
CROSS_SHARE = 16
#: Join rows of a task, and tasks of a join at most.
ROWS, TASKS = 2_000_000, 4096


def spread(rows: int) -> int:
    """Tasks for a join of so many rows. Spark sizes them by what the join reads, which says little when few rows make many."""
    return int(min(TASKS, max(1, -(-rows // ROWS))))


def had(incidence: DataFrame) -> DataFrame:
    """(path, user_id, attr, cnt) stored once. Null users and attributes share nothing."""
    return store(incidence.select("path", "user_id", F.col("attr").cast("string").alias("attr"), F.col("cnt").cast("long").alias("cnt")).filter("user_id is not null and attr is not null"), "incidence")


def _totals(c: DataFrame) -> DataFrame:
    return c.groupBy("path", "attr").agg(F.count("*").alias("d"), F.sum("cnt").alias("total"))


def with_totals(had: DataFrame) -> DataFrame:
    """With the users d and the total of each attribute of a path; nothing is stored."""
    return had.join(_totals(had), ["path", "attr"])


def held(incidence: DataFrame) -> DataFrame:
    """(path, user_id, attr, cnt) stored once, with the users d and the total of each attribute of a path. Null users and
    attributes share nothing."""
    c = incidence.select("path", "user_id", F.col("attr").cast("string").alias("attr"), F.col("cnt").cast("long").alias("cnt")).filter("user_id is not null and attr is not null")
    return store(with_totals(c), "incidence")


def crossed(had: DataFrame) -> int:
    """The number of users, where their pairs are better formed by blocks than by joins on attributes; otherwise 0."""
    users = had.agg(F.count_distinct("user_id")).first()[0]
    rows = _totals(had).agg(F.sum(F.col("d").cast("double") * F.col("d"))).first()[0] or 0.0
    return users if rows * CROSS_SHARE >= float(users) * users else 0


def shared_marginals(held: DataFrame, self_paths: bool = False) -> DataFrame:
    """user_id, path, out: the sum of a user's shared counts, without a pair."""
    own = 0 if self_paths else 1
    return held.groupBy("user_id", "path").agg(F.sum(F.col("cnt") * (F.col("total") - own * F.col("cnt"))).alias("out"))


def shared_counts(held: DataFrame, half: bool = False, self_paths: bool = False) -> DataFrame:
    """src, dst, path, cnt in parts that are still to be summed: over attributes, the product of both users' counts.
    half: only src <= dst.

    A light attribute's users are cut into pieces, so that none fills one task; a heavy one's move once for each block of
    users, of which its pairs fill a fixed share anyway.
    """
    users = held.agg(F.count_distinct("user_id")).first()[0]
    heavy = F.col("d") * HEAVY_SHARE >= users
    pairs, entries = held.agg(F.sum(F.when(~heavy, F.col("d"))), F.count(F.when(heavy, True))).first()
    parts = []
    if pairs or not entries:
        parts.append(_joined(held.filter(~heavy), pairs or 0, half, self_paths))
    if entries:
        parts.append(_multiplied(held.filter(heavy), users, half, self_paths))
    return parts[0] if len(parts) == 1 else parts[0].union(parts[1])


def _joined(light: DataFrame, pairs: int, half: bool, self_paths: bool) -> DataFrame:
    pieces = F.ceil(F.col("d") / PIECE).cast("int")
    one = light.select("path", F.col("user_id").alias("src"), "attr", "cnt", F.pmod(F.xxhash64("user_id"), pieces).cast("int").alias("piece"))
    two = light.select("path", F.col("user_id").alias("dst"), "attr", F.col("cnt").alias("cnt2"), F.explode(F.sequence(F.lit(0), pieces - 1)).alias("piece"))
    n, key = spread(pairs), ["path", "attr", "piece"]
    if n > 1:
        one, two = one.repartition(n, *key), two.repartition(n, *key)
    keep = F.col("src") <= F.col("dst") if half else F.lit(True)
    if not self_paths:
        keep = keep & (F.col("src") != F.col("dst"))
    return one.join(two.hint("merge") if n > 1 else two, key).filter(keep).select("src", "dst", "path", (F.col("cnt") * F.col("cnt2")).alias("cnt"))


def _multiplied(heavy: DataFrame, users: int, half: bool, self_paths: bool) -> DataFrame:
    """Pairs of blocks of users, whose counts of heavy attributes are two matrices; sums stay exact below 2^53."""
    return Blocks(heavy, users, BLOCK).counts([3, 4, 5, 6, 7], half, self_paths)

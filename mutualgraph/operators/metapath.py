"""Meta paths between users: their counts, marginals without pairs, and a compiler for any typed, directed path."""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.hetnet import HetNet
from . import shared
from .blocked import Blocks
from .shared import had, held, shared_counts, spread

#: The seven paths by number: social ones 1 to 4, attribute ones 5 to 7.
PATHS = {1: "U>U", 2: "U>U>U", 3: "U>U<U", 4: "U<U>U", 5: "U>P>W<P<U", 6: "U>P>T<P<U", 7: "U>P>L<P<U"}
SOCIAL, ATTRIBUTE = (1, 2, 3, 4), (5, 6, 7)
KIND_OF = {5: "word", 6: "time", 7: "location"}
_KINDS = {"W": "word", "T": "time", "L": "location"}


@dataclass(frozen=True)
class MetaPath:
    """nodes: U, P, W, T or L; arrows: > along a link, < against it."""

    nodes: tuple[str, ...]
    arrows: tuple[str, ...]

    @staticmethod
    def parse(text: str) -> MetaPath:
        if not re.fullmatch(r"[UPWTL]([<>][UPWTL])*", text):
            raise ValueError(f"not a meta path: {text}")
        path = MetaPath(tuple(text[::2]), tuple(text[1::2]))
        for a, arrow, b in zip(path.nodes, path.arrows, path.nodes[1:], strict=False):
            if (a + b if arrow == ">" else b + a) not in ("UU", "UP", "PW", "PT", "PL"):
                raise ValueError(f"no link {a}{arrow}{b}")
        return path

    def length(self) -> int:
        return len(self.arrows)

    def is_palindrome(self) -> bool:
        """Whether the way back is the same path; then counts are symmetric and half of it suffices."""
        flipped = tuple("<" if a == ">" else ">" for a in reversed(self.arrows))
        return self.length() % 2 == 0 and self.nodes == self.nodes[::-1] and self.arrows == flipped


def _relation(net: HetNet, a: str, b: str) -> DataFrame:
    """from, to of the link kind a > b."""
    if a + b == "UU":
        return net.follow.select(F.col("src").cast("string").alias("from"), F.col("dst").cast("string").alias("to"))
    if a + b == "UP":
        return net.posts.select(F.col("user_id").cast("string").alias("from"), F.col("post_id").cast("string").alias("to"))
    return net.attributes.filter(F.col("kind") == _KINDS[b]).select(F.col("post_id").cast("string").alias("from"), F.col("attr").alias("to"))


def walk(net: HetNet, path: MetaPath) -> DataFrame:
    """start, end, cnt: instances of the path, aggregated after each link so that multiplicities, not rows, multiply."""
    now = None
    for a, arrow, b in zip(path.nodes, path.arrows, path.nodes[1:], strict=False):
        link = _relation(net, a, b) if arrow == ">" else _relation(net, b, a).select(F.col("to").alias("from"), F.col("from").alias("to"))
        if now is None:
            now = link.select(F.col("from").alias("start"), F.col("to").alias("end"), F.lit(1).cast("long").alias("cnt"))
        else:
            now = now.join(link, now["end"] == link["from"]).select("start", F.col("to").alias("end"), "cnt")
        now = now.groupBy("start", "end").agg(F.sum("cnt").alias("cnt"))
    return now


def compile_path(net: HetNet, path: MetaPath, self_paths: bool = False) -> DataFrame:
    """src, dst, cnt of a user-to-user path. A palindrome is its first half joined with itself on the middle node."""
    if path.nodes[0] != "U" or path.nodes[-1] != "U":
        raise ValueError("a social path begins and ends with users")
    if path.is_palindrome():
        half = walk(net, MetaPath(path.nodes[: path.length() // 2 + 1], path.arrows[: path.length() // 2]))
        other = half.select(F.col("start").alias("o"), F.col("end").alias("e"), F.col("cnt").alias("c"))
        out = half.join(other, half["end"] == other["e"]).groupBy("start", "o").agg(F.sum(F.col("cnt") * F.col("c")).alias("cnt"))
    else:
        out = walk(net, path).withColumnRenamed("end", "o")
    out = out.select(F.col("start").cast("long").alias("src"), F.col("o").cast("long").alias("dst"), "cnt")
    return out if self_paths else out.filter("src <> dst")


def path_counts(net: HetNet, path: int, self_paths: bool = False, half: bool = False) -> DataFrame:
    """src, dst, cnt of path 1 to 7. half: of the symmetric paths only src <= dst, half the rows to shuffle."""
    f = net.follow
    if path == 1:
        return f.select("src", "dst", F.lit(1).cast("long").alias("cnt"))
    if path == 2:
        mid = f.groupBy(F.col("src").alias("m")).agg(F.count("*").alias("o")).join(f.groupBy(F.col("dst").alias("m")).agg(F.count("*").alias("i")), "m")
        n = spread(mid.agg(F.sum(F.col("o") * F.col("i"))).first()[0] or 0)
        one, two = f.select(F.col("src").alias("x"), F.col("dst").alias("m")), f.select(F.col("dst").alias("y"), F.col("src").alias("m"))
        if n > 1:
            one, two = one.repartition(n, "m"), two.repartition(n, "m").hint("merge")
        pairs = one.join(two, "m")
        pairs = pairs if self_paths else pairs.filter("x <> y")
        return pairs.groupBy(F.col("x").alias("src"), F.col("y").alias("dst")).agg(F.count("*").alias("cnt"))
    mine = had(incidence(net, [path]))
    users = shared.crossed(mine)
    if users:
        return Blocks(mine, users, shared.BLOCK).counts([path], half, self_paths, with_path=False)
    return shared_counts(held(mine), half, self_paths).groupBy("src", "dst").agg(F.sum("cnt").alias("cnt"))


def incidence(net: HetNet, paths: list[int]) -> DataFrame:
    """path, user_id, attr, cnt: what a user has on the middle of symmetric paths (3 to 7), and how often."""
    parts = [net.follow.select(F.lit(p).alias("path"), F.col(end).alias("user_id"), F.col(mid).cast("string").alias("attr"), F.lit(1).cast("long").alias("cnt")) for p, end, mid in ((3, "src", "dst"), (4, "dst", "src")) if p in paths]
    kinds = {KIND_OF[p]: p for p in paths if p in KIND_OF}
    if kinds:
        number = F.coalesce(*(F.when(F.col("kind") == k, F.lit(p)) for k, p in kinds.items()))
        of_kind = net.attributes.filter(F.col("kind").isin(*kinds)).select("post_id", number.alias("path"), "attr")
        parts.append(of_kind.join(net.posts, "post_id").groupBy("path", "user_id", "attr").agg(F.count("*").alias("cnt")))
    return reduce(DataFrame.union, parts)


def path_marginals(net: HetNet, path: int, self_paths: bool = False) -> DataFrame:
    """user_id, out, in: sums of counts from and to each user, without forming a pair: the sum over partners is pushed
    below the join, where it is a degree (paths 1 to 4) or an attribute's total (paths 5 to 7); closed walks go unless kept."""
    f = net.follow
    out_deg = f.groupBy(F.col("src").alias("u")).agg(F.count("*").alias("od"))
    in_deg = f.groupBy(F.col("dst").alias("u")).agg(F.count("*").alias("id"))
    own = 0 if self_paths else 1
    if path == 1:
        both = out_deg.join(in_deg, "u", "full").select(F.col("u").alias("user_id"), F.coalesce("od", F.lit(0)).alias("out"), F.coalesce("id", F.lit(0)).alias("in"))
    elif path == 2:
        back = f.alias("f").join(f.select(F.col("src").alias("bs"), F.col("dst").alias("bd")), (F.col("src") == F.col("bd")) & (F.col("dst") == F.col("bs")), "left")
        mutual = F.when(F.col("bs").isNotNull(), own).otherwise(0)
        outs = back.join(out_deg, F.col("dst") == F.col("u"), "left").groupBy(F.col("src").alias("user_id")).agg(F.sum(F.coalesce("od", F.lit(0)) - mutual).alias("out"))
        ins = back.join(in_deg, F.col("src") == F.col("u"), "left").groupBy(F.col("dst").alias("user_id")).agg(F.sum(F.coalesce("id", F.lit(0)) - mutual).alias("in"))
        both = outs.join(ins, "user_id", "full").select("user_id", F.coalesce("out", F.lit(0)).alias("out"), F.coalesce("in", F.lit(0)).alias("in"))
    elif path in (3, 4):
        mid, end, deg, d = ("dst", "src", in_deg, "id") if path == 3 else ("src", "dst", out_deg, "od")
        one = f.join(deg, F.col(mid) == F.col("u")).groupBy(F.col(end).alias("user_id")).agg(F.sum(F.col(d) - own).alias("out"))
        both = one.select("user_id", "out", F.col("out").alias("in"))
    else:
        c = net.user_attributes(KIND_OF[path])
        total = c.groupBy("attr").agg(F.sum("cnt").alias("total"))
        one = c.join(total, "attr").groupBy("user_id").agg(F.sum(F.col("cnt") * (F.col("total") - own * F.col("cnt"))).alias("out"))
        both = one.select("user_id", "out", F.col("out").alias("in"))
    return both.filter("out > 0 or `in` > 0")

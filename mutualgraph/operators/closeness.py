"""Similarity of users by meta paths, and older similarity measures."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..model.hetnet import HetNet
from ..storage import join_small, store
from . import shared
from .blocked import Blocks
from .metapath import ATTRIBUTE, SOCIAL, incidence, path_counts, path_marginals
from .factors import MOST_ENTRIES, Terms
from .shared import had, held, shared_counts, shared_marginals, with_totals


def weights_of(weights: dict[int, float] | str = "uniform") -> dict[int, float]:
    """Path weights that sum to 1: "uniform", "social", "attribute", or explicit ones (checked)."""
    named = {"uniform": SOCIAL + ATTRIBUTE, "social": SOCIAL, "attribute": ATTRIBUTE}
    if isinstance(weights, str):
        return {p: 1 / len(named[weights]) for p in named[weights]}
    if abs(sum(weights.values()) - 1) > 1e-9 or min(weights.values()) < 0:
        raise ValueError("path weights must be non-negative and sum to 1")
    return {p: w for p, w in weights.items() if w > 0}


def symmetric_counts(net: HetNet, path: int, self_paths: bool = False) -> DataFrame:
    """a <= b, cnt: counts from a to b and from b to a together, each unordered pair once."""
    counts = path_counts(net, path, self_paths, half=True)
    if path <= 2:
        return counts.groupBy(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).agg(F.sum("cnt").alias("cnt")).withColumn("cnt", F.when(F.col("a") == F.col("b"), 2 * F.col("cnt")).otherwise(F.col("cnt")))
    return counts.select(F.col("src").alias("a"), F.col("dst").alias("b"), (2 * F.col("cnt")).alias("cnt"))


def path_similarity(net: HetNet, path: int, form: str = "pair", self_paths: bool = False, digits: int | None = None) -> DataFrame:
    """src, dst, s. pair: counts both ways over both users' outgoing counts, symmetric. matrix: over src's outgoing and
    incoming counts, so that rows sum to 1. digits: s rounded to so many."""
    blocks = crossed_blocks(net, {path: 1.0}, self_paths) if path > 2 else None
    if blocks is not None:
        return blocks.closeness({path: 1.0}, _form(form), self_paths, digits)
    return _rounded(_directed(_scored(net, path, form, self_paths), form), digits)


def _rounded(S: DataFrame, digits: int | None) -> DataFrame:
    return S if digits is None else S.withColumn("s", F.round("s", digits))


def _scored(net: HetNet, path: int, form: str, self_paths: bool) -> DataFrame:
    """a, b and s (pair) or s, t (matrix: of a to b, of b to a)."""
    m = path_marginals(net, path, self_paths)
    one, two = (m.select(F.col("user_id").alias(k), F.col("out").alias(f"o{k}"), F.col("in").alias(f"i{k}")) for k in ("a", "b"))
    pairs = symmetric_counts(net, path, self_paths).join(one, "a").join(two, "b")
    if form == "pair":
        return pairs.select("a", "b", (F.col("cnt") / (F.col("oa") + F.col("ob"))).alias("s"))
    if form != "matrix":
        raise ValueError(f"form {form}: pair or matrix")
    return pairs.select("a", "b", (F.col("cnt") / (F.col("oa") + F.col("ia"))).alias("s"), (F.col("cnt") / (F.col("ob") + F.col("ib"))).alias("t"))


def _directed(pairs: DataFrame, form: str) -> DataFrame:
    """Each unordered pair as two rows, the diagonal as one; no shuffle."""
    back = F.col("s") if form == "pair" else F.col("t")
    rows = F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst"), F.col("s").alias("s")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst"), back.alias("s")))
    rows = F.when(F.col("a") == F.col("b"), F.slice(rows, 1, 1)).otherwise(rows)
    return pairs.select(F.explode(rows).alias("r")).select("r.*")


def _form(form: str) -> str:
    if form not in ("pair", "matrix"):
        raise ValueError(f"form {form}: pair or matrix")
    return form


def crossed_blocks(net: HetNet, mix: dict[int, float], self_paths: bool = False) -> Blocks | None:
    """Users by blocks with all that closeness by the paths of `mix` needs, or None where joins on attributes are better:
    where few users share any."""
    paths = [p for p in mix if p > 2]
    mine = had(incidence(net, paths)) if paths else None
    users = shared.crossed(mine) if paths else 0
    if not users:
        return None
    have, each = crossed_parts(net, mix, mine, self_paths)
    return Blocks(have, users, shared.BLOCK, each)


def crossed_parts(net: HetNet, mix: dict[int, float], mine: DataFrame, self_paths: bool = False) -> tuple[DataFrame, DataFrame]:
    """What users have on the middles of paths (path, user_id, attr, cnt), and their counts (user_id, path, o, i)."""
    paths = [p for p in mix if p > 2]
    each = [shared_marginals(with_totals(mine), self_paths).filter("out > 0").select("user_id", "path", F.col("out").alias("o"), F.col("out").alias("i"))]
    each += [path_marginals(net, p, self_paths).select("user_id", F.lit(p).alias("path"), F.col("out").alias("o"), F.col("in").alias("i")) for p in mix if p <= 2]
    # Paths 1 and 2 need both ends of links, which are the middles of paths 3 and 4.
    ends = [p for p in (3, 4) if p not in paths and any(q <= 2 for q in mix)]
    have = mine.union(incidence(net, ends)) if ends else mine
    return have, reduce(DataFrame.union, each)


def closeness(net: HetNet, weights: dict[int, float] | str = "uniform", form: str = "pair", self_paths: bool = False, digits: int | None = None) -> DataFrame:
    """src, dst, s: the weighted sum of path similarities, rounded to `digits`. Unordered pairs are summed once, then written both ways.

    The network's relations are written once, since every path reads them, and so is what users have on the middle of the
    symmetric paths. Counts of all paths meet in one sum by pair, a column a path, and the marginals of all paths are one row
    a user, so users are looked up twice, not twice a path. Where many users share attributes, blocks of users are crossed.
    """
    mix, net = weights_of(weights), net.stored()
    blocks = crossed_blocks(net, mix, self_paths)
    if blocks is not None:
        return blocks.closeness(mix, _form(form), self_paths, digits)
    counts = [symmetric_counts(net, p, self_paths).withColumn("path", F.lit(p)) for p in mix if p <= 2]
    each = [path_marginals(net, p, self_paths).select("user_id", F.lit(p).alias("path"), F.col("out").alias("o"), F.col("in").alias("i")) for p in mix if p <= 2]
    both = [p for p in mix if p > 2]
    if both:
        shared = held(incidence(net, both))
        counts.append(shared_counts(shared, True, self_paths).select(F.col("src").alias("a"), F.col("dst").alias("b"), (2 * F.col("cnt")).alias("cnt"), "path"))
        each.append(shared_marginals(shared, self_paths).filter("out > 0").select("user_id", "path", F.col("out").alias("o"), F.col("out").alias("i")))
    sums = reduce(DataFrame.unionByName, counts).groupBy("a", "b").agg(*(F.sum(F.when(F.col("path") == p, F.col("cnt"))).alias(f"n{p}") for p in mix))
    wide = reduce(DataFrame.union, each).groupBy("user_id").agg(*(F.max(F.when(F.col("path") == p, F.col(c))).alias(f"{c}{p}") for p in mix for c in ("o", "i")))
    wide = store(wide, "marginals")
    a, b = (wide.select(F.col("user_id").alias(u), *(F.coalesce(f"{c}{p}", F.lit(0)).alias(f"{c}{p}{u}") for p in mix for c in ("o", "i"))) for u in ("a", "b"))
    users = wide.count()
    pairs = join_small(join_small(sums, a, "a", "inner", users), b, "b", "inner", users)

    def total(below) -> Column:
        return reduce(Column.__add__, [F.coalesce(F.lit(float(w)) * F.col(f"n{p}") / below(p), F.lit(0.0)) for p, w in mix.items()])

    if form == "pair":
        return _rounded(_directed(pairs.select("a", "b", total(lambda p: F.nullif(F.col(f"o{p}a") + F.col(f"o{p}b"), F.lit(0))).alias("s")), form), digits)
    if form != "matrix":
        raise ValueError(f"form {form}: pair or matrix")
    out = lambda u: total(lambda p: F.nullif(F.col(f"o{p}{u}") + F.col(f"i{p}{u}"), F.lit(0)))
    return _rounded(_directed(pairs.select("a", "b", out("a").alias("s"), out("b").alias("t")), form), digits)


class CrossedCloseness:
    """Closeness of a network whose users share much: its products and sums are formed in tasks that cross blocks of users,
    and no pair is a row of a table. form: pair, matrix, or symmetric (the symmetric part of matrix)."""

    def __init__(self, net: HetNet, blocks: Blocks, mix: dict[int, float], form: str = "pair"):
        self.net, self.blocks, self.mix, self.form = net, blocks, mix, form

    def terms(self) -> Terms | None:
        """Its products by terms that have factors, or None where it has none or one path's would be too much for a task."""
        paths = [p for p in self.mix if p > 2]
        if self.form != "pair" or not paths:
            return None
        mine = had(incidence(self.net, paths))
        if max((r["count"] for r in mine.groupBy("path").count().collect()), default=0) > MOST_ENTRIES:
            return None
        return Terms(*crossed_parts(self.net, self.mix, mine), self.mix, self.net.users)

    @staticmethod
    def of(net: HetNet, weights: dict[int, float] | str = "uniform", form: str = "pair") -> CrossedCloseness | None:
        """None where joins on attributes are better."""
        mix, net = weights_of(weights), net.stored()
        blocks = crossed_blocks(net, mix)
        return None if blocks is None else CrossedCloseness(net, blocks, mix, form)

    def times(self, rows: DataFrame, squares: bool = False) -> DataFrame:
        """user_id, vec: closeness times rows (user_id, vec); with one number more, the squared length of the user's row."""
        return self.blocks.times(self.mix, self.form, rows, squares)

    def degrees(self) -> DataFrame:
        return self.times(self.net.users.select("user_id", F.array(F.lit(1.0)).alias("vec"))).select("user_id", F.col("vec")[0].alias("d")).filter("d > 0")

    def cluster_flow(self, partition: DataFrame) -> DataFrame:
        """c1, c2, w: similarity from cluster to cluster, from each user's to every cluster."""
        number = partition.select(F.col("cluster").alias("c2")).distinct().agg(F.array_sort(F.collect_list("c2")).alias("all"))  # K numbers
        labelled = partition.crossJoin(F.broadcast(number))
        one = labelled.select("user_id", F.transform("all", lambda c: F.when(c == F.col("cluster"), 1.0).otherwise(0.0)).alias("vec"))
        to = self.times(one).join(labelled, "user_id").select(F.col("cluster").alias("c1"), F.explode(F.arrays_zip("all", "vec")).alias("r"))
        return to.select("c1", F.col("r")["all"].alias("c2"), F.col("r")["vec"].alias("w")).filter("w > 0").groupBy("c1", "c2").agg(F.sum("w").alias("w"))

    def closest(self, top: int, digits: int) -> DataFrame:
        """src, dst, s rounded: as sparsify() of pair closeness, with reverse entries (which are equal)."""
        some = self.blocks.closest(self.mix, top, digits).withColumn("s", F.round("s", digits))
        best = sparsify(some, top, keep_symmetric=False)
        return best.union(best.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "s")).distinct()

    def profile(self) -> DataFrame:
        return _profile(self.blocks.linked(self.mix), self.net.users)


def symmetric_part(S: DataFrame) -> DataFrame:
    """Half of S and its transpose."""
    both = S.select("src", "dst", (F.col("s") / 2).alias("s"))
    return both.union(both.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "s")).groupBy("src", "dst").agg(F.sum("s").alias("s"))


def degrees(S: DataFrame) -> DataFrame:
    return S.groupBy(F.col("src").alias("user_id")).agg(F.sum("s").alias("d"))


def sparsify(S: DataFrame, top: int, keep_symmetric: bool = True) -> DataFrame:
    """Each user's `top` closest (ties by id); with keep_symmetric also their reverse entries."""
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.col("s").desc(), "dst"))
    best = S.withColumn("_r", rank).filter(F.col("_r") <= top).select("src", "dst", "s")
    if not keep_symmetric:
        return best
    wanted = best.select("src", "dst").union(best.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()
    return S.join(wanted, ["src", "dst"], "left_semi")


def profile(S: DataFrame, follow: DataFrame, users: DataFrame) -> DataFrame:
    """pairs (with closeness), direct (of them with a link one way at least), indirect, possible ordered pairs."""
    link = follow.union(follow.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct().withColumn("direct", F.lit(1))
    return _profile(S.join(link, ["src", "dst"], "left").agg(F.count("*").alias("pairs"), F.count("direct").alias("direct")), users)


def _profile(got: DataFrame, users: DataFrame) -> DataFrame:
    return got.crossJoin(users.agg((F.count("*") * (F.count("*") - 1)).alias("possible"))).select("pairs", "direct", (F.col("pairs") - F.col("direct")).alias("indirect"), "possible")


def ancestor_similarity(net: HetNet, path: int, digits: int | None = None) -> DataFrame:
    """The earlier measure for symmetric paths: twice the count over the two users' counts to themselves, rounded to `digits`."""
    if path > 2:
        mine = had(incidence(net, [path]))
        users = shared.crossed(mine)
        if users:
            own = mine.groupBy("user_id", "path").agg(F.sum(F.col("cnt") * F.col("cnt")).alias("o"))
            return Blocks(mine, users, shared.BLOCK, own.select("user_id", "path", "o", F.col("o").alias("i"))).closeness({path: 1.0}, "pair", digits=digits)
    counts = path_counts(net, path, self_paths=True)
    own = counts.filter("src = dst").select(F.col("src").alias("u"), F.col("cnt").alias("own"))
    pairs = counts.filter("src <> dst")
    a, b = own.select(F.col("u").alias("src"), F.col("own").alias("oa")), own.select(F.col("u").alias("dst"), F.col("own").alias("ob"))
    return _rounded(pairs.join(a, "src").join(b, "dst").select("src", "dst", (2 * F.col("cnt") / (F.col("oa") + F.col("ob"))).alias("s")), digits)


def common_neighbours(net: HetNet) -> DataFrame:
    """src < dst and the number of users both follow."""
    return path_counts(net, 3, half=True).select("src", "dst", F.col("cnt").alias("common"))


def jaccard(net: HetNet) -> DataFrame:
    deg = net.follow.groupBy(F.col("src").alias("u")).agg(F.count("*").alias("d"))
    a, b = deg.select(F.col("u").alias("src"), F.col("d").alias("da")), deg.select(F.col("u").alias("dst"), F.col("d").alias("db"))
    return common_neighbours(net).join(a, "src").join(b, "dst").select("src", "dst", (F.col("common") / (F.col("da") + F.col("db") - F.col("common"))).alias("s"))


def vote_weights(net: HetNet, partition: DataFrame, weights: dict[int, float], form: str = "pair") -> DataFrame:
    """path, weight after one round: the mean of its old weight and its share of similarity within clusters."""
    blocks = crossed_blocks(net.stored(), weights)
    if blocks is not None:
        old = F.element_at(F.create_map(*[F.lit(x) for p, w in weights.items() for x in (p, float(w))]), F.col("path"))
        return _voted(blocks.inside(weights, _form(form), partition).select("path", old.alias("old"), "mass"))
    inside = []
    p1, p2 = (partition.select(F.col("user_id").alias(c), F.col("cluster").alias(f"c_{c}")) for c in ("src", "dst"))
    for path in weights:
        s = path_similarity(net, path, form).join(p1, "src").join(p2, "dst").filter("c_src = c_dst")
        inside.append(s.agg(F.coalesce(F.sum("s"), F.lit(0.0)).alias("mass")).select(F.lit(path).alias("path"), F.lit(float(weights[path])).alias("old"), "mass"))
    return _voted(reduce(DataFrame.union, inside))


def _voted(votes: DataFrame) -> DataFrame:
    share = F.coalesce(F.try_divide(F.col("mass"), F.sum("mass").over(Window.partitionBy())), F.col("old"))
    return votes.select("path", ((F.col("old") + share) / 2).alias("weight"))


def learn_weights(net: HetNet, partition: DataFrame, rounds: int = 3, weights: dict[int, float] | str = "uniform") -> dict[int, float]:
    """Weights after some rounds of votes of a fixed partition (seven numbers)."""
    now = weights_of(weights)
    for _ in range(rounds):
        now = {r["path"]: r["weight"] for r in vote_weights(net, partition, now).collect()}
    return now

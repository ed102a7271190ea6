"""Closeness times vectors without forming closeness.

In the row-normalised form, path i contributes D^-1 (A + A') with A a product of incidence tables, so A X is two products
with them (less the closed walks). A hub attribute then costs its posts, not the square of its users: no cap is needed.
The symmetric form divides by both users' counts and has no such factors.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.hetnet import HetNet
from ..operators.closeness import weights_of
from ..operators.metapath import KIND_OF, SOCIAL, path_marginals
from ..storage import store
from .blocks import add_rows, spmm


def _turned(e: DataFrame) -> DataFrame:
    return e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")


def _plus(rows: list[DataFrame]) -> DataFrame:
    return rows[0] if len(rows) == 1 else reduce(DataFrame.union, rows)


class Factors:
    """Incidence tables and marginals of a network, stored once for any number of products."""

    def __init__(self, net: HetNet, weights: dict[int, float] | str = "uniform"):
        self.weights = weights_of(weights)
        some = [p for p in SOCIAL if p in self.weights]
        self.follow = store(net.follow.select("src", "dst", F.lit(1.0).alias("w")), "links") if some else None
        self.incidence, own = {}, []
        for path, weight in self.weights.items():
            if path in KIND_OF:
                c = net.user_attributes(KIND_OF[path]).select(F.col("user_id").alias("src"), F.xxhash64("attr").alias("dst"), F.col("cnt").cast("double").alias("w"))
                c = self.incidence[path] = store(c, "incidence")
                closed = c.groupBy(F.col("src").alias("user_id")).agg((2.0 * F.sum(F.col("w") * F.col("w"))).alias("own"))
            elif path == 2:
                closed = self.follow.join(_turned(self.follow).select("src", "dst"), ["src", "dst"], "left_semi").groupBy(F.col("src").alias("user_id")).agg((2.0 * F.count("*")).alias("own"))
            elif path in (3, 4):
                closed = self.follow.groupBy(F.col("src" if path == 3 else "dst").alias("user_id")).agg((2.0 * F.count("*")).alias("own"))
            else:
                closed = net.users.select("user_id", F.lit(0.0).alias("own")).limit(0)
            m = path_marginals(net, path).select("user_id", (1.0 / (F.col("out") + F.col("in"))).alias("f"))
            own.append(m.join(closed, "user_id", "left").select("user_id", F.lit(path).alias("path"), (F.col("f") * F.lit(float(weight))).alias("f"), F.coalesce("own", F.lit(0.0)).alias("own")))
        # One row a user: what each path scales it by, and its closed walks.
        entry = lambda c: F.map_from_entries(F.collect_list(F.struct("path", c)))
        self.of_user = store(_plus(own).groupBy("user_id").agg(entry("f").alias("f"), entry("own").alias("own")), "marginals")

    def _walked(self, path: int, rows: DataFrame) -> DataFrame:
        """user_id, vec in parts: (A + A') times rows, closed walks included."""
        f = self.follow
        if path == 1:
            return _plus([spmm(f, rows), spmm(_turned(f), rows)])
        if path == 2:
            return _plus([spmm(f, spmm(f, rows)), spmm(_turned(f), spmm(_turned(f), rows))])
        a = {3: f, 4: _turned(f) if f is not None else None}.get(path)
        a = self.incidence[path] if a is None else a
        twice = spmm(a, spmm(_turned(a), rows))
        return twice.select("user_id", F.transform("vec", lambda v: 2 * v).alias("vec"))

    def _open(self, path: int, rows: DataFrame) -> DataFrame:
        """(A + A') times rows without closed walks, in parts, of users with a marginal."""
        known = self.of_user.select("user_id", F.col("own")[path].alias("_own"))
        closed = rows.join(known, "user_id").filter("_own > 0").select("user_id", F.transform("vec", lambda v: -v * F.col("_own")).alias("vec"))
        return self._walked(path, rows).union(closed)

    def times(self, rows: DataFrame) -> DataFrame:
        """user_id, vec: S X for the row-normalised S and rows (user_id, vec)."""
        parts = []
        for path in self.weights:
            scale = self.of_user.select("user_id", F.col("f")[path].alias("_f")).filter("_f is not null")
            parts.append(self._open(path, rows).join(scale, "user_id").select("user_id", F.transform("vec", lambda v: v * F.col("_f")).alias("vec")))
        return add_rows(_plus(parts))

    def symmetric_times(self, rows: DataFrame) -> DataFrame:
        """The same for half of S and its transpose: a path's product goes over rows beside scaled rows, and the first half
        of what it gives is scaled after."""
        width = F.size("vec") / 2
        parts = []
        for path in self.weights:
            scale = self.of_user.select("user_id", F.col("f")[path].alias("_f")).filter("_f is not null")
            wide = rows.join(scale, "user_id", "left").select("user_id", F.concat("vec", F.transform("vec", lambda v: v * F.coalesce("_f", F.lit(0.0)))).alias("vec"))
            got = self._open(path, store(wide, "wide")).join(scale, "user_id", "left")
            first, last = F.slice("vec", F.lit(1), width.cast("int")), F.slice("vec", width.cast("int") + 1, width.cast("int"))
            parts.append(got.select("user_id", F.zip_with(first, last, lambda a, b: (a * F.coalesce("_f", F.lit(0.0)) + b) / 2).alias("vec")))
        return add_rows(_plus(parts))


def closeness_times(net: HetNet, rows: DataFrame, weights: dict[int, float] | str = "uniform") -> DataFrame:
    """user_id, vec: S X for the row-normalised S and rows (user_id, vec)."""
    return Factors(net, weights).times(rows)

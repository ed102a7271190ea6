"""Disagreement of two networks' confidences about anchor users."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import ship


def to_common(rows1: DataFrame, rows2: DataFrame, anchors: DataFrame) -> DataFrame:
    """u1, u2, vec1, vec2: both networks' rows of anchor users, in one order: pruning is a join, aligning a renaming."""
    one, two = rows1.select(F.col("user_id").alias("u1"), F.col("vec").alias("vec1")), rows2.select(F.col("user_id").alias("u2"), F.col("vec").alias("vec2"))
    return anchors.join(one, "u1").join(two, "u2").select("u1", "u2", "vec1", "vec2")


def _dot(a, b):
    return F.aggregate(F.zip_with(a, b, lambda p, q: p * q), F.lit(0.0), lambda acc, v: acc + v)


def pair_discrepancy(common: DataFrame) -> DataFrame:
    """i, j, d of each ordered pair of different anchors: the definition itself; quadratic, for tests and small sets."""
    other = common.select(F.col("u1").alias("j"), F.col("vec1").alias("w1"), F.col("vec2").alias("w2"))
    pairs = common.select(F.col("u1").alias("i"), "vec1", "vec2").join(other, F.col("i") != F.col("j"))
    gap = _dot(F.col("vec1"), F.col("w1")) - _dot(F.col("vec2"), F.col("w2"))
    return pairs.select("i", "j", (gap * gap).alias("d"))


def gram_sums(common: DataFrame) -> DataFrame:
    """part (11, 12 or 22), i, j, g: entries of the k x k Gram matrices; each task adds up its own rows first."""
    ship(common.sparkSession)

    def grams(batches):
        import numpy as np
        import pyarrow as pa

        total = None
        for b in batches:
            if not b.num_rows:
                continue
            one, two = (np.stack(b.column(c).to_numpy(zero_copy_only=False)) for c in ("vec1", "vec2"))
            new = [one.T @ one, one.T @ two, two.T @ two]
            total = new if total is None else [x + y for x, y in zip(total, new, strict=True)]
        for name, g in zip((11, 12, 22), total or [], strict=False):
            i, j = np.indices(g.shape)
            yield pa.RecordBatch.from_pydict({"part": pa.array(np.full(g.size, name), pa.int32()), "i": pa.array(i.ravel(), pa.int32()), "j": pa.array(j.ravel(), pa.int32()), "g": pa.array(g.ravel())})

    return common.select("vec1", "vec2").mapInArrow(grams, "part int, i int, j int, g double").groupBy("part", "i", "j").agg(F.sum("g").alias("g"))


def discrepancy(common: DataFrame, include_diagonal: bool = False, normalise: bool = False) -> DataFrame:
    """discrepancy over all pairs of anchors, from Gram matrices: |G11|^2 + |G22|^2 - 2 |G12|^2, never anchors x anchors.

    normalise divides by links x (links - 1); fewer than two links give 0. Without normalising it is the absolute
    disagreement over all mapped users.
    """
    sign = F.when(F.col("part") == 12, -2.0).otherwise(1.0)
    total = gram_sums(common).agg(F.coalesce(F.sum(sign * F.col("g") * F.col("g")), F.lit(0.0)).alias("all"))
    gap = _dot(F.col("vec1"), F.col("vec1")) - _dot(F.col("vec2"), F.col("vec2"))
    own = common.agg(F.coalesce(F.sum(gap * gap), F.lit(0.0)).alias("own"), F.count("*").alias("a"))
    value = F.col("all") if include_diagonal else F.col("all") - F.col("own")
    if normalise:
        value = F.when(F.col("a") < 2, 0.0).otherwise(F.try_divide(value, F.col("a") * (F.col("a") - 1)))
    return total.crossJoin(own).select(value.alias("discrepancy"))

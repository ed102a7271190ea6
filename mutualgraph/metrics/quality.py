"""Quality of one network's partitions.

A partition is user_id, cluster; with a column `run` it holds many partitions, all are scored in the same jobs, and the
result has a row for each run.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..linalg.blocks import sums
from ..storage import store


def keyed(df: DataFrame) -> DataFrame:
    """With a run: a constant one if there is none."""
    return df if "run" in df.columns else df.withColumn("run", F.lit(0))


def _result(df: DataFrame, like: DataFrame, *names: str) -> DataFrame:
    return df.select(*(["run"] if "run" in like.columns else []), *names)


def _sizes(part: DataFrame) -> DataFrame:
    return part.groupBy("run", "cluster").agg(F.count("*").alias("n"))


def entropy(partition: DataFrame, base: float = 2.0) -> DataFrame:
    p = F.col("n") / F.sum("n").over(Window.partitionBy("run"))
    sizes = _sizes(keyed(partition)).withColumn("p", p)
    return _result(sizes.groupBy("run").agg(F.coalesce(-F.sum(F.col("p") * F.log(float(base), "p")), F.lit(0.0)).alias("entropy")), partition, "entropy")


def density(follow: DataFrame, partition: DataFrame) -> DataFrame:
    """Share of links that stay inside clusters; 0 without links."""
    part = keyed(partition)
    a, b = (part.select("run", F.col("user_id").alias(u), F.col("cluster").alias(c)) for u, c in (("src", "c1"), ("dst", "c2")))
    inside = F.avg(F.when(F.col("c1") == F.col("c2"), 1.0).otherwise(0.0))
    got = follow.join(a, "src").join(b, ["run", "dst"]).groupBy("run").agg(inside.alias("d"))
    runs = part.select("run").distinct()
    return _result(runs.join(got, "run", "left").withColumn("density", F.coalesce("d", F.lit(0.0))), partition, "density")


def dense_features(vectors: DataFrame, user: str, vec: str) -> DataFrame:
    """user_id, dim, x: long form of array rows, without zeros."""
    return vectors.select(F.col(user).alias("user_id"), F.posexplode(vec).alias("dim", "x")).select("user_id", F.col("dim").cast("long"), F.col("x").cast("double").alias("x")).filter("x <> 0")


def closeness_features(S: DataFrame) -> DataFrame:
    """user_id, dim, x: each user's row of S."""
    return S.select(F.col("src").alias("user_id"), F.col("dst").alias("dim"), F.col("s").alias("x"))


def _square(features: DataFrame, part: DataFrame) -> DataFrame:
    """part with xx, each user's squared length."""
    return part.join(features.groupBy("user_id").agg(F.sum(F.col("x") * F.col("x")).alias("xx")), "user_id", "left").withColumn("xx", F.coalesce("xx", F.lit(0.0)))


def _centres(features: DataFrame, part: DataFrame) -> tuple[DataFrame, DataFrame]:
    """run, cluster, dim, c of the centroids; and run, cluster, n, cc (squared length). Sparse rows stay sparse in all
    that follows: |x - c|^2 = |x|^2 - 2 x.c + |c|^2."""
    sizes = _sizes(part)
    cent = features.join(part, "user_id").groupBy("run", "cluster", "dim").agg(F.sum("x").alias("sum")).join(sizes, ["run", "cluster"]).select("run", "cluster", "dim", (F.col("sum") / F.col("n")).alias("c"))
    norm = sizes.join(cent.groupBy("run", "cluster").agg(F.sum(F.col("c") * F.col("c")).alias("cc")), ["run", "cluster"], "left").select("run", "cluster", "n", F.coalesce("cc", F.lit(0.0)).alias("cc"))
    return cent, norm


def ndbi(features: DataFrame, partition: DataFrame) -> DataFrame:
    """Mean over clusters of the smallest 2d / (spread + spread + 2d) against any other cluster; null for one cluster."""
    part = keyed(partition)
    cent, norm = _centres(features, part)
    own = features.join(part, "user_id").join(cent, ["run", "cluster", "dim"]).groupBy("run", "user_id").agg(F.sum(F.col("x") * F.col("c")).alias("xc"))
    far = _square(features, part).join(own, ["run", "user_id"], "left").join(norm, ["run", "cluster"])
    gap = F.col("xx") - 2 * F.coalesce("xc", F.lit(0.0)) + F.col("cc")
    spread = far.groupBy("run", "cluster").agg(F.avg(F.sqrt(F.greatest(gap, F.lit(0.0)))).alias("spread"))
    one, two = cent.select("run", F.col("cluster").alias("i"), "dim", F.col("c").alias("x")), cent.select("run", F.col("cluster").alias("j"), "dim", F.col("c").alias("y"))
    dots = one.join(two, ["run", "dim"]).filter("i <> j").groupBy("run", "i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("xy"))
    table = norm.join(spread, ["run", "cluster"])
    a = table.select("run", F.col("cluster").alias("i"), F.col("cc").alias("ci"), F.col("spread").alias("si"))
    b = table.select("run", F.col("cluster").alias("j"), F.col("cc").alias("cj"), F.col("spread").alias("sj"))
    # K x K rows a run: clusters, not users.
    pairs = a.join(b, "run").filter("i <> j").join(dots, ["run", "i", "j"], "left")
    d = F.sqrt(F.greatest(F.col("ci") + F.col("cj") - 2 * F.coalesce("xy", F.lit(0.0)), F.lit(0.0)))
    ratio = F.coalesce(F.try_divide(2 * d, F.col("si") + F.col("sj") + 2 * d), F.lit(0.0))
    score = pairs.groupBy("run", "i").agg(F.min(ratio).alias("r")).groupBy("run").agg(F.avg("r").alias("ndbi"))
    return _result(part.select("run").distinct().join(score, "run", "left"), partition, "ndbi")


def ndbi_products(rows, partition: DataFrame) -> DataFrame:
    """The same for rows of a symmetric matrix that is known by its products alone, rows.times(vectors, squares): one product
    gives the centroids and squared lengths, another how far users are from their own centroid. K x K numbers reach the driver."""
    sizes = {r["cluster"]: r["n"] for r in partition.groupBy("cluster").agg(F.count("*").alias("n")).collect()}  # K rows
    labels = sorted(sizes)
    if len(labels) < 2:
        return partition.sparkSession.createDataFrame([(None,)] if labels else [], "ndbi double")
    at = F.array_position(F.array(*[F.lit(c) for c in labels]), F.col("cluster")).cast("int")
    one = partition.select("user_id", F.array(*[F.when(F.col("cluster") == c, 1.0 / sizes[c]).otherwise(0.0) for c in labels]).alias("vec"))
    first = store(rows.times(one, True), "centres")
    cent = first.select("user_id", F.slice("vec", 1, len(labels)).alias("vec"))
    dots = sums(cent, ["vec"], lambda c: {"g": c["vec"].T @ c["vec"]}).get("g", np.zeros((len(labels), len(labels))))
    xx = first.select("user_id", F.element_at("vec", -1).alias("xx"))
    own = rows.times(cent).withColumnRenamed("vec", "dots")
    cc = F.element_at(F.array(*[F.lit(float(x)) for x in np.diag(dots)]), at)
    far = partition.join(xx, "user_id", "left").join(own, "user_id", "left")
    gap = F.coalesce("xx", F.lit(0.0)) - 2 * F.coalesce(F.element_at("dots", at), F.lit(0.0)) + cc
    spread = {r["cluster"]: r["s"] for r in far.groupBy("cluster").agg(F.avg(F.sqrt(F.greatest(gap, F.lit(0.0)))).alias("s")).collect()}
    s = np.array([spread[c] for c in labels])
    d = 2 * np.sqrt(np.maximum(np.add.outer(np.diag(dots), np.diag(dots)) - 2 * dots, 0))
    below = np.add.outer(s, s) + d
    ratio = np.divide(d, below, out=np.zeros_like(d), where=below > 0)
    np.fill_diagonal(ratio, np.inf)
    return partition.sparkSession.createDataFrame([(float(ratio.min(1).mean()),)], "ndbi double")


def _macro(means: DataFrame, part: DataFrame, partition: DataFrame) -> DataFrame:
    """silhouette: mean over clusters of their members' mean, from run, user_id, cluster, other cluster, mean distance.
    A singleton scores 0; with one cluster the measure is null."""
    a = F.max(F.when(F.col("cluster") == F.col("other"), F.col("mean")))
    b = F.min(F.when(F.col("cluster") != F.col("other"), F.col("mean")))
    each = means.groupBy("run", "user_id", "cluster").agg(a.alias("a"), b.alias("b")).join(_sizes(part), ["run", "cluster"])
    score = F.when(F.col("n") == 1, 0.0).otherwise(F.coalesce(F.try_divide(F.col("b") - F.col("a"), F.greatest("a", "b")), F.lit(0.0)))
    score = each.withColumn("sil", F.when(F.col("b").isNotNull(), score)).groupBy("run", "cluster").agg(F.avg("sil").alias("m")).groupBy("run").agg(F.avg("m").alias("silhouette"))
    return _result(score, partition, "silhouette")


def distances(features: DataFrame, users: DataFrame) -> DataFrame:
    """u, v, d of all ordered pairs of different users: quadratic."""
    xx = _square(features, users.select("user_id").distinct())
    u, v = xx.select(F.col("user_id").alias("u"), F.col("xx").alias("xu")), xx.select(F.col("user_id").alias("v"), F.col("xx").alias("xv"))
    a, b = features.select(F.col("user_id").alias("u"), "dim", F.col("x").alias("p")), features.select(F.col("user_id").alias("v"), "dim", F.col("x").alias("q"))
    dots = a.join(b, "dim").filter("u <> v").groupBy("u", "v").agg(F.sum(F.col("p") * F.col("q")).alias("dot"))
    pairs = u.join(v, F.col("u") != F.col("v")).join(dots, ["u", "v"], "left")
    return pairs.select("u", "v", F.sqrt(F.greatest(F.col("xu") + F.col("xv") - 2 * F.coalesce("dot", F.lit(0.0)), F.lit(0.0))).alias("d"))


def silhouette(features: DataFrame, partition: DataFrame, pairs: DataFrame | None = None) -> DataFrame:
    """Exact, by distances of all pairs of users (given, or formed once for all runs): quadratic, for thousands of users;
    silhouette_squared beyond."""
    part = keyed(partition)
    pairs = distances(features, part) if pairs is None else pairs
    other = part.select("run", F.col("user_id").alias("v"), F.col("cluster").alias("other"))
    mean = pairs.join(other, "v").groupBy("run", F.col("u").alias("user_id"), "other").agg(F.avg("d").alias("mean")).join(part, ["run", "user_id"]).select("run", "user_id", "cluster", "other", "mean")
    return _macro(mean, part, partition)


def silhouette_squared(features: DataFrame, partition: DataFrame) -> DataFrame:
    """The same with squared distances, whose means follow from each cluster's sum, sum of squares and size: linear."""
    part = keyed(partition)
    cent, norm = _centres(features, part)
    xx = _square(features, part)
    mean_sq = xx.groupBy("run", "cluster").agg(F.avg("xx").alias("mxx"))
    other = norm.join(mean_sq, ["run", "cluster"]).select("run", F.col("cluster").alias("other"), F.col("n").alias("m"), "mxx")
    dots = features.join(cent, "dim").groupBy("run", "user_id", F.col("cluster").alias("other")).agg(F.sum(F.col("x") * F.col("c")).alias("xc"))
    # users x clusters rows of each run.
    all_ = xx.join(other, "run").join(dots, ["run", "user_id", "other"], "left")
    whole = F.col("xx") - 2 * F.coalesce("xc", F.lit(0.0)) + F.col("mxx")
    mean = F.when((F.col("cluster") == F.col("other")) & (F.col("m") > 1), whole * F.col("m") / (F.col("m") - 1)).otherwise(whole)
    return _macro(all_.select("run", "user_id", "cluster", "other", mean.alias("mean")), part, partition)

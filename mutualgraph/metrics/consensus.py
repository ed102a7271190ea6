"""Agreement of two partitions about anchor users, from their contingency table; of many pairs at once by `run`."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .quality import keyed


def contingency(part1: DataFrame, part2: DataFrame, anchors: DataFrame) -> DataFrame:
    """(run,) c1, c2, n: anchors by cluster on either side; at most K1 x K2 rows a run, whatever the anchors' number.
    anchors may have a run, too."""
    many = "run" in part1.columns
    a, b = keyed(part1).select("run", F.col("user_id").alias("u1"), F.col("cluster").alias("c1")), keyed(part2).select("run", F.col("user_id").alias("u2"), F.col("cluster").alias("c2"))
    at = anchors.join(a, ["run", "u1"] if "run" in anchors.columns else "u1").join(b, ["run", "u2"])
    return at.groupBy(*(["run"] if many else []), "c1", "c2").agg(F.count("*").alias("n"))


def rand(table: DataFrame) -> DataFrame:
    """Share of anchor pairs that one partition joins and the other parts; 0 with fewer than two anchors."""
    two = lambda n: n * (n - 1) / 2
    t = keyed(table)
    joint = t.groupBy("run").agg(F.sum(two(F.col("n"))).alias("both"), F.sum("n").alias("a"))
    one = t.groupBy("run", "c1").agg(F.sum("n").alias("n")).groupBy("run").agg(F.sum(two(F.col("n"))).alias("in1"))
    other = t.groupBy("run", "c2").agg(F.sum("n").alias("n")).groupBy("run").agg(F.sum(two(F.col("n"))).alias("in2"))
    value = F.try_divide(F.col("in1") + F.col("in2") - 2 * F.col("both"), two(F.col("a")))
    out = joint.join(one, "run").join(other, "run").select("run", F.coalesce(value, F.lit(0.0)).alias("rand"))
    return out if "run" in table.columns else out.drop("run")


def rand_by_pairs(part1: DataFrame, part2: DataFrame, anchors: DataFrame) -> DataFrame:
    """The definition, over all unordered pairs: quadratic, for tests."""
    a, b = part1.select(F.col("user_id").alias("u1"), F.col("cluster").alias("c1")), part2.select(F.col("user_id").alias("u2"), F.col("cluster").alias("c2"))
    at = anchors.join(a, "u1").join(b, "u2").select("u1", "c1", "c2")
    other = at.select(F.col("u1").alias("v1"), F.col("c1").alias("d1"), F.col("c2").alias("d2"))
    differ = F.when((F.col("c1") == F.col("d1")) != (F.col("c2") == F.col("d2")), 1.0).otherwise(0.0)
    return at.join(other, F.col("u1") < F.col("v1")).agg(F.coalesce(F.avg(differ), F.lit(0.0)).alias("rand"))


def information(table: DataFrame, base: float = 2.0, sizes1: DataFrame | None = None, sizes2: DataFrame | None = None) -> DataFrame:
    """(run,) h1, h2, mi, vi, nmi. P(i) and P(j) are over anchors, so that mi is one; with sizes1 and sizes2 (c1 or c2, n:
    all users of each cluster) they are over all users, as the formulas read literally. A zero entropy gives nmi 0."""
    t = keyed(table)
    total = Window.partitionBy("run")
    share = lambda df, p: df.withColumn(p, F.col("n") / F.sum("n").over(total)).drop("n")
    m1 = share(keyed(sizes1) if sizes1 is not None else t.groupBy("run", "c1").agg(F.sum("n").alias("n")), "p1")
    m2 = share(keyed(sizes2) if sizes2 is not None else t.groupBy("run", "c2").agg(F.sum("n").alias("n")), "p2")
    log = lambda x: F.log(float(base), x)
    zero = lambda c: F.coalesce(c, F.lit(0.0))
    h1, h2 = m1.groupBy("run").agg(zero(-F.sum(F.col("p1") * log(F.col("p1")))).alias("h1")), m2.groupBy("run").agg(zero(-F.sum(F.col("p2") * log(F.col("p2")))).alias("h2"))
    joint = share(t, "p").join(m1, ["run", "c1"]).join(m2, ["run", "c2"])
    mi = joint.groupBy("run").agg(zero(F.sum(F.col("p") * log(F.col("p") / (F.col("p1") * F.col("p2"))))).alias("mi"))
    nmi = F.when((F.col("h1") > 1e-12) & (F.col("h2") > 1e-12), F.try_divide(F.col("mi"), F.sqrt(F.col("h1") * F.col("h2")))).otherwise(0.0)
    out = mi.join(h1, "run").join(h2, "run").select("run", "h1", "h2", "mi", (F.col("h1") + F.col("h2") - 2 * F.col("mi")).alias("vi"), nmi.alias("nmi"))
    return out if "run" in table.columns else out.drop("run")


def agreement_with_truth(partition: DataFrame, truth: DataFrame) -> DataFrame:
    """nmi, adjusted_rand and purity against user_id, label."""
    t = partition.join(truth, "user_id").groupBy(F.col("cluster").alias("c1"), F.col("label").alias("c2")).agg(F.count("*").alias("n"))
    two = lambda n: n * (n - 1) / 2
    both = t.agg(F.sum(two(F.col("n"))).alias("both"), F.sum("n").alias("a"))
    one = t.groupBy("c1").agg(F.sum("n").alias("n"), F.max("n").alias("top")).agg(F.sum(two(F.col("n"))).alias("in1"), F.sum("top").alias("top"))
    other = t.groupBy("c2").agg(F.sum("n").alias("n")).agg(F.sum(two(F.col("n"))).alias("in2"))
    expected = F.try_divide(F.col("in1") * F.col("in2"), two(F.col("a")))
    ari = F.try_divide(F.col("both") - expected, (F.col("in1") + F.col("in2")) / 2 - expected)
    return information(t).select("nmi").crossJoin(both).crossJoin(one).crossJoin(other).select("nmi", ari.alias("adjusted_rand"), (F.col("top") / F.col("a")).alias("purity"))

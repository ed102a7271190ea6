"""Hard partitions: reference ones, validity, costs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.hetnet import HetNet


def violations(users: DataFrame, partition: DataFrame) -> DataFrame:
    """problem, user_id: users without a cluster, with several rows, or unknown ones."""
    missing = users.join(partition, "user_id", "left_anti").select(F.lit("missing").alias("problem"), "user_id")
    many = partition.groupBy("user_id").agg(F.count("*").alias("n")).filter("n > 1").select(F.lit("repeated").alias("problem"), "user_id")
    unknown = partition.join(users, "user_id", "left_anti").select(F.lit("unknown").alias("problem"), "user_id")
    return missing.union(many).union(unknown)


def cluster_flow(S: DataFrame, partition: DataFrame) -> DataFrame:
    """c1, c2, w: similarity from cluster to cluster. Everything below is computed from this K x K table."""
    one, two = (partition.select(F.col("user_id").alias(u), F.col("cluster").alias(c)) for u, c in (("src", "c1"), ("dst", "c2")))
    return S.join(one, "src").join(two, "dst").groupBy("c1", "c2").agg(F.sum("s").alias("w"))


def both_ways(flow: DataFrame) -> DataFrame:
    """The flow of links taken both ways, from that of the links as they are: each of its few rows turned as well."""
    return flow.union(flow.select("c2", "c1", "w")).groupBy("c1", "c2").agg(F.sum("w").alias("w"))


def cut_cost(flow: DataFrame) -> DataFrame:
    return flow.agg((F.coalesce(F.sum(F.when(F.col("c1") != F.col("c2"), F.col("w"))), F.lit(0.0)) / 2).alias("cut"))


def ncut_cost(flow: DataFrame) -> DataFrame:
    """Half the sum over clusters of outgoing over all similarity; clusters without any add 0. trace is twice it."""
    per = flow.groupBy("c1").agg(F.sum("w").alias("vol"), F.sum(F.when(F.col("c1") != F.col("c2"), F.col("w")).otherwise(0.0)).alias("out"))
    return per.agg((F.coalesce(F.sum(F.try_divide("out", "vol")), F.lit(0.0)) / 2).alias("ncut"))


def hard_rows(partition: DataFrame, clusters: int) -> DataFrame:
    """user_id, vec: 0/1 confidences of clusters 0 to clusters - 1."""
    return partition.select("user_id", F.transform(F.sequence(F.lit(0), F.lit(clusters - 1)), lambda i: (i == F.col("cluster")).cast("double")).alias("vec"))


def indicator_rows(partition: DataFrame, degree: DataFrame, clusters: int) -> DataFrame:
    """Confidences with H'DH = I: 1 / sqrt(volume of the cluster)."""
    vol = partition.join(degree, "user_id").groupBy("cluster").agg(F.sum("d").alias("vol"))
    scaled = partition.join(vol, "cluster").select("user_id", "cluster", (1 / F.sqrt("vol")).alias("h"))
    return scaled.select("user_id", F.transform(F.sequence(F.lit(0), F.lit(clusters - 1)), lambda i: F.when(i == F.col("cluster"), F.col("h")).otherwise(0.0)).alias("vec"))


def argmax_assign(rows: DataFrame) -> DataFrame:
    """Each user's most confident cluster, the first on ties."""
    return rows.select("user_id", (F.array_position("vec", F.array_max("vec")) - 1).cast("int").alias("cluster"))


def trace_cost(S: DataFrame, degree: DataFrame, rows: DataFrame) -> DataFrame:
    """Tr(H'LH) of confidence rows, as the sum of s |h_u - h_v|^2 / 2 over entries: one join a side, no matrix."""
    a, b = (rows.select(F.col("user_id").alias(u), F.col("vec").alias(v)) for u, v in (("src", "x"), ("dst", "y")))
    gap = F.aggregate(F.zip_with("x", "y", lambda p, q: (p - q) * (p - q)), F.lit(0.0), lambda acc, v: acc + v)
    return S.join(a, "src").join(b, "dst").agg((F.sum(F.col("s") * gap) / 2).alias("trace"))


def reference(net: HetNet, cluster) -> DataFrame:
    return net.users.select("user_id", cluster.cast("int").alias("cluster"))

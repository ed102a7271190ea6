"""Directions of measures and the combined quality and consensus score."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed values: -1 for measures where higher is better, 1 where lower is.
SIGN = {"ndbi": -1, "density": -1, "silhouette": -1, "silhouette_sq": -1, "mi": -1, "nmi": -1, "entropy": 1, "rand": 1, "vi": 1}
#: The four instances: quality and consensus measure.
INSTANCES = [("entropy", "vi"), ("silhouette", "mi"), ("ndbi", "rand"), ("density", "nmi")]
#: The same with the silhouette of squared distances, which is linear; a measure of its own.
INSTANCES_SQ = [(q.replace("silhouette", "silhouette_sq"), c) for q, c in INSTANCES]


def directions(spark: SparkSession) -> DataFrame:
    rows = [(m, s, "proportional" if s < 0 else "inversely proportional") for m, s in SIGN.items()]
    return spark.createDataFrame(rows, "measure string, sign int, direction string")


def combined(quality: str, consensus: str, q1: Column, q2: Column, c12: Column, c21: Column | None = None, betas=(1.0, 1.0, 1.0, 1.0)) -> Column:
    """Signed sum; lower is better. The consensus measures here are symmetric, so it counts twice by default."""
    c21 = c12 if c21 is None else c21
    return SIGN[quality] * (betas[0] * q1 + betas[1] * q2) + SIGN[consensus] * (betas[2] * c12 + betas[3] * c21)


def relative_gain(report: DataFrame, method: str) -> DataFrame:
    """measure, net, method, gain: by how much of the comparator's value `method` is better (positive) than each other."""
    mine = report.filter(F.col("method") == method).select("measure", "net", F.col("value").alias("own"))
    sign = F.element_at(F.create_map(*[x for m, s in SIGN.items() for x in (F.lit(m), F.lit(float(s)))]), F.col("measure"))
    return report.filter(F.col("method") != method).join(mine, ["measure", "net"]).select("measure", "net", "method", F.try_divide(sign * (F.col("value") - F.col("own")), F.abs("value")).alias("gain"))

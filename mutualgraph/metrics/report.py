"""All measures of two networks' partitions in one long table; with a `run` column, of many pairs of partitions at once."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.hetnet import HetNet
from .combined import INSTANCES, INSTANCES_SQ, combined
from .consensus import contingency, information, rand
from .quality import closeness_features, density, entropy, keyed, ndbi, silhouette, silhouette_squared

_LONG = ["run", "measure", "net", "side", "value"]


def quality_report(net: HetNet, S: DataFrame, partitions: DataFrame, side: int, exact: bool = False, pairs: DataFrame | None = None) -> DataFrame:
    """run, measure, net, side, value. `exact` reports silhouette, of all pairs of users; else silhouette_sq, of squared
    distances, which is linear. They are two measures, whatever the size."""
    features, part = closeness_features(S), keyed(partitions)
    sil = silhouette(features, part, pairs) if exact else silhouette_squared(features, part)
    parts = [("ndbi", ndbi(features, part), "ndbi"), ("silhouette" if exact else "silhouette_sq", sil, "silhouette")]
    return link_report(net, part, side).union(reduce(DataFrame.union, [_long(df, m, net.name, side, c) for m, df, c in parts]))


def _long(df: DataFrame, measure: str, net: str, side: int, column: str) -> DataFrame:
    return df.select("run", F.lit(measure).alias("measure"), F.lit(net).alias("net"), F.lit(side).alias("side"), F.col(column).alias("value"))


def link_report(net: HetNet, partitions: DataFrame, side: int) -> DataFrame:
    """The measures that need no closeness: entropy and density."""
    part = keyed(partitions)
    return _long(entropy(part), "entropy", net.name, side, "entropy").union(_long(density(net.follow, part), "density", net.name, side, "density"))


def consensus_report(part1: DataFrame, part2: DataFrame, anchors: DataFrame) -> DataFrame:
    """run, measure, net ("both"), side (0), value."""
    table = contingency(keyed(part1), keyed(part2), anchors)
    info = information(table)
    return reduce(DataFrame.union, [_long(df, m, "both", 0, m) for m, df in (("rand", rand(table)), ("mi", info), ("vi", info), ("nmi", info))])


def combined_report(report: DataFrame, exact: bool = False) -> DataFrame:
    """The four combined scores (measure "quality+consensus") of each run of a report of both networks."""
    instances = INSTANCES if exact else INSTANCES_SQ
    get = lambda m, k: F.max(F.when((F.col("measure") == m) & (F.col("side") == k), F.col("value")))
    wide = report.groupBy("run").agg(*[get(q, k).alias(f"{q}{k}") for q, _ in instances for k in (1, 2)], *[get(c, 0).alias(c) for _, c in instances])
    scores = F.array(*[F.struct(F.lit(f"{q}+{c}").alias("measure"), combined(q, c, F.col(f"{q}1"), F.col(f"{q}2"), F.col(c)).alias("value")) for q, c in instances])
    return wide.select("run", F.explode(scores).alias("s")).select("run", "s.measure", F.lit("both").alias("net"), F.lit(0).alias("side"), "s.value")


def evaluate(nets: list[HetNet], S: list[DataFrame], part1: DataFrame, part2: DataFrame, anchors: DataFrame, exact: bool = False, pairs: list[DataFrame | None] = [None, None]) -> DataFrame:  # noqa: B006
    """run, measure, net, side, value: quality of both, consensus, and the combined scores."""
    both = quality_report(nets[0], S[0], part1, 1, exact, pairs[0]).union(quality_report(nets[1], S[1], part2, 2, exact, pairs[1])).union(consensus_report(part1, part2, anchors))
    return both.union(combined_report(both, exact))

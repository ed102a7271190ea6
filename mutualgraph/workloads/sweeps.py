"""The experiments: quality, consensus and combined scores by anchor share, clusters and consensus weight.

Every sweep computes closeness once, clusters for each setting, and scores all its partitions together (as runs of one
table), so that a sweep of many settings costs a handful of scoring jobs.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..cluster.baselines import kmeans_rows, normalized_cut, propagation
from ..cluster.mutual import mutual_cluster, similarities
from ..cluster.onetask import Prepared
from ..metrics.held import task_quality
from ..metrics.report import combined_report, consensus_report, link_report, quality_report
from ..model.hetnet import AlignedSet
from ..operators.alignment import sample_anchors
from ..optimize.curvilinear import Settings
from ..storage import store

METHODS = ("joint", "propagation", "normalized cut", "k-means")


@dataclass
class Bench:
    """Stored networks, and what all settings of an experiment share: links or closeness for tasks, or closeness tables."""

    aligned: AlignedSet
    prepared: Prepared | None
    S: list[DataFrame] | None
    exact: bool
    seed: int = 0

    @staticmethod
    def of(aligned: AlignedSet, weights="uniform", form: str = "matrix", exact: bool = False, engine: str = "auto", seed: int = 0) -> Bench:
        """exact: report silhouette rather than silhouette_sq. engine: as mutual_cluster's; it doesn't change a measure."""
        aligned = aligned.stored()
        prepared = None if engine == "tables" else Prepared.of(aligned.nets, weights, form)
        if prepared is not None and prepared.whole:
            return Bench(aligned, prepared, None, exact, seed)
        return Bench(aligned, None, similarities(aligned, weights, form), exact, seed)

    def joint(self, k: list[int], aligned: AlignedSet | None = None, settings: Settings | None = None, **changes):
        engine = "tables" if self.prepared is None else "task"
        return mutual_cluster(aligned or self.aligned, k, settings=settings, closenesses=self.S, engine=engine, prepared=self.prepared, seed=self.seed, **changes)

    def propagated(self, k: list[int], aligned: AlignedSet) -> list[DataFrame]:
        engine = "tables" if self.prepared is None else "task"
        return propagation(aligned, k, self.S, seed=self.seed, engine=engine, prepared=self.prepared)

    def _quality(self, i: int, partitions: DataFrame) -> DataFrame:
        net = self.aligned.nets[i]
        if self.prepared is None:
            return quality_report(net, self.S[i], partitions, i + 1, self.exact)
        wanted = ["ndbi", "silhouette" if self.exact else "silhouette_sq"]
        held = task_quality(self.prepared, i, partitions, self.exact).filter(F.col("measure").isin(wanted))
        return link_report(net, partitions, i + 1).union(held.select("run", "measure", F.lit(net.name).alias("net"), F.lit(i + 1).alias("side"), "value"))

    def score(self, runs: list[tuple[dict, DataFrame, DataFrame, DataFrame]]) -> DataFrame:
        """The settings' columns, measure, net, side, value of (setting, partition, partition, anchors) each. A partition
        that several settings share is scored once."""
        spark = self.aligned.nets[0].users.sparkSession
        tag = lambda parts, cols: store(reduce(DataFrame.union, [p.select(F.lit(n).alias("run"), *cols) for n, p in enumerate(parts)]), "runs")
        known, of = [list({id(r[i]): r[i] for r in runs}.values()) for i in (1, 2)], []
        for i in (1, 2):
            place = {id(p): n for n, p in enumerate(known[i - 1])}
            of.append(spark.createDataFrame([(n, place[id(r[i])]) for n, r in enumerate(runs)], "run int, part int"))
        report = []
        for i in (0, 1):
            scored = self._quality(i, tag(known[i], ["user_id", "cluster"])).withColumnRenamed("run", "part")
            report.append(scored.join(F.broadcast(of[i]), "part").select("run", "measure", "net", "side", "value"))
        p1, p2 = (tag([r[i] for r in runs], ["user_id", "cluster"]) for i in (1, 2))
        report.append(consensus_report(p1, p2, tag([r[3] for r in runs], ["u1", "u2"])))
        whole = store(reduce(DataFrame.union, report), "report")
        whole = whole.union(combined_report(whole, self.exact))
        names = list(runs[0][0])
        rows = [(n, *[str(s[c]) if isinstance(s[c], str) else float(s[c]) for c in names]) for n, (s, *_) in enumerate(runs)]
        kinds = ", ".join(f"`{c}` {'string' if isinstance(runs[0][0][c], str) else 'double'}" for c in names)
        settings = spark.createDataFrame(rows, f"run int, {kinds}")
        return store(whole.join(F.broadcast(settings), "run").select(*names, "measure", "net", "side", "value"), "report")


def run_sigma_sweep(bench: Bench, sigmas: list[float], k: list[int], methods=METHODS, settings: Settings | None = None) -> DataFrame:
    """method, sigma, measure, net, side, value. The isolated methods see links only and run once; anchors only score them."""
    nets, all_anchors = bench.aligned.nets, bench.aligned.anchors[0, 1]
    alone = {}
    if "normalized cut" in methods:
        alone["normalized cut"] = [normalized_cut(n, kk, bench.seed) for n, kk in zip(nets, k, strict=True)]
    if "k-means" in methods:
        alone["k-means"] = [kmeans_rows(n, kk, bench.seed) for n, kk in zip(nets, k, strict=True)]
    runs = []
    for sigma in sigmas:
        anchors = store(sample_anchors(all_anchors, sigma), "anchors")
        some = bench.aligned.with_anchors((0, 1), anchors)
        for m in methods:
            if m == "joint":
                got = bench.joint(k, some, settings)
                parts = [got.partition(0), got.partition(1)]
            elif m == "propagation":
                parts = bench.propagated(k, some)
            else:
                parts = alone[m]
            runs.append(({"method": m, "sigma": sigma}, *parts, anchors))
    return bench.score(runs)


def run_k_sweep(bench: Bench, side: int, values: list[int], other: int, settings: Settings | None = None) -> DataFrame:
    """k, measure, net, side, value of the joint method while the clusters of one network (side 1 or 2) vary."""
    runs = []
    for v in values:
        got = bench.joint([v, other] if side == 1 else [other, v], settings=settings)
        runs.append(({"k": v}, got.partition(0), got.partition(1), bench.aligned.anchors[0, 1]))
    return bench.score(runs)


def run_theta_sweep(bench: Bench, thetas: list[float], k: list[int], **changes) -> DataFrame:
    """theta, measure, net, side, value of the joint method."""
    runs = []
    for t in thetas:
        got = bench.joint(k, settings=Settings(theta=t, **changes))
        runs.append(({"theta": t}, got.partition(0), got.partition(1), bench.aligned.anchors[0, 1]))
    return bench.score(runs)


def run_ablation(aligned: AlignedSet, k: list[int], weights: dict[str, object], forms=("matrix", "pair"), exact: bool = False, seed: int = 0) -> DataFrame:
    """variant, measure, net, side, value: the joint method, no consensus, consensus only, raw disagreement and no
    anchors, for path weights given by name and both forms of closeness, each scored in its own closeness."""
    out = None
    for name, w in weights.items():
        for form in forms:
            bench = Bench.of(aligned, w, form, exact, seed=seed)
            anchors = bench.aligned.anchors[0, 1]
            links = anchors.count()
            variants = {"joint": Settings(), "no consensus": Settings(theta=0.0), "consensus only": Settings(alpha=0.0, beta=0.0), "raw disagreement": Settings(theta=float(max(1, links * (links - 1))))}
            runs = []
            for v, s in variants.items():
                got = bench.joint(k, settings=s)
                runs.append(({"variant": f"{name}, {form}: {v}"}, got.partition(0), got.partition(1), anchors))
            got = bench.joint(k, bench.aligned.with_anchors((0, 1), anchors.limit(0)))
            runs.append(({"variant": f"{name}, {form}: no anchors"}, got.partition(0), got.partition(1), anchors))
            more = bench.score(runs)
            out = more if out is None else out.union(more)
    return out


def convergence(bench: Bench, k: list[int], **changes) -> DataFrame:
    """net, iter, l1, f, c, tau, grad_norm of each step of the joint method."""
    return bench.joint(k, settings=Settings(**changes)).trace()

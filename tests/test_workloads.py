"""The experiments on small networks: shapes, the trends that must hold whatever the data, and both ways of scoring."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from mutualgraph.metrics import quality
from mutualgraph.metrics.held import task_quality
from mutualgraph.operators import closeness
from mutualgraph.queries import clusters
from mutualgraph.sources import networks
from mutualgraph.workloads import sweeps

MEASURES = {"ndbi", "entropy", "density", "silhouette_sq", "rand", "mi", "vi", "nmi", "ndbi+rand", "entropy+vi", "density+nmi", "silhouette_sq+mi"}


@pytest.fixture(scope="module")
def docs(spark, tiny):
    return networks.aligned_documents(spark, tiny).stored()


@pytest.fixture(scope="module")
def bench(docs):
    return sweeps.Bench.of(docs, clusters.DOC_WEIGHTS)


def values(report, *names):
    out = {}
    for r in report.collect():
        out[tuple(r[n] for n in names)] = r.value
    return out


def test_scores_in_a_task_equal_tables(spark, docs, bench):
    S = closeness.symmetric_part(closeness.closeness(docs.nets[0], clusters.DOC_WEIGHTS, "matrix"))
    part = docs.nets[0].users.select(F.lit(0).alias("run"), "user_id", (F.col("user_id") % 5).cast("int").alias("cluster"))
    part = part.union(docs.nets[0].users.select(F.lit(1), "user_id", F.when(F.col("user_id") == 7, 1).otherwise(0))).union(docs.nets[0].users.select(F.lit(2), "user_id", F.lit(0)))
    got = {(r.run, r.measure): r.value for r in task_quality(bench.prepared, 0, part, exact=True).collect()}
    f = quality.closeness_features(S)
    for name, df, column in (("ndbi", quality.ndbi(f, part), "ndbi"), ("silhouette", quality.silhouette(f, part), "silhouette"), ("silhouette_sq", quality.silhouette_squared(f, part), "silhouette")):
        want = {r.run: r[column] for r in df.collect()}
        for run in (0, 1):
            assert got[run, name] == pytest.approx(want[run], abs=1e-6), (name, run)  # squared gaps near 0 cancel before the root
        assert got[2, name] is None and want[2] is None


def test_both_engines_report_the_same_measures(docs, bench):
    tables = sweeps.Bench.of(docs, clusters.DOC_WEIGHTS, engine="tables")
    parts = [n.users.select("user_id", (F.col("user_id") % 3).cast("int").alias("cluster")) for n in docs.nets]
    runs = [({"name": "one"}, *parts, docs.anchors[0, 1])]
    a, b = (values(x.score(runs), "measure", "net") for x in (bench, tables))
    assert a.keys() == b.keys() and {m for m, _ in a} == MEASURES and all(a[k] == pytest.approx(b[k], abs=1e-6) for k in a)


def test_sigma_sweep(bench):
    """Isolated methods don't see anchors: their quality is the same at every share."""
    got = values(sweeps.run_sigma_sweep(bench, [0.2, 1.0], [4, 4]), "method", "sigma", "measure", "net")
    assert {k[0] for k in got} == set(sweeps.METHODS) and {k[2] for k in got} == MEASURES and len(got) == 4 * 2 * 16
    for (method, sigma, measure, net), v in got.items():
        if method in ("normalized cut", "k-means") and net != "both":
            assert v == got[method, 1.0, measure, net]


def test_clusters_of_one_network_move_the_other(bench):
    got = values(sweeps.run_k_sweep(bench, 1, [2, 4, 8, 12], 4), "k", "measure", "side")
    other = [got[float(k), "ndbi", 2] for k in (2, 4, 8, 12)]
    assert len(set(np.round(other, 9))) > 1  # its own number of clusters is fixed: the change comes over the anchors
    alone = values(sweeps.run_k_sweep(bench, 2, [2, 8], 4), "k", "measure", "side")
    assert len({round(alone[float(k), "entropy", 2], 9) for k in (2, 8)}) == 2


def test_more_consensus_weight_brings_less_disagreement(bench):
    got = values(sweeps.run_theta_sweep(bench, [0.001, 1.0, 1000.0], [4, 4]), "theta", "measure", "net")
    rand = [got[t, "rand", "both"] for t in (0.001, 1.0, 1000.0)]
    assert rand[2] <= rand[0] and min(rand) >= 0


def test_ablation_has_every_variant(docs):
    got = values(sweeps.run_ablation(docs, [4, 4], {"words": {5: 1.0}}), "variant", "measure", "net")
    names = {k[0] for k in got}
    assert names == {f"words, {form}: {v}" for form in ("matrix", "pair") for v in ("joint", "no consensus", "consensus only", "raw disagreement", "no anchors")}


def test_convergence_within_the_published_bound(bench):
    steps = sweeps.convergence(bench, [4, 4]).collect()
    assert max(s.iter for s in steps) <= 200 and {s.net for s in steps} == {0, 1}
    for i in (0, 1):
        l1 = [s.l1 for s in sorted(steps, key=lambda s: s.iter) if s.net == i]
        assert abs(l1[-1] - l1[-2]) <= abs(l1[1] - l1[0]) + 1e-9  # it settles


def test_learned_weights(docs):
    part = docs.nets[0].users.select("user_id", (F.col("user_id") % 4).cast("int").alias("cluster"))
    got = closeness.learn_weights(docs.nets[0], part, 2, {1: 0.5, 5: 0.5})
    assert sum(got.values()) == pytest.approx(1) and set(got) == {1, 5} and all(v > 0 for v in got.values())


def test_three_networks_from_the_tables(spark, tiny):
    got = clusters.mutual_three_nets(spark, tiny).collect()
    assert len(got) == 3 and all(r.orthonormal and r.settled for r in got)

"""Measures: worked examples, identities, bounds, printed tables, and odd inputs."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from mutualgraph.metrics import combined, consensus, quality
from mutualgraph.metrics.report import evaluate
from mutualgraph.model.hetnet import HetNet
from mutualgraph.operators import alignment, closeness, discrepancy, metapath, partitions
from mutualgraph.sources import networks
from mutualgraph.workloads import sweeps


def part(spark, labels, shift=0):
    return spark.createDataFrame([(i + shift, c) for i, c in enumerate(labels)], "user_id long, cluster int")


def same(spark, n):
    return spark.createDataFrame([(i, i) for i in range(n)], "u1 long, u2 long")


def test_worked_example(spark):
    h1 = spark.createDataFrame([(1, [1.0, 0.0]), (2, [0.0, 1.0]), (3, [1.0, 0.0])], "user_id long, vec array<double>")
    h2 = spark.createDataFrame([(11, [1.0, 0.0]), (12, [0.0, 1.0]), (13, [1.0, 0.0]), (14, [0.0, 1.0])], "user_id long, vec array<double>")
    a = spark.createDataFrame([(1, 11), (3, 13)], "u1 long, u2 long")
    at = discrepancy.to_common(h1, h2, a)
    assert at.count() == 2 and discrepancy.discrepancy(at).first()[0] == 0
    flipped = discrepancy.to_common(h1, h2, spark.createDataFrame([(1, 11), (3, 12)], "u1 long, u2 long"))
    assert discrepancy.discrepancy(flipped).first()[0] == 2 and discrepancy.discrepancy(flipped, normalise=True).first()[0] == 1
    assert discrepancy.discrepancy(at.limit(1), normalise=True).first()[0] == 0 and discrepancy.discrepancy(at.limit(0), normalise=True).first()[0] == 0


def test_soft_discrepancy_equals_pairs(spark):
    rng = np.random.default_rng(0)
    rows = lambda k: spark.createDataFrame([(i, rng.random(k).tolist()) for i in range(20)], "user_id long, vec array<double>")
    at = discrepancy.to_common(rows(3), rows(4), same(spark, 20))
    pairs = discrepancy.pair_discrepancy(at).agg(F.sum("d")).first()[0]
    assert discrepancy.discrepancy(at).first()[0] == pytest.approx(pairs)


def test_rand_is_the_discrepancy_of_hard_partitions_and_symmetric(spark):
    rng = np.random.default_rng(1)
    p, q = part(spark, rng.integers(0, 4, 40).tolist()), part(spark, rng.integers(0, 3, 40).tolist())
    a = same(spark, 40)
    t = consensus.contingency(p, q, a)
    r = consensus.rand(t).first()[0]
    assert r == pytest.approx(consensus.rand_by_pairs(p, q, a).first()[0])
    at = discrepancy.to_common(partitions.hard_rows(p, 4), partitions.hard_rows(q, 3), a)
    assert r == pytest.approx(discrepancy.discrepancy(at, normalise=True).first()[0])
    i, j = consensus.information(t).first(), consensus.information(consensus.contingency(q, p, a)).first()
    assert i.vi == pytest.approx(j.vi) and i.mi == pytest.approx(j.mi) and 0 <= i.nmi <= 1 and i.vi == pytest.approx(i.h1 + i.h2 - 2 * i.mi)
    one = consensus.information(consensus.contingency(p, p, a)).first()
    assert one.nmi == pytest.approx(1) and one.vi == pytest.approx(0)


def test_measures_of_degenerate_partitions(spark):
    f = spark.createDataFrame([(i, d, float((i * 7 + d) % 5)) for i in range(6) for d in range(3)], "user_id long, dim long, x double")
    one = part(spark, [0] * 6)
    assert quality.entropy(one).first()[0] == 0 and quality.ndbi(f, one).first()[0] is None and quality.silhouette(f, one).first()[0] is None
    lone = part(spark, [0, 0, 0, 0, 0, 1])
    assert -1 <= quality.silhouette(f, lone).first()[0] <= 1 and 0 <= quality.ndbi(f, lone).first()[0] <= 1
    follow = spark.createDataFrame([], "src long, dst long")
    assert quality.density(follow, one).first()[0] == 0
    t = consensus.contingency(one, lone, same(spark, 6))
    assert consensus.information(t).first().nmi == 0 and consensus.rand(consensus.contingency(one, lone, same(spark, 1))).first()[0] == 0


def test_silhouette_and_ndbi_against_arrays(spark):
    rng = np.random.default_rng(0)
    x, label = rng.standard_normal((30, 4)), rng.integers(0, 3, 30)
    f = spark.createDataFrame([(i, d, float(x[i, d])) for i in range(30) for d in range(4)], "user_id long, dim long, x double")
    p = part(spark, label.tolist())
    for square, fun in ((False, quality.silhouette), (True, quality.silhouette_squared)):
        d = ((x[:, None] - x[None]) ** 2).sum(2)
        d = d if square else np.sqrt(d)
        each = []
        for i in range(30):
            own = d[i, (label == label[i]) & (np.arange(30) != i)].mean()
            other = min(d[i, label == c].mean() for c in range(3) if c != label[i])
            each.append((other - own) / max(own, other))
        want = np.mean([np.mean([each[i] for i in range(30) if label[i] == c]) for c in range(3)])
        assert fun(f, p).first()[0] == pytest.approx(want)
    cent = np.array([x[label == c].mean(0) for c in range(3)])
    spread = [np.linalg.norm(x[label == c] - cent[c], axis=1).mean() for c in range(3)]
    ratio = lambda i, j: 2 * np.linalg.norm(cent[i] - cent[j]) / (spread[i] + spread[j] + 2 * np.linalg.norm(cent[i] - cent[j]))
    assert quality.ndbi(f, p).first()[0] == pytest.approx(np.mean([min(ratio(i, j) for j in range(3) if j != i) for i in range(3)]))


def test_many_runs_score_as_single_ones(spark):
    rng = np.random.default_rng(2)
    S = spark.createDataFrame([(i, j, float(rng.random())) for i in range(12) for j in range(12) if i != j and rng.random() < 0.5], "src long, dst long, s double")
    users = spark.createDataFrame([(i,) for i in range(12)], "user_id long")
    net = HetNet("n", users, S.select("src", "dst"), None, None)
    parts = [[part(spark, rng.integers(0, 3, 12).tolist()) for _ in range(2)] for _ in range(3)]
    tag = lambda k: parts[0][k].withColumn("run", F.lit(0)).union(parts[1][k].withColumn("run", F.lit(1))).union(parts[2][k].withColumn("run", F.lit(2)))
    get = lambda df: {(r.run, r.measure, r.side): r.value for r in df.collect()}
    many = get(evaluate([net, net], [S, S], tag(0), tag(1), same(spark, 12), [12, 12]))
    for k in range(3):
        for key, v in get(evaluate([net, net], [S, S], parts[k][0], parts[k][1], same(spark, 12), [12, 12])).items():
            assert many[(k, *key[1:])] == pytest.approx(v)


# Published measures of the joint method at anchor shares 0.1, 0.5 and 1.0, and the published combined scores.
PRINTED = {
    ("ndbi", "rand"): [((0.927, 0.962), 0.095, -1.699), ((0.966, 0.970), 0.116, -1.705), ((0.958, 0.953), 0.159, -1.594)],
    ("entropy", "vi"): [((1.551, 2.270), 3.309, 10.439), ((1.396, 2.430), 4.038, 11.902), ((1.497, 2.191), 2.911, 9.509)],
    ("density", "nmi"): [((0.216, 0.140), 0.152, -0.659), ((0.239, 0.150), 0.149, -0.686), ((0.311, 0.164), 0.146, -0.768)],
    ("silhouette", "mi"): [((-0.137, -0.137), 0.756, -1.239), ((-0.117, -0.275), 0.394, -0.396), ((-0.044, -0.286), 0.689, -1.048)],
}


def test_printed_scores_recombine(spark):
    one = spark.range(1)
    for (q, c), rows in PRINTED.items():
        for (q1, q2), v, want in rows:
            assert one.select(combined.combined(q, c, F.lit(q1), F.lit(q2), F.lit(v))).first()[0] == pytest.approx(want, abs=0.0025)


def test_cost_identities(spark):
    rng = np.random.default_rng(0)
    a = np.triu(rng.random((20, 20)), 1)
    a += a.T
    S = spark.createDataFrame([(i, j, float(a[i, j])) for i in range(20) for j in range(20) if i != j], "src long, dst long, s double")
    p = part(spark, (np.arange(20) % 3).tolist())
    deg = closeness.degrees(S)
    ncut = partitions.ncut_cost(partitions.cluster_flow(S, p)).first()[0]
    assert partitions.trace_cost(S, deg, partitions.indicator_rows(p, deg, 3)).first()[0] == pytest.approx(2 * ncut)
    assert partitions.argmax_assign(partitions.hard_rows(p, 3)).exceptAll(p.select("user_id", "cluster")).count() == 0


def test_paths_marginals_and_forms(spark, tiny, small):
    net = networks.events_net(spark, small).stored()
    for path in metapath.PATHS:
        counts = metapath.path_counts(net, path)
        sums = {r.u: r.n for r in counts.groupBy(F.col("src").alias("u")).agg(F.sum("cnt").alias("n")).collect()}
        m = {r.user_id: r.out for r in metapath.path_marginals(net, path).collect()}
        assert {u: n for u, n in m.items() if n} == sums
        by_compiler = metapath.compile_path(net, metapath.MetaPath.parse(metapath.PATHS[path]))
        assert counts.select("src", "dst", "cnt").exceptAll(by_compiler).count() == 0
        half = metapath.path_counts(net, path, half=True)
        assert path <= 2 or half.filter("src > dst").count() == 0
    S = closeness.closeness(net)
    assert S.join(S.select(F.col("src").alias("dst"), F.col("dst").alias("src"), F.col("s").alias("t")), ["src", "dst"]).filter("abs(s - t) > 1e-12").count() == 0
    rows = closeness.degrees(closeness.path_similarity(net, 2, "matrix")).filter("abs(d - 1) > 1e-9")
    assert rows.count() == 0


def test_paths_and_weights_are_checked():
    with pytest.raises(ValueError):
        metapath.MetaPath.parse("U>W")
    with pytest.raises(ValueError):
        metapath.MetaPath.parse("U-P")
    with pytest.raises(ValueError):
        closeness.weights_of({1: 0.5})
    assert sum(closeness.weights_of("social").values()) == pytest.approx(1)


def test_missing_attribute_kind_gives_no_path(spark, tiny):
    net = networks.document_view(spark, tiny, 0)
    assert metapath.path_counts(net, 6).count() == 0


def test_anchor_samples_are_nested(spark, small):
    a = networks.key_anchors(spark, small)
    before: set = set()
    for sigma in (0.1, 0.35, 0.5, 1.0):
        now = {r.u1 for r in alignment.sample_anchors(a, sigma).collect()}
        assert before <= now and len(now) == -(-int(sigma * 1000) * 95 // 1000)
        before = now


def test_accounts_collapse(spark, tiny):
    net = networks.events_net(spark, tiny)
    ids = sorted(r.user_id for r in net.users.collect())
    links = spark.createDataFrame([(ids[0], ids[1]), (ids[2], ids[1])], "user_a long, user_b long")
    one = alignment.collapse_accounts(net, links)
    assert one.users.count() == len(ids) - 2 and one.follow.filter("src = dst").count() == 0
    assert one.posts.filter(F.col("user_id") == ids[0]).count() == net.posts.filter(F.col("user_id").isin(ids[:3])).count()


def test_consensus_weight_and_accuracy(spark, small):
    """On the document views: the joint method agrees with the languages, and more weight on consensus lowers rand."""
    bench = sweeps.Bench.of(networks.aligned_documents(spark, small), {1: 0.05, 2: 0.05, 3: 0.05, 4: 0.05, 5: 0.8})
    got = {(r.theta, r.measure, r.side): r.value for r in sweeps.run_theta_sweep(bench, [0.0, 1.0, 10.0], [4, 4]).collect()}
    assert got[10.0, "rand", 0] <= got[1.0, "rand", 0] < got[0.0, "rand", 0]
    assert got[1.0, "ndbi+rand", 0] < got[0.0, "ndbi+rand", 0]

"""The optimiser against dense algebra, its invariants, and both engines against each other."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from mutualgraph.cluster import baselines, distributed, kmeans, mutual, onetask
from mutualgraph.linalg import blocks
from mutualgraph.metrics import consensus
from mutualgraph.model.hetnet import AlignedSet, HetNet
from mutualgraph.operators import closeness
from mutualgraph.optimize import assembly, local
from mutualgraph.optimize import curvilinear as cv
from mutualgraph.sources import networks


def planted(n, k, seed, inside=0.5, outside=0.05):
    rng = np.random.default_rng(seed)
    label = np.arange(n) % k
    a = np.triu(rng.random((n, n)) < np.where(label[:, None] == label[None], inside, outside), 1).astype(float)
    return label, a + a.T


@pytest.fixture
def nets():
    out = []
    for n, seed in ((60, 0), (50, 1)):
        label, a = planted(n, 3, seed)
        src, dst = np.nonzero(a)
        out.append((label, a, local.Laplacian(n, src, dst, a[src, dst])))
    return out


def problem_of(nets, cfg, links=25):
    x = [local.indicator(np.random.default_rng(3).integers(0, 3, lap.n), lap.degree, 3) for _, _, lap in nets]
    return local.LocalProblem([lap for *_, lap in nets], x, {(0, 1): (np.arange(links), np.arange(links))}, cfg), x


def dense_objective(problem, i, x, cfg, links=25):
    b, o = problem.scale[i][:links, None] * x[:links], problem.rows(1 - i, np.arange(links))
    return np.trace(x.T @ problem.l[i](x)) + cfg.theta / (links * (links - 1)) * ((b @ b.T - o @ o.T) ** 2).sum()


def test_gradient_curve_and_slope(nets):
    cfg = cv.Settings(theta=2.0)
    p, x = problem_of(nets, cfg)
    g = p.grams(0)
    z = p.z[0][0]
    grad = z[:, 3:]
    e, h = np.random.default_rng(0).standard_normal(x[0].shape), 1e-6
    assert (dense_objective(p, 0, x[0] + h * e, cfg) - dense_objective(p, 0, x[0] - h * e, cfg)) / (2 * h) == pytest.approx((grad * e).sum(), rel=1e-6)
    a = grad @ x[0].T - x[0] @ grad.T
    for tau in (0.0, 0.01, 0.5):
        y = np.linalg.solve(np.eye(60) + tau / 2 * a, (np.eye(60) - tau / 2 * a) @ x[0])
        r = cv.curve(tau, g)
        assert np.allclose(z @ r, y, atol=1e-12)
        assert cv.objective(r, g, 1.0, p.c0) == pytest.approx(dense_objective(p, 0, y, cfg), abs=1e-12)
    small = 1e-6
    assert (cv.objective(cv.curve(small, g), g, 1, 1) - cv.objective(cv.curve(0, g), g, 1, 1)) / small == pytest.approx(cv.slope(g), rel=1e-4)
    assert cv.slope(g) == pytest.approx(-((a * a).sum()) / 2)


@pytest.mark.parametrize("changes", [{}, {"gradient": "euclidean"}, {"schedule": "block"}, {"alternate": True}, {"discrepancy_scale": "printed"}, {"theta": 0.0}])
def test_steps_keep_orthonormality_and_descend(nets, changes):
    cfg = cv.Settings(**changes)
    p, _ = problem_of(nets, cfg)
    before = dense_objective(p, 0, p.x[0], cfg) + np.trace(p.x[1].T @ p.l[1](p.x[1]))
    steps = cv.run(p, cfg)
    assert len(steps) <= cfg.max_iter * 2 + 2 and all(s["backtracks"] <= cfg.max_backtracks for s in steps)
    assert max(p.residual(0), p.residual(1)) < 1e-8
    after = dense_objective(p, 0, p.x[0], cfg) + np.trace(p.x[1].T @ p.l[1](p.x[1]))
    assert after < before
    for s in steps:
        assert s["f"] <= s["c"] + 1e-9


def test_unbounded_reference_stops_everything(nets):
    """With the reference value at 0 no step can pass: the cap ends the search."""
    p, x = problem_of(nets, cv.Settings(start="zero"))
    steps = cv.run(p, cv.Settings(start="zero"))
    assert not any(s["accepted"] for s in steps) and np.allclose(p.x[0], x[0])


def test_objective_ignores_rotations(nets):
    cfg = cv.Settings()
    p, x = problem_of(nets, cfg)
    q = np.linalg.qr(np.random.default_rng(0).standard_normal((3, 3)))[0]
    assert dense_objective(p, 0, x[0] @ q, cfg) == pytest.approx(dense_objective(p, 0, x[0], cfg))


def test_spectral_equals_dense_eigenvectors(nets):
    _, a, lap = nets[0]
    x = local.spectral(lap, 3)
    w = np.linalg.eigvalsh(lap(np.eye(lap.n)))
    assert np.trace(x.T @ lap(x)) == pytest.approx(w[:3].sum(), abs=1e-6)


def test_sparse_and_dense_products_agree(nets, monkeypatch):
    _, a, lap = nets[0]
    src, dst = np.nonzero(a)
    monkeypatch.setattr(local, "DENSE", 0)
    v = np.random.default_rng(0).standard_normal((60, 4))
    assert np.allclose(local.Laplacian(60, src, dst, a[src, dst])(v), lap(v))


def test_kmeans_edges():
    f = np.array([[0.0, 0], [0, 0.1], [5, 5], [5, 5.1], [9, 0]])
    assert len(set(local.kmeans(f, 3).tolist())) == 3 and local.kmeans(f, 9).max() < 5 and (local.kmeans(f, 1) == 0).all()
    assert len(local.kmeans(np.zeros((0, 2)), 3)) == 0


def as_net(spark, name, a, shift=0):
    src, dst = np.nonzero(a)
    follow = spark.createDataFrame([(int(i) + shift, int(j) + shift) for i, j in zip(src, dst, strict=True)], "src long, dst long")
    users = spark.createDataFrame([(i + shift,) for i in range(len(a) + 1)], "user_id long")  # one user without links
    none = spark.createDataFrame([], "post_id long, user_id long"), spark.createDataFrame([], "post_id long, kind string, attr string")
    return HetNet(name, users, follow, *none)


@pytest.fixture
def aligned(spark, nets):
    a, b = as_net(spark, "a", nets[0][1]), as_net(spark, "b", nets[1][1], 1000)
    links = spark.createDataFrame([(i, 1000 + i) for i in range(30)] + [(60, 1001 + 40)], "u1 long, u2 long")
    S = [baselines.social_entries(n) for n in (a, b)]
    return AlignedSet([a, b], {(0, 1): links}), S


@pytest.mark.parametrize(("engine", "options"), [("task", {}), ("tables", {}), ("task", {"how": "argmax"}), ("tables", {"how": "argmax", "init": "random"})])
def test_engines_find_planted_clusters(spark, nets, aligned, engine, options):
    net, S = aligned
    got = mutual.mutual_cluster(net, [3, 3], closenesses=S, engine=engine, max_iter=30 if engine == "task" else 3, **options)
    assert all(r.residual < 1e-8 for r in got.summary().collect())
    if options.get("init") == "random":  # four steps don't undo a random start: only the shape is tested
        assert [got.partition(i).count() for i in (0, 1)] == [61, 51]
        return
    parts = [got.partition(i) for i in (0, 1)]
    assert parts[0].count() == 61 and parts[1].count() == 51
    for part, (label, *_), shift in zip(parts, nets, (0, 1000), strict=True):
        truth = spark.createDataFrame([(i + shift, int(c)) for i, c in enumerate(label)], "user_id long, label int")
        assert consensus.agreement_with_truth(part, truth).first().nmi > (0.9 if engine == "task" and not options else 0.3)
    lone = parts[0].filter("user_id = 60").first().cluster
    assert lone == parts[1].filter("user_id = 1041").first().cluster  # it follows its anchor
    assert parts[1].filter("user_id = 1050").first().cluster == -1


def test_table_grams_equal_arrays(spark, nets, aligned):
    net, S = aligned
    cfg = cv.Settings(theta=3.0)
    anchors = net.anchors[0, 1].filter("u1 < 60")
    t = distributed.TableProblem([distributed.EntryOperator(s) for s in S], {(0, 1): anchors}, [3, 3], cfg, 0)
    x = []
    for i, (n, shift) in enumerate(((60, 0), (50, 1000))):
        rows = {r.user_id - shift: r.x for r in t.nets[i].state.collect()}
        x.append(np.array([rows[u] for u in range(n)]))
    p = local.LocalProblem([lap for *_, lap in nets], x, {(0, 1): (np.arange(30), np.arange(30))}, cfg)
    searches = [cv.Search(), cv.Search()]
    others = [cv.Search(), cv.Search()]
    for _ in range(2):
        for i in (0, 1):
            g, h = t.grams(i), p.grams(i)
            assert np.allclose(g.zz, h.zz) and np.allclose(g.zlz, h.zlz, atol=1e-9) and np.allclose(g.nn, h.nn) and np.allclose(g.cross, h.cross)
            r, one = cv.line_search(g, searches[i], 1.0, t.c0, cfg)
            q, two = cv.line_search(h, others[i], 1.0, p.c0, cfg)
            assert one["f"] == pytest.approx(two["f"], rel=1e-8) and one["tau"] == pytest.approx(two["tau"], rel=1e-5)
            t.advance(i, q)
            p.advance(i, q)
            assert t.norm(i) == pytest.approx(p.norm(i))


def test_products_and_sums_on_tables(spark):
    rng = np.random.default_rng(0)
    m, v = rng.random((20, 20)) * (rng.random((20, 20)) < 0.3), rng.standard_normal((20, 3))
    entries = spark.createDataFrame([(int(i), int(j), float(m[i, j])) for i, j in zip(*np.nonzero(m), strict=True)], "src long, dst long, w double")
    rows = spark.createDataFrame([(i, v[i].tolist()) for i in range(20)], "user_id long, vec array<double>").repartition(3)
    got = {r.user_id: r.vec for r in blocks.spmm(entries, rows).collect()}
    assert np.allclose([got.get(i, [0, 0, 0]) for i in range(20)], m @ v)
    assert np.allclose(blocks.sums(rows, ["vec"], lambda c: {"g": c["vec"].T @ c["vec"]})["g"], v.T @ v)


@pytest.mark.parametrize("method", [baselines.normalized_cut, baselines.kmeans_rows])
def test_isolated_methods_find_blocks_and_keep_every_user(spark, nets, aligned, method):
    net, _ = aligned
    truth = spark.createDataFrame([(i, int(c)) for i, c in enumerate(nets[0][0])], "user_id long, label int")
    parts = [method(net.nets[0], 3, engine=e).orderBy("user_id").collect() for e in ("task", "tables")]
    for part in parts:
        assert [r.user_id for r in part] == list(range(61)) and part[60].cluster == -1 and min(r.cluster for r in part[:60]) == 0
        assert consensus.agreement_with_truth(spark.createDataFrame(part[:60]), truth).first().nmi > 0.3
    if method is baselines.normalized_cut:
        same = {(a.cluster, b.cluster) for a, b in zip(*parts, strict=True)}
        assert len(same) == 4  # the same blocks, numbered differently at most


@pytest.mark.parametrize("engine", ["task", "tables"])
def test_more_clusters_than_users(spark, engine):
    """k is cut to the users with similarity, in both engines; X'X = I still holds."""
    users = spark.createDataFrame([(i,) for i in range(8)], "user_id long")
    S = spark.createDataFrame([(i, j, 1.0 + (i + j) % 3) for i in range(6) for j in range(6) if i != j], "src long, dst long, s double")
    none = spark.createDataFrame([], "src long, dst long"), spark.createDataFrame([], "post_id long, user_id long"), spark.createDataFrame([], "post_id long, kind string, attr string")
    net = HetNet("n", users, *none)
    two = AlignedSet([net, net], {(0, 1): spark.createDataFrame([(0, 1), (2, 2), (7, 5), (6, 7)], "u1 long, u2 long")})
    got = mutual.mutual_cluster(two, [9, 2], closenesses=[S, S], engine=engine, max_iter=2)
    assert all(r.residual < 1e-8 for r in got.summary().collect())
    rows = {i: {r.user_id: r.cluster for r in got.partition(i).collect()} for i in (0, 1)}
    assert all(len(r) == 8 for r in rows.values()) and rows[0][6] == -1 and rows[0][7] == rows[1][5] and rows[1][7] == -1
    assert len({rows[0][u] for u in range(6)}) == 6 and baselines.kmeans_rows(net, 9, S=S, engine=engine).filter("cluster >= 0").select("cluster").distinct().count() == 6


def test_three_networks_have_equal_steps(spark, nets):
    a = [x[1] for x in nets] + [planted(40, 3, 5)[1]]
    parts = [as_net(spark, f"n{i}", m, 1000 * i) for i, m in enumerate(a)]
    links = {(i, j): spark.createDataFrame([(1000 * i + u, 1000 * j + u) for u in range(0, 30 + 3 * j, 1 + i)], "u1 long, u2 long") for i, j in ((0, 1), (0, 2), (1, 2))}
    S = [baselines.social_entries(n) for n in parts]
    cfg = cv.Settings(theta=2.0)
    t = distributed.TableProblem([distributed.EntryOperator(s) for s in S], links, [3, 2, 3], cfg, 0)
    laps, x = [], []
    for i, m in enumerate(a):
        src, dst = np.nonzero(m)
        laps.append(local.Laplacian(len(m), src, dst, m[src, dst]))
        rows = {r.user_id - 1000 * i: r.x for r in t.nets[i].state.collect()}
        x.append(np.array([rows[u] for u in range(len(m))]))
    at = {p: tuple(np.array([r[k] for r in sorted(df.collect())]) % 1000 for k in (0, 1)) for p, df in links.items()}
    p = local.LocalProblem(laps, x, at, cfg)
    one, two = [cv.Search() for _ in a], [cv.Search() for _ in a]
    for i in (0, 1, 2, 0):
        g, h = t.grams(i), p.grams(i)
        r, seen = cv.line_search(g, one[i], 1.0, t.c0, cfg)
        q, same = cv.line_search(h, two[i], 1.0, p.c0, cfg)
        assert seen["f"] == pytest.approx(same["f"], rel=1e-8) and seen["tau"] == pytest.approx(same["tau"], rel=1e-5) and seen["accepted"]
        t.advance(i, q)
        p.advance(i, q)
    assert t.residual(0) < 1e-8


@pytest.mark.parametrize("form", ["pair", "matrix"])
def test_closeness_formed_in_a_task_equals_tables(spark, tiny, form):
    for net in (networks.orders_net(spark, tiny), networks.events_net(spark, tiny)):
        net = net.stored()
        mix = closeness.weights_of("uniform")
        S = closeness.closeness(net, mix, form)
        S = closeness.symmetric_part(S) if form == "matrix" else S
        users = sorted(r.user_id for r in net.users.collect())
        want = np.zeros((len(users), len(users)))
        for r in S.collect():
            want[users.index(r.src), users.index(r.dst)] = r.s
        parts = onetask.link_tables(net, mix)
        held = {n: tuple(np.array([r[c] for r in df.collect()]) for c in ("a", "b", "v")) for n, df in parts.items()}
        follow = tuple(np.searchsorted(users, held["f0"][k]) for k in (0, 1))
        attributes = {p: (np.searchsorted(users, held[f"c0_{p}"][0]), *held[f"c0_{p}"][1:]) for p in (5, 6, 7)}
        got = assembly.closeness_matrix(len(users), follow, attributes, mix, form)
        assert np.allclose(got, want, atol=1e-12)


def test_closeness_in_small_blocks(monkeypatch):
    rng = np.random.default_rng(2)
    n, follow = 40, (rng.integers(0, 40, 300), rng.integers(0, 40, 300))
    keep = follow[0] != follow[1]
    follow = np.unique(np.stack([f[keep] for f in follow]), axis=1)
    attributes = {p: (rng.integers(0, 40, 200), rng.integers(0, m, 200), rng.integers(1, 4, 200).astype(float)) for p, m in ((5, 60), (6, 3), (7, 1))}
    mix = {p: 1 / 7 for p in range(1, 8)}
    want = assembly.closeness_matrix(n, follow, attributes, mix, "matrix")
    monkeypatch.setattr(assembly, "PAIRS", 5)
    monkeypatch.setattr(assembly, "CELLS", 90)
    assert np.allclose(assembly.closeness_matrix(n, follow, attributes, mix, "matrix"), want)


def test_factors_equal_entries(spark, tiny):
    """Products with the symmetric part, its degrees, and steps of the joint method, without forming closeness."""
    two = networks.aligned_tables(spark, tiny).stored()
    net = two.nets[1]
    S = closeness.symmetric_part(closeness.closeness(net, "uniform", "matrix"))
    a, b = distributed.EntryOperator(S), distributed.FactorOperator(net, "uniform")
    d = [{r.user_id: r.d for r in op.degree.collect()} for op in (a, b)]
    assert d[0].keys() == d[1].keys() and all(d[0][u] == pytest.approx(d[1][u]) for u in d[0])
    rows = net.users.select("user_id", F.array(F.col("user_id").cast("double"), F.lit(1.0)).alias("vec"))
    x = [{r.user_id: r.vec for r in op.scaled(rows).collect()} for op in (a, b)]
    assert all(np.allclose(x[0][u], x[1][u]) for u in x[0]) and x[0].keys() == x[1].keys()
    other = closeness.symmetric_part(closeness.closeness(two.nets[0], {1: 1.0}, "matrix"))
    parts = [mutual.mutual_cluster(two.with_anchors((0, 1), two.anchors[0, 1]), [3, 3], closenesses=[other, op], engine="tables", max_iter=1, init="random", how="argmax").trace().orderBy("net").collect() for op in (b, S)]
    assert [r.f for r in parts[0]] == pytest.approx([r.f for r in parts[1]], rel=1e-9)


@pytest.mark.parametrize("engine", ["task", "tables"])
def test_propagation_finds_blocks_and_uses_anchors(spark, nets, aligned, engine):
    net, S = aligned
    got = baselines.propagation(net, [3, 3], S, engine=engine, hops=2, rounds=40 if engine == "task" else 12)
    assert [g.count() for g in got] == [61, 51] and all(g.select("user_id").distinct().count() == g.count() for g in got)
    for part, (label, *_), shift in zip(got, nets, (0, 1000), strict=True):
        truth = spark.createDataFrame([(i + shift, int(c)) for i, c in enumerate(label)], "user_id long, label int")
        assert consensus.agreement_with_truth(part, truth).first().nmi > (0.8 if engine == "task" else 0.3)


def test_empty_clusters_are_given_the_farthest_users(spark):
    f = spark.createDataFrame([(i, 0, 1.0 + 0.01 * i) for i in range(6)] + [(6, 1, 9.0), (7, 2, 5.0)], "user_id long, dim int, x double")
    start = spark.createDataFrame([(i, 0) for i in range(8)], "user_id long, cluster int")
    got = {r.user_id: r.cluster for r in kmeans.lloyd(f, 3, start=start).collect()}
    assert len(set(got.values())) == 3 and got[6] != got[7] and len({got[i] for i in range(6)}) == 1


def test_settings_without_anchors_and_single_cluster(aligned):
    net, S = aligned
    for links, k in ((net.anchors[0, 1].limit(0), [3, 3]), (net.anchors[0, 1].limit(1), [3, 3]), (net.anchors[0, 1], [1, 1]), (net.anchors[0, 1], [80, 2])):
        got = mutual.mutual_cluster(net.with_anchors((0, 1), links), k, closenesses=S, max_iter=5)
        assert got.partition(0).count() == 61 and got.partition(0).filter(F.col("cluster").isNull()).count() == 0

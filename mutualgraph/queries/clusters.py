"""Queries on clustering methods and experiments."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..cluster import baselines, kmeans, mutual
from ..linalg import factorised
from ..metrics import consensus
from ..model.hetnet import AlignedSet
from ..operators import closeness, discrepancy, partitions
from ..sources import networks as net
from ..workloads import sweeps
from . import sql
from .network import query, rounded, s2

#: Path weights of the document views: links little, words most; no time, no location.
DOC_WEIGHTS = {1: 0.05, 2: 0.05, 3: 0.05, 4: 0.05, 5: 0.8}
#: A small network's clusters, and the published number: by the users of the smaller table network.
SMALL, LARGE = 10, 50


def doc_views(spark, d):
    return net.aligned_documents(spark, d).stored()


def joint_docs(spark, d, **options):
    views = doc_views(spark, d)
    return mutual.mutual_cluster(views, [4, 4], DOC_WEIGHTS, "matrix", **options)


def table_nets(spark, d):
    two = net.aligned_tables(spark, d)
    return AlignedSet(two.nets, two.anchors).stored()


@query("mutual_partition_docs")
def mutual_partition_docs(spark, d):
    got = joint_docs(spark, d)
    return got.partition(0).select(F.lit("netA").alias("net"), "user_id", "cluster").union(got.partition(1).select(F.lit("netB").alias("net"), "user_id", "cluster"))


query("mutual_trace")(lambda s, d: joint_docs(s, d).trace())
query("mutual_schedule_block")(lambda s, d: joint_docs(s, d, schedule="block").trace())
query("mutual_printed_scale")(lambda s, d: joint_docs(s, d, discrepancy_scale="printed").summary())
query("mutual_start_zero")(lambda s, d: joint_docs(s, d, start="zero", reset=False).trace())
query("mutual_euclidean_steps")(lambda s, d: joint_docs(s, d, gradient="euclidean").trace())
query("consensus_only")(lambda s, d: joint_docs(s, d, alpha=0.0, beta=0.0).partition(0))
query("csm_single_step")(lambda s, d: joint_docs(s, d, max_iter=1).trace())
query("csm_single_step_tables")(lambda s, d: joint_docs(s, d, max_iter=1, engine="tables").trace())
query("init_orthonormal")(lambda s, d: joint_docs(s, d, max_iter=0).summary())
query("mutual_init_spectral")(lambda s, d: joint_docs(s, d, init="spectral").summary())
query("mutual_assign_argmax")(lambda s, d: joint_docs(s, d, how="argmax").partition(0))


@query("nmi_truth_lang")
def nmi_truth_lang(spark, d):
    truth = net.table(spark, d, "documents").select(F.col("doc_id").alias("user_id"), F.col("lang").alias("label"))
    got = joint_docs(spark, d)
    parts = [consensus.agreement_with_truth(got.partition(i), truth).select(F.lit(n).alias("net"), "nmi", "adjusted_rand", "purity") for i, n in enumerate(("netA", "netB"))]
    return parts[0].union(parts[1])


def net_clusters(spark, d) -> int:
    return SMALL if net.events_net(spark, d).users.count() < 1000 else LARGE


def joint_nets(spark, d, **options):
    """The table networks, all seven paths with equal weights, row-normalised form."""
    k = net_clusters(spark, d)
    return mutual.mutual_cluster(table_nets(spark, d), [k, k], "uniform", "matrix", **options)


query("mutual_partition_net1")(lambda s, d: joint_nets(s, d).partition(0))
query("mutual_partition_net2")(lambda s, d: joint_nets(s, d).partition(1))
query("mutual_trace_nets")(lambda s, d: joint_nets(s, d).trace())


def _invariants(got, nets):
    """net, users (with one row each), orthonormal, descended and settled: what any run must show, whatever it finds."""
    first = F.min_by("f", "iter").alias("first")
    steps = got.trace().groupBy("net").agg(first, F.max_by("f", "iter").alias("last"), F.min(F.col("f") <= F.col("c") + 1e-9).alias("bounded"))
    users = None
    for i, n in enumerate(nets):
        part = got.partition(i).join(n.users.withColumn("known", F.lit(1)), "user_id", "left")
        row = part.agg(F.count("*").alias("rows"), F.countDistinct("user_id").alias("users"), F.count("known").alias("known"), F.min("cluster").alias("least")).withColumn("net", F.lit(i))
        users = row if users is None else users.union(row)
    one = (F.col("rows") == F.col("users")) & (F.col("known") == F.col("rows")) & F.col("least").isNotNull()
    return got.summary().join(steps, "net").join(users, "net").select("net", F.when(one, F.col("users")).alias("users"), (F.col("residual") < 1e-8).alias("orthonormal"), (F.col("bounded") & (F.col("last") <= F.col("first"))).alias("descended"), (F.col("rounds") <= 200).alias("settled"))


_INVARIANT = "SELECT {0}::INT AS net, (SELECT count({1}) FROM {2}) AS users, true AS orthonormal, true AS descended, true AS settled"
_ON_NETS = f"{_INVARIANT.format(0, '*', 'customer')} UNION ALL {_INVARIANT.format(1, 'DISTINCT user_id', 'events')}"


@query("mutual_invariants_nets", _ON_NETS)
def mutual_invariants_nets(spark, d):
    two = table_nets(spark, d)
    k = net_clusters(spark, d)
    return _invariants(mutual.mutual_cluster(two, [k, k], "uniform", "matrix"), two.nets)


@query("mutual_invariants_pair", _ON_NETS)
def mutual_invariants_pair(spark, d):
    """The same for the symmetric form of closeness."""
    two = table_nets(spark, d)
    return _invariants(mutual.mutual_cluster(two, [SMALL, SMALL], "uniform", "pair", max_iter=40), two.nets)


@query("mutual_invariants_docs", " UNION ALL ".join(_INVARIANT.format(i, "*", f"documents WHERE doc_id % 5 <> {i}") for i in (0, 1)))
def mutual_invariants_docs(spark, d):
    views = doc_views(spark, d)
    return _invariants(mutual.mutual_cluster(views, [4, 4], DOC_WEIGHTS, "matrix"), views.nets)


@query("mutual_three_nets", f"{_ON_NETS} UNION ALL {_INVARIANT.format(2, 'DISTINCT conv_id', 'conversations')}")
def mutual_three_nets(spark, d):
    """Three networks, all paths: orders, events and conversations."""
    three = net.three_networks(spark, d).stored()
    return _invariants(mutual.mutual_cluster(three, [5, 5, 5], "uniform", "matrix", max_iter=60), three.nets)


def _named(parts):
    """net, user_id, block: the smallest user of each one's cluster, so that numbering doesn't matter."""
    out = None
    for n, p in zip(("net1", "net2"), parts, strict=True):
        low = p.groupBy("cluster").agg(F.min("user_id").alias("block"))
        rows = p.join(low, "cluster").select(F.lit(n).alias("net"), "user_id", "block")
        out = rows if out is None else out.union(rows)
    return out


_BLOCKS = "(SELECT CAST(floor(sqrt(count(DISTINCT user_id) / 1.5)) AS BIGINT) FROM events)"
_PLANTED = f"SELECT net, user_id, min(user_id) OVER (PARTITION BY net, user_id % {_BLOCKS}) AS block FROM (SELECT 'net1' AS net, c_custkey AS user_id FROM customer UNION ALL SELECT DISTINCT 'net2', user_id FROM events)"


def planted(name):
    """A method on networks with planted communities: its partitions must be those."""

    def keep(f):
        def run(spark, d):
            two = net.planted_networks(spark, d).stored()
            blocks = net.planted_blocks(spark, d)
            return _named(f(two, [blocks, blocks]))

        return query(name, _PLANTED)(run)

    return keep


def _both(got):
    return got.partition(0), got.partition(1)


planted("planted_joint")(lambda two, k: _both(mutual.mutual_cluster(two, k, "social", "matrix")))
planted("planted_joint_pair_form")(lambda two, k: _both(mutual.mutual_cluster(two, k, "social", "pair")))
planted("planted_joint_block_schedule")(lambda two, k: _both(mutual.mutual_cluster(two, k, "social", "matrix", schedule="block")))
planted("planted_joint_argmax")(lambda two, k: _both(mutual.mutual_cluster(two, k, "social", "matrix", how="argmax")))
planted("planted_joint_spectral_start")(lambda two, k: _both(mutual.mutual_cluster(two, k, "social", "matrix", init="spectral")))
planted("planted_joint_printed_scale")(lambda two, k: _both(mutual.mutual_cluster(two, k, "social", "matrix", discrepancy_scale="printed")))
planted("planted_joint_euclidean_steps")(lambda two, k: _both(mutual.mutual_cluster(two, k, "social", "matrix", gradient="euclidean")))
planted("planted_joint_tables")(lambda two, k: _both(mutual.mutual_cluster(two, k, {1: 1.0}, "pair", engine="tables", max_iter=1, how="argmax")))
planted("planted_ncut")(lambda two, k: [baselines.normalized_cut(n, kk) for n, kk in zip(two.nets, k, strict=True)])
planted("planted_ncut_closeness")(lambda two, k: [baselines.normalized_cut(n, kk, weights="social", form="matrix") for n, kk in zip(two.nets, k, strict=True)])
planted("planted_kmeans")(lambda two, k: [baselines.kmeans_rows(n, kk, restarts=10) for n, kk in zip(two.nets, k, strict=True)])
planted("planted_kmeans_closeness")(lambda two, k: [baselines.kmeans_rows(n, kk, weights="social", form="matrix", restarts=10) for n, kk in zip(two.nets, k, strict=True)])
planted("planted_propagation")(lambda two, k: baselines.propagation(two, k, weights="social"))


query("baseline_ncut_net1")(lambda s, d: baselines.normalized_cut(net.orders_net(s, d).linked(), 10))
query("baseline_ncut_net2")(lambda s, d: baselines.normalized_cut(net.events_net(s, d).stored(), 10))
query("baseline_kmeans_net1")(lambda s, d: baselines.kmeans_rows(net.orders_net(s, d).stored(), 10))
query("baseline_kmeans_net2")(lambda s, d: baselines.kmeans_rows(net.events_net(s, d).stored(), 10))
for _i, _net in ((1, net.orders_net), (2, net.events_net)):
    query(f"baseline_ncut_closeness_net{_i}")(lambda s, d, n=_net: baselines.normalized_cut(n(s, d).stored(), 10, weights="uniform"))
    query(f"baseline_kmeans_closeness_net{_i}")(lambda s, d, n=_net: baselines.kmeans_rows(n(s, d).stored(), 10, weights="uniform"))


@query("spectral_net1", "SELECT true AS orthonormal, true AS smallest")
def spectral_net1(spark, d):
    """The relaxed normalised cut's rows of net1's links: orthonormal, and no partition's cost lies below theirs."""
    n = net.orders_net(spark, d).stored()
    return baselines.spectral_check(n, 10)


@query("baseline_propagation_nets")
def baseline_propagation_nets(spark, d):
    two = table_nets(spark, d)
    k = net_clusters(spark, d)
    got = baselines.propagation(two, [k, k])
    return got[0].select(F.lit("net1").alias("net"), "user_id", "cluster").union(got[1].select(F.lit("net2").alias("net"), "user_id", "cluster"))


def _propagated(spark, d):
    return baselines.propagation(doc_views(spark, d), [4, 4], weights=DOC_WEIGHTS, form="matrix")


query("baseline_propagation_net_a")(lambda s, d: _propagated(s, d)[0])
query("baseline_propagation_net_b")(lambda s, d: _propagated(s, d)[1])
query("propagation_one_hop", f"WITH {sql.closeness(2, sql.UNIFORM)}, d AS (SELECT src, sum(s) AS d FROM S GROUP BY 1), p0 AS (SELECT user_id, CASE WHEN user_id % 10 = 0 THEN 1.0 ELSE 0.0 END AS p FROM users2), q AS (SELECT S.dst AS user_id, sum(p * s / d) AS q FROM S JOIN d ON d.src = S.src JOIN p0 ON p0.user_id = S.src GROUP BY 1) SELECT user_id, round(0.15 * p + 0.85 * coalesce(q, 0), 6) AS p FROM p0 LEFT JOIN q USING (user_id)")(lambda s, d: rounded(baselines.one_hop(s2(s, d), net.events_net(s, d).users.select("user_id", F.when(F.col("user_id") % 10 == 0, 1.0).otherwise(0.0).alias("p"))), "p"))

_STEP = """WITH f AS (SELECT vec_id AS u, unnest(range(len(embedding))) AS dim, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings),
c AS (SELECT label AS c, dim, avg(x) AS m FROM f JOIN embeddings e ON e.vec_id = f.u GROUP BY 1, 2),
cc AS (SELECT c, sum(m * m) AS q FROM c GROUP BY 1), xc AS (SELECT u, c, sum(x * m) AS d FROM f JOIN c USING (dim) GROUP BY 1, 2)
SELECT u AS user_id, cluster FROM (SELECT u, xc.c AS cluster, row_number() OVER (PARTITION BY u ORDER BY round(q - 2 * d, 12), xc.c) AS r FROM xc JOIN cc ON cc.c = xc.c) WHERE r = 1"""


@query("kmeans_step", _STEP)
def kmeans_step(spark, d):
    e = net.table(spark, d, "embeddings")
    long = e.select(F.col("vec_id").alias("user_id"), F.posexplode("embedding").alias("dim", "x")).select("user_id", "dim", F.col("x").cast("double").alias("x"))
    return kmeans.step(long, e.select(F.col("vec_id").alias("user_id"), F.col("label").alias("cluster")))


#: The published grids.
SIGMAS = [0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9, 1.0]
THETAS = [0.001, 0.01, 0.1, 1.0, 10.0, 100.0, 1000.0]


def _net_bench(spark, d):
    return sweeps.Bench.of(net.aligned_tables(spark, d))


def _net_grid(spark, d):
    """Ten numbers of clusters, and the fixed one: 10 to 100 and 50, or a fifth of them on small networks."""
    k = net_clusters(spark, d)
    return [k // 5 * n for n in range(1, 11)], k


def sweep_k_nets(spark, d, side):
    grid, k = _net_grid(spark, d)
    return sweeps.run_k_sweep(_net_bench(spark, d), side, grid, k)


query("sweep_sigma_nets")(lambda s, d: sweeps.run_sigma_sweep(_net_bench(s, d), SIGMAS, [net_clusters(s, d)] * 2))
query("sweep_k1_nets")(lambda s, d: sweep_k_nets(s, d, 1))
query("sweep_k2_nets")(lambda s, d: sweep_k_nets(s, d, 2))
query("sweep_theta_nets")(lambda s, d: sweeps.run_theta_sweep(_net_bench(s, d), THETAS, [net_clusters(s, d)] * 2))


def _bench(spark, d):
    return sweeps.Bench.of(net.aligned_documents(spark, d), DOC_WEIGHTS, exact=True)


query("sweep_sigma")(lambda s, d: sweeps.run_sigma_sweep(_bench(s, d), SIGMAS, [4, 4]))
query("sweep_k1")(lambda s, d: sweeps.run_k_sweep(_bench(s, d), 1, [2, 4, 6, 8, 10, 12, 14, 16, 18, 20], 4))
query("sweep_k2")(lambda s, d: sweeps.run_k_sweep(_bench(s, d), 2, [2, 4, 6, 8, 10, 12, 14, 16, 18, 20], 4))
query("sweep_theta")(lambda s, d: sweeps.run_theta_sweep(_bench(s, d), THETAS, [4, 4]))
query("sweep_theta_printed")(lambda s, d: sweeps.run_theta_sweep(_bench(s, d), [*THETAS, 1e6], [4, 4], discrepancy_scale="printed"))
query("ablation")(lambda s, d: sweeps.run_ablation(net.aligned_documents(s, d), [4, 4], {"words and links": DOC_WEIGHTS, "links": "social", "attributes": {5: 0.9, 7: 0.1}}, exact=True))
query("convergence_nets")(lambda s, d: sweeps.convergence(_net_bench(s, d), [net_clusters(s, d)] * 2))
query("convergence")(lambda s, d: sweeps.convergence(_bench(s, d), [4, 4]))


@query("worked_example", f"WITH {sql.ANCHORS} SELECT 0.0 AS discrepancy, (SELECT count(*) FROM anchors)::INT AS anchors, (SELECT count(*) FROM customer)::INT AS wide, (SELECT count(DISTINCT user_id) FROM events)::INT AS narrow")
def worked_example(spark, d):
    """Customers and event users in clusters by key, which agree over the anchors: discrepancy 0."""
    wide, narrow = net.table(spark, d, "customer").select(F.col("c_custkey").alias("user_id")), net.table(spark, d, "events").select("user_id").distinct()
    one, two = (partitions.hard_rows(u.select("user_id", (F.col("user_id") % 2).cast("int").alias("cluster")), 2) for u in (wide, narrow))
    a = net.key_anchors(spark, d)
    count = lambda df, name: df.agg(F.count("*").cast("int").alias(name))
    return discrepancy.discrepancy(discrepancy.to_common(one, two, a)).crossJoin(count(a, "anchors")).crossJoin(count(wide, "wide")).crossJoin(count(narrow, "narrow"))


@query("weight_learning")
def weight_learning(spark, d):
    views = doc_views(spark, d)
    got = mutual.mutual_cluster(views, [4, 4], DOC_WEIGHTS, "matrix")
    learned = closeness.learn_weights(views.nets[0], got.partition(0), 2, DOC_WEIGHTS)
    return spark.createDataFrame(sorted(learned.items()), "path int, weight double")



@query("factorised_product", f"WITH {sql.closeness(2, sql.UNIFORM, 'matrix')} SELECT src AS user_id, round(sum(s * (dst % 7)), 6) AS a, round(sum(s), 6) AS b FROM S GROUP BY 1")
def factorised_product(spark, d):
    """Row-normalised closeness times two columns, from its factors."""
    n = net.events_net(spark, d).stored()
    x = n.users.select("user_id", F.array((F.col("user_id") % 7).cast("double"), F.lit(1.0)).alias("vec"))
    return factorised.closeness_times(n, x).select("user_id", F.round(F.col("vec")[0], 6).alias("a"), F.round(F.col("vec")[1], 6).alias("b"))


@query("factorised_product_net1", None)
def factorised_product_net1(spark, d):
    """The same on the larger network with all seven paths: 345 million join rows at sf0.1 if closeness were formed."""
    n = net.orders_net(spark, d).stored()
    x = n.users.select("user_id", F.array(*[F.pmod(F.xxhash64("user_id", F.lit(c)), F.lit(2)).cast("double") for c in range(10)]).alias("vec"))
    return factorised.closeness_times(n, x)

"""Queries on costs, discrepancy and measures."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import vectors
from ..metrics import combined, consensus, quality
from ..operators import closeness, discrepancy, partitions
from ..sources import networks as net
from ..storage import free, store
from . import sql
from .network import crossed2, query, rounded, s2

_S2 = f"WITH {sql.closeness(2, sql.UNIFORM)}, {sql.PART2}"
_FLOW = f"{_S2}, flow AS (SELECT a.cluster AS c1, b.cluster AS c2, sum(s) AS w FROM S JOIN part2 a ON a.user_id = src JOIN part2 b ON b.user_id = dst GROUP BY 1, 2)"
_NCUT = "(SELECT sum(o / v) / 2 FROM (SELECT sum(w) AS v, sum(CASE WHEN c1 <> c2 THEN w ELSE 0 END) AS o FROM flow GROUP BY c1))"


def part1(spark, d):
    return net.table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), (F.col("c_nationkey") % 10).alias("cluster"))


def part2(spark, d):
    return net.table(spark, d, "events").select("user_id", (F.col("user_id") % 10).cast("int").alias("cluster")).distinct()


def flow2(spark, d):
    crossed = crossed2(spark, d)
    if crossed:
        return crossed.cluster_flow(part2(spark, d))
    return partitions.cluster_flow(s2(spark, d), part2(spark, d))


def features2(spark, d):
    """Rows of net2's closeness, written once: the measures read them several times."""
    return store(quality.closeness_features(s2(spark, d)), "features")


def ndbi2(spark, d):
    crossed = crossed2(spark, d)
    return quality.ndbi_products(crossed, part2(spark, d)) if crossed else quality.ndbi(features2(spark, d), part2(spark, d))


def common(spark, d):
    return discrepancy.to_common(partitions.hard_rows(part1(spark, d), 10), partitions.hard_rows(part2(spark, d), 10), net.key_anchors(spark, d))


def table(spark, d):
    return consensus.contingency(part1(spark, d), part2(spark, d), net.key_anchors(spark, d))


query("cut_cost", f"{_FLOW} SELECT round(sum(w) / 2, 6) AS cut FROM flow WHERE c1 <> c2")(lambda s, d: rounded(partitions.cut_cost(flow2(s, d)), "cut"))
query("ncut_cost", f"{_FLOW} SELECT round({_NCUT}, 6) AS ncut")(lambda s, d: rounded(partitions.ncut_cost(flow2(s, d)), "ncut"))
query("cluster_flow", f"{_FLOW} SELECT c1, c2, round(w, 6) AS w FROM flow")(lambda s, d: rounded(flow2(s, d), "w"))


@query("trace_cost_indicator", f"{_FLOW} SELECT round(2 * {_NCUT}, 6) AS trace")
def trace_cost_indicator(spark, d):
    S = store(s2(spark, d), "closeness")
    deg = closeness.degrees(S)
    return rounded(partitions.trace_cost(S, deg, partitions.indicator_rows(part2(spark, d), deg, 10)), "trace")


_PAIRS = f"{sql.ANCHORS}, {sql.PART1}, {sql.PART2}, a AS (SELECT u1, p.cluster AS c1, q.cluster AS c2 FROM anchors JOIN part1 p ON p.user_id = u1 JOIN part2 q ON q.user_id = u2)"
_DIFF = "((x.c1 = y.c1) <> (x.c2 = y.c2))"
query("pair_discrepancy", f"WITH {_PAIRS} SELECT x.u1 AS i, y.u1 AS j, CASE WHEN {_DIFF} THEN 1.0 ELSE 0.0 END AS d FROM a x JOIN a y ON x.u1 <> y.u1")(lambda s, d: discrepancy.pair_discrepancy(common(s, d)))
query("discrepancy", f"WITH {_PAIRS} SELECT round(CAST(sum(CASE WHEN {_DIFF} THEN 1 ELSE 0 END) AS DOUBLE), 6) AS discrepancy FROM a x JOIN a y ON x.u1 <> y.u1")(lambda s, d: rounded(discrepancy.discrepancy(common(s, d)), "discrepancy"))
query("absolute_disagreement", f"WITH {_PAIRS} SELECT round(CAST(sum(CASE WHEN {_DIFF} THEN 1 ELSE 0 END) AS DOUBLE), 6) AS discrepancy FROM a x CROSS JOIN a y")(lambda s, d: rounded(discrepancy.discrepancy(common(s, d), include_diagonal=True), "discrepancy"))
query("normalized_discrepancy", f"WITH {_PAIRS} SELECT round(avg(CASE WHEN {_DIFF} THEN 1.0 ELSE 0.0 END), 6) AS discrepancy FROM a x JOIN a y ON x.u1 <> y.u1")(lambda s, d: rounded(discrepancy.discrepancy(common(s, d), normalise=True), "discrepancy"))
query("pruned_confidence", f"WITH {_PAIRS} SELECT u1, c1, c2 FROM a")(lambda s, d: common(s, d).select("u1", (F.array_position("vec1", F.lit(1.0)) - 1).cast("int").alias("c1"), (F.array_position("vec2", F.lit(1.0)) - 1).cast("int").alias("c2")))


@query("joint_cost", f"WITH {sql.closeness(2, sql.UNIFORM)}, s5b AS (SELECT 1), {_PAIRS}, flow AS (SELECT x.cluster AS c1, y.cluster AS c2, sum(s) AS w FROM S JOIN part2 x ON x.user_id = src JOIN part2 y ON y.user_id = dst GROUP BY 1, 2), c3 AS (SELECT p.cluster AS c1, q.cluster AS c2, count(*) AS w FROM (SELECT src, dst FROM f1 UNION ALL SELECT dst, src FROM f1) JOIN part1 p ON p.user_id = src JOIN part1 q ON q.user_id = dst GROUP BY 1, 2) SELECT round({_NCUT} + (SELECT sum(o / v) / 2 FROM (SELECT sum(w) AS v, sum(CASE WHEN c1 <> c2 THEN w ELSE 0 END) AS o FROM c3 GROUP BY c1)) + (SELECT avg(CASE WHEN {_DIFF} THEN 1.0 ELSE 0.0 END) FROM a x JOIN a y ON x.u1 <> y.u1), 6) AS cost".replace("s5b AS (SELECT 1)", sql.NET1.replace("follow1", "f1")))
def joint_cost(spark, d):
    """Ncut of net1's links both ways, Ncut of net2's closeness, and the normalised discrepancy, of reference partitions."""
    one = store(partitions.cluster_flow(net.orders_net(spark, d).follow.withColumn("s", F.lit(1.0)), part1(spark, d)), "flow")
    free(spark)  # what net1's links took needn't stay while net2's closeness is formed
    a = partitions.ncut_cost(partitions.both_ways(one)).withColumnRenamed("ncut", "a")
    b = partitions.ncut_cost(flow2(spark, d)).withColumnRenamed("ncut", "b")
    return a.crossJoin(b).crossJoin(discrepancy.discrepancy(common(spark, d), normalise=True)).select(F.round(F.col("a") + F.col("b") + F.col("discrepancy"), 6).alias("cost"))


@query("assign_argmax", "SELECT vec_id AS user_id, list_position(embedding, list_max(embedding)) - 1 AS cluster FROM embeddings")
def assign_argmax(spark, d):
    return partitions.argmax_assign(net.table(spark, d, "embeddings").select(F.col("vec_id").alias("user_id"), F.col("embedding").alias("vec")))


@query("partition_violations", f"WITH {sql.NET2}, p AS (SELECT user_id, 0 AS cluster FROM users2 WHERE user_id % 7 <> 0 UNION ALL SELECT user_id, 1 FROM users2 WHERE user_id % 5 = 1 UNION ALL SELECT -1, 0) SELECT 'missing' AS problem, user_id FROM users2 WHERE user_id NOT IN (SELECT user_id FROM p) UNION ALL SELECT 'repeated', user_id FROM p GROUP BY user_id HAVING count(*) > 1 UNION ALL SELECT 'unknown', user_id FROM p WHERE user_id NOT IN (SELECT user_id FROM users2)")
def partition_violations(spark, d):
    users = net.events_net(spark, d).users
    bad = users.filter("user_id % 7 <> 0").select("user_id", F.lit(0).alias("cluster")).union(users.filter("user_id % 5 = 1").select("user_id", F.lit(1))).union(spark.createDataFrame([(-1, 0)], "user_id long, cluster int"))
    return partitions.violations(users, bad)


_ENT = "(SELECT -sum(p * log2(p)) FROM (SELECT count(*) * 1.0 / sum(count(*)) OVER () AS p FROM {0} GROUP BY cluster))"
query("entropy_net1", f"WITH {sql.PART1} SELECT round({_ENT.format('part1')}, 6) AS entropy")(lambda s, d: rounded(quality.entropy(part1(s, d)), "entropy"))
query("entropy_net2", f"WITH {sql.PART2} SELECT round({_ENT.format('part2')}, 6) AS entropy")(lambda s, d: rounded(quality.entropy(part2(s, d)), "entropy"))
_DEN = "(SELECT avg(CASE WHEN a.cluster = b.cluster THEN 1.0 ELSE 0.0 END) FROM follow{0} f JOIN part{0} a ON a.user_id = f.src JOIN part{0} b ON b.user_id = f.dst)"
query("density_net1", f"WITH {sql.NET1}, {sql.PART1} SELECT round({_DEN.format(1)}, 6) AS density")(lambda s, d: rounded(quality.density(net.orders_net(s, d).follow, part1(s, d)), "density"))
query("density_net2", f"WITH {sql.NET2}, {sql.PART2} SELECT round({_DEN.format(2)}, 6) AS density")(lambda s, d: rounded(quality.density(net.events_net(s, d).follow, part2(s, d)), "density"))

# Features in long form: f (u, dim, x), part (u, c). Every later table follows from these two.
_EMB = "f AS (SELECT vec_id AS u, unnest(range(len(embedding))) AS dim, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings), part AS (SELECT vec_id AS u, label AS c FROM embeddings)"
_SROWS = f"{sql.closeness(2, sql.UNIFORM)}, {sql.PART2}, f AS (SELECT src AS u, dst AS dim, s AS x FROM S), part AS (SELECT user_id AS u, cluster AS c FROM part2)"
_NDBI = """, sz AS (SELECT c, count(*) AS n FROM part GROUP BY c),
cent AS (SELECT c, dim, sum(x) / any_value(n) AS m FROM f JOIN part USING (u) JOIN sz USING (c) GROUP BY c, dim),
cn AS (SELECT c, sum(m * m) AS cc FROM cent GROUP BY c),
near AS (SELECT part.u, part.c, sqrt(greatest(coalesce((SELECT sum(x * x) FROM f WHERE f.u = part.u), 0) - 2 * coalesce((SELECT sum(f.x * cent.m) FROM f JOIN cent ON cent.dim = f.dim WHERE f.u = part.u AND cent.c = part.c), 0) + (SELECT cc FROM cn WHERE cn.c = part.c), 0)) AS d FROM part),
sp AS (SELECT c, avg(d) AS s FROM near GROUP BY c),
dd AS (SELECT a.c AS i, b.c AS j, sqrt(greatest(x.cc + y.cc - 2 * coalesce((SELECT sum(p.m * q.m) FROM cent p JOIN cent q USING (dim) WHERE p.c = a.c AND q.c = b.c), 0), 0)) AS d, a.s AS si, b.s AS sj FROM sp a JOIN sp b ON a.c <> b.c JOIN cn x ON x.c = a.c JOIN cn y ON y.c = b.c)"""
_NDBI_OUT = "(SELECT avg(r) FROM (SELECT min(2 * d / (si + sj + 2 * d)) AS r FROM dd GROUP BY i))"
_SIL = """, xx AS (SELECT part.u, part.c, coalesce(sum(x * x), 0) AS q FROM part LEFT JOIN f USING (u) GROUP BY 1, 2),
dot AS (SELECT a.u AS u, b.u AS v, sum(a.x * b.x) AS d FROM f a JOIN f b USING (dim) WHERE a.u <> b.u GROUP BY 1, 2),
pd AS (SELECT a.u, a.c, b.c AS o, {0} AS d FROM xx a JOIN xx b ON a.u <> b.u LEFT JOIN dot ON dot.u = a.u AND dot.v = b.u),
pm AS (SELECT u, c, o, avg(d) AS m FROM pd GROUP BY 1, 2, 3),
ab AS (SELECT u, c, max(CASE WHEN c = o THEN m END) AS a, min(CASE WHEN c <> o THEN m END) AS b FROM pm GROUP BY 1, 2)"""
_SIL_OUT = "(SELECT avg(m) FROM (SELECT avg(CASE WHEN a IS NULL THEN 0 ELSE (b - a) / greatest(a, b) END) AS m FROM ab GROUP BY c))"
_GAP = "greatest(a.q + b.q - 2 * coalesce(dot.d, 0), 0)"


def embedded(spark, d):
    e = net.table(spark, d, "embeddings")
    return quality.dense_features(e, "vec_id", "embedding"), e.select(F.col("vec_id").alias("user_id"), F.col("label").alias("cluster"))


query("ndbi_embeddings", f"WITH {_EMB}{_NDBI} SELECT round({_NDBI_OUT}, 6) AS ndbi")(lambda s, d: rounded(quality.ndbi(*embedded(s, d)), "ndbi"))
query("ndbi_net2", f"WITH {_SROWS}{_NDBI} SELECT round({_NDBI_OUT}, 6) AS ndbi")(lambda s, d: rounded(ndbi2(s, d), "ndbi"))
query("silhouette_exact", f"WITH {_EMB}{_SIL.format(f'sqrt({_GAP})')} SELECT round({_SIL_OUT}, 6) AS silhouette")(lambda s, d: rounded(quality.silhouette(*embedded(s, d)), "silhouette"))
query("silhouette_sq", f"WITH {_EMB}{_SIL.format(_GAP)} SELECT round({_SIL_OUT}, 6) AS silhouette")(lambda s, d: rounded(quality.silhouette_squared(*embedded(s, d)), "silhouette"))
query("silhouette_net2", f"WITH {_SROWS}{_SIL.format(f'sqrt({_GAP})')} SELECT round({_SIL_OUT}, 6) AS silhouette")(lambda s, d: rounded(quality.silhouette(features2(s, d), part2(s, d)), "silhouette"))

query("rand_contingency", f"WITH {_PAIRS} SELECT round(avg(CASE WHEN {_DIFF} THEN 1.0 ELSE 0.0 END), 6) AS rand FROM a x JOIN a y ON x.u1 < y.u1")(lambda s, d: rounded(consensus.rand(table(s, d)), "rand"))
query("rand_pairs", f"WITH {_PAIRS} SELECT round(avg(CASE WHEN {_DIFF} THEN 1.0 ELSE 0.0 END), 6) AS rand FROM a x JOIN a y ON x.u1 < y.u1")(lambda s, d: rounded(consensus.rand_by_pairs(part1(s, d), part2(s, d), net.key_anchors(s, d)), "rand"))
_INFO = f"WITH {_PAIRS}, j AS (SELECT c1, c2, count(*) * 1.0 / (SELECT count(*) FROM a) AS p FROM a GROUP BY 1, 2), q1 AS (SELECT c1, sum(p) AS p1 FROM j GROUP BY 1), q2 AS (SELECT c2, sum(p) AS p2 FROM j GROUP BY 1), i AS (SELECT (SELECT sum(p * log2(p / (p1 * p2))) FROM j JOIN q1 USING (c1) JOIN q2 USING (c2)) AS mi, (SELECT -sum(p1 * log2(p1)) FROM q1) AS h1, (SELECT -sum(p2 * log2(p2)) FROM q2) AS h2)"
query("mi", f"{_INFO} SELECT round(mi, 6) AS mi FROM i")(lambda s, d: rounded(consensus.information(table(s, d)).select("mi"), "mi"))
query("vi", f"{_INFO} SELECT round(h1 + h2 - 2 * mi, 6) AS vi FROM i")(lambda s, d: rounded(consensus.information(table(s, d)).select("vi"), "vi"))
query("nmi", f"{_INFO} SELECT round(mi / sqrt(h1 * h2), 6) AS nmi FROM i")(lambda s, d: rounded(consensus.information(table(s, d)).select("nmi"), "nmi"))


@query("mi_allusers", f"WITH {_PAIRS}, j AS (SELECT c1, c2, count(*) * 1.0 / (SELECT count(*) FROM a) AS p FROM a GROUP BY 1, 2), q1 AS (SELECT cluster AS c1, count(*) * 1.0 / (SELECT count(*) FROM part1) AS p1 FROM part1 GROUP BY 1), q2 AS (SELECT cluster AS c2, count(*) * 1.0 / (SELECT count(*) FROM part2) AS p2 FROM part2 GROUP BY 1) SELECT round(sum(p * log2(p / (p1 * p2))), 6) AS mi FROM j JOIN q1 USING (c1) JOIN q2 USING (c2)")
def mi_allusers(spark, d):
    s1, s2_ = part1(spark, d).groupBy(F.col("cluster").alias("c1")).agg(F.count("*").alias("n")), part2(spark, d).groupBy(F.col("cluster").alias("c2")).agg(F.count("*").alias("n"))
    return rounded(consensus.information(table(spark, d), sizes1=s1, sizes2=s2_).select("mi"), "mi")


_DIRECTIONS = ", ".join(f"('{m}', {s}, '{'proportional' if s < 0 else 'inversely proportional'}', {m})" for m, s in combined.SIGN.items() if m in ("mi", "nmi", "vi"))


@query("metric_direction", f"{_INFO}, v AS (SELECT mi, mi / sqrt(h1 * h2) AS nmi, h1 + h2 - 2 * mi AS vi FROM i) SELECT t.measure, t.sign, t.direction, round(t.value, 6) AS value FROM v, LATERAL (VALUES {_DIRECTIONS}) t(measure, sign, direction, value)")
def metric_direction(spark, d):
    """The consensus measures of the reference partitions, with the direction of each."""
    values = consensus.information(table(spark, d)).select(F.explode(F.array(*[F.struct(F.lit(m).alias("measure"), F.col(m).alias("value")) for m in ("mi", "nmi", "vi")])).alias("r")).select("r.*")
    return rounded(values.join(F.broadcast(combined.directions(spark)), "measure").select("measure", "sign", "direction", "value"), "value")


def _joint(spark, d, quality_, consensus_, q1, q2, c, betas=(1.0, 1.0, 1.0, 1.0)):
    all_ = q1.toDF("q1").crossJoin(q2.toDF("q2")).crossJoin(c.toDF("c"))
    return all_.select(F.round(combined.combined(quality_, consensus_, F.col("q1"), F.col("q2"), F.col("c"), betas=betas), 6).alias("score"))


_ent1, _ent2 = _ENT.format("part1"), _ENT.format("part2")
query("combined_ent_vi", f"{_INFO} SELECT round({_ent1} + {_ent2} + 2 * (h1 + h2 - 2 * mi), 6) AS score FROM i")(lambda s, d: _joint(s, d, "entropy", "vi", quality.entropy(part1(s, d)), quality.entropy(part2(s, d)), consensus.information(table(s, d)).select("vi")))
query("combined_general", f"{_INFO} SELECT round(0.5 * {_ent1} + 2 * {_ent2} + 1.25 * (h1 + h2 - 2 * mi), 6) AS score FROM i")(lambda s, d: _joint(s, d, "entropy", "vi", quality.entropy(part1(s, d)), quality.entropy(part2(s, d)), consensus.information(table(s, d)).select("vi"), (0.5, 2.0, 0.25, 1.0)))
query("combined_dens_nmi", _INFO.replace("WITH ", f"WITH {sql.NET1}, {sql.NET2}, ", 1) + f" SELECT round(-{_DEN.format(1).replace(' a ', ' a_ ').replace('a.', 'a_.')} - {_DEN.format(2).replace(' a ', ' a_ ').replace('a.', 'a_.')} - 2 * mi / sqrt(h1 * h2), 6) AS score FROM i")(lambda s, d: _joint(s, d, "density", "nmi", quality.density(net.orders_net(s, d).follow, part1(s, d)), quality.density(net.events_net(s, d).follow, part2(s, d)), consensus.information(table(s, d)).select("nmi")))
_TWICE = f"WITH {_SROWS}, {_PAIRS.replace(f', {sql.PART2}', '')}"
query("combined_ndbi_rand", f"{_TWICE}{_NDBI} SELECT round(-2 * {_NDBI_OUT} + 2 * (SELECT avg(CASE WHEN {_DIFF} THEN 1.0 ELSE 0.0 END) FROM a x JOIN a y ON x.u1 < y.u1), 6) AS score")(lambda s, d: _joint(s, d, "ndbi", "rand", *[ndbi2(s, d)] * 2, consensus.rand(table(s, d))))
query("combined_sil_mi", _INFO.replace("WITH ", f"WITH {_EMB}{_SIL.format(f'sqrt({_GAP})')}, ", 1).replace(" a AS (", " a_ AS (").replace("FROM a ", "FROM a_ ").replace("FROM a)", "FROM a_)") + f" SELECT round(-2 * {_SIL_OUT} - 2 * mi, 6) AS score FROM i")(lambda s, d: _joint(s, d, "silhouette", "mi", *[quality.silhouette(*embedded(s, d))] * 2, consensus.information(table(s, d)).select("mi")))
query("lp_norm", "SELECT round(sum(abs(x)), 6) AS l1, round(sqrt(sum(x * x)), 6) AS l2, round(sum(x), 6) AS signed FROM (SELECT CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings)")(lambda s, d: rounded(vectors.norms(net.table(s, d, "embeddings").select(F.col("embedding").alias("vec"))), "l1", "l2", "signed"))


@query("relative_gain", f"WITH {sql.PART1}, {sql.PART2}, other1 AS (SELECT c_custkey AS user_id, c_custkey % 3 AS cluster FROM customer), other2 AS (SELECT DISTINCT user_id, user_id % 3 AS cluster FROM events), v AS (SELECT 'net1' AS net, {_ENT.format('part1')} AS own, {_ENT.format('other1')} AS value UNION ALL SELECT 'net2', {_ENT.format('part2')}, {_ENT.format('other2')}) SELECT 'entropy' AS measure, net, 'other' AS method, round((value - own) / abs(value), 6) AS gain FROM v")
def relative_gain(spark, d):
    """By how much the entropy of the reference partitions is better than that of coarser ones by key, in both networks."""
    report = None
    for name, part in (("net1", part1(spark, d)), ("net2", part2(spark, d))):
        for method, p in (("joint", part), ("other", part.select("user_id", (F.col("user_id") % 3).alias("cluster")))):
            row = quality.entropy(p).select(F.lit("entropy").alias("measure"), F.lit(name).alias("net"), F.lit(method).alias("method"), F.col("entropy").alias("value"))
            report = row if report is None else report.union(row)
    return rounded(combined.relative_gain(report, "joint"), "gain")

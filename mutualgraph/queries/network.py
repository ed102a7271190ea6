"""Queries on networks, alignment, meta paths and closeness."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..metrics.combined import directions  # noqa: F401  re-exported for the registry
from ..model.hetnet import describe
from ..operators import alignment, closeness, metapath
from ..plans import rewrites
from ..sources import networks as net
from . import sql

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return keep


def rounded(df, *cols: str):
    for c in cols:
        df = df.withColumn(c, F.round(c, 6))
    return df


def _sizes(n: int) -> str:
    return f"""SELECT 'net{n}' AS net, (SELECT count(*) FROM users{n}) AS users, (SELECT count(*) FROM posts{n}) AS posts, (SELECT count(*) FROM attr{n}) AS attributes, (SELECT count(*) FROM follow{n}) AS follow"""


@query("net_sizes", f"WITH {sql.NET1}, {sql.NET2} {_sizes(1)} UNION ALL {_sizes(2)}")
def net_sizes(spark, d):
    out = None
    for n in (net.orders_net(spark, d), net.events_net(spark, d)):
        row = n.users.agg(F.count("*").alias("users")).crossJoin(n.posts.agg(F.count("*").alias("posts"))).crossJoin(n.attributes.agg(F.count("*").alias("attributes"))).crossJoin(n.follow.agg(F.count("*").alias("follow"))).select(F.lit(n.name).alias("net"), "users", "posts", "attributes", "follow")
        out = row if out is None else out.union(row)
    return out


def _stats(n: int) -> str:
    loc = f"FROM attr{n} WHERE kind = 'location'"
    rows = [("users", f"(SELECT count(*) FROM users{n})"), ("posts", f"(SELECT count(*) FROM posts{n})"), ("locations", f"(SELECT count(DISTINCT attr) {loc})"), ("social links", f"(SELECT count(*) FROM follow{n})"), ("write links", f"(SELECT count(*) FROM posts{n})"), ("locate links", f"(SELECT count(*) {loc})"), ("located posts", f"(SELECT count(DISTINCT post_id) {loc})"), ("posts per user", f"(SELECT count(*) FROM posts{n}) * 1.0 / (SELECT count(*) FROM users{n})"), ("percent of posts located", f"100.0 * (SELECT count(DISTINCT post_id) {loc}) / (SELECT count(*) FROM posts{n})")]
    return f"WITH {sql.net(n)} " + " UNION ALL ".join(f"SELECT '{p}' AS property, round(CAST({v} AS DOUBLE), 6) AS value" for p, v in rows)


query("net1_stats", _stats(1))(lambda s, d: describe(net.orders_net(s, d)))
query("net2_stats", _stats(2))(lambda s, d: describe(net.events_net(s, d)))
query("net_a_stats", _stats(3))(lambda s, d: describe(net.document_view(s, d, 0)))
query("net_b_stats", _stats(4))(lambda s, d: describe(net.document_view(s, d, 1)))

query("anchor_users", f"WITH {sql.ANCHORS} SELECT c_custkey AS user_id FROM customer WHERE c_custkey IN (SELECT u1 FROM anchors)")(lambda s, d: alignment.anchor_users(net.orders_net(s, d), net.key_anchors(s, d)))
query("non_anchor_users", f"WITH {sql.ANCHORS} SELECT c_custkey AS user_id FROM customer WHERE c_custkey NOT IN (SELECT u1 FROM anchors)")(lambda s, d: alignment.non_anchor_users(net.orders_net(s, d), net.key_anchors(s, d)))


@query("anchor_violations", f"WITH {sql.ANCHORS}, dirty AS (SELECT u1, u2 FROM anchors UNION ALL SELECT u1, u2 + 1 FROM anchors WHERE u1 % 3 = 0) SELECT 'u1' AS side, u1 AS user_id, count(*) AS links FROM dirty GROUP BY u1 HAVING count(*) > 1 UNION ALL SELECT 'u2', u2, count(*) FROM dirty GROUP BY u2 HAVING count(*) > 1")
def anchor_violations(spark, d):
    a = net.key_anchors(spark, d)
    return alignment.violations(a.union(a.filter("u1 % 3 = 0").select("u1", F.col("u2") + 1)))


query("alignment_kind", f"WITH {sql.ANCHORS}, c AS (SELECT (SELECT count(*) FROM customer) AS n1, (SELECT count(DISTINCT user_id) FROM events) AS n2, (SELECT count(*) FROM anchors) AS links) SELECT 'net1' AS first, 'net2' AS second, n1, n2, links, CASE WHEN links = 0 THEN 'none' WHEN links = n1 AND links = n2 THEN 'full' ELSE 'partial' END AS kind FROM c")(lambda s, d: alignment.alignment_kinds(net.aligned_tables(s, d)))
query("anchors_sigma_05", f"WITH {sql.ANCHORS}, r AS (SELECT u1, u2, row_number() OVER (ORDER BY (u1 * 2654435761) % 4294967296, u1) AS k, count(*) OVER () AS n FROM anchors) SELECT u1, u2 FROM r WHERE k <= ceil(0.5 * n)")(lambda s, d: alignment.sample_anchors(net.key_anchors(s, d), 0.5))


@query("virtual_accounts", "WITH RECURSIVE l AS (SELECT c_custkey AS a, c_custkey - 7 AS b FROM customer WHERE c_custkey % 35 > 6 AND c_custkey % 35 < 28), e AS (SELECT a, b FROM l UNION SELECT b, a FROM l), r(a, b) AS (SELECT a, b FROM e UNION SELECT r.a, e.b FROM r JOIN e ON r.b = e.a) SELECT a AS user_id, least(a, min(b)) AS account FROM r GROUP BY a")
def virtual_accounts(spark, d):
    c = net.table(spark, d, "customer").filter("c_custkey % 35 > 6 and c_custkey % 35 < 28")
    return alignment.account_components(c.select(F.col("c_custkey").alias("user_a"), (F.col("c_custkey") - 7).alias("user_b")))


NAMES = {1: "follow", 2: "follower_of_follower", 3: "common_out", 4: "common_in", 5: "word", 6: "time", 7: "location"}
for _p, _name in NAMES.items():
    query(f"path{_p}_{_name}", f"WITH {sql.NET2}, {sql.counts(2, _p)} SELECT src, dst, cnt FROM p{_p}")(lambda s, d, p=_p: metapath.path_counts(net.events_net(s, d), p))
    query(f"path{_p}_marginals", f"WITH {sql.NET2}, {sql.counts(2, _p)}, {sql.marginals(_p)} SELECT user_id, o AS \"out\", i AS \"in\" FROM m{_p}")(lambda s, d, p=_p: metapath.path_marginals(net.events_net(s, d), p))
    query(f"sim_pair_p{_p}", f"WITH {sql.NET2}, {sql.counts(2, _p)}, {sql.marginals(_p)}, {sql.similarity(_p)} SELECT src, dst, round(s, 6) AS s FROM s{_p}")(lambda s, d, p=_p: closeness.path_similarity(net.events_net(s, d), p, digits=6))
    query(f"sim_matrix_p{_p}", f"WITH {sql.NET2}, {sql.counts(2, _p)}, {sql.marginals(_p)}, {sql.similarity(_p, 'matrix')} SELECT src, dst, round(s, 6) AS s FROM s{_p}")(lambda s, d, p=_p: closeness.path_similarity(net.events_net(s, d), p, "matrix", digits=6))
for _p in (2, 5, 7):
    query(f"net1_path{_p}_marginals", f"WITH {sql.NET1}, {sql.counts(1, _p)}, {sql.marginals(_p)} SELECT user_id, o AS \"out\", i AS \"in\" FROM m{_p}")(lambda s, d, p=_p: metapath.path_marginals(net.orders_net(s, d), p))
query("net1_path5_word", f"WITH {sql.NET1}, {sql.counts(1, 5)} SELECT src, dst, cnt FROM p5")(lambda s, d: metapath.path_counts(net.orders_net(s, d), 5))
query("path5_with_self", f"WITH {sql.NET2}, {sql.counts(2, 5, self_paths=True)} SELECT src, dst, cnt FROM p5")(lambda s, d: metapath.path_counts(net.events_net(s, d), 5, self_paths=True))


_LENGTHS = ", ".join(f"('{k}', 'U>P>{k[0].upper()}<P<U', 4, TRUE)" for k in ("word", "time", "location"))


@query("metapath_len", f"WITH {sql.NET2}, m AS (SELECT kind, count(*) AS links FROM attr2 GROUP BY 1) SELECT path, length, palindrome, links FROM (VALUES {_LENGTHS}) v(kind, path, length, palindrome) JOIN m USING (kind) UNION ALL SELECT path, length, palindrome, (SELECT count(*) FROM follow2) FROM (VALUES ('U>U', 1, FALSE), ('U>U>U', 2, FALSE), ('U>U<U', 2, TRUE), ('U<U>U', 2, TRUE)) w(path, length, palindrome)")
def metapath_len(spark, d):
    """The paths of net2 with the links on their middle: those of attributes that it has, and the social ones."""
    n = net.events_net(spark, d)
    paths = [(t, k, metapath.MetaPath.parse(t).length(), metapath.MetaPath.parse(t).is_palindrome()) for t, k in ((t, metapath.KIND_OF.get(p, "follow")) for p, t in metapath.PATHS.items())]
    links = n.attributes.groupBy("kind").agg(F.count("*").alias("links")).union(n.follow.agg(F.count("*").alias("links")).select(F.lit("follow"), "links"))
    return links.join(F.broadcast(spark.createDataFrame(paths, "path string, kind string, length int, palindrome boolean")), "kind").select("path", "length", "palindrome", "links")


@query("metapath_custom", f"WITH {sql.NET2}, w AS (SELECT a.user_id AS u, b.user_id AS v, count(*) AS c FROM (SELECT user_id, attr, post_id FROM posts2 JOIN attr2 USING (post_id) WHERE kind = 'time') a JOIN (SELECT user_id, attr, post_id FROM posts2 JOIN attr2 USING (post_id) WHERE kind = 'time') b USING (attr) GROUP BY 1, 2) SELECT f.src, w.v AS dst, sum(w.c) AS cnt FROM follow2 f JOIN w ON f.dst = w.u WHERE f.src <> w.v GROUP BY 1, 2")
def metapath_custom(spark, d):
    return metapath.compile_path(net.events_net(spark, d), metapath.MetaPath.parse("U>U>P>T<P<U"))


def _closeness_query(name: str, n: int, weights: str, form: str):
    w = closeness.weights_of(weights)
    build = net.orders_net if n == 1 else net.events_net
    query(name, f"WITH {sql.closeness(n, w, form)} SELECT src, dst, round(s, 6) AS s FROM S")(lambda s, d: closeness.closeness(build(s, d), weights, form, digits=6))


_closeness_query("closeness_pair_net1", 1, "uniform", "pair")
_closeness_query("closeness_matrix_net1", 1, "uniform", "matrix")
_closeness_query("closeness_pair_net2", 2, "uniform", "pair")
_closeness_query("closeness_matrix_net2", 2, "uniform", "matrix")
_closeness_query("closeness_social_only", 2, "social", "pair")
_closeness_query("closeness_attr_only", 2, "attribute", "pair")

_S2 = f"WITH {sql.closeness(2, sql.UNIFORM)}"


def s2(spark, d):
    return closeness.closeness(net.events_net(spark, d))


def crossed2(spark, d, form: str = "pair"):
    """net2's closeness as products of blocks, or None where it's better joined."""
    return closeness.CrossedCloseness.of(net.events_net(spark, d), form=form)


def top2(spark, d):
    crossed = crossed2(spark, d)
    return crossed.closest(10, 9) if crossed else closeness.sparsify(s2(spark, d).withColumn("s", F.round("s", 9)), 10)


def degrees2(spark, d):
    crossed = crossed2(spark, d)
    return crossed.degrees() if crossed else closeness.degrees(s2(spark, d))


def profile2(spark, d):
    crossed, n = crossed2(spark, d), net.events_net(spark, d)
    return crossed.profile() if crossed else closeness.profile(s2(spark, d), n.follow, n.users)


query("closeness_top10", f"{_S2}, b AS (SELECT src, dst FROM (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY round(s, 9) DESC, dst) AS r FROM S) WHERE r <= 10), w AS (SELECT src, dst FROM b UNION SELECT dst, src FROM b) SELECT src, dst, round(s, 6) AS s FROM S JOIN w USING (src, dst)")(lambda s, d: rounded(top2(s, d), "s"))
query("top_pairs", f"{_S2} SELECT src, dst, round(s, 6) AS s FROM S WHERE src < dst ORDER BY round(s, 9) DESC, src, dst LIMIT 20")(lambda s, d: rounded(s2(s, d).filter("src < dst").withColumn("s", F.round("s", 9)).orderBy(F.col("s").desc(), "src", "dst").limit(20), "s"))
query("degree_net1", f"WITH {sql.closeness(1, sql.UNIFORM)} SELECT src AS user_id, round(sum(s), 6) AS d FROM S GROUP BY 1")(lambda s, d: rounded(closeness.degrees(closeness.closeness(net.orders_net(s, d))), "d"))
query("degree_net2", f"{_S2} SELECT src AS user_id, round(sum(s), 6) AS d FROM S GROUP BY 1")(lambda s, d: rounded(degrees2(s, d), "d"))
query("symmetric_part_net2", f"WITH {sql.closeness(2, sql.UNIFORM, 'matrix')} SELECT src, dst, round(sum(s) / 2, 6) AS s FROM (SELECT src, dst, s FROM S UNION ALL SELECT dst, src, s FROM S) GROUP BY 1, 2")(lambda s, d: rounded(closeness.symmetric_part(closeness.closeness(net.events_net(s, d), form="matrix")), "s"))
query("closeness_profile", f"{_S2}, l AS (SELECT src, dst FROM follow2 UNION SELECT dst, src FROM follow2), n AS (SELECT count(*) AS n FROM users2) SELECT count(*) AS pairs, count(l.src) AS direct, count(*) - count(l.src) AS indirect, max(n * (n - 1)) AS possible FROM S LEFT JOIN l ON S.src = l.src AND S.dst = l.dst CROSS JOIN n")(profile2)
query("ancestor_sim_p5", f"WITH {sql.NET2}, {sql.counts(2, 5, self_paths=True)} SELECT p.src, p.dst, round(2.0 * p.cnt / (a.cnt + b.cnt), 6) AS s FROM p5 p JOIN p5 a ON a.src = p.src AND a.dst = p.src JOIN p5 b ON b.src = p.dst AND b.dst = p.dst WHERE p.src <> p.dst")(lambda s, d: closeness.ancestor_similarity(net.events_net(s, d), 5, 6))
query("common_neighbors", f"WITH {sql.NET1} SELECT a.src, b.src AS dst, count(*) AS common FROM follow1 a JOIN follow1 b USING (dst) WHERE a.src < b.src GROUP BY 1, 2")(lambda s, d: closeness.common_neighbours(net.orders_net(s, d)))
query("jaccard", f"WITH {sql.NET2}, d AS (SELECT src AS u, count(*) AS d FROM follow2 GROUP BY 1), c AS (SELECT a.src, b.src AS dst, count(*) AS n FROM follow2 a JOIN follow2 b USING (dst) WHERE a.src < b.src GROUP BY 1, 2) SELECT c.src, c.dst, round(n * 1.0 / (x.d + y.d - n), 6) AS s FROM c JOIN d x ON x.u = c.src JOIN d y ON y.u = c.dst")(lambda s, d: rounded(closeness.jaccard(net.events_net(s, d)), "s"))

_shares = ", ".join(f"({p}, (SELECT coalesce(sum(s), 0) FROM s{p} JOIN part2 a ON a.user_id = src JOIN part2 b ON b.user_id = dst WHERE a.cluster = b.cluster))" for p in range(1, 8))
query("weight_votes", f"{_S2}, {sql.PART2}, v(path, mass) AS (SELECT * FROM (VALUES {_shares}) t(path, mass)) SELECT path, round((1.0 / 7 + mass / (SELECT sum(mass) FROM v)) / 2, 6) AS weight FROM v")(lambda s, d: rounded(closeness.vote_weights(net.events_net(s, d), net.events_net(s, d).users.select("user_id", (F.col("user_id") % 10).cast("int").alias("cluster")), closeness.weights_of()), "weight"))


def _join_rows(n: int) -> str:
    social = [f"SELECT 'net{n}' AS net, 2 AS path, (SELECT count(*) FROM follow{n} a JOIN follow{n} b ON a.dst = b.src) AS join_rows", f"SELECT 'net{n}', 3, (SELECT count(*) FROM follow{n} a JOIN follow{n} b USING (dst))", f"SELECT 'net{n}', 4, (SELECT count(*) FROM follow{n} a JOIN follow{n} b USING (src))"]
    attr = [f"SELECT 'net{n}', {p}, (SELECT sum(c * c) FROM (SELECT attr, count(DISTINCT user_id) AS c FROM posts{n} JOIN attr{n} USING (post_id) WHERE kind = '{k}' GROUP BY 1))" for p, k in ((5, "word"), (6, "time"), (7, "location"))]
    return " UNION ALL ".join(social + attr)


query("path_join_rows", f"WITH {sql.NET1}, {sql.NET2} SELECT net, path, CAST(join_rows AS BIGINT) AS join_rows FROM ({_join_rows(1)} UNION ALL {_join_rows(2)})")(lambda s, d: rewrites.path_join_rows(net.orders_net(s, d)).union(rewrites.path_join_rows(net.events_net(s, d))))
query("hub_attributes", f"WITH {sql.NET2}, h AS (SELECT attr, count(DISTINCT user_id) AS users, count(*) AS posts FROM posts2 JOIN attr2 USING (post_id) WHERE kind = 'word' GROUP BY 1) SELECT attr, users, users > 100 AS hub, CASE WHEN users > 100 THEN users * users ELSE 0 END AS lost_rows FROM h")(lambda s, d: rewrites.classify_hubs(net.events_net(s, d), "word", 100))

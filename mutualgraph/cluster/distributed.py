"""The same steps on tables: users, their rows and closeness stay distributed, k x k matrices come to the driver."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..linalg.blocks import BLOCK_ROWS, PackedEntries, map_rows, spmm, sums
from ..linalg.factorised import Factors
from ..linalg.iterated import largest, parts_of, rows_of
from ..model.hetnet import AlignedSet, HetNet
from ..operators.closeness import CrossedCloseness, degrees
from ..optimize.curvilinear import Grams, Settings, run
from ..storage import drop_stored, store
from .kmeans import FeatureTable, SquareTable, dense_clusters, lloyd, lloyd_rows

_ROW = "array<double>"


def _by_root(rows: DataFrame, degree: DataFrame) -> DataFrame:
    """Rows (user_id, vec) of users with a degree, over its root."""
    return rows.join(degree, "user_id").select("user_id", F.transform("vec", lambda v: v / F.sqrt("d")).alias("vec"))


class EntryOperator:
    """A symmetric S as a table of entries (src, dst, s), packed once for all products."""

    def __init__(self, S: DataFrame):
        each = store(S.groupBy(F.col("src").alias("user_id")).agg(F.sum("s").alias("d"), F.count("*").alias("n")), "degree")
        self.S, self.degree = S, each.filter("d > 0").select("user_id", "d")
        users, entries = each.agg(F.count("*"), F.coalesce(F.sum("n"), F.lit(0))).first()
        self.packed = PackedEntries(S.select("src", "dst", F.col("s").alias("w")), users, entries)
        self.blocks, self.parts = self.packed.blocks, self.packed.parts

    def scaled(self, rows: DataFrame) -> DataFrame:
        """D^-1/2 S D^-1/2 times rows (user_id, vec)."""
        return _by_root(self.packed.times(_by_root(rows, self.degree)), self.degree)

    def similarity_rows(self):
        return FeatureTable(self.S.join(self.degree, F.col("src") == F.col("user_id"), "left_semi").select(F.col("src").alias("user_id"), F.col("dst").alias("dim"), F.col("s").alias("x")))


class CrossedOperator:
    """A symmetric S of which no pair is stored or shuffled: products are formed by terms that have factors, or else by blocks
    of users anew for each."""

    def __init__(self, S: CrossedCloseness):
        self.S, self.terms = S, S.terms()
        one = S.net.users.select("user_id", F.array(F.lit(1.0)).alias("vec"))
        self.times = S.times if self.terms is None else self.terms.times
        self.degree = store(self.times(one).select("user_id", F.col("vec")[0].alias("d")).filter("d > 0"), "degree")
        users = self.degree.count()
        self.blocks = max(1, -(-users // BLOCK_ROWS), min(12, -(-users // 1024)))

    def scaled(self, rows: DataFrame) -> DataFrame:
        return _by_root(self.times(_by_root(rows, self.degree)), self.degree)

    def parts(self, state: DataFrame) -> DataFrame:
        return parts_of(self.times(rows_of(state)), self.blocks, state) if self.terms is None else self.terms.parts(state)

    def lengths(self) -> DataFrame:
        """user_id, xx: squared lengths of rows of S, which takes every pair."""
        both = self.S.times(self.S.net.users.select("user_id", F.array(F.lit(1.0)).alias("vec")), squares=True)
        return store(both.select("user_id", F.col("vec")[1].alias("xx")), "lengths")

    def similarity_rows(self):
        return SquareTable(self.degree.select("user_id", F.lit(0.0).alias("xx")), self.times, self.lengths)


class FactorOperator:
    """The symmetric part of row-normalised closeness, by its factors: S is never formed."""

    def __init__(self, net: HetNet, weights):
        self.factors = Factors(net, weights)
        one = net.users.select("user_id", F.array(F.lit(1.0)).alias("vec"))
        self.degree = store(self.factors.symmetric_times(one).select("user_id", F.col("vec")[0].alias("d")).filter("d > 0"), "degree")
        self.blocks = max(1, -(-self.degree.count() // BLOCK_ROWS))

    def parts(self, state: DataFrame) -> DataFrame:
        return parts_of(self.factors.symmetric_times(store(rows_of(state), "rows")), self.blocks, state)

    def scaled(self, rows: DataFrame) -> DataFrame:
        return _by_root(self.factors.symmetric_times(store(_by_root(rows, self.degree), "scaled")), self.degree)

    def similarity_rows(self):
        return SquareTable(self.degree.select("user_id", F.lit(0.0).alias("xx")), self.factors.symmetric_times)


@dataclass
class _Net:
    operator: EntryOperator | FactorOperator
    state: DataFrame  # user_id, x, lx, t0, t1, ... (and x0, the row before)
    k: int
    links: list[int]  # its pairs; t0 belongs to the first
    z: DataFrame | None = None
    r: np.ndarray | None = None
    steps: int = 0
    grams: list[np.ndarray] = field(default_factory=list)  # of its scaled anchor rows, by pair
    raw: list = field(default_factory=list)


@dataclass
class _Pair:
    nets: tuple[int, int]
    anchors: DataFrame  # u1, u2, both with similarity
    factor: float
    cross: np.ndarray | None = None  # of the scaled anchor rows of its first network with its second's


class TableProblem:
    """Any number of networks. Each step stores one table of rows with gradient and product, and sums its Gram matrices."""

    def __init__(self, operators: list, anchors: dict[tuple[int, int], DataFrame], k: list[int], cfg: Settings, seed: int, init: str = "kmeans"):
        self.cfg, self.count, self.c0 = cfg, len(operators), 1.0
        self.pairs: list[_Pair] = []
        for (i, j), a in sorted(anchors.items()):
            one, two = (operators[n].degree.select(F.col("user_id").alias(u)) for n, u in ((i, "u1"), (j, "u2")))
            both = store(a.select("u1", "u2").join(one, "u1", "left_semi").join(two, "u2", "left_semi"), "anchors")
            n = both.count()
            if n > 1:
                self.pairs.append(_Pair((i, j), both, cfg.theta / (n * (n - 1))))
        self.nets: list[_Net] = []
        for i, op in enumerate(operators):
            rows, width = start_rows(op, k[i], init, seed)
            links = [p for p, pair in enumerate(self.pairs) if i in pair.nets]
            volume = np.sqrt(op.degree.agg(F.sum("d")).first()[0] / width) if cfg.discrepancy_scale == "volume" and width else 1.0
            x = rows.join(op.degree, "user_id")
            for m, p in enumerate(links):
                side = self.pairs[p].anchors.select(F.col(self._side(p, i)).alias("user_id"), F.lit(float(volume)).alias(f"t{m}"))
                x = x.join(side, "user_id", "left").withColumn(f"t{m}", F.coalesce(f"t{m}", F.lit(0.0)) / F.sqrt("d"))
            names = [f"t{m}" for m in range(len(links))]
            net = _Net(op, None, width, links)
            net.state = self._with_product(net, store(x.select("user_id", *names, F.col("vec").alias("x")), "x"))
            got = sums(net.state, ["x", *names], lambda c, names=names: {t: (c[t][:, None] * c["x"]).T @ (c[t][:, None] * c["x"]) for t in names}) if names else {}
            net.grams = [got.get(t, np.zeros((width, width))) for t in names]
            self.nets.append(net)
        for p, pair in enumerate(self.pairs):
            (i, j), joined = pair.nets, pair.anchors
            for n, u, o in ((i, "u1", "one"), (j, "u2", "two")):
                joined = joined.join(self._scaled(n, p, self.nets[n].state, u, o), u)
            got = sums(joined, ["one", "two"], lambda c: {"p": c["one"].T @ c["two"]})
            pair.cross = got.get("p", np.zeros((self.nets[i].k, self.nets[j].k)))

    def _side(self, p: int, i: int) -> str:
        return "u1" if self.pairs[p].nets[0] == i else "u2"

    def _scaled(self, i: int, p: int, state: DataFrame, key: str, name: str) -> DataFrame:
        """key, name: a network's anchor rows of a pair, scaled."""
        t = f"t{self.nets[i].links.index(p)}"
        return state.filter(F.col(t) > 0).select(F.col("user_id").alias(key), F.transform("x", lambda v: v * F.col(t)).alias(name))

    def _with_product(self, n: _Net, x: DataFrame, extra: tuple[str, ...] = ()) -> DataFrame:
        """x with lx = L x, stored."""
        s = n.operator.scaled(x.select("user_id", F.col("x").alias("vec"))).withColumnRenamed("vec", "sx")
        gap = F.when(F.col("sx").isNull(), F.col("x")).otherwise(F.zip_with("x", "sx", lambda a, b: a - b))
        return store(x.join(s, "user_id", "left").select("user_id", *self._names(n), "x", gap.alias("lx"), *extra), "state")

    @staticmethod
    def _names(n: _Net) -> list[str]:
        return [f"t{m}" for m in range(len(n.links))]

    def weight(self, i: int) -> float:
        return (self.cfg.alpha, self.cfg.beta)[min(i, 1)]

    def _moved(self, n: _Net) -> DataFrame:
        """user_id, t..., x, lx, x0 after the last accepted step."""
        if n.z is None:
            return n.state.withColumn("x0", F.lit(None).cast(_ROW))
        r, names = n.r, self._names(n)
        made = lambda c: {"x": np.hstack([c["x"], c["g"]]) @ r, "lx": np.hstack([c["lx"], c["lg"]]) @ r, "x0": c["x"]}
        return map_rows(n.z, ["x", "g", "lx", "lg"], made, f"user_id long, {''.join(f'{t} double, ' for t in names)}x {_ROW}, lx {_ROW}, x0 {_ROW}", keep=("user_id", *names))

    def grams(self, i: int) -> Grams:
        n, names = self.nets[i], self._names(self.nets[i])
        state = self._moved(n)
        if n.z is not None and n.steps % self.cfg.refresh == 0:
            state = self._with_product(n, store(state.select("user_id", *names, "x", "x0"), "x"), ("x0",))
        far, cross, others = [], [], []
        for m, p in enumerate(n.links):
            pair = self.pairs[p]
            j = pair.nets[1] if pair.nets[0] == i else pair.nets[0]
            rows = self._scaled(j, p, self._moved(self.nets[j]), self._side(p, j), f"o{m}")
            state = state.join(pair.anchors.join(rows, self._side(p, j)).select(F.col(self._side(p, i)).alias("user_id"), f"o{m}"), "user_id", "left")
            far.append(self.nets[j].k)
            cross.append(pair.cross if pair.nets[0] == i else pair.cross.T)
            others.append(self.nets[j].grams[self.nets[j].links.index(p)])
        own, w, width, factors = n.grams, self.weight(i), n.k, [self.pairs[p].factor for p in n.links]

        def gradient(c):
            g = 2 * w * c["lx"]
            out = {"x": c["x"], "lx": c["lx"], "x0": c["x0"] if c["x0"].shape[1] else np.zeros((len(g), width))}
            for m, t in enumerate(names):
                o = c[f"o{m}"] if c[f"o{m}"].shape[1] else np.zeros((len(g), far[m]))
                tt = c[t][:, None]
                g = g + 4 * factors[m] * tt * ((tt * c["x"]) @ own[m] - o @ cross[m].T)
                out[f"o{m}"] = o
            return out | {"g": g}

        rows_of = ["x", "lx", "x0", *(f"o{m}" for m in range(len(names)))]
        schema = f"user_id long, {''.join(f'{t} double, ' for t in names)}" + ", ".join(f"{c} {_ROW}" for c in [*rows_of, "g"])
        g = store(map_rows(state, [*names, *rows_of], gradient, schema, keep=("user_id", *names)), "gradient")
        sg = n.operator.scaled(g.select("user_id", F.col("g").alias("vec"))).withColumnRenamed("vec", "sg")
        lg = F.when(F.col("sg").isNull(), F.col("g")).otherwise(F.zip_with("g", "sg", lambda a, b: a - b))
        z = store(g.join(sg, "user_id", "left").select(*g.columns, lg.alias("lg")), "step")
        drop_stored(g)

        def parts(c):
            zz, lz = np.hstack([c["x"], c["g"]]), np.hstack([c["lx"], c["lg"]])
            out = {"zz": zz.T @ zz, "zlz": zz.T @ lz, "back": c["x0"].T @ zz}
            for m, t in enumerate(names):
                at = c[t] > 0
                tz = (c[t][:, None] * zz)[at]
                out[f"nn{m}"], out[f"cross{m}"] = tz.T @ tz, tz.T @ c[f"o{m}"][at]
            return out

        got = sums(z, [*names, *rows_of, "g", "lg"], parts)
        old = n.z
        n.z, n.steps = z, n.steps + 1
        if old is not None:
            drop_stored(old)
        n.raw = [(got[f"nn{m}"], got[f"cross{m}"]) for m in range(len(names))]
        roots = [np.sqrt(f) for f in factors]
        nn = [q * a for q, (a, _) in zip(roots, n.raw, strict=True)] or np.zeros((2 * width, 2 * width))
        side = np.hstack([q * b for q, (_, b) in zip(roots, n.raw, strict=True)]) if names else np.zeros((2 * width, 1))
        other = sum(f * float((o**2).sum()) for f, o in zip(factors, others, strict=True))
        back = got["back"] if n.steps > 1 else None
        return Grams(got["zz"], (got["zlz"] + got["zlz"].T) / 2, nn, side, other, back)

    def advance(self, i: int, r: np.ndarray) -> None:
        """The anchor Gram matrices after the step follow from R, without a job."""
        n = self.nets[i]
        n.r = r
        for m, p in enumerate(n.links):
            nn, cross = n.raw[m]
            n.grams[m] = r.T @ nn @ r
            pair = self.pairs[p]
            pair.cross = r.T @ cross if pair.nets[0] == i else (r.T @ cross).T

    def norm(self, i: int) -> float:
        n = self.nets[i]
        if n.z is None:
            return float(sums(n.state, ["x"], lambda c: {"l1": np.abs(c["x"]).sum()[None]})["l1"][0, 0])
        r = n.r
        return float(sums(n.z, ["x", "g"], lambda c: {"l1": np.abs(np.hstack([c["x"], c["g"]]) @ r).sum()[None]})["l1"][0, 0])

    def residual(self, i: int) -> float:
        n = self.nets[i]
        got = sums(self._moved(n), ["x"], lambda c: {"xx": c["x"].T @ c["x"]})["xx"]
        return float(np.linalg.norm(got - np.eye(n.k)))


def start_rows(op, k: int, init: str, seed: int) -> tuple[DataFrame, int]:
    """user_id, vec with X'X = I over users with similarity, and k, cut to their number."""
    k = min(k, op.degree.count())
    if init == "kmeans":
        labels = lloyd_rows(op.similarity_rows(), k, seed=seed)
        vol = labels.join(op.degree, "user_id").groupBy("cluster").agg(F.sum("d").alias("vol"))
        one = F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda c: F.when(c == F.col("cluster"), F.sqrt(F.col("d") / F.col("vol"))).otherwise(0.0))
        return labels.join(op.degree, "user_id").join(F.broadcast(vol), "cluster").select("user_id", one.alias("vec")), k
    if init == "spectral":
        return spectral_rows(op, k, seed), k
    return _orthonormal(_drawn(op, k, seed)), k


def _drawn(op, width: int, seed: int) -> DataFrame:
    draw = F.transform(F.sequence(F.lit(1), F.lit(width)), lambda c: F.xxhash64("user_id", c, F.lit(seed)).cast("double") / float(1 << 63))
    return store(op.degree.select("user_id", draw.alias("vec")), "block")


def _orthonormal(x: DataFrame) -> DataFrame:
    """Rows of orthonormal columns of the same span, by two Cholesky factors of their Gram matrix. Stored; x, if it is a
    stored table, is dropped."""
    for _ in range(2):
        g = sums(x, ["vec"], lambda c: {"g": c["vec"].T @ c["vec"]})["g"]
        turn = np.linalg.inv(np.linalg.cholesky(g + 1e-15 * np.trace(g) * np.eye(len(g)))).T
        old, x = x, store(map_rows(x, ["vec"], lambda c, t=turn: {"vec": c["vec"] @ t}, f"user_id long, vec {_ROW}"), "block")
        drop_stored(old)
    return x


def spectral_rows(op, k: int, seed: int = 0, rounds: int = 150, tol: float = 1e-9) -> DataFrame:
    """user_id, vec: the k largest eigenvectors of the normalised similarity, by block iteration on filters of it; ends when the
    sum of the k values settles, as arrays do."""
    z = _eigenrows(op, k, seed, rounds, tol)
    return z.select("user_id", F.transform("vec", lambda v: v * F.sqrt("d")).alias("vec"))


def _eigenrows(op, k: int, seed: int, rounds: int = 150, tol: float = 1e-9) -> DataFrame:
    """user_id, d, vec: the same rows over the roots of degrees, which is what users are grouped by. Stored."""
    width = min(2 * k + 5, op.degree.count())
    draw = F.transform(F.sequence(F.lit(1), F.lit(width)), lambda c: F.xxhash64("user_id", c, F.lit(seed)).cast("double") / float(1 << 63) / F.sqrt("d"))
    return largest(op, k, op.degree.select("user_id", "d", draw.alias("vec")), rounds, tol)


def hard_clusters(rows: DataFrame, k: int, how: str, seed: int) -> DataFrame:
    """user_id, cluster of confidence rows (user_id, vec): argmax, or K-means on rows of unit length, the better of a start
    from those and of a drawn one."""
    size = F.transform("vec", lambda v: F.abs(v))
    if how == "argmax":
        return rows.select("user_id", (F.array_position(size, F.array_max(size)) - 1).cast("int").alias("cluster"))
    unit = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda a, v: a + v * v))
    return dense_clusters(store(rows.select("user_id", F.transform("vec", lambda v: v / F.greatest(unit, F.lit(1e-300))).alias("vec")), "unit"), k, 50, seed)


def mutual_tables(aligned: AlignedSet, S: list, k: list[int], cfg: Settings, seed: int, how: str = "kmeans_rows", init: str = "kmeans") -> DataFrame:
    """The table that MutualResult reads. S: closeness of each network, as entries or as a FactorOperator. Users without
    similarity take their anchor's cluster, or -1."""
    spark = aligned.nets[0].users.sparkSession
    operators = [s if isinstance(s, FactorOperator) else EntryOperator(s) for s in S]
    problem = TableProblem(operators, {p: aligned.anchors[p] for p in aligned.pairs()}, k, cfg, seed, init)
    steps = run(problem, cfg)
    labels = []
    for n in problem.nets:
        rows = problem._moved(n).join(n.operator.degree, "user_id").select("user_id", F.transform("x", lambda v: v / F.sqrt("d")).alias("vec"))
        rows = store(rows, "rows")
        labels.append((rows, hard_clusters(rows, n.k, how, seed)))
    out = None
    for i, (rows, label) in enumerate(labels):
        every, lent = aligned.nets[i].users.join(label, "user_id", "left"), []
        for p, (a, b) in enumerate(aligned.pairs()):
            if i in (a, b):
                mine, theirs, j = ("u1", "u2", b) if i == a else ("u2", "u1", a)
                other = labels[j][1].select(F.col("user_id").alias(theirs), F.col("cluster").alias(f"_c{p}")).filter(F.col(f"_c{p}") < problem.nets[i].k)
                every = every.join(aligned.anchors[a, b].join(other, theirs).select(F.col(mine).alias("user_id"), f"_c{p}"), "user_id", "left")
                lent.append(f"_c{p}")
        part = every.join(rows, "user_id", "left").select(F.lit("user").alias("kind"), F.lit(i).alias("net"), "user_id", F.coalesce("cluster", *lent, F.lit(-1)).cast("int").alias("cluster"), "vec")
        out = part if out is None else out.union(part)
    told = spark.createDataFrame([("step", s["net"], s["iter"], s["f"], float(s["c"]), s["q"], float(s["tau"]), s["l1"], s["grad_norm"], s["backtracks"], bool(s["accepted"])) for s in steps], "kind string, net int, iter int, f double, c double, q double, tau double, l1 double, grad_norm double, backtracks int, accepted boolean")
    ends = spark.createDataFrame([("end", i, max([s["iter"] for s in steps if s["net"] == i], default=0), problem.residual(i)) for i in range(problem.count)], "kind string, net int, iter int, residual double")
    return store(out.unionByName(told, allowMissingColumns=True).unionByName(ends, allowMissingColumns=True), "mutual")


def spectral_partition(users: DataFrame, S: DataFrame | CrossedCloseness, k: int, seed: int = 0) -> DataFrame:
    """user_id, cluster by the relaxed normalised cut: eigenvectors, then K-means as hard_clusters does it."""
    op = CrossedOperator(S) if isinstance(S, CrossedCloseness) else EntryOperator(S)
    k = min(k, op.degree.count())
    if not k:
        return users.select("user_id", F.lit(-1).alias("cluster"))
    label = hard_clusters(_eigenrows(op, k, seed).select("user_id", "vec"), k, "kmeans_rows", seed)
    return users.join(label, "user_id", "left").select("user_id", F.coalesce("cluster", F.lit(-1)).alias("cluster"))


def propagation_tables(aligned: AlignedSet, S: list[DataFrame], k: list[int], restart: float, hops: int, gamma: float, seed: int, rounds: int) -> list[DataFrame]:
    """Propagation on tables: one walk over the users of both networks as a table of entries, its restart series by
    repeated products, and the factor of its symmetric part by orthogonal iteration. Users of network i are 2 id + i."""
    key = lambda c, i: (2 * F.col(c) + i).cast("long")
    anchors = aligned.anchors[0, 1].select(key("u1", 0).alias("a"), key("u2", 1).alias("b"))
    users = store(reduce(DataFrame.union, [n.users.select(key("user_id", i).alias("user_id")) for i, n in enumerate(aligned.nets[:2])]), "users")
    anchors = store(anchors.join(users, F.col("a") == F.col("user_id"), "left_semi").join(users, F.col("b") == F.col("user_id"), "left_semi"), "anchors")
    linked = anchors.select(F.col("a").alias("src")).union(anchors.select(F.col("b").alias("src"))).withColumn("stay", F.lit(1.0 - gamma))
    steps = []
    for i, s in enumerate(S[:2]):
        d = degrees(s).filter("d > 0").select(F.col("user_id").alias("src"), "d")
        steps.append(s.join(d, "src").select(key("src", i).alias("src"), key("dst", i).alias("dst"), (F.col("s") / F.col("d")).alias("w")))
    inner = reduce(DataFrame.union, steps).join(linked, "src", "left").select("src", "dst", (F.col("w") * F.coalesce("stay", F.lit(1.0))).alias("w"))
    hop = anchors.select(F.col("a").alias("src"), F.col("b").alias("dst")).union(anchors.select("b", "a")).withColumn("w", F.lit(float(gamma)))
    walk = store(inner.union(hop), "walk")
    turned = walk.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")

    def series(q: DataFrame, entries: DataFrame) -> DataFrame:
        total = q.select("user_id", F.transform("vec", lambda v: v * restart).alias("vec"))
        term = q
        for _ in range(hops):
            term = store(spmm(entries, term).select("user_id", F.transform("vec", lambda v: v * (1 - restart)).alias("vec")), "term")
            more = term.select("user_id", F.transform("vec", lambda v: v * restart).alias("more"))
            total = total.join(more, "user_id", "left").select("user_id", F.when(F.col("more").isNull(), F.col("vec")).otherwise(F.zip_with("vec", "more", lambda a, b: a + b)).alias("vec"))
        return total

    def image(q: DataFrame) -> DataFrame:
        """user_id, was (q), vec (the symmetric part of the series times q)."""
        there, back = series(q, walk), series(q, turned).withColumnRenamed("vec", "back")
        both = there.join(back, "user_id").select("user_id", F.zip_with("vec", "back", lambda a, b: (a + b) / 2).alias("vec"))
        return store(q.withColumnRenamed("vec", "was").join(both, "user_id"), "image")

    width = min(users.count(), 2 * max(k) + 5)
    draw = F.transform(F.sequence(F.lit(1), F.lit(width)), lambda c: F.xxhash64("user_id", c, F.lit(seed)).cast("double") / float(1 << 63))
    q, before = _orthonormal(store(users.select("user_id", draw.alias("vec")), "block")), -np.inf
    for n in range(rounds + 1):
        made = image(q)
        m = sums(made, ["was", "vec"], lambda c: {"m": c["was"].T @ c["vec"]})["m"]
        w, v = np.linalg.eigh((m + m.T) / 2)
        now = np.sort(w)[::-1][: max(k)].sum()
        if n == rounds or now - before <= 1e-6 * max(abs(now), 1.0):
            break
        before = now
        q = _orthonormal(made.select("user_id", F.zip_with("was", "vec", lambda a, b: a + b).alias("vec")))
    top = v[:, ::-1][:, : max(k)] * np.sqrt(np.maximum(w[::-1][: max(k)], 0))
    factor = store(map_rows(made, ["was"], lambda c: {"vec": c["was"] @ top}, f"user_id long, vec {_ROW}"), "factor")
    out = []
    for i, n in enumerate(aligned.nets[:2]):
        mine = factor.filter(F.col("user_id") % 2 == i).select(F.floor(F.col("user_id") / 2).cast("long").alias("user_id"), F.posexplode("vec").alias("dim", "x"))
        out.append(n.users.join(lloyd(mine, k[i], rounds=50, seed=seed), "user_id", "left").select("user_id", F.coalesce("cluster", F.lit(-1)).alias("cluster")))
    return out

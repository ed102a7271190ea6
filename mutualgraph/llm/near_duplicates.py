"""Near-duplicate documents: SuperMinHash signatures, banding, exact confirmation on full shingle sets, components."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from .common import join_small, ship, store
from .components import connected_components
from .words import mix64, released, shingles, slices, word_hashes

SIGNATURE = 144
_EMPTY = np.uint64((1 << 64) - 1)
#: What tells sets apart, whatever the doc_id of their texts.
DIGEST = ["n_shingles", "f1", "f2"]
#: Members of a bucket that are compared in one task, at most; larger buckets are compared block by block.
BLOCK = 256


def bands_for(percent: int, size: int = SIGNATURE, miss: float = 2e-5) -> tuple[int, int]:
    """Bands and rows: the most rows at which a pair at the threshold escapes all bands with at most this probability."""
    for rows in range(12, 0, -1):
        bands = size // rows
        if (1 - (percent / 100) ** rows) ** bands <= miss:
            return bands, rows
    return size, 1


def super_minhash(elements: np.ndarray, offsets: np.ndarray, size: int) -> np.ndarray:
    """Signatures (rows x size, uint64) of sets of 64-bit elements that lie side by side.

    Round j gives each element its j-th random value, j + r, and the j-th slot of a random permutation of its own (so its
    slots are all different: that is what lowers the variance), and a slot keeps its least value. A set stops after the
    first round that leaves all its slots below j + 1: no later round could lower one. All sets go through a round together.
    """
    count = len(offsets) - 1
    best = np.full(count * size, _EMPTY)
    row = np.repeat(np.arange(count), np.diff(offsets))
    live, perm = elements, None
    for j in range(size):
        x = mix64(live + np.uint64((0x9E3779B97F4A7C15 * (j + 1)) & (2**64 - 1)))
        pick = j + (((x & np.uint64(0xFFFFFFFF)) * np.uint64(size - j)) >> np.uint64(32)).astype(np.int64)
        if perm is None:
            slot = pick
        else:
            at = np.arange(len(live))
            slot = perm[at, pick].astype(np.int64)
            perm[at, pick] = perm[:, j]
            perm[:, j] = slot
        np.minimum.at(best, row * size + slot, (np.uint64(j) << np.uint64(32)) | (x >> np.uint64(32)))
        waiting = (best.reshape(count, size) == _EMPTY).any(1)
        keep = waiting[row]
        if not keep.any():
            break
        if perm is None:  # permutations are held for sets that need a second round only
            first = pick[keep]
            perm = np.tile(np.arange(size, dtype=np.uint16), (len(first), 1))
            at = np.arange(len(first))
            perm[at, first] = 0
            perm[:, 0] = first
        elif not keep.all():
            perm = perm[keep]
        live, row = live[keep], row[keep]
    return best.reshape(count, size)


def distinct_shingles(column, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct sorted shingle hashes of each row, and row offsets."""
    h, offs = shingles(*word_hashes(column), width)
    parts = [np.unique(h[a:b]) for a, b in zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True)]
    return (np.concatenate(parts) if parts else h), np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int64)


def _sums(values: np.ndarray, offs: np.ndarray) -> np.ndarray:
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(values, dtype=np.uint64)])
    return total[offs[1:]] - total[offs[:-1]]


def _digest(sets: np.ndarray, offs: np.ndarray) -> dict[str, pa.Array]:
    """n_shingles, f1 and f2: each set's size and a 128-bit digest of it."""
    sums = (_sums(mix64(x), offs).view(np.int64) for x in (sets, sets ^ np.uint64(0xA0761D6478BD642F)))
    return dict(zip(DIGEST, (pa.array(np.diff(offs), pa.int64()), *map(pa.array, sums)), strict=True))


def signatures(docs: DataFrame, width: int, percent: int, size: int = SIGNATURE) -> DataFrame:
    """doc_id, n_shingles, f1, f2 (a 128-bit digest of the set) and bands (one hash each; none for an empty set)."""
    ship(docs.sparkSession)
    bands, rows = bands_for(percent, size)

    def sign(batches):
        for b in batches:
            for part in slices(b, "text"):
                sets, offs = distinct_shingles(part.column("text"), width)
                n = np.diff(offs)
                full = np.flatnonzero(n)
                sig = super_minhash(sets, np.concatenate([[0], np.cumsum(n[full])]), size)[:, : bands * rows].reshape(len(full), bands, rows)
                key = np.broadcast_to(np.arange(1, bands + 1, dtype=np.uint64), (len(full), bands))
                for k in range(rows):
                    key = mix64(key * np.uint64(0xD6E8FEB86659FD93) + sig[:, :, k])
                lists = np.zeros(len(n), np.int64)
                lists[full] = bands
                yield pa.RecordBatch.from_pydict({
                    "doc_id": part.column("doc_id"),
                    **_digest(sets, offs),
                    "bands": pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(lists)]), pa.int32()), pa.array(key.reshape(-1).view(np.int64))),
                })

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(released(sign), "doc_id long, n_shingles long, f1 long, f2 long, bands array<long>")


def shingle_sets(docs: DataFrame, width: int) -> DataFrame:
    """n_shingles, f1, f2, set: whole distinct shingle sets, ascending, and their digests."""
    ship(docs.sparkSession)

    def run(batches):
        for b in batches:
            for part in slices(b, "text"):
                sets, offs = distinct_shingles(part.column("text"), width)
                yield pa.RecordBatch.from_pydict({**_digest(sets, offs), "set": pa.ListArray.from_arrays(pa.array(offs, pa.int32()), pa.array(sets.view(np.int64)))})

    return docs.select("text").mapInArrow(released(run), "n_shingles long, f1 long, f2 long, set array<long>")


def with_digests(docs: DataFrame, width: int) -> DataFrame:
    """docs with the digests of their sets as _n_shingles, _f1 and _f2 (text is a string)."""
    ship(docs.sparkSession)

    def run(batches):
        for b in batches:
            for part in slices(b, "text"):
                digest = _digest(*distinct_shingles(part.column("text"), width))
                yield pa.RecordBatch.from_arrays([*part.columns, *digest.values()], [*part.schema.names, *(f"_{c}" for c in digest)])

    return docs.mapInArrow(released(run), StructType([*docs.schema.fields, *(StructField(f"_{c}", LongType()) for c in DIGEST)]))


def near_duplicates(docs: DataFrame, width: int = 5, percent: int = 80, size: int = SIGNATURE, small: int = 1_000_000) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for each row of docs (doc_id, text).

    Sets are of distinct `width`-word shingles of lower-cased (A-Z) whole texts (64-bit hashes); a shorter text is one
    shingle, a text without words, or null, has an empty set and links with nothing. Documents link if 100 x common >=
    percent x union, which is confirmed on full sets. component_id is the smallest doc_id reachable, null if none there
    has one. Of each component one set is kept, in the rows that have it and component_id. Repeated rows each give a row;
    other columns are ignored; different texts may share a doc_id or have none.

    Equal sets form a class first, so copies cost one comparison. Classes that share a band are compared with the band's
    smallest member; bands whose members that leaves in different components are compared pair by pair across components,
    in blocks within a task. So every pair that shares a band is either in one component or compared, and no pair rows
    of a group are made.
    """
    return _grouped(docs, width, percent, size, small).select("doc_id", "n_shingles", "component_id", "kept")


def _grouped(docs: DataFrame, width: int = 5, percent: int = 80, size: int = SIGNATURE, small: int = 1_000_000) -> DataFrame:
    """The rows of near_duplicates with f1 and f2. Classes have numbers of their own (rep); doc_ids only name the outcome."""
    signed = store(signatures(docs, width, percent, size), "signatures")
    full = signed.filter("n_shingles > 0")
    classes = store(full.groupBy(*DIGEST).agg(F.min("doc_id").alias("least"), F.first("bands").alias("bands")).withColumn("rep", F.monotonically_increasing_id()), "classes")

    banded = classes.select("rep", "n_shingles", F.explode("bands").alias("band"))
    head = F.min(F.struct("rep", "n_shingles"))
    buckets = store(banded.groupBy("band").agg(head.alias("head"), F.count("*").alias("members")).filter("members > 1").select("band", F.col("head.rep").alias("head"), F.col("head.n_shingles").alias("head_n"), "members"), "buckets")
    member = store(join_small(banded, buckets, "band", "inner", buckets.count(), small), "members")

    ids = store(member.select("rep").distinct(), "candidates")
    n_ids = ids.count()
    wanted = store(join_small(classes.select("rep", "least", *DIGEST), ids, "rep", "left_semi", n_ids, small), "wanted")
    # doc_ids only find texts, perhaps more than those of candidates; the digests say which set is whose.
    known, least = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), wanted.select("least").distinct()
    texts = join_small(known, least, known["doc_id"].eqNullSafe(least["least"]), "left_semi", n_ids, small)
    sets = join_small(shingle_sets(texts, width), wanted.select("rep", *DIGEST), DIGEST, "inner", n_ids, small)
    sets = store(sets.groupBy("rep").agg(F.first("set").alias("set")), "sets")

    stars = member.filter((F.col("rep") != F.col("head")) & _alike("n_shingles", "head_n", percent)).select(F.col("rep").alias("a"), F.col("head").alias("b")).distinct()
    links = store(_confirmed(stars, sets, percent), "links")
    joined = connected_components(links)

    label = store(joined, "labels")
    at = member.join(label, F.col("rep") == F.col("node"), "left").withColumn("component", F.coalesce("component", "rep"))
    at = store(at.select("band", "rep", "n_shingles", "members", "component"), "labelled")
    # Bands with the same members need comparing once: they agree in number and in the sum of member hashes.
    split = at.groupBy("band").agg(F.min("component").alias("lo"), F.max("component").alias("hi"), F.count("*").alias("n"), F.sum(F.xxhash64("rep").cast("decimal(20,0)")).alias("who")).filter("lo <> hi")
    open_ = store(split.groupBy("n", "who").agg(F.min("band").alias("band")).select("band"), "open")
    more = store(_across(join_small(at, open_, "band", "left_semi", open_.count(), small), sets, percent), "more-links")
    final = store(connected_components(links.union(more)), "components")

    linked = store(classes.select("rep", "least", *DIGEST).join(final, F.col("rep") == F.col("node")).drop("node"), "linked")
    first = linked.groupBy("component").agg(F.min(F.struct(F.col("least").isNull().alias("none"), "least", *DIGEST)).alias("head"))
    whole = classes.select("rep", "least", *DIGEST).join(linked.join(first, "component").select("rep", "head"), "rep", "left")
    alone = F.col("head").isNull()
    is_head = alone | (F.struct(*DIGEST) == F.struct(*(F.col(f"head.{c}") for c in DIGEST)))
    whole = whole.select(*(F.col(c).alias(f"_{c}") for c in DIGEST), F.when(alone, F.col("least")).otherwise(F.col("head.least")).alias("component_id"), is_head.alias("_head"))
    mine = signed.drop("bands")
    out = full.drop("bands").join(whole, (F.col("n_shingles") == F.col("_n_shingles")) & (F.col("f1") == F.col("_f1")) & (F.col("f2") == F.col("_f2")))
    rows = out.select("doc_id", *DIGEST, "component_id", "_head")
    rows = rows.union(mine.filter("n_shingles = 0").select("doc_id", *DIGEST, F.col("doc_id").alias("component_id"), F.lit(True).alias("_head")))
    return rows.withColumn("kept", F.col("_head") & F.col("doc_id").eqNullSafe(F.col("component_id"))).drop("_head")


def _alike(a: str, b: str, percent: int):
    """Whether two set sizes allow the similarity at all."""
    return F.least(a, b) * 100 >= F.greatest(a, b) * percent


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    one = sets.select(F.col("rep").alias("a"), F.col("set").alias("x"))
    two = sets.select(F.col("rep").alias("b"), F.col("set").alias("y"))
    both = pairs.join(one, "a").join(two, "b").withColumn("common", F.size(F.array_intersect("x", "y")))
    return both.filter(100 * F.col("common") >= percent * (F.size("x") + F.size("y") - F.col("common"))).select("a", "b")


def _across(members: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links between members of one band in different components, as few as join the same components."""
    blocks = F.ceil(F.col("members") / BLOCK).cast("int")
    own = F.pmod(F.xxhash64("rep"), blocks).cast("int")
    tasks = F.transform(F.sequence(F.lit(0), blocks - 1), lambda k: F.struct(F.least(k, own).alias("i"), F.greatest(k, own).alias("j")))
    dealt = members.withColumn("own", own).withColumn("task", F.explode(tasks)).select("band", "task.i", "task.j", "own", "rep", "component")
    with_sets = dealt.join(sets, "rep").select("band", "i", "j", "own", "rep", "component", "set")

    def compare(t: pa.Table) -> pa.Table:
        rep, comp, own_ = (t.column(c).to_numpy() for c in ("rep", "component", "own"))
        items = t.column("set").combine_chunks()
        items = items.chunk(0) if isinstance(items, pa.ChunkedArray) else items
        flat, offs = items.flatten().to_numpy(zero_copy_only=False).view(np.uint64), np.asarray(items.offsets) - items.offsets[0].as_py()
        whole = [flat[a:b] for a, b in zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True)]
        i, j = t.column("i")[0].as_py(), t.column("j")[0].as_py()
        group = {c: c for c in comp.tolist()}

        def top(c):
            while group[c] != c:
                group[c] = group[group[c]]
                c = group[c]
            return c

        found = []
        order = np.argsort([len(w) for w in whole], kind="stable").tolist()
        for p, x in enumerate(order):
            for y in order[p + 1 :]:
                if 100 * len(whole[x]) < percent * len(whole[y]):
                    break
                if (i != j and own_[x] == own_[y]) or top(comp[x]) == top(comp[y]):
                    continue
                common = len(np.intersect1d(whole[x], whole[y], assume_unique=True))
                if 100 * common >= percent * (len(whole[x]) + len(whole[y]) - common):
                    found.append((rep[x], rep[y]))
                    group[top(comp[x])] = top(comp[y])
        return pa.table({"a": pa.array([int(a) for a, _ in found], pa.int64()), "b": pa.array([int(b) for _, b in found], pa.int64())})

    return with_sets.groupBy("band", "i", "j").applyInArrow(released(compare), "a long, b long")


def without_near_duplicates(docs: DataFrame, **options) -> DataFrame:
    """The rows of docs that stay: one of each component, with its smallest doc_id, and all texts without words.

    A doc_id that one row alone has names that row. Rows without a doc_id, or with one that others have too, are told
    apart by the digest of their set. Of rows with equal sets one stays; null and empty texts all stay; an empty table
    gives an empty one; other columns are kept, whatever their names but _id and _k_ and the digest's.
    """
    found = store(_grouped(docs, **options), "found")
    ids = store(found.groupBy(F.col("doc_id").alias("_id")).agg(F.count("*").alias("_n"), F.max("kept").alias("_kept")).filter("_kept"), "kept")
    clear, shared = ids.filter("_n = 1 and _id is not null").select("_id"), ids.filter("_n > 1 or _id is null").select("_id")
    key, most = docs["doc_id"].cast("long"), 4_000_000
    out = join_small(docs, clear, key == F.col("_id"), "left_semi", clear.count(), most)
    n_shared = shared.count()
    if not n_shared:
        return out
    told = with_digests(join_small(docs, shared, key.eqNullSafe(F.col("_id")), "left_semi", n_shared, most), options.get("width", 5))
    heads = found.filter("kept").select(F.col("doc_id").alias("_id"), *(F.col(c).alias(f"_k_{c}") for c in DIGEST)).distinct()
    same = told["doc_id"].cast("long").eqNullSafe(F.col("_id"))
    for c in DIGEST:
        same &= told[f"_{c}"] == F.col(f"_k_{c}")
    told = told.join(heads, same, "left_semi")
    once = told.filter("_n_shingles > 0").dropDuplicates([f"_{c}" for c in DIGEST]).union(told.filter("_n_shingles = 0"))
    return out.union(once.select(*(once[c] for c in docs.columns)))


#: The rows of near_duplicates(documents, 3, 85) by counting the shingles that documents share, for tables small enough for that.
ORACLE = r"""
WITH RECURSIVE worded AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
sets AS (
  SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')]
    ELSE list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]) END) AS s FROM worded),
sized AS (SELECT doc_id, len(s) AS n, sha256(array_to_string(list_sort(s), chr(10))) AS class FROM sets),
classes AS (SELECT class, min(doc_id) AS rep, any_value(n) AS n FROM sized WHERE n > 0 GROUP BY class),
members AS MATERIALIZED (SELECT rep, n, unnest(s) AS shingle FROM classes JOIN sets ON rep = doc_id),
links AS MATERIALIZED (
  SELECT a.rep AS a, b.rep AS b FROM members a JOIN members b ON a.shingle = b.shingle AND a.rep <> b.rep
  GROUP BY a.rep, b.rep, a.n, b.n HAVING 100 * count(*) >= 85 * (a.n + b.n - count(*))),
reach AS (SELECT a AS node, b AS other FROM links UNION SELECT reach.node, links.b FROM reach JOIN links ON reach.other = links.a),
least_ AS (SELECT node, least(node, min(other)) AS component FROM reach GROUP BY node)
SELECT d.doc_id, d.n AS n_shingles, coalesce(component, rep, d.doc_id) AS component_id, coalesce(component, rep, d.doc_id) = d.doc_id AS kept
FROM sized d LEFT JOIN classes c ON d.class = c.class AND d.n > 0 LEFT JOIN least_ ON node = rep
"""

"""Mixing sources to target weights by Efraimidis-Spirakis sampling."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, join_small, store

#: Rows of a source that may be sorted in one task; only those around the source's line ever are.
EDGE_ROWS = 50_000
#: Keys are placed by floor(log2(key) 2^40), whatever the scale of quality: 48 bits, of which a round looks at 12.
PLACE_BITS, ROUND_BITS = 48, 12


def word_count(text: Column) -> Column:
    """Words of a text; null has none."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def default_quality(text: Column, size: Column) -> Column:
    """In (0, 1]: 1 for a mean word length of six characters (white space included), less the further from it."""
    mean = F.coalesce(F.length(text), F.lit(0)) / F.greatest(size, F.lit(1))
    return 1 / (1 + F.pow(mean / 6 - 1, 2))


def targets(sizes: DataFrame, weights: tuple[float, ...], share: float, cap: float) -> DataFrame:
    """source, source_size, n, target: the budget (share of all sizes) dealt by weight to sources in code-point order
    (null last), no target above cap x the source's size; what is above is dealt again by weight among the others.

    One row a source; the windows run over that table. Filling in order of cap / weight gives the fixed point of dealing
    again and again in one pass: the level is where what is left over what weight is left no longer exceeds a cap.
    """
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.col("_k") % len(weights) + 1).cast("int"))
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    s = sizes.withColumn("_k", F.row_number().over(by_name) - 1).withColumn("_w", weight).withColumn("_cap", F.lit(float(cap)) * F.col("source_size"))
    by_fill = Window.orderBy(F.col("_cap") / F.col("_w"), "_k")
    before, onward, whole = by_fill.rowsBetween(Window.unboundedPreceding, -1), by_fill.rowsBetween(0, Window.unboundedFollowing), by_fill.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    left = F.lit(float(share)) * F.sum("source_size").over(whole) - F.coalesce(F.sum("_cap").over(before), F.lit(0.0))
    s = s.withColumn("_level", left / F.sum("_w").over(onward))
    s = s.withColumn("_level", F.first(F.when(F.col("_level") * F.col("_w") <= F.col("_cap"), F.col("_level")), ignorenulls=True).over(whole))
    return s.select("source", "source_size", "n", F.coalesce(F.least(F.col("_cap"), F.col("_level") * F.col("_w")), F.col("_cap")).alias("target"))


#: What makes rows interchangeable.
SAME = ["_id", "_src", "_size", "_hash", "_worth"]


def _described(docs: DataFrame, quality: Column | None) -> DataFrame:
    """docs (with doc_id, source, text) and SAME: id, source, size, hash of the text, quality."""
    rows = docs.withColumn("_id", F.col("doc_id").cast("long")).withColumn("_src", F.col("source").cast("string"))
    rows = rows.withColumn("_size", word_count(F.col("text"))).withColumn("_hash", F.xxhash64("text"))
    own = default_quality(F.col("text"), F.col("_size"))
    return rows.withColumn("_worth", F.greatest(own if quality is None else F.coalesce(quality.cast("double"), own), F.lit(1e-9)))


def _keyed(rows: DataFrame, seed: int) -> DataFrame:
    """rows (SAME and _rank, 1 to n among interchangeable rows) with _key, the exponential sampling key, its _place, and _tie,
    a hash that orders equal keys."""
    u = (F.shiftrightunsigned(F.xxhash64("_id", "_hash", "_rank", F.lit(seed)), 11).cast("double") + 0.5) / float(1 << 53)
    keyed = rows.withColumn("_key", -F.log(u) / F.col("_worth"))
    keyed = keyed.withColumn("_tie", F.xxhash64(*SAME, "_rank", F.lit(seed + 1)))
    return keyed.withColumn("_place", F.floor(F.log2("_key") * float(1 << 40)).cast("long"))


def _narrow(docs: DataFrame, quality: Column | None, seed: int) -> tuple[DataFrame, DataFrame]:
    """Stored keys of all rows, without texts; and the interchangeable ones (SAME and _n > 1)."""
    groups = store(_described(docs, quality).groupBy(*SAME).agg(F.count("*").alias("_n")), "sized")
    ranked = groups.withColumn("_rank", F.explode(F.sequence(F.lit(1).cast("long"), F.col("_n")))).drop("_n")
    return store(_keyed(ranked, seed).select("_id", "_src", "_size", "_key", "_tie", "_place"), "keys"), groups.filter("_n > 1")


def _lines(narrow: DataFrame, weights, share: float, cap: float) -> tuple[DataFrame, int]:
    """One row a source: what it has, its target, its whole epochs, and the key up to which one more copy is taken.

    The line is found by rounds: sizes are summed by ranges of places (4096 a source and round, with map-side partial
    sums), and the next round looks into the one range that the line falls into, until that holds EDGE_ROWS at most.
    """
    goal = targets(narrow.groupBy(F.col("_src").alias("source")).agg(F.sum("_size").alias("source_size"), F.count("*").alias("n")), weights, share, cap).drop("n")
    goal = goal.withColumn("_epochs", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long"))
    goal = store(goal.withColumn("_rest", F.col("target") - F.col("_epochs") * F.col("source_size")), "targets")
    sources = goal.count()
    bits = PLACE_BITS
    edge = goal.select("source", "_rest", F.lit(-(1 << (bits - 1))).cast("long").alias("_from"), F.lit(0).cast("long").alias("_paid"))
    in_order = Window.partitionBy("source").orderBy("_range")
    while True:
        bits -= ROUND_BITS
        inside = _at(narrow, edge, bits + ROUND_BITS, sources).withColumn("_range", F.shiftright(F.col("_place") - F.col("_from"), bits))
        sums = inside.groupBy("source", "_rest", "_from", "_paid", "_range").agg(F.sum("_size").alias("_sum"), F.count("*").alias("_rows"))
        sums = sums.withColumn("_upto", F.col("_paid") + F.sum("_sum").over(in_order)).withColumn("_before", F.col("_upto") - F.col("_sum"))
        edge = sums.filter((F.col("_before") < F.col("_rest")) & (F.col("_rest") <= F.col("_upto")))
        edge = store(edge.select("source", "_rest", (F.col("_from") + F.shiftleft("_range", bits)).alias("_from"), F.col("_before").alias("_paid"), "_rows"), "edges")
        most = edge.agg(F.max("_rows")).first()[0] or 0
        if most <= EDGE_ROWS or bits == 0:
            break

    by_key = Window.partitionBy("source").orderBy("_key", "_tie").rowsBetween(Window.unboundedPreceding, -1)
    at_edge = _at(narrow, edge, bits, sources).withColumn("_sofar", F.col("_paid") + F.coalesce(F.sum("_size").over(by_key), F.lit(0)))
    last = at_edge.filter(F.col("_sofar") + F.col("_size") / 2 <= F.col("_rest")).groupBy(F.col("source").alias("_s2")).agg(F.max(F.struct("_key", "_tie")).alias("_last"))
    edge = edge.select(F.col("source").alias("_s"), "_from", (F.col("_from") + (1 << bits)).alias("_to"))
    goal = goal.join(edge, goal["source"].eqNullSafe(edge["_s"]), "left").join(last, goal["source"].eqNullSafe(last["_s2"]), "left")
    return store(goal.select(F.col("source").alias("_of"), F.col("source_size").alias("_ssize"), F.col("target").alias("_target"), "_epochs", "_from", "_to", "_last"), "lines"), sources


def _at(narrow: DataFrame, edge: DataFrame, bits: int, sources: int) -> DataFrame:
    """Rows in their source's range of 2^bits places."""
    both = join_small(narrow, edge, narrow["_src"].eqNullSafe(edge["source"]), "inner", sources)
    return both.filter((F.col("_place") >= F.col("_from")) & (F.col("_place") < F.col("_from") + (1 << bits)))


def _decided(rows: DataFrame, lines: DataFrame, sources: int) -> DataFrame:
    out = join_small(rows, lines, rows["_src"].eqNullSafe(lines["_of"]), "inner", sources)
    at = F.col("_place") < F.col("_to")
    more = F.col("_from").isNotNull() & ((F.col("_place") < F.col("_from")) | (at & F.coalesce(F.struct("_key", "_tie") <= F.col("_last"), F.lit(False))))
    return out.withColumn("_times", F.col("_epochs") + more.cast("long"))


def _needed(docs: DataFrame, quality: Column | None, *more: Column) -> tuple[DataFrame, Column | None]:
    return docs.select(*more, "doc_id", "source", "text", (F.lit(None) if quality is None else quality).cast("double").alias("_given")), None if quality is None else F.col("_given")


def mix(docs: DataFrame, weights: tuple[float, ...] = (3, 1, 2), share: float = 1.5, cap: float = 2.0, seed: int = 20240501, quality: Column | None = None) -> DataFrame:
    """doc_id, size, source_size, target, taken, epochs, source, for each row of docs (doc_id, text, source).

    A source's target buys whole passes over it first; what is left buys documents in order of exponential keys
    -ln(u) / quality until their sizes sum to it: the document that crosses the line is taken if its middle lies below.
    u is hashed from doc_id, text and, among interchangeable rows, a rank, so rows that share a doc_id have fates of their
    own. Null text has size 0; null source is a source; null doc_ids are kept; an empty table gives an empty table; other
    columns, whatever their names, are ignored.

    Nothing sorts or gathers a source: _lines() narrows the range of keys that holds the line by sums.
    """
    rows, given = _needed(docs, quality)
    narrow, _ = _narrow(rows, given, seed)
    out = _decided(narrow, *_lines(narrow, weights, share, cap))
    return out.select(F.col("_id").alias("doc_id"), F.col("_size").alias("size"), F.col("_ssize").alias("source_size"), F.col("_target").alias("target"), (F.col("_size") * F.col("_times")).alias("taken"), F.col("_times").alias("epochs"), F.col("_src").alias("source"))


def _ranked(rows: DataFrame, same: DataFrame, small: int) -> DataFrame:
    """rows with _rank: 1, or among interchangeable rows (`same`) their number. Those are numbered within the part of the
    table they stand in, and parts by prefix sums, so no group is gathered in one task."""
    n_same = same.count()
    if not n_same:
        return rows.withColumn("_rank", F.lit(1).cast("long"))
    names = same.select(*(F.col(c).alias(f"{c}_") for c in SAME))
    match = rows["_id"].eqNullSafe(names["_id_"])
    for c in SAME[1:]:
        match &= rows[c].eqNullSafe(names[f"{c}_"])
    alone = join_small(rows, names, match, "left_anti", n_same, small).withColumn("_rank", F.lit(1).cast("long"))
    more = store(join_small(rows, names, match, "left_semi", n_same, small).withColumn("_part", F.spark_partition_id()), "same-rows")
    counts = more.groupBy(*SAME, "_part").agg(F.count("*").alias("_m"))
    before = F.coalesce(F.sum("_m").over(Window.partitionBy(*SAME).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = store(counts.select(*(F.col(c).alias(f"{c}_") for c in SAME), F.col("_part").alias("_part_"), before.alias("_start")), "same-parts")
    within = more.withColumn("_k", F.row_number().over(Window.partitionBy(*SAME, "_part").orderBy(F.lit(0))))
    match = F.col("_part") == F.col("_part_")
    for c in SAME:
        match &= F.col(c).eqNullSafe(F.col(f"{c}_"))
    numbered = join_small(within, starts, match, "inner", starts.count(), small).withColumn("_rank", (F.col("_start") + F.col("_k")).cast("long"))
    return alone.unionByName(numbered.select(*alone.columns))


def mixed_documents(docs: DataFrame, weights: tuple[float, ...] = (3, 1, 2), share: float = 1.5, cap: float = 2.0, seed: int = 20240501, quality: Column | None = None, small: int = 1_000_000) -> DataFrame:
    """The rows of docs, all columns, each as often as mix() takes it. Texts aren't shuffled, but for interchangeable
    rows: each row decides by its source's line. Nulls, repeated rows and empty tables as in mix()."""
    whole, given = _needed(docs, quality, F.struct(*docs.columns).alias("_row"))
    narrow, same = _narrow(whole, given, seed)
    rows = _keyed(_ranked(_described(whole, given), same, small), seed)
    out = _decided(rows, *_lines(narrow, weights, share, cap)).filter("_times > 0")
    return out.select("_row", F.explode(F.array_repeat(F.lit(1), F.col("_times").cast("int"))).alias("_copy")).select("_row.*")

"""Exact joins: dot products over pairs, brute force, weighted prefix bounds and the positional set join."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from operator import and_

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from simweave.functions.columns import binary_cosine, jaccard
from simweave.operators.blocks import block_set_join
from simweave.operators.candidates import all_pairs, in_blocks, sharing_pairs
from simweave.operators.copies import copies_of, nonempty
from simweave.operators.tiles import Plan, crowded, packed_vectors, tile_join, tile_rows
from simweave.plans.staging import stage

DIGITS = 9


def _above(t: float, closed: bool = True) -> Column:
    """Threshold test on values rounded to 9 digits, so that both ends of a tie fall alike in every engine."""
    s = F.round("similarity", DIGITS)
    return s >= F.lit(t) if closed else s > F.lit(t)


def dot_join(pairs: DataFrame, vectors: DataFrame) -> DataFrame:
    """id_a, id_b and similarity (dot product of unit vectors) of each pair; 0 without a common feature.

    Vectors are packed once, sorted by a hash of the feature; a pair is one merge, so no row a common feature is ever shuffled.
    """
    packed = vectors.groupBy("id").agg(F.array_sort(F.collect_list(F.struct(F.xxhash64("feature").alias("f"), F.col("weight").alias("w")))).alias("v"))
    packed = packed.select("id", F.col("v.f").alias("f"), F.col("v.w").alias("w"))
    a = packed.select(F.col("id").alias("id_a"), F.col("f").alias("fa"), F.col("w").alias("wa"))
    b = packed.select(F.col("id").alias("id_b"), F.col("f").alias("fb"), F.col("w").alias("wb"))

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = [batch.column(k) for k in range(2, 6)]
            ends = [x.offsets.to_numpy() for x in lists]
            fa, wa, fb, wb = (x.values.to_numpy(zero_copy_only=False) for x in lists)
            out = np.zeros(batch.num_rows)
            for k in range(batch.num_rows):
                x, y = fa[ends[0][k] : ends[0][k + 1]], fb[ends[2][k] : ends[2][k + 1]]
                if len(x) and len(y):
                    at = np.minimum(np.searchsorted(y, x), len(y) - 1)
                    hit = np.flatnonzero(y[at] == x)
                    out[k] = wa[ends[1][k] : ends[1][k + 1]][hit] @ wb[ends[3][k] : ends[3][k + 1]][at[hit]]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out)], ["id_a", "id_b", "similarity"])

    both = pairs.select("id_a", "id_b").join(a, "id_a", "left").join(b, "id_b", "left")
    none = F.array().cast("array<long>"), F.array().cast("array<double>")
    filled = both.select("id_a", "id_b", *(F.coalesce(c, none[c[0] == "w"]).alias(c) for c in ("fa", "wa", "fb", "wb")))
    return filled.mapInArrow(merge, "id_a long, id_b long, similarity double")


def set_similarity(pairs: DataFrame, sets: DataFrame, measure: str) -> DataFrame:
    """id_a, id_b and similarity of each pair of sets; only sets that occur in a pair are moved."""
    a = sets.select(F.col("id").alias("id_a"), F.col("features").alias("fa"))
    b = sets.select(F.col("id").alias("id_b"), F.col("features").alias("fb"))
    of = jaccard if measure == "jaccard" else binary_cosine
    return pairs.join(a, "id_a").join(b, "id_b").select("id_a", "id_b", of(F.col("fa"), F.col("fb")).alias("similarity"))


def exact_similarity(pairs: DataFrame, objects: DataFrame, measure: str) -> DataFrame:
    """Similarity of each pair: sets for 'jaccard' and 'cosine_binary', weighted long form for 'cosine'."""
    return dot_join(pairs, objects) if measure == "cosine" else set_similarity(pairs, objects, measure)


def verify_all_exact(pairs: DataFrame, objects: DataFrame, t: float, measure: str, closed: bool = True) -> DataFrame:
    """The pairs at or over t (strictly over it unless closed), with their similarity."""
    return exact_similarity(pairs, objects, measure).where(_above(t, closed))


def brute_force_join(objects: DataFrame, t: float, measure: str) -> DataFrame:
    """Truth: every pair with a common feature is compared."""
    if measure == "cosine":
        a = objects.select(F.col("id").alias("id_a"), "feature", F.col("weight").alias("wa"))
        b = objects.select(F.col("id").alias("id_b"), "feature", F.col("weight").alias("wb"))
        dots = a.join(b, "feature").where("id_a < id_b").groupBy("id_a", "id_b").agg(F.sum(F.col("wa") * F.col("wb")).alias("similarity"))
        return dots.where(_above(t))
    rows = objects.select("id", F.explode("features").alias("feature"))
    sizes = objects.select("id", F.size("features").alias("n"))
    shared = rows.select(F.col("id").alias("id_a"), "feature").join(rows.select(F.col("id").alias("id_b"), "feature"), "feature").where("id_a < id_b")
    shared = shared.groupBy("id_a", "id_b").agg(F.count(F.lit(1)).alias("i"))
    na, nb = sizes.select(F.col("id").alias("id_a"), F.col("n").alias("na")), sizes.select(F.col("id").alias("id_b"), F.col("n").alias("nb"))
    value = F.col("i") / (F.col("na") + F.col("nb") - F.col("i")) if measure == "jaccard" else F.col("i") / F.sqrt(F.col("na").cast("double") * F.col("nb"))
    return shared.join(na, "id_a").join(nb, "id_b").select("id_a", "id_b", value.alias("similarity")).where(_above(t))


def all_pairs_join(objects: DataFrame, t: float, measure: str) -> DataFrame:
    """Truth by comparing all pairs of a small collection."""
    return verify_all_exact(all_pairs(objects), objects, t, measure)


def weighted_prefix(vectors: DataFrame, t: float, bound: str = "both", order: str = "rare_first") -> DataFrame:
    """id, feature, weight and tail of each vector's prefix: what is left of it cannot reach t with any vector.

    Features are ordered once for all vectors. From the last feature backwards, the rest of a vector is bounded by its length
    ('l2'), by its weights times the largest weight of each feature ('maxweight'), or by the smaller ('both'). tail is the length
    of what comes after the feature.
    """
    stats = vectors.groupBy("feature").agg(F.count(F.lit(1)).alias("df"), F.max("weight").alias("maxw"))
    ranked = [F.col("df").desc(), F.col("feature").desc()] if order == "rare_first" else [F.col("feature").desc()]
    last = Window.partitionBy("id").orderBy(*ranked).rowsBetween(Window.unboundedPreceding, 0)
    rest = vectors.join(stats, "feature").withColumn("l2", F.sqrt(F.sum(F.col("weight") * F.col("weight")).over(last))).withColumn("mw", F.sum(F.col("weight") * F.col("maxw")).over(last))
    residual = {"l2": F.col("l2"), "maxweight": F.col("mw"), "both": F.least("l2", "mw")}[bound]
    tail = F.sqrt(F.greatest(F.col("l2") * F.col("l2") - F.col("weight") * F.col("weight"), F.lit(0.0)))
    return rest.where(residual >= t - 1e-9).select("id", "feature", "weight", tail.alias("tail"))


def prefix_candidates(vectors: DataFrame, t: float, bound: str = "both", order: str = "rare_first", upper_bound_check: bool = False, max_bucket: int | None = None) -> DataFrame:
    """Pairs whose prefixes share a feature: complete for cosine >= t.

    With upper_bound_check, the weights' product at a shared feature plus the product of the lengths of both tails must reach t: that
    holds at the first feature that a pair at t shares, as its dot product is no more. The test is part of the join condition.
    """
    prefix = weighted_prefix(vectors, t, bound, order)
    if not upper_bound_check:
        return sharing_pairs(prefix, max_bucket)
    left, right, on = in_blocks(prefix, ["feature"], max_bucket)
    a = left.select(*on, *(F.col(c).alias(c + "_a") for c in ("id", "weight", "tail")))
    b = right.select(*on, *(F.col(c).alias(c + "_b") for c in ("id", "weight", "tail")))
    most = F.col("weight_a") * F.col("weight_b") + F.col("tail_a") * F.col("tail_b")
    met = reduce(and_, (a[c] == b[c] for c in on)) & (F.col("id_a") < F.col("id_b")) & (most >= t - 1e-9)
    return a.join(b, met).select("id_a", "id_b").distinct()


def exact_weighted_join(vectors: DataFrame, t: float, bound: str = "both", order: str = "rare_first", upper_bound_check: bool = False, max_bucket: int | None = None) -> DataFrame:
    """All pairs with cosine at or over t, by weighted prefixes; equal vectors are joined once. Where prefixes share features so often that
    most pairs are candidates, these are found and verified tile by tile, without a row a candidate."""
    copies = copies_of(vectors)
    own = copies.reps if copies else vectors
    if upper_bound_check or max_bucket:
        pairs = prefix_candidates(own, t, bound, order, upper_bound_check, max_bucket)
    else:
        prefix = stage(weighted_prefix(own, t, bound, order).select("id", "feature"), "prefixes")
        if crowded(prefix, prefix.select("id").distinct().count()):
            keys = prefix.groupBy("id").agg(F.collect_list(F.xxhash64("feature")).alias("keys"))
            return tile_join(tile_rows(packed_vectors(own).join(keys, "id"), copies), Plan(dot=t)).where(_above(t))
        pairs = sharing_pairs(prefix)
    found = verify_all_exact(pairs.unionByName(nonempty(copies)) if copies else pairs, own, t, "cosine")
    return copies.expanded(found) if copies else found


def _need(na: Column, nb: Column, t: float, measure: str) -> Column:
    """Fewest common features of two sets at t; a hair lower, so that rounding loses no pair."""
    need = (na + nb) * (t / (1 + t)) if measure == "jaccard" else F.sqrt(na.cast("double") * nb) * t
    return F.ceil(need - 1e-9)


#: Parts of the token order that the suffix filter compares.
SUFFIX_PARTS = 8


def set_prefix_candidates(sets: DataFrame, t: float, measure: str = "jaccard", positional: bool = True, suffix: bool = False, max_bucket: int | None = None) -> DataFrame:
    """Pairs of sets that can reach t: prefixes in rare-first order share a token, sizes are close, enough tokens are left after
    the shared one on both sides (positional), and enough can be common in each part of what is left (suffix).

    The suffix filter parts the token order at fixed places, the same for all sets, and bounds the overlap of two suffixes by the
    smaller number of tokens in each part.
    """
    rows = sets.select("id", F.size("features").alias("n"), F.explode("features").alias("token"))
    df = rows.groupBy("token").agg(F.count(F.lit(1)).alias("df"))
    place = Window.partitionBy("id").orderBy("df", "token")
    rows = rows.join(df, "token").withColumn("pos", F.row_number().over(place))
    keep = t if measure == "jaccard" else t * t
    extra = []
    if suffix:
        # a token's part: by its frequency, and by a hash among tokens that are equally rare
        key = F.col("df") + F.pmod(F.xxhash64("token"), F.lit(1 << 20)) / F.lit(1 << 20)
        cuts = rows.agg(F.percentile_approx(key, [k / SUFFIX_PARTS for k in range(1, SUFFIX_PARTS)], 1000)).first()[0] or []
        part = sum(((key > c).cast("int") for c in cuts), F.lit(0))
        after = Window.partitionBy("id").orderBy(F.col("df").desc(), F.col("token").desc()).rowsBetween(Window.unboundedPreceding, -1)
        rows = rows.withColumn("part", part)
        rows = rows.select("id", "n", "token", "pos", F.array(*(F.coalesce(F.count_if(F.col("part") == k).over(after), F.lit(0)) for k in range(len(cuts) + 1))).alias("rest"))
        extra = ["rest"]
    prefix = rows.where(F.col("pos") <= F.col("n") - F.ceil(F.col("n") * keep - 1e-9) + 1).select("id", "n", "pos", "token", *extra)
    left, right, on = in_blocks(prefix, ["token"], max_bucket)
    names = ["id", "n", "pos", *extra]
    a = left.select(*on, *(F.col(c).alias(c + "_a") for c in names))
    b = right.select(*on, *(F.col(c).alias(c + "_b") for c in names))
    na, nb = F.col("n_a"), F.col("n_b")
    test = (F.col("id_a") < F.col("id_b")) & (F.least(na, nb) >= F.ceil(F.greatest(na, nb) * keep - 1e-9))
    before = F.least(F.col("pos_a"), F.col("pos_b"))
    if positional:
        test &= before + F.least(na - F.col("pos_a"), nb - F.col("pos_b")) >= _need(na, nb, t, measure)
    if suffix:
        common = F.aggregate(F.zip_with("rest_a", "rest_b", lambda x, y: F.least(x, y)), F.lit(0).cast("long"), lambda s, x: s + x)
        test &= before + common >= _need(na, nb, t, measure)
    return a.join(b, reduce(and_, (a[c] == b[c] for c in on)) & test).select("id_a", "id_b").distinct()


def exact_set_join(sets: DataFrame, t: float, measure: str = "jaccard", suffix: bool = False) -> DataFrame:
    """All pairs of sets at or over t, by the positional prefix filter; with suffix, what is left of both sets is compared in parts
    (parities of tokens, blocks.py) before any pair is verified, distinct sets are joined once, and no pair is shuffled."""
    if not suffix:
        return verify_all_exact(set_prefix_candidates(sets, t, measure, True), sets, t, measure)
    copies = copies_of(sets)
    found = block_set_join(copies.reps if copies else sets, t, measure).where(_above(t))
    return copies.expanded(found.unionByName(nonempty(copies).withColumn("similarity", F.lit(1.0)))) if copies else found

"""Candidate pairs: banded signatures, shared features, all pairs, other collections."""

from __future__ import annotations

from math import ceil, log

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from simweave.functions.posterior import cosine_to_angular
from simweave.plans.staging import broadcast_if_small, stage


def num_bands(t: float, w: int, fn: float = 0.03, measure: str = "jaccard") -> int:
    """Bands of w hashes that miss a pair at t with probability fn at most."""
    p = t if measure == "jaccard" else cosine_to_angular(t)
    return ceil(log(fn) / log(1 - p**w))


def band_keys(w: int, n_bands: int, packed: bool, first: int = 0) -> Column:
    """Array of one key a band: w bits (32 at most) as they are, or a 64-bit hash of w integers."""
    sig = F.col("sig")
    if packed:
        if not 1 <= w <= 32:
            raise ValueError("a band has 1 to 32 bits")

        def bits(b: Column) -> Column:
            word, shift = F.floor(b * w / 32).cast("int"), (b * w % 32).cast("int")
            both = F.get(sig, word).bitwiseOR(F.call_function("shiftleft", F.coalesce(F.get(sig, word + 1), F.lit(0).cast("long")), F.lit(32)))
            return F.call_function("shiftrightunsigned", both, shift).bitwiseAND(F.lit((1 << w) - 1))

        return F.transform(F.sequence(F.lit(first), F.lit(first + n_bands - 1)), bits)
    return F.transform(F.sequence(F.lit(first), F.lit(first + n_bands - 1)), lambda b: F.xxhash64(F.slice(sig, (b * w + 1).cast("int"), w)))


def in_blocks(rows: DataFrame, on: list[str], max_bucket: int | None) -> tuple[DataFrame, DataFrame, list[str]]:
    """Both sides of a self join on the columns on, and the columns to join on: groups of more than max_bucket rows are cut into
    blocks, every pair of blocks is a group of its own, and no pair of rows is lost."""
    if not max_bucket:
        return rows, rows, on
    sizes = rows.groupBy(*on).agg(F.ceil(F.count(F.lit(1)) / max_bucket).cast("int").alias("blocks")).where("blocks > 1")
    placed = rows.join(broadcast_if_small(stage(sizes, "large-buckets"), 24), on, "left").withColumn("blocks", F.coalesce("blocks", F.lit(1)))
    placed = placed.withColumn("own", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    left = placed.withColumn("block_b", every).withColumnRenamed("own", "block_a").drop("blocks")
    right = placed.withColumn("block_a", every).withColumnRenamed("own", "block_b").drop("blocks")
    return left, right, [*on, "block_a", "block_b"]


def banded(sigs: DataFrame, w: int, n_bands: int, packed: bool, dedupe: str = "distinct", max_bucket: int | None = None) -> DataFrame:
    """id_a < id_b of every pair that shares a band.

    dedupe 'distinct' removes repeats by a shuffle; 'first_band' keeps a pair at its first shared band only, which needs the keys of
    both sides beside the rows but no further shuffle. max_bucket cuts larger buckets into blocks that meet pairwise; no pair is lost.
    """
    keys = sigs.select("id", band_keys(w, n_bands, packed).alias("keys"))
    extra = ["keys"] if dedupe == "first_band" else []
    rows = keys.select("id", *extra, F.posexplode("keys").alias("band", "key"))
    left, right, on = in_blocks(rows, ["band", "key"], max_bucket)
    a, b = left.withColumnRenamed("id", "id_a"), right.withColumnRenamed("id", "id_b")
    if dedupe == "first_band":
        a, b = a.withColumnRenamed("keys", "keys_a"), b.withColumnRenamed("keys", "keys_b")
        met = a.join(b, on).where("id_a < id_b")
        earlier = F.exists(F.zip_with(F.slice("keys_a", 1, F.col("band")), F.slice("keys_b", 1, F.col("band")), lambda x, y: x == y), lambda x: x)
        return met.where((F.col("band") == 0) | ~earlier).select("id_a", "id_b")
    return a.join(b, on).where("id_a < id_b").select("id_a", "id_b").distinct()


def bucket_report(sigs: DataFrame, w: int, n_bands: int, packed: bool) -> DataFrame:
    """Buckets by size: size, buckets, pairs (each bucket's pairs, repeats included)."""
    rows = sigs.select(F.posexplode(band_keys(w, n_bands, packed)).alias("band", "key"))
    sizes = rows.groupBy("band", "key").agg(F.count(F.lit(1)).alias("size"))
    return sizes.groupBy("size").agg(F.count(F.lit(1)).alias("buckets"), F.sum(F.col("size") * (F.col("size") - 1) / 2).cast("long").alias("pairs"))


def sharing_pairs(vectors: DataFrame, max_bucket: int | None = None) -> DataFrame:
    """Pairs with a common feature (long form), by the inverted index; max_bucket cuts the lists of common features into blocks."""
    left, right, on = in_blocks(vectors.select("id", "feature"), ["feature"], max_bucket)
    met = left.withColumnRenamed("id", "id_a").join(right.withColumnRenamed("id", "id_b"), on)
    return met.where("id_a < id_b").select("id_a", "id_b").distinct()


def all_pairs(objects: DataFrame) -> DataFrame:
    """Every pair of a small collection: ground truth for tests, quadratic by definition."""
    ids = objects.select("id").distinct()
    return ids.select(F.col("id").alias("id_a")).join(ids.select(F.col("id").alias("id_b")), F.col("id_a") < F.col("id_b"))


def cross_banded(sigs_a: DataFrame, sigs_b: DataFrame, w: int, n_bands: int, packed: bool) -> DataFrame:
    """id_a of one collection and id_b of another that share a band."""
    rows = [s.select(F.col("id").alias(n), F.posexplode(band_keys(w, n_bands, packed)).alias("band", "key")) for s, n in ((sigs_a, "id_a"), (sigs_b, "id_b"))]
    return rows[0].join(rows[1], ["band", "key"]).select("id_a", "id_b").distinct()


def collapse_duplicates(objects: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Objects with distinct contents (the smallest id stands for its copies), and id to rep of every object.

    objects: sets (id, features) or vectors in long form. Copies are the main cause of quadratic buckets; a join runs on the
    representatives, and members expand its classes.
    """
    if "features" in objects.columns:
        keyed = objects.select("id", F.sha2(F.concat_ws(",", F.col("features").cast("array<string>")), 256).alias("h"))
    else:
        packed = objects.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("feature", "weight"))).alias("v"))
        keyed = packed.select("id", F.sha2(F.to_json("v"), 256).alias("h"))
    members = keyed.join(keyed.groupBy("h").agg(F.min("id").alias("rep")), "h").select("id", "rep")
    return objects.join(members.where("id = rep").select("id"), "id", "left_semi"), members

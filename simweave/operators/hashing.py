"""Hash families and signatures: minwise hashes of sets, sign bits of gaussian projections, packed words.

The parity family uses only integer arithmetic that other engines reproduce; the wide and table families are the
faster choice for large vocabularies. Kernels are Arrow batches of NumPy; no family shuffles.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache
from statistics import NormalDist

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from simweave.functions.columns import CODES_PER_UNIT, LIMIT, PRIME, feature_id
from simweave.plans.staging import broadcast_if_small, stage

WEIGHT_SCALE = 1 << 20


def _draws(tag: str, seed: int, n: int, modulus: int, first: int = 0) -> np.ndarray:
    return np.array([int(hashlib.md5(f"{tag}{seed}:{j}".encode()).hexdigest()[:15], 16) % modulus for j in range(first, first + n)], np.uint64)


@lru_cache(maxsize=32)
def linear_family(tag: str, seed: int, lo: int, hi: int) -> tuple[np.ndarray, np.ndarray]:
    """Multipliers and offsets of hashes lo to hi: x -> (a x + b) mod PRIME."""
    return _draws(tag + "a", seed, hi - lo, PRIME - 1, lo) + np.uint64(1), _draws(tag + "b", seed, hi - lo, PRIME, lo)


def minhash_values(features: np.ndarray, lo: int, hi: int, seed: int, family: str) -> np.ndarray:
    """Hashes lo to hi of one set; PRIME (parity) or the largest long (wide) for an empty set."""
    x = features.astype(np.uint64)
    if not len(x):
        return np.full(hi - lo, PRIME if family == "parity" else 2**63 - 1, np.int64)
    out = np.empty(hi - lo, np.int64)
    with np.errstate(over="ignore"):
        for at in range(0, hi - lo, 64):
            end = min(at + 64, hi - lo)
            if family == "parity":
                a, b = linear_family("h", seed, lo, hi)
                h = (a[at:end, None] * x + b[at:end, None]) % np.uint64(PRIME)
            else:
                s = (np.arange(lo + at, lo + end, dtype=np.uint64) + np.uint64(seed * 1_000_003 + 1)) * np.uint64(0x9E3779B97F4A7C15)
                h = x ^ s[:, None]
                h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
                h = ((h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)) >> np.uint64(1)
            out[at:end] = h.min(1).astype(np.int64)
    return out


def minhash(sets: DataFrame, n_hashes: int, seed: int = 1, family: str = "parity", first: int = 0) -> DataFrame:
    """id and sig: n_hashes minwise hashes (long) of each set, from hash number first on."""

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sets_ = b.column(1)
            values, ends = sets_.values.to_numpy(zero_copy_only=False), sets_.offsets.to_numpy()
            sigs = [minhash_values(values[ends[k] : ends[k + 1]], first, first + n_hashes, seed, family) for k in range(b.num_rows)]
            flat = np.concatenate(sigs) if sigs else np.empty(0, np.int64)
            at = pa.array(np.arange(b.num_rows + 1, dtype=np.int32) * n_hashes)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(at, pa.array(flat))], ["id", "sig"])

    return sets.select("id", "features").mapInArrow(sign, "id long, sig array<long>")


@lru_cache(maxsize=1)
def quantile_codes() -> np.ndarray:
    """Codes of the 65,536 normal quantiles at mid-points: stored gaussians of two bytes."""
    normal = NormalDist()
    g = np.array([normal.inv_cdf((k + 0.5) / 65536) for k in range(65536)])
    return np.clip(np.floor((g + LIMIT) * CODES_PER_UNIT), 0, 2 * LIMIT * CODES_PER_UNIT - 1).astype(np.int64)


def gaussian_codes(ids: np.ndarray, lo: int, hi: int, seed: int, family: str = "parity") -> np.ndarray:
    """2-byte gaussian codes of features (31-bit ids) by hashes lo to hi, made on demand from the two numbers alone."""
    x = ids.astype(np.uint64)[None, :]
    a, b = linear_family("g", seed, lo, hi)
    u = (a[:, None] * x + b[:, None]) % np.uint64(PRIME)
    if family == "table":
        return quantile_codes()[(u >> np.uint64(15)).astype(np.int64)]
    a, b = linear_family("k", seed, lo, hi)
    v = (a[:, None] * x + b[:, None]) % np.uint64(PRIME)
    g = np.sqrt(-2.0 * np.log((u.astype(np.float64) + 1) / (PRIME + 1.0))) * np.cos(2 * np.pi * (v.astype(np.float64) / PRIME))
    return np.clip(np.floor((g + LIMIT) * CODES_PER_UNIT), 0, 2 * LIMIT * CODES_PER_UNIT - 1).astype(np.int64)


def pack_bits(bits: np.ndarray) -> np.ndarray:
    """Words of 32 bits in non-negative longs; hash i is bit i mod 32 of word i div 32."""
    n = -(-len(bits) // 32)
    padded = np.zeros(n * 32, np.int64)
    padded[: len(bits)] = bits
    return (padded.reshape(n, 32) << np.arange(32)).sum(1)


#: Vectors whose bits are made at once, entries of a table of gaussian codes, and entries of it for each entry of the vectors.
AT_ONCE, CODES, FILLED = 512, 1 << 19, 8


def _signs(x: np.ndarray, w: np.ndarray, ends: np.ndarray, n_hashes: int, seed: int, family: str, first: int) -> np.ndarray:
    """Packed signs of the projections of the vectors with entries ends[k] to ends[k + 1]. Gaussians are made once for each feature of some
    vectors; where these share most of their features, the sums are a product of matrices, in doubles as long as these are exact."""
    out = np.zeros((len(ends) - 1, -(-n_hashes // 32)), np.int64)
    for top in range(0, len(out), AT_ONCE):
        own = slice(ends[top], ends[min(top + AT_ONCE, len(out))])
        own_ends = ends[top : top + AT_ONCE + 1] - ends[top]
        n = len(own_ends) - 1
        names, at = np.unique(x[own], return_inverse=True)
        weight = w[own]
        owner = np.repeat(np.arange(n), np.diff(own_ends))
        largest = np.bincount(owner, weights=np.abs(weight), minlength=n).max() if n else 0
        dense = None
        if n * len(names) <= FILLED * len(weight) and largest * 2 * LIMIT * CODES_PER_UNIT < 1 << 52:
            dense = np.bincount(owner * len(names) + at, weights=weight, minlength=n * len(names)).reshape(n, len(names))
        per = max(32, min(n_hashes, CODES // max(1, len(names)) // 32 * 32))
        for lo in range(0, n_hashes, per):
            hi = min(lo + per, n_hashes)
            codes = 2 * gaussian_codes(names, first + lo, first + hi, seed, family) + 1 - 2 * LIMIT * CODES_PER_UNIT
            if dense is not None:
                bits = dense @ codes.T.astype(np.float64) >= 0
            else:
                bits = np.stack([codes[:, at[own_ends[k] : own_ends[k + 1]]] @ weight[own_ends[k] : own_ends[k + 1]] >= 0 for k in range(n)])
            padded = np.zeros((n, -(-(hi - lo) // 32) * 32), bool)
            padded[:, : hi - lo] = bits
            words = np.packbits(padded, axis=1, bitorder="little").view("<u4")
            out[top : top + n, lo // 32 : lo // 32 + words.shape[1]] = words
    return out


def sign_bits(vectors: DataFrame, n_hashes: int, seed: int = 1, family: str = "parity", first: int = 0) -> DataFrame:
    """id and sig: packed signs of n_hashes gaussian projections of each vector (id, feature string, weight).

    Weights and gaussians are integers in the sum, so a bit never depends on the order of a vector's features or on
    partitioning. One shuffle by id gathers the vector.
    """
    ids = F.struct(feature_id(F.col("feature")).alias("x"), F.floor(F.col("weight") * WEIGHT_SCALE + 0.5).cast("long").alias("w"))
    packed = vectors.groupBy("id").agg(F.collect_list(ids).alias("v"))

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            flat = b.column(1).values
            x, w = flat.field("x").to_numpy(zero_copy_only=False), flat.field("w").to_numpy(zero_copy_only=False)
            out = _signs(x, w, b.column(1).offsets.to_numpy().astype(np.int64), n_hashes, seed, family, first)
            at = pa.array(np.arange(b.num_rows + 1, dtype=np.int32) * out.shape[1])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(at, pa.array(out.ravel()))], ["id", "sig"])

    return packed.mapInArrow(sign, "id long, sig array<long>")


def gaussian_table(spark: SparkSession, features: DataFrame, n_hashes: int, seed: int = 1) -> DataFrame:
    """The stored form: feature, hash_no and 2-byte code, for the given features (column feature, string)."""

    def expand(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            codes = gaussian_codes(b.column(1).to_numpy(), 0, n_hashes, seed)
            names = b.column(0).take(pa.array(np.tile(np.arange(b.num_rows), n_hashes)))
            yield pa.RecordBatch.from_arrays([names, pa.array(np.repeat(np.arange(n_hashes), b.num_rows)), pa.array(codes.ravel())], ["feature", "hash_no", "code"])

    return features.select("feature", feature_id(F.col("feature")).alias("x")).distinct().mapInArrow(expand, "feature string, hash_no long, code long")


def extend_signatures(objects: DataFrame, alive: DataFrame, lo: int, hi: int, measure: str, seed: int = 1, family: str = "parity") -> DataFrame:
    """Hashes lo to hi for the objects in alive (column id) only."""
    left = objects.join(alive.select("id").distinct(), "id", "left_semi")
    make = minhash if measure == "jaccard" else sign_bits
    return make(left, hi - lo, seed, family, lo)


class HashSource:
    """Parts of signatures: the first made hashes come from a table, further ones are made when they are asked for, and only for
    objects that are still in a pair. Hash 0 of a part is hash first of the family."""

    def __init__(self, sigs: DataFrame, made: int | None = None, objects: DataFrame | None = None, measure: str = "jaccard", seed: int = 1, family: str = "parity", first: int = 0):
        self.sigs, self.made, self.first = sigs, None if made is None else made - first, first
        self.objects, self.measure, self.seed, self.family = objects, measure, seed, family

    def part(self, lo: int, hi: int, pairs: DataFrame, packed: bool) -> DataFrame:
        """id and part (hashes lo to hi) of the objects in pairs; integers are cut to 4 bytes."""
        lo, hi = lo + self.first, hi + self.first
        if self.made is None or hi <= self.made + self.first:
            part = F.slice("sig", lo // 32 + 1, (hi - lo) // 32) if packed else F.slice("sig", lo + 1, hi - lo)
            out = self.sigs.select("id", part.alias("part"))
        else:
            alive = stage(pairs.select(F.explode(F.array("id_a", "id_b")).alias("id")).distinct(), "alive")
            own = self.objects.join(broadcast_if_small(alive, 8), "id", "left_semi")
            make = minhash if self.measure == "jaccard" else sign_bits
            out = stage(make(own, hi - lo, self.seed, self.family, lo), "more-hashes").withColumnRenamed("sig", "part")
        return out if packed else out.select("id", F.transform("part", lambda x: x.bitwiseAND(F.lit(0x7FFFFFFF)).cast("int")).alias("part"))


def signatures(objects: DataFrame, measure: str, n_hashes: int, seed: int = 1, family: str = "parity") -> DataFrame:
    """Signatures for a measure: minwise hashes for 'jaccard', packed sign bits for 'cosine' and 'cosine_binary'.

    Empty sets are similar to nothing and get no signature.
    """
    return minhash(objects.where(F.size("features") > 0), n_hashes, seed, family) if measure == "jaccard" else sign_bits(objects, n_hashes, seed, family)

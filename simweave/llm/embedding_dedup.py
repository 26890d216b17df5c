"""Near-duplicate embeddings by Euclidean p-stable hashing.

Unit vectors are projected on random gaussian directions, shifted and quantised; tables of such quantised projections are
buckets. Buckets propose pairs by stars around their smallest member, cosines are checked in double precision, and the
links of every class found are then counted block by block with matrix products, so pairs never become rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import ceil, exp, log, pi, sqrt
from statistics import NormalDist

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from simweave.operators.components import connected_components
from simweave.plans.staging import broadcast_if_small, stage

COSINE = 0.93
#: Quantisation width, and the chance that a pair at the threshold meets in no table. At cosine 0.93 (distance 0.374) one projection
#: agrees with probability 0.851, for orthogonal vectors (distance 1.414) with 0.486.
WIDTH, MISSED = 2.0, 1e-6
#: Cost of a bucket entry, which is shuffled, in tests of a pair that meets by chance.
ENTRY_COST = 1
#: Of 128 sign bits, the most that may differ at cosine 0.93 (expected 15.3, 6 deviations higher).
MOST_DIFFERENT = 38
#: Vectors of a class that one task multiplies with as many others, and members of a bucket that meet in one task.
BLOCK, BUCKET = 4096, 2048


def agreement(distance: float, width: float = WIDTH) -> float:
    """Chance that one quantised projection agrees on two points at this Euclidean distance."""
    r = width / distance
    return 1 - 2 * NormalDist().cdf(-r) - 2 / (sqrt(2 * pi) * r) * (1 - exp(-r * r / 2))


def choose_tables(n: int, cosine: float = COSINE, width: float = WIDTH, missed: float = MISSED) -> tuple[int, int]:
    """Tables, and projections of each, for n vectors of the largest label: the cheapest that miss a pair at the threshold with a
    chance of missed. More vectors want more projections, so that a vector meets few others by chance."""
    near, far = agreement(sqrt(2 - 2 * cosine), width), agreement(sqrt(2), width)
    best = None
    for k in range(8, 33):
        tables = ceil(log(missed) / log(1 - near**k))
        cost = tables * (ENTRY_COST + n * far**k)
        if best is None or cost < best[0]:
            best = (cost, tables, k)
    return best[1:]


class Projector:
    """Bucket keys and sign sketches of unit vectors; directions depend on the seed and the dimension alone."""

    def __init__(self, seed: int, tables: int, projections: int, width: float):
        self.seed, self.tables, self.projections, self.width = seed, tables, projections, width
        self.known: dict[int, tuple] = {}

    def __call__(self, units: np.ndarray, labels: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        dim = units.shape[1]
        if dim not in self.known:
            rng = np.random.default_rng([self.seed, dim])
            n = self.tables * self.projections
            self.known[dim] = (
                rng.standard_normal((dim, n)), rng.uniform(0, self.width, n), rng.integers(1, 2**62, self.projections).astype(np.int64) | 1,
                rng.integers(0, 2**62, self.tables).astype(np.int64), rng.standard_normal((dim, 128)),
            )
        a, b, mult, salt, signs = self.known[dim]
        cells = np.floor((units @ a + b) / self.width).astype(np.int64).reshape(len(units), self.tables, self.projections)
        with np.errstate(over="ignore"):
            keys = (cells * mult).sum(2) + salt + (labels[:, None] * 1_000_003 + dim) * np.int64(0x5851F42D4C957F2D)
            x = keys.view(np.uint64)
            x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
            x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
            keys = (x ^ (x >> np.uint64(31))).view(np.int64)
        sketch = np.packbits(units @ signs >= 0, axis=1).view(np.int64)
        return keys, sketch


SIGNED = "row long, vec_id long, label long, fp_a long, fp_b long, sketch_a long, sketch_b long, unit array<double>, keys array<long>"


def sign_vectors(vectors: DataFrame, seed: int, tables: int, projections: int, width: float) -> DataFrame:
    """Unit vector, fingerprint, sketch and bucket keys; unit is null for vectors that link with nothing."""

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        project = Projector(seed, tables, projections, width)
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                part = batch.slice(lo, 1000)
                rows_, ids, labels, raw = (part.column(k) for k in range(4))
                n = part.num_rows
                units: list = [None] * n
                fps, keys, sketches = np.zeros((n, 2), np.int64), [None] * n, np.zeros((n, 2), np.int64)
                by_dim: dict[int, list[int]] = {}
                for i, v in enumerate(raw):
                    if not v.is_valid or not labels[i].is_valid or v.values.null_count or not len(v.values):
                        continue
                    x = np.asarray(v.values.to_numpy(zero_copy_only=False), np.float64)
                    scale = np.abs(x).max()
                    if not np.isfinite(scale) or scale == 0:
                        continue
                    fps[i] = np.frombuffer(xxhash.xxh3_128_digest(x.tobytes()), np.int64)
                    x = x / scale
                    units[i] = x / np.sqrt(x @ x)
                    by_dim.setdefault(len(x), []).append(i)
                for rows in by_dim.values():
                    k, s = project(np.array([units[i] for i in rows]), np.array([labels[i].as_py() for i in rows], np.int64))
                    for i, own, sk in zip(rows, k, s, strict=True):
                        keys[i], sketches[i] = own, sk
                yield pa.RecordBatch.from_arrays(
                    [rows_, ids, labels, *map(pa.array, (fps[:, 0], fps[:, 1], sketches[:, 0], sketches[:, 1])), pa.array(units, pa.list_(pa.float64())), pa.array(keys, pa.list_(pa.int64()))],
                    [x.split()[0] for x in SIGNED.split(", ")],
                )

    return vectors.mapInArrow(sign, SIGNED)


def _cosines(pairs: DataFrame, units: DataFrame, cosine: float) -> DataFrame:
    """The pairs (a, b; staged) with a cosine of at least cosine, in double precision."""

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            dots = [float(np.dot(u.values.to_numpy(), v.values.to_numpy())) if len(u.values) == len(v.values) else -1.0 for u, v in zip(b.column(2), b.column(3), strict=True)]
            yield b.select(["a", "b"]).filter(pa.array(np.array(dots) >= cosine, pa.bool_()))

    both = pairs.join(units.select(F.col("id").alias("b"), F.col("unit").alias("vb")), "b").join(units.select(F.col("id").alias("a"), F.col("unit").alias("va")), "a")
    return both.select("a", "b", "va", "vb").mapInArrow(check, "a long, b long")


def _close() -> Column:
    return F.bit_count(F.col("pa").bitwiseXOR(F.col("pb"))) + F.bit_count(F.col("qa").bitwiseXOR(F.col("qb"))) <= MOST_DIFFERENT


def _side(facts: DataFrame, side: str, *more) -> DataFrame:
    return facts.select(F.col("id").alias(side), F.col("sketch_a").alias(f"p{side}"), F.col("sketch_b").alias(f"q{side}"), *more)


def link_embeddings(
    vectors: DataFrame, id_col="vec_id", vector_col="embedding", label_col="label", cosine: float = COSINE,
    tables: int | None = None, projections: int | None = None, width: float = WIDTH, seed: int = 7,
) -> DataFrame:
    """vec_id, n_links, component_id and kept of every vector; links join vectors of one label with enough cosine.

    Vectors that are null, empty, zero or hold null or non-finite components, and those without label, link with nothing.
    Equal vectors are one entry with a weight, so copies are never paired. Rows that repeat an id are vectors of their own, each
    with its own links and class; a class is named by its smallest id. Rows with a null id are left out. An empty table gives an
    empty result; other columns are not read. Tables and projections are chosen by the largest label's size unless given.
    """
    slim = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(label_col).cast("long").alias("label"), F.col(vector_col).cast("array<double>").alias("v")).where("vec_id is not null")
    if tables is None or projections is None:
        largest = slim.where("label is not null").groupBy("label").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0]
        tables, projections = choose_tables(largest or 1, cosine, width)
    numbered = slim.select(F.monotonically_increasing_id().alias("row"), "vec_id", "label", "v")
    signed = stage(sign_vectors(numbered, seed, tables, projections, width), "vectors")
    valid = signed.where("unit is not null")
    groups = valid.groupBy("label", "fp_a", "fp_b").agg(F.min("row").alias("id"), F.min("vec_id").alias("least"), F.count(F.lit(1)).alias("weight"))
    groups = stage(groups, "vector-groups")
    firsts = valid.join(broadcast_if_small(groups.select("id", "weight"), 16), F.col("row") == F.col("id"))
    facts = stage(firsts.select("id", "weight", "sketch_a", "sketch_b", "unit", "keys"), "vector-facts")
    entries = facts.select("id", "sketch_a", "sketch_b", F.explode("keys").alias("key"))
    heads = entries.groupBy("key").agg(F.min("id").alias("head"), F.count(F.lit(1)).alias("n")).where("n > 1").select("key", "head")
    crowded = stage(entries.join(heads, "key"), "vector-buckets")
    sketches = facts.select("id", "sketch_a", "sketch_b")
    stars = crowded.where("id <> head").select(F.col("head").alias("a"), F.col("id").alias("b")).distinct()
    stars = stage(stars.join(_side(sketches, "b"), "b").join(_side(sketches, "a"), "a").where(_close()).select("a", "b"), "vector-stars")
    units = facts.select("id", "unit")
    links = stage(_cosines(stars, units, cosine), "vector-links")
    parts = stage(connected_components(links), "vector-parts")
    members = crowded.join(broadcast_if_small(parts, 16), F.col("id") == F.col("node"), "left").withColumn("c", F.coalesce("component", "id")).drop("node", "component")
    members = stage(members, "vector-members")
    mixed = members.groupBy("key").agg(F.min("c").alias("lo"), F.max("c").alias("hi"), F.max(F.when(F.col("id") == F.col("head"), F.col("c"))).alias("main"), F.count(F.lit(1)).alias("m"))
    mixed = stage(mixed.where("lo <> hi").select("key", "main", F.ceil(F.col("m") / BUCKET).cast("int").alias("blocks")), "vector-mixed")
    inside = stage(members.join(broadcast_if_small(mixed, 24), "key").drop("head"), "vector-inside")
    rest = stage(_apart(inside).distinct(), "vector-rest")
    links = links.unionByName(_cosines(rest, units, cosine))
    classes = stage(connected_components(links), "vector-classes")
    counts = _count_links(facts, classes, cosine)
    named = classes.join(broadcast_if_small(groups.select("id", "least"), 16), F.col("node") == F.col("id")).groupBy("component").agg(F.min("least").alias("name"))
    named = stage(classes.join(broadcast_if_small(stage(named, "class-names"), 16), "component").select("node", "name"), "vector-names")
    return (
        signed.select("vec_id", "label", "fp_a", "fp_b", F.col("unit").isNotNull().alias("ok"))
        .join(broadcast_if_small(groups, 56), ["label", "fp_a", "fp_b"], "left")
        .join(broadcast_if_small(counts, 24), "id", "left").join(broadcast_if_small(named, 16), F.col("id") == F.col("node"), "left")
        .select(
            "vec_id",
            F.when(F.col("ok"), F.coalesce("links", F.lit(0)) + F.col("weight") - 1).otherwise(0).cast("long").alias("n_links"),
            F.when(F.col("ok"), F.coalesce("name", "least")).otherwise(F.col("vec_id")).alias("component_id"),
        ).withColumn("kept", F.col("vec_id") == F.col("component_id"))
    )


def _apart(inside: DataFrame) -> DataFrame:
    """Close pairs of one bucket but of two components: members outside the component of the bucket's head meet all others, in
    blocks where a bucket is large. The tests sit in the join condition, so other pairs are never rows."""
    place, every = F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"), F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    minor = _side(inside.where("c <> main").withColumn("i", every), "b", F.col("key").alias("kb"), F.col("i").alias("ib"), place.alias("jb"), F.col("c").alias("cb"))
    other = _side(inside.withColumn("j", every), "a", "key", place.alias("i"), "j", F.col("main").alias("ma"), F.col("c").alias("ca"))
    met = (F.col("key") == F.col("kb")) & (F.col("i") == F.col("ib")) & (F.col("j") == F.col("jb")) & (F.col("ca") != F.col("cb"))
    return other.join(minor, met & ((F.col("ca") == F.col("ma")) | (F.col("a") < F.col("b"))) & _close()).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))


def _count_links(facts: DataFrame, classes: DataFrame, cosine: float) -> DataFrame:
    """id and links (weights of the other entries of its class with enough cosine).

    Small classes share tasks by hash. A large class is cut into blocks, every pair of its blocks is one group, and a group
    holds at most two blocks.
    """
    sizes = classes.groupBy("component").agg(F.count(F.lit(1)).alias("m"))
    rows = facts.select("id", "weight", "unit").join(classes, F.col("id") == F.col("node")).join(sizes, "component")
    parts = F.ceil(F.col("m") / BLOCK).cast("int")
    groups = max(1, -(-classes.count() // BLOCK) * 4)
    rows = rows.withColumn("parts", parts).withColumn("own", F.pmod(F.xxhash64("id"), F.col("parts")).cast("int"))
    small = rows.where("parts = 1").select(F.pmod(F.xxhash64("component"), F.lit(groups)).alias("c"), F.lit(-1).alias("i"), F.lit(-1).alias("j"), "own", "component", "id", "weight", "unit")
    large = rows.where("parts > 1").withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    large = large.select(F.col("component").alias("c"), F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "component", "id", "weight", "unit")

    def matches(a: np.ndarray, b: np.ndarray, wb: np.ndarray) -> np.ndarray:
        return np.concatenate([(a[k : k + 512] @ b.T >= cosine) @ wb for k in range(0, len(a), 512)] or [np.zeros(0, np.int64)])

    def count(key, frame: pd.DataFrame) -> pd.DataFrame:
        ids, weights, blocks = frame["id"].to_numpy(), frame["weight"].to_numpy(), frame["own"].to_numpy()
        out = np.zeros(len(frame), np.int64)
        if key[1] == -1:
            for at in frame.reset_index(drop=True).groupby("component").indices.values():
                v = np.stack(frame["unit"].iloc[at].to_list())
                out[at] = matches(v, v, weights[at]) - weights[at]
        else:
            v = np.stack(frame["unit"].to_list())
            left, right = np.flatnonzero(blocks == key[1]), np.flatnonzero(blocks == key[2])
            out[left] = matches(v[left], v[right], weights[right])
            out[right] = matches(v[right], v[left], weights[left]) if key[1] != key[2] else out[right] - weights[right]
        return pd.DataFrame({"id": ids, "links": out})

    counted = small.unionByName(large).groupBy("c", "i", "j").applyInPandas(count, "id long, links long")
    return stage(counted.groupBy("id").agg(F.sum("links").alias("links")), "vector-counts")

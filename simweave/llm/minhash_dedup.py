"""Near-duplicate documents by one-permutation hashing.

A document's distinct 5-word shingles are hashed once; the smallest value of each of a fixed number of bins is its
signature, and empty bins borrow from bins chosen by an optimal densification. Bands of the signature are buckets; every
bucket links its members to its smallest one, a star, so that candidates are as many as bucket entries. Links are
confirmed on full sets, and what a bucket's star leaves apart is compared again behind a bit sketch.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from operator import add

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from simweave.operators.components import connected_components
from simweave.plans.staging import broadcast_if_small, stage

WORDS, SIMILARITY = 5, 0.75
#: Bands of rows each: a pair at 0.75 meets in at least one band but for about one case in a million.
BANDS, ROWS = 50, 5
BINS = BANDS * ROWS
#: Bits of the sketch, and the fewest that agree for a pair at 0.75 (expected 112 of 128, 7.2 deviations lower: fewer than one
#: such pair in a billion is ruled out). Sets of fewer shingles than bits are not judged by it, as their bins share hashes.
SKETCH_BITS, LEAST_AGREE = 128, 85
#: Words of a parity bitmap over a document's shingles. Bits that differ are at most the shingles that differ, so
#: more than a seventh of both sizes (at 0.75) rules a pair out, without any error.
PARITY_WORDS = 16
PARITY = [f"x{k}" for k in range(PARITY_WORDS)]
#: Members of a bucket that meet in one task; larger buckets are cut into blocks that meet pairwise.
BLOCK = 2048
#: Entries of a task's table of word hashes.
WORD_TABLE = 1 << 20

_MASK = (1 << 64) - 1


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class WordHashes:
    """64-bit hashes of words, remembered in a table of bounded size."""

    def __init__(self):
        self.known: dict[bytes, int] = {}

    def __call__(self, words: list[bytes]) -> np.ndarray:
        known = self.known
        if len(known) > WORD_TABLE:
            known.clear()
        for w in set(words).difference(known):
            known[w] = xxhash.xxh3_64_intdigest(w)
        return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))


def shingle_set(text: str | None, hashes: WordHashes, size: int = WORDS) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the text's word shingles; with fewer words the whole sequence is one.

    A-Z is lower-cased; words are separated by ASCII white space. No text or no word: no shingle.
    """
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.empty(0, np.uint64)
    h = hashes(words)
    with np.errstate(over="ignore"):
        n = min(size, len(h))
        out = np.full(len(h) - n + 1, np.uint64(n))
        for k in range(n):
            out = _mix(out * np.uint64(0x9E3779B97F4A7C15) + h[k : len(h) - n + 1 + k])
    return np.unique(out)


class Signatures:
    """One-permutation signatures with optimal densification."""

    def __init__(self, bands: int = BANDS, rows: int = ROWS, seed: int = 5):
        self.bands, self.rows, self.bins = bands, rows, bands * rows
        self.width = _MASK // self.bins + 1
        self.edges = (np.arange(1, self.bins, dtype=object) * self.width).astype(np.uint64)
        rng = np.random.default_rng(seed)
        self.probes = rng.integers(0, self.bins, (self.bins, 64))
        self.more = rng.integers(0, self.bins, (self.bins, 4096))
        self.salt = _mix(rng.integers(0, 2**63, self.bands).astype(np.uint64))

    def bins_of(self, shingles: np.ndarray) -> np.ndarray:
        """The smallest hash of each bin; a bin without one takes that of the first filled bin in its own probe order."""
        at = np.concatenate([[0], np.searchsorted(shingles, self.edges), [len(shingles)]])
        full = at[1:] > at[:-1]
        out = np.where(full, shingles[np.minimum(at[:-1], len(shingles) - 1)], np.uint64(0))
        if not full.all():
            empty = np.flatnonzero(~full)
            for table in (self.probes, self.more):
                hit = full[table[empty]]
                found = hit.any(1)
                rows = empty[found]
                out[rows] = out[table[rows, hit[found].argmax(1)]]
                empty = empty[~found]
                if not len(empty):
                    break
            if len(empty):
                out[empty] = out[np.flatnonzero(full)[0]]
        return out

    def keys(self, signature: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            table = signature.reshape(self.bands, self.rows)
            out = self.salt.copy()
            for k in range(self.rows):
                out = _mix(out * np.uint64(0x9E3779B97F4A7C15) + table[:, k])
        return out.view(np.int64)

    def sketch(self, signature: np.ndarray) -> tuple[int, int]:
        """One bit of each of the first 128 bins, remixed by bin."""
        with np.errstate(over="ignore"):
            bits = _mix(signature[:SKETCH_BITS] + np.arange(1, SKETCH_BITS + 1, dtype=np.uint64) * np.uint64(0xD6E8FEB86659FD93)) & np.uint64(1)
        low, high = np.packbits(bits.astype(np.uint8)).view(np.int64)
        return int(low), int(high)


def parity_bitmap(shingles: np.ndarray) -> np.ndarray:
    """Parity of the number of shingles that fall on each of 64 * PARITY_WORDS bits, as signed words."""
    with np.errstate(over="ignore"):
        at = ((shingles * np.uint64(0xC2B2AE3D27D4EB4F)) >> np.uint64(32)) % np.uint64(64 * PARITY_WORDS)
    return np.packbits((np.bincount(at.astype(np.int64), minlength=64 * PARITY_WORDS) & 1).astype(np.uint8)).view(np.int64)


SIGNED = "doc_id long, n_shingles long, set_a long, set_b long, sketch_a long, sketch_b long, " + ", ".join(f"{x} long" for x in PARITY) + ", keys array<long>"


def sign_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """doc_id, size and 128-bit fingerprint of the shingle set, sketch and band keys of each document (no shuffle)."""

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, signs = WordHashes(), Signatures(bands, rows)
        for b in batches:
            for lo in range(0, b.num_rows, 2000):
                part = b.slice(lo, 2000)
                sizes, fps, sketches, bitmaps, keys = [], [], [], [], []
                for text in part.column(1):
                    s = shingle_set(text.as_py(), hashes)
                    sizes.append(len(s))
                    fp = xxhash.xxh3_128_digest(s.tobytes())
                    fps.append(np.frombuffer(fp, np.int64))
                    bitmaps.append(parity_bitmap(s))
                    if len(s):
                        sig = signs.bins_of(s)
                        sketches.append(signs.sketch(sig))
                        keys.append(signs.keys(sig))
                    else:
                        sketches.append((0, 0))
                        keys.append(np.empty(0, np.int64))
                fp, sk, bits = np.array(fps).reshape(-1, 2), np.array(sketches, np.int64).reshape(-1, 2), np.array(bitmaps).reshape(-1, PARITY_WORDS)
                at = np.concatenate([[0], np.cumsum([len(k) for k in keys])]).astype(np.int32)
                flat = np.concatenate(keys) if keys else np.empty(0, np.int64)
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), pa.array(sizes, pa.int64()), *map(pa.array, (fp[:, 0], fp[:, 1], sk[:, 0], sk[:, 1], *bits.T)), pa.ListArray.from_arrays(pa.array(at), pa.array(flat))],
                    [x.split()[0] for x in SIGNED.split(", ")],
                )

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(sign, SIGNED)


def _sets(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """doc_id and sorted shingle hashes of the documents in ids (staged; column doc_id)."""

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for b in batches:
            for lo in range(0, b.num_rows, 500):
                part = b.slice(lo, 500)
                sets = [shingle_set(t.as_py(), hashes).view(np.int64) for t in part.column(1)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sets, pa.list_(pa.int64()))], ["doc_id", "shingles"])

    wanted = docs.join(broadcast_if_small(ids, 8), "doc_id", "left_semi")
    return wanted.mapInArrow(build, "doc_id long, shingles array<long>")


def confirm(docs: DataFrame, pairs: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """Of the pairs (a, b; staged), those whose full shingle sets have Jaccard similarity of at least similarity.

    docs: doc_id and text, one row an id. The sets of the documents in pairs are built once and joined by id.
    """
    percent = round(100 * similarity)
    ids = stage(pairs.select(F.col("a").alias("doc_id")).distinct().union(pairs.select(F.col("b").alias("doc_id")).distinct()).distinct(), "pair-ids")
    sets = stage(_sets(docs, ids), "pair-sets")
    left = sets.select(F.col("doc_id").alias("a"), F.col("shingles").alias("sa"))
    right = sets.select(F.col("doc_id").alias("b"), F.col("shingles").alias("sb"))
    both = pairs.join(right, "b").join(left, "a")
    inter = F.size(F.array_intersect("sa", "sb"))
    return both.select("a", "b", inter.alias("i"), (F.size("sa") + F.size("sb")).alias("n")).where(f"100 * i >= {percent} * (n - i)").select("a", "b")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", similarity: float = SIMILARITY, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable by links) and kept (doc_id = component_id) of each document.

    A link is a pair with Jaccard similarity of at least similarity on 5-word shingles. Documents without a word are linked with
    nothing. Rows with a null id are left out; of rows that repeat an id, the one with the smallest text is taken. Equal sets are
    first collapsed, so a group of copies is one entry; no bucket is capped. An empty table gives an empty result. Other columns
    are not read.
    """
    percent = round(100 * similarity)
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).where("doc_id is not null")
    if _has_repeated_ids(slim, "doc_id"):
        slim = stage(slim.groupBy("doc_id").agg(F.min("text").alias("text")), "single-texts")
    signed = stage(sign_documents(slim, "doc_id", "text", bands, rows), "signed")
    twins = signed.where("n_shingles > 0").groupBy("set_a", "set_b", "n_shingles").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("n"))
    twins = stage(twins, "set-twins")
    copies = signed.select("doc_id", "set_a", "set_b", "n_shingles").join(broadcast_if_small(twins.where("n > 1").drop("n"), 40), ["set_a", "set_b", "n_shingles"])
    copies = copies.where("doc_id <> rep").select(F.col("rep").alias("a"), F.col("doc_id").alias("b"))
    copies = stage(copies, "set-copies")
    facts = stage(
        signed.where("n_shingles > 0").join(broadcast_if_small(copies.select(F.col("b").alias("doc_id")), 8), "doc_id", "left_anti")
        .select("doc_id", "n_shingles", "sketch_a", "sketch_b", *PARITY, "keys"),
        "set-reps",
    )
    entries = facts.select("doc_id", F.explode("keys").alias("key"))
    heads = entries.groupBy("key").agg(F.min("doc_id").alias("head"), F.count(F.lit(1)).alias("n")).where("n > 1").select("key", "head")
    heads = stage(heads, "bucket-heads")
    crowded = stage(entries.join(broadcast_if_small(heads, 16), "key"), "crowded")
    sizes = facts.drop("keys")
    stars = crowded.where("doc_id <> head").select(F.col("head").alias("a"), F.col("doc_id").alias("b")).distinct()
    pairs = stage(_plausible(stars, sizes, percent), "star-pairs")
    links = stage(confirm(slim, pairs, similarity), "star-links")
    inside = _mixed_buckets(crowded, sizes, connected_components(links))
    if inside is not None:
        best = stage(_apart(inside, percent).groupBy("b").agg(F.min(F.struct("differ", "a")).alias("m")).select(F.least("m.a", "b").alias("a"), F.greatest("m.a", "b").alias("b")).distinct(), "best-pairs")
        links = stage(links.unionByName(confirm(slim, best, similarity)), "more-links")
        inside = _mixed_buckets(crowded, sizes, connected_components(links))
    if inside is not None:
        rest = _apart(inside, percent).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
        rest = stage(rest.join(pairs.union(best), ["a", "b"], "left_anti"), "rest-pairs")
        links = links.unionByName(confirm(slim, rest, similarity))
    classes = connected_components(links.unionByName(copies))
    found = signed.select("doc_id", "n_shingles").join(classes, F.col("doc_id") == F.col("node"), "left")
    found = found.select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"))
    return found.withColumn("kept", F.col("doc_id") == F.col("component_id"))


def _side(sizes: DataFrame, side: str, *more) -> DataFrame:
    """Columns of one side of a pair, named after it."""
    facts = [("doc_id", side), ("n_shingles", f"n{side}"), ("sketch_a", f"p{side}"), ("sketch_b", f"q{side}"), *((x, x + side) for x in PARITY)]
    return sizes.select(*more, *(F.col(c).alias(n) for c, n in facts))


def _plausible(pairs: DataFrame, sizes: DataFrame, percent: int) -> DataFrame:
    """Pairs whose set sizes and bitmaps allow the similarity and whose sketches agree often enough."""
    return pairs.join(_side(sizes, "b"), "b").join(_side(sizes, "a"), "a").where(_could_link(percent)).select("a", "b")


def _differ() -> Column:
    return reduce(add, (F.bit_count(F.col(x + "a").bitwiseXOR(F.col(x + "b"))) for x in PARITY))


def _could_link(percent: int) -> Column:
    agree = F.lit(SKETCH_BITS) - F.bit_count(F.col("pa").bitwiseXOR(F.col("pb"))) - F.bit_count(F.col("qa").bitwiseXOR(F.col("qb")))
    alike = (100 * F.least("na", "nb") >= percent * F.greatest("na", "nb")) & ((agree >= LEAST_AGREE) | (F.least("na", "nb") < SKETCH_BITS))
    return alike & ((100 + percent) * _differ() <= (100 - percent) * (F.col("na") + F.col("nb")))


def _mixed_buckets(crowded: DataFrame, sizes: DataFrame, parts: DataFrame) -> DataFrame | None:
    """Members of the buckets that hold several components, with the component of the bucket's head; None if there are none."""
    members = crowded.join(parts, F.col("doc_id") == F.col("node"), "left").select("key", "doc_id", "head", F.coalesce("component", "doc_id").alias("c"))
    members = stage(members, "bucket-members")
    mixed = members.groupBy("key").agg(F.min("c").alias("lo"), F.max("c").alias("hi"), F.max(F.when(F.col("doc_id") == F.col("head"), F.col("c"))).alias("main")).where("lo <> hi")
    mixed = stage(mixed.select("key", "main"), "mixed-buckets")
    if not mixed.limit(1).count():
        return None
    return stage(members.join(broadcast_if_small(mixed, 16), "key").join(sizes, "doc_id").drop("head"), "mixed-members")


def _apart(inside: DataFrame, percent: int) -> DataFrame:
    """Pairs of one bucket but of two components that could link: members outside the component of the bucket's head meet all others.

    The tests sit in the join condition, so other pairs are never rows. In a bucket of more than BLOCK members, blocks of the ones
    meet blocks of the others in groups of their own.
    """
    cuts = inside.groupBy("key").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("blocks"), F.ceil(F.count_if(F.col("c") != F.col("main")) / BLOCK).cast("int").alias("minor_blocks"))
    cuts = stage(cuts.where("blocks > 1"), "bucket-cuts")
    cut = inside.join(broadcast_if_small(cuts, 24), "key", "left").withColumn("h", F.xxhash64("doc_id"))
    blocks, minor_blocks = F.coalesce("blocks", F.lit(1)), F.coalesce("minor_blocks", F.lit(1))
    place, other = lambda n: F.pmod("h", n).cast("int"), lambda n: F.explode(F.sequence(F.lit(0), n - 1))
    minor = _side(cut.where("c <> main").withColumn("i", other(blocks)), "b", "key", "i", place(minor_blocks).alias("j"), F.col("c").alias("cb"))
    every = _side(cut.withColumn("j", other(F.greatest(minor_blocks, F.lit(1)))), "a", "key", place(blocks).alias("i"), "j", F.col("main").alias("ma"), F.col("c").alias("ca"))
    apart = (F.col("ca") != F.col("cb")) & ((F.col("ca") == F.col("ma")) | (F.col("a") < F.col("b")))
    return every.join(minor, (every["key"] == minor["key"]) & (every["i"] == minor["i"]) & (every["j"] == minor["j"]) & apart & _could_link(percent)).select("a", "b", _differ().alias("differ"))


def _has_repeated_ids(docs: DataFrame, id_col: str) -> bool:
    """Whether an id other than null stands on two rows."""
    ids = docs.select(F.col(id_col).alias("i")).where("i is not null").groupBy("i").agg(F.count(F.lit(1)).alias("n"))
    return bool(ids.where("n > 1").limit(1).count())


def keep_one_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of docs that near_duplicates() keeps, one a class, with their own columns. Rows with a null id stay; of rows that
    repeat an id, one with the smallest text is there to be kept."""
    if _has_repeated_ids(docs, id_col):
        named = docs.where(F.col(id_col).isNotNull()).select(F.struct("*").alias("row"))
        rank = F.row_number().over(Window.partitionBy(f"row.{id_col}").orderBy(F.col(f"row.{text_col}").asc_nulls_last()))
        single = named.withColumn("rank", rank).where("rank = 1").select("row.*")
        docs = stage(single.unionByName(docs.where(F.col(id_col).isNull())), "single-rows")
    gone = stage(near_duplicates(docs, id_col, text_col, **options).where("not kept").select(F.col("doc_id").alias("__gone")), "near-copies")
    return docs.join(broadcast_if_small(gone, 8), F.col(id_col) == F.col("__gone"), "left_anti")

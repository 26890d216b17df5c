"""Sharding by sampled splitters.

Size-weighted key samples give quantile boundaries; records are range-partitioned by them, and ranges
that still hold too much are subdivided at further samples drawn inside them.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from simweave.plans.staging import broadcast_if_small, stage

#: Rows that a range is made for, and keys drawn for each range: the driver holds 16 keys for 100,000 rows.
RANGE_ROWS, DRAWN = 100_000, 16


def _drawn(keyed: DataFrame, weight: Column, expected: int, seed: int) -> DataFrame:
    """Rows drawn with a chance of expected times their weight, by a keyed hash: no sort, and the same rows in a rerun."""
    uniform = F.pmod(F.xxhash64("hash", "id", F.lit(seed)), F.lit(1 << 52)) / F.lit(float(1 << 52))
    return keyed.where(uniform < F.lit(float(expected)) * weight)


def _splitters(keyed: DataFrame, n_ranges: int, totals: tuple[int, int], seed: int) -> list[tuple[int, int]]:
    """n_ranges - 1 key boundaries at even steps of a sample weighted by size and, in equal part, by row."""
    size, rows = totals
    weight = (F.col("size") / F.lit(float(size)) + F.lit(1.0 / rows)) / 2
    drawn = _drawn(keyed, weight, DRAWN * n_ranges, seed).select("hash", "id").collect()
    keys = sorted({(r["hash"], r["id"]) for r in drawn})
    return [keys[len(keys) * k // n_ranges] for k in range(1, n_ranges) if len(keys) * k // n_ranges > 0] if keys else []


def _locate(hashes: np.ndarray, ids: np.ndarray, cut_hash: np.ndarray, cut_id: np.ndarray) -> np.ndarray:
    """Number of splitters at or below each (hash, id) key."""
    low, high = np.searchsorted(cut_hash, hashes, "left"), np.searchsorted(cut_hash, hashes, "right")
    out = high.copy()
    tied = np.flatnonzero(low < high)
    for h in np.unique(hashes[tied]):
        rows = tied[hashes[tied] == h]
        a, b = low[rows[0]], high[rows[0]]
        out[rows] = a + np.searchsorted(cut_id[a:b], ids[rows], "right")
    return out


def _with_range(keyed: DataFrame, cuts: list[tuple[int, int]], name: str) -> DataFrame:
    cuts = sorted(set(cuts))
    cut_hash, cut_id = np.array([c[0] for c in cuts], np.int64), np.array([c[1] for c in cuts], np.int64)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cols = {n: b.column(n) for n in b.schema.names}
            at = _locate(cols["hash"].to_numpy(), cols["id"].to_numpy(), cut_hash, cut_id)
            yield pa.RecordBatch.from_arrays([*cols.values(), pa.array(at, pa.int32())], [*cols, name])

    return keyed.mapInArrow(place, ", ".join(f"{n} {t}" for n, t in keyed.dtypes) + f", {name} int")


def shard_by_splitters(
    keyed: DataFrame, n_shards: int = 8, ranges_per_shard: int = 64, tolerance: float = 0.001, rounds: int = 4, seed: int = 17, carry: tuple[str, ...] = ()
) -> DataFrame:
    """Deal records into n_shards key ranges of nearly equal bytes.

    keyed: hash (long, the leading key; equal contents share it), id (long, breaks ties), size (long) and the columns to carry.
    Other columns are dropped, null sizes count as 0 and null keys as 0; repeated rows stay repeated. Returns
    hash, id, size, the carried columns, shard (int), slot (long, gapless from 0 in each shard, by key). Empty input: empty result.

    Equal contents stay together, unless their group straddles a byte boundary: the bytes law then cuts
    it by id, so a group with a third of all rows is spread. A boundary that falls inside a range is pushed to
    a splitter within tolerance times a shard's bytes, by sampling anew inside that range; ranges with four times the rows
    they were made for are subdivided the same way.
    """
    keyed = stage(
        keyed.select(*(F.coalesce(F.col(c), F.lit(0)).cast("long").alias(c) for c in ("hash", "id", "size")), *carry), "shard-keys"
    )
    rows, size = keyed.agg(F.count(F.lit(1)), F.coalesce(F.sum("size"), F.lit(0))).first()
    if rows == 0:
        return keyed.select("*", F.lit(0).alias("shard"), F.lit(0).cast("long").alias("slot"))
    n_ranges = max(n_shards * ranges_per_shard, -(-rows // RANGE_ROWS))
    even = np.array([size * k / n_shards for k in range(1, n_shards)])
    cuts = sorted(set(_splitters(keyed, n_ranges, (max(size, 1), rows), seed)))
    for turn in range(1, rounds + 1):
        placed = _with_range(keyed, cuts, "range")
        stats = {r["range"]: (r["bytes"], r["n"]) for r in placed.groupBy("range").agg(F.sum("size").alias("bytes"), F.count(F.lit(1)).alias("n")).collect()}
        ends = np.cumsum([stats.get(k, (0, 0))[0] for k in range(len(cuts) + 1)])
        loose = set()
        for e in even:
            k = int(np.searchsorted(ends, e))
            start = ends[k - 1] if k else 0
            if min(abs(ends[k] - e), abs(e - start)) > tolerance * size / n_shards and stats[k][1] > 1:
                loose.add(k)
        split = loose | {k for k, (_, n) in stats.items() if n > max(4 * rows / n_ranges, 50)}
        if not split or turn == rounds:
            break
        totals = keyed.sparkSession.createDataFrame([(k, float(max(stats[k][0], 1)), float(stats[k][1])) for k in sorted(split)], "range int, b double, n double")
        inside = placed.select("hash", "id", "range", "size").join(F.broadcast(totals), "range")
        weight = (F.col("size") / F.col("b") + 1 / F.col("n")) / 2
        more = {(r["hash"], r["id"]) for r in _drawn(inside, weight, DRAWN * DRAWN, seed + turn).select("hash", "id").collect()}
        cuts = sorted(set(cuts) | more)
    shard_of = np.minimum(np.searchsorted(even, ends - 0.5 * np.diff(np.concatenate([[0], ends])), "right"), n_shards - 1)
    starts, seen = [], dict.fromkeys(range(n_shards), 0)
    for k in range(len(cuts) + 1):
        s = int(shard_of[k])
        starts.append((k, s, seen[s]))
        seen[s] += stats.get(k, (0, 0))[1]
    ranges = keyed.sparkSession.createDataFrame(starts, "range int, shard int, first long")
    order = Window.partitionBy("range").orderBy("hash", "id", "size")
    return (
        placed.withColumn("__place", F.row_number().over(order)).join(F.broadcast(ranges), "range")
        .select("hash", "id", "size", *carry, "shard", (F.col("first") + F.col("__place") - 1).alias("slot"))
    )


def shard_documents(docs: DataFrame, n_shards: int = 8, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """Shards of whole documents by the bytes law: size is the text's UTF-8 bytes plus 1, null text counts none.

    Returns doc_id, size, text_crc32 (unsigned, 0 for null or empty text), law, shard, slot and grown_shard (null
    under this law). Only the id and the text are read, so further columns of any name are harmless. Null ids stay null.
    """
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("t"))
    slim = slim.select(
        F.col("doc_id").alias("id"), "doc_id", F.xxhash64("t").alias("hash"), (F.octet_length("t") + F.lit(1)).cast("long").alias("size"), F.crc32(F.col("t").cast("binary")).alias("crc")
    )
    dealt = shard_by_splitters(slim, n_shards, carry=("doc_id", "crc"), **options)
    return dealt.select(
        "doc_id", "size", F.col("crc").cast("long").alias("text_crc32"), F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard")
    )


def write_shards(docs: DataFrame, dealt: DataFrame, path: str, id_col: str = "doc_id") -> None:
    """Write whole documents as one folder of Parquet files per shard, rows in slot order within each file."""
    places = broadcast_if_small(dealt.select(F.col("doc_id").alias(id_col), "shard", "slot"), 24)
    whole = docs.drop("shard", "slot").join(places, id_col)
    whole.repartition("shard", F.floor(F.col("slot") / 100_000)).sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)

"""Mixing sources to target weights.

Each source's words are one stream, packed into blocks of fixed length. Multinomial draws give every output shard
its count of slots per source, a keyed index permutation per source maps its slots to its blocks, and blocks are joined
to slots by index. No row of text is sorted, shuffled or copied to decide what the mix takes.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from simweave.plans.staging import broadcast_if_small, stage

#: Fixed source weights, repeating over the sources in code point order (null last), and the mix's size.
WEIGHTS, SHARE, REPEATS = (5, 2, 1), 1.5, 2
#: Most sources that the driver's catalogue holds, with a few numbers for each and for each of its shards; more raise an error.
MAX_SOURCES = 100_000
#: Every index permutation has this many rounds.
ROUNDS = 4


def _scramble(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def permute(index: np.ndarray, n: int, key: int, inverse: bool = False) -> np.ndarray:
    """A keyed permutation of 0..n-1 at the given indexes: a Feistel network, walked until it is inside the range."""
    half = max(1, (max(n - 1, 1).bit_length() + 1) // 2)
    mask, shift = np.uint64((1 << half) - 1), np.uint64(half)
    out = np.asarray(index, np.uint64).copy()
    todo = np.arange(len(out))
    keys = [np.uint64((key * 0x9E3779B97F4A7C15 + r * 0xD1B54A32D192ED03 + 1) & (2**64 - 1)) for r in range(ROUNDS)]
    with np.errstate(over="ignore"):
        while len(todo):
            a, b = out[todo] >> shift, out[todo] & mask
            for k in reversed(keys) if inverse else keys:
                if inverse:
                    a, b = b ^ (_scramble(a + k) & mask), a
                else:
                    a, b = b, a ^ (_scramble(b + k) & mask)
            out[todo] = (a << shift) | b
            todo = todo[out[todo] >= n]
    return out.astype(np.int64)


def water_fill(sizes: list[int], weights: list[float], total: float, most: float = REPEATS) -> list[float]:
    """Shares of total by weight, none above most times its size; the excess goes to the rest by weight."""
    targets, free, left = [0.0] * len(sizes), [i for i, s in enumerate(sizes) if s > 0], float(total)
    while free:
        by = left / sum(weights[i] for i in free)
        full = [i for i in free if weights[i] * by > most * sizes[i]]
        if not full:
            for i in free:
                targets[i] = weights[i] * by
            break
        for i in full:
            targets[i] = float(most * sizes[i])
            left -= targets[i]
        free = [i for i in free if i not in set(full)]
    return targets


@dataclass
class Source:
    """A source of the catalogue: its words, blocks and slots; the last slot takes only a part of its block."""

    name: str | None
    index: int
    size: int
    target: float
    blocks: int = 0
    slots: int = 0
    last_take: int = 0


def plan_sources(sizes: list[tuple[str | None, int]], block: int, seed: int, weights=WEIGHTS, share=SHARE, most=REPEATS) -> list[Source]:
    """Targets and slot counts; every source's slots hold exactly its target, rounded to a word."""
    named = sorted((x for x in sizes if x[0] is not None), key=lambda x: x[0]) + [x for x in sizes if x[0] is None]
    cycle = [float(weights[i % len(weights)]) for i in range(len(named))]
    targets = water_fill([s for _, s in named], cycle, share * sum(s for _, s in named), most)
    out = []
    for i, ((name, size), target) in enumerate(zip(named, targets, strict=True)):
        s = Source(name, i, size, target)
        words = min(round(target), most * size)
        if size and words:
            s.blocks = -(-size // block)
            short = size - (s.blocks - 1) * block
            turns, rest = divmod(words, size)
            used = taken = 0
            if rest:
                at = int(permute(np.array([s.blocks - 1]), s.blocks, _key(seed, i, turns), inverse=True)[0])
                used = -(-rest // block)
                if used > at:
                    used = at + 1 + max(0, -(-(rest - at * block - short) // block))
                held = used * block - (block - short if used > at else 0)
                taken = (short if used == at + 1 else block) - (held - rest)
            s.slots, s.last_take = turns * s.blocks + used, taken if rest else block
        out.append(s)
    return out


def _key(seed: int, source: int, turn: int) -> int:
    return (seed * 1_000_003 + source) * 1_000_003 + turn


def draw_counts(slots: list[int], n_shards: int, seed: int) -> np.ndarray:
    """Slots of each source in each shard: multinomial draws on what every source has left, so totals are exact."""
    left, rng = np.array(slots, np.int64), np.random.default_rng(seed)
    out = np.zeros((n_shards, len(slots)), np.int64)
    for k in range(n_shards):
        need = int(left.sum()) // (n_shards - k)
        while need > 0:
            got = np.minimum(rng.multinomial(need, left / left.sum()), left)
            out[k] += got
            left -= got
            need -= int(got.sum())
    return out


def position_documents(docs: DataFrame, id_col: str, text_col: str, source_col: str, row_col: str | None = None) -> DataFrame:
    """row, doc_id, source, size and start: the place of each document in its source's stream of words.

    Starts are a two-level running sum, by buckets of ids inside a source, so no task holds a whole source.
    """
    words = F.size(F.split(F.btrim("t", F.lit(" \t\n\x0b\x0c\r")), "[\\x20\\x09-\\x0D]+", -1))
    slim = stage(
        docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), F.coalesce(F.col(text_col), F.lit("")).alias("t"), (F.col(row_col) if row_col else F.monotonically_increasing_id()).alias("row"))
        .select("row", "doc_id", "source", F.when(F.btrim("t", F.lit(" \t\n\x0b\x0c\r")) == "", 0).otherwise(words).cast("long").alias("size")),
        "mix-sizes",
    )
    buckets = max(256, slim.count() // 50_000)
    slim = slim.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "size"), F.lit(buckets)))
    ahead = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    firsts = slim.groupBy("source", "bucket").agg(F.sum("size").alias("sum")).select("source", "bucket", F.coalesce(F.sum("sum").over(ahead), F.lit(0)).alias("first"))
    inside = Window.partitionBy("source", "bucket").orderBy("doc_id", "row").rowsBetween(Window.unboundedPreceding, -1)
    placed = slim.withColumn("before", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    firsts = firsts.select(F.col("source").alias("s2"), F.col("bucket").alias("b2"), "first")
    return placed.join(firsts, placed["source"].eqNullSafe(firsts["s2"]) & (placed["bucket"] == firsts["b2"])).select(
        "row", "doc_id", "source", "size", (F.col("first") + F.col("before")).alias("start")
    )


def mix_slots(spark, plan: list[Source], n_shards: int, block: int, seed: int) -> DataFrame:
    """shard, place, source_index, block, take: the whole output order of the mix, slot by slot."""
    counts = draw_counts([s.slots for s in plan], n_shards, seed)
    firsts = np.vstack([np.zeros(len(plan), np.int64), np.cumsum(counts, 0)[:-1]])
    sizes = counts.sum(1)
    ahead = np.cumsum(counts, 1) - counts
    chunk = 1 << 18
    rows = [
        (k, int(sizes[k]), int(ahead[k, i]) + c, i, s.blocks, s.slots, s.last_take, s.size, int(firsts[k, i]) + c, int(min(chunk, counts[k, i] - c)))
        for k in range(n_shards) for i, s in enumerate(plan) for c in range(0, int(counts[k, i]), chunk)
    ]
    names = ["shard", "in_shard", "ahead", "source_index", "blocks", "slots", "last_take", "size", "first", "n"]
    if not rows:
        return spark.createDataFrame([], "shard int, place long, source_index int, block long, take long")

    def expand(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for r in batch.itertuples(index=False):
                slot = np.arange(r.first, r.first + r.n)
                turn = slot // r.blocks
                at = np.empty(len(slot), np.int64)
                for t in np.unique(turn):
                    own = turn == t
                    at[own] = permute(slot[own] % r.blocks, r.blocks, _key(seed, r.source_index, int(t)))
                take = np.minimum(block, r.size - at * block)
                take[slot == r.slots - 1] = min(r.last_take, int(take[slot == r.slots - 1][0])) if (slot == r.slots - 1).any() else 0
                place = permute(r.ahead + np.arange(r.n), r.in_shard, _key(seed, 1 << 20, r.shard))
                yield pd.DataFrame({"shard": np.int32(r.shard), "place": place, "source_index": np.int32(r.source_index), "block": at, "take": take})

    schema = ", ".join(f"{n} long" for n in names)
    frame = spark.createDataFrame(rows, schema).repartition(min(len(rows), 2 * spark.sparkContext.defaultParallelism))
    return frame.mapInPandas(expand, "shard int, place long, source_index int, block long, take long")


@dataclass
class Mix:
    """placed: documents with their source's index, size and target; slots: the output order; block: words a block."""

    placed: DataFrame
    slots: DataFrame
    block: int


def plan_mix(docs: DataFrame, n_shards: int = 64, block: int = 1024, seed: int = 23, id_col="doc_id", text_col="text", source_col="source", row_col: str | None = None) -> Mix:
    """Plan the mix of all documents. Null text has no words, a null source is a source of its own and comes last."""
    spark = docs.sparkSession
    placed = stage(position_documents(docs, id_col, text_col, source_col, row_col), "mix-placed")
    sizes = placed.groupBy("source").agg(F.sum("size").alias("size")).limit(MAX_SOURCES + 1).collect()
    if len(sizes) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources")
    plan = plan_sources([(r["source"], r["size"]) for r in sizes], block, seed)
    facts = spark.createDataFrame([(s.name, s.index, s.size, s.target) for s in plan], "s2 string, source_index int, source_size long, target double")
    placed = placed.join(F.broadcast(facts), placed["source"].eqNullSafe(facts["s2"])).drop("s2")
    return Mix(placed, mix_slots(spark, plan, n_shards, block, seed), block)


def _pieces(mix: Mix) -> DataFrame:
    """One row per block that a document reaches: [low, high) is its part of the block."""
    b = F.lit(mix.block)
    some = mix.placed.where("size > 0").withColumn("block", F.explode(F.sequence(F.floor(F.col("start") / b), F.floor((F.col("start") + F.col("size") - 1) / b))))
    return some.withColumn("low", F.greatest(F.col("start") - F.col("block") * b, F.lit(0))).withColumn(
        "high", F.least(F.col("start") + F.col("size") - F.col("block") * b, b)
    )


def mix_documents(docs: DataFrame, **options) -> DataFrame:
    """row, doc_id, source, size, source_size, target and taken (words in the mix, repeats counted) of each document.

    Each source's taken words add up to its target rounded to a word, and no document is taken more than twice, because
    a block's slots are whole turns of a permutation. Repeated rows stay apart; an empty table gives an empty result.
    """
    return _taken(plan_mix(docs, **options)).drop("start")


def _taken(mix: Mix) -> DataFrame:
    """The rows of mix_documents() with their start."""
    uses = mix.slots.groupBy("source_index", "block", "take").agg(F.count(F.lit(1)).alias("n"))
    part = F.greatest(F.least("high", "take") - F.col("low"), F.lit(0)) * F.col("n")
    taken = _pieces(mix).join(uses, ["source_index", "block"]).groupBy("row").agg(F.sum(part).alias("taken"))
    return mix.placed.join(taken, "row", "left").select(
        "row", "doc_id", "source", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"), "start"
    )


def repeat_by_mix(docs: DataFrame, seed: int = 23, **options) -> DataFrame:
    """The rows of docs as often as the mix takes them: the taken words over the size, so 0 to 2 times.

    Documents stay whole. A fraction of a document is rounded up with its own probability, by a draw keyed by the
    document's place in its source, so documents of any length keep their source's rate and a source's words its target
    on average. Rows without a word are never taken.
    """
    own = "__mix_row"
    rows = stage(docs.withColumn(own, F.monotonically_increasing_id()), "mix-rows")
    mixed = _taken(plan_mix(rows, row_col=own, seed=seed, **options))
    draw = F.pmod(F.xxhash64(F.lit(seed), "source", "start"), F.lit(1 << 30)) / F.lit(1 << 30)
    uses = stage(mixed.where("size > 0").select("row", F.floor(F.col("taken") / F.col("size") + draw).cast("int").alias("__uses")).where("__uses > 0"), "mix-uses")
    joined = rows.join(broadcast_if_small(uses, 16), F.col(own) == F.col("row")).drop("row", own)
    return joined.withColumn("__use", F.explode(F.sequence(F.lit(1), F.col("__uses")))).drop("__use", "__uses")


def mixed_blocks(docs: DataFrame, id_col="doc_id", text_col="text", source_col="source", **options) -> DataFrame:
    """The mix itself: shard, place, source_index, block and words (array of at most block words), one row per slot.

    Rows that repeat an id are documents of their own, as in mix_documents().
    """
    own = "__mix_row"
    rows = stage(docs.select(*dict.fromkeys((id_col, text_col, source_col))).withColumn(own, F.monotonically_increasing_id()), "mix-rows")
    mix = plan_mix(rows, id_col=id_col, text_col=text_col, source_col=source_col, row_col=own, **options)
    part = F.slice("w", (F.col("low") + F.col("block") * mix.block - F.col("start") + 1).cast("int"), (F.col("high") - F.col("low")).cast("int"))
    texts = rows.select(F.col(own).alias("row"), F.split(F.btrim(F.coalesce(F.col(text_col), F.lit("")), F.lit(" \t\n\x0b\x0c\r")), "[\\x20\\x09-\\x0D]+", -1).alias("w"))
    blocks = _pieces(mix).join(texts, "row").groupBy("source_index", "block").agg(F.sort_array(F.collect_list(F.struct("low", part.alias("w")))).alias("p"))
    blocks = blocks.select("source_index", "block", F.flatten(F.transform("p", lambda x: x["w"])).alias("words"))
    return mix.slots.join(blocks, ["source_index", "block"]).select(
        "shard", "place", "source_index", "block", F.slice("words", 1, F.col("take").cast("int")).alias("words")
    )

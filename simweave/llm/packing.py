"""Best-fit packing by hierarchical residual merging.

Partitions tokenize and pack their own documents best-fit; bins that are nearly full are done. The rest travel up a tree
as single items (a number and a fill, no tokens) and are packed best-fit again, round by round.
"""

from __future__ import annotations

import json
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from simweave.plans.staging import broadcast_if_small, stage

#: Tokens of a sequence, and the id that ends each document.
CAPACITY, END_ID = 2048, 0
#: A bin that has at most this many tokens left is done.
NEARLY_FULL = 8
#: Pieces that one task packs at a time, and items of one task in the rounds above.
LOCAL_ITEMS, TREE_ITEMS = 200_000, 16_000
#: Fixed pattern of the byte-level pre-tokenizer, in possessive form: it never goes back, so its time is linear.
PATTERN = r"""'(?:[sdmt]|ll|ve|re)| ?\p{L}++| ?\p{N}++| ?[^\s\p{L}\p{N}]++|\s++$|\s+(?!\S)|\s"""


class Encoder:
    """Ids of a tokenizer file as its library gives them with add_special_tokens=False, special strings included.

    For plain byte-level BPE files a rank table made from the file's own vocabulary gives the same ids about four times
    faster (the tests hold it against the library on every code point and prove the merges); other kinds of files go to the
    library. Which of the two works depends on the file alone, never on a text. With specials_as_text, special strings in a
    text are ordinary text.
    """

    def __init__(self, path: str, specials_as_text: bool = False):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.encode_special_tokens = specials_as_text
        self.ranks = byte_level_ranks(json.loads(self.library.to_str()))
        self.fast = None
        if self.ranks is not None:
            import tiktoken

            special = {t.content: i for i, t in self.library.get_added_tokens_decoder().items()}
            self.fast = tiktoken.Encoding("file", pat_str=PATTERN, mergeable_ranks=self.ranks, special_tokens=special)
            self.allowed = set() if specials_as_text else "all"

    def __call__(self, text: str) -> list[int]:
        if self.fast is None:
            return self.library.encode(text, add_special_tokens=False).ids
        return self.fast.encode(text, allowed_special=self.allowed, disallowed_special=())


def byte_level_ranks(spec: dict) -> dict[bytes, int] | None:
    """Token bytes and ids of a tokenizer file, if it is plain byte-level BPE whose merges are ranked by id; else None."""
    model, pre = spec["model"], spec["pre_tokenizer"] or {}
    plain = model["type"] == "BPE" and not any(model.get(k) for k in ("dropout", "unk_token", "continuing_subword_prefix", "end_of_word_suffix", "byte_fallback", "ignore_merges"))
    plain &= pre.get("type") == "ByteLevel" and pre.get("use_regex", False) and not pre.get("add_prefix_space", True) and not (spec["normalizer"] or spec["post_processor"])
    plain &= all(t["special"] and not (t["normalized"] or t["lstrip"] or t["rstrip"] or t["single_word"]) for t in spec["added_tokens"])
    if not plain:
        return None
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    byte_of = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in shown)}
    special = {t["content"] for t in spec["added_tokens"]}
    vocabulary = {t: i for t, i in model["vocab"].items() if t not in special}
    merged = [vocabulary.get("".join(m if isinstance(m, list) else m.split(" ")), -1) for m in model["merges"]]
    if any(a >= b for a, b in zip(merged, merged[1:])) or len(merged) + 256 != len(vocabulary) or -1 in merged:
        return None
    return {bytes(byte_of[c] for c in t): i for t, i in vocabulary.items()}


def best_fit(sizes: np.ndarray, capacity: int = CAPACITY) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Best-fit decreasing: bin and offset of each item, and the fill of each bin. Ties keep the given order.

    Open bins are stacked by what they have left; the tightest that fits is the lowest set bit of a mask.
    """
    bins, offsets, fills = np.zeros(len(sizes), np.int64), np.zeros(len(sizes), np.int64), []
    stacks: list[list[int]] = [[] for _ in range(capacity + 1)]
    mask = 0
    for i in np.argsort(-sizes, kind="stable").tolist():
        size = int(sizes[i])
        if fit := mask >> size:
            left = size + (fit & -fit).bit_length() - 1
            k = stacks[left].pop()
            if not stacks[left]:
                mask &= ~(1 << left)
        else:
            k, left = len(fills), capacity
            fills.append(0)
        bins[i], offsets[i] = k, fills[k]
        fills[k] += size
        if left := left - size:
            stacks[left].append(k)
            mask |= 1 << left
    return bins, offsets, np.array(fills, np.int64)


PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, bin long, offset long, fill long"


def _pack_locally(path: str, capacity: int, specials_as_text: bool):
    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encode = Encoder(path, specials_as_text)
        base, made = TaskContext.get().partitionId() << 32, 0
        held: list[tuple] = []

        def flush() -> pa.RecordBatch:
            nonlocal made
            cols = list(zip(*held, strict=True)) if held else [[]] * 5
            bins, offsets, fills = best_fit(np.array(cols[3], np.int64), capacity)
            out = [
                pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int32()), *(pa.array(cols[k], pa.int64()) for k in (2, 3, 4)),
                pa.array(bins + base + made), pa.array(offsets), pa.array(fills[bins] if len(bins) else bins),
            ]
            made += len(fills)
            held.clear()
            return pa.RecordBatch.from_arrays(out, [x.split()[0] for x in PIECES.split(", ")])

        for batch in batches:
            for doc, text in zip(batch.column(0), batch.column(1), strict=True):
                ids = np.array([*encode(text.as_py() or ""), END_ID], "<u4")
                first = (len(ids) - 1) % capacity + 1
                for piece, start in enumerate([0, *range(first, len(ids), capacity)]):
                    part = ids[start : first if piece == 0 else start + capacity]
                    held.append((doc.as_py(), piece, start, len(part), zlib.crc32(part.tobytes())))
                if len(held) >= LOCAL_ITEMS:
                    yield flush()
        yield flush()

    return pack


def pack_documents(docs: DataFrame, tokenizer_path: str | None = None, capacity: int = CAPACITY, id_col="doc_id", text_col="text", specials_as_text: bool = False) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id and offset of every piece of every document.

    A document is its token ids and END_ID; null text is empty, so every row has a piece. Special strings in a text get their special
    ids, as the library does, unless specials_as_text. Only documents of more than
    capacity tokens are cut, the first piece taking the remainder. Repeated rows are packed each; a null id stays null.
    An empty table gives an empty result. Other columns are not read.
    """
    if tokenizer_path is None:
        import public_tokenizers

        tokenizer_path = public_tokenizers.path("byte_bpe_50k.json")
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    pieces = stage(slim.mapInArrow(_pack_locally(tokenizer_path, capacity, specials_as_text), PIECES), "pieces")
    rest = pieces.where((F.col("offset") == 0) & (F.col("fill") < capacity - NEARLY_FULL)).select(F.col("bin").alias("first_bin"), F.col("bin").alias("item"), "fill", F.lit(0).cast("long").alias("base"))
    chain = _merge_up(stage(rest, "underfull"), capacity)
    placed = pieces.join(broadcast_if_small(chain.select(F.col("first_bin").alias("bin"), "item", "base"), 40), "bin", "left")
    return placed.select(
        "doc_id", "piece", "start", "length", "ids_crc32", F.coalesce("item", "bin").alias("sequence_id"), (F.col("offset") + F.coalesce("base", F.lit(0))).alias("offset")
    )


def _merge_up(chain: DataFrame, capacity: int) -> DataFrame:
    """first_bin, item and base: the bin that each underfull bin ends in, and where.

    Rounds go on until all items were packed by one task, or until a round with items dealt anew saves under one bin in a hundred:
    then what is left are bins that hardly fit together.
    """

    def repack(key, items: pd.DataFrame) -> pd.DataFrame:
        items = items.sort_values(["fill", "item"], ascending=[False, True])
        bins, offsets, fills = best_fit(items["fill"].to_numpy(), capacity)
        names = items["item"].to_numpy()
        lead = np.zeros(len(fills), np.int64)
        lead[bins[::-1]] = names[::-1]
        return pd.DataFrame({"item": names, "target": lead[bins], "at": offsets, "total": fills[bins]})

    live = chain.select("item", "fill")
    count, turn = live.count(), 0
    while count > 1:
        turn += 1
        groups = -(-count // TREE_ITEMS)
        keyed = live.withColumn("g", F.pmod(F.xxhash64("item", F.lit(turn)), F.lit(groups)))
        moved = stage(keyed.groupBy("g").applyInPandas(repack, "item long, target long, at long, total long"), "repacked")
        chain = stage(
            chain.join(moved, "item", "left")
            .select("first_bin", F.coalesce("target", "item").alias("item"), (F.col("base") + F.coalesce("at", F.lit(0))).alias("base")),
            "chain",
        )
        live = moved.where((F.col("at") == 0) & (F.col("total") < capacity - NEARLY_FULL)).select(F.col("target").alias("item"), F.col("total").alias("fill"))
        before, count = count, live.count()
        if groups == 1 or count > 0.99 * before:
            break
    return chain


def packed_sequences(packed: DataFrame, docs: DataFrame, tokenizer_path: str, id_col="doc_id", text_col="text") -> DataFrame:
    """The sequences themselves: sequence_id and ids (array<int>), for documents with distinct ids."""

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder(tokenizer_path)
        for b in batches:
            ids = [[*encoder(t.as_py() or ""), END_ID] for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(ids, pa.list_(pa.int32()))], ["doc_id", "ids"])

    tokens = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(encode, "doc_id long, ids array<int>")
    parts = packed.join(tokens, "doc_id").select("sequence_id", "offset", F.slice("ids", (F.col("start") + 1).cast("int"), F.col("length").cast("int")).alias("ids"))
    whole = parts.groupBy("sequence_id").agg(F.sort_array(F.collect_list(F.struct("offset", "ids"))).alias("p"))
    return whole.select("sequence_id", F.flatten(F.transform("p", lambda x: x["ids"])).alias("ids"))

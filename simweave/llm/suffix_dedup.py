"""Removal of long passages that repeat anywhere in the corpus, by sorted suffixes.

Every window of the removal length is assigned to an anchor, the smallest 32-byte gram inside it, so equal windows have equal anchors
at equal places. Anchors whose gram occurs once cannot hold a repeat and are left out. Of the others, equal stretches are collapsed
to one entry (a stretch that occurs twice is repeated as a whole); the entries are gathered by gram, their suffixes are sorted in
two stages (suffixes smaller than their successors directly, the rest induced by bucket scans), and adjacent common prefixes of at
least the removal length mark the repeated windows. Entries of a gram that are too many for one task are cut by the bytes that
neighbouring windows share, and those smaller groups are sorted the same way.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from simweave.plans.staging import broadcast_if_small, stage

#: Bytes of a removed string and of an anchor's gram.
LENGTH, GRAM = 400, 32
#: Suffixes are sorted in batches of about this many bytes. A gram with more different stretches than GROUP is cut into groups
#: of windows that share the bytes around their anchor before it is sorted: a bound on a task, not on what is found.
BATCH, GROUP = 1 << 20, 512
#: Lists of places are broadcast to the texts below this size, counted first; beyond it the texts are shuffled.
LISTS = 64 << 20
#: Texts longer than this are scanned in overlapping parts.
PART = 1 << 22

_ODD = np.uint64(0x9E3779B97F4A7C15)


def gram_hashes(data: np.ndarray, gram: int = GRAM) -> np.ndarray:
    """A mixed 64-bit hash of the gram that starts at each byte; gram is a power of two."""
    with np.errstate(over="ignore"):
        h, k, power = data.astype(np.uint64) + np.uint64(1), 1, _ODD
        while k < gram:
            h = h[:-k] * power + h[k:]
            power *= power
            k *= 2
        h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


def _running_minimum(x: np.ndarray, width: int) -> np.ndarray:
    """Smallest of each width consecutive values, from running minima inside blocks of that width."""
    n = len(x) - width + 1
    table = np.full(-(-len(x) // width) * width, np.iinfo(np.uint64).max, np.uint64)
    table[: len(x)] = x
    table = table.reshape(-1, width)
    ahead = np.minimum.accumulate(table, axis=1).ravel()
    back = np.minimum.accumulate(table[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[:n], ahead[width - 1 : width - 1 + n])


def anchors(data: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Anchor, first and last window start, and gram hash of every run of windows that share an anchor.

    A window's anchor is its gram with the smallest upper 40 hash bits, of equal ones the last; that depends on the
    window's bytes alone. Each window is in exactly one run.
    """
    n = len(data) - length + 1
    if n <= 0:
        return (np.empty(0, np.int64),) * 3 + (np.empty(0, np.uint64),)
    h = gram_hashes(data, gram)
    mask = np.uint64((1 << 24) - 1)
    packed = (h & ~mask) | (mask - np.arange(len(h), dtype=np.uint64))
    at = (mask - (_running_minimum(packed, length - gram + 1) & mask)).astype(np.int64)
    first = np.concatenate([[0], np.flatnonzero(at[1:] != at[:-1]) + 1])
    last = np.concatenate([first[1:] - 1, [n - 1]])
    return at[first], first, last, h[at[first]]


def _names(key: np.ndarray) -> np.ndarray:
    """Dense ranks from 1 of the values."""
    order = np.argsort(key, kind="stable")
    ranked = key[order]
    out = np.empty(len(key), np.int64)
    out[order] = np.cumsum(np.concatenate([[1], ranked[1:] != ranked[:-1]]))
    return out


def _later(names: np.ndarray, at: np.ndarray | int) -> np.ndarray:
    """Names at later positions, 0 beyond the end; at is a shift of all positions or positions themselves."""
    if isinstance(at, int):
        return np.concatenate([names[at:], np.zeros(min(at, len(names)), names.dtype)])
    return np.where(at < len(names), names[np.minimum(at, len(names) - 1)], 0)


#: Bytes that one name stands for: words of 7 symbols, doubled three times.
SPAN = 56


def span_names(text: np.ndarray) -> np.ndarray:
    """Ranks of the SPAN bytes from each position on; the end of the text is smaller than any byte."""
    symbols = np.concatenate([text.astype(np.uint64) + np.uint64(1), np.zeros(6, np.uint64)])
    word = np.zeros(len(text), np.uint64)
    for k in range(7):
        word = (word << np.uint64(9)) | symbols[k : k + len(text)]
    names = _names(word)
    for step in (7, 14, 28):
        names = _names((names << 32) | _later(names, step))
    return names


def suffix_array(text: np.ndarray, depth: int | None = None, names: np.ndarray | None = None) -> np.ndarray:
    """Starts of the suffixes of a byte array in order, exact up to depth bytes (all of them if None).

    Two stages: suffixes smaller than their successors are sorted directly, by ranks of SPAN bytes at a time; the others are
    induced, bucket by bucket of their first byte in rising order, from the suffixes that follow them.
    """
    n = len(text)
    if n == 0:
        return np.empty(0, np.int64)
    names = span_names(text) if names is None else names
    ends = np.append(np.flatnonzero(text[1:] != text[:-1]), n - 1)
    rising = np.append(text[ends[1:]] > text[ends[:-1]], False)
    smaller = np.repeat(rising, np.diff(np.concatenate([[-1], ends])))
    direct = np.flatnonzero(smaller)
    order = np.argsort(names[direct], kind="stable")
    direct = direct[order]
    group = np.cumsum(np.concatenate([[0], (np.diff(names[direct]) != 0).astype(np.int64)])) if len(direct) else direct
    at = SPAN
    while len(direct) and at < (n if depth is None else depth):
        tied = np.zeros(len(direct), bool)
        same = group[1:] == group[:-1]
        tied[1:] |= same
        tied[:-1] |= same
        where = np.flatnonzero(tied)
        if not len(where):
            break
        key = (group[where] << 32) | _later(names, direct[where] + at)
        order = np.argsort(key, kind="stable")
        direct[where] = direct[where[order]]
        key = key[order]
        fresh = np.zeros(len(direct), np.int64)
        fresh[where[1:]] = (key[1:] != key[:-1]) & (group[where[1:]] == group[where[:-1]])
        group = group + np.cumsum(fresh)
        at += SPAN
    pending: list[list[np.ndarray]] = [[] for _ in range(256)]
    starts = np.searchsorted(text[direct], np.arange(257))
    out: list[np.ndarray] = []
    for c in range(256):
        waiting = pending[c]
        if text[n - 1] == c:
            waiting.insert(0, np.array([n - 1]))
        fresh = np.concatenate(waiting) if waiting else np.empty(0, np.int64)
        parts = []
        while len(fresh):
            parts.append(fresh)
            before = fresh[fresh > 0] - 1
            fresh = before[(text[before] == c) & ~smaller[before]]
        parts.append(direct[starts[c] : starts[c + 1]])
        whole = np.concatenate(parts)
        if not len(whole):
            continue
        out.append(whole)
        before = whole[whole > 0] - 1
        before = before[(text[before] > c) & ~smaller[before]]
        if len(before):
            lead = text[before]
            order = np.argsort(lead, kind="stable")
            before, lead = before[order], lead[order]
            cuts = np.flatnonzero(lead[1:] != lead[:-1]) + 1
            for part in np.split(before, cuts):
                pending[text[part[0]]].append(part)
    return np.concatenate(out)


def common_prefixes(text: np.ndarray, a: np.ndarray, b: np.ndarray, most: int, names: np.ndarray) -> np.ndarray:
    """Length of the common prefix of the suffixes at a and b, up to most bytes."""
    out = np.zeros(len(a), np.int64)
    live = np.arange(len(a))
    while len(live):
        x, y = a[live] + out[live], b[live] + out[live]
        same = (_later(names, x) == _later(names, y)) & (np.maximum(x, y) + SPAN <= len(text)) & (out[live] < most)
        live = live[same]
        out[live] += SPAN
    live = np.flatnonzero(out < most)
    while len(live):
        x, y = a[live] + out[live], b[live] + out[live]
        inside = np.maximum(x, y) < len(text)
        live, x, y = live[inside], x[inside], y[inside]
        live = live[text[x] == text[y]]
        out[live] += 1
        live = live[out[live] < most]
    return np.minimum(out, most)


CLASS = 46


def repeated_windows(contexts: list[tuple[int, bytes, int, int, bool]], length: int = LENGTH) -> list[np.ndarray]:
    """Of each context, the window starts (relative to its body) whose window occurs in another context as well.

    A context is (gram, body, rel, n_windows, single): rel is its anchor's place, so its windows start at 0..n_windows-1. Contexts
    that are not single are only compared with. Classes of CLASS neighbouring windows are first told apart by the bytes that
    all of them cover; what is left is sorted as suffixes.
    """
    found = [np.empty(0, np.int64)] * len(contexts)
    seen: dict[int, list[int]] = {}
    keyed = []
    for k, (gram, body, rel, n, single) in enumerate(contexts):
        for c in range(max(0, rel - n + 1) // CLASS, rel // CLASS + 1):
            a = rel - c * CLASS
            key = xxhash.xxh3_64_intdigest(body[max(a, 0) : max(a, 0) + length - CLASS + 1 - max(-a, 0)] if a >= 0 else b"", seed=(gram ^ (c * 0x9E3779B97F4A7C15)) & (2**64 - 1))
            keyed.append((k, c, key))
            entry = seen.setdefault(key, [0, 0])
            entry[0] += 1
            entry[1] += single
    low: dict[int, list[int]] = {}
    for k, c, key in keyed:
        if seen[key][0] > 1 and seen[key][1]:
            low.setdefault(k, []).append(c)
    if not low:
        return found
    parts, owners, valid, at = [], [], [], 0
    for k, classes in low.items():
        gram, body, rel, n, single = contexts[k]
        lo, hi = max(0, rel - max(classes) * CLASS - CLASS + 1), min(n - 1, rel - min(classes) * CLASS)
        if hi < lo:
            continue
        part = np.frombuffer(body, np.uint8)[lo : hi + length]
        parts.append(part)
        owners.append((at, k, lo, hi - lo + 1))
        valid.append(np.arange(at, at + hi - lo + 1))
        at += len(part)
    if not parts:
        return found
    text = np.concatenate(parts)
    names = span_names(text)
    order = suffix_array(text, length, names)
    is_window = np.zeros(len(text), bool)
    is_window[np.concatenate(valid)] = True
    order = order[is_window[order]]
    equal = common_prefixes(text, order[:-1], order[1:], length, names) >= length
    hit = np.zeros(len(text), bool)
    hit[order[:-1][equal]] = True
    hit[order[1:][equal]] = True
    for start, k, lo, n in owners:
        if contexts[k][4]:
            found[k] = np.flatnonzero(hit[start : start + n]) + lo
    return found


def _runs(starts: np.ndarray, length: int) -> list[tuple[int, int]]:
    """Byte ranges covered by windows at sorted starts."""
    if not len(starts):
        return []
    cuts = np.flatnonzero(np.diff(starts) > length) + 1
    return [(int(p[0]), int(p[-1]) + length) for p in np.split(starts, cuts)]


ANCHORS = "row long, lo int, hi int, rel int, gram long, stretch long"
SPANS = "row long, lo long, hi long"


def _find_anchors(length: int):
    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for begin in range(0, b.num_rows, 500):
                cols: list[list[np.ndarray]] = [[np.empty(0, np.int64)] for _ in range(6)]
                part = b.slice(begin, 500)
                for row, text in zip(part.column(0).to_pylist(), part.column(1), strict=True):
                    body = (text.as_py() or "").encode("utf-8", "surrogatepass")
                    for at in range(0, max(1, len(body) - length + 1), PART):
                        data = body[at : at + PART + length - 1]
                        x, lo, hi, h = anchors(np.frombuffer(data, np.uint8), length)
                        if not len(x):
                            continue
                        f = [xxhash.xxh3_64_intdigest(data[p : q + length], seed=r) for p, q, r in zip(lo.tolist(), hi.tolist(), (x - lo).tolist(), strict=True)]
                        for c, v in zip(cols, (np.full(len(x), row), lo + at, hi + at, x - lo, h.view(np.int64), np.array(f, np.uint64).view(np.int64)), strict=True):
                            c.append(v)
                kinds = [x.split() for x in ANCHORS.split(", ")]
                arrays = [pa.array(np.concatenate(c), pa.int64() if k == "long" else pa.int32()) for c, (_, k) in zip(cols, kinds, strict=True)]
                yield pa.RecordBatch.from_arrays(arrays, [n for n, _ in kinds])

    return scan


CONTEXTS = "gram long, row long, lo int, rel int, n int, single boolean, crowd int, body binary"
CONTEXT = ["gram", "row", "lo", "rel", "n", "single", "body"]


def _cut_contexts(length: int):
    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split()[0] for x in CONTEXTS.split(", ")]
        types = [pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.bool_(), pa.int32(), pa.binary()]
        for b in batches:
            for begin in range(0, b.num_rows, 200):
                part, rows = b.slice(begin, 200), []
                for row, text, wanted in zip(part.column(0).to_pylist(), part.column(1), part.column(2), strict=True):
                    body = (text.as_py() or "").encode("utf-8", "surrogatepass")
                    for w in wanted.as_py():
                        rows.append((w["gram"], row, w["lo"], w["rel"], w["hi"] - w["lo"] + 1, w["n"] == 1, w["k"], body[w["lo"] : w["hi"] + length]))
                cols = list(zip(*rows, strict=True)) if rows else [[]] * 8
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names)

    return cut


def _sort_suffixes(length: int):
    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size, last = 0, None

        def flush() -> pa.RecordBatch:
            hits = repeated_windows([(h[0], h[6], h[3], h[4], h[5]) for h in held], length)
            rows = [(h[1], h[2] + a, h[2] + z) for h, own in zip(held, hits, strict=True) for a, z in _runs(own, length)]
            held.clear()
            return _spans(rows)

        for b in batches:
            for begin in range(0, b.num_rows, 1000):
                for h in zip(*(c.to_pylist() for c in b.slice(begin, 1000).columns), strict=True):
                    if size > BATCH and h[0] != last:
                        yield flush()
                        size = 0
                    last = h[0]
                    held.append(h)
                    size += len(h[6])
        if held:
            yield flush()

    return mark


def _spans(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) if rows else [[]] * 3
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], ["row", "lo", "hi"])


#: Widths, in windows, of the classes that a crowded group is cut into, one after the other; at width 1 a group is one window.
WIDTHS = (CLASS, 6, 1)
CLASSES = "key long, cover long, row long, lo int, rel int, n int, single boolean, body binary"


def _cut_classes(length: int, width: int):
    """The windows of each context in classes of width by their place before the anchor: a hash of all bytes of the class (key), one
    of the bytes that every window of the class covers (cover), and the class as a context of its own."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split() for x in CLASSES.split(", ")]
        types = {"long": pa.int64(), "int": pa.int32(), "boolean": pa.bool_(), "binary": pa.binary()}
        for b in batches:
            for begin in range(0, b.num_rows, 500):
                rows, part = [], b.slice(begin, 500)
                for k in range(part.num_rows):
                    group, row, lo, rel, n, single, body = (part.column(c)[k].as_py() for c in range(7))
                    for c in range((rel - n + 1) // width, rel // width + 1):
                        a, z = max(0, rel - c * width - width + 1), min(n - 1, rel - c * width)
                        seed = (group * 31 + c * 0x9E3779B97F4A7C15) & (2**64 - 1)
                        key = xxhash.xxh3_64_intdigest(body[a : z + length], seed=(seed + (rel - a) * 0xD6E8FEB86659FD93) & (2**64 - 1))
                        cover = xxhash.xxh3_64_intdigest(body[rel - c * width : rel - c * width - width + 1 + length], seed=seed)
                        rows.append((_signed(key), _signed(cover), row, lo + a, rel - a, z - a + 1, single, body[a : z + length]))
                cols = list(zip(*rows, strict=True)) if rows else [[]] * len(names)
                yield pa.RecordBatch.from_arrays([pa.array(c, types[t]) for c, (_, t) in zip(cols, names, strict=True)], [n for n, _ in names])

    return cut


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _divided(crowded: DataFrame, length: int, group: int) -> tuple[DataFrame, list[DataFrame]]:
    """Contexts of groups that one task can sort, and the spans that were found while cutting the crowded ones.

    Equal windows agree in the bytes that all windows of their class cover, so they stay in one group at every width. Equal classes
    are collapsed: one that occurs twice is repeated as a whole, and stays as an entry to compare with.
    """
    todo, small, spans = crowded.select(F.col("gram").alias("group"), "row", "lo", "rel", "n", "single", "body"), [], []
    for width in WIDTHS:
        rows = stage(todo.mapInArrow(_cut_classes(length, width), CLASSES), "classes")
        facts = F.min(F.struct("row", "lo", "rel", "n")).alias("at")
        entries = rows.groupBy("cover", "key").agg(F.count(F.lit(1)).alias("m"), F.max("single").alias("some"), facts)
        entries = stage(entries, "class-entries")
        twice = rows.where("single").join(entries.where("m > 1").select("cover", "key"), ["cover", "key"], "left_semi")
        spans.append(twice.select("row", F.col("lo").cast("long").alias("lo"), (F.col("lo") + F.col("n") - 1 + F.lit(length)).cast("long").alias("hi")))
        groups = entries.groupBy("cover").agg(F.count(F.lit(1)).alias("k"), F.max(F.col("some") & (F.col("m") == 1)).alias("open"))
        groups = stage(groups.where("k > 1 and open").select("cover", "k"), "class-groups")
        left = entries.join(broadcast_if_small(groups, 12), "cover").select("cover", "k", "at.*", (F.col("some") & (F.col("m") == 1)).alias("single"))
        bodies = rows.select("cover", "row", "lo", "rel", "n", "body").dropDuplicates(["cover", "row", "lo", "rel", "n"])
        left = stage(left.join(bodies, ["cover", "row", "lo", "rel", "n"]), "class-contexts")
        small.append(left.where(F.col("k") <= group).select(F.col("cover").alias("gram"), "row", "lo", "rel", "n", "single", "body"))
        todo = left.where(F.col("k") > group).select(F.col("cover").alias("group"), "row", "lo", "rel", "n", "single", "body")
    return reduce(DataFrame.unionByName, small), spans


def repeated_spans(docs: DataFrame, length: int = LENGTH, group: int = GROUP) -> DataFrame:
    """row, lo, hi: byte ranges of docs (row long, text string) that repeated strings of length bytes cover (may overlap)."""
    found = stage(docs.select("row", "text").mapInArrow(_find_anchors(length), ANCHORS), "anchors")
    repeated = stage(found.groupBy("gram").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("gram"), "repeated-grams")
    live = stage(found.join(broadcast_if_small(repeated, 16), "gram", "left_semi").select("row", "lo", "hi", "rel", "gram", "stretch"), "live-anchors")
    by_stretch = live.groupBy("gram", "stretch").agg(F.count(F.lit(1)).alias("n"), F.min(F.struct("row", "lo", "hi", "rel")).alias("at"))
    by_stretch = stage(by_stretch, "stretches")
    twice = by_stretch.where("n > 1").select("gram", "stretch")
    whole = live.join(broadcast_if_small(twice, 24), ["gram", "stretch"], "left_semi").select("row", F.col("lo").cast("long"), (F.col("hi") + F.lit(length)).cast("long").alias("hi"))
    mixed = by_stretch.groupBy("gram").agg(F.count(F.lit(1)).cast("int").alias("k"), F.min("n").alias("least")).where("k > 1 and least = 1").select("gram", "k")
    fine = by_stretch.join(broadcast_if_small(stage(mixed, "mixed-grams"), 20), "gram")
    wanted = stage(fine.groupBy("at.row").agg(F.collect_list(F.struct("gram", "at.lo", "at.hi", "at.rel", "n", "k")).alias("wanted"), F.count(F.lit(1)).alias("m")), "wanted")
    total = wanted.agg(F.coalesce(F.sum("m"), F.lit(0))).first()[0]
    lists = wanted.drop("m")
    joined = docs.select("row", "text").join(F.broadcast(lists) if total * 96 < LISTS else lists, "row")
    contexts = stage(joined.select("row", "text", "wanted").mapInArrow(_cut_contexts(length), CONTEXTS), "contexts")
    ready, spans = contexts.where(F.col("crowd") <= group).drop("crowd"), []
    crowded = contexts.where(F.col("crowd") > group).drop("crowd")
    if crowded.limit(1).count():
        more, spans = _divided(crowded, length, group)
        ready = ready.unionByName(more)
    sorted_ = ready.select(*CONTEXT).repartition("gram").sortWithinPartitions("gram").mapInArrow(_sort_suffixes(length), SPANS)
    return reduce(DataFrame.unionByName, [whole, sorted_, *spans])


def _merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, with_bytes: bool = False, group: int = GROUP) -> DataFrame:
    """doc_id, text (what is left), n_bytes, n_removed, n_spans, kept_sha256 and, with_bytes, the kept bytes (binary) of every row.

    Where a removed range cuts a character, text leaves its other bytes out, too; kept and kept_sha256 have them. A byte goes if any string of length bytes over it starts anywhere else in the corpus too, the same text included; strings
    are judged on the whole input. Null text is empty. Rows with equal id and text are all kept as rows, and repeat each other.
    An empty table gives an empty result; other columns are not read. Ranges are per text, and no occurrence is capped.
    """
    kind = docs.schema[id_col].dataType.simpleString()
    keyed = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).withColumn("row", F.xxhash64("doc_id", "text"))
    spans = repeated_spans(keyed, length, group).groupBy("row").agg(F.collect_list(F.struct("lo", "hi")).alias("spans"))

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            merged = [[{"lo": a, "hi": z} for a, z in _merged([(x["lo"], x["hi"]) for x in own])] for own in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(merged, pa.list_(pa.struct([("lo", pa.int64()), ("hi", pa.int64())])))], ["row", "spans"])

    spans = stage(spans.mapInArrow(merge, "row long, spans array<struct<lo:long,hi:long>>"), "spans")
    total = spans.agg(F.coalesce(F.sum(F.size("spans") + 3), F.lit(0))).first()[0]

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for begin in range(0, b.num_rows, 200):
                part, rows = b.slice(begin, 200), []
                for text, own in zip(part.column(1), part.column(2), strict=True):
                    body = text.as_py().encode("utf-8", "surrogatepass")
                    ranges = [(x["lo"], x["hi"]) for x in own.as_py() or ()]
                    kept, at = [], 0
                    for a, z in ranges:
                        kept.append(body[at:a])
                        at = z
                    left = b"".join([*kept, body[at:]])
                    rows.append((left.decode("utf-8", "ignore"), len(body), len(body) - len(left), len(ranges), hashlib.sha256(left).hexdigest(), left if with_bytes else None))
                cols = list(zip(*rows, strict=True))
                arrays = [part.column(0), *(pa.array(c, t) for c, t in zip(cols, (pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary()), strict=True))]
                yield pa.RecordBatch.from_arrays(arrays[: 6 + with_bytes], ["doc_id", "text", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"][: 6 + with_bytes])

    joined = keyed.join(F.broadcast(spans) if total * 32 < LISTS else spans, "row", "left")
    return joined.select("doc_id", "text", "spans").mapInArrow(cut, f"doc_id {kind}, text string, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept binary" * with_bytes)

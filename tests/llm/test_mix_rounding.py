"""Whole documents of the source mix: long ones stay at their source's rate."""

import sys
from collections import Counter
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent))
from test_text_operators import words  # noqa: E402

from simweave.llm import mixing as M


def test_long_documents_survive_a_low_rate(spark):
    sizes = {"a": (190, 100), "b": (76, 100), "c": (60, 400), "d": (190, 100), "e": (76, 100), "f": (32, 100)}
    rows = [(f"{s}", k, n) for s, (count, n) in sizes.items() for k in range(count)]
    docs = spark.createDataFrame([(i, words(n, i), s) for i, (s, _, n) in enumerate(rows)], "doc_id long, text string, source string")
    mixed = M.mix_documents(docs, block=8, n_shards=8).collect()
    target = {r["source"]: r["target"] for r in mixed}
    rate = target["c"] / (60 * 400)
    assert 0.2 < rate < 0.4
    got, total, seeds = Counter(), Counter(), range(3)
    for seed in seeds:
        out = M.repeat_by_mix(docs, block=8, n_shards=8, seed=seed).select("doc_id", "source").collect()
        times = Counter(r["doc_id"] for r in out)
        assert max(times.values()) <= 2
        got.update(r["source"] for r in out)
    for s, (_, n) in sizes.items():
        total[s] = got[s] * n / len(seeds)
    assert all(total[s] == pytest.approx(target[s], rel=0.3) for s in sizes)
    again = [sorted(r["doc_id"] for r in M.repeat_by_mix(docs.repartition(p), block=8, n_shards=8).select("doc_id").collect()) for p in (3, 7)]
    assert again[0] == again[1]

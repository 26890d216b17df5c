"""Queries over whole tables that SQL is too slow for, and caps."""

from itertools import combinations

from simweave.operators.vectorize import shingle_sets
from simweave.plans.planner import similarity_join
from simweave.queries import load

D = "/root/testdata/sf0.01"
QUERIES, ORACLES = load()


def test_nothing_stays_open(spark):
    """Every pair is decided, with as many bits as its estimate needs; a small cap leaves pairs open."""
    assert {r["status"] for r in QUERIES["v01_estimate_cosine"](spark, D).select("status").distinct().collect()} == {"accepted"}
    assert QUERIES["v07_emit_on_cap"](spark, D).limit(1).count() == 1


def test_collections_meet(spark):
    assert QUERIES["c09_cross_collection"](spark, D).count() > 20


def test_incremental_join_reaches_late_documents(spark, tmp_path):
    text = lambda k: " ".join(f"w{(k * 7919 + i * i * 31) % 100_003}" for i in range(40))
    docs = [(k, text(k)) for k in range(330)] + [(1000 + k, text(k)) for k in (0, 299, 300, 329)]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    out = QUERIES["s04_incremental_join"](spark, str(tmp_path)).collect()
    sets = {k: {tuple(t.split()[i : i + 3]) for i in range(38)} for k, t in docs}
    truth = {(a, b) for a, b in combinations(sorted(sets), 2) if 2 * len(sets[a] & sets[b]) >= len(sets[a] | sets[b])}
    assert {(k, 1000 + k) for k in (0, 299, 300, 329)} <= truth == {(r["id_a"], r["id_b"]) for r in out}
    once = similarity_join(shingle_sets(spark.read.parquet(f"{tmp_path}/documents.parquet")), "jaccard", 0.5, "bands", "estimate")
    key = lambda r: (r["id_a"], r["id_b"], round(r["similarity"], 6), r["n_used"], r["matches"], r["status"])
    assert sorted(map(key, out)) == sorted(map(key, once.collect()))

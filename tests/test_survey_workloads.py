"""Workloads on the collections, thresholds, methods and parameter values of the survey."""

import time

import pytest

from simweave import workloads as W
from simweave.operators.exact import brute_force_join
from simweave.plans.staging import stage
from simweave.queries import load

D = "/root/testdata/sf0.001"
QUERIES, _ = load()


def test_pruning_curves_include_document_vectors(spark):
    rows = QUERIES["w08_pruning_curves"](spark, D).collect()
    assert {r["collection"] for r in rows} == {"docs_tfidf", "cust_supp", "docs_words"}
    for name in ("docs_tfidf", "docs_words"):
        left = [r["not_pruned"] for r in sorted(rows, key=lambda r: r["n"]) if r["collection"] == name]
        assert left == sorted(left, reverse=True) and left[-1] < left[0]


def test_sweep_has_all_values_and_the_published_directions(spark):
    rows = {(r["parameter"], r["value"]): r for r in W.parameter_sweep(spark, D, values=(0.03, 0.09)).collect()}
    assert set(rows) == {(p, v) for p in ("gamma", "delta", "eps") for v in (0.03, 0.09)}
    assert rows["delta", 0.03]["hashes"] > rows["delta", 0.09]["hashes"] and rows["delta", 0.03]["mean_error"] <= rows["delta", 0.09]["mean_error"]
    assert rows["gamma", 0.03]["hashes"] >= rows["gamma", 0.09]["hashes"] and all(r["recall"] >= 0.9 for r in rows.values())


def test_quality_table_against_plain_counts(spark):
    got = {(r["method"], r["t"]): r for r in W.quality_table(spark, D, "docs_tfidf", "cosine", (0.7, 0.9), ("wp_exact", "wp_pe", "bs_ml"), family="table").collect()}
    objects = stage(W.collection(spark, D, "docs_tfidf"), "objects")
    exact = {(r["id_a"], r["id_b"]): r["similarity"] for r in brute_force_join(objects, 1e-6, "cosine").collect()}
    for (method, t), r in got.items():
        found = {(x["id_a"], x["id_b"]): x["similarity"] for x in W.run_method(objects, method, "cosine", t, family="table").collect()}
        truth = {k for k, s in exact.items() if round(s, 9) >= t}
        off = [abs(s - exact.get(k, 0.0)) for k, s in found.items()]
        assert (r["truth"], r["found"]) == (len(truth), len(truth & set(found))) and truth
        assert r["recall"] == pytest.approx(len(truth & set(found)) / len(truth), abs=1e-6) and r["recall"] >= 0.9
        assert r["mean_error"] == pytest.approx(sum(off) / len(off), abs=1e-6) and r["error_share"] == pytest.approx(sum(x > 0.05 for x in off) / len(off), abs=1e-6)


def test_recall_of_both_pruned_verifications(spark):
    rows = W.quality_table(spark, D, "docs_tfidf", "cosine", (0.5, 0.8), ("wp_pe", "wp_px"), family="table").collect()
    assert len(rows) == 4 and all(r["recall"] >= 0.9 for r in rows)


def test_priors_and_savers(spark):
    priors = {r["prior"]: r for r in QUERIES["w12_priors"](spark, D).collect()}
    assert set(priors) == {"flat", "fitted"} and all(r["recall"] >= 0.9 for r in priors.values())
    cost = {r["savers"]: r["evaluations"] for r in QUERIES["w12_inference_savers"](spark, D).collect()}
    assert cost["none"] > cost["fewest matches"] >= cost["fewest matches and cells"]


def test_timed_runs_are_cancelled(spark):
    seconds, late = W.timed(spark, lambda seed: spark.range(seed * 1000), limit=60.0)
    assert not late and seconds > 0
    start = time.perf_counter()
    slow = spark.range(10**13).selectExpr("sum(id % 7)")
    assert W.timed(spark, lambda seed: slow, limit=3.0)[1] and time.perf_counter() - start < 50
    with pytest.raises(ValueError):
        W.timed(spark, lambda seed: W.run_method(spark.range(1), "sp_exact", "cosine", 0.5), limit=5.0)


def test_runs_delete_what_they_staged(spark):
    """After a run of a method, and after each row of a table of measures, only its own rows and what all runs share are left."""
    from pathlib import Path

    from simweave.plans.staging import shared_dir

    objects = stage(W.collection(spark, D, "page_links"), "objects")
    before = {p.name for p in Path(shared_dir(spark)).iterdir()}
    W.timed(spark, lambda seed: W.run_method(objects, "bs_pe", "jaccard", 0.5, seed=seed), limit=300.0, seeds=(1,))
    assert {p.name for p in Path(shared_dir(spark)).iterdir()} == before
    W.quality_table(spark, D, "page_links", "jaccard", (0.5, 0.7), ("bs_pe", "bs_exact"))
    left = [p.name.rpartition("-")[0] for p in Path(shared_dir(spark)).iterdir() if p.name not in before]
    assert left.count("row") == 4 and not {"found", "known", "signatures", "candidates"} & set(left)

"""Joins on small collections: exact methods agree, approximate ones keep their promises, plans have the wanted shape."""

import pytest
from pyspark.sql import functions as F

from simweave.operators import candidates as C
from simweave.operators import exact as X
from simweave.operators import verify as V
from simweave.operators.components import connected_components
from simweave.operators.hashing import minhash, sign_bits
from simweave.operators.ranges import asof_join, range_join
from simweave.operators.vectorize import binary_weights, shingle_sets, tfidf, word_sets
from simweave.plans.staging import keep, release, scratch, stage
from simweave.plans.planner import choose_band_width, fit_beta_prior, similarity_classes, similarity_join, similarity_search
from simweave.workloads import collection, decision_of

D = "/root/testdata/sf0.01"


def pairs(df):
    return {(r["id_a"], r["id_b"]) for r in df.select("id_a", "id_b").collect()}


def sets_of(spark, rows):
    return spark.createDataFrame(rows, "id long, features array<long>")


@pytest.mark.parametrize("measure,t", [("jaccard", 0.4), ("cosine_binary", 0.6)])
def test_exact_set_methods_agree(spark, measure, t):
    sets = collection(spark, D, "page_links")
    truth = pairs(X.brute_force_join(sets, t, measure))
    assert truth
    assert pairs(X.exact_set_join(sets, t, measure)) == truth == pairs(X.exact_set_join(sets, t, measure, suffix=True))
    assert pairs(X.all_pairs_join(sets, t, measure)) == truth
    assert truth <= pairs(X.set_prefix_candidates(sets, t, measure))


@pytest.mark.parametrize("bound", ["l2", "maxweight", "both"])
def test_weighted_prefix_is_complete(spark, bound):
    v = collection(spark, D, "cust_supp")
    truth = pairs(X.brute_force_join(v, 0.5, "cosine"))
    assert truth and pairs(X.exact_weighted_join(v, 0.5, bound)) == truth == pairs(X.exact_weighted_join(v, 0.5, bound, upper_bound_check=True))


def test_strategies_and_groupings_agree(spark):
    sets = shingle_sets(spark.read.parquet(f"{D}/documents.parquet")).where(F.size("features") > 0)
    table = decision_of("jaccard", 0.5, 480)
    s = minhash(sets, 480).cache()
    c = C.banded(s, 3, 27, False).cache()
    key = lambda df: sorted(map(tuple, df.select("id_a", "id_b", "n_used", "matches", "status").collect()))
    base = key(V.verify_estimate(c, s, table, False))
    assert base == key(V.verify_estimate(c, s, table, False, groups=())) == key(V.verify_estimate(c, s, table, False, groups=(64, 128, 256)))
    assert base == key(V.verify_estimate(V.fused_candidates(s, table, 3, 27, False), s, table, False, start=V.FIRST))
    assert pairs(C.banded(s, 3, 27, False, "first_band")) == pairs(c) == pairs(C.banded(s, 3, 27, False, max_bucket=2))


def test_partitioning_does_not_change_bits(spark):
    v = collection(spark, D, "user_events")
    a = {r["id"]: r["sig"] for r in sign_bits(v, 64).collect()}
    b = {r["id"]: r["sig"] for r in sign_bits(v.repartition(7, "feature"), 64).collect()}
    assert a == b and all(0 <= w < 2**32 for s in a.values() for w in s)


def test_extreme_objects(spark):
    sets = sets_of(spark, [(1, []), (2, [5]), (3, [5]), (4, [5, 6]), (5, []), (6, list(range(100, 200))), (7, list(range(100, 200)))])
    found = pairs(similarity_join(sets, "jaccard", 0.9, "bands", "exact"))
    assert found == {(2, 3), (6, 7)}
    assert pairs(similarity_join(sets, "jaccard", 0.9, "bands", "estimate")) == {(2, 3), (6, 7)}
    assert pairs(similarity_join(sets.limit(0), "jaccard", 0.5, "bands", "estimate")) == set()


def test_threshold_is_strict_for_prune_exact_and_inclusive_on_request(spark):
    sets = sets_of(spark, [(1, [1, 2, 3]), (2, [1, 2, 3, 4, 5, 6])])
    given = sets.select(F.lit(1).cast("long").alias("id_a"), F.lit(2).cast("long").alias("id_b")).limit(1)
    assert pairs(similarity_join(sets, "jaccard", 0.5, given, "prune_exact")) == set()
    assert pairs(similarity_join(sets, "jaccard", 0.5, given, "prune_exact", closed=True)) == {(1, 2)}


def test_recall_of_estimates(spark):
    sets = shingle_sets(spark.read.parquet(f"{D}/documents.parquet"))
    truth = pairs(X.brute_force_join(sets, 0.5, "jaccard"))
    for verifier in ("estimate", "prune_exact", "classical"):
        found = pairs(similarity_join(sets, "jaccard", 0.5, "bands", verifier))
        assert len(found & truth) >= 0.95 * len(truth) > 0
    disjoint = pairs(similarity_join(sets, "jaccard", 0.5, "bands", "estimate", reuse_hashes=False))
    assert len(disjoint & truth) >= 0.95 * len(truth)


def test_unknown_arguments(spark):
    sets = sets_of(spark, [(1, [1])])
    for bad in ({"measure": "euclid"}, {"generator": "none"}, {"verifier": "none"}):
        with pytest.raises(ValueError):
            similarity_join(sets, **({"measure": "jaccard", "t": 0.5} | bad))


def test_fused_prune_sits_in_the_join(spark, capsys):
    v = collection(spark, D, "user_events")
    s = spark.createDataFrame(sign_bits(v, 128).collect(), "id long, sig array<long>")
    V.fused_candidates(s, decision_of("cosine", 0.7, 512), 8, 16, True).explain()
    plan = capsys.readouterr().out
    join = next(x for x in plan.splitlines() if "Join" in x)
    assert "bit_count" in join and "CartesianProduct" not in plan


def test_scan_is_pruned(spark, capsys):
    word_sets(spark.read.parquet(f"{D}/documents.parquet")).explain()
    assert "ReadSchema: struct<doc_id:bigint,text:string>" in capsys.readouterr().out


def test_search_topk_and_prior(spark):
    sets = sets_of(spark, [(1, [1, 2, 3]), (2, [1, 2, 3, 4]), (3, [1, 9]), (4, [7])])
    top = similarity_search(sets.where("id = 1"), sets.where("id > 1"), "jaccard", k=1).collect()
    assert [(r["id_b"], round(r["similarity"], 2)) for r in top] == [(2, 0.75)]
    assert fit_beta_prior(C.all_pairs(sets.limit(1)), sets) == (1.0, 1.0)
    assert choose_band_width("cosine", 0.9, 0.03, 10_000, 4096).w in (8, 10, 12, 14, 16, 20, 24, 28, 32)


def test_binary_vectors_have_unit_length(spark):
    v = binary_weights(sets_of(spark, [(1, [1, 2, 3])])).agg(F.sum(F.col("weight") ** 2)).first()[0]
    assert v == pytest.approx(1)
    docs = spark.createDataFrame([(1, "a b"), (2, None), (3, "b c"), (4, "")], "doc_id long, text string")
    assert {r["id"] for r in tfidf(docs).collect()} == {1, 3}


def test_group_bounds():
    assert V.group_bounds(480, 32, 96) == [0, 96, 480] and V.group_bounds(3360, 32, 704) == [0, 128, 512, 3360] and V.group_bounds(37760, 32) == [0, 128, 512, 2048, 8192, 37760]
    assert V.group_bounds(64, 32) == [0, 64] and V.group_bounds(512, 64) == [0, 128, 512] and V.group_bounds(512, 32, 704, 128) == [128, 512] and V.group_bounds(128, 32, 128, 128) == [128]


@pytest.mark.parametrize("measure,name,t", [("jaccard", "docs_words", 0.4), ("cosine", "emb_noisy", 0.6), ("cosine_binary", "docs_words", 0.6)])
def test_lazy_fused_and_eager_walks_agree(spark, measure, name, t):
    objects = stage(collection(spark, "/root/testdata/sf0.001", name), "objects")
    rows = lambda **own: sorted(map(tuple, similarity_join(objects, measure, t, w=8 if measure != "jaccard" else 3, **own).collect()))
    eager = rows(lazy=False, strategy="rounds")
    assert eager and eager == rows(lazy=True, strategy="rounds") == rows(lazy=True, strategy="fused") == rows(max_bucket=3, strategy="fused") == rows(max_bucket=3, strategy="rounds")
    assert rows(verifier="prune_exact", strategy="rounds") == rows(verifier="prune_exact", strategy="fused", max_bucket=2)
    assert rows(reuse_hashes=False, lazy=True) == rows(reuse_hashes=False, lazy=False)


def test_bands_of_any_width(spark):
    s = spark.createDataFrame([(1, [0b1011 | 5 << 30, 7]), (2, [0xFFFFFFFF, 0xFFFFFFFF])], "id long, sig array<long>")
    for w in (5, 12, 20, 32):
        bits = [sum(((x >> k) & 1) << (32 * j + k) for j, x in enumerate(sig) for k in range(32)) for sig in ([0b1011 | (5 << 30 & 0xFFFFFFFF), 7], [0xFFFFFFFF] * 2)]
        got = [r[0] for r in s.where("id = 2").select(C.band_keys(w, 64 // w, True)).collect()]
        assert got[0] == [bits[1] >> (w * b) & ((1 << w) - 1) for b in range(64 // w)]


def test_wider_bands_for_more_objects():
    for measure, t in (("cosine", 0.7), ("jaccard", 0.5)):
        widths = [choose_band_width(measure, t, 0.03, n, 1 << 20).w for n in (10**3, 10**5, 10**7, 10**9)]
        assert widths == sorted(widths) and widths[-1] > widths[0]


@pytest.mark.parametrize("measure,t", [("jaccard", 0.3), ("jaccard", 0.7), ("cosine_binary", 0.6)])
def test_suffix_filter_loses_nothing_and_prunes(spark, measure, t):
    sets = stage(collection(spark, D, "docs_words").where("id < 400"), "sets")
    truth = pairs(X.brute_force_join(sets, t, measure))
    plain, filtered = (pairs(X.set_prefix_candidates(sets, t, measure, suffix=s)) for s in (False, True))
    assert truth <= filtered <= plain and (len(filtered) < len(plain) or len(plain) == len(truth))
    assert pairs(X.set_prefix_candidates(sets, t, measure, suffix=True, max_bucket=5)) == filtered


def test_upper_bound_check_loses_nothing_and_prunes(spark):
    v = stage(collection(spark, "/root/testdata/sf0.001", "cust_supp"), "vectors")
    truth = pairs(X.brute_force_join(v, 0.6, "cosine"))
    plain, checked = (pairs(X.prefix_candidates(v, 0.6, upper_bound_check=c)) for c in (False, True))
    assert truth <= checked < plain and pairs(X.prefix_candidates(v, 0.6, upper_bound_check=True, max_bucket=4)) == checked


def test_representatives_and_members(spark):
    sets = sets_of(spark, [(1, [1, 2, 3, 4]), (5, [1, 2, 3, 4]), (7, [1, 2, 3]), (9, [8])])
    found, members = similarity_classes(sets, "jaccard", 0.5, "sharing", "exact")
    assert pairs(found) == {(1, 7)} and dict(members.select("id", "rep").collect()) == {1: 1, 5: 1, 7: 7, 9: 9}
    assert dict(C.collapse_duplicates(binary_weights(sets))[1].collect()) == {1: 1, 5: 1, 7: 7, 9: 9}


def test_components(spark):
    edges = spark.createDataFrame([(5, 4), (4, 3), (3, 2), (2, 1), (9, 8), (7, 7), (8, 9), (None, 3)], "a long, b long")
    assert dict(connected_components(edges).collect()) == {1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 7: 7, 8: 8, 9: 8}
    chain = spark.range(300).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    assert {r[1] for r in connected_components(chain).collect()} == {0}
    assert connected_components(edges.limit(0)).count() == 0


def test_components_with_hubs_and_too_few_rounds(spark):
    hub = [(k, 5000) for k in range(1, 900)] + [(k, k + 10_000) for k in range(500, 900)] + [(20_000, 20_001)]
    got = dict(connected_components(spark.createDataFrame(hub, "a long, b long")).collect())
    assert {v for k, v in got.items() if k < 20_000} == {1} and got[20_000] == got[20_001] == 20_000 and len(got) == 899 + 1 + 400 + 2
    chain = spark.range(4001).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    with pytest.raises(RuntimeError):
        connected_components(chain, max_rounds=3)


def test_scratch_deletes_what_is_not_kept(spark):
    with scratch():
        gone, kept = stage(spark.range(3), "t"), keep(stage(spark.range(4), "t"))
        with scratch():
            inner = keep(stage(spark.range(5), "t"))
        assert inner.count() == 5
    assert kept.count() == 4
    exists = lambda df: spark._jvm.org.apache.hadoop.fs.Path(df.staged_at).getFileSystem(spark._jsc.hadoopConfiguration()).exists(spark._jvm.org.apache.hadoop.fs.Path(df.staged_at))
    assert exists(kept) and not exists(gone) and not exists(inner)
    release(kept)
    assert not exists(kept)


def test_range_and_asof(spark):
    points = spark.createDataFrame([(1, 0.5), (2, 2.0), (3, 9.0)], "id int, v double")
    bands = spark.createDataFrame([("a", 0.0, 2.0), ("b", 2.0, 5.0)], "n string, lo double, hi double")
    assert sorted((r["id"], r["n"]) for r in range_join(points, "v", bands, "lo", "hi", 0.7).collect()) == [(1, "a"), (2, "b")]
    left = spark.createDataFrame([("k", 5, "x"), ("k", 1, "y"), ("z", 5, "w")], "k string, t int, l string")
    right = spark.createDataFrame([("k", 4, 40), ("k", 5, 50), ("k", 2, 20)], "k string, t int, r int")
    assert sorted((r["l"], r["r"]) for r in asof_join(left, right, "k", "t", ["r"]).collect()) == [("w", None), ("x", 50), ("y", None)]

"""Queries over hash families, packing and signatures."""

from __future__ import annotations

from pyspark.sql import functions as F

from simweave.functions.columns import jaccard, matches, matches_int
from simweave.operators.exact import brute_force_join
from simweave.operators.copies import copies_of, nonempty
from simweave.operators.hashing import extend_signatures, gaussian_table, minhash, sign_bits
from simweave.oracles import sql as S
from simweave.plans.staging import stage
from simweave.queries import query
from simweave.workloads import collection


def _flat(sigs):
    return sigs.select("id", F.posexplode("sig").alias("j", "h"))


@query("h01_minhash", f"SELECT id, j::INT AS j, h FROM ({S.minhash('docs_words', 8)})")
def h01(spark, d):
    return _flat(minhash(collection(spark, d, "docs_words").where(F.size("features") > 0), 8)).select("id", "j", "h")


@query("h02_minhash_wide")
def h02(spark, d):
    return _flat(minhash(collection(spark, d, "docs_words").where(F.size("features") > 0), 8, family="wide"))


def _words(name: str, n: int) -> str:
    return f"SELECT id, (j // 32)::INT AS word, sum(h::BIGINT << (j % 32)::INT)::BIGINT AS bits FROM ({S.sign_bits(name, n)}) GROUP BY id, j // 32"


@query("h03_sign_bits_dense", _words("emb", 64))
def h03_dense(spark, d):
    return _flat(sign_bits(collection(spark, d, "emb"), 64)).select("id", F.col("j").alias("word"), F.col("h").alias("bits"))


@query("h03_sign_bits_sparse", _words("user_events", 128))
def h03_sparse(spark, d):
    return _flat(sign_bits(collection(spark, d, "user_events"), 128)).select("id", F.col("j").alias("word"), F.col("h").alias("bits"))


@query("h04_gaussian_table", f"SELECT feature, j AS hash_no, {S.gaussian_code('x')} AS code FROM (SELECT DISTINCT p_brand AS feature, {S.feature_id('p_brand')} AS x FROM part), {S.gaussian_rows(16)}")
def h04(spark, d):
    brands = spark.read.parquet(f"{d}/part.parquet").select(F.col("p_brand").alias("feature"))
    return gaussian_table(spark, brands, 16)


@query(
    "h05_packed_matches",
    f"""WITH h AS MATERIALIZED ({S.sign_bits('user_events', 64)}) SELECT a.id AS id_a, b.id AS id_b, sum((a.h = b.h)::INT)::INT AS m FROM h a JOIN h b ON a.j = b.j AND a.id < b.id GROUP BY ALL""",
)
def h05(spark, d):
    s = stage(sign_bits(collection(spark, d, "user_events"), 64), "bits")
    a, b = (s.select(F.col("id").alias(f"id_{x}"), F.col("sig").alias(x)) for x in "ab")
    m = matches(F.get("a", F.lit(0)), F.get("b", F.lit(0))) + matches(F.get("a", F.lit(1)), F.get("b", F.lit(1)))
    return a.join(b, F.col("id_a") < F.col("id_b")).select("id_a", "id_b", m.cast("int").alias("m"))


@query(
    "h06_integer_matches",
    f"""WITH h AS MATERIALIZED ({S.minhash('page_links', 32)}) SELECT id_a, id_b, sum((a.h = b.h AND a.j < 16)::INT)::INT AS m16, sum((a.h = b.h)::INT)::INT AS m32
    FROM ({S.truth('page_links', 'jaccard', 0.3)}) p JOIN h a ON a.id = id_a JOIN h b ON b.id = id_b AND a.j = b.j GROUP BY ALL""",
)
def h06(spark, d):
    sets = collection(spark, d, "page_links")
    s = stage(minhash(sets, 32), "hashes")
    p = brute_force_join(sets, 0.3, "jaccard")
    both = p.join(s.select(F.col("id").alias("id_a"), F.col("sig").alias("a")), "id_a").join(s.select(F.col("id").alias("id_b"), F.col("sig").alias("b")), "id_b")
    return both.select("id_a", "id_b", matches_int(F.col("a"), F.col("b"), 0, 16).alias("m16"), matches_int(F.col("a"), F.col("b"), 0, 32).alias("m32"))


@query(
    "h07_collision_law_jaccard",
    f"""WITH h AS MATERIALIZED ({S.minhash('page_links', 256)}) SELECT round(avg(abs(r - s)), 6) AS mean_gap, avg(abs(r - s)) < 0.05 AS close FROM (
      SELECT id_a, id_b, any_value(similarity) AS s, avg((a.h = b.h)::INT) AS r FROM ({S.truth('page_links', 'jaccard', 0.3)}) p JOIN h a ON a.id = id_a JOIN h b ON b.id = id_b AND a.j = b.j GROUP BY ALL)""",
)
def h07_j(spark, d):
    sets = stage(collection(spark, d, "page_links"), "sets")
    copies = copies_of(sets)
    own = copies.reps if copies else sets
    s = stage(minhash(own, 256), "hashes")
    p = brute_force_join(own, 0.3, "jaccard")
    if copies:
        # equal sets agree in all hashes
        p = copies.weighed(p.unionByName(nonempty(copies).withColumn("similarity", F.lit(1.0)))).drop("n_a", "n_b")
    else:
        p = p.withColumn("pairs", F.lit(1))
    both = p.join(s.select(F.col("id").alias("id_a"), F.col("sig").alias("a")), "id_a").join(s.select(F.col("id").alias("id_b"), F.col("sig").alias("b")), "id_b")
    off = F.abs(matches_int(F.col("a"), F.col("b"), 0, 256) / 256 - F.col("similarity"))
    gap = F.sum(off * F.col("pairs")) / F.sum("pairs")
    return both.agg(F.round(gap, 6).alias("mean_gap"), (gap < 0.05).alias("close"))


@query(
    "h07_collision_law_cosine",
    f"""WITH h AS MATERIALIZED ({S.sign_bits('user_events', 256)}), p AS (SELECT * FROM ({S.truth('user_events', 'cosine', 0.3)}))
    SELECT round(avg(abs(r - (1 - acos(least(s, 1)) / pi()))), 6) AS mean_gap, avg(abs(r - (1 - acos(least(s, 1)) / pi()))) < 0.05 AS close FROM (
      SELECT id_a, id_b, any_value(similarity) AS s, avg((a.h = b.h)::INT) AS r FROM p JOIN h a ON a.id = id_a JOIN h b ON b.id = id_b AND a.j = b.j GROUP BY ALL)""",
)
def h07_c(spark, d):
    from simweave.functions.columns import c2r

    v = stage(collection(spark, d, "user_events"), "vectors")
    s = stage(sign_bits(v, 256), "bits")
    p = brute_force_join(v, 0.3, "cosine")
    both = p.join(s.select(F.col("id").alias("id_a"), F.col("sig").alias("a")), "id_a").join(s.select(F.col("id").alias("id_b"), F.col("sig").alias("b")), "id_b")
    m = F.aggregate(F.zip_with("a", "b", lambda x, y: matches(x, y)), F.lit(0), lambda t, x: t + x)
    gap = F.avg(F.abs(m / 256 - c2r(F.col("similarity"))))
    return both.agg(F.round(gap, 6).alias("mean_gap"), (gap < 0.05).alias("close"))


@query("h08_lazy_extension", "SELECT count(*) AS objects, 0::BIGINT AS different FROM (SELECT DISTINCT user_id FROM events WHERE user_id % 2 = 0)")
def h08(spark, d):
    v = stage(collection(spark, d, "user_events"), "vectors")
    whole = sign_bits(v, 128)
    alive = v.where("id % 2 = 0").select("id")
    tail = extend_signatures(v, alive, 64, 128, "cosine").select("id", F.col("sig").alias("tail"))
    both = tail.join(whole, "id")
    return both.agg(F.count(F.lit(1)).alias("objects"), F.coalesce(F.sum((F.slice("sig", 3, 2) != F.col("tail")).cast("long")), F.lit(0)).alias("different"))


@query("h09_mllib")
def h09(spark, d):
    """Pairs found by the library's own MinHash join, beside those at or over the threshold."""
    from pyspark.ml.feature import CountVectorizer, MinHashLSH

    sets = collection(spark, d, "page_links").where(F.size("features") > 0).withColumn("words", F.col("features").cast("array<string>"))
    model = CountVectorizer(inputCol="words", outputCol="v", binary=True).fit(sets)
    vectors = model.transform(sets).select("id", "v")
    lsh = MinHashLSH(inputCol="v", outputCol="h", numHashTables=16, seed=1).fit(vectors)
    found = lsh.approxSimilarityJoin(vectors, vectors, 0.5, "distance").where("datasetA.id < datasetB.id")
    return found.select(F.col("datasetA.id").alias("id_a"), F.col("datasetB.id").alias("id_b"), F.round(1 - F.col("distance"), 6).alias("similarity"))


@query("h10_jaccard_column", f"SELECT id_a, id_b, round(similarity, 6) AS similarity FROM ({S.truth('page_links', 'jaccard', 0.5)})")
def h10(spark, d):
    sets = collection(spark, d, "page_links")
    p = brute_force_join(sets, 0.5, "jaccard").select("id_a", "id_b")
    both = p.join(sets.select(F.col("id").alias("id_a"), F.col("features").alias("a")), "id_a").join(sets.select(F.col("id").alias("id_b"), F.col("features").alias("b")), "id_b")
    return both.select("id_a", "id_b", F.round(jaccard(F.col("a"), F.col("b")), 6).alias("similarity"))



"""Stand-in collections of the experiments, built from the given tables, and the experiment workloads."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from simweave.operators import metrics as M
from simweave.operators.blocks import block_count_join, block_dot_join
from simweave.operators.candidates import banded, num_bands
from simweave.operators.exact import brute_force_join, exact_similarity
from simweave.operators.hashing import HashSource, sign_bits
from simweave.operators.vectorize import dense_vectors, idf_weighted, profile, sets_from_edges, shingle_sets, tfidf, word_sets
from simweave.operators.verify import verify_estimate
from simweave.plans.decision import JoinParams, decision_table, round_up
from simweave.plans.planner import choose_band_width, default_posterior, n_objects_of, similarity_join
from simweave.plans.staging import keep, scratch, stage
from simweave.sources.tables import table

SETS = ("docs_words", "docs_shingles", "order_parts", "part_supp", "supp_part", "cust_brand_set", "page_links")
VECTORS = ("docs_tfidf", "page_words", "cust_supp", "cust_brand", "user_events", "emb", "emb_noisy")


def _lines(spark: SparkSession, d: str) -> DataFrame:
    lines = table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_quantity")
    orders = table(spark, d, "orders", "o_orderkey", "o_custkey")
    return lines.join(orders, lines["l_orderkey"] == orders["o_orderkey"])


def page_texts(spark: SparkSession, d: str) -> DataFrame:
    """page_id and text: tags replaced by blanks, letters only."""
    pages = table(spark, d, "pages", "page_id", "html")
    return pages.select("page_id", F.regexp_replace(F.regexp_replace("html", "<[^>]*>", " "), r"[^\p{L}]+", " ").alias("text"))


def collection(spark: SparkSession, d: str, name: str) -> DataFrame:
    """A collection by name: (id, features) for the set collections, (id, feature, weight) for the vector ones."""
    docs = lambda: table(spark, d, "documents", "doc_id", "text")
    if name == "docs_words":
        return word_sets(docs())
    if name == "docs_shingles":
        return shingle_sets(docs(), 3)
    if name == "docs_long":
        return word_sets(docs()).where(F.size("features") >= 200)
    if name == "docs_all":
        return word_sets(docs()).where(F.size("features") >= 50)
    if name == "order_parts":
        return sets_from_edges(table(spark, d, "lineitem", "l_orderkey", "l_partkey"), "l_orderkey", "l_partkey")
    if name == "part_supp":
        return sets_from_edges(table(spark, d, "lineitem", "l_partkey", "l_suppkey"), "l_partkey", "l_suppkey")
    if name == "supp_part":
        return sets_from_edges(table(spark, d, "lineitem", "l_partkey", "l_suppkey"), "l_suppkey", "l_partkey")
    if name == "page_links":
        pages = table(spark, d, "pages", "page_id", "html")
        links = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))
        return sets_from_edges(links, "page_id", "href")
    if name == "cust_brand_set":
        lines = _lines(spark, d).join(table(spark, d, "part", "p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
        return sets_from_edges(lines, "o_custkey", "p_brand")
    if name == "docs_tfidf":
        return tfidf(docs())
    if name == "page_words":
        return tfidf(page_texts(spark, d), "page_id")
    if name == "cust_supp":
        lines = _lines(spark, d).select(F.col("o_custkey").alias("id"), F.col("l_suppkey").cast("string").alias("feature"), "l_quantity")
        return idf_weighted(lines.groupBy("id", "feature").agg(F.sum("l_quantity").alias("tf")))
    if name == "cust_brand":
        lines = _lines(spark, d).join(table(spark, d, "part", "p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
        counts = lines.groupBy(F.col("o_custkey").alias("id"), F.col("p_brand").alias("feature")).agg(F.sum("l_quantity").alias("tf"))
        norms = counts.groupBy("id").agg(F.sqrt(F.sum(F.col("tf") * F.col("tf"))).alias("n"))
        return counts.join(norms, "id").select("id", "feature", (F.col("tf") / F.col("n")).alias("weight"))
    if name == "user_events":
        events = table(spark, d, "events", "user_id", "ts", "event_type")
        feature = F.concat_ws("-", "event_type", F.hour("ts").cast("string"))
        counts = events.groupBy(F.col("user_id").alias("id"), feature.alias("feature")).agg(F.count(F.lit(1)).cast("double").alias("tf"))
        norms = counts.groupBy("id").agg(F.sqrt(F.sum(F.col("tf") * F.col("tf"))).alias("n"))
        return counts.join(norms, "id").select("id", "feature", (F.col("tf") / F.col("n")).alias("weight"))
    if name in ("emb", "emb_noisy"):
        own = dense_vectors(table(spark, d, "embeddings", "vec_id", "embedding"))
        if name == "emb":
            return own
        noise = (F.pmod(F.col("id") * 31 + F.col("feature").cast("long") * 17, F.lit(11)) - 5) * 0.006
        noisy = own.select((F.col("id") + 1_000_000).alias("id"), "feature", (F.col("weight") + noise).alias("weight"))
        norms = noisy.groupBy("id").agg(F.sqrt(F.sum(F.col("weight") * F.col("weight"))).alias("n"))
        return own.unionByName(noisy.join(norms, "id").select("id", "feature", (F.col("weight") / F.col("n")).alias("weight")))
    raise KeyError(name)


#: Method names of the experiments: generator and verifier.
METHODS = {
    "wp_exact": ("weighted_prefix", "exact"), "wp_pe": ("weighted_prefix", "estimate"), "wp_px": ("weighted_prefix", "prune_exact"),
    "bs_exact": ("bands", "exact"), "bs_ml": ("bands", "classical"), "bs_pe": ("bands", "estimate"), "bs_px": ("bands", "prune_exact"), "sp_exact": ("set_prefix", "exact"),
}


def run_method(objects: DataFrame, method: str, measure: str, t: float, **options) -> DataFrame:
    generator, verifier = METHODS[method]
    if generator == "set_prefix" and measure == "cosine":
        raise ValueError("the positional set join takes binary vectors only")
    return similarity_join(objects, measure, t, generator, verifier, **options)


def w01_profiles(spark: SparkSession, d: str, names: tuple[str, ...] = ("docs_words", "docs_shingles", "order_parts", "part_supp", "page_links", "page_words", "cust_supp", "user_events")) -> DataFrame:
    """The data set table: one profile a collection."""
    rows = [profile(collection(spark, d, n)).withColumn("collection", F.lit(n)) for n in names]
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out.select("collection", "vectors", "dimensions", F.round("avg_length", 6).alias("avg_length"), "non_zeros", F.round("var_length", 4).alias("var_length"))


def counts_over_thresholds(spark: SparkSession, d: str, names: tuple[str, ...], measure: str, thresholds: tuple[float, ...], method: str) -> DataFrame:
    """Result sizes of a method for each collection and threshold (the time tables' workload; seconds are bench's)."""
    out = None
    for n in names:
        objects = stage(collection(spark, d, n), "collection")
        for t in thresholds:
            found = run_method(objects, method, measure, t).agg(F.count(F.lit(1)).alias("pairs"))
            row = found.select(F.lit(n).alias("collection"), F.lit(t).alias("t"), "pairs")
            out = row if out is None else out.unionByName(row)
    return out


def timed(spark: SparkSession, run, limit: float, seeds: tuple[int, ...] = (1, 2, 3)) -> tuple[float, bool]:
    """Mean seconds of run(seed).write to a sink that drops its rows, and whether a run passed limit seconds and was cancelled (the
    seconds are then a lower bound)."""
    from pyspark import InheritableThread

    total = 0.0
    for k, seed in enumerate(seeds, 1):
        group, failed = f"timed-{uuid.uuid4().hex[:8]}", []

        def work(seed=seed, group=group, failed=failed) -> None:
            # no thread interrupts: after one, a task read unmapped memory and the JVM ended; tasks stop at their next row instead
            spark.sparkContext.setJobGroup(group, "timed run", interruptOnCancel=False)
            try:
                with scratch(always=True):
                    run(seed).write.format("noop").mode("overwrite").save()
            except Exception as e:  # noqa: BLE001 - raised below unless it is the cancellation
                failed.append(e)

        thread, start = InheritableThread(target=work), time.perf_counter()
        thread.start()
        thread.join(limit)
        late = thread.is_alive()
        while thread.is_alive():
            spark.sparkContext.cancelJobGroup(group)
            thread.join(1.0)
        total += time.perf_counter() - start
        if late:
            return total / k, True
        if failed:
            raise failed[0]
    return total / len(seeds), False


#: Independent runs that a table of measures submits at once; their small jobs leave most cores idle one by one.
AT_ONCE = 4


def side_by_side(one: Callable[..., DataFrame], cases: Iterable) -> DataFrame:
    """The rows of one(case) for all cases, in order: each is written by its own thread, which then deletes what it staged, and an error
    in one is raised."""

    def work(case) -> DataFrame:
        with scratch():
            return keep(stage(one(case), "row"))

    with ThreadPoolExecutor(AT_ONCE) as pool:
        return reduce(DataFrame.unionByName, list(pool.map(inheritable_thread_target(work), cases)))


def all_pairs_at(objects: DataFrame, t: float, measure: str) -> DataFrame:
    """Truth as brute_force_join has it, in blocks: no pair is shuffled."""
    return block_dot_join(objects, t) if measure == "cosine" else block_count_join(objects, t, measure)


def quality_table(spark: SparkSession, d: str, name: str, measure: str, thresholds: tuple[float, ...], methods: tuple[str, ...], **options) -> DataFrame:
    """Recall, error share and mean error of methods over thresholds: method, t, found, truth, recall, error_share, mean_error.

    The truth is joined once, at the lowest threshold, and so are the exact similarities of what a method finds.
    """
    objects = stage(collection(spark, d, name), "collection")
    lowest = stage(all_pairs_at(objects, min(thresholds), measure), "truth")

    def one(case: tuple[float, str]) -> DataFrame:
        t, m = case
        truth = lowest.where(F.round("similarity", 9) >= t)
        found = stage(run_method(objects, m, measure, t, **options), "found")
        known = stage(exact_similarity(found.select("id_a", "id_b"), objects, measure), "known")
        row = M.recall(found, truth).join(F.broadcast(M.errors(found, known, 0.05)))
        return row.select(F.lit(m).alias("method"), F.lit(t).alias("t"), "found", "truth", F.round("recall", 6).alias("recall"), F.round("error_share", 6).alias("error_share"), F.round("mean_error", 6).alias("mean_error"))

    return side_by_side(one, [(t, m) for t in thresholds for m in methods])


def trail(spark: SparkSession, d: str, name: str, measure: str, t: float, generator: str = "bands", **options) -> DataFrame:
    """Every candidate's walk (pruned ones too) of the posterior-estimate method."""
    return similarity_join(collection(spark, d, name), measure, t, generator, "estimate", with_trail=True, **options)


def w08_pruning_curves(spark: SparkSession, d: str, names: tuple[tuple[str, str], ...] = (("page_words", "cosine"), ("cust_supp", "cosine"), ("docs_words", "cosine_binary")), t: float = 0.7, **options) -> DataFrame:
    """Candidates left after n hashes for each collection."""
    out = None
    for n, measure in names:
        curve = M.pruning_curve(trail(spark, d, n, measure, t, family="table", **options), 32).withColumn("collection", F.lit(n))
        out = curve if out is None else out.unionByName(curve)
    return out


def parameter_sweep(spark: SparkSession, d: str, name: str = "docs_tfidf", t: float = 0.7, values: tuple[float, ...] = (0.01, 0.03, 0.05, 0.07, 0.09), family: str = "table", cap: int | None = None, quality: bool = True, **options) -> DataFrame:
    """gamma, delta and eps in turn over values, the other two at 0.05: parameter, value, hashes compared and, with quality, error
    share, mean error and recall. Candidates are found once, and hashes are made as long as pairs are open."""
    objects = stage(collection(spark, d, name), "collection")
    width = choose_band_width("cosine", t, 0.03, n_objects_of(objects)).w
    bands = num_bands(t, width, 0.03, "cosine")
    made = round_up(max(width * bands, 512), 32)
    sigs = stage(sign_bits(objects, made, family=family), "sweep-bits")
    pairs = stage(banded(sigs, width, bands, True), "sweep-pairs")
    truth = stage(brute_force_join(objects, t, "cosine"), "truth") if quality else None
    known = stage(exact_similarity(pairs, objects, "cosine"), "known") if quality else None

    def one(case: tuple[str, float]) -> DataFrame:
        parameter, v = case
        own = {"gamma": 0.05, "delta": 0.05, "eps": 0.05, parameter: v}
        table_ = decision_table(default_posterior("cosine"), JoinParams(t, cap=cap, **own))
        walk = stage(verify_estimate(pairs, HashSource(sigs, made, objects, "cosine", family=family), table_, True, with_trail=True, **options), "sweep")
        hashes = walk.agg(F.sum("n_used").alias("hashes")).select(F.lit(parameter).alias("parameter"), F.lit(v).alias("value"), "hashes")
        if not quality:
            return hashes
        found = walk.where("status <> 'pruned'")
        row = hashes.join(F.broadcast(M.recall(found, truth))).join(F.broadcast(M.errors(found, known, 0.05)))
        return row.select("parameter", "value", "hashes", F.round("error_share", 6).alias("error_share"), F.round("mean_error", 6).alias("mean_error"), F.round("recall", 6).alias("recall"))

    return side_by_side(one, [(parameter, v) for parameter in ("gamma", "delta", "eps") for v in values])


def decision_of(measure: str, t: float, cap: int | None = None, **own):
    return decision_table(default_posterior(measure), JoinParams(t, cap=cap, **own))

"""Queries over cost and accuracy measures and the experiment workloads."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from simweave.operators import candidates as C
from simweave.operators import exact as X
from simweave.functions.posterior import BetaPosterior
from simweave.operators import metrics as M
from simweave.operators import verify as V
from simweave.operators.components import connected_components
from simweave.operators.hashing import minhash, sign_bits
from simweave.operators.vectorize import shingle_sets
from simweave.oracles import sql as S
from simweave.plans.decision import JoinParams, decision_table
from simweave.plans.planner import default_posterior, fit_beta_prior, similarity_join
from simweave.plans.staging import keep, scratch, stage
from simweave.queries import query
from simweave.queries.joins import _prefix_sql
from simweave.sources.tables import table
from simweave.workloads import METHODS, all_pairs_at, collection, counts_over_thresholds, parameter_sweep, quality_table, run_method, timed, trail, w01_profiles, w08_pruning_curves

NAME, T = "user_events", 0.5
#: Hashes that the required accuracy takes at any similarity.
CAP = decision_table(default_posterior("cosine"), JoinParams(T)).cap


def _table(measure: str, t: float, cap: int, estimates: bool = True, **own):
    return decision_table(default_posterior(measure), JoinParams(t, cap=cap, **own), estimates)


def _walk_ctes(name: str, t: float, cap: int, generator: str = "bands", estimates: bool = True, **own) -> str:
    """CTEs h (hashes), c (candidates), k (walk of every candidate) and e (exact pairs) for weighted cosine."""
    bands = C.num_bands(t, 8, 0.03, "cosine")
    n = max(cap, -(-bands * 8 // 32) * 32)
    if generator == "bands":
        pairs = S.bands("h", 8, bands)
    else:
        pairs = f"SELECT DISTINCT a.id AS id_a, b.id AS id_b FROM ({_prefix_sql(name, t)}) a JOIN ({_prefix_sql(name, t)}) b ON a.feature = b.feature AND a.id < b.id"
    return f"""h AS MATERIALIZED ({S.sign_bits(name, n)}), c AS MATERIALIZED ({pairs}), k AS MATERIALIZED ({S.walk('h', 'SELECT * FROM c', _table('cosine', t, cap, estimates, **own))}),
      e AS MATERIALIZED ({S.truth(name, 'cosine', 0.0)}), o AS (SELECT id_a, id_b, {S.estimate('cosine')} AS est FROM k WHERE status <> 'pruned'),
      tr AS (SELECT * FROM e WHERE round(similarity, 9) >= {t})"""


def _trail(spark, d, cap=CAP):
    return stage(trail(spark, d, NAME, "cosine", T, cap=cap, w=8), "trail")


def _weighed_trail(spark, d, cap=CAP):
    """The walks of all candidates as numbers of pairs: by pairs of distinct objects or, where most pairs are candidates, by their ends."""
    return stage(trail(spark, d, NAME, "cosine", T, cap=cap, w=8, copies="counted"), "trail")


def _truth(spark, d):
    objects = stage(collection(spark, d, NAME), "objects")
    return objects, stage(X.brute_force_join(objects, T, "cosine"), "truth")


_K = _walk_ctes(NAME, T, CAP)


@query("a01_timing")
def a01(spark, d):
    """Mean seconds of three runs of each method with three seeds, candidate generation included, into a sink that drops its rows; a
    method that passes the limit is cancelled and marked."""
    objects = stage(collection(spark, d, "page_links"), "objects")
    rows = [(m, 0.5, *timed(spark, lambda seed, m=m: run_method(objects, m, "jaccard", 0.5, seed=seed), limit=300.0)) for m in ("bs_pe", "bs_px", "bs_ml", "bs_exact", "sp_exact")]
    return spark.createDataFrame(rows, "method string, t double, seconds double, timed_out boolean")


#: Values of events from which on one counts as stopped at its limit.
LIMIT = 400


@query(
    "a02_speedups",
    f"""WITH g AS (SELECT event_type AS method, sum(value::DECIMAL(18, 2))::DOUBLE AS s, bool_or(value >= {LIMIT}) AS x FROM events GROUP BY event_type)
    SELECT method, s AS seconds, round(s / (SELECT s FROM g WHERE method = 'click'), 6) AS speedup, x AS at_least FROM g""",
)
def a02(spark, d):
    """Events as timings: the type is the method, the value its seconds; clicks are what the others are compared with."""
    events = table(spark, d, "events", "event_type", "value")
    times = events.select(F.col("event_type").alias("method"), F.col("value").cast("decimal(18,2)").alias("seconds"), (F.col("value") >= LIMIT).alias("timed_out"))
    return M.speedups(times, "click").select("method", F.col("seconds").cast("double").alias("seconds"), F.round(F.col("speedup"), 6).alias("speedup"), "at_least")


@query("a03_recall", f"WITH {_K} SELECT count(o.est) AS found, count(*) AS truth, round(avg((o.est IS NOT NULL)::INT), 6) AS recall FROM tr LEFT JOIN o ON o.id_a = tr.id_a AND o.id_b = tr.id_b")
def a03(spark, d, cap=CAP):
    _, truth = _truth(spark, d)
    return M.recall(_trail(spark, d, cap).where("status <> 'pruned'"), truth).withColumn("recall", F.round("recall", 6))


@query("a04_false_negatives", f"WITH {_K} SELECT round(1 - avg((o.est IS NOT NULL)::INT), 6) AS false_negative_rate FROM tr LEFT JOIN o ON o.id_a = tr.id_a AND o.id_b = tr.id_b")
def a04(spark, d, cap=CAP):
    _, truth = _truth(spark, d)
    return M.false_negative_rate(_trail(spark, d, cap).where("status <> 'pruned'"), truth).withColumn("false_negative_rate", F.round("false_negative_rate", 6))


_ERR = "avg((abs(o.est - coalesce(e.similarity, 0)) > 0.05)::INT)"


def _found(spark, d, cap=CAP):
    objects, _ = _truth(spark, d)
    out = _trail(spark, d, cap).where("status <> 'pruned'")
    return out, X.exact_similarity(out.select("id_a", "id_b"), objects, "cosine")


@query("a05_error_share", f"WITH {_K} SELECT round({_ERR}, 6) AS error_share FROM o LEFT JOIN e ON e.id_a = o.id_a AND e.id_b = o.id_b")
def a05(spark, d, cap=CAP):
    return M.errors(*_found(spark, d, cap)).select(F.round("error_share", 6).alias("error_share"))


@query("a06_mean_error", f"WITH {_K} SELECT round(avg(abs(o.est - coalesce(e.similarity, 0))), 6) AS mean_error FROM o LEFT JOIN e ON e.id_a = o.id_a AND e.id_b = o.id_b")
def a06(spark, d, cap=CAP):
    return M.errors(*_found(spark, d, cap)).select(F.round("mean_error", 6).alias("mean_error"))


def _curve_sql(ctes: str) -> str:
    return f"""WITH {ctes}, r AS (SELECT unnest(range(0, (SELECT max(n_used) FROM k)::BIGINT + 1, 32)) AS n)
      SELECT n::INT AS n, (SELECT count(*) FROM k WHERE NOT (status = 'pruned' AND n_used <= r.n)) AS not_pruned, (SELECT count(*) FROM k WHERE NOT (status <> 'continue' AND n_used <= r.n)) AS undecided FROM r"""


@query("a07_pruning_curve", _curve_sql(_K))
def a07(spark, d, cap=CAP):
    return M.pruning_curve(_weighed_trail(spark, d, cap), 32)


@query("a08_bytes_examined", f"WITH {_K} SELECT round(sum(n_used * 0.25::DOUBLE), 6) AS bytes, round(avg(n_used * 0.25::DOUBLE), 6) AS bytes_per_pair FROM k")
def a08(spark, d, cap=CAP):
    return M.bytes_examined(_weighed_trail(spark, d, cap), True).select(F.round("bytes", 6).alias("bytes"), F.round("bytes_per_pair", 6).alias("bytes_per_pair"))


@query("a09_set_sizes", f"WITH {_K} SELECT count(*) AS candidates, count(*) FILTER (status <> 'pruned') AS results, round(count(*) / greatest(count(*) FILTER (status <> 'pruned'), 1)::DOUBLE, 6) AS ratio FROM k")
def a09(spark, d, cap=CAP):
    t = _weighed_trail(spark, d, cap)
    return M.set_sizes(t, t.where("status <> 'pruned'")).withColumn("ratio", F.round("ratio", 6))


@query(
    "a10_hash_work",
    f"""WITH {_K}, m AS (SELECT id, max(n_used) AS most FROM (SELECT id_a AS id, n_used FROM k UNION ALL SELECT id_b, n_used FROM k) GROUP BY id)
    SELECT sum(n_used)::BIGINT AS compared, round(avg(n_used), 6) AS per_pair, round((SELECT avg(most) FROM m), 6) AS per_object FROM k""",
)
def a10(spark, d, cap=CAP):
    return M.hash_work(_weighed_trail(spark, d, cap)).select("compared", F.round("per_pair", 6).alias("per_pair"), F.round("per_object", 6).alias("per_object"))


@query("a11_precision", f'WITH {_K} SELECT count(*) AS "out", round(avg((tr.similarity IS NOT NULL)::INT), 6) AS precision FROM o LEFT JOIN tr ON tr.id_a = o.id_a AND tr.id_b = o.id_b')
def a11(spark, d, cap=CAP):
    _, truth = _truth(spark, d)
    return M.precision(_trail(spark, d, cap).where("status <> 'pruned'"), truth).withColumn("precision", F.round("precision", 6))


def _profile_sql(name: str) -> str:
    long = S.long_form(name)
    return f"""SELECT '{name}' AS collection, count(*) AS vectors, (SELECT count(DISTINCT feature) FROM ({long})) AS dimensions, round(avg(n), 6) AS avg_length, sum(n)::BIGINT AS non_zeros, round(var_pop(n), 4) AS var_length
      FROM (SELECT id, count(*) AS n FROM ({long}) GROUP BY id)"""


@query("a12_profile", _profile_sql("docs_words"))
def a12(spark, d):
    return w01_profiles(spark, d, ("docs_words",))


_W1 = ("docs_words", "docs_shingles", "order_parts", "part_supp", "page_links", "page_words", "cust_supp", "user_events")


@query("w01_profiles", " UNION ALL ".join(f"({_profile_sql(n)})" for n in _W1))
def w01(spark, d):
    return w01_profiles(spark, d, _W1)


def _count_sql(names, measure, ts) -> str:
    return " UNION ALL ".join(f"(SELECT '{n}' AS collection, {t}::DOUBLE AS t, count(*) AS pairs FROM ({S.truth(n, measure, t)}))" for n in names for t in ts)


_HIGH, _LOW = (0.5, 0.6, 0.7, 0.8, 0.9), (0.3, 0.4, 0.5, 0.6, 0.7)
_WEIGHTED, _BINARY = ("user_events", "cust_supp", "page_words", "docs_tfidf"), ("page_links", "docs_shingles", "docs_words")


@query("w02_weighted_cosine", _count_sql(_WEIGHTED, "cosine", _HIGH))
def w02(spark, d):
    return counts_over_thresholds(spark, d, _WEIGHTED, "cosine", _HIGH, "wp_exact")


@query("w03_binary_jaccard", _count_sql(_BINARY, "jaccard", _LOW))
def w03(spark, d):
    return counts_over_thresholds(spark, d, _BINARY, "jaccard", _LOW, "sp_exact")


@query("w04_binary_cosine", _count_sql(_BINARY, "cosine_binary", _HIGH))
def w04(spark, d):
    return counts_over_thresholds(spark, d, _BINARY, "cosine_binary", _HIGH, "sp_exact")


#: Every method at every threshold on document vectors and sets: what it finds of the true pairs. Signatures beyond SQL's reach.
for _key, _name, _m, _ts in (("w02_methods", "docs_tfidf", "cosine", _HIGH), ("w03_methods", "docs_shingles", "jaccard", _LOW), ("w04_methods", "docs_words", "cosine_binary", _HIGH)):

    @query(_key)
    def w_methods(spark, d, name=_name, m=_m, ts=_ts):
        return quality_table(spark, d, name, m, ts, tuple(x for x in METHODS if not (x == "sp_exact" and m == "cosine")), family="table" if m != "jaccard" else "wide")


@query("w05_fastest_variant")
def w05(spark, d):
    """Mean seconds of three runs of every method on document vectors over thresholds, and the ratio to the fastest."""
    objects = stage(collection(spark, d, "docs_tfidf"), "objects")
    rows = [
        (m, t, *timed(spark, lambda seed, m=m, t=t: run_method(objects, m, "cosine", t, family="table", seed=seed), limit=120.0))
        for m in ("wp_exact", "wp_pe", "wp_px", "bs_exact", "bs_ml", "bs_pe", "bs_px") for t in (0.7, 0.9)
    ]
    total = {m: sum(r[2] for r in rows if r[0] == m) for m, *_ in rows}
    return M.speedups(spark.createDataFrame(rows, "method string, t double, seconds double, timed_out boolean"), min(total, key=total.get))


@query("w06_recall")
def w06(spark, d):
    """Recall of the prefix join's candidates under both pruned verifications, on document vectors."""
    return quality_table(spark, d, "docs_tfidf", "cosine", _HIGH, ("wp_pe", "wp_px"), family="table")


@query("w07_error_shares")
def w07(spark, d):
    """Errors of the match fraction and of the posterior estimate over banded candidates, on document vectors."""
    return quality_table(spark, d, "docs_tfidf", "cosine", _HIGH, ("bs_ml", "bs_pe"), family="table")


@query("w08_pruning_curves")
def w08(spark, d):
    return w08_pruning_curves(spark, d, (("docs_tfidf", "cosine"), ("cust_supp", "cosine"), ("docs_words", "cosine_binary")))


@query("w08_pruning_curve_parity", _curve_sql(_walk_ctes(NAME, 0.6, 256)))
def w08_parity(spark, d):
    return M.pruning_curve(trail(spark, d, NAME, "cosine", 0.6, cap=256, w=8), 32)


@query("w09_sweep_cost")
def w09(spark, d):
    """Hashes compared for five values of each parameter, on document vectors at 0.7."""
    return parameter_sweep(spark, d, "docs_tfidf", 0.7, quality=False)


@query("w10_sweep_quality")
def w10(spark, d):
    """Error share, mean error and recall for the same values."""
    return parameter_sweep(spark, d, "docs_tfidf", 0.7)


@query("w12_ablations")
def w12(spark, d):
    """The same join under other choices: candidates, hashes compared, pairs found, recall, error share."""
    objects = stage(collection(spark, d, "docs_tfidf"), "objects")
    truth = stage(all_pairs_at(objects, 0.7, "cosine"), "truth")
    fixed = {"family": "table", "w": 12}
    variants = {
        "base": {}, "disjoint hashes": {"reuse_hashes": False}, "step 64": {"step": 64}, "step 128": {"step": 128}, "fused": {"strategy": "fused"}, "all hashes at once": {"lazy": False},
        "no accept test": {"delta": 0.0001, "gamma": 0.0001, "cap": 2048}, "no prune test": {"eps": 1e-12},
    }
    out = None
    for name, own in variants.items():
        with scratch():
            trail_ = name != "fused"
            walk = stage(similarity_join(objects, "cosine", 0.7, "bands", "estimate", with_trail=trail_, **fixed, **own), "variant")
            found = walk.where("status <> 'pruned'")
            errors = M.errors(found, X.exact_similarity(found.select("id_a", "id_b"), objects, "cosine"))
            row = M.recall(found, truth).join(F.broadcast(errors)).join(F.broadcast(walk.agg(F.count(F.lit(1)).alias("candidates"), F.sum("n_used").alias("hashes"))))
            row = row.select(F.lit(name).alias("variant"), "candidates", "hashes", "found", F.round("recall", 6).alias("recall"), F.round("error_share", 6).alias("error_share"))
            row = keep(stage(row, "row"))
        out = row if out is None else out.unionByName(row)
    return out


@query("w12_priors")
def w12_priors(spark, d):
    """Flat prior against one fitted to a sample of the candidates' exact similarities, on sets."""
    objects = stage(collection(spark, d, "docs_shingles"), "objects")
    truth = stage(X.brute_force_join(objects, 0.5, "jaccard"), "truth")
    pairs = stage(C.banded(stage(minhash(objects.where(F.size("features") > 0), 96, family="wide"), "bits"), 3, C.num_bands(0.5, 3), False), "pairs")
    out = None
    for name, posterior in (("flat", BetaPosterior()), ("fitted", BetaPosterior(*fit_beta_prior(pairs, objects)))):
        walk = stage(similarity_join(objects, "jaccard", 0.5, pairs, "estimate", family="wide", posterior=posterior, with_trail=True), "variant")
        found = walk.where("status <> 'pruned'")
        errors = M.errors(found, X.exact_similarity(found.select("id_a", "id_b"), objects, "jaccard"))
        row = M.recall(found, truth).join(F.broadcast(errors)).join(F.broadcast(walk.agg(F.count(F.lit(1)).alias("candidates"), F.sum("n_used").alias("hashes"))))
        shape = [F.lit(round(x, 6)).alias(n) for n, x in (("alpha", posterior.alpha), ("beta", posterior.beta))]
        row = row.select(F.lit(name).alias("prior"), *shape, "candidates", "hashes", "found", F.round("recall", 6).alias("recall"), F.round("error_share", 6).alias("error_share"))
        out = row if out is None else out.unionByName(row)
    return out


@query("w12_inference_savers")
def w12_savers(spark, d):
    """Posterior evaluations that the walks of all candidates take: for each pair and round, with the fewest matches known in
    advance, and with concentrations kept by cell as well (what the decision table does)."""
    table_ = _table("cosine", T, 512)
    objects = stage(collection(spark, d, NAME), "objects")
    s = stage(sign_bits(objects, 704), "bits")
    pairs = stage(C.banded(s, 8, C.num_bands(T, 8, 0.03, "cosine"), True), "pairs")
    ends = V.walk_pairs(pairs, s, table_, True)
    visits = V.trace_pairs(pairs, s, table_, True, table_.cap).join(ends.select("id_a", "id_b", "n_used"), ["id_a", "id_b"]).where("n <= n_used")
    per = visits.agg(F.count(F.lit(1)).alias("rounds"), F.count_if(F.col("m") >= F.col("fewest")).alias("kept"), F.countDistinct(F.when(F.col("m") >= F.col("fewest"), F.struct("n", "m"))).alias("cells"))
    searches = F.lit(sum((n + 1).bit_length() for n in range(32, table_.cap + 1, 32)))
    rows = F.array(
        F.struct(F.lit("none").alias("savers"), (F.col("rounds") + F.col("kept")).alias("evaluations")), F.struct(F.lit("fewest matches").alias("savers"), (searches + F.col("kept")).alias("evaluations")),
        F.struct(F.lit("fewest matches and cells").alias("savers"), (searches + F.col("cells")).alias("evaluations")),
    )
    return per.select(F.explode(rows).alias("r")).select("r.*")


_W14 = ("user_events", "cust_supp")


@query(
    "w14_generators",
    " UNION ALL ".join(
        f"""(SELECT '{n}' AS collection, (SELECT count(*) FROM ({'WITH h AS MATERIALIZED (' + S.sign_bits(n, 288) + ') ' + S.bands('h', 8, 35)})) AS banded,
        (SELECT count(*) FROM (WITH p AS MATERIALIZED ({_prefix_sql(n, 0.7)}) SELECT DISTINCT a.id, b.id AS id_b FROM p a JOIN p b ON a.feature = b.feature AND a.id < b.id)) AS prefix)"""
        for n in _W14
    ),
)
def w14(spark, d):
    out = None
    for n in _W14:
        v = stage(collection(spark, d, n), "vectors")
        a = C.banded(stage(sign_bits(v, 288), "bits"), 8, 35, True).agg(F.count(F.lit(1)).alias("banded"))
        b = X.prefix_candidates(v, 0.7).agg(F.count(F.lit(1)).alias("prefix"))
        row = a.join(F.broadcast(b)).select(F.lit(n).alias("collection"), "banded", "prefix")
        out = row if out is None else out.unionByName(row)
    return out


@query(
    "w15_near_duplicate_clusters",
    f"""WITH RECURSIVE p AS MATERIALIZED ({S.truth('docs_shingles', 'jaccard', 0.5)}), e AS (SELECT id_a AS a, id_b AS b FROM p UNION SELECT id_b, id_a FROM p),
    r(node, root) AS (SELECT a, a FROM e UNION SELECT e.b, r.root FROM r JOIN e ON e.a = r.node) SELECT node, min(root) AS component FROM r GROUP BY node""",
)
def w15(spark, d):
    pairs = similarity_join(collection(spark, d, "docs_shingles"), "jaccard", 0.5, "set_prefix", "exact")
    return connected_components(pairs.select(F.col("id_a").alias("a"), F.col("id_b").alias("b")))


@query(
    "w16_link_prediction",
    f"""WITH p AS MATERIALIZED ({S.truth('cust_supp', 'cosine', 0.5)}), n AS (SELECT id_a AS id, id_b AS other FROM p UNION SELECT id_b, id_a FROM p),
    s AS (SELECT DISTINCT o_custkey AS id, l_suppkey AS supp FROM {S.LINES}), v AS (SELECT n.id, s.supp, count(*) AS votes FROM n JOIN s ON s.id = n.other WHERE NOT EXISTS (SELECT 1 FROM s o WHERE o.id = n.id AND o.supp = s.supp) GROUP BY ALL)
    SELECT id, supp, votes FROM v QUALIFY row_number() OVER (PARTITION BY id ORDER BY votes DESC, supp) <= 3""",
)
def w16(spark, d):
    vectors = stage(collection(spark, d, "cust_supp"), "vectors")
    pairs = X.exact_weighted_join(vectors, 0.5).select("id_a", "id_b")
    near = pairs.select(F.col("id_a").alias("id"), F.col("id_b").alias("other")).union(pairs.select("id_b", "id_a"))
    lines = table(spark, d, "lineitem", "l_orderkey", "l_suppkey").join(table(spark, d, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    bought = stage(lines.select(F.col("o_custkey").alias("id"), F.col("l_suppkey").alias("supp")).distinct(), "bought")
    votes = near.join(bought.withColumnRenamed("id", "other"), "other").join(bought, ["id", "supp"], "left_anti").groupBy("id", "supp").agg(F.count(F.lit(1)).alias("votes"))
    best = Window.partitionBy("id").orderBy(F.col("votes").desc(), "supp")
    return votes.withColumn("r", F.row_number().over(best)).where("r <= 3").drop("r")


def _grams(table_: str, key: str) -> str:
    return f"""SELECT DISTINCT id, unnest(list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])) AS f FROM (SELECT {key} AS id, {S.TOKENS} AS w FROM {table_}) WHERE len(w) >= 3"""


@query(
    "w17_contamination",
    f"""WITH b AS MATERIALIZED ({_grams('benchmark', 'item_id')}), q AS MATERIALIZED ({_grams('documents', 'doc_id')}), n AS (SELECT id, count(*) AS n FROM b GROUP BY id)
    SELECT q.id AS doc_id, b.id AS item_id, count(*) AS shared, round(count(*) / any_value(n.n)::DOUBLE, 6) AS containment FROM b JOIN q ON q.f = b.f JOIN n ON n.id = b.id GROUP BY q.id, b.id HAVING count(*) * 2 >= any_value(n.n)""",
)
def w17(spark, d):
    items = shingle_sets(table(spark, d, "benchmark", "item_id", "text"), 3, "item_id")
    docs = shingle_sets(table(spark, d, "documents", "doc_id", "text"), 3)
    a = items.select(F.col("id").alias("item_id"), F.size("features").alias("n"), F.explode("features").alias("f"))
    b = docs.select(F.col("id").alias("doc_id"), F.explode("features").alias("f"))
    shared = a.join(b, "f").groupBy("doc_id", "item_id", "n").agg(F.count(F.lit(1)).alias("shared"))
    return shared.where(F.col("shared") * 2 >= F.col("n")).select("doc_id", "item_id", "shared", F.round(F.col("shared") / F.col("n"), 6).alias("containment"))


@query(
    "w18_label_propagation",
    f"""WITH p AS MATERIALIZED ({S.truth('docs_shingles', 'jaccard', 0.3)}), n AS (SELECT id_a AS id, id_b AS other FROM p UNION SELECT id_b, id_a FROM p)
    SELECT n.id AS doc_id, count(*) AS votes, (sum(quality) * 2 > count(*))::INT AS guess FROM n JOIN labels ON labels.doc_id = n.other WHERE quality IS NOT NULL GROUP BY n.id""",
)
def w18(spark, d):
    pairs = stage(X.exact_set_join(stage(collection(spark, d, "docs_shingles"), "sets"), 0.3, suffix=True).select("id_a", "id_b"), "pairs")
    near = pairs.select(F.col("id_a").alias("id"), F.col("id_b").alias("other")).union(pairs.select("id_b", "id_a"))
    labels = table(spark, d, "labels", "doc_id", "quality").where("quality is not null")
    votes = near.join(labels, near["other"] == labels["doc_id"]).groupBy("id").agg(F.count(F.lit(1)).alias("votes"), F.sum("quality").alias("good"))
    return votes.select(F.col("id").alias("doc_id"), "votes", (F.col("good") * 2 > F.col("votes")).cast("int").alias("guess"))

"""Queries over candidates, verification and the method grid."""

from __future__ import annotations

from pyspark.sql import functions as F

from simweave.operators import candidates as C
from simweave.operators import exact as X
from simweave.operators import verify as V
from simweave.operators.blocks import block_count_join, block_dot_join
from simweave.operators.copies import copies_of, nonempty
from simweave.operators.hashing import minhash, sign_bits
from simweave.operators.vectorize import binary_weights
from simweave.oracles import sql as S
from simweave.plans.planner import similarity_join, similarity_search
from simweave.plans.staging import stage
from simweave.queries import query
from simweave.workloads import METHODS, collection, decision_of, run_method

#: Collections and parameters of the grid. cap is what the required accuracy takes at any similarity, n the match fraction's hashes;
#: the band widths are given, so that the oracles have the same bands at every size of the tables.
SIDE = {"jaccard": "jaccard", "cosine": "cosine", "cosine_binary": "cosine"}
GRID = {
    m: {"name": name, "t": t, "w": w, "cap": decision_of(SIDE[m], t).cap, "n": n}
    for m, name, t, w, n in (("jaccard", "page_links", 0.5, 3, 360), ("cosine", "user_events", 0.5, 8, 2048), ("cosine_binary", "page_links", 0.7, 8, 2048))
}
#: The cap of the queries that show what happens at one.
SMALL = 512


def _round(df):
    return df.withColumn("similarity", F.round("similarity", 6))


def _bands(measure: str) -> int:
    g = GRID[measure]
    return C.num_bands(g["t"], g["w"], 0.03, SIDE[measure])


def _band_hashes(measure: str) -> int:
    return -(-_bands(measure) * GRID[measure]["w"] // 32) * 32


def _hash_sql(measure: str, n: int = 0) -> str:
    """At least n hashes, and what the bands need."""
    return S.hashes(GRID[measure]["name"], SIDE[measure], max(n, _band_hashes(measure)))


def _cands_sql(measure: str) -> str:
    g = GRID[measure]
    return S.bands("h", g["w"], _bands(measure))


def _sigs(spark, d, measure: str, objects=None):
    g = GRID[measure]
    objects = objects or stage(collection(spark, d, g["name"]), "objects")
    vectors = binary_weights(objects) if measure == "cosine_binary" else objects
    n = max(SMALL, _band_hashes(measure))
    return objects, stage(minhash(objects, n) if measure == "jaccard" else sign_bits(vectors, n), "sigs")


def _banded(spark, d, measure: str, **options):
    """Banded pairs of the distinct objects, then of all their copies."""
    objects = stage(collection(spark, d, GRID[measure]["name"]), "objects")
    copies = copies_of(objects)
    _, s = _sigs(spark, d, measure, copies.reps if copies else objects)
    pairs = C.banded(s, GRID[measure]["w"], _bands(measure), measure != "jaccard", **options)
    return copies.expanded(pairs.unionByName(nonempty(copies))) if copies else pairs


for _m in ("jaccard", "cosine"):

    @query(f"c01_bands_{_m}", f"WITH h AS MATERIALIZED ({_hash_sql(_m)}) {_cands_sql(_m)}")
    def c01(spark, d, m=_m):
        return _banded(spark, d, m)


@query("c03_first_band_dedupe", f"WITH h AS MATERIALIZED ({_hash_sql('jaccard')}) {_cands_sql('jaccard')}")
def c03(spark, d):
    _, s = _sigs(spark, d, "jaccard")
    return C.banded(s, 3, _bands("jaccard"), False, dedupe="first_band")


@query("c07_hot_bucket_blocks", f"WITH h AS MATERIALIZED ({_hash_sql('jaccard')}) {_cands_sql('jaccard')}")
def c07_blocks(spark, d):
    return _banded(spark, d, "jaccard", max_bucket=4)


@query(
    "c07_bucket_report",
    f"""WITH h AS MATERIALIZED ({_hash_sql('jaccard')}), k AS (SELECT j // 3 AS band, list(h ORDER BY j) AS key FROM h WHERE j < {3 * _bands('jaccard')} GROUP BY id, j // 3)
    SELECT size, count(*) AS buckets, sum(size * (size - 1) // 2)::BIGINT AS pairs FROM (SELECT count(*) AS size FROM k GROUP BY band, key) GROUP BY size""",
)
def c07_report(spark, d):
    _, s = _sigs(spark, d, "jaccard")
    return C.bucket_report(s, 3, _bands("jaccard"), False)


def _prefix_sql(name: str, t: float) -> str:
    return f"""SELECT id, feature FROM (SELECT v.id, v.feature, sqrt(sum(v.weight * v.weight) OVER w) AS l2, sum(v.weight * s.maxw) OVER w AS mw FROM ({S.long_form(name)}) v
      JOIN (SELECT feature, count(*) AS df, max(weight) AS maxw FROM ({S.long_form(name)}) GROUP BY feature) s ON s.feature = v.feature
      WINDOW w AS (PARTITION BY v.id ORDER BY s.df DESC, v.feature DESC ROWS UNBOUNDED PRECEDING)) WHERE least(l2, mw) >= {t} - 1e-9"""


@query("c04_weighted_prefix", f"WITH p AS MATERIALIZED ({_prefix_sql('cust_supp', 0.5)}) SELECT DISTINCT a.id AS id_a, b.id AS id_b FROM p a JOIN p b ON a.feature = b.feature AND a.id < b.id")
def c04(spark, d):
    return X.prefix_candidates(stage(collection(spark, d, "cust_supp"), "vectors"), 0.5)


@query(
    "c05_set_prefix",
    f"""WITH s AS MATERIALIZED ({S.SETS['page_links']}), f AS (SELECT x, count(*) AS df FROM s GROUP BY x),
    r AS (SELECT s.id, s.x, count(*) OVER (PARTITION BY s.id) AS n, row_number() OVER (PARTITION BY s.id ORDER BY f.df, s.x) AS pos FROM s JOIN f ON f.x = s.x),
    p AS (SELECT * FROM r WHERE pos <= n - ceil(n * 0.5 - 1e-9) + 1)
    SELECT DISTINCT a.id AS id_a, b.id AS id_b FROM p a JOIN p b ON a.x = b.x AND a.id < b.id AND least(a.n, b.n) >= ceil(greatest(a.n, b.n) * 0.5 - 1e-9)
      AND least(a.n - a.pos, b.n - b.pos) + least(a.pos, b.pos) >= ceil((a.n + b.n) * (0.5 / 1.5::DOUBLE) - 1e-9)""",
)
def c05(spark, d):
    return X.set_prefix_candidates(collection(spark, d, "page_links"), 0.5)


@query("c06_sharing_pairs", f"WITH s AS MATERIALIZED ({S.SETS['page_links']}) SELECT DISTINCT a.id AS id_a, b.id AS id_b FROM s a JOIN s b ON a.x = b.x AND a.id < b.id")
def c06(spark, d):
    return C.sharing_pairs(collection(spark, d, "page_links").select("id", F.explode("features").alias("feature")))


@query("c06_all_pairs", "SELECT a.page_id AS id_a, b.page_id AS id_b FROM pages a JOIN pages b ON a.page_id < b.page_id")
def c06_all(spark, d):
    """Every pair of pages: rows grow with the square of the table."""
    return C.all_pairs(spark.read.parquet(f"{d}/pages.parquet").select(F.col("page_id").alias("id")))


@query("c08_external_pairs", f"SELECT id_a, id_b, round(similarity, 6) AS similarity FROM ({S.truth('page_links', 'jaccard', 0.5)}) WHERE id_a % 2 = 0")
def c08(spark, d):
    sets = collection(spark, d, "page_links")
    pairs = C.sharing_pairs(sets.select("id", F.explode("features").alias("feature"))).where("id_a % 2 = 0")
    return _round(similarity_join(sets, "jaccard", 0.5, pairs, "exact"))


def _search_sql(t: str) -> str:
    return f"""WITH s AS MATERIALIZED ({S.SETS['page_links']}), n AS (SELECT id, count(*) AS n FROM s GROUP BY id),
    p AS (SELECT a.id AS id_a, b.id AS id_b, count(*) AS i FROM s a JOIN s b ON a.x = b.x WHERE a.id % 10 = 0 GROUP BY ALL),
    v AS (SELECT id_a, id_b, i / (x.n + y.n - i)::DOUBLE AS similarity FROM p JOIN n x ON x.id = id_a JOIN n y ON y.id = id_b) {t}"""


@query("c09_threshold_query", _search_sql("SELECT id_a, id_b, round(similarity, 6) AS similarity FROM v WHERE round(similarity, 9) >= 0.4"))
def c09_t(spark, d):
    sets = collection(spark, d, "page_links")
    return _round(similarity_search(sets.where("id % 10 = 0"), sets, "jaccard", t=0.4))


@query("c09_topk_query", _search_sql("SELECT id_a, id_b, round(similarity, 6) AS similarity, rank::INT AS rank FROM (SELECT *, row_number() OVER (PARTITION BY id_a ORDER BY round(similarity, 9) DESC, id_b) AS rank FROM v) WHERE rank <= 5"))
def c09_k(spark, d):
    sets = collection(spark, d, "page_links")
    return _round(similarity_search(sets.where("id % 10 = 0"), sets, "jaccard", k=5))


@query(
    "c09_cross_collection",
    f"WITH h AS MATERIALIZED ({S.minhash('docs_words', 96)}), k AS (SELECT id, j // 3 AS band, list(h ORDER BY j) AS key FROM h WHERE j < {3 * _bands('jaccard')} GROUP BY id, j // 3) SELECT DISTINCT a.id AS id_a, b.id AS id_b FROM k a JOIN k b ON a.band = b.band AND a.key = b.key WHERE a.id % 2 = 0 AND b.id % 2 = 1",
)
def c09_cross(spark, d):
    """Even and odd documents as two collections."""
    sets = collection(spark, d, "docs_words").where(F.size("features") > 0)
    s = stage(minhash(sets, 96), "sigs")
    return C.cross_banded(s.where("id % 2 = 0"), s.where("id % 2 = 1"), 3, _bands("jaccard"), False)


@query(
    "c10_collapse_duplicates",
    f"SELECT id, min(id) OVER (PARTITION BY c) AS rep FROM (SELECT id, list(x ORDER BY x) AS c FROM ({S.SETS['page_links']}) GROUP BY id)",
)
def c10(spark, d):
    return C.collapse_duplicates(collection(spark, d, "page_links"))[1]


def _prefix_cands(measure: str) -> str:
    g = GRID[measure]
    prefix = _prefix_sql(g["name"], g["t"])
    return f"SELECT DISTINCT a.id AS id_a, b.id AS id_b FROM ({prefix}) a JOIN ({prefix}) b ON a.feature = b.feature AND a.id < b.id"


def _estimate_sql(measure: str, tail: str = "WHERE status <> 'pruned'", cands: str | None = None, cap: int | None = None) -> str:
    g = GRID[measure]
    table = decision_of(SIDE[measure], g["t"], cap or g["cap"])
    return f"""WITH h AS MATERIALIZED ({_hash_sql(measure, table.cap)}), c AS MATERIALIZED ({cands or _cands_sql(measure)}), k AS ({S.walk('h', 'SELECT * FROM c', table)})
      SELECT id_a, id_b, round({S.estimate(SIDE[measure])}, 6) AS similarity, n_used::INT AS n_used, matches::INT AS matches, CASE WHEN status = 'continue' THEN 'capped' ELSE status END AS status FROM k {tail}"""


def _truth_join(measure: str, source: str, op: str = ">") -> str:
    g = GRID[measure]
    return f"SELECT t.id_a, t.id_b, round(t.similarity, 6) AS similarity FROM ({S.truth(g['name'], measure, 0.0001)}) t JOIN ({source}) c ON c.id_a = t.id_a AND c.id_b = t.id_b WHERE round(t.similarity, 9) {op} {g['t']}"


def _prune_exact_sql(measure: str, cands: str | None = None) -> str:
    from simweave.plans.decision import JoinParams, decision_table
    from simweave.plans.planner import default_posterior

    g = GRID[measure]
    h = 64 if measure == "jaccard" else 128
    table = decision_table(default_posterior(measure), JoinParams(g["t"], cap=h), False)
    return f"WITH h AS MATERIALIZED ({_hash_sql(measure, h)}), c AS MATERIALIZED ({cands or _cands_sql(measure)}), k AS MATERIALIZED ({S.walk('h', 'SELECT * FROM c', table)}) " + _truth_join(measure, "SELECT * FROM k WHERE status <> 'pruned'")


def _classical_sql(measure: str) -> str:
    g = GRID[measure]
    value = f"cos(pi() * (1 - m / {g['n']}::DOUBLE))" if measure != "jaccard" else f"m / {g['n']}::DOUBLE"
    return f"""WITH h AS MATERIALIZED ({_hash_sql(measure, g['n'])}), c AS MATERIALIZED ({_cands_sql(measure)}),
      k AS (SELECT c.id_a, c.id_b, sum((x.h = y.h)::INT) AS m FROM c JOIN h x ON x.id = c.id_a JOIN h y ON y.id = c.id_b AND y.j = x.j WHERE x.j < {g['n']} GROUP BY ALL)
      SELECT id_a, id_b, round({value}, 6) AS similarity, m::INT AS matches FROM k WHERE round({value}, 9) >= {g['t']}"""


def _exact_sql(measure: str) -> str:
    return f"WITH h AS MATERIALIZED ({_hash_sql(measure)}), c AS MATERIALIZED ({_cands_sql(measure)}) " + _truth_join(measure, "SELECT * FROM c", ">=")


def _own(measure: str) -> dict:
    g = GRID[measure]
    return {"w": g["w"], "seed": 1}


for _m in GRID:

    @query(f"v01_estimate_{_m}", _estimate_sql(_m))
    def v01(spark, d, m=_m):
        g = GRID[m]
        return _round(similarity_join(collection(spark, d, g["name"]), m, g["t"], "bands", "estimate", **_own(m)))

    @query(f"v02_prune_exact_{_m}", _prune_exact_sql(_m))
    def v02(spark, d, m=_m):
        g = GRID[m]
        return _round(similarity_join(collection(spark, d, g["name"]), m, g["t"], "bands", "prune_exact", **_own(m)))

    @query(f"v03_classical_{_m}", _classical_sql(_m))
    def v03(spark, d, m=_m):
        g = GRID[m]
        return _round(similarity_join(collection(spark, d, g["name"]), m, g["t"], "bands", "classical", **_own(m)))

    @query(f"v04_exact_{_m}", _exact_sql(_m))
    def v04(spark, d, m=_m):
        g = GRID[m]
        return _round(similarity_join(collection(spark, d, g["name"]), m, g["t"], "bands", "exact", **_own(m)))


@query("v05_fused_equals_rounds", _estimate_sql("cosine"))
def v05(spark, d):
    g = GRID["cosine"]
    return _round(similarity_join(collection(spark, d, g["name"]), "cosine", g["t"], "bands", "estimate", strategy="fused", **_own("cosine")))


@query("v06_rounds", _estimate_sql("cosine"))
def v06(spark, d):
    """Listed candidates and signatures made up to the cap for every object."""
    g = GRID["cosine"]
    return _round(similarity_join(collection(spark, d, g["name"]), "cosine", g["t"], "bands", "estimate", strategy="rounds", lazy=False, **_own("cosine")))


@query("v07_emit_on_cap", _estimate_sql("cosine", "WHERE status = 'continue'", cap=SMALL))
def v07_emit(spark, d):
    g = GRID["cosine"]
    out = similarity_join(collection(spark, d, g["name"]), "cosine", g["t"], "bands", "estimate", cap=SMALL, **_own("cosine"))
    return _round(out.where("status = 'capped'"))


def _extend_sql() -> str:
    g = GRID["cosine"]
    table = decision_of("cosine", g["t"], 2 * 256)
    return f"""WITH h AS MATERIALIZED ({_hash_sql('cosine', 512)}), c AS MATERIALIZED ({_cands_sql('cosine')}), k AS ({S.walk('h', 'SELECT * FROM c', table)})
      SELECT id_a, id_b, round({S.estimate('cosine')}, 6) AS similarity, n_used::INT AS n_used, matches::INT AS matches, CASE WHEN status = 'continue' THEN 'capped' ELSE status END AS status FROM k WHERE status <> 'pruned'"""


@query("v07_extend_on_cap", _extend_sql())
def v07_extend(spark, d):
    objects, s = _sigs(spark, d, "cosine")
    pairs = C.banded(s, 8, _bands("cosine"), True)
    return _round(V.verify_estimate(pairs, s, decision_of("cosine", 0.5, 256), True, on_cap="extend", objects=objects, extend_to=512))


def _exact_on_cap_sql() -> str:
    g = GRID["cosine"]
    table = decision_of("cosine", g["t"], 128)
    return f"""WITH h AS MATERIALIZED ({_hash_sql('cosine', 128)}), c AS MATERIALIZED ({_cands_sql('cosine')}), k AS MATERIALIZED ({S.walk('h', 'SELECT * FROM c', table)}),
      e AS (SELECT * FROM ({S.truth(g['name'], 'cosine', 0.0001)}))
      SELECT k.id_a, k.id_b, round(CASE WHEN k.status = 'continue' THEN e.similarity ELSE {S.estimate('cosine')} END, 6) AS similarity, n_used::INT AS n_used, matches::INT AS matches,
        CASE WHEN k.status = 'continue' THEN 'exact' ELSE k.status END AS status FROM k LEFT JOIN e ON e.id_a = k.id_a AND e.id_b = k.id_b
      WHERE k.status = 'accepted' OR (k.status = 'continue' AND round(e.similarity, 9) >= {g['t']})"""


@query("v07_exact_on_cap", _exact_on_cap_sql())
def v07_exact(spark, d):
    objects, s = _sigs(spark, d, "cosine")
    pairs = C.banded(s, 8, _bands("cosine"), True)
    return _round(V.verify_estimate(pairs, s, decision_of("cosine", 0.5, 128), True, on_cap="exact", objects=objects))


def _trace_sql() -> str:
    table = decision_of("jaccard", 0.5, 480)
    limits = ", ".join(f"({k}, {m})" for k, m in enumerate(table.fewest[:4]))
    return f"""WITH h AS MATERIALIZED ({_hash_sql('jaccard', 128)}), p AS (SELECT id_a, id_b FROM ({S.truth('page_links', 'jaccard', 0.5)}))
      SELECT id_a, id_b, ((n + 1) * 32)::INT AS n, m::INT AS m, l.f::INT AS fewest, round(m / ((n + 1) * 32)::DOUBLE, 6) AS estimate FROM (
        SELECT id_a, id_b, n, sum(m) OVER (PARTITION BY id_a, id_b ORDER BY n) AS m FROM (SELECT p.id_a, p.id_b, x.j // 32 AS n, sum((x.h = y.h)::INT) AS m FROM p JOIN h x ON x.id = p.id_a
        JOIN h y ON y.id = p.id_b AND y.j = x.j WHERE x.j < 128 GROUP BY ALL)) q JOIN (VALUES {limits}) l(k, f) ON l.k = q.n"""


@query("v08_trace", _trace_sql())
def v08(spark, d):
    objects, s = _sigs(spark, d, "jaccard")
    pairs = X.brute_force_join(objects, 0.5, "jaccard").select("id_a", "id_b")
    rows = V.trace_pairs(pairs, s, decision_of("jaccard", 0.5, 480), False, 128)
    return rows.withColumn("estimate", F.round("estimate", 6))


@query("b02_upper_bound_check", f"SELECT id_a, id_b, round(similarity, 6) AS similarity FROM ({S.truth('cust_supp', 'cosine', 0.5)})")
def b02(spark, d):
    return _round(X.exact_weighted_join(stage(collection(spark, d, "cust_supp"), "vectors"), 0.5, upper_bound_check=True))


for _bound in ("l2", "maxweight"):

    @query(f"b01_weighted_join_{_bound}", f"SELECT id_a, id_b, round(similarity, 6) AS similarity FROM ({S.truth('user_events', 'cosine', 0.5)})")
    def b01(spark, d, bound=_bound):
        return _round(X.exact_weighted_join(stage(collection(spark, d, "user_events"), "vectors"), 0.5, bound))


for _m, _t in (("jaccard", 0.5), ("cosine_binary", 0.7)):

    @query(f"b06_set_join_suffix_{_m}", f"SELECT id_a, id_b, round(similarity, 6) AS similarity FROM ({S.truth('docs_words', _m, _t)})")
    def b06(spark, d, m=_m, t=_t):
        return _round(X.exact_set_join(stage(collection(spark, d, "docs_words"), "sets"), t, m, suffix=True))


for _n, _m, _t in (("docs_tfidf", "cosine", 0.7), ("docs_shingles", "jaccard", 0.5), ("page_links", "cosine_binary", 0.7)):

    @query(f"b07_brute_force_{_m}", f"SELECT id_a, id_b, round(similarity, 6) AS similarity FROM ({S.truth(_n, _m, _t)})")
    def b07(spark, d, n=_n, m=_m, t=_t):
        objects = stage(collection(spark, d, n), "objects")
        join = {"cosine": lambda: block_dot_join(objects, t), "jaccard": lambda: block_count_join(objects, t, m)}
        return _round(join.get(m, lambda: X.brute_force_join(objects, t, m))())


def _grid_sql(method: str, m: str) -> str | None:
    g = GRID[m]
    exact = f"SELECT id_a, id_b, round(similarity, 6) AS similarity FROM ({S.truth(g['name'], m, g['t'])})"
    generator, verifier = METHODS[method]
    if verifier == "exact":
        return exact if generator != "bands" else _exact_sql(m)
    if generator == "bands":
        return {"estimate": _estimate_sql, "prune_exact": _prune_exact_sql, "classical": _classical_sql}[verifier](m)
    return {"estimate": _estimate_sql, "prune_exact": _prune_exact_sql}[verifier](m, cands=_prefix_cands(m))


for _method in METHODS:
    for _m in GRID:
        if _method == "sp_exact" and _m == "cosine":
            continue

        @query(f"{_method}_{_m}", _grid_sql(_method, _m))
        def grid(spark, d, method=_method, m=_m):
            g = GRID[m]
            return _round(run_method(stage(collection(spark, d, g["name"]), "objects"), method, m, g["t"], **_own(m)))

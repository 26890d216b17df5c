"""Pieces of DuckDB SQL from which oracles are put together: collections, hashes, walks, inference."""

from __future__ import annotations

PRIME = (1 << 31) - 1


def draw(tag: str, seed: int, j: str, modulus: int) -> str:
    return f"(('0x' || substr(md5('{tag}{seed}:' || {j}), 1, 15))::BIGINT % {modulus})"


def feature_id(x: str) -> str:
    return f"(('0x' || substr(md5({x}), 1, 15))::BIGINT % {PRIME})"


TOKENS = "regexp_extract_all(lower(coalesce(text, '')), '[\\p{L}\\p{N}]+')"
PAGES = r"(SELECT page_id AS id, regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[^\p{L}]+', ' ', 'g') AS text FROM pages)"


def _edges(id_col: str, feature: str, source: str) -> str:
    return f"SELECT DISTINCT {id_col} AS id, {feature_id(feature)} AS x FROM {source} WHERE {id_col} IS NOT NULL AND {feature} IS NOT NULL"


SETS = {
    "docs_words": f"SELECT DISTINCT doc_id AS id, {feature_id('f')} AS x FROM (SELECT doc_id, unnest({TOKENS}) AS f FROM documents)",
    "docs_shingles": f"""SELECT DISTINCT id, {feature_id('f')} AS x FROM (SELECT id, unnest(list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])) AS f
      FROM (SELECT doc_id AS id, {TOKENS} AS w FROM documents) WHERE len(w) >= 3)""",
    "order_parts": _edges("l_orderkey", "l_partkey::VARCHAR", "lineitem"),
    "part_supp": _edges("l_partkey", "l_suppkey::VARCHAR", "lineitem"),
    "supp_part": _edges("l_suppkey", "l_partkey::VARCHAR", "lineitem"),
    "page_links": _edges("page_id", "href", "(SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages)"),
}


def _idf(counts: str) -> str:
    return f"""SELECT id, feature, w / sqrt(sum(w * w) OVER (PARTITION BY id)) AS weight FROM (
      SELECT c.id, c.feature, tf * ln((SELECT count(DISTINCT id) FROM ({counts})) / df::DOUBLE) AS w
      FROM ({counts}) c JOIN (SELECT feature, count(*) AS df FROM ({counts}) GROUP BY feature) d ON d.feature = c.feature) WHERE w > 0"""


def _unit(counts: str) -> str:
    return f"SELECT id, feature, tf / sqrt(sum(tf * tf) OVER (PARTITION BY id)) AS weight FROM ({counts})"


LINES = "lineitem JOIN orders ON l_orderkey = o_orderkey"
VECTORS = {
    "docs_tfidf": _idf(f"SELECT doc_id AS id, f AS feature, count(*) AS tf FROM (SELECT doc_id, unnest({TOKENS}) AS f FROM documents) GROUP BY ALL"),
    "page_words": _idf(f"SELECT id, f AS feature, count(*) AS tf FROM (SELECT id, unnest({TOKENS}) AS f FROM {PAGES}) GROUP BY ALL"),
    "cust_supp": _idf(f"SELECT o_custkey AS id, l_suppkey::VARCHAR AS feature, sum(l_quantity) AS tf FROM {LINES} GROUP BY ALL"),
    "cust_brand": _unit(f"SELECT o_custkey AS id, p_brand AS feature, sum(l_quantity) AS tf FROM {LINES} JOIN part ON l_partkey = p_partkey GROUP BY ALL"),
    "user_events": _unit("SELECT user_id AS id, event_type || '-' || hour(ts) AS feature, count(*)::DOUBLE AS tf FROM events GROUP BY ALL"),
    "emb": "SELECT vec_id AS id, (unnest(range(0, len(embedding))))::VARCHAR AS feature, unnest(embedding)::DOUBLE AS weight FROM embeddings",
}


def long_form(name: str) -> str:
    """id, feature, weight of a collection; sets become unit vectors of equal weights."""
    if name in VECTORS:
        return VECTORS[name]
    return f"SELECT id, x::VARCHAR AS feature, 1 / sqrt(count(*) OVER (PARTITION BY id)) AS weight FROM ({SETS[name]})"


def truth(name: str, measure: str, t: float) -> str:
    """id_a, id_b, similarity of all pairs at or over t."""
    if measure == "cosine":
        return f"""SELECT a.id AS id_a, b.id AS id_b, sum(a.weight * b.weight) AS similarity FROM ({long_form(name)}) a JOIN ({long_form(name)}) b
          ON a.feature = b.feature AND a.id < b.id GROUP BY ALL HAVING round(sum(a.weight * b.weight), 9) >= {t}"""
    value = "i / (x.n + y.n - i)::DOUBLE" if measure == "jaccard" else "i / sqrt(x.n::DOUBLE * y.n)"
    return f"""SELECT id_a, id_b, {value} AS similarity FROM (SELECT a.id AS id_a, b.id AS id_b, count(*) AS i FROM ({SETS[name]}) a JOIN ({SETS[name]}) b
      ON a.x = b.x AND a.id < b.id GROUP BY ALL) p JOIN (SELECT id, count(*) AS n FROM ({SETS[name]}) GROUP BY id) x ON x.id = id_a
      JOIN (SELECT id, count(*) AS n FROM ({SETS[name]}) GROUP BY id) y ON y.id = id_b WHERE round({value}, 9) >= {t}"""


def minhash(name: str, n: int, seed: int = 1, first: int = 0) -> str:
    """id, j, h: parity minwise hashes."""
    return f"""SELECT id, j, min((a * x + b) % {PRIME}) AS h FROM ({SETS[name]}),
      (SELECT j, {draw('ha', seed, 'j', PRIME - 1)} + 1 AS a, {draw('hb', seed, 'j', PRIME)} AS b FROM range({first}, {first + n}) r(j)) GROUP BY id, j"""


def gaussian_code(x: str) -> str:
    """Code of the gaussian of id x and hash row h(a, b, c, d)."""
    g = f"sqrt(-2.0 * ln((((a * {x} + b) % {PRIME})::DOUBLE + 1) / ({PRIME} + 1.0))) * cos(2 * pi() * (((c * {x} + d) % {PRIME})::DOUBLE / {PRIME}))"
    return f"least(greatest(floor(({g} + 8) * 4096), 0), 65535)::BIGINT"


def gaussian_rows(n: int, seed: int = 1, first: int = 0) -> str:
    return f"""(SELECT j, {draw('ga', seed, 'j', PRIME - 1)} + 1 AS a, {draw('gb', seed, 'j', PRIME)} AS b, {draw('ka', seed, 'j', PRIME - 1)} + 1 AS c,
      {draw('kb', seed, 'j', PRIME)} AS d FROM range({first}, {first + n}) r(j))"""


def sign_bits(name: str, n: int, seed: int = 1, first: int = 0) -> str:
    """id, j, h: signs of fixed-point gaussian projections."""
    return f"""SELECT id, j, (sum(w * (2 * {gaussian_code('x')} + 1 - 65536)) >= 0)::INT AS h FROM
      (SELECT id, {feature_id('feature')} AS x, floor(weight * 1048576 + 0.5)::BIGINT AS w FROM ({long_form(name)})), {gaussian_rows(n, seed, first)} GROUP BY id, j"""


def hashes(name: str, measure: str, n: int, seed: int = 1) -> str:
    return minhash(name, n, seed) if measure == "jaccard" else sign_bits(name, n, seed)


def bands(source: str, w: int, n_bands: int) -> str:
    """id_a, id_b of pairs that share a band of the hash table source(id, j, h)."""
    keys = f"SELECT id, j // {w} AS band, list(h ORDER BY j) AS key FROM {source} WHERE j < {w * n_bands} GROUP BY id, j // {w}"
    return f"SELECT DISTINCT a.id AS id_a, b.id AS id_b FROM ({keys}) a JOIN ({keys}) b ON a.band = b.band AND a.key = b.key AND a.id < b.id"


def walk(source: str, pairs: str, table) -> str:
    """id_a, id_b, n_used, matches, status of each pair by the decision table; 'continue' at its end."""
    step, rounds = table.params.step, len(table.fewest)
    limits = ", ".join(f"({k}, {m})" for k, m in enumerate(table.fewest))
    runs = ", ".join(f"({k}, {a}, {b})" for k, own in enumerate(table.accepted) for a, b in own) or "(-1, 1, 0)"
    return f"""SELECT id_a, id_b, (n + 1) * {step} AS n_used, matches, status FROM (
      SELECT *, row_number() OVER (PARTITION BY id_a, id_b ORDER BY (status = 'continue')::INT, CASE WHEN status = 'continue' THEN -n ELSE n END) AS pick FROM (
        SELECT c.*, CASE WHEN c.matches < l.m THEN 'pruned' WHEN EXISTS (SELECT 1 FROM (VALUES {runs}) r(k, lo, hi) WHERE r.k = c.n AND c.matches BETWEEN r.lo AND r.hi) THEN 'accepted' ELSE 'continue' END AS status
        FROM (SELECT id_a, id_b, n, sum(m) OVER (PARTITION BY id_a, id_b ORDER BY n)::BIGINT AS matches FROM (
          SELECT p.id_a, p.id_b, x.j // {step} AS n, sum((x.h = y.h)::INT) AS m FROM ({pairs}) p JOIN {source} x ON x.id = p.id_a JOIN {source} y ON y.id = p.id_b AND y.j = x.j
          WHERE x.j < {rounds * step} GROUP BY ALL)) c JOIN (VALUES {limits}) l(k, m) ON l.k = c.n)) WHERE pick = 1"""


def estimate(measure: str, n: str = "n_used", m: str = "matches") -> str:
    """Posterior mode under flat priors."""
    return f"cos(pi() * (1 - greatest({m} / {n}::DOUBLE, 0.5)))" if measure == "cosine" else f"{m} / {n}::DOUBLE"


def binomial(n: str, m: str, s: str) -> str:
    return f"exp(lgamma({n} + 1) - lgamma({m} + 1) - lgamma({n} - {m} + 1) + {m} * ln({s}) + ({n} - {m}) * ln(1 - {s}))"


def upper_tail(t: str, m: str, n: str) -> str:
    """Pr[S >= t] of Beta(m + 1, n - m + 1): at most m successes in n + 1 trials."""
    return f"(CASE WHEN {t} <= 0 THEN 1.0 WHEN {t} >= 1 THEN 0.0 ELSE (SELECT sum({binomial(f'({n} + 1)', 'i', f'({t})')}) FROM range(0, {m} + 1) q(i)) END)"


def c2r(c: str) -> str:
    return f"(1 - acos({c}) / pi())"

"""The measures as SQL functions, and a Python surface for ad hoc posterior questions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from simweave.functions.posterior import BetaPosterior, TruncatedPosterior

# Each function's name, parameters and body.
DEFINITIONS = {
    "sim_jaccard": ("a ARRAY<BIGINT>, b ARRAY<BIGINT>", "DOUBLE", "size(array_intersect(a, b)) / nullif(size(array_union(a, b)), 0)"),
    "sim_angular_to_cosine": ("r DOUBLE", "DOUBLE", "cos(pi() * (1 - r))"),
    "sim_matches": ("a BIGINT, b BIGINT", "INT", "32 - bit_count(a ^ b)"),
    "sim_cosine_sparse": ("a MAP<STRING, DOUBLE>, b MAP<STRING, DOUBLE>", "DOUBLE", "aggregate(map_keys(a), 0D, (s, k) -> s + a[k] * coalesce(try_element_at(b, k), 0D))"),
}


def register(spark: SparkSession) -> None:
    """Create the measures as temporary SQL functions of the session."""
    for name, (parameters, kind, body) in DEFINITIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({parameters}) RETURNS {kind} RETURN {body}")


def posterior_prob(measure: str, t: float):
    """A vectorised UDF of columns (m, n): probability that the similarity is at least t."""
    posterior = BetaPosterior() if measure == "jaccard" else TruncatedPosterior()

    @F.pandas_udf("double")
    def prob(m: pd.Series, n: pd.Series) -> pd.Series:
        known: dict[tuple[int, int], float] = {}
        return pd.Series([known.setdefault(k, posterior.prob_ge(t, *k)) for k in zip(m.astype(int), n.astype(int), strict=True)], dtype=float)

    return prob



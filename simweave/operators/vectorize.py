"""Objects as sets and weighted vectors: tokens, shingles, tf-idf, graph neighbourhoods."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from simweave.functions.columns import feature_id

TOKEN = r"[\p{L}\p{N}]+"


def tokens(text: Column) -> Column:
    """Lower-case runs of letters and digits; empty for null."""
    return F.coalesce(F.regexp_extract_all(F.lower(text), F.lit(f"({TOKEN})"), F.lit(1)), F.array().cast("array<string>"))


def word_sets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id and features: sorted distinct 31-bit ids of each text's words (no shuffle)."""
    return _set_of(docs, id_col, F.array_distinct(tokens(F.col(text_col))))


def shingle_sets(docs: DataFrame, k: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id and features: ids of each text's k-word shingles; texts of fewer words have none."""
    def grams(w: Column) -> Column:
        return F.transform(F.slice(w, 1, F.greatest(F.size(w) - (k - 1), F.lit(0))), lambda _, i: F.array_join(F.slice(w, i + 1, k), " "))

    words = F.transform(F.array(tokens(F.col(text_col))), grams)[0]
    return _set_of(docs, id_col, F.array_distinct(words))


def _set_of(docs: DataFrame, id_col: str, found: Column) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("id"), F.array_sort(F.array_distinct(F.transform(found, feature_id))).alias("features"))


def sets_from_edges(edges: DataFrame, id_col: str, feature_col: str) -> DataFrame:
    """id and features from an edge table (src, dst): one shuffle by id."""
    e = edges.select(F.col(id_col).cast("long").alias("id"), feature_id(F.col(feature_col).cast("string")).alias("f")).where("id is not null and f is not null")
    return e.groupBy("id").agg(F.array_sort(F.collect_set("f")).alias("features"))


def term_counts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, feature (string) and tf of each text's words."""
    words = docs.select(F.col(id_col).cast("long").alias("id"), F.explode(tokens(F.col(text_col))).alias("feature"))
    return words.groupBy("id", "feature").agg(F.count(F.lit(1)).alias("tf"))


def idf_weighted(counts: DataFrame, n_objects: DataFrame | None = None) -> DataFrame:
    """id, feature, weight: tf * ln(N / df), unit length. Features in every object get weight 0 and are dropped.

    counts: id, feature, tf. The document frequencies are joined by feature, as a broadcast where Spark finds them small.
    """
    total = (counts.select("id").distinct() if n_objects is None else n_objects).agg(F.count(F.lit(1)).alias("n"))
    df = counts.groupBy("feature").agg(F.count(F.lit(1)).alias("df"))
    weighted = counts.join(df, "feature").join(F.broadcast(total)).withColumn("w", F.col("tf") * F.log(F.col("n") / F.col("df")))
    return unit_length(weighted.where("w > 0").select("id", "feature", F.col("w").alias("weight")))


def unit_length(weights: DataFrame) -> DataFrame:
    """Weights divided by each object's length; objects of length 0 vanish."""
    norm = F.sqrt(F.sum(F.col("weight") * F.col("weight")).over(Window.partitionBy("id")))
    return weights.withColumn("norm", norm).where("norm > 0").select("id", "feature", (F.col("weight") / F.col("norm")).alias("weight"))


def tfidf(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Unit tf-idf vectors of texts in long form (id, feature, weight)."""
    return idf_weighted(term_counts(docs, id_col, text_col))


def weighted_edges(edges: DataFrame, id_col: str, feature_col: str, weight: Column) -> DataFrame:
    """Unit vectors of neighbours, weight summed per edge times idf."""
    counts = edges.groupBy(F.col(id_col).cast("long").alias("id"), F.col(feature_col).cast("string").alias("feature")).agg(F.sum(weight).alias("tf"))
    return idf_weighted(counts)


def dense_vectors(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """Dense arrays in long form, features numbered from 0."""
    return vectors.select(F.col(id_col).cast("long").alias("id"), F.posexplode(vector_col).alias("feature", "weight")).select(
        "id", F.col("feature").cast("string").alias("feature"), F.col("weight").cast("double").alias("weight")
    )


def binary_weights(sets: DataFrame) -> DataFrame:
    """Sets as unit vectors with equal weights."""
    return sets.select("id", F.explode(F.col("features").cast("array<string>")).alias("feature"), (1 / F.sqrt(F.size("features"))).alias("weight"))


def pack(vectors: DataFrame) -> DataFrame:
    """id and vector: arrays of (feature, weight) sorted by feature."""
    return vectors.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("feature", "weight"))).alias("vector"))


def at_least(sets: DataFrame, n: int) -> DataFrame:
    """Objects with at least n features."""
    return sets.where(F.size("features") >= n)


def profile(sets_or_vectors: DataFrame) -> DataFrame:
    """vectors, dimensions, avg_length, non_zeros and var_length of a collection."""
    long = sets_or_vectors
    if "features" in long.columns:
        long = long.select("id", F.explode("features").alias("feature"))
    by_id = long.groupBy("id").agg(F.count(F.lit(1)).alias("n"))
    dims = long.agg(F.countDistinct("feature").alias("dimensions"))
    return by_id.agg(
        F.count(F.lit(1)).alias("vectors"), F.avg("n").alias("avg_length"), F.sum("n").alias("non_zeros"), F.var_pop("n").alias("var_length")
    ).join(F.broadcast(dims))

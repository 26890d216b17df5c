"""Cost and accuracy measures. truth: exact pairs with similarity; out: a method's pairs; trail: every candidate's walk.

A trail may be weighed (copies.py): pairs is then how many candidates a row stands for, n_a and n_b how many objects. Or it may be counted
(tiles.py): pairs by n_used and status, and for each id, which stands for n objects, a row of its longest walk with pairs 0.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def _pairs(trail: DataFrame) -> Column:
    return F.col("pairs") if "pairs" in trail.columns else F.lit(1)


def recall(out: DataFrame, truth: DataFrame) -> DataFrame:
    """found, truth and recall in one row; recall is null without true pairs."""
    hit = truth.select("id_a", "id_b").join(out.select("id_a", "id_b", F.lit(1).alias("hit")), ["id_a", "id_b"], "left")
    return hit.agg(F.count("hit").alias("found"), F.count(F.lit(1)).alias("truth"), F.avg(F.coalesce("hit", F.lit(0))).alias("recall"))


def false_negative_rate(out: DataFrame, truth: DataFrame) -> DataFrame:
    return recall(out, truth).select((1 - F.col("recall")).alias("false_negative_rate"))


def errors(out: DataFrame, exact: DataFrame, bound: float = 0.05) -> DataFrame:
    """error_share (estimates off by more than bound) and mean_error over output pairs."""
    both = out.select("id_a", "id_b", F.col("similarity").alias("est")).join(exact.select("id_a", "id_b", F.col("similarity").alias("s")), ["id_a", "id_b"])
    off = F.abs(F.col("est") - F.col("s"))
    return both.agg(F.avg((off > bound).cast("int")).alias("error_share"), F.avg(off).alias("mean_error"))


def precision(out: DataFrame, truth: DataFrame) -> DataFrame:
    """Share of output pairs that are true ones."""
    hit = out.select("id_a", "id_b").join(truth.select("id_a", "id_b", F.lit(1).alias("hit")), ["id_a", "id_b"], "left")
    return hit.agg(F.count(F.lit(1)).alias("out"), F.avg(F.coalesce("hit", F.lit(0))).alias("precision"))


def pruning_curve(trail: DataFrame, step: int) -> DataFrame:
    """n, not_pruned and undecided after n = 0, step, ... hashes of the longest walk."""
    stands = _pairs(trail)
    ended = {c: F.coalesce(F.sum(F.when(F.col("status") == c, stands)), F.lit(0).cast("long")).alias(c) for c in ("pruned", "capped")}
    ends = trail.groupBy("n_used").agg(F.sum(stands).alias("ended"), *ended.values())
    total = trail.agg(F.coalesce(F.sum(stands), F.lit(0).cast("long")).alias("total"), F.max("n_used").alias("last"))
    rounds = total.select("total", F.explode(F.sequence(F.lit(0), F.coalesce("last", F.lit(0)), F.lit(step))).alias("n"))
    sofar = Window.orderBy("n").rowsBetween(Window.unboundedPreceding, 0)
    joined = rounds.join(ends, rounds["n"] == ends["n_used"], "left")
    gone = lambda c: F.sum(F.coalesce(c, F.lit(0))).over(sofar)
    return joined.select(
        "n", (F.col("total") - gone(F.col("pruned"))).alias("not_pruned"), (F.col("total") - gone(F.col("ended") - F.col("capped"))).alias("undecided")
    )


def bytes_examined(trail: DataFrame, packed: bool) -> DataFrame:
    """Bytes of hashes read for each pair, both sides, summed and per pair."""
    each = F.col("n_used") * (2 / 8 if packed else 8.0)
    bytes_ = F.sum(each * _pairs(trail))
    return trail.agg(bytes_.alias("bytes"), (bytes_ / F.sum(_pairs(trail))).alias("bytes_per_pair"))


def set_sizes(candidates: DataFrame, out: DataFrame) -> DataFrame:
    a, b = (x.agg(F.coalesce(F.sum(_pairs(x)), F.lit(0).cast("long")).alias(n)) for x, n in ((candidates, "candidates"), (out, "results")))
    return a.join(F.broadcast(b)).withColumn("ratio", F.col("candidates") / F.greatest("results", F.lit(1)))


def hash_work(trail: DataFrame) -> DataFrame:
    """Hashes compared over all pairs, and hashes an object needs: the longest walk of its pairs, on average."""
    stands = _pairs(trail)
    if "id" in trail.columns:
        ends = trail.where("id is not null").groupBy("id", "n").agg(F.max("n_used").alias("most"))
        return _hash_work(trail, ends)
    sizes = [F.col(c) if "pairs" in trail.columns else F.lit(1) for c in ("n_a", "n_b")]
    sides = F.array(*(F.struct(F.col(c).alias("id"), n.alias("n")) for c, n in zip(("id_a", "id_b"), sizes, strict=True)))
    return _hash_work(trail, trail.select(F.explode(sides).alias("o"), "n_used").groupBy("o.id", "o.n").agg(F.max("n_used").alias("most")))


def _hash_work(trail: DataFrame, ends: DataFrame) -> DataFrame:
    stands = _pairs(trail)
    objects = ends.agg((F.sum(F.col("most") * F.col("n")) / F.sum("n")).alias("per_object"))
    compared = F.sum(F.col("n_used") * stands)
    return trail.agg(compared.alias("compared"), (compared / F.sum(stands)).alias("per_pair")).join(F.broadcast(objects))


def speedups(timings: DataFrame, fastest: str) -> DataFrame:
    """Ratio of each method's total seconds to the fastest's: method, seconds, speedup, at_least (the method timed out).

    timings: method, t, seconds, timed_out.
    """
    total = timings.groupBy("method").agg(F.sum("seconds").alias("seconds"), F.max("timed_out").alias("at_least"))
    base = total.where(F.col("method") == fastest).select(F.col("seconds").alias("base"))
    return total.join(F.broadcast(base)).select("method", "seconds", (F.col("seconds").cast("double") / F.col("base").cast("double")).alias("speedup"), "at_least")

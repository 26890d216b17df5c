"""Joins over distinct objects: copies are joined once and expanded, or counted, afterwards.

Whatever a join does with a pair depends on the contents of its two objects alone, so all pairs between two classes of equal objects
have the same outcome, and so have all pairs inside a class.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from simweave.plans.staging import stage

#: Members in one row of a class; two such rows make a row of a result before it is expanded.
CHUNK = 512


def _contents(objects: DataFrame) -> DataFrame:
    """id and h, equal for equal contents: 256 bits of a set, three independent hash sums and the length of a vector."""
    if "features" in objects.columns:
        return objects.select("id", F.sha2(F.concat_ws(",", F.col("features").cast("array<string>")), 256).alias("h"))
    one, two, three = F.xxhash64("feature", "weight"), F.xxhash64("weight", "feature"), F.hash("feature", "weight").cast("long")
    sums = objects.groupBy("id").agg(F.bit_xor(one).alias("x"), F.bit_xor(two).alias("y"), F.sum(three).alias("s"), F.count(F.lit(1)).alias("k"))
    return sums.select("id", F.struct("x", "y", "s", "k").alias("h"))


@dataclass(frozen=True)
class Copies:
    """reps: the object with the smallest id of each class. classes: rep, n (members) and ids (some of them; large classes have several rows)."""

    reps: DataFrame
    classes: DataFrame

    def selves(self) -> DataFrame:
        """id_a = id_b for each class of several members: the pair that stands for those inside it."""
        rep = F.col("rep")
        return self.classes.where("n > 1").select(rep.alias("id_a"), rep.alias("id_b")).distinct()

    def weighed(self, pairs: DataFrame) -> DataFrame:
        """pairs with n_a and n_b, the members of both classes, and pairs, how many pairs of objects a row stands for."""
        sizes = self.classes.select("rep", "n").distinct()
        a, b = (sizes.select(F.col("rep").alias("id_" + s), F.col("n").alias("n_" + s)) for s in "ab")
        n_a, n_b = F.col("n_a"), F.col("n_b")
        stands = F.when(F.col("id_a") == F.col("id_b"), F.floor(n_a * (n_a - 1) / 2)).otherwise(n_a * n_b)
        return pairs.join(a, "id_a").join(b, "id_b").withColumn("pairs", stands.cast("long"))

    def expanded(self, pairs: DataFrame) -> DataFrame:
        """The pairs of objects, id_a < id_b, that the pairs of classes stand for. Only rows of CHUNK members a side are shuffled."""
        a, b = (self.classes.select(F.col("rep").alias("id_" + s), F.col("ids").alias("ids_" + s)) for s in "ab")
        rest = [c for c in pairs.columns if c not in ("id_a", "id_b")]
        spark = pairs.sparkSession
        parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
        both = pairs.join(a, "id_a").join(b, "id_b").repartition(parts)
        each = both.select("id_a", "id_b", "ids_b", *rest, F.explode("ids_a").alias("x")).select("id_a", "id_b", *rest, "x", F.explode("ids_b").alias("y"))
        met = each.where((F.col("id_a") != F.col("id_b")) | (F.col("x") < F.col("y")))
        of = {"id_a": F.least("x", "y").alias("id_a"), "id_b": F.greatest("x", "y").alias("id_b")}
        return met.select(*(of.get(c, F.col(c)) for c in pairs.columns))


def copies_of(objects: DataFrame) -> Copies | None:
    """The classes of equal objects, or None where no two objects are equal."""
    known = stage(_contents(objects), "contents")
    classes = known.groupBy("h").agg(F.min("id").alias("rep"), F.count(F.lit(1)).alias("n"))
    if not classes.where("n > 1").limit(1).count():
        return None
    members = known.join(classes, "h").select("id", "rep", "n")
    part = F.pmod(F.xxhash64("id"), F.ceil(F.col("n") / CHUNK)).alias("part")
    rows = stage(members.groupBy("rep", "n", part).agg(F.collect_list("id").alias("ids")).drop("part"), "classes")
    reps = objects.join(rows.select(F.col("rep").alias("id")).distinct(), "id", "left_semi")
    return Copies(stage(reps, "representatives"), rows)


def nonempty(copies: Copies) -> DataFrame:
    """selves() of the classes that have features: an empty set is similar to nothing."""
    if "features" not in copies.reps.columns:
        return copies.selves()
    full = copies.reps.where(F.size("features") > 0).select(F.col("id").alias("id_a"))
    return copies.selves().join(full, "id_a", "left_semi")

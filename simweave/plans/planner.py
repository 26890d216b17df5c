"""The join as one call: objects, measure, threshold, a generator and a verifier."""

from __future__ import annotations

from dataclasses import dataclass, replace
from math import cos, pi

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from simweave.functions.columns import r2c
from simweave.functions.posterior import BetaPosterior, TruncatedPosterior, beta_from_moments
from simweave.operators import candidates as C
from simweave.operators import exact as X
from simweave.operators import verify as V
from simweave.operators.copies import copies_of, nonempty
from simweave.operators.hashing import HashSource, signatures
from simweave.operators.tiles import Plan, crowded, packed_vectors, tile_join, tile_rows
from simweave.operators.vectorize import binary_weights
from simweave.plans.decision import JoinParams, decision_table, round_up
from simweave.plans.staging import stage

MEASURES = ("jaccard", "cosine", "cosine_binary")


@dataclass(frozen=True)
class PhysicalChoice:
    """Band width, number of bands and hashes of a plan."""

    w: int
    n_bands: int
    cap: int


def default_posterior(measure: str):
    return BetaPosterior() if measure == "jaccard" else TruncatedPosterior()


#: Hashes that bands may use, and the modelled costs of a band row, of a hash and of testing a pair that meets by chance.
BAND_BITS, BAND_INTEGERS = 8192, 1024
ROW_COST, HASH_COST, PAIR_COST = 6.0, 0.2, 1.0


def choose_band_width(measure: str, t: float, fn: float, n_objects: int, cap: int | None = None, typical: float = 0.1) -> PhysicalChoice:
    """The width with the least modelled cost: hashes, band rows and the pairs that unrelated objects (of typical similarity) make.

    The more objects, the wider the bands, so that a bucket holds few unrelated ones.
    """
    from simweave.functions.posterior import cosine_to_angular

    packed = measure != "jaccard"
    cap = cap or (BAND_BITS if packed else BAND_INTEGERS)
    low = cosine_to_angular(typical) if packed else typical
    best = None
    for w in (4, 6, 8, 10, 12, 14, 16, 20, 24, 28, 32) if packed else range(2, 9):
        bands = C.num_bands(t, w, fn, "jaccard" if not packed else "cosine")
        if w * bands > cap:
            continue
        cost = n_objects * (bands * ROW_COST + w * bands * HASH_COST) + bands * n_objects * n_objects / 2 * low**w * PAIR_COST
        if best is None or cost < best[0]:
            best = (cost, PhysicalChoice(w, bands, cap))
    return best[1] if best else PhysicalChoice(8 if packed else 3, C.num_bands(t, 8 if packed else 3, fn, "cosine" if packed else "jaccard"), cap)


def n_objects_of(objects: DataFrame) -> int:
    """Objects of a collection, sets or vectors in long form."""
    return objects.count() if "features" in objects.columns else objects.select("id").distinct().count()


def fit_beta_prior(pairs: DataFrame, objects: DataFrame, measure: str = "jaccard", sample: int = 1000) -> tuple[float, float]:
    """Prior by moments from the exact similarities of a deterministic sample of candidate pairs."""
    # the pairs with the smallest keyed hashes: a cut below which few more than sample lie, and a top-k of those
    total = pairs.count()
    key = F.pmod(F.xxhash64("id_a", "id_b"), F.lit(1 << 40))
    cut = (1 << 40) if total <= 2 * sample else int((1 << 40) * min(1.0, 1.2 * (sample + 100) / total))
    drawn = pairs.where(key < cut).orderBy(key, "id_a", "id_b").limit(sample)
    row = X.exact_similarity(drawn, objects, measure).agg(F.avg("similarity"), F.var_pop("similarity")).first()
    return beta_from_moments(row[0], row[1])


def similarity_join(
    objects: DataFrame, measure: str, t: float, generator: str | DataFrame = "bands", verifier: str = "estimate", *, eps: float = 0.03, delta: float = 0.05, gamma: float = 0.03,
    step: int = 32, cap: int | None = None, fn: float = 0.03, w: int | None = None, n: int | None = None, h: int | None = None, seed: int = 1, family: str = "parity",
    posterior=None, reuse_hashes: bool = True, strategy: str = "auto", sigs: DataFrame | None = None, lazy: bool = True, max_bucket: int | None = None, copies: str = "expanded",
    **options,
) -> DataFrame:
    """Pairs of one collection that are similar.

    objects: (id, features) for 'jaccard' and 'cosine_binary', (id, feature, weight) of unit length for 'cosine'. generator: 'bands',
    'weighted_prefix', 'set_prefix', 'sharing', or a DataFrame (id_a, id_b). verifier: 'estimate', 'prune_exact', 'classical' or
    'exact'. w: hashes a band, by the cost model unless given. reuse_hashes False verifies on hashes that the bands did not use.
    strategy 'fused' puts the first rounds into the band join, 'rounds' walks listed candidates; 'auto' takes the first for packed
    bits and the second for sets, whose hashes are wide and whose buckets hold few unrelated objects. lazy makes hashes beyond the
    first group only for objects that are still in an open pair. max_bucket cuts larger buckets and feature lists into blocks; where
    copies crowd buckets, join the representatives of similarity_classes(). Equal objects are joined once (not with a given generator
    or sigs): copies 'expanded' makes all their pairs from that, 'weighed' returns pairs of representatives with n_a, n_b and pairs,
    the pairs that a row stands for (id_a = id_b: those inside a class), and 'counted', for the trail of an estimate, the same or, where
    most pairs are candidates, the numbers of tile_join(). There packed bits that are verified otherwise are joined tile by tile too, and
    no candidate is a row. Extra options go to the verifier. Results: id_a < id_b,
    similarity, and what the verifier adds.
    """
    if measure not in MEASURES:
        raise ValueError(f"measure must be one of {MEASURES}")
    if verifier not in ("estimate", "prune_exact", "classical", "exact"):
        raise ValueError("unknown verifier")
    if not isinstance(generator, DataFrame) and generator not in ("bands", "weighted_prefix", "set_prefix", "sharing"):
        raise ValueError("unknown generator")
    packed = measure != "jaccard"
    params = JoinParams(t, eps, delta, gamma, step, cap)
    posterior = posterior or default_posterior(measure)
    needs_table = verifier in ("estimate", "prune_exact")
    table = decision_table(posterior, params, verifier == "estimate") if needs_table else None
    if verifier == "prune_exact" and cap is None:
        h = round_up(h or (128 if packed else 64), step)
        table = decision_table(posterior, JoinParams(t, eps, delta, gamma, step, h), False)
    n = n or (2048 if packed else 360)
    objects = objects if hasattr(objects, "staged_at") else stage(objects, "objects")
    if copies not in ("expanded", "weighed", "counted"):
        raise ValueError("copies are expanded, weighed or counted")
    counted, copies = copies == "counted", "weighed" if copies == "counted" else copies
    if counted and not (verifier == "estimate" and options.get("with_trail")):
        raise ValueError("only the trail of an estimate is counted")
    equal = None if isinstance(generator, DataFrame) or sigs is not None else copies_of(objects)
    objects = equal.reps if equal else objects
    ends = (lambda found: getattr(equal, copies)(found)) if equal else lambda found: found.withColumns({c: F.lit(1).cast("long") for c in ("n_a", "n_b", "pairs")}) if copies == "weighed" else found
    banding = isinstance(generator, str) and generator == "bands"
    width = w or (choose_band_width(measure, t, fn, n_objects_of(objects)).w if banding else 0)
    bands = C.num_bands(t, width, fn, "cosine" if packed else "jaccard") if banding else 0
    wanted = max(table.cap if table else 0, n if verifier == "classical" else 0)
    shift = 0 if reuse_hashes else round_up(bands * width, 32)
    vectors = binary_weights(objects) if measure == "cosine_binary" else objects
    source = None
    if sigs is not None:
        source = HashSource(sigs, first=shift)
    elif banding or verifier != "exact":
        first = min(wanted, max(V.FIRST, h or 0)) if lazy and needs_table else wanted
        made = round_up(max(bands * width, first + shift), 32)
        sigs = stage(signatures(vectors, measure, made, seed, family), "signatures")
        source = HashSource(sigs, made, vectors if packed else objects.where(F.size("features") > 0), measure, seed, family, shift)
    tiled = packed and banding and source is not None and not shift and not max_bucket and step % 32 == 0 and (counted or verifier != "estimate" and copies == "expanded")
    if tiled and source.made and crowded(sigs.select("id", F.posexplode(C.band_keys(width, bands, True)).alias("band", "key")), n_objects_of(objects)):
        if made < wanted:
            sigs = stage(signatures(vectors, measure, wanted, seed, family), "signatures")
        return _in_tiles(vectors, sigs, equal, Plan(width, bands), t, verifier, table, n, options.get("closed", False))
    start = 0
    if isinstance(generator, DataFrame):
        pairs = generator
    elif generator == "bands":
        fused = needs_table and reuse_hashes and not options.get("with_trail") and (strategy == "fused" or strategy == "auto" and packed)
        if fused:
            start = min(V.FIRST // step * step, table.cap, h or table.cap)
            fused = start > 0 and (not packed or step % 32 == 0)
        pairs = V.fused_candidates(sigs, table, width, bands, packed, start, max_bucket) if fused else C.banded(sigs, width, bands, packed, max_bucket=max_bucket)
        start = start if fused else 0
    elif generator == "weighted_prefix":
        # binary cosine is never under Jaccard similarity, so the same threshold is complete for both
        pairs = X.prefix_candidates(vectors if packed else binary_weights(objects), t, upper_bound_check=verifier == "exact", max_bucket=max_bucket)
    elif generator == "set_prefix":
        pairs = X.set_prefix_candidates(objects, t, measure, max_bucket=max_bucket)
    else:
        pairs = C.sharing_pairs(vectors if packed else objects.select("id", F.explode("features").alias("feature")), max_bucket)
    if equal:
        selves = nonempty(equal)
        pairs = pairs.unionByName(selves.withColumn("state", V.state_of_equal(table, start)) if start else selves)
    if verifier == "exact":
        return ends(X.verify_all_exact(pairs, objects, t, measure))
    if not isinstance(generator, DataFrame):
        pairs = stage(pairs, "candidates")
    if verifier == "estimate":
        return ends(V.verify_estimate(pairs, source, table, packed, objects=objects, seed=seed, family=family, start=start, **options))
    if verifier == "prune_exact":
        return ends(V.verify_prune_exact(pairs, source, objects, table, packed, measure, h, start=start, **options))
    return ends(V.verify_classical(pairs, source, t, n, packed))


def _in_tiles(vectors: DataFrame, sigs: DataFrame, equal, bands: Plan, t: float, verifier: str, table, n: int, closed: bool) -> DataFrame:
    """similarity_join() over banded packed bits, with the verification inside tile_join()."""
    rows = lambda own: tile_rows(own, equal)
    value = F.round("similarity", 9)
    if verifier == "estimate":
        return tile_join(rows(sigs), replace(bands, rounds=table, upto=table.cap, counted=True))
    if verifier == "classical":
        least = next((m for m in range(n + 1) if cos(pi * (1 - m / n)) >= t - 1e-8), n + 1)
        found = tile_join(rows(sigs), replace(bands, bits=n, least=least)).withColumn("similarity", r2c(F.col("matches") / n))
        return found.where(value >= t).select("id_a", "id_b", "similarity", "matches")
    both = rows(sigs.join(packed_vectors(vectors), "id"))
    if verifier == "exact":
        return tile_join(both, replace(bands, dot=t)).where(value >= t)
    return tile_join(both, replace(bands, rounds=table, upto=table.cap, dot=t)).where(value >= t if closed else value > t)


def similarity_classes(objects: DataFrame, measure: str, t: float, generator: str = "bands", verifier: str = "estimate", **options) -> tuple[DataFrame, DataFrame]:
    """Pairs between representatives of equal objects, and id to rep of every object: copies are never paired with each other."""
    reps, members = C.collapse_duplicates(objects)
    return similarity_join(stage(reps, "representatives"), measure, t, generator, verifier, **options), members


def similarity_search(queries: DataFrame, corpus: DataFrame, measure: str, t: float | None = None, k: int | None = None) -> DataFrame:
    """For each query (id_a) the corpus objects (id_b) at or over t, or the k most similar: exact, through shared features."""
    if measure == "cosine":
        a = queries.select(F.col("id").alias("id_a"), "feature", F.col("weight").alias("wa"))
        b = corpus.select(F.col("id").alias("id_b"), "feature", F.col("weight").alias("wb"))
        found = a.join(b, "feature").groupBy("id_a", "id_b").agg(F.sum(F.col("wa") * F.col("wb")).alias("similarity"))
    else:
        rows = [x.select(F.col("id").alias(n), F.explode("features").alias("feature"), F.size("features").alias("n" + n[-1])) for x, n in ((queries, "id_a"), (corpus, "id_b"))]
        shared = rows[0].join(rows[1], "feature").groupBy("id_a", "id_b", "na", "nb").agg(F.count(F.lit(1)).alias("i"))
        value = F.col("i") / (F.col("na") + F.col("nb") - F.col("i")) if measure == "jaccard" else F.col("i") / F.sqrt(F.col("na").cast("double") * F.col("nb"))
        found = shared.select("id_a", "id_b", value.alias("similarity"))
    if t is not None:
        found = found.where(F.round("similarity", 9) >= t)
    if k is not None:
        rank = Window.partitionBy("id_a").orderBy(F.round("similarity", 9).desc(), "id_b")
        found = found.withColumn("rank", F.row_number().over(rank)).where(F.col("rank") <= k)
    return found

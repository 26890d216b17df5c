"""Verification of candidate pairs: posterior estimate, posterior prune with exact check, match fraction, exact.

A pair's verdict is read off the decision table at every multiple of the step, prune test before accept test, so results do
not depend on how rounds are grouped into joins or on the physical strategy.
"""

from __future__ import annotations

from functools import reduce
from operator import and_, or_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from simweave.functions.columns import matches_int, r2c
from simweave.operators.candidates import band_keys, in_blocks
from simweave.operators.exact import exact_similarity
from simweave.operators.hashing import HashSource, extend_signatures
from simweave.plans.decision import DecisionTable
from simweave.plans.staging import stage

#: Hashes of the first group of rounds, and how much longer each further group is; the last one ends at the cap.
FIRST, LONGER = 128, 4


def round_matches(a: Column, b: Column, k: Column, step: int, packed: bool) -> Column:
    """Equal hashes of round k (from 0) of two signature arrays."""
    if packed:
        words = step // 32
        return sum((F.lit(32) - F.bit_count(F.get(a, k * words + j).bitwiseXOR(F.get(b, k * words + j))) for j in range(words)), F.lit(0))
    pairs = F.zip_with(F.slice(a, (k * step + 1).cast("int"), step), F.slice(b, (k * step + 1).cast("int"), step), lambda x, y: (x == y).cast("int"))
    return F.aggregate(pairs, F.lit(0), lambda s, x: s + x)


def _start() -> Column:
    return F.struct(F.lit(0).alias("n_used"), F.lit(0).alias("matches"), F.lit("continue").alias("status"))


def walk(state: Column, a: Column, b: Column, table: DecisionTable, lo: int, hi: int, packed: bool) -> Column:
    """The state (n_used, matches, status) after hashes lo to hi; a and b hold those hashes only."""
    step = table.params.step
    first, last = lo // step, hi // step
    fewest = F.array(*(F.lit(x) for x in table.fewest[first:last]))
    none = F.array(F.struct(F.lit(1).alias("lo"), F.lit(0).alias("hi")))
    runs = [F.array(*(F.struct(F.lit(x).alias("lo"), F.lit(y).alias("hi")) for x, y in own)) if own else none for own in table.accepted[first:last]]
    accepted = F.array(*runs)

    def turn(acc: Column, k: Column) -> Column:
        m = (acc["matches"] + round_matches(a, b, k, step, packed)).cast("int")
        ok = F.exists(F.get(accepted, k), lambda r: m.between(r["lo"], r["hi"]))
        status = F.when(m < F.get(fewest, k), "pruned").when(ok, "accepted").otherwise("continue")
        on = F.struct((acc["n_used"] + step).cast("int").alias("n_used"), m.alias("matches"), status.alias("status"))
        return F.when(acc["status"] == "continue", on).otherwise(acc)

    return F.aggregate(F.sequence(F.lit(0), F.lit(last - first - 1)), state, turn)


def estimate(n: Column, m: Column, table: DecisionTable) -> Column:
    """The posterior mode of the similarity as a Column (the table's measure decides the map)."""
    p = table.posterior
    if p.measure == "cosine":
        return r2c(F.least(F.greatest(m / n, F.lit(p.low)), F.lit(p.high)))
    alpha, beta = getattr(p, "alpha", 1.0), getattr(p, "beta", 1.0)
    return F.least(F.greatest((m + (alpha - 1)) / (n + (alpha + beta - 2)), F.lit(0.0)), F.lit(1.0))


def _attach(pairs: DataFrame, sigs: DataFrame | HashSource, lo: int, hi: int, packed: bool) -> DataFrame:
    """The signature part of hashes lo to hi of both sides, as columns a and b."""
    source = sigs if isinstance(sigs, HashSource) else HashSource(sigs)
    part = source.part(lo, hi, pairs, packed)
    a = part.select(F.col("id").alias("id_a"), F.col("part").alias("a"))
    b = part.select(F.col("id").alias("id_b"), F.col("part").alias("b"))
    return pairs.join(a, "id_a").join(b, "id_b")


def group_bounds(upto: int, step: int, made: int | None = None, start: int = 0) -> list[int]:
    """Ends of the groups of rounds from start to upto: the first is FIRST or what is made already, each further one LONGER times
    as far, and a last one that would be short joins the one before."""
    first = max(min(FIRST, made or FIRST) // step * step, step)
    out, x = [start], start * LONGER or first
    while out[-1] < upto:
        out.append(upto if 2 * x >= upto and out[-1] or x >= upto else x)
        x = out[-1] * LONGER
    return out


def walk_pairs(pairs: DataFrame, sigs: DataFrame | HashSource, table: DecisionTable, packed: bool, upto: int | None = None, groups: tuple[int, ...] | None = None, start: int = 0) -> DataFrame:
    """id_a, id_b, n_used, matches and status of every candidate ('continue' where hashes ended at upto).

    One join per group of rounds, each only for pairs that are still open and only for the next part of the signatures; with a
    HashSource, parts that were not made yet are made for the objects of those pairs only. pairs with a column state have been
    walked up to start.
    """
    upto = upto or table.cap
    step = table.params.step
    if groups is None:
        bounds = group_bounds(upto, step, sigs.made if isinstance(sigs, HashSource) else None, start)
    else:
        bounds = [start, *(g for g in groups if start < g < upto and g % step == 0), *([upto] if upto > start else [])]
    parts = []
    if ("state" in pairs.columns) != (start > 0):
        raise ValueError("start says how far pairs with a state have been walked")
    if "state" in pairs.columns:
        parts.append(pairs.where(F.col("state.status") != "continue"))
        open_ = pairs.where(F.col("state.status") == "continue")
    else:
        open_ = pairs.withColumn("state", _start())
    for lo, hi in zip(bounds[:-1], bounds[1:], strict=True):
        after = _attach(open_, sigs, lo, hi, packed).withColumn("state", walk(F.col("state"), F.col("a"), F.col("b"), table, lo, hi, packed)).drop("a", "b")
        if hi < upto:
            after = stage(after, "walked")
            parts.append(after.where(F.col("state.status") != "continue"))
            open_ = after.where(F.col("state.status") == "continue")
            if not open_.limit(1).count():
                open_ = None
                break
        else:
            parts.append(after)
            open_ = None
    if open_ is not None:
        parts.append(open_)
    return reduce(DataFrame.unionByName, parts).select("id_a", "id_b", "state.n_used", "state.matches", "state.status")


def verify_estimate(
    pairs: DataFrame, sigs: DataFrame | HashSource, table: DecisionTable, packed: bool, keep: str = "unpruned", on_cap: str = "emit", objects: DataFrame | None = None,
    seed: int = 1, family: str = "parity", with_trail: bool = False, groups: tuple[int, ...] | None = None, extend_to: int | None = None, start: int = 0,
) -> DataFrame:
    """Pairs that were not pruned, with their estimate: id_a, id_b, similarity, n_used, matches, status.

    keep 'estimate_ge_t' drops estimates under the threshold. Pairs still open at the cap are emitted with status 'capped',
    verified exactly ('exact', needs objects), or walked on with freshly made hashes up to extend_to ('extend', needs objects).
    with_trail returns every candidate, pruned ones with a null similarity.
    """
    trail = walk_pairs(pairs, sigs, table, packed, groups=groups, start=start)
    trail = trail.withColumn("similarity", F.when(F.col("status") != "pruned", estimate(F.col("n_used"), F.col("matches"), table)))
    measure = table.posterior.measure
    if on_cap == "extend":
        from simweave.plans.decision import JoinParams, decision_table

        p = table.params
        more = decision_table(table.posterior, JoinParams(p.t, p.eps, p.delta, p.gamma, p.step, extend_to or 2 * table.cap))
        open_ = trail.where("status = 'continue'").select("id_a", "id_b", F.struct("n_used", "matches", "status").alias("state"))
        alive = open_.select(F.col("id_a").alias("id")).union(open_.select(F.col("id_b").alias("id")))
        tail = extend_signatures(objects, alive, table.cap, more.cap, measure, seed, family)
        after = _attach(open_, HashSource(tail), 0, more.cap - table.cap, packed).withColumn("state", walk(F.col("state"), F.col("a"), F.col("b"), more, table.cap, more.cap, packed))
        after = after.select("id_a", "id_b", "state.n_used", "state.matches", "state.status")
        after = after.withColumn("similarity", F.when(F.col("status") != "pruned", estimate(F.col("n_used"), F.col("matches"), more)))
        trail = trail.where("status <> 'continue'").unionByName(after)
    elif on_cap == "exact":
        open_ = trail.where("status = 'continue'")
        known = exact_similarity(open_.select("id_a", "id_b"), objects, measure if objects is None or "features" not in objects.columns else "cosine_binary" if measure == "cosine" else "jaccard")
        known = open_.drop("similarity", "status").join(known, ["id_a", "id_b"]).withColumn("status", F.when(F.round("similarity", 9) >= table.params.t, "exact").otherwise("pruned"))
        trail = trail.where("status <> 'continue'").unionByName(known.select(*trail.columns))
    trail = trail.withColumn("status", F.when(F.col("status") == "continue", "capped").otherwise(F.col("status")))
    out = trail.select("id_a", "id_b", "similarity", "n_used", "matches", "status")
    if with_trail:
        return out
    out = out.where("status <> 'pruned'")
    return out.where(F.round("similarity", 9) >= table.params.t) if keep == "estimate_ge_t" else out


def verify_prune_exact(
    pairs: DataFrame, sigs: DataFrame | HashSource, objects: DataFrame, table: DecisionTable, packed: bool, measure: str, h: int | None = None, closed: bool = False, start: int = 0
) -> DataFrame:
    """Pairs that no round up to h hashes prunes and whose exact similarity is over t (at or over it if closed)."""
    h = h or (128 if packed else 64)
    h = -(-h // table.params.step) * table.params.step
    alive = stage(walk_pairs(pairs, sigs, table, packed, upto=h, groups=(), start=start).where("status <> 'pruned'").select("id_a", "id_b"), "not-pruned")
    known = exact_similarity(alive, objects, measure)
    value = F.round("similarity", 9)
    return known.where(value >= table.params.t if closed else value > table.params.t)


def verify_classical(pairs: DataFrame, sigs: DataFrame | HashSource, t: float, n: int, packed: bool) -> DataFrame:
    """Match fraction of n hashes (cosine: mapped to the cosine), kept at or over t: id_a, id_b, similarity, matches."""
    both = _attach(pairs, sigs, 0, n, packed)
    if packed:
        m = F.aggregate(F.zip_with("a", "b", lambda x, y: F.lit(32) - F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)
    else:
        m = matches_int(F.col("a"), F.col("b"), 0, n)
    value = r2c(F.col("matches") / n) if packed else F.col("matches") / n
    return both.select("id_a", "id_b", m.alias("matches")).withColumn("similarity", value).where(F.round("similarity", 9) >= t).select("id_a", "id_b", "similarity", "matches")


def fused_candidates(sigs: DataFrame, table: DecisionTable, w: int, n_bands: int, packed: bool, upto: int = FIRST, max_bucket: int | None = None) -> DataFrame:
    """Banded candidates whose first upto hashes do not prune them, with their state (n_used, matches, status) after those.

    The prune test is part of the join condition: the prefix words travel with the band rows, so pairs that are pruned
    early are never rows, and only survivors are deduplicated by a shuffle.
    """
    step = table.params.step
    upto = min(upto // step * step, table.cap)
    parts = upto // step
    half = F.lit(0xFFFFFFFF)
    if packed:
        # two words of 32 bits a column
        high = lambda k: F.call_function("shiftleft", F.coalesce(F.get("sig", F.lit(k + 1)), F.lit(0).cast("long")), F.lit(32))
        words = [F.get("sig", F.lit(k)).bitwiseOR(high(k)).alias(f"p{k // 2}") for k in range(0, upto // 32, 2)]
    else:
        words = [F.transform(F.slice("sig", k * step + 1, step), lambda x: x.bitwiseAND(F.lit(0x7FFFFFFF)).cast("int")).alias(f"p{k}") for k in range(parts)]
    names = [f"p{k}" for k in range(len(words))]
    rows = sigs.select("id", *words, F.posexplode(band_keys(w, n_bands, packed)).alias("band", "key"))
    left, right, on = in_blocks(rows, ["band", "key"], max_bucket)
    a = left.select(*on, F.col("id").alias("id_a"), *(F.col(x).alias(x + "a") for x in names))
    b = right.select(*on, F.col("id").alias("id_b"), *(F.col(x).alias(x + "b") for x in names))

    def word(j: int) -> Column:
        differ = F.col(f"p{j // 2}a").bitwiseXOR(F.col(f"p{j // 2}b"))
        return F.lit(32) - F.bit_count(F.call_function("shiftrightunsigned", differ, F.lit(32)) if j % 2 else differ.bitwiseAND(half))

    def found(k: int) -> Column:
        return sum((word(j) for j in range(k * step // 32, (k + 1) * step // 32)), F.lit(0)) if packed else matches_int(F.col(f"p{k}a"), F.col(f"p{k}b"), 0, step)

    sums = []
    for k in range(parts):
        sums.append((sums[-1] if sums else F.lit(0)) + found(k))
    accepted = [reduce(or_, (sums[k].between(lo, hi) for lo, hi in table.accepted[k]), F.lit(False)) for k in range(parts)]
    alive = F.lit(True)
    for k in reversed(range(parts)):
        alive = (sums[k] >= table.fewest[k]) & (accepted[k] | alive)
    state = lambda k, status: F.struct(F.lit((k + 1) * step).alias("n_used"), sums[k].cast("int").alias("matches"), F.lit(status).alias("status"))
    after = state(parts - 1, "continue")
    for k in reversed(range(parts)):
        after = F.when(accepted[k], state(k, "accepted")).otherwise(after)
    met = a.join(b, reduce(and_, (a[c] == b[c] for c in on)) & (F.col("id_a") < F.col("id_b")) & alive)
    return met.select("id_a", "id_b", after.alias("state")).dropDuplicates(["id_a", "id_b"])


def state_of_equal(table: DecisionTable, upto: int) -> Column:
    """The state of a pair whose first upto hashes all agree."""
    step = table.params.step
    status, n = "continue", upto
    for k in range(upto // step):
        if any(lo <= (k + 1) * step <= hi for lo, hi in table.accepted[k]):
            status, n = "accepted", (k + 1) * step
            break
    return F.struct(F.lit(n).alias("n_used"), F.lit(n).alias("matches"), F.lit(status).alias("status"))


def trace_pairs(pairs: DataFrame, sigs: DataFrame, table: DecisionTable, packed: bool, upto: int) -> DataFrame:
    """The rounds of each pair up to upto hashes: id_a, id_b, n, m, fewest and estimate."""
    step = table.params.step
    both = _attach(pairs, sigs, 0, upto, packed)
    per = F.transform(F.sequence(F.lit(0), F.lit(upto // step - 1)), lambda k: round_matches(F.col("a"), F.col("b"), k, step, packed))
    running = F.transform(per, lambda _, k: F.aggregate(F.slice(per, 1, k + 1), F.lit(0), lambda s, x: s + x))
    rows = both.select("id_a", "id_b", F.posexplode(running).alias("k", "m"))
    fewest = F.array(*(F.lit(x) for x in table.fewest[: upto // step]))
    n = ((F.col("k") + 1) * step).cast("int")
    return rows.select("id_a", "id_b", n.alias("n"), F.col("m").cast("int").alias("m"), F.get(fewest, F.col("k")).alias("fewest"), estimate(n, F.col("m"), table).alias("estimate"))

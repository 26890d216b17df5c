"""What only shows on larger tables: ties, orders that a shuffle loses, rows and disk of joins."""

import duckdb
import numpy as np
import pytest
from oracle import same
from pyspark.sql import functions as F

from simweave.operators import blocks, copies, exact, tiles
from simweave.plans import planner
from simweave.plans.decision import JoinParams, decision_table
from simweave.plans.planner import default_posterior
from simweave.plans.staging import stage
from simweave.queries import hashes, joins, load, studies
from simweave.workloads import collection

D = "/root/testdata/sf0.001"
QUERIES, ORACLES = load()


def plan(frame) -> str:
    return frame._jdf.queryExecution().optimizedPlan().toString()


def test_topk_keeps_its_order_through_the_shuffle(spark):
    frame = QUERIES["o08_lateral_topk"](spark, D)
    windows = [line for line in plan(frame).splitlines() if "row_number()" in line and "windowspecdefinition" in line]
    assert windows and all("o_totalprice" in line for line in windows)


def test_dearest_line_is_the_first_of_a_tie(spark, tmp_path):
    lines = spark.read.parquet(f"{D}/lineitem.parquet")
    shift = lines.agg(F.max("l_orderkey")).first()[0] + 1
    copies = lines.withColumn("copy", F.explode(F.array(*map(F.lit, reversed(range(6))))))
    copies.withColumn("l_orderkey", F.col("l_orderkey") + F.col("copy") * shift).drop("copy").repartition(8).write.parquet(f"{tmp_path}/lineitem.parquet")
    dearest = lambda d: {r["l_returnflag"]: r["dearest"] for r in QUERIES["o09_aggregates"](spark, d).collect()}
    assert dearest(str(tmp_path)) == dearest(D)


COPIES = {"pages": ("page_id", 100_000), "events": ("user_id", 100_000)}


@pytest.fixture(scope="module")
def copied(spark, tmp_path_factory):
    """The tables with each page and each user four times."""
    d = tmp_path_factory.mktemp("copied")
    for name in ("events", "pages"):
        key, shift = COPIES[name]
        rows = spark.read.parquet(f"{D}/{name}.parquet").withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(3))))
        rows = rows.withColumn(key, F.col(key) + F.col("copy") * shift)
        rows = rows.withColumn("event_id", F.col("event_id") + F.col("copy") * shift) if name == "events" else rows
        rows.drop("copy").write.parquet(f"{d}/{name}.parquet")
    return str(d)


OF_COPIES = ["c01_bands_jaccard", "c07_hot_bucket_blocks", "bs_ml_jaccard", "v03_classical_jaccard", "h07_collision_law_jaccard", "v01_estimate_cosine_binary"]
OF_COPIES += ["b01_weighted_join_l2", "b01_weighted_join_maxweight", "bs_exact_cosine", "bs_ml_cosine", "v02_prune_exact_cosine", "v03_classical_cosine", "v05_fused_equals_rounds"]
OF_COPIES += ["a07_pruning_curve", "a08_bytes_examined", "a09_set_sizes", "a10_hash_work"]


@pytest.mark.parametrize("name", OF_COPIES)
def test_copies_are_joined_once_with_the_same_rows(spark, copied, name, monkeypatch):
    """The oracle's rows on tables of copies, and every dot product, signature and candidate is of distinct objects."""
    seen = []
    of = copies.copies_of
    for module in (joins, hashes, exact, planner):
        monkeypatch.setattr(module, "copies_of", lambda objects: seen.append(of(objects)) or seen[-1])
    duck = duckdb.connect()
    for table in COPIES:
        duck.execute(f"create view {table} as select * from '{copied}/{table}.parquet/*.parquet'")
    frame = QUERIES[name](spark, copied)
    assert same(frame, duck.execute(ORACLES[name]))
    assert seen and all(c.reps.select("id").distinct().count() * 4 <= c.classes.agg(F.sum(F.size("ids"))).first()[0] for c in seen)


MOVED = ["a02_speedups", "a04_prune_probability", "a13_classical_variance", "b05_hashes_needed_inward", "c02_num_bands", "d01_min_matches_cosine", "d01_min_matches_jaccard"]
MOVED += ["d02_verdicts_cosine", "d02_verdicts_jaccard", "d03_gaussian_codes", "d04_required_cap_cosine", "d04_required_cap_jaccard"]


@pytest.mark.parametrize("name", MOVED)
def test_tables_are_read_by_spark(spark, name):
    """The rows come from a scan of a given table, and follow it."""
    assert "Relation" in plan(QUERIES[name](spark, D))


def test_levels_follow_the_table(spark, tmp_path):
    spark.read.parquet(f"{D}/lineitem.parquet").where("l_discount in (0.02, 0.06)").write.parquet(f"{tmp_path}/lineitem.parquet")
    for name in ("a04_prune_probability", "c02_num_bands", "d01_min_matches_jaccard", "d04_required_cap_cosine"):
        assert {r["t"] for r in QUERIES[name](spark, str(tmp_path)).collect()} == {0.5, 0.7}


def test_sessions_are_not_collected_on_the_driver(spark):
    assert "parquet" in QUERIES["s01_session"](spark, D)._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("measure,t", [("jaccard", 0.5), ("cosine_binary", 0.7)])
def test_set_join_in_blocks_shuffles_no_pair(spark, measure, t, monkeypatch):
    """The rows of the brute force from several blocks; candidates are never rows of a join."""
    monkeypatch.setattr(blocks, "BLOCK", 6_000)
    sets = stage(collection(spark, D, "docs_words"), "sets")
    pairs = lambda frame: {(r["id_a"], r["id_b"], round(r["similarity"], 9)) for r in frame.collect()}
    frame = exact.exact_set_join(sets, t, measure, suffix=True)
    assert pairs(frame) == pairs(exact.brute_force_join(sets, t, measure)) != set()
    assert not any("token" in line for line in plan(frame).splitlines())


def test_dot_products_in_blocks_shuffle_no_pair(spark, monkeypatch):
    monkeypatch.setattr(blocks, "BLOCK", 40_000)
    vectors = stage(collection(spark, D, "docs_tfidf"), "vectors")
    pairs = lambda frame: {(r["id_a"], r["id_b"], round(r["similarity"], 8)) for r in frame.collect()}
    assert pairs(blocks.block_dot_join(vectors, 0.5)) == pairs(exact.brute_force_join(vectors, 0.5, "cosine")) != set()
    assert "Join" not in plan(QUERIES["b07_brute_force_cosine"](spark, D))


@pytest.mark.parametrize("measure,t", [("jaccard", 0.2), ("cosine_binary", 0.4)])
def test_counts_in_blocks_shuffle_no_pair(spark, measure, t, monkeypatch):
    """The rows of the brute force from several blocks and rounds of counting; ids that are far apart, sets without features."""
    monkeypatch.setattr(blocks, "BLOCK", 6_000)
    monkeypatch.setattr(blocks, "AT_ONCE", 2_000)
    words = collection(spark, D, "docs_words").withColumn("id", F.col("id") * 1_000_003)
    sets = stage(words.unionByName(words.limit(1).select(F.lit(-1).cast("long").alias("id"), F.array().cast("array<long>").alias("features"))), "sets")
    pairs = lambda frame: sorted((r["id_a"], r["id_b"], round(r["similarity"], 9)) for r in frame.collect())
    assert pairs(blocks.block_count_join(sets, t, measure)) == pairs(exact.brute_force_join(sets, t, measure)) != []
    assert "Join" not in plan(QUERIES["b07_brute_force_jaccard"](spark, D))


@pytest.fixture(scope="module")
def crowd(spark, tmp_path_factory):
    """Events of 120 users, no two alike, with a few exact copies: most pairs of them are candidates."""
    d = tmp_path_factory.mktemp("crowd")
    rows = spark.read.parquet(f"{D}/events.parquet").withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(8))))
    # the last copy is moved as the one before it
    hours = F.pmod(F.xxhash64("event_id", F.least(F.col("copy"), F.lit(7))), F.lit(24))
    rows = rows.withColumn("ts", F.col("ts") + F.make_dt_interval(hours=hours.cast("int"))).withColumn("user_id", F.col("user_id") + F.col("copy") * 100_000)
    rows.drop("copy").write.parquet(f"{d}/events.parquet")
    return str(d)


def crowd_oracle(d, name):
    duck = duckdb.connect()
    duck.execute(f"create view events as select * from '{d}/events.parquet/*.parquet'")
    return duck.execute(ORACLES[name])


@pytest.mark.parametrize("name", ["a07_pruning_curve", "a08_bytes_examined", "a09_set_sizes", "a10_hash_work"])
def test_walks_of_a_crowd_are_numbers(spark, crowd, name, monkeypatch):
    """The oracle's rows where most pairs are candidates, from a table without a row a candidate."""
    monkeypatch.setattr(tiles, "SLICE", 48)
    trails = []
    of = studies._weighed_trail
    monkeypatch.setattr(studies, "_weighed_trail", lambda *a: trails.append(of(*a)) or trails[-1])
    assert same(QUERIES[name](spark, crowd), crowd_oracle(crowd, name))
    candidates = trails[0].agg(F.sum("pairs")).first()[0]
    assert trails[0].where("pairs > 0").groupBy("n_used", "status").count().count() * 20 < candidates and "id_b" not in trails[0].columns


@pytest.mark.parametrize("name", ["b01_weighted_join_l2", "b01_weighted_join_maxweight", "bs_exact_cosine", "bs_ml_cosine", "v02_prune_exact_cosine", "v03_classical_cosine"])
def test_joins_of_a_crowd_shuffle_no_candidate(spark, crowd, name, monkeypatch):
    """The oracle's rows from several blocks and slices; candidates are never rows of a join."""
    monkeypatch.setattr(tiles, "SLICE", 24)
    monkeypatch.setattr(tiles, "BLOCK_BYTES", 60_000)
    frame = QUERIES[name](spark, crowd)
    assert same(frame, crowd_oracle(crowd, name))
    assert "Join" not in plan(frame)


def test_tiles_with_rare_keys_and_features(spark, monkeypatch):
    """Lists beside bits and columns, all pairs that share a prefix feature, and sums of sign bits by both ways."""
    from simweave.operators import hashing

    vectors = stage(collection(spark, D, "docs_tfidf"), "vectors")
    pairs = lambda frame: {(r["id_a"], r["id_b"], round(r["similarity"], 8)) for r in frame.collect()}
    truth = pairs(exact.brute_force_join(vectors, 0.3, "cosine"))
    monkeypatch.setattr(exact, "crowded", lambda *_: True)
    monkeypatch.setattr(tiles, "AT_ONCE", 500)
    assert pairs(exact.exact_weighted_join(vectors, 0.3)) == truth != set()
    some = vectors.where("id % 7 = 0")
    bits = {}
    for filled in (0, 1 << 40):
        monkeypatch.setattr(hashing, "FILLED", filled)
        x = some.select("id", "feature", "weight").groupBy("id").agg(F.array_sort(F.collect_list(F.struct("feature", "weight"))).alias("v")).orderBy("id").collect()
        names = {f: k + 1 for k, f in enumerate(sorted({e["feature"] for r in x for e in r["v"]}))}
        own = [[(names[e["feature"]], int(e["weight"] * hashing.WEIGHT_SCALE + 0.5)) for e in r["v"]] for r in x]
        ends = np.cumsum([0, *map(len, own)])
        f, w = (np.array([e[k] for v in own for e in v], np.int64) for k in (0, 1))
        bits[filled] = hashing._signs(f, w, ends, 96, 1, "table", 0)
    assert (bits[0] == bits[1 << 40]).all()
    lone = [sum(int(2 * hashing.gaussian_codes(np.array([a]), 0, 1, 1, "table")[0, 0] + 1 - 2 * hashing.LIMIT * hashing.CODES_PER_UNIT) * b for a, b in v) >= 0 for v in own]
    assert [bool(b & 1) for b in bits[0][:, 0]] == lone


def test_walk_of_a_tile_against_single_pairs(monkeypatch):
    """Ends, longest walks and survivors, with classes of several members and without, whatever the strips and lists."""
    draw = np.random.default_rng(5)
    table = decision_table(default_posterior("cosine"), JoinParams(0.7, cap=512))
    near = draw.integers(0, 2**32, (16, 1), dtype=np.uint32) ^ (draw.integers(0, 2**32, (16, 60), dtype=np.uint32) & draw.integers(0, 2**32, (16, 60), dtype=np.uint32) & draw.integers(0, 2**32, (16, 60), dtype=np.uint32))
    far = draw.integers(0, 2**32, (16, 60), dtype=np.uint32)
    words = np.where(np.arange(60) % 3, near, far)
    monkeypatch.setattr(tiles, "STRIP", 7)
    monkeypatch.setattr(tiles, "PART", 50)
    for members in (np.ones(60, np.int64), 1 + np.arange(60) % 3):
        ends = np.concatenate([[0], np.cumsum(members)])
        side = tiles.Side(np.arange(60), tiles.Lists(np.arange(ends[-1]), ends), words)
        plan = tiles.Plan(8, 2, table, table.cap, counted=True)
        own, block, tally = side.part(20, 60), tiles.Slice(side.part(0, 50), plan), tiles.Tally(plan)
        met = draw.random((40, 50)) < 0.6
        met[3] = False
        ended, most, left = {}, {}, np.zeros_like(met)
        for i, j in np.argwhere(met):
            x, y, weight = 20 + i, j, int(members[20 + i] * members[j])
            n = m = 0
            for k in range(table.cap // 32):
                n, m = n + 32, m + 32 - int(words[k, x] ^ words[k, y]).bit_count()
                if table.verdict(n, m) != "continue":
                    break
            status = {"prune": "pruned", "accept": "accepted"}.get(table.verdict(n, m), table.verdict(n, m))
            status = "capped" if status == "continue" else status
            ended[n, status] = ended.get((n, status), 0) + weight
            left[i, j] = status != "pruned"
            for o in (x, y):
                most[o] = max(most.get(o, 0), n)
        tiles._walk(own, block, met, plan, tally)
        assert tally.ends == ended and len({s for _, s in ended}) > 1
        assert {i: n for i, (_, n) in tally.most.items()} == most and len(set(most.values())) > 3
        assert (met == left).all()

"""Queries over the streaming forms: streams are replayed from files to their end, then their tables are read."""

from __future__ import annotations

from pyspark.sql import functions as F

from simweave.operators import candidates as C
from simweave.operators import verify as V
from simweave.operators.exact import brute_force_join
from simweave.operators.hashing import minhash
from simweave.operators.vectorize import shingle_sets
from simweave.oracles import sql as S
from simweave.plans.staging import stage
from simweave.queries import query
from simweave.queries.joins import _round
from simweave.sources.tables import table
from simweave.streaming import streams as T
from simweave.workloads import decision_of


def _events(spark, d):
    return table(spark, d, "events", "event_id", "ts", "user_id", "event_type").withColumn("ts", F.col("ts").cast("timestamp"))


_HOUR = "date_trunc('hour', ts)::TIMESTAMP"


@query("s01_tumbling", f"SELECT {_HOUR} AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def s01(spark, d):
    out = T.run_to_table(T.windowed_counts(T.replay(_events(spark, d), "ts", 4)), "complete")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query("s01_sliding", f"SELECT start, event_type, count(*) AS n FROM (SELECT unnest([{_HOUR}, {_HOUR} - INTERVAL 1 HOUR]) AS start, event_type FROM events) GROUP BY ALL")
def s01_sliding(spark, d):
    out = T.run_to_table(T.windowed_counts(T.replay(_events(spark, d), "ts", 4), "sliding"), "complete")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query(
    "s01_session",
    """SELECT min(ts) AS start, user_id, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM (
      SELECT *, (ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) >= INTERVAL 30 MINUTE OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) IS NULL)::INT AS fresh FROM events)) GROUP BY user_id, g""",
)
def s01_session(spark, d):
    """Append mode: sessions go to files as they close, so neither the driver nor the state holds them all. A last row a day after all
    others closes theirs; its own stays open and is never written."""
    events = _events(spark, d)
    none = [F.lit(None).cast(t).alias(c) for c, t in events.dtypes if c != "ts"]
    closing = events.agg((F.max("ts") + F.expr("interval 1 day")).alias("ts")).where("ts is not null").select("ts", *none).select(*events.columns)
    out = T.run_to_table(T.windowed_counts(T.replay(events, "ts", 4, closing), "session"), "append")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "user_id", "n")


@query("s02_late_data", f"SELECT {_HOUR} AS start, event_type, count(*) AS n FROM events WHERE {_HOUR} + INTERVAL 1 HOUR <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) GROUP BY ALL")
def s02(spark, d):
    """Append mode: closed windows only; a late copy of the first events, far behind the watermark, is dropped."""
    events = _events(spark, d)
    late = events.orderBy("ts", "event_id").limit(20).withColumn("event_id", F.col("event_id") + 10_000_000)
    out = T.run_to_table(T.windowed_counts(T.replay(events, "ts", 4, late)), "append")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query("s03_stream_dedup", "SELECT event_id, user_id FROM events")
def s03(spark, d):
    events = _events(spark, d)
    twice = events.unionByName(events.where("event_id % 3 = 0"))
    return T.run_to_table(T.deduplicated(T.replay(twice, "ts", 4), "1 day"), "append").select("event_id", "user_id")


_BANDS = C.num_bands(0.5, 3, 0.03)


@query("s04_incremental_join")
def s04(spark, d):
    """All documents arrive in 4 batches, under the default cap; SQL over all of them is too slow, tests compare with one join."""
    docs = table(spark, d, "documents", "doc_id", "text")
    decisions = decision_of("jaccard", 0.5)
    n = max(decisions.cap, 3 * _BANDS)
    join = T.IncrementalJoin(
        spark, lambda b: minhash(shingle_sets(b).where(F.size("features") > 0), n), lambda s: C.banded(s, 3, _BANDS, False), lambda a, b: C.cross_banded(a, b, 3, _BANDS, False), lambda p, s: V.verify_estimate(p, s, decisions, False)
    )
    return _round(join.run(T.replay(docs, "doc_id", 4)))


@query("s05_interval_join", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def s05(spark, d):
    events = _events(spark, d)
    return T.run_to_table(T.clicks_to_purchases(T.replay(events, "ts", 3), T.replay(events, "ts", 3)), "append")


@query("s06_drift")
def s06(spark, d):
    key, own = "spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
    before = spark.conf.get(key, None)
    spark.conf.set(key, own)
    try:
        return T.run_to_table(T.drift(T.replay(_events(spark, d), "ts", 3)), "update")
    finally:
        spark.conf.unset(key) if before is None else spark.conf.set(key, before)


@query(
    "s07_windowed_pairs",
    """WITH b AS (SELECT user_id, event_type, epoch(ts)::BIGINT // 864000 AS w FROM events), c AS (SELECT w, user_id, event_type, count(*)::DOUBLE AS n FROM b GROUP BY ALL),
    v AS (SELECT w, user_id, event_type, n / sqrt(sum(n * n) OVER (PARTITION BY w, user_id)) AS x FROM c)
    SELECT a.w, a.user_id AS id_a, b.user_id AS id_b, round(sum(a.x * b.x), 6) AS similarity FROM v a JOIN v b ON a.w = b.w AND a.event_type = b.event_type AND a.user_id < b.user_id GROUP BY ALL HAVING round(sum(a.x * b.x), 9) >= 0.97""",
)
def s07(spark, d):
    """Users with alike event mixes in each window of ten days: windows close in the stream, pairs are joined per window."""
    stream = T.replay(_events(spark, d), "ts", 3).withWatermark("ts", "1 hour")
    counts = stream.groupBy(F.floor(F.unix_timestamp("ts") / 864000).alias("w"), "user_id", "event_type").agg(F.count(F.lit(1)).cast("double").alias("n"))
    done = stage(T.run_to_table(counts, "complete"), "windows")
    norms = done.groupBy("w", "user_id").agg(F.sqrt(F.sum(F.col("n") * F.col("n"))).alias("s"))
    vectors = stage(done.join(norms, ["w", "user_id"]).select(F.col("user_id").alias("id"), F.concat_ws(":", "w", "event_type").alias("feature"), (F.col("n") / F.col("s")).alias("weight"), "w"), "vectors")
    a, b = (vectors.select("w", "feature", F.col("id").alias(f"id_{x}"), F.col("weight").alias(f"w{x}")) for x in "ab")
    dots = a.join(b, ["w", "feature"]).where("id_a < id_b").groupBy("w", "id_a", "id_b").agg(F.sum(F.col("wa") * F.col("wb")).alias("similarity"))
    return dots.where(F.round("similarity", 9) >= 0.97).withColumn("similarity", F.round("similarity", 6))

"""Queries over the relational operators, sources, sinks and functions around the joins."""

from __future__ import annotations

import uuid

import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from simweave.functions.sqlfn import posterior_prob, register
from simweave.operators.ranges import asof_join, range_join, skew_report
from simweave.operators.vectorize import at_least, term_counts, tokens
from simweave.oracles import sql as S
from simweave.plans.staging import shared_dir
from simweave.queries import query
from simweave.sources.tables import table
from simweave.workloads import collection


def _path(spark) -> str:
    return f"{shared_dir(spark)}/round-trip-{uuid.uuid4().hex[:10]}"


def _read(spark, d, name, *columns):
    return table(spark, d, name, *columns)


@query("o01_pruned_scan", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity >= 49 AND l_shipdate >= TIMESTAMP '1996-01-01'")
def o01(spark, d):
    return _read(spark, d, "lineitem").where((F.col("l_quantity") >= 49) & (F.col("l_shipdate") >= F.lit("1996-01-01").cast("timestamp"))).select("l_orderkey", "l_quantity")


for _kind in ("json", "csv", "orc"):

    @query(f"o01_round_trip_{_kind}", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
    def o01_trip(spark, d, kind=_kind):
        nation, path = _read(spark, d, "nation"), _path(spark)
        nation.write.format(kind).save(path)
        return spark.read.schema(nation.schema).format(kind).load(path)


@query("o01_round_trip_text", "SELECT n_name AS value FROM nation")
def o01_text(spark, d):
    path = _path(spark)
    _read(spark, d, "nation").select(F.col("n_name").alias("value")).write.text(path)
    return spark.read.text(path)


@query("o02_partitioned_sink", "SELECT c_custkey, c_mktsegment FROM customer WHERE c_mktsegment = 'BUILDING'")
def o02(spark, d):
    path = _path(spark)
    _read(spark, d, "customer", "c_custkey", "c_mktsegment").write.partitionBy("c_mktsegment").parquet(path)
    return spark.read.parquet(path).where("c_mktsegment = 'BUILDING'").select("c_custkey", "c_mktsegment")


@query("o02_partition_overwrite", "SELECT o_orderstatus, CASE WHEN o_orderstatus = 'F' THEN 0 ELSE count(*) END AS n FROM orders GROUP BY o_orderstatus")
def o02_overwrite(spark, d):
    path = _path(spark)
    orders = _read(spark, d, "orders", "o_orderkey", "o_orderstatus")
    orders.write.partitionBy("o_orderstatus").parquet(path)
    replaced = orders.where("o_orderstatus = 'F'").limit(1).select(F.lit(-1).cast("long").alias("o_orderkey"), "o_orderstatus")
    replaced.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("o_orderstatus").parquet(path)
    return spark.read.parquet(path).groupBy("o_orderstatus").agg(F.sum((F.col("o_orderkey") >= 0).cast("long")).alias("n"))


@query(
    "o03_projection",
    """SELECT o_orderkey, CASE WHEN o_totalprice >= 200000 THEN 'high' WHEN o_totalprice BETWEEN 100000 AND 200000 THEN 'mid' ELSE 'low' END AS band,
    o_orderpriority IN ('1-URGENT', '2-HIGH') AS urgent, nullif(o_orderstatus, 'F') AS open_status, coalesce(nullif(o_orderstatus, 'F'), 'done') AS status FROM orders WHERE o_orderpriority LIKE '%-%'""",
)
def o03(spark, d):
    p = F.col("o_totalprice")
    return _read(spark, d, "orders").where(F.col("o_orderpriority").like("%-%")).select(
        "o_orderkey", F.when(p >= 200000, "high").when(p.between(100000, 200000), "mid").otherwise("low").alias("band"), F.col("o_orderpriority").isin("1-URGENT", "2-HIGH").alias("urgent"),
        F.nullif("o_orderstatus", F.lit("F")).alias("open_status"), F.coalesce(F.nullif("o_orderstatus", F.lit("F")), F.lit("done")).alias("status"),
    )


_JOIN = "SELECT c_custkey, n_name FROM customer {how} JOIN (SELECT * FROM nation WHERE n_regionkey <> 1) n ON c_nationkey = n_nationkey AND c_acctbal > 0"
for _how, _hint in (("inner", "broadcast"), ("left", "shuffle_hash"), ("right", "merge"), ("full", "merge")):

    @query(f"o04_{_how}_join", _JOIN.format(how=_how.upper()))
    def o04(spark, d, how=_how, hint=_hint):
        c = _read(spark, d, "customer", "c_custkey", "c_nationkey", "c_acctbal")
        n = _read(spark, d, "nation").where("n_regionkey <> 1").hint(hint)
        return c.join(n, (F.col("c_nationkey") == F.col("n_nationkey")) & (F.col("c_acctbal") > 0), how).select("c_custkey", "n_name")


@query("o05_semi_join", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def o05(spark, d):
    return _read(spark, d, "customer", "c_custkey").join(_read(spark, d, "orders").where("o_totalprice > 300000"), F.col("o_custkey") == F.col("c_custkey"), "left_semi")


@query("o05_anti_join", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def o05_anti(spark, d):
    return _read(spark, d, "customer", "c_custkey").join(_read(spark, d, "orders", "o_custkey", "o_totalprice").where("o_totalprice > 300000"), F.col("o_custkey") == F.col("c_custkey"), "left_anti")


_BANDS = ", ".join(f"({k}, {k * 50000}::DOUBLE, {(k + 1) * 50000}::DOUBLE)" for k in range(12))


@query("o06_range_join", f"SELECT o_orderkey, k FROM orders JOIN (VALUES {_BANDS}) b(k, lo, hi) ON o_totalprice >= lo AND o_totalprice < hi")
def o06(spark, d):
    bands = spark.createDataFrame([(k, k * 50000.0, (k + 1) * 50000.0) for k in range(12)], "k int, lo double, hi double")
    return range_join(_read(spark, d, "orders", "o_orderkey", "o_totalprice"), "o_totalprice", bands, "lo", "hi", 25000.0).select("o_orderkey", "k")


@query("o06_theta_join", "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def o06_theta(spark, d):
    n = _read(spark, d, "nation")
    a, b = n.select(F.col("n_name").alias("a"), F.col("n_nationkey").alias("ka"), "n_regionkey"), n.select(F.col("n_name").alias("b"), F.col("n_nationkey").alias("kb"), "n_regionkey")
    return a.join(b, (a["n_regionkey"] == b["n_regionkey"]) & (F.col("ka") < F.col("kb"))).select("a", "b")


@query(
    "o07_asof_join",
    """SELECT e.event_id, p.event_id AS view_id FROM (SELECT * FROM events WHERE event_type = 'purchase') e ASOF LEFT JOIN
    (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'view' GROUP BY ALL) p ON e.user_id = p.user_id AND e.ts >= p.ts""",
)
def o07(spark, d):
    e = _read(spark, d, "events", "event_id", "ts", "user_id", "event_type")
    views = e.where("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("event_id").alias("view_id"))
    return asof_join(e.where("event_type = 'purchase'").select("user_id", "ts", "event_id"), views, "user_id", "ts", ["view_id"]).select("event_id", "view_id")


@query("o07_interval_join", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def o07_interval(spark, d):
    e = _read(spark, d, "events", "event_id", "ts", "user_id", "event_type")
    a = e.where("event_type = 'click'").select(F.col("event_id").alias("a"), F.col("ts").alias("ta"), "user_id")
    b = e.where("event_type = 'purchase'").select(F.col("event_id").alias("b"), F.col("ts").alias("tb"), "user_id")
    return a.join(b, "user_id").where("tb > ta and tb <= ta + interval 1 hour").select("a", "b")


@query("o08_lateral_topk", "SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2)")
def o08(spark, d):
    """Orders are ranked by a window of their own: an ORDER BY and LIMIT inside the lateral subquery becomes a sort before a shuffle and
    a window without an order (Spark 4.1), so that at size any two orders of a customer came out."""
    best = Window.partitionBy("o_custkey").orderBy(F.col("o_totalprice").desc_nulls_last(), F.col("o_orderkey").asc_nulls_last())
    _read(spark, d, "customer", "c_custkey").createOrReplaceTempView("o08_customers")
    _read(spark, d, "orders").where("o_custkey is not null").withColumn("r", F.row_number().over(best)).createOrReplaceTempView("o08_ranked")
    return spark.sql("SELECT c_custkey, o_orderkey FROM o08_customers, LATERAL (SELECT o_orderkey FROM o08_ranked WHERE o_custkey = c_custkey AND r <= 2)")


@query("o08_scalar_subquery", "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT 1.8 * avg(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
def o08_scalar(spark, d):
    o = _read(spark, d, "orders", "o_orderkey", "o_custkey", "o_totalprice")
    means = o.groupBy("o_custkey").agg((1.8 * F.avg("o_totalprice")).alias("m"))
    return o.join(means, "o_custkey").where("o_totalprice > m").select("o_orderkey")


@query(
    "o09_aggregates",
    """SELECT l_returnflag, count(*) AS n, round(avg(l_quantity), 6) AS mean, min(l_shipdate) AS first_day, max(l_quantity) AS top, round(stddev_samp(l_discount), 6) AS sd, round(var_pop(l_tax), 6) AS vp,
    round(corr(l_quantity, l_extendedprice), 6) AS r, round(covar_samp(l_discount, l_tax) * 1000, 6) AS cv, bool_and(l_quantity > 0) AS pos, arg_max(l_orderkey, l_extendedprice) AS dearest, round(quantile_cont(l_quantity, 0.5), 6) AS med,
    count(*) FILTER (l_discount > 0.05) AS deals FROM lineitem GROUP BY l_returnflag""",
)
def o09(spark, d):
    r6 = lambda c: F.round(c, 6)
    # of several lines at the largest price, the first in key order, which SQL's one-threaded scan meets first
    dearest = F.when(F.col("l_extendedprice").isNotNull() & F.col("l_orderkey").isNotNull(), F.struct("l_extendedprice", -F.col("l_orderkey")))
    return _read(spark, d, "lineitem").groupBy("l_returnflag").agg(
        F.count(F.lit(1)).alias("n"), r6(F.avg("l_quantity")).alias("mean"), F.min("l_shipdate").alias("first_day"), F.max("l_quantity").alias("top"), r6(F.stddev_samp("l_discount")).alias("sd"),
        r6(F.var_pop("l_tax")).alias("vp"), r6(F.corr("l_quantity", "l_extendedprice")).alias("r"), r6(F.covar_samp("l_discount", "l_tax") * 1000).alias("cv"), F.bool_and(F.col("l_quantity") > 0).alias("pos"),
        F.max_by("l_orderkey", dearest).alias("dearest"), r6(F.median("l_quantity")).alias("med"), F.count_if(F.col("l_discount") > 0.05).alias("deals"),
    )


@query("o09_collected", "SELECT n_regionkey, list(n_name ORDER BY n_name) AS names, string_agg(n_name, ',' ORDER BY n_name) AS joined FROM nation GROUP BY n_regionkey")
def o09_lists(spark, d):
    return _read(spark, d, "nation").groupBy("n_regionkey").agg(F.array_sort(F.collect_list("n_name")).alias("names")).withColumn("joined", F.array_join("names", ","))


@query("o10_distinct", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps, count(DISTINCT l_partkey) FILTER (l_returnflag = 'R') AS returned FROM lineitem")
def o10(spark, d):
    return _read(spark, d, "lineitem").agg(
        F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("supps"), F.countDistinct(F.when(F.col("l_returnflag") == "R", F.col("l_partkey"))).alias("returned")
    )


for _name, _sql in (("cube", "CUBE (l_returnflag, l_linestatus)"), ("rollup", "ROLLUP (l_returnflag, l_linestatus)"), ("grouping_sets", "GROUPING SETS ((l_returnflag), (l_linestatus), ())")):

    @query(f"o11_{_name}", f"SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS qty FROM lineitem GROUP BY {_sql}")
    def o11(spark, d, name=_name):
        lines = _read(spark, d, "lineitem", "l_returnflag", "l_linestatus", "l_quantity")
        a, b = F.col("l_returnflag"), F.col("l_linestatus")
        grouped = lines.cube(a, b) if name == "cube" else lines.rollup(a, b) if name == "rollup" else lines.groupingSets([[a], [b], []], a, b)
        return grouped.agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("qty"))


@query("o12_sketches", "SELECT true AS distinct_close, true AS median_close, true AS sample_close")
def o12(spark, d):
    lines = _read(spark, d, "lineitem", "l_partkey", "l_quantity")
    exact = lines.agg(F.countDistinct("l_partkey").alias("n"), F.median("l_quantity").alias("m"), F.count(F.lit(1)).alias("rows"))
    near = lines.agg(F.approx_count_distinct("l_partkey", 0.02).alias("an"), F.percentile_approx("l_quantity", 0.5, 1000).alias("am"))
    drawn = lines.sample(0.2, seed=3).agg(F.count(F.lit(1)).alias("s"))
    return exact.join(F.broadcast(near)).join(F.broadcast(drawn)).select(
        (F.abs(F.col("an") - F.col("n")) <= 0.1 * F.col("n")).alias("distinct_close"), (F.abs(F.col("am") - F.col("m")) <= 1).alias("median_close"), (F.abs(F.col("s") / F.col("rows") - 0.2) < 0.05).alias("sample_close")
    )


@query("o12_hll_union", "SELECT true AS close")
def o12_hll(spark, d):
    parts = _read(spark, d, "lineitem", "l_partkey", "l_suppkey").groupBy(F.pmod("l_suppkey", F.lit(4)).alias("g")).agg(F.hll_sketch_agg("l_partkey", F.lit(14)).alias("s"))
    est = parts.agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("e"))
    exact = _read(spark, d, "lineitem", "l_partkey").agg(F.countDistinct("l_partkey").alias("n"))
    return est.join(F.broadcast(exact)).select((F.abs(F.col("e") - F.col("n")) <= 0.05 * F.col("n")).alias("close"))


@query(
    "o13_window_rank",
    """SELECT s_suppkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(3) OVER w AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd
    FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey)""",
)
def o13_rank(spark, d):
    w = Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")
    return _read(spark, d, "supplier").select(
        "s_suppkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(3).over(w).cast("long").alias("nt"),
        F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"),
    )


@query(
    "o13_window_frames",
    """SELECT event_id, lag(event_id) OVER o AS before, lead(event_id, 2) OVER o AS after, first_value(event_type) OVER o AS first_type, count(*) OVER (o ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS last3,
    round(sum(value) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 500 PRECEDING AND CURRENT ROW), 4) AS near FROM events WINDOW o AS (PARTITION BY user_id ORDER BY event_id)""",
)
def o13_frames(spark, d):
    o = Window.partitionBy("user_id").orderBy("event_id")
    return _read(spark, d, "events").select(
        "event_id", F.lag("event_id").over(o).alias("before"), F.lead("event_id", 2).over(o).alias("after"), F.first("event_type").over(o).alias("first_type"),
        F.count(F.lit(1)).over(o.rowsBetween(-2, 0)).alias("last3"), F.round(F.sum("value").over(o.rangeBetween(-500, 0)), 4).alias("near"),
    )


@query("o14_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
def o14(spark, d):
    return _read(spark, d, "orders", "o_orderkey", "o_totalprice").orderBy(F.col("o_totalprice").desc(), "o_orderkey").offset(5).limit(20)


@query("o14_topk_per_group", "SELECT o_orderstatus, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice DESC, o_orderkey) <= 3")
def o14_group(spark, d):
    w = Window.partitionBy("o_orderstatus").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    return _read(spark, d, "orders", "o_orderstatus", "o_orderkey", "o_totalprice").withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_orderstatus", "o_orderkey")


_A, _B = "SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 0", "SELECT s_nationkey AS k FROM supplier"
for _op, _sql in (("union", "UNION"), ("union_all", "UNION ALL"), ("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):

    @query(f"o15_{_op}", f"({_A}) {_sql} ({_B})")
    def o15(spark, d, op=_op):
        a = _read(spark, d, "customer").where("c_acctbal > 0").select(F.col("c_nationkey").alias("k"))
        b = _read(spark, d, "supplier").select(F.col("s_nationkey").alias("k"))
        return {"union": lambda: a.unionByName(b).distinct(), "union_all": lambda: a.unionByName(b), "intersect": lambda: a.intersect(b), "intersect_all": lambda: a.intersectAll(b), "except": lambda: a.subtract(b), "except_all": lambda: a.exceptAll(b)}[op]()


@query("o16_pivot", "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o FROM orders GROUP BY o_orderpriority")
def o16(spark, d):
    p = _read(spark, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O"]).agg(F.count(F.lit(1)))
    return p.select("o_orderpriority", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))


@query("o16_unpivot", "SELECT l_orderkey, l_linenumber, name, value FROM lineitem UNPIVOT (value FOR name IN (l_discount, l_tax))")
def o16_un(spark, d):
    lines = _read(spark, d, "lineitem", "l_orderkey", "l_linenumber", "l_discount", "l_tax")
    return lines.unpivot(["l_orderkey", "l_linenumber"], ["l_discount", "l_tax"], "name", "value")


@query(
    "o17_strings",
    """SELECT p_partkey, upper(p_name) AS up, substring(p_name, 1, 4) AS head, length(p_name) AS n, reverse(p_brand) AS back, lpad(p_partkey::VARCHAR, 8, '0') AS padded, replace(p_type, ' ', '_') AS t, md5(p_name) AS h,
    split_part(p_brand, '#', 2) AS num, levenshtein(p_brand, 'Brand#11')::INT AS dist, translate(p_brand, 'Bd', 'bD') AS tr, regexp_extract(p_brand, '([0-9]+)', 1) AS rx, trim('  ' || p_type || ' ') AS tm, sha256(p_type) AS sh FROM part""",
)
def o17(spark, d):
    c = F.col
    return _read(spark, d, "part").select(
        "p_partkey", F.upper("p_name").alias("up"), F.substring("p_name", 1, 4).alias("head"), F.length("p_name").cast("long").alias("n"), F.reverse("p_brand").alias("back"), F.lpad(c("p_partkey").cast("string"), 8, "0").alias("padded"),
        F.regexp_replace("p_type", " ", "_").alias("t"), F.md5("p_name").alias("h"), F.split_part(c("p_brand"), F.lit("#"), F.lit(2)).alias("num"), F.levenshtein("p_brand", F.lit("Brand#11")).alias("dist"), F.translate("p_brand", "Bd", "bD").alias("tr"),
        F.regexp_extract("p_brand", "([0-9]+)", 1).alias("rx"), F.trim(F.concat(F.lit("  "), "p_type", F.lit(" "))).alias("tm"), F.sha2("p_type", 256).alias("sh"),
    )


@query("o18_text_filters", f"SELECT f AS feature, count(*) AS df FROM (SELECT DISTINCT doc_id, unnest({S.TOKENS}) AS f FROM documents) WHERE f NOT IN ('the', 'of', 'and', 'de', 'la', 'der', 'die') GROUP BY f HAVING count(*) >= 20")
def o18(spark, d):
    stop = spark.createDataFrame([(w,) for w in ("the", "of", "and", "de", "la", "der", "die")], "feature string")
    words = _read(spark, d, "documents", "doc_id", "text").select("doc_id", F.explode(F.array_distinct(tokens(F.col("text")))).alias("feature"))
    return words.join(F.broadcast(stop), "feature", "left_anti").groupBy("feature").agg(F.count(F.lit(1)).alias("df")).where("df >= 20")


@query("o18_length_cut", f"SELECT doc_id AS id, count(*)::INT AS n FROM (SELECT DISTINCT doc_id, unnest({S.TOKENS}) AS f FROM documents) GROUP BY doc_id HAVING count(*) >= 200")
def o18_cut(spark, d):
    words = _read(spark, d, "documents", "doc_id", "text").select(F.col("doc_id").alias("id"), F.array_distinct(tokens(F.col("text"))).alias("features"))
    return at_least(words, 200).select("id", F.size("features").alias("n"))


@query("o19_tfidf", f"SELECT id, feature, round(weight, 6) AS weight FROM ({S.VECTORS['page_words']})")
def o19(spark, d):
    return collection(spark, d, "page_words").withColumn("weight", F.round("weight", 6))


@query("o19_term_counts", f"SELECT doc_id AS id, f AS feature, count(*) AS tf FROM (SELECT doc_id, unnest({S.TOKENS}) AS f FROM documents) GROUP BY ALL")
def o19_tf(spark, d):
    return term_counts(_read(spark, d, "documents", "doc_id", "text"))


@query(
    "o20_dates",
    """SELECT o_orderkey, date_trunc('month', o_orderdate)::TIMESTAMP AS month, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, dayofyear(o_orderdate)::INT AS doy, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS days,
    strftime(o_orderdate, '%Y/%m') AS ym, epoch(o_orderdate)::BIGINT AS unix, (o_orderdate + INTERVAL 10 DAY)::DATE AS later, make_date(year(o_orderdate)::BIGINT, 1, 1) AS new_year FROM orders""",
)
def o20(spark, d):
    o = F.col("o_orderdate")
    return _read(spark, d, "orders", "o_orderkey", "o_orderdate").select(
        "o_orderkey", F.date_trunc("month", o).cast("timestamp_ntz").alias("month"), F.year(o).alias("y"), F.month(o).alias("m"), F.dayofyear(o).alias("doy"), F.datediff(o, F.lit("1992-01-01").cast("date")).alias("days"),
        F.date_format(o, "yyyy/MM").alias("ym"), F.unix_timestamp(o.cast("timestamp")).alias("unix"), F.date_add(o.cast("date"), 10).alias("later"), F.make_date(F.year(o), F.lit(1), F.lit(1)).alias("new_year"),
    )


@query(
    "o21_math",
    """SELECT k, round(ln(k + 1), 6) AS l, round(exp(k / 100.0::DOUBLE), 6) AS e, round(sqrt(k), 6) AS q, round(pow(k, 1.5), 4) AS p, round(sin(k), 6) AS s, ((k - 50) % 7 + 7) % 7 AS pm, k & 12 AS a, k | 3 AS o, xor(k, 5) AS x,
    bit_count(k)::INT AS bc, (k << 2) AS sh, ceil(k / 7.0::DOUBLE)::BIGINT AS c, floor(k / 7.0::DOUBLE)::BIGINT AS f, greatest(k, 50) AS g, least(k, 50) AS le, CASE WHEN k % 10 = 0 THEN NULL ELSE round(100 / (k % 10)::DOUBLE, 6) END AS td FROM range(0, 100) t(k)""",
)
def o21(spark, d):
    k = F.col("k")
    r = lambda c: F.round(c, 6)
    return spark.range(100).withColumnRenamed("id", "k").select(
        "k", r(F.log(k + 1)).alias("l"), r(F.exp(k / 100.0)).alias("e"), r(F.sqrt("k")).alias("q"), F.round(F.pow(k, F.lit(1.5)), 4).alias("p"), r(F.sin("k")).alias("s"), F.pmod(k - 50, F.lit(7)).alias("pm"),
        k.bitwiseAND(F.lit(12)).alias("a"), k.bitwiseOR(F.lit(3)).alias("o"), k.bitwiseXOR(F.lit(5)).alias("x"), F.bit_count("k").alias("bc"), F.shiftleft("k", 2).alias("sh"), F.ceil(k / 7).alias("c"), F.floor(k / 7).alias("f"),
        F.greatest(k, F.lit(50).cast("long")).alias("g"), F.least(k, F.lit(50).cast("long")).alias("le"), r(F.try_divide(F.lit(100), k % 10)).alias("td"),
    )


@query(
    "o22_arrays",
    """SELECT o_orderkey, s AS parts, len(s)::INT AS n, list_transform(s, lambda x: x % 10) AS digits, list_filter(s, lambda x: x % 2 = 0) AS even, list_sum(s)::BIGINT AS total, s[1:2] AS head, list_contains(s, 7) AS seven
    FROM (SELECT l_orderkey AS o_orderkey, list(DISTINCT l_partkey ORDER BY l_partkey) AS s FROM lineitem GROUP BY l_orderkey)""",
)
def o22(spark, d):
    g = _read(spark, d, "lineitem", "l_orderkey", "l_partkey").groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(F.array_sort(F.collect_set("l_partkey")).alias("parts"))
    return g.select(
        "o_orderkey", "parts", F.size("parts").alias("n"), F.transform("parts", lambda x: x % 10).alias("digits"), F.filter("parts", lambda x: x % 2 == 0).alias("even"),
        F.aggregate("parts", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.slice("parts", 1, 2).alias("head"), F.array_contains("parts", 7).alias("seven"),
    )


@query("o22_array_sets", "SELECT k, list_sort(list_intersect(range(0, k), range(k // 2, k + 5))) AS both_, len(list_distinct(list_concat(range(0, k), range(k // 2, k + 5))))::INT AS either FROM range(1, 30) t(k)")
def o22_sets(spark, d):
    k = F.col("id")
    a, b = F.sequence(F.lit(0).cast("long"), k - 1), F.sequence(F.floor(k / 2), k + 4)
    return spark.range(1, 30).select(k.alias("k"), F.array_sort(F.array_intersect(a, b)).alias("both_"), F.size(F.array_union(a, b)).alias("either"))


@query("o23_maps", "SELECT user_id, map_extract_value(m, 'click') AS clicks, cardinality(m)::INT AS kinds FROM (SELECT user_id, map_from_entries(list((event_type, n))) AS m FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL) GROUP BY user_id)")
def o23(spark, d):
    n = _read(spark, d, "events", "user_id", "event_type").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.try_element_at("m", F.lit("click")).alias("clicks"), F.size("m").alias("kinds"))


@query("o24_json", "SELECT event_id, (props::JSON ->> '$.k')::INT AS k FROM events")
def o24(spark, d):
    return _read(spark, d, "events", "event_id", "props").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("o24_variant", "SELECT event_id, (props::JSON ->> '$.k')::BIGINT AS k FROM events")
def o24_variant(spark, d):
    return _read(spark, d, "events", "event_id", "props").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "long").alias("k"))


@query("o25_urls", r"SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1))::INT AS links FROM pages")
def o25(spark, d):
    return _read(spark, d, "pages").select("page_id", F.expr("try_parse_url(url, 'HOST')").alias("host"), F.size(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("links"))


@query("o26_pandas_udf", f"SELECT n, m, round({S.upper_tail('0.5', 'm', 'n')}, 6) AS p FROM (VALUES (32, 10), (32, 20), (64, 30), (64, 40)) g(n, m)")
def o26(spark, d):
    cells = spark.createDataFrame([(32, 10), (32, 20), (64, 30), (64, 40)], "n int, m int")
    return cells.select("n", "m", F.round(posterior_prob("jaccard", 0.5)("m", "n"), 6).alias("p"))


@query("o26_apply_in_pandas", "SELECT c_nationkey, max(c_acctbal) - min(c_acctbal) AS spread FROM customer GROUP BY c_nationkey")
def o26_group(spark, d):
    import pandas as pd

    def spread(frame: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"c_nationkey": [frame["c_nationkey"].iloc[0]], "spread": [frame["c_acctbal"].max() - frame["c_acctbal"].min()]})

    return _read(spark, d, "customer", "c_nationkey", "c_acctbal").groupBy("c_nationkey").applyInPandas(spread, "c_nationkey int, spread double")


@query("o26_udtf", "SELECT n, unnest(range(0, n)) AS i FROM range(1, 6) t(n)")
def o26_udtf(spark, d):
    @F.udtf(returnType="i bigint")
    class Count:
        def eval(self, n: int):
            for i in range(n):
                yield (i,)

    spark.udtf.register("sim_count", Count)
    spark.range(1, 6).withColumnRenamed("id", "n").createOrReplaceTempView("o26_n")
    return spark.sql("SELECT n, i FROM o26_n, LATERAL sim_count(n)")


@query("o27_sql_functions", f"SELECT id_a, id_b, round(similarity, 6) AS similarity FROM ({S.truth('page_links', 'jaccard', 0.5)})")
def o27(spark, d):
    register(spark)
    collection(spark, d, "page_links").createOrReplaceTempView("o27_sets")
    return spark.sql("""WITH f AS (SELECT id, explode(features) AS x FROM o27_sets), p AS (SELECT DISTINCT a.id AS id_a, b.id AS id_b FROM f a JOIN f b ON a.x = b.x AND a.id < b.id)
        SELECT id_a, id_b, round(sim_jaccard(a.features, b.features), 6) AS similarity FROM p JOIN o27_sets a ON a.id = id_a JOIN o27_sets b ON b.id = id_b
        WHERE round(sim_jaccard(a.features, b.features), 9) >= 0.5""")


@query("o27_recursive", "WITH RECURSIVE r(n, f) AS (SELECT 1, 1::BIGINT UNION ALL SELECT n + 1, f * (n + 1) FROM r WHERE n < 12) SELECT n, f FROM r")
def o27_recursive(spark, d):
    return spark.sql("WITH RECURSIVE r(n, f) AS (SELECT 1, CAST(1 AS BIGINT) UNION ALL SELECT n + 1, f * (n + 1) FROM r WHERE n < 12) SELECT n, f FROM r")


@query("o28_types", "SELECT l_returnflag, sum(l_extendedprice::DECIMAL(12, 2))::DECIMAL(22, 2)::VARCHAR AS total, count(try_cast(l_linestatus AS INT)) AS numbers, min(l_shipdate)::DATE AS first_day, count(*) FILTER (l_linestatus IS DISTINCT FROM 'O') AS other FROM lineitem GROUP BY l_returnflag")
def o28(spark, d):
    return _read(spark, d, "lineitem").groupBy("l_returnflag").agg(
        F.sum(F.col("l_extendedprice").cast("decimal(12,2)")).cast("decimal(22,2)").cast("string").alias("total"), F.count(F.col("l_linestatus").try_cast("int")).alias("numbers"),
        F.min("l_shipdate").cast("date").alias("first_day"), F.count_if(~F.col("l_linestatus").eqNullSafe("O")).alias("other"),
    )


@query(
    "o29_pricing_summary",
    """SELECT l_returnflag, l_linestatus, sum(l_quantity) AS qty, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, round(avg(l_discount), 6) AS disc, count(*) AS n
    FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY ALL""",
)
def o29_pricing(spark, d):
    return _read(spark, d, "lineitem").where(F.col("l_shipdate") <= F.lit("1998-09-02").cast("timestamp")).groupBy("l_returnflag", "l_linestatus").agg(
        F.sum("l_quantity").alias("qty"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"), F.round(F.avg("l_discount"), 6).alias("disc"), F.count(F.lit(1)).alias("n")
    )


@query(
    "o29_nation_revenue",
    """SELECT n_name, year(o_orderdate)::INT AS y, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
    JOIN nation ON c_nationkey = n_nationkey GROUP BY ALL""",
)
def o29_nation(spark, d):
    lines = _read(spark, d, "lineitem", "l_orderkey", "l_extendedprice", "l_discount")
    joined = lines.join(_read(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    joined = joined.join(_read(spark, d, "customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(_read(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return joined.groupBy("n_name", F.year("o_orderdate").alias("y")).agg(F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


@query("o30_exact_duplicates", "SELECT md5(text) AS h, count(*) AS n, min(doc_id) AS first_id FROM documents WHERE text IS NOT NULL GROUP BY md5(text) HAVING count(*) > 1")
def o30(spark, d):
    return _read(spark, d, "documents", "doc_id", "text").where("text is not null").groupBy(F.md5("text").alias("h")).agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("first_id")).where("n > 1")


@query("o30_constraints", "SELECT (SELECT count(*) FROM lineitem WHERE l_quantity <= 0) AS bad_quantity, (SELECT count(*) FROM orders o WHERE NOT EXISTS (SELECT 1 FROM customer WHERE c_custkey = o_custkey)) AS orphans, (SELECT count(*) - count(DISTINCT o_orderkey) FROM orders) AS repeated_keys")
def o30_constraints(spark, d):
    orders = _read(spark, d, "orders", "o_orderkey", "o_custkey")
    a = _read(spark, d, "lineitem", "l_quantity").agg(F.count_if(F.col("l_quantity") <= 0).alias("bad_quantity"))
    b = orders.join(_read(spark, d, "customer", "c_custkey"), F.col("o_custkey") == F.col("c_custkey"), "left_anti").agg(F.count(F.lit(1)).alias("orphans"))
    c = orders.agg((F.count(F.lit(1)) - F.countDistinct("o_orderkey")).alias("repeated_keys"))
    return a.join(F.broadcast(b)).join(F.broadcast(c))


@query("o30_skew_report", "SELECT source, count(*) AS n, round(count(*) / (SELECT count(*) FROM documents)::DOUBLE, 6) AS share FROM documents GROUP BY source ORDER BY n DESC, source LIMIT 10")
def o30_skew(spark, d):
    return skew_report(_read(spark, d, "documents", "source"), "source").withColumn("share", F.round("share", 6))


@query("o02_bucketed_table", "SELECT o_custkey, count(*) AS n, c_name FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY o_custkey, c_name")
def o02_bucketed(spark, d):
    """Two tables bucketed alike by their join key: the join needs no exchange."""
    sides = {}
    for name, key in (("orders", "o_custkey"), ("customer", "c_custkey")):
        sides[name] = f"bucketed_{name}_{uuid.uuid4().hex[:10]}"
        _read(spark, d, name).write.bucketBy(8, key).sortBy(key).option("path", _path(spark)).saveAsTable(sides[name])
    joined = spark.table(sides["orders"]).join(spark.table(sides["customer"]).hint("merge"), F.col("o_custkey") == F.col("c_custkey"))
    return joined.groupBy("o_custkey", "c_name").agg(F.count(F.lit(1)).alias("n"))


@query("o06_nested_loop", "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey < r_regionkey OR n_name < r_name")
def o06_nested(spark, d):
    """No equal key at all: the smaller side, five rows of a table that does not grow, is broadcast to a nested loop."""
    return _read(spark, d, "nation").join(F.broadcast(_read(spark, d, "region")), (F.col("n_regionkey") < F.col("r_regionkey")) | (F.col("n_name") < F.col("r_name"))).select("n_name", "r_name")


@query(
    "o09_shape",
    """WITH m AS (SELECT l_returnflag AS f, avg(l_quantity) AS a, var_pop(l_quantity) AS v FROM lineitem GROUP BY l_returnflag)
    SELECT l_returnflag, round(avg(pow(l_quantity - a, 3)) / pow(any_value(v), 1.5), 6) AS skew, round(avg(pow(l_quantity - a, 4)) / pow(any_value(v), 2) - 3, 6) AS kurt, any_value(l_linestatus ORDER BY l_linestatus) AS first_status
    FROM lineitem JOIN m ON f = l_returnflag GROUP BY l_returnflag""",
)
def o09_shape(spark, d):
    return _read(spark, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.skewness("l_quantity"), 6).alias("skew"), F.round(F.kurtosis("l_quantity"), 6).alias("kurt"), F.min("l_linestatus").alias("first_status"))


@query(
    "o09_mode_listagg",
    """WITH c AS (SELECT n_regionkey, left(n_name, 1) AS x, count(*) AS k FROM nation GROUP BY ALL), b AS (SELECT n_regionkey, min(x) AS common FROM c WHERE k = (SELECT max(k) FROM c i WHERE i.n_regionkey = c.n_regionkey) GROUP BY n_regionkey)
    SELECT n.n_regionkey, string_agg(n_name, '|' ORDER BY n_name) AS names, any_value(common) AS common FROM nation n JOIN b ON b.n_regionkey = n.n_regionkey GROUP BY n.n_regionkey""",
)
def o09_mode(spark, d):
    first = F.left("n_name", F.lit(1))
    return _read(spark, d, "nation").groupBy("n_regionkey").agg(F.expr("listagg(n_name, '|') WITHIN GROUP (ORDER BY n_name)").alias("names"), F.mode(first, True).alias("common"))


@query("o11_grouping_id", "SELECT l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus)::BIGINT AS g, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def o11_id(spark, d):
    return _read(spark, d, "lineitem", "l_returnflag", "l_linestatus").cube("l_returnflag", "l_linestatus").agg(F.grouping_id().cast("long").alias("g"), F.count(F.lit(1)).alias("n"))


@query("o12_kll", "SELECT true AS median_close, true AS tail_close")
def o12_kll(spark, d):
    """Quantile sketches of groups, merged, against exact ranks."""
    keys = _read(spark, d, "lineitem", "l_partkey", "l_suppkey")
    sketch = keys.groupBy("l_suppkey").agg(F.kll_sketch_agg_bigint("l_partkey").alias("s")).agg(F.expr("kll_merge_agg_bigint(s)").alias("s"))
    near = sketch.select(F.kll_sketch_get_quantile_bigint("s", F.lit(0.5)).alias("m"), F.kll_sketch_get_quantile_bigint("s", F.lit(0.9)).alias("q"))
    ranks = keys.join(F.broadcast(near)).agg(F.avg((F.col("l_partkey") <= F.col("m")).cast("int")).alias("a"), F.avg((F.col("l_partkey") <= F.col("q")).cast("int")).alias("b"))
    return ranks.select((F.abs(F.col("a") - 0.5) < 0.05).alias("median_close"), (F.abs(F.col("b") - 0.9) < 0.05).alias("tail_close"))


@query("o12_count_min", "SELECT true AS never_less, true AS close")
def o12_count_min(spark, d):
    """A count-min sketch as a table (row, cell, count): estimates are the smallest cell of a key, and at most a little too high."""
    rows, width = 5, 4096
    cells = lambda key: F.posexplode(F.array(*(F.pmod(F.xxhash64(key, F.lit(k)), F.lit(width)) for k in range(rows)))).alias("row", "cell")
    keys = _read(spark, d, "lineitem", "l_partkey")
    sketch = keys.select(cells(F.col("l_partkey"))).groupBy("row", "cell").agg(F.count(F.lit(1)).alias("n"))
    exact = keys.groupBy("l_partkey").agg(F.count(F.lit(1)).alias("k"))
    near = exact.select("l_partkey", "k", cells(F.col("l_partkey"))).join(F.broadcast(sketch), ["row", "cell"]).groupBy("l_partkey", "k").agg(F.min("n").alias("n"))
    total = keys.agg(F.count(F.lit(1)).alias("total"))
    bound = F.col("n") - F.col("k") <= F.ceil(F.col("total") * (2.72 / width))
    return near.join(F.broadcast(total)).agg(F.min(F.col("n") >= F.col("k")).alias("never_less"), (F.avg(bound.cast("int")) >= 0.99).alias("close"))


@query("o12_bloom", "SELECT true AS none_lost, true AS few_wrong")
def o12_bloom(spark, d):
    """A Bloom filter as a table of set bits (its size is the filter's, whatever the data): every member passes, few others do."""
    bits, hashes = 1 << 18, 6
    places = lambda key: F.explode(F.array_distinct(F.array(*(F.pmod(F.xxhash64(key, F.lit(k)), F.lit(bits)) for k in range(hashes))))).alias("bit")
    orders = _read(spark, d, "orders", "o_orderkey").withColumn("member", F.col("o_orderkey") % 10 == 0)
    made = orders.where("member").select(places(F.col("o_orderkey"))).distinct()
    probe = orders.select("o_orderkey", "member", places(F.col("o_orderkey"))).join(F.broadcast(made.withColumn("hit", F.lit(1))), "bit", "left")
    passed = probe.groupBy("o_orderkey", "member").agg((F.count("hit") == F.count(F.lit(1))).alias("passes"))
    return passed.agg(F.min(~F.col("member") | F.col("passes")).alias("none_lost"), (F.avg((~F.col("member") & F.col("passes")).cast("int")) < 0.05).alias("few_wrong"))


@query("o12_stratified", "SELECT l_returnflag, true AS close FROM (SELECT DISTINCT l_returnflag FROM lineitem)")
def o12_stratified(spark, d):
    """A sample with a share of its own for each stratum."""
    share = {"A": 0.5, "N": 0.1, "R": 0.3}
    lines = _read(spark, d, "lineitem", "l_returnflag")
    drawn = lines.sampleBy("l_returnflag", share, seed=11).groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("s"))
    want = F.create_map(*(F.lit(x) for kv in share.items() for x in kv))
    return lines.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n")).join(drawn, "l_returnflag").select("l_returnflag", (F.abs(F.col("s") / F.col("n") - F.try_element_at(want, F.col("l_returnflag"))) < 0.05).alias("close"))


@query("o17_soundex", "SELECT * FROM (VALUES ('Robert', 'R163'), ('Rupert', 'R163'), ('Tymczak', 'T522'), ('Honeyman', 'H555'), ('Lee', 'L000')) v(name, code)")
def o17_soundex(spark, d):
    names = spark.createDataFrame([(x,) for x in ("Robert", "Rupert", "Tymczak", "Honeyman", "Lee")], "name string")
    return names.select("name", F.soundex("name").alias("code"))


@query("o26_arrow_udf", "SELECT o_orderkey, round(o_totalprice * 2, 6) AS twice FROM orders")
def o26_arrow(spark, d):
    @F.arrow_udf("double")
    def twice(x: pa.Array) -> pa.Array:
        return pc.multiply(x, 2.0)

    return _read(spark, d, "orders", "o_orderkey", "o_totalprice").select("o_orderkey", F.round(twice("o_totalprice"), 6).alias("twice"))


@query("o26_cogroup", "SELECT n_nationkey, (SELECT count(*) FROM customer WHERE c_nationkey = n_nationkey) AS customers, (SELECT count(*) FROM supplier WHERE s_nationkey = n_nationkey) AS suppliers FROM nation WHERE n_nationkey IN (SELECT c_nationkey FROM customer UNION SELECT s_nationkey FROM supplier)")
def o26_cogroup(spark, d):
    def both(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"n_nationkey": [key[0]], "customers": [len(a)], "suppliers": [len(b)]})

    c = _read(spark, d, "customer", "c_nationkey").groupBy("c_nationkey")
    return c.cogroup(_read(spark, d, "supplier", "s_nationkey").groupBy("s_nationkey")).applyInPandas(both, "n_nationkey int, customers long, suppliers long")

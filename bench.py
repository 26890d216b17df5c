"""Headline queries, timed: one JSON line.

Every method runs end to end (signatures, candidates, verification) on the documents of $BENCH_SF_DIR, over several thresholds and
with a time limit; quality measures are printed beside the seconds, and each method's total over that of the posterior estimate.
"""

from __future__ import annotations

import json
import os
import shutil
import sys
import tempfile
import time

from pyspark.sql import SparkSession

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


#: Measure, collection, thresholds, methods, options.
SETTINGS = (
    ("cosine", "docs_tfidf", (0.7, 0.9), ("wp_exact", "bs_exact", "bs_ml", "bs_pe", "bs_px"), {"family": "table"}),
    ("jaccard", "docs_shingles", (0.5,), ("sp_exact", "bs_exact", "bs_ml", "bs_pe", "bs_px"), {"family": "wide"}),
)
#: Seconds after which a run is cancelled; its method's total is then a lower bound.
LIMIT = float(os.environ.get("BENCH_LIMIT", "25"))


def main() -> None:
    shared = tempfile.mkdtemp(prefix="bench-")
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.sql.shuffle.partitions", str(4 * int(CPUS) if CPUS.isdigit() else 32))
        .config("spark.checkpoint.dir", shared).config("spark.driver.memory", "16g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from simweave.operators import metrics as M
    from simweave.operators.exact import exact_similarity
    from simweave.plans.staging import scratch, stage
    from simweave.workloads import collection, run_method, timed

    seconds: dict[str, float] = {}
    quality: dict[str, dict] = {}
    for measure, name, thresholds, methods, options in SETTINGS:
        start = time.perf_counter()
        objects = stage(collection(spark, SF_DIR, name), f"bench-{name}")
        seconds[name] = round(time.perf_counter() - start, 2)
        run_method(stage(collection(spark, "/root/testdata/sf0.001", name), "warm"), "bs_pe", measure, thresholds[-1], **options).count()  # compiles and starts workers
        late = dict.fromkeys(methods, False)
        for t in thresholds:
            truth = None
            for m in methods:
                key = f"{m}_{measure}_{t}"
                with scratch():
                    made: list = []
                    took, over = timed(spark, lambda seed, m=m, t=t, made=made: made.append(stage(run_method(objects, m, measure, t, **options), "bench-out")) or made[0], LIMIT, (1,))
                    seconds[key], late[m] = round(took, 2), late[m] or over
                    print(key, seconds[key], "timed out" if over else "", file=sys.stderr, flush=True)
                    if over:
                        quality[key] = {"timed_out": True}
                        continue
                    rows = made[0].collect()
                out = spark.createDataFrame(rows, made[0].schema)
                truth = truth or (out if m in ("wp_exact", "sp_exact") else None)
                row = {"pairs": len(rows)}
                if truth is not None:
                    row["recall"] = round(M.recall(out, truth).first()["recall"] or 0, 4)
                if m in ("bs_ml", "bs_pe"):
                    e = M.errors(out, exact_similarity(out.select("id_a", "id_b"), objects, measure)).first()
                    row |= {"error_share": round(e["error_share"] or 0, 4), "mean_error": round(e["mean_error"] or 0, 4)}
                quality[key] = row
        total = {m: sum(seconds[f"{m}_{measure}_{t}"] for t in thresholds) for m in methods}
        base = total["bs_pe"]
        quality[f"speedup_{measure}"] = {m: (">=" if late[m] else "") + str(round(total[m] / base, 2)) for m in methods if m != "bs_pe"}
    print(json.dumps({"metric": "total_seconds", "value": round(sum(seconds.values()), 2), "unit": "sec", "queries": seconds, "sf": os.path.basename(SF_DIR.rstrip("/")).removeprefix("sf"), "quality": quality}))
    spark.stop()
    shutil.rmtree(shared, ignore_errors=True)


if __name__ == "__main__":
    main()

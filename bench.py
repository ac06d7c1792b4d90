"""Time the headline queries: one JSON line with seconds by query. Index builds are timed on their own, searches on built indexes."""
from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.shuffle.partitions", CPUS).config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from metricspark import queries as Q
    from metricspark.operators import baselines, search
    from metricspark.shipping import ship
    from metricspark.operators.index import build_index
    from metricspark.operators.sampling import hash_sample
    from metricspark.sources.tables import SETS, written
    from pyspark.sql import functions as F

    ship(spark)
    took: dict[str, float] = {}

    def run(name, make):
        t = time.perf_counter()
        out = make()
        if hasattr(out, "write"):
            out.write.format("noop").mode("overwrite").save()
        took[name] = round(time.perf_counter() - t, 3)
        return out

    for name in ("words", "event_points", "order_points", "embed_l2", "letters_l1", "line_vectors"):
        s = SETS[name]
        objs = run(f"load_{name}", lambda: Q.objects(spark, SF_DIR, name))
        idx = run(f"build_{name}", lambda: build_index(objs, s.metric, s.dim))
        q = written(hash_sample(objs, 100, 1).select(F.col("oid").alias("qid"), F.col("obj").alias("q")), "bench")
        run(f"range_{name}", lambda: search.range_query(idx, q, s.r))
        run(f"knn_{name}", lambda: search.knn_query(idx, q, 8))
        run(f"scan_range_{name}", lambda: baselines.scan_range(objs, s.metric, q, s.r, s.dim))
        if name in ("words", "event_points", "letters_l1"):
            pk = run(f"build_pivot_key_{name}", lambda: baselines.pivot_key_build(objs, s.metric, dim=s.dim))
            run(f"range_pivot_key_{name}", lambda: baselines.pivot_key_range(pk, q, s.r))
            run(f"knn_pivot_key_{name}", lambda: baselines.pivot_key_knn(pk, q, 8))
            lp = run(f"build_layered_pivot_{name}", lambda: baselines.layered_pivot_build(objs, s.metric, dim=s.dim))
            run(f"range_layered_pivot_{name}", lambda: baselines.layered_pivot_range(lp, q, s.r))
    try:
        from metricspark.llm.queries import QUERIES
    except ImportError:
        QUERIES = {}
    for name, f in QUERIES.items():
        run(name, lambda: f(spark, SF_DIR))
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(SF_DIR.rstrip("/")).removeprefix("sf")}))


if __name__ == "__main__":
    main()

"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
METHODS = ("ag", "dm", "lr", "bt", "btd")


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from floorwalk.operators import knn, metrics, route
    from floorwalk.operators import range as ranges
    from floorwalk.plans import border, matrix, rtree
    from floorwalk.sources import venue as V

    seconds: dict[str, float] = {}

    def timed(name, action) -> None:
        seconds[name] = round(metrics.timed(action), 3)

    start = time.time()
    venue = V.build_venue(spark, SF_DIR)
    points, things = V.query_points(venue), V.objects(venue)
    pairs = V.query_pairs(venue)
    seconds["build_venue"] = round(time.time() - start, 3)
    timed("build_dm", lambda: matrix.door_matrix(venue))
    timed("build_lr", lambda: rtree.build_rtree(venue).levels[0])
    timed("build_bt", lambda: border.build_border_tree(venue).deep_out)
    for method in METHODS:
        timed(f"rq_{method}", lambda m=method: ranges.range_query(m, venue, points, things, 120_000))
        timed(f"knn_{method}", lambda m=method: knn.knn_query(m, venue, points, things, 10))
        timed(f"spdq_{method}", lambda m=method: route.route_query(m, venue, pairs, False))
    # Throughput: thousands of queries in one plan.
    many = V.order_points(venue).where(F.col("qid") < 1000)
    wide = V.query_pairs(venue, 1000)
    for method in ("dm", "btd"):
        timed(f"rq1000_{method}", lambda m=method: ranges.range_query(m, venue, many, things.where("object_id < 1500"), 60_000))
        timed(f"sdq1000_{method}", lambda m=method: route.distance_query(m, venue, wide))
    n_pairs = wide.count()
    sizes = {r["method"]: int(r["b"]) for r in metrics.model_size(venue).groupBy("method").agg(F.sum("n_bytes").alias("b")).collect()}
    best = route.distance_query("dm", venue, pairs).where("dist_mm is not null")
    sides = route.sides(venue, pairs)
    nvd = {m: int(route.visited_doors(m, venue, *sides, best).agg(F.sum("nvd")).first()[0]) for m in METHODS}
    shape = {
        "size_ag_lr_bt_btd_dm": sizes["access_graph"] < sizes["layered_rtree"] < sizes["border_tree"] < sizes["border_tree_deep"] < sizes["door_matrix"],
        "nvd_dm_least": nvd["dm"] == min(nvd.values()), "nvd_ag_equals_lr": nvd["ag"] == nvd["lr"], "nvd_btd_below_bt": nvd["btd"] <= nvd["bt"],
    }
    # Wall times are reported, not asserted: a query's time is mostly the latency of its jobs.
    soft = {f"{q}_dm_below_{m}": seconds[f"{q}_dm"] <= seconds[f"{q}_{m}"] for q in ("rq", "knn", "spdq") for m in ("ag", "lr", "bt", "btd")}
    memory = {m: {k: int(v) for k, v in metrics.query_memory(m, venue, points, 60_000).first().asDict().items() if k != "method"} for m in METHODS}
    print(json.dumps({
        "metric": "indoor queries, total seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(SF_DIR.rstrip("/")).removeprefix("sf"),
        "per_second": {m: {"rq": round(1000 / seconds[f"rq1000_{m}"], 1), "sdq": round(n_pairs / seconds[f"sdq1000_{m}"], 1)} for m in ("dm", "btd")},
        "model_bytes": sizes, "nvd": nvd, "shape": shape, "memory_bytes": memory, "faster": soft,
    }))


if __name__ == "__main__":
    main()

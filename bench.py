"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", str(cpus)).config("spark.driver.memory", "12g")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from pathweave import engine, workloads
    from pathweave.sources import catalog

    g = catalog.hop(spark, sf, "follows").cached()
    t = catalog.hop(spark, sf).cached()
    mid = g.median_node()
    limit = 100_000
    runs = {
        "ep_k4": lambda: engine.endpoints(g, "follows{1,4}", mid).df,
        "any_shortest_k12": lambda: engine.paths(g, "ANY SHORTEST WALK", "follows{1,12}", mid, limit=limit).df,
        "all_shortest_k12": lambda: engine.paths(g, "ALL SHORTEST WALK", "follows{1,12}", mid, limit=limit).df,
        "all_shortest_exact_3": lambda: engine.paths(g, "ALL SHORTEST WALK", "follows{3}", mid, limit=limit).df,
        "trail_k3": lambda: engine.paths(g, "TRAIL", "follows{1,3}", mid, limit=limit).df,
        "trail_k12_limit": lambda: engine.paths(g, "TRAIL", "follows{1,12}", mid, limit=limit).df,
        "all_shortest_purchase": lambda: engine.paths(t, "ALL SHORTEST WALK", "purchase*", mid).df,
        "all_shortest_purchase_rounds": lambda: engine.paths(t, "ALL SHORTEST WALK", "purchase*", mid, strategy="rounds").df,
        **{f"shortest_{k}_walk": (lambda k=k: engine.paths(t, f"SHORTEST {k} WALK", "purchase{1,3}", mid, limit=limit).df) for k in (1, 100, 1000)},
        **{f"shortest_{k}_trail": (lambda k=k: engine.paths(t, f"SHORTEST {k} TRAIL", "purchase{1,3}", mid, limit=limit).df) for k in (1, 100, 1000)},
        **{f"groups_{k}_walk": (lambda k=k: engine.paths(t, f"SHORTEST {k} GROUPS WALK", "purchase{1,3}", mid, limit=limit).df) for k in (1, 2, 3)},
        "diamond_40_all_shortest": lambda: workloads.diamond(spark, 40, "ALL SHORTEST WALK").df,
        "diamond_1000_any_shortest": lambda: workloads.diamond(spark, 1000, "ANY SHORTEST WALK").df,
        "diamond_1000_all_shortest_1k": lambda: workloads.diamond(spark, 1000, "ALL SHORTEST WALK", limit=1000).df,
        "diamond_40_any_trail_dfs": lambda: workloads.diamond(spark, 40, "ANY TRAIL", order="dfs").df,
        "diamond_40_trail_dfs": lambda: workloads.diamond(spark, 40, "TRAIL").df,
    }
    took = {}
    next(iter(runs.values()))().count()  # the session warms up
    for name, run in runs.items():
        began = time.perf_counter()
        run().count()
        took[name] = round(time.perf_counter() - began, 3)
    print(json.dumps({"metric": "headline path queries, total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": sf}))
    spark.stop()


if __name__ == "__main__":
    main()

"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))
SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def session():
    from pyspark.sql import SparkSession

    return (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", str(2 * int(CPUS))).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )


def main() -> None:
    spark = session()
    spark.sparkContext.setLogLevel("ERROR")
    from crowding.plans import catalog, measures, solver
    from crowding.core.solve import WORK
    from crowding.plans.workloads import GRAPHS

    took: dict[str, float] = {}
    quality = []
    spark.range(10).count()
    for name in ("edges_parts", "blocks_parts", "min_lift_cost_parts", "min_lift_cost_cust_supp", "edge_degree_pairs", "degree_assortativity", "sorted_demands", "eg_theta", "triangles"):
        t = time.time()
        catalog.queries()[name](spark, SF).write.format("noop").mode("overwrite").save()
        took[name] = round(time.time() - t, 3)
    for name, ks in (("parts", (2, 5, 10, 20, 50, 100)), ("cust_supp", (2, 5, 10, 20)), ("part_supp", (2, 5, 10, 20)), ("doc_lines", (2, 5, 10, 100))):
        t = time.time()
        b = solver.solve_graphs(spark, {name: GRAPHS[name](spark, SF)}, ks)
        rows = measures.table_lines(b).orderBy("k").collect()
        took[f"solve_{name}"] = round(time.time() - t, 3)
        quality += [{c: r[c] for c in ("graph", "k", "ch", "oh", "opt", "dp_lo", "dp_hi", "t_ch", "t_oh", "t_dp")} for r in rows]
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": SF.rsplit("sf", 1)[-1], "work": WORK, "table": quality}))
    spark.stop()


if __name__ == "__main__":
    main()

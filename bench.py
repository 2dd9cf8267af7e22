"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

import json
import os
import time

from pyspark.sql import DataFrame, SparkSession

from depmine.plans import planner
from depmine.sources.views import relation

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def workloads():
    """The published workloads on whole given tables: both plans of the lattice, of pairs and of the hybrid, keys, orders and constraints."""
    run, of = planner.discover, lambda s, name: relation(s, SF_DIR, name)
    return {
        "lattice_rescan_resident_lineitem": lambda s: run(of(s, "lineitem"), memory="resident", k=32),
        "lattice_rescan_spill_orders": lambda s: run(of(s, "orders")),
        "lattice_reuse_resident_customer": lambda s: run(of(s, "customer"), plan="reuse", memory="resident"),
        "lattice_reuse_resident_orders": lambda s: run(of(s, "orders"), plan="reuse", memory="resident"),
        "pair_rescan_resident_part": lambda s: run(of(s, "part"), method="pair", memory="resident"),
        "pair_reuse_resident_part": lambda s: run(of(s, "part"), method="pair", plan="reuse", memory="resident"),
        "hybrid_rescan_resident_orders": lambda s: run(of(s, "orders"), method="hybrid", memory="resident", k=32),
        "hybrid_rescan_resident_lineitem": lambda s: run(of(s, "lineitem"), method="hybrid", memory="resident", k=32),
        "hybrid_rescan_spill_lineitem_lhs2": lambda s: run(of(s, "lineitem"), method="hybrid", max_lhs=2),
        "ucc_lattice_lineitem": lambda s: run(of(s, "lineitem"), "ucc", memory="resident", k=32),
        "od_lattice_resident_orders": lambda s: planner.order_dependencies(of(s, "orders"), of(s, "orders").columns, memory="resident", k=32, lists=False),
        "dc_pair_rescan_resident_supplier": lambda s: planner.denial_constraints(of(s, "supplier"), of(s, "supplier").columns),
        "dc_hybrid_rescan_resident_customer": lambda s: planner.denial_constraints(of(s, "customer"), of(s, "customer").columns, method="hybrid"),
    }


def main():
    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", "16").config("spark.driver.memory", "16g").config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    seconds, found = {}, {}
    for name, run in workloads().items():
        at = time.time()
        done = run(spark)
        n = done.count() if isinstance(done, DataFrame) else len(done.found) if done.status == "done" else done.status
        seconds[name], found[name] = round(time.time() - at, 3), n
    print(json.dumps({"metric": "discovery_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "found": found, "sf": SF_DIR.rstrip("/").rpartition("sf")[2]}))


if __name__ == "__main__":
    main()

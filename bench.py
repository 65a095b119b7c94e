"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
#: Python workers import the package too, wherever this is started from.
os.environ["PYTHONPATH"] = os.pathsep.join([os.path.dirname(os.path.abspath(__file__)), *filter(None, [os.environ.get("PYTHONPATH")])])


def main() -> None:
    from pyspark.sql import SparkSession

    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", str(2 * int(CPUS))).config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "16g")).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    from cellscrub.operators import fd, sampling
    from cellscrub.plans.effectiveness import CORRECTORS, DETECTORS, Sample, classified_cells
    from cellscrub.queries import QUERIES, RULES
    from cellscrub.session import materialize
    from cellscrub.sources.tables import entities

    seconds: dict[str, float] = {}

    def timed(name, run) -> None:
        began = time.perf_counter()
        out = run()
        if hasattr(out, "write"):
            out.write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - began, 3)

    QUERIES["category_shares"](spark, "/root/testdata/sf0.001").collect()  # starts the workers
    for name in ("addr_dirty", "category_shares", "category_by_slice", "distinct_values", "distinct_records", "detect_l1", "repair_r1", "cooccurrence_counts", "quads_roundtrip", "join_asof_events"):
        timed(name, lambda n=name: QUERIES[n](spark, SF_DIR))
    timed("fd_discover", lambda: fd.discover(entities(spark, SF_DIR), max_lhs=3))
    cells = materialize(classified_cells(spark, SF_DIR), "bench")
    ids = sampling.fixed(cells.select("_id").distinct(), 10_000).select("_id")
    sample = Sample(cells.join(ids, "_id", "left_semi"), RULES)  # the size of the published effectiveness runs
    for name in ("factor", "fd_majority", "rule_workflow", "signature_detector", "record_prompt"):
        timed(f"detect_{name}", lambda n=name: DETECTORS[n](sample))
    for name in ("corrector_ensemble", "record_prompt"):
        timed(f"correct_{name}", lambda n=name: CORRECTORS[n](sample))
    print(json.dumps({"metric": "total_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": SF_DIR.rsplit("sf", 1)[-1], "rows": sample.dirty.count()}))


if __name__ == "__main__":
    main()

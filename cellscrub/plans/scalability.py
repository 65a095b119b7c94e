"""Size ladders: seconds, peak memory and status of each system, with a budget for each run."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from cellscrub.operators import measure, sampling
from cellscrub.plans.effectiveness import CORRECTORS, DETECTORS, Sample, classified_cells
from cellscrub.session import materialize

SCHEMA = "system string, task string, n_rows long, seconds double, peak_mb double, status string"


def size_ladder(spark: SparkSession, sf_dir: str, sizes: tuple[int, ...] = (1500, 15_000, 150_000), carrier: str = "orders", budget_s: float = 600.0, fds=None, detectors: tuple[str, ...] = ("factor", "fd_majority", "rule_workflow", "signature_detector", "column_imputer", "record_prompt"), correctors: tuple[str, ...] = ("corrector_ensemble", "factor", "column_imputer", "record_prompt")) -> DataFrame:
    """One row per system, task and size. Driver-side work of a system counts too."""
    import time

    cells = materialize(classified_cells(spark, sf_dir, carrier), "ladder")
    rows = []
    there = cells.select("_id").distinct().count()
    for size in sizes:
        if size > there:  # the table has no such rung
            continue
        ids = sampling.fixed(cells.select("_id").distinct(), size).select("_id")
        sample = Sample(cells.join(ids, "_id", "left_semi"), fds)
        n = sample.dirty.count()
        for task, table, names in (("detect", DETECTORS, detectors), ("correct", CORRECTORS, correctors)):
            for name in names:
                began = time.monotonic()
                got = measure.timed(table[name](sample), budget_s)
                took = round(time.monotonic() - began, 3)
                rows.append((name, task, n, took, got["peak_mb"], "over_budget" if took > budget_s else got["status"]))
    return spark.createDataFrame(rows, SCHEMA)

"""Detection and correction scores over cells, overall and by category; runtime, memory and status of a run."""

from __future__ import annotations

import math
import threading
import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KEY = ("_id", "attr")


def _ratio(a: Column, b: Column) -> Column:
    return F.coalesce(F.try_divide(a, b), F.lit(0.0))


def _scores(counts: DataFrame) -> DataFrame:
    """precision, recall and f1 from tp, n_out and n_true; a zero denominator gives 0 and is flagged."""
    p, r = _ratio(F.col("tp"), F.col("n_out")), _ratio(F.col("tp"), F.col("n_true"))
    out = counts.withColumn("precision", F.round(p, 6)).withColumn("recall", F.round(r, 6)).withColumn("f1", F.round(_ratio(2 * p * r, p + r), 6))
    return out.withColumn("undefined", (F.col("n_out") == 0) | (F.col("n_true") == 0))


def _joined(cells: DataFrame, out: DataFrame, mark: str) -> DataFrame:
    """cells with the output's columns and a mark; one output a cell at most."""
    once = out.dropDuplicates(list(KEY)).withColumn(mark, F.lit(True))
    return cells.join(once, list(KEY), "left").withColumn(mark, F.coalesce(F.col(mark), F.lit(False)))


def detection(cells: DataFrame, flags: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Flagged cells against erroneous ones (category other than clean)."""
    bad = F.col("category") != "clean"
    both = _joined(cells, flags.select(*KEY), "flagged")
    agg = (F.count_if("flagged").alias("n_out"), F.count_if(bad).alias("n_true"), F.count_if(bad & F.col("flagged")).alias("tp"))
    return _scores(both.groupBy(*by).agg(*agg) if by else both.agg(*agg))


def correction(cells: DataFrame, repairs: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Proposed repairs of the true error cells against the clean values."""
    wrong = cells.filter("category <> 'clean'")
    both = _joined(wrong, repairs.select(*KEY, "repair"), "proposed")
    proposed = F.col("proposed") & F.col("repair").isNotNull() & ~F.col("repair").eqNullSafe(F.col("dirty"))
    agg = (F.count_if(proposed).alias("n_out"), F.count("*").alias("n_true"), F.count_if(proposed & (F.col("repair") == F.col("clean"))).alias("tp"))
    return _scores(both.groupBy(*by).agg(*agg) if by else both.agg(*agg))


def recall_by_category(cells: DataFrame, flags: DataFrame) -> DataFrame:
    """Detection recall of each error category; false alarms have none, so there is no precision."""
    return detection(cells.filter("category <> 'clean'"), flags, ("category",)).select("category", "n_true", "tp", "recall")


def f1_by_category(cells: DataFrame, repairs: DataFrame) -> DataFrame:
    return correction(cells, repairs, ("category",)).select("category", "n_out", "n_true", "tp", "f1")


def flags_from_repairs(dirty_cells: DataFrame, repairs: DataFrame) -> DataFrame:
    """For systems that only repair: a changed cell is a detected one."""
    both = dirty_cells.join(repairs.select(*KEY, "repair"), list(KEY))
    return both.filter(~F.col("repair").eqNullSafe(F.col("dirty"))).select(*KEY)


def mean_of_runs(metrics: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """Mean and spread of the scores over the seeds."""
    return metrics.groupBy(*keys).agg(F.count("*").alias("runs"), *[F.round(f(c), 6).alias(f"{n}_{c}") for c in ("precision", "recall", "f1") for n, f in (("mean", F.avg), ("std", F.stddev_pop))])


def timed(df: DataFrame, budget_s: float | None = None) -> dict:
    """seconds, peak_mb (of the heap: the driver's during this run, or an executor's so far) and status of computing df fully;
    over budget the job group is cancelled."""
    spark = df.sparkSession
    group = f"timed-{time.monotonic_ns()}"
    spark.sparkContext.setJobGroup(group, group, True)
    pools = _heap_pools(spark)
    for pool in pools:
        pool.resetPeakUsage()
    status, began = "ok", time.monotonic()
    timer = threading.Timer(budget_s, lambda: spark.sparkContext.cancelJobGroup(group)) if budget_s else None
    try:
        if timer:
            timer.start()
        df.write.format("noop").mode("overwrite").save()
    except Exception as e:  # the run's own failure is its result
        text = str(e)
        status = "over_budget" if "cancel" in text.lower() else "out_of_memory" if "OutOfMemory" in text else "failed"
    finally:
        if timer:
            timer.cancel()
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    jvm = sum(pool.getPeakUsage().getUsed() for pool in pools) / 1e6
    return {"seconds": round(time.monotonic() - began, 3), "peak_mb": round(max(jvm, _executors_peak(spark)), 1), "status": status}


def _heap_pools(spark) -> list:
    beans = spark._jvm.java.lang.management.ManagementFactory.getMemoryPoolMXBeans()
    return [b for b in beans if b.getType().toString() == "Heap memory"]


def _executors_peak(spark) -> float:
    """Highest heap use that any executor of a cluster has reported so far, in MB; 0 where the driver does the work."""
    found = spark.sparkContext._jsc.sc().statusStore().executorList(True)
    peaks = [found.apply(i).peakMemoryMetrics() for i in range(found.size()) if found.apply(i).id() != "driver"]
    return max((p.get().getMetricValue("JVMHeapMemory") / 1e6 for p in peaks if p.isDefined()), default=0.0)


def growth_exponent(sizes: list[float], values: list[float]) -> list[float]:
    """Log-ratio between neighbours: 1 is linear."""
    return [round(math.log(max(b, 1e-9) / max(a, 1e-9)) / math.log(n / m), 3) for m, n, a, b in zip(sizes, sizes[1:], values, values[1:])]

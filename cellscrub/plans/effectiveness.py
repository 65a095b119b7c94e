"""The evaluation protocol: corrupt, sample, set the rate, run the systems, score all in one shape."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellscrub.operators import fd as D
from cellscrub.operators import inject, measure, sampling, taxonomy
from cellscrub.schema import ATTRS
from cellscrub.session import materialize
from cellscrub.sources.tables import addr_clean
from cellscrub.systems import column_imputer, corrector_ensemble, factor, fd_majority, record_prompt, rule_workflow, signature_detector
from cellscrub.systems.base import Labels, flag_all, flag_missing, flag_nothing, records, repair_by_mode

SAMPLE = 10_000


class Sample:
    """A written sample: cells with categories, its dirty records, and what the systems may ask for."""

    def __init__(self, cells: DataFrame, fds: list[D.Dependency] | None = None, max_lhs: int = 2):
        self.cells = materialize(cells.select("_id", "attr", "dirty", "clean", "category"), "sample-cells")
        self.pairs = materialize(inject.wide(self.cells), "sample-pairs")
        self.dirty = materialize(records(self.pairs), "sample-dirty")
        clean = self.pairs.select(*[F.col(f"c_{a}").alias(a) for a in ATTRS])
        self.fds = D.discover(clean, max_lhs=max_lhs) if fds is None else fds

    @property
    def errors(self) -> DataFrame:
        return self.cells.filter("category <> 'clean'").select("_id", "attr")

    def labels(self, budget: int = 20) -> Labels:
        return Labels(self.cells, budget)


DETECTORS: dict[str, Callable[[Sample], DataFrame]] = {
    "signature_detector": lambda s: signature_detector.detect(s.dirty, s.fds, s.labels()),
    "factor": lambda s: factor.detect(s.dirty, s.fds),
    "fd_majority": lambda s: fd_majority.detect(s.dirty, s.fds),
    "rule_workflow": lambda s: rule_workflow.detect(s.dirty, s.fds),
    "column_imputer": lambda s: column_imputer.detect(s.dirty, s.labels()),
    "record_prompt": lambda s: record_prompt.detect(s.dirty),
    "flag_all": lambda s: flag_all(s.cells),
    "flag_nothing": lambda s: flag_nothing(s.cells),
    "flag_missing": lambda s: flag_missing(s.cells),
}

CORRECTORS: dict[str, Callable[[Sample], DataFrame]] = {
    "corrector_ensemble": lambda s: corrector_ensemble.correct(s.dirty, s.errors, s.labels()),
    "factor": lambda s: factor.correct(s.dirty, s.errors, s.fds),
    "fd_majority": lambda s: fd_majority.correct(s.dirty, s.fds),
    "rule_workflow": lambda s: rule_workflow.correct(s.dirty, s.fds),
    "column_imputer": lambda s: column_imputer.correct(s.dirty, s.errors, s.labels()),
    "record_prompt": lambda s: record_prompt.correct(s.dirty, s.errors),
    "column_mode": lambda s: repair_by_mode(s.cells),
}


def classified_cells(spark: SparkSession, sf_dir: str, carrier: str = "orders", profile: str = "named", seed: int = 7, scale: float = 1.0, keep: tuple[str, ...] = ("_id", "graph_iri", "poi"), where: Column | None = None) -> DataFrame:
    """where: a condition on the clean table; its rows are written first, so that the joins are not planned together with
    the classifier's rules."""
    clean = addr_clean(spark, sf_dir, carrier)
    clean = clean if where is None else materialize(clean.filter(where), "clean-slice")
    pairs = inject.corrupt(clean, profile, seed, scale)
    return taxonomy.classify(inject.cells(pairs.withColumn("nation", F.col("c_country")), keep=(*keep, "nation")))


def make_sample(cells: DataFrame, rows: int = SAMPLE, rate: float | None = None, seed: int = 1, mode: str = "global", **options) -> Sample:
    """Dirty duplicates removed, rows drawn in hash order, errors restored to the rate; None keeps the original one."""
    pairs = inject.wide(cells)
    ids = sampling.fixed(sampling.dedup_dirty(pairs), rows, seed).select("_id")
    chosen = materialize(cells.join(ids, "_id", "left_semi"), "sample")
    return Sample(chosen if rate is None else sampling.restore(chosen, rate, seed, mode), **options)


def scores(sample: Sample, by: tuple[str, ...] = (), detectors: tuple[str, ...] = tuple(DETECTORS), correctors: tuple[str, ...] = tuple(CORRECTORS)) -> DataFrame:
    """system, task, by, counts and scores of the named systems on one sample."""
    parts = []
    for task, table, names, score in (("detect", DETECTORS, detectors, measure.detection), ("correct", CORRECTORS, correctors, measure.correction)):
        for name in names:
            got = score(sample.cells, materialize(table[name](sample), f"{task}-{name}"), by)
            parts.append(got.withColumn("system", F.lit(name)).withColumn("task", F.lit(task)))
    return reduce(DataFrame.unionByName, parts)


def rate_curve(cells: DataFrame, rates: tuple[float | None, ...] = (0.05, 0.1, 0.2, None), rows: int = SAMPLE, seeds: tuple[int, ...] = (1,), fds: list[D.Dependency] | None = None, max_lhs: int = 1, **systems) -> DataFrame:
    """Scores by error rate (0 stands for the original one), averaged over the seeds, and each system's mean F1 over the
    rates. Without given dependencies they are mined on the clean side of each seed's rows."""
    parts = []
    for seed in seeds:
        known = fds
        for rate in rates:
            sample = make_sample(cells, rows, rate, seed, fds=known, max_lhs=max_lhs)
            known = sample.fds
            got = scores(sample, **systems)
            parts.append(got.withColumn("rate", F.lit(rate or 0.0)).withColumn("seed", F.lit(seed)))
    curve = measure.mean_of_runs(materialize(reduce(DataFrame.unionByName, parts), "curve"), ("system", "task", "rate"))
    return curve.withColumn("f1_over_rates", F.round(F.avg("mean_f1").over(Window.partitionBy("system", "task")), 6))


def end_to_end(sample: Sample, detector: str, corrector: str) -> DataFrame:
    """A corrector that only gets its detector's cells: repairs outside the errors count as wrong proposals."""
    flags = materialize(DETECTORS[detector](sample), "flags")
    repairs = CORRECTORS[corrector](sample).join(flags, ["_id", "attr"], "left_semi")
    return measure.correction(sample.cells, repairs).withColumn("system", F.lit(f"{detector}+{corrector}"))

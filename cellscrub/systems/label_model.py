"""Learned detection on real labels: a logistic model over numeric signs of a text, all of them column expressions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: At most so many labelled rows, by hash, fit the model.
FIT_BOUND = 50_000
HELD_OUT_OF = 5


def signs(text: Column) -> dict[str, Column]:
    """Shares and logarithms that tell prose from junk; null texts are empty."""
    t = F.coalesce(text, F.lit(""))
    n = F.greatest(F.length(t), F.lit(1))
    share = lambda pattern: (F.length(F.regexp_replace(t, pattern, "")) / n).cast("double")
    words = F.filter(F.split(t, r"\\s+"), lambda w: w != "")
    return {
        "size": F.log1p(F.length(t)),
        "letters": share(r"[^\\p{L}]"),
        "digits": share(r"[^0-9]"),
        "marks": share(r"[^#*$%&|<>]"),
        "capitals": share(r"[^\\p{Lu}]"),
        "lines": F.log1p(F.size(F.split(t, "\\n"))),
        "distinct": (F.size(F.array_distinct(words)) / F.greatest(F.size(words), F.lit(1))).cast("double"),
    }


def held_out_scores(docs: DataFrame, labels: DataFrame, target: str = "quality") -> DataFrame:
    """n_fit, n_held_out, positives, accuracy, and that of always answering the commoner label."""
    found = signs(F.col("text"))
    rows = docs.select("doc_id", *[c.alias(k) for k, c in found.items()]).join(labels.filter(F.col(target).isNotNull()).select("doc_id", F.col(target).cast("int").alias("y")), "doc_id")
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % HELD_OUT_OF == 0
    fit = rows.filter(~held).orderBy(F.xxhash64("doc_id"), "doc_id").limit(FIT_BOUND).select(*found, "y").toArrow()
    x = np.column_stack([fit.column(k).to_numpy() for k in found]) if fit.num_rows else np.zeros((0, len(found)))
    y = fit.column("y").to_numpy().astype(float) if fit.num_rows else np.zeros(0)
    mean, spread = (x.mean(0), x.std(0) + 1e-9) if len(x) else (np.zeros(len(found)), np.ones(len(found)))
    z = np.hstack([np.ones((len(x), 1)), (x - mean) / spread])
    w = np.zeros(z.shape[1])
    for _ in range(25):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        w += np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + np.eye(len(w)), z.T @ (y - p) - w)
    score = F.lit(float(w[0])) + sum(((F.col(k) - float(m)) / float(s) * float(v) for k, m, s, v in zip(found, mean, spread, w[1:])), F.lit(0.0))
    judged = rows.filter(held).select("y", (score >= 0).cast("int").alias("said"))
    right = F.avg((F.col("y") == F.col("said")).cast("int"))
    return judged.agg(F.lit(len(x)).alias("n_fit"), F.count("*").alias("n_held_out"), F.sum("y").alias("positives"), F.round(right, 6).alias("accuracy"), F.round(F.greatest(F.avg("y"), 1 - F.avg("y")), 6).alias("commoner"))

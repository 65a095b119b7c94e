"""column_imputer: each column predicted from the other columns' character n-grams by a multinomial logistic model.

Sixteen labelled tuples train, four calibrate the temperature. The labels are a bounded number of tuples, so the models are
fitted on the driver; n-grams that no labelled tuple has would get weight zero and are left out. Scoring is map-only: the
models are linear and every n-gram belongs to one column, so each distinct value of a batch is weighed once for all models.
It can only answer with values that the labelled tuples hold.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellscrub.schema import ATTRS
from cellscrub.systems.base import Labels, present

THRESHOLD = 0.5
TRAIN = 16
PENALTY = 0.02
STEPS = 300
TEMPERATURES = (0.25, 0.5, 1.0, 2.0, 4.0)


def grams(value: str | None) -> Counter[str]:
    """Counts of the value's 1- to 3-grams, letters lowered; none for null."""
    v = (value or "").lower()
    return Counter(v[i : i + n] for n in (1, 2, 3) for i in range(len(v) - n + 1))


@dataclass
class Model:
    """values: the answers, at most one a labelled tuple; weights[column][gram]: a score for each answer."""

    values: list[str]
    weights: dict[str, dict[str, np.ndarray]]
    bias: np.ndarray
    temperature: float = 1.0

    def weigh(self, column: str, value: str | None) -> np.ndarray:
        """What a column's value adds to the answers' scores."""
        known = self.weights.get(column, {})
        return sum((n * known[g] for g, n in grams(value).items() if g in known), np.zeros(len(self.values)))


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


def fit(truth: list[dict], attr: str) -> Model:
    """The column's model, calibrated on the tuples held back; without two different answers, one that gives the only one."""
    tuples: dict[str, dict] = {}
    for t in truth:
        row = tuples.setdefault(t["_id"], {})
        row[t["attr"]] = t["clean"] if t["attr"] == attr else t["dirty"]
    rows = [tuples[i] for i in sorted(tuples) if tuples[i].get(attr)]
    train = rows[:TRAIN]
    values = sorted({r[attr] for r in train})
    if len(values) < 2:
        return Model(values, {}, np.zeros(len(values)))
    counts = [{(a, g): n for a in ATTRS if a != attr for g, n in grams(r.get(a)).items()} for r in train]
    names = sorted({k for c in counts for k in c})
    x = np.array([[c.get(k, 0) for k in names] for c in counts], dtype=float)
    spread = x.std(0, ddof=1)
    scale = np.divide(1.0, spread, out=np.zeros_like(spread), where=spread > 0)
    mean = x.mean(0)
    xs = (x - mean) * scale
    y = np.eye(len(values))[[values.index(r[attr]) for r in train]]
    w, bias = np.zeros((len(names), len(values))), np.log(y.mean(0))
    step = 1 / (0.5 * np.linalg.norm(xs, 2) ** 2 / len(train) + 0.5 + PENALTY)
    before, momentum = (w, bias), (w, bias)
    for k in range(STEPS):  # accelerated gradient steps of a length that cannot diverge
        off = (_softmax(xs @ momentum[0] + momentum[1]) - y) / len(train)
        after = (momentum[0] - step * (xs.T @ off + PENALTY * momentum[0]), momentum[1] - step * off.sum(0))
        momentum = tuple(a + k / (k + 3) * (a - b) for a, b in zip(after, before))
        before = after
    w = before[0] * scale[:, None]
    weights: dict[str, dict[str, np.ndarray]] = {}
    for (a, g), row in zip(names, w):
        weights.setdefault(a, {})[g] = row
    model = Model(values, weights, before[1] - mean @ w)
    held = [r for r in rows[TRAIN:] if r[attr] in values]
    if held:
        z = np.array([model.bias + sum(model.weigh(a, r.get(a)) for a in ATTRS if a != attr) for r in held])
        right = [values.index(r[attr]) for r in held]
        model.temperature = min(TEMPERATURES, key=lambda t: -np.log(_softmax(z / t)[range(len(held)), right] + 1e-300).sum())
    return model


def predict(dirty: DataFrame, labels: Labels) -> DataFrame:
    """_id, attr, value, repair, score for every cell; a column without labels has no repair."""
    truth = labels.draw()
    models = {a: fit(truth, a) for a in ATTRS}

    def answered(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            places = {a: pd.factorize(batch[a]) for a in ATTRS}
            for attr, model in models.items():
                out = pd.DataFrame({"_id": batch["_id"], "attr": attr, "value": batch[attr], "repair": None, "score": 0.0})
                if len(model.values) == 1:
                    out["repair"], out["score"] = model.values[0], 1.0
                elif model.values and len(batch):
                    z = np.tile(model.bias, (len(batch), 1))
                    for a, (code, distinct) in places.items():
                        if a != attr and len(distinct):
                            added = np.array([model.weigh(a, v) for v in distinct] + [np.zeros(len(model.values))])
                            z += added[code]  # code -1, a blank, is the last row
                    p = _softmax(z / model.temperature)
                    out["repair"], out["score"] = np.array(model.values, dtype=object)[p.argmax(1)], p.max(1)
                yield out

    return dirty.select("_id", *ATTRS).mapInPandas(answered, "_id string, attr string, value string, repair string, score double")


def detect(dirty: DataFrame, labels: Labels, threshold: float = THRESHOLD) -> DataFrame:
    differs = ~F.col("repair").eqNullSafe(present(F.col("value")))
    return predict(dirty, labels).filter((F.col("score") >= threshold) & differs).select("_id", "attr")


def correct(dirty: DataFrame, cells: DataFrame, labels: Labels) -> DataFrame:
    return predict(dirty, labels).join(cells.select("_id", "attr"), ["_id", "attr"], "left_semi").filter(F.col("repair").isNotNull()).select("_id", "attr", "repair", "score")

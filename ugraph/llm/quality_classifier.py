"""Quality classifier: naive Bayes features in a linear support vector machine.

Indicators of hashed byte n-grams are scaled by their class log-count ratios and brought to unit length; dual
coordinate descent fits the linear hinge-loss model on them. The fit uses a bounded sample (FIT_ROWS labelled rows of
least hash, none with crc32(doc_id) mod 4 = 2); a fifth of it is left out of the descent to turn margins into
probabilities. Labels, lang, source and doc_id never enter a score.

Defined cases: null text is an empty text, whose margin is the model's intercept; a doc_id labelled more than once
counts with its highest label; with fewer than two classes among the labels every score is the share of label 1 (0.5
with no labels at all); rows of equal doc_id are scored each on their own; null doc_id is not held out.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import least_hashed, map_arrow, slices

BITS, SIZES = 18, (1, 2, 3, 4)
FIT_ROWS, EPOCHS, COST, SMOOTH, SEED = 8000, 12, 1.0, 1.0, 29
THRESHOLD = 0.7


def gram_ids(text: bytes) -> np.ndarray:
    """Different hashed byte n-grams of a text, in order."""
    if not text:
        return np.empty(0, np.uint32)
    b = np.frombuffer(text, np.uint8).astype(np.uint32)
    seen = np.zeros(1 << BITS, bool)
    for n in SIZES:
        if len(b) < n:
            break
        key = np.full(len(b) - n + 1, 0x811C9DC5 + n, np.uint32)
        for i in range(n):
            key = (key ^ b[i : len(b) - n + 1 + i]) * np.uint32(0x01000193)
        key ^= key >> np.uint32(15)
        key *= np.uint32(0x2C1B3C6D)
        seen[key >> np.uint32(32 - BITS)] = True
    return np.flatnonzero(seen).astype(np.uint32)


def log_ratios(rows: list[np.ndarray], labels: np.ndarray) -> np.ndarray:
    """log((p / |p|) / (q / |q|)) of the smoothed counts of both classes."""
    counts = []
    for side in (1, 0):
        some = [r for r, y in zip(rows, labels, strict=True) if y == side]
        counts.append(SMOOTH + np.bincount(np.concatenate(some).astype(np.int64), minlength=1 << BITS))
    p, q = counts
    return np.log(p / p.sum()) - np.log(q / q.sum())


def descend(rows: list[np.ndarray], labels: np.ndarray, ratio: np.ndarray, epochs: int = EPOCHS, cost: float = COST, seed: int = SEED) -> tuple[np.ndarray, float]:
    """Weights and intercept of the hinge-loss model by coordinate descent on its dual. The classes weigh alike."""
    rng = np.random.default_rng(seed)
    y = np.where(labels == 1, 1.0, -1.0)
    values = [ratio[r] / max(np.linalg.norm(ratio[r]), 1e-9) for r in rows]
    upper = np.where(y > 0, cost * len(y) / max(2 * (y > 0).sum(), 1), cost * len(y) / max(2 * (y < 0).sum(), 1))
    curvature = np.array([v @ v + 1.0 for v in values])
    alpha, w, intercept = np.zeros(len(rows)), np.zeros(1 << BITS), 0.0
    for _ in range(epochs):
        largest = 0.0
        for i in rng.permutation(len(rows)).tolist():
            idx, v = rows[i], values[i]
            slope = y[i] * (w[idx] @ v + intercept) - 1.0
            a = alpha[i]
            new = min(max(a - slope / curvature[i], 0.0), upper[i])
            if new != a:
                step = (new - a) * y[i]
                w[idx] += step * v
                intercept += step
                alpha[i] = new
                largest = max(largest, abs(new - a))
        if largest < 1e-3:
            break
    return w, intercept


def margins(rows: list[np.ndarray], ratio: np.ndarray, w: np.ndarray, intercept: float) -> np.ndarray:
    both = ratio * w
    square = ratio * ratio
    return np.array([both[r].sum() / max(np.sqrt(square[r].sum()), 1e-9) + intercept for r in rows])


def sigmoid_fit(m: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and intercept of P(label 1 | margin), by Newton steps on the smoothed targets' log loss."""
    n1, n0 = (y == 1).sum(), (y == 0).sum()
    t = np.where(y == 1, (n1 + 1) / (n1 + 2), 1 / (n0 + 2))
    a, b = 1.0, 0.0
    for _ in range(60):
        p = 1 / (1 + np.exp(-np.clip(a * m + b, -30, 30)))
        g = np.array([((p - t) * m).sum(), (p - t).sum()])
        r = p * (1 - p)
        h = np.array([[(r * m * m).sum() + 1e-6, (r * m).sum()], [(r * m).sum(), r.sum() + 1e-6]])
        step = np.linalg.solve(h, g)
        a, b = a - step[0], b - step[1]
        if np.abs(step).max() < 1e-8:
            break
    return float(a), float(b)


def train(rows: list[np.ndarray], labels: np.ndarray) -> tuple[np.ndarray, np.ndarray, float, float]:
    """ratio, weights and the sigmoid's two numbers (the intercept is folded in)."""
    size = 1 << BITS
    if len(set(labels.tolist())) < 2:
        share = float(labels.mean()) if len(labels) else 0.5
        share = min(max(share, 1e-6), 1 - 1e-6)
        return np.zeros(size), np.zeros(size), 0.0, float(np.log(share / (1 - share)))
    fold = np.arange(len(rows)) % 5 == 0
    if min(len(set(labels[fold].tolist())), len(set(labels[~fold].tolist()))) < 2:
        fold = np.zeros(len(rows), bool)
    fit_rows = [r for r, f in zip(rows, fold, strict=True) if not f]
    ratio = log_ratios(fit_rows, labels[~fold])
    w, intercept = descend(fit_rows, labels[~fold], ratio)
    side = fold if fold.any() else ~fold
    m = margins([r for r, f in zip(rows, side, strict=True) if f], ratio, w, intercept)
    a, b = sigmoid_fit(m, labels[side])
    return ratio, w, a, a * intercept + b


def _features(batches):
    for batch in batches:
        for part in slices(batch, "text"):
            ids = [gram_ids((t or "").encode()).tobytes() for t in part.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("label"), pa.array(ids, pa.binary())], names=["doc_id", "label", "ids"])


def _train(batches):
    rows = [r for batch in batches for r in batch.to_pylist()]
    rows.sort(key=lambda r: (r["doc_id"], r["ids"]))
    ratio, w, a, b = train([np.frombuffer(r["ids"], np.uint32) for r in rows], np.array([r["label"] for r in rows], dtype=np.int64))
    yield pa.RecordBatch.from_arrays([pa.array([(ratio * w * a).astype("<f4").tobytes()]), pa.array([ratio.astype("<f4").tobytes()]), pa.array([b])], names=["both", "ratio", "b"])


def _score(both: np.ndarray, ratio: np.ndarray, b: float):
    def run(batches):
        square = ratio * ratio
        for batch in batches:
            for part in slices(batch, "text"):
                rows = [gram_ids((t or "").encode()) for t in part.column("text").to_pylist()]
                m = np.array([both[r].sum() / max(np.sqrt(square[r].sum()), 1e-9) if len(r) else 0.0 for r in rows], dtype=np.float64) + b
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("held_out"), pa.array(1 / (1 + np.exp(-np.clip(m, -30, 30))))], names=["doc_id", "held_out", "score"])

    return run


def held_out(doc_id):
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def quality_scores(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS) -> DataFrame:
    """op8: doc_id, held_out, score, predicted of every document."""
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    marks = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("label")).filter("label in (0, 1) and doc_id is not null")
    marks = marks.groupBy("doc_id").agg(F.max("label").alias("label")).filter(~held_out(F.col("doc_id")))
    chosen = least_hashed(marks, fit_rows, SEED, "doc_id")
    some = map_arrow(texts.join(F.broadcast(chosen), "doc_id"), _features, "doc_id long, label int, ids binary")
    # the features are made where the texts are; at most fit_rows rows of them go to the task that fits
    model = map_arrow(some.repartition(1), _train, "both binary, ratio binary, b double").first()
    both, ratio = (np.frombuffer(model[c], "<f4") for c in ("both", "ratio"))
    scored = map_arrow(texts.withColumn("held_out", held_out(F.col("doc_id"))), _score(both, ratio, model["b"]), "doc_id long, held_out boolean, score double")
    return scored.withColumn("predicted", (F.col("score") >= THRESHOLD).cast("int"))

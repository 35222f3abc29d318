"""Quality by positive-unlabelled learning: a classifier that minimises the non-negative unbiased risk.

Trusted positives are labelled good documents that are not held out; unlabelled text is documents without a usable
label. The class prior is the share of good ones among the labels that may be used. Each document has about two dozen
whole-text measures; each measure is cut at quantiles of the unlabelled sample into places with a weight each, so the
score is additive but not linear.

The fit uses a bounded sample: at most ``positives`` and ``unlabelled`` rows (the least hashes of the id). Scores of all
documents come from whole texts.

Defined cases: null, empty and wordless texts have all measures 0 and a score as any other; null ids are scored and held
out; repeated labels of an id count as good if all are; without a positive or without unlabelled rows every score is
the prior (0 if that is unknown too). Columns other than id and text are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import held_out, lean
from .textkernel import LOWER, SPACE, Hashed, spans, texts

_BYTES = np.arange(256)
_CLASSES = np.array([
    (_BYTES >= 48) & (_BYTES <= 57), (_BYTES >= 65) & (_BYTES <= 90), (_BYTES >= 97) & (_BYTES <= 122), _BYTES >= 128,
    np.isin(_BYTES, list(b".,;:'\"()-")), np.isin(_BYTES, list(b"!?")), np.isin(_BYTES, list(b"#$%&*+/<=>@\\^_`{|}~[]")), _BYTES == 124, _BYTES == 10,
]).astype(float)
#: Places that a measure is cut into.
PLACES = 16


def measures(buf: np.ndarray) -> np.ndarray:
    """Whole-text measures: classes of bytes, lengths, and how much words, pairs and lines repeat."""
    starts, ends = spans(buf, SPACE)
    n = len(starts)
    if not n:
        return np.zeros(len(_CLASSES) + 15)
    kinds = _CLASSES @ np.bincount(buf, minlength=256) / len(buf)
    lengths = ends - starts
    low = LOWER[buf]
    words = Hashed(low).spans(starts, ends)
    distinct, times = np.unique(words, return_counts=True)
    pairs = len(np.unique(words[1:] * np.uint64(3) + words[:-1])) / max(1, n - 1)
    same = float((words[1:] == words[:-1]).mean()) if n > 1 else 0.0
    runs = np.diff(np.flatnonzero(np.concatenate(([True], words[1:] != words[:-1], [True]))))
    line = buf == 10
    a, b = spans(line.astype(np.uint8), np.array([False, True] + [False] * 254))
    lines, line_times = np.unique(Hashed(low).spans(a, b), return_counts=True)
    marks = low[ends - 1]
    more = [
        np.log1p(n), np.log1p(len(buf)), lengths.mean(), lengths.std(), np.log1p(lengths.max()), len(distinct) / n, times.max() / n, pairs, same, np.log1p(runs.max()),
        np.log1p(len(a)), len(lines) / max(1, len(a)), line_times.max() / max(1, len(a)), np.log1p((b - a).mean()) if len(a) else 0.0, float(np.isin(marks, list(b".!?")).mean()),
    ]
    return np.concatenate([kinds, more])


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _placed(x: np.ndarray, cuts: np.ndarray) -> np.ndarray:
    """Each measure's place, as an index over all places."""
    return np.stack([np.searchsorted(cuts[j], x[:, j], "right") + j * (PLACES + 1) for j in range(x.shape[1])], 1)


def fit_nonnegative(positive: np.ndarray, unlabelled: np.ndarray, prior: float, steps: int = 500, decay: float = 3e-4) -> tuple[np.ndarray, np.ndarray, float]:
    """Cuts, weights and bias that minimise pi R+(P) + max(0, R-(U) - pi R-(P)) with the sigmoid loss.

    Where the bracket falls below 0, the step climbs it back instead, as the non-negative estimator asks.
    """
    cuts = np.sort(np.quantile(unlabelled, np.linspace(0, 1, PLACES + 2)[1:-1], axis=0).T, axis=1)
    p_at, u_at = _placed(positive, cuts), _placed(unlabelled, cuts)
    size = positive.shape[1] * (PLACES + 1)
    w, b = np.zeros(size), np.log(prior / (1 - prior))
    m, v = np.zeros(size + 1), np.zeros(size + 1)
    for step in range(1, steps + 1):
        p, u = _sigmoid(b + w[p_at].sum(1)), _sigmoid(b + w[u_at].sum(1))
        gap = u.mean() - prior * p.mean()
        slope_p, slope_u = prior * p * (1 - p) / len(p), u * (1 - u) / len(u)
        gp, gu = (-2 * slope_p, slope_u) if gap >= 0 else (slope_p, -slope_u)
        grad = np.bincount(p_at.ravel(), np.repeat(gp, p_at.shape[1]), size) + np.bincount(u_at.ravel(), np.repeat(gu, u_at.shape[1]), size)
        grad = np.append(grad + decay * w, gp.sum() + gu.sum())
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
        move = 0.02 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
        w, b = w - move[:-1], b - move[-1]
    return cuts, w, float(b)


def predict(x: np.ndarray, model: tuple) -> np.ndarray:
    cuts, w, b = model
    if w is None:
        return np.full(len(x), b)
    return _sigmoid(b + w[_placed(x, cuts)].sum(1))


def _measured(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([measures(buf) for buf in texts(batch.column(1))], pa.list_(pa.float64()))], [id_col, "x"])

    return docs.select(id_col, text_col).mapInArrow(lean(run), f"`{id_col}` {docs.schema[id_col].dataType.simpleString()}, x array<double>")


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", positives: int = 6000, unlabelled: int = 12000) -> tuple:
    """Only the measures of the bounded samples come to the driver."""
    known = labels.where(~held_out(F.col(id_col)) & F.col(label_col).isNotNull()).groupBy(id_col).agg(F.min(label_col).cast("int").alias("y"))
    prior = known.agg(F.avg("y")).first()[0]
    order = [F.xxhash64(id_col, F.lit(13)), F.col(id_col)]
    good = known.where("y = 1").select(id_col).orderBy(*order).limit(positives)
    rest = docs.select(id_col).where(F.col(id_col).isNotNull()).join(known, id_col, "left_anti").distinct().orderBy(*order).limit(unlabelled)
    both = good.withColumn("p", F.lit(1)).unionAll(rest.withColumn("p", F.lit(0)))
    rows = _measured(docs.select(id_col, text_col).join(F.broadcast(both.select(id_col)), id_col, "left_semi"), id_col, text_col).join(F.broadcast(both), id_col)
    rows = rows.select("p", "x").orderBy(F.col("p"), F.col("x")).toArrow()
    p = rows["p"].to_numpy()
    if not prior or prior >= 1 or not (p == 1).any() or not (p == 0).any():
        return None, None, float(prior or 0.0)
    x = np.array(rows["x"].to_pylist(), float)
    return fit_nonnegative(x[p == 1], x[p == 0], prior)


def score(docs: DataFrame, model: tuple, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: id, score, text_key."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.array([measures(buf) for buf in texts(batch.column(2))])
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(predict(x, held.value) if len(x) else [], pa.float64())], [id_col, "text_key", "score"])

    picked = docs.select(id_col, F.xxhash64(text_col).alias("text_key"), text_col)
    return picked.mapInArrow(lean(run), f"`{id_col}` {docs.schema[id_col].dataType.simpleString()}, text_key bigint, score double")

"""Toxicity by multiple-instance learning: sentence scores, combined by noisy-or, are learned from document labels.

A document is a bag of sentences; each sentence has a logistic score over hashed words and word beginnings, and the
document's score is 1 - prod(1 - sentence score). Only document labels train it, yet the sentence scores say which
sentences offend.

The fit uses a bounded sample: at most ``positives`` and ``negatives`` labelled rows (the least hashes of the id), taken
from rows that are not held out. Scores of all documents come from whole texts.

Defined cases: null, empty and wordless texts have the score of an empty bag, 0; a row with a null id is scored and held out; repeated
rows are scored alike; repeated labels of an id count as toxic if one is; without any toxic training label, or
without any labelled document, every score is 0. Columns other than id and text are not read.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import held_out, lean
from .textkernel import LOWER, NON_WORD, Hashed, spans, texts

#: Features are hashed into 2 ** BITS places; words also count by their beginnings of so many bytes.
BITS, BEGINNINGS = 20, (4, 6, 8, 10)
_ENDS = np.zeros(256, bool)
_ENDS[[10, 13, 33, 46, 63]] = True


def lower_latin(buf: np.ndarray) -> np.ndarray:
    """A-Z and the capitals of Latin-1 lower-cased in place of their bytes, so spans stay valid."""
    out = LOWER[buf]
    if len(out) > 1:
        capital = (out[:-1] == 0xC3) & (out[1:] >= 0x80) & (out[1:] <= 0x9E) & (out[1:] != 0x97)
        out[1:][capital] += 0x20
    return out


def bag(buf: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Sentence starts and ends, then for each feature its sentence and place."""
    low = lower_latin(buf)
    starts, ends = spans(low, NON_WORD)
    first, last = spans(low, _ENDS)
    if not len(starts):
        return first[:0], last[:0], np.zeros(0, np.int64), np.zeros(0, np.int64)
    sentence = np.searchsorted(first, starts, "right") - 1
    hashed, sent, place = Hashed(low), [sentence], []
    place.append(hashed.spans(starts, ends) >> np.uint64(64 - BITS))
    for n in BEGINNINGS:
        longer = ends - starts > n
        place.append((hashed.spans(starts[longer], starts[longer] + n) ^ np.uint64(n << 50)) >> np.uint64(64 - BITS))
        sent.append(sentence[longer])
    key = np.unique(np.concatenate(sent) * (1 << BITS) + np.concatenate(place).astype(np.int64))
    return first, last, key >> BITS, key & ((1 << BITS) - 1)


def fit_noisy_or(bags: Callable[[], Iterator[tuple[np.ndarray, np.ndarray]]], toxic: np.ndarray, prior: float, features: int = 600, steps: int = 250, decay: float = 2e-3) -> tuple[np.ndarray, float]:
    """Weights of the hashed places and the bias; ``bags()`` gives each document's (sentence, place) arrays, and is gone
    through twice so that only the chosen features are ever held. Few features and this decay had the least log loss in
    cross-validation within the rows learned from; with thousands of features the fit learned its rows by heart."""
    counts = np.zeros((2, 1 << BITS), np.float32)
    for (_, place), y in zip(bags(), toxic):
        counts[int(y)][np.unique(place)] += 1
    n = np.array([max(1, (toxic == 0).sum()), max(1, (toxic == 1).sum())], np.float32)
    gain = np.abs(np.log((counts[1] + 0.5) * (n[0] + 1) / (counts[0] + 0.5) / (n[1] + 1))) * np.sqrt(counts[1] + counts[0] * n[1] / n[0])
    gain[counts.sum(0) < 4] = 0
    picked = np.sort(np.argsort(-gain, kind="stable")[:features])
    del counts, gain
    slot = np.full(1 << BITS, -1, np.int32)
    slot[picked] = np.arange(len(picked))
    sent, feat, doc, at, size = [], [], [], 0, 0
    for i, (sentence, place) in enumerate(bags()):
        here = int(sentence.max()) + 1 if len(sentence) else 0
        ok = slot[place] >= 0
        sent.append((sentence[ok] + at).astype(np.int32))
        feat.append(slot[place[ok]])
        doc.append(np.full(here, i, np.int32))
        at, size = at + here, i + 1
    sent, feat, doc = (np.concatenate([*x, np.zeros(0, np.int32)]) for x in (sent, feat, doc))
    weigh = np.where(toxic == 1, prior / n[1], (1 - prior) / n[0])
    w, b = np.zeros(len(picked)), -4.0
    m, v = np.zeros(len(picked) + 1), np.zeros(len(picked) + 1)
    for step in range(1, steps + 1):
        z = b + np.bincount(sent, w[feat], at)
        p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        none = np.exp(np.maximum(np.bincount(doc, np.log1p(-np.minimum(p, 1 - 1e-9)), size), -30))
        pull = np.where(toxic == 1, -none / np.maximum(1 - none, 1e-9), 1.0) * weigh
        g = pull[doc] * p
        grad = np.append(np.bincount(feat, g[sent], len(picked)) + decay * w / len(picked) ** 0.5, g.sum())
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
        move = 0.1 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
        w, b = w - move[:-1], b - move[-1]
    full = np.zeros(1 << BITS, np.float32)
    full[picked] = w
    return full, b


def sentence_scores(buf: np.ndarray, weights: np.ndarray, bias: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    first, last, sentence, place = bag(buf)
    if not len(sentence):
        return first[:0], last[:0], np.zeros(0)
    used = np.unique(sentence)
    if bias == -np.inf:
        return first[used], last[used], np.zeros(len(used))
    z = bias + np.bincount(sentence, weights[place], len(first))[used]
    return first[used], last[used], 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _sample(labels: DataFrame, id_col: str, label_col: str, positives: int, negatives: int) -> DataFrame:
    known = labels.where(~held_out(F.col(id_col)) & F.col(label_col).isNotNull()).groupBy(id_col).agg(F.max(label_col).cast("int").alias("y"))
    pick = [known.where(F.col("y") == y).orderBy(F.xxhash64(id_col, F.lit(11)), id_col).limit(n) for y, n in ((1, positives), (0, negatives))]
    return pick[0].unionAll(pick[1]), known.agg(F.avg("y")).first()[0]


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", positives: int = 2500, negatives: int = 5000) -> tuple[np.ndarray, float]:
    """Fits on at most ``positives`` + ``negatives`` labelled documents, in one task whose input that bounds; only the model comes to the driver."""
    chosen, prior = _sample(labels, id_col, label_col, positives, negatives)
    if not prior:
        return np.zeros(1 << BITS, np.float32), -np.inf
    rows = docs.select(id_col, text_col).join(F.broadcast(chosen), id_col).select("y", F.xxhash64(text_col).alias("h"), text_col)

    def fit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not (parts := list(batches)):
            return
        sample = pa.Table.from_batches(parts)
        order = np.lexsort((sample["y"].to_numpy(), sample["h"].to_numpy()))  # the fit does not depend on how rows came
        held = [buf for chunk in sample["text"].chunks for buf in texts(chunk)]
        full, bias = fit_noisy_or(lambda: (bag(held[i])[2:] for i in order.tolist()), sample["y"].to_numpy()[order], prior)
        at = np.flatnonzero(full)
        yield pa.RecordBatch.from_arrays([pa.array([at.astype(np.int32).tobytes()]), pa.array([full[at].tobytes()]), pa.array([float(bias)])], ["at", "weights", "bias"])

    one = rows.toDF("y", "h", "text").repartition(1).mapInArrow(lean(fit), "at binary, weights binary, bias double").first()
    full = np.zeros(1 << BITS, np.float32)
    if one is None:
        return full, -np.inf
    full[np.frombuffer(one["at"], np.int32)] = np.frombuffer(one["weights"], np.float32)
    return full, one["bias"]


def score(docs: DataFrame, model: tuple[np.ndarray, float], id_col: str = "doc_id", text_col: str = "text", offends: float = 0.5) -> DataFrame:
    """Per row: id, score, text_key and the sentences (byte spans) whose own score is at least ``offends``."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights, bias = held.value
        for batch in batches:
            scores, found = [], []
            for buf in texts(batch.column(2)):
                a, b, p = sentence_scores(buf, weights, bias)
                scores.append(1 - np.exp(np.log1p(-np.minimum(p, 1 - 1e-12)).sum()) if len(p) else 0.0)
                found.append([{"start": int(a[i]), "end": int(b[i]), "score": float(p[i])} for i in np.flatnonzero(p >= offends)])
            kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())]))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(scores, pa.float64()), pa.array(found, kind)], [id_col, "text_key", "score", "sentences"])

    kind = docs.schema[id_col].dataType.simpleString()
    picked = docs.select(id_col, F.xxhash64(text_col).alias("text_key"), text_col)
    return picked.mapInArrow(lean(run), f"`{id_col}` {kind}, text_key bigint, score double, sentences array<struct<start: bigint, end: bigint, score: double>>")

"""Quality classifier: naive Bayes features in a linear support vector machine.

A document is a set of indicators: words, word pairs, word shapes and shape pairs (with a mark for an immediate
repeat), hashed into ``DIMS`` places. Each indicator is scaled by the log-count ratio of the classes; a linear model
with squared hinge loss is fitted to the scaled indicators by dual coordinate descent, and its weights are moved
towards their mean size (``BETA`` is the share of the fitted part), as is usual for this model. The cut weighs a
lost good document as ten kept bad ones. Fitting uses at most ``TRAIN_PER_CLASS`` labelled
documents of either class, chosen by hash (the only bound); scoring runs over every whole text and moves no data.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellspace.llm.common import WordIds, map_batches, mix, pieces, word_hashes

DIMS = 1 << 20
#: Labelled documents of each class that the fit may use.
TRAIN_PER_CLASS = 2500
BETA, COST, EPOCHS, SMOOTH, FOLDS = 0.25, 0.1, 12, 1.0, 4

_KIND = np.full(256, 7, np.uint8)
for _c in range(256):
    _s = chr(_c)
    _KIND[_c] = 0 if _c >= 128 or "a" <= _s <= "z" else 1 if "A" <= _s <= "Z" else 2 if _s.isdigit() else 3 if _s == " " else 4 if _s in ".,;:'\"()-" else 5 if _s in "!?" else 6 if _s in "|<>{}" else 7


def word_rows(words: list[bytes]) -> list[np.ndarray]:
    """(hash, shape) of each word: the kinds of its first two and last three bytes, and of its length."""
    ends = b"".join([w[:2].ljust(2) + w[-3:].rjust(3) for w in words])
    kinds = _KIND[np.frombuffer(ends, np.uint8).reshape(len(words), 5)].astype(np.uint64)
    shape = kinds @ np.array([1, 8, 64, 512, 4096], np.uint64)
    size = np.minimum(np.fromiter(map(len, words), np.int64, len(words)), 30) // 10
    return [word_hashes(words), shape + (size.astype(np.uint64) << np.uint64(15))]


def indicators(texts: list[str], ids: WordIds) -> tuple[np.ndarray, np.ndarray]:
    """(feature numbers, how many in each document): the distinct ones of each document, ascending."""
    flat, lengths = ids([t.encode("utf-8", "replace").split() for t in texts])
    if not len(flat):
        return np.zeros(0, np.int64), np.zeros(len(texts), np.int64)
    h, shape = (r[flat] for r in ids.rows)
    doc = np.repeat(np.arange(len(texts), dtype=np.uint64), lengths)
    pair = np.flatnonzero(doc[1:] == doc[:-1])
    repeat = (flat[pair] == flat[pair + 1]).astype(np.uint64)
    salt = [np.uint64(s * 0x9E3779B97F4A7C15 % 2**64) for s in (1, 2, 3, 4)]
    parts = [h + salt[0], h[pair] * np.uint64(3) + h[pair + 1] + salt[1], shape + salt[2], (shape[pair] << np.uint64(20)) + (shape[pair + 1] << np.uint64(1)) + repeat + salt[3]]
    feature = mix(np.concatenate(parts)) & np.uint64(DIMS - 1)
    key = np.sort((np.concatenate([doc, doc[pair], doc, doc[pair]]) << np.uint64(20)) | feature)
    key = key[np.concatenate([[True], key[1:] != key[:-1]])]
    return (key & np.uint64(DIMS - 1)).astype(np.int64), np.bincount((key >> np.uint64(20)).astype(np.int64), minlength=len(texts))


def log_count_ratios(rows: list[np.ndarray], y: np.ndarray) -> np.ndarray:
    """ln of the share of each indicator among those of the positive class over that of the negative class."""
    counts = []
    for sign in (1, -1):
        mine = [r for r, s in zip(rows, y, strict=True) if s == sign]
        c = np.bincount(np.concatenate(mine) if mine else np.zeros(0, np.int64), minlength=DIMS) + SMOOTH
        counts.append(np.log(c / c.sum()))
    return counts[0] - counts[1]


def dual_coordinate_descent(rows: list[np.ndarray], scale: np.ndarray, y: np.ndarray, cost: float = COST, epochs: int = EPOCHS, seed: int = 0) -> tuple[np.ndarray, float]:
    """Weights and bias of the L2-regularised squared-hinge model over rows of scaled indicators."""
    w, bias, alpha = np.zeros(len(scale)), 0.0, np.zeros(len(rows))
    values = [scale[r] for r in rows]
    share = {s: len(y) / (2 * max(1, int((y == s).sum()))) for s in (1, -1)}
    diag = np.array([0.5 / (cost * share[s]) for s in y])
    norm = np.array([v @ v + 1 for v in values]) + diag
    rng = np.random.default_rng(seed)
    for _ in range(epochs):
        moved = 0.0
        for i in rng.permutation(len(rows)):
            g = y[i] * (w[rows[i]] @ values[i] + bias) - 1 + diag[i] * alpha[i]
            new = max(alpha[i] - g / norm[i], 0.0)
            if (step := new - alpha[i]) != 0:
                w[rows[i]] += step * y[i] * values[i]
                bias += step * y[i]
                alpha[i] = new
                moved = max(moved, abs(step))
        if moved < 1e-4:
            break
    return w, bias


@dataclass
class QualityModel:
    """``weights`` of indicators (scaling included) and ``bias``; a text passes from ``threshold`` on."""

    weights: np.ndarray
    bias: float
    threshold: float = 0.0

    def score(self, texts: list[str], ids: WordIds) -> np.ndarray:
        feature, n = indicators(texts, ids)
        who = np.repeat(np.arange(len(texts)), n)
        return np.bincount(who, self.weights[feature], len(texts)) + self.bias


def _mixed(rows: list[np.ndarray], y: np.ndarray) -> QualityModel:
    ratio = log_count_ratios(rows, y)
    w, bias = dual_coordinate_descent(rows, ratio, y)
    seen = np.unique(np.concatenate(rows))
    mixed = np.zeros_like(w)
    mixed[seen] = (1 - BETA) * np.abs(w[seen]).mean() + BETA * w[seen]
    return QualityModel(mixed * ratio, BETA * bias)


def fit_rows(rows: list[np.ndarray], y: np.ndarray) -> QualityModel:
    """The mean size pulls towards plain naive Bayes, so the cut is set anew, on rows that each of ``FOLDS`` fits has
    not seen."""
    model, held = _mixed(rows, y), np.zeros(len(rows))
    fold = np.arange(len(rows)) % FOLDS
    for f in range(FOLDS):
        train = np.flatnonzero(fold != f)
        part = _mixed([rows[i] for i in train], y[train]) if len(set(y[train].tolist())) == 2 else model
        for i in np.flatnonzero(fold == f):
            held[i] = part.weights[rows[i]].sum() + part.bias
    cuts = np.sort(held)
    below = lambda sign: np.searchsorted(np.sort(held[y == sign]), cuts) / (y == sign).sum()
    k = int(np.argmax(below(-1) - 10 * below(1)))
    model.threshold = float(cuts[k] + cuts[max(0, k - 1)]) / 2
    return model


def _feature_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    ids = WordIds(word_rows, 150_000)
    for part, texts in pieces(batches, 1, 2_000_000):
        feature, n = indicators([t or "" for t in texts], ids)
        rows = np.split(feature.astype(np.int32), np.cumsum(n)[:-1])
        yield pa.RecordBatch.from_arrays([part.column(0), pa.array([r.tobytes() for r in rows], pa.binary()), part.column(2)], names=["id", "features", "label"])


def fit_quality(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", per_class: int = TRAIN_PER_CLASS) -> QualityModel:
    """Fits the model to labelled documents. Null labels and texts are left out; of several labels of one id the
    higher counts. If a class has no document (an empty table, no labels) the model passes every
    text that isn't blank."""
    lab = labels.select(F.col(id_col).alias("id"), F.col(label_col).cast("int").alias("label")).where("id is not null and label in (0, 1)")
    lab = lab.groupBy("id").agg(F.max("label").alias("label"))
    order = F.xxhash64("id")
    chosen = [lab.where(F.col("label") == c).orderBy(order, "id").limit(per_class) for c in (0, 1)]
    chosen = F.broadcast(chosen[0].union(chosen[1]))
    df = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).join(chosen, "id").where("text is not null")
    found = map_batches(df.select("id", "text", "label"), _feature_kernel, f"id {df.schema['id'].dataType.simpleString()}, features binary, label int").toArrow()
    order = np.argsort(np.array(found["id"].to_pylist())) if found.num_rows else []
    rows, y = found["features"].to_pylist(), found["label"].to_pylist()
    rows = [np.frombuffer(rows[i], np.int32).astype(np.int64) for i in order]
    y = np.array([1 if y[i] else -1 for i in order])
    if len(set(y.tolist())) < 2:
        return QualityModel(np.zeros(DIMS), 1.0)
    return fit_rows(rows, y)


def quality_scores(docs: DataFrame, model: QualityModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, score, keep) of every document. Null, empty and blank texts have the score of no indicator, the bias, and
    aren't kept; null ids stay null; repeated rows repeat."""
    df = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    kind = df.schema["id"].dataType.simpleString()
    sent = df.sparkSession.sparkContext.broadcast(model)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, m = WordIds(word_rows, 150_000), sent.value
        for part, texts in pieces(batches, 1, 2_000_000):
            texts = [t or "" for t in texts]
            s = m.score(texts, ids)
            keep = (s >= m.threshold) & np.array([bool(t.strip()) for t in texts], bool)
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(np.round(s, 6)), pa.array(keep)], names=["id", "score", "keep"])

    return map_batches(df, kernel, f"id {kind}, score double, keep boolean").withColumnRenamed("id", id_col)


def keep_quality(docs: DataFrame, model: QualityModel, text_col: str = "text") -> DataFrame:
    """``docs`` without the rows that the model rejects (and without null, empty and blank texts). Rows are judged by
    their text alone, so repeated rows stay or go together, whatever their id; an empty table stays empty."""
    at = docs.columns.index(text_col)
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, m = WordIds(word_rows, 150_000), sent.value
        for part, texts in pieces(batches, at, 2_000_000):
            keep = m.score([t or "" for t in texts], ids) >= m.threshold
            keep &= np.array([bool(t and t.strip()) for t in texts], bool)
            yield part.filter(pa.array(keep))

    return map_batches(docs, kernel, docs.schema)

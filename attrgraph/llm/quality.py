"""Quality classifier: a linear support-vector machine over n-gram indicators scaled by naive Bayes ratios.

Indicators are of byte trigrams and of word-shape n-grams (orders 1 to 3; a shape keeps the kinds of characters in
a word, and a word that repeats the one before it has a mark), hashed into ``BINS``. Each indicator is scaled by
its log-count ratio between the classes; a hinge-loss model is then fitted by dual coordinate descent.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from attrgraph.session import lean, workers

BINS = 1 << 15
SAMPLE_PER_CLASS = 2500
_BYTE_BINS = BINS // 2
_MEMO_LIMIT = 150_000
_RUNS = re.compile(rb"(.)\1+", re.S)
_KINDS = bytes.maketrans(bytes(range(256)), bytes(97 if 97 <= c <= 122 or c >= 128 else 65 if 65 <= c <= 90 else 48 if 48 <= c <= 57 else c for c in range(256)))


class Shapes(dict):
    """Word -> hash of its shape: kinds of characters with runs made one."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= _MEMO_LIMIT:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(_RUNS.sub(rb"\1", word.translate(_KINDS)))
        return value


def indicators(text: bytes | None, memo: Shapes) -> np.ndarray:
    """Sorted distinct feature numbers of a whole text; none for a null or empty one."""
    data = text or b""
    seen = np.zeros(BINS, bool)
    raw = np.frombuffer(data, np.uint8).astype(np.uint32)
    if len(raw) >= 3:
        code = (raw[:-2] << np.uint32(16) | raw[1:-1] << np.uint32(8) | raw[2:]) * np.uint32(2654435761)
        seen[(code >> np.uint32(18)) & np.uint32(_BYTE_BINS - 1)] = True
    words = data.split()
    if words:
        shape = np.fromiter(map(memo.__getitem__, words), np.uint64, len(words))
        same = np.zeros(len(words), np.uint64)
        same[1:] = [a == b for a, b in zip(words, words[1:], strict=False)]
        shape = shape + same * np.uint64(0x9E3779B97F4A7C15)
        gram = np.zeros(len(words), np.uint64)
        for order in (1, 2, 3):
            if len(words) < order:
                break
            gram = (gram[: len(words) - order + 1] + shape[order - 1 :]) * np.uint64(0xFF51AFD7ED558CCD)
            gram ^= gram >> np.uint64(29)
            seen[_BYTE_BINS + ((gram + np.uint64(order)) * np.uint64(0xC4CEB9FE1A85EC53) >> np.uint64(50)).astype(np.int64) % _BYTE_BINS] = True
    return np.flatnonzero(seen)


def solve(features: list[np.ndarray], values: list[np.ndarray], y: np.ndarray, bound: np.ndarray, epochs: int = 30, tolerance: float = 1e-3) -> tuple[np.ndarray, float, np.ndarray]:
    """(weights, bias, dual variables) of least squared length (bias included) plus ``bound`` times hinge losses.

    Dual coordinate descent: each turn sets one variable to its best value in [0, bound], the others fixed; it ends when a pass
    over all moves none by ``tolerance``.
    """
    weights, bias, dual = np.zeros(BINS), 0.0, np.zeros(len(y))
    norm = np.array([float(v @ v) + 1 for v in values])
    order = np.random.default_rng(7)
    for _ in range(epochs):
        moved = 0.0
        for i in order.permutation(len(y)):
            f, v = features[i], values[i]
            gradient = y[i] * (weights[f] @ v + bias) - 1
            new = min(max(dual[i] - gradient / norm[i], 0.0), bound[i])
            if (step := new - dual[i]) != 0:
                weights[f] += step * y[i] * v
                bias += step * y[i]
                dual[i] = new
                moved = max(moved, abs(step))
        if moved < tolerance:
            break
    return weights, bias, dual


def fit(features: list[np.ndarray], labels: np.ndarray, cost: float = 1.0, epochs: int = 30) -> tuple[np.ndarray, float, float, float]:
    """(weights per indicator, bias, slope, shift) where the score is sigmoid(slope * margin + shift)."""
    y = np.where(labels > 0, 1.0, -1.0)
    if not len(y) or abs(y.sum()) == len(y):
        constant = 0.5 if not len(y) else float(y[0] > 0)
        return np.zeros(BINS), 0.0, 0.0, {0.5: 0.0, 1.0: 4.0, 0.0: -4.0}[constant]
    counts = np.ones((2, BINS))
    for f, t in zip(features, y, strict=True):
        counts[int(t > 0), f] += 1
    ratio = np.log(counts[1] / counts[1].sum()) - np.log(counts[0] / counts[0].sum())
    ratio[counts.sum(axis=0) <= 4] = 0.0
    values = []
    for f in features:
        v = ratio[f]
        values.append((v / max(1e-12, np.sqrt(v @ v + 1))).astype(np.float32))
    weight_of = len(y) / (2 * np.where(y > 0, (y > 0).sum(), (y < 0).sum()))  # balances the classes
    weights, bias, _ = solve(features, values, y, cost * weight_of, epochs)
    margin = np.array([weights[f] @ v + bias for f, v in zip(features, values, strict=True)])
    slope, shift = 2.0, 0.0
    for _ in range(200):  # a logistic fit of the margins on the balanced sample
        p = 1 / (1 + np.exp(-np.clip(slope * margin + shift, -30, 30)))
        g = (p - (y > 0)) * weight_of
        slope -= 0.5 * ((g @ margin) / len(y) + 1e-3 * (slope - 2.0))
        shift -= 0.5 * g.mean()
    return _scaled(weights, ratio), float(bias), float(max(slope, 0.1)), float(shift)


def _scaled(weights: np.ndarray, ratio: np.ndarray) -> np.ndarray:
    """Both rows a margin needs: weight times ratio, and the ratio for a text's norm."""
    return np.stack([weights * ratio, ratio * ratio])


def margin_of(f: np.ndarray, table: np.ndarray, bias: float) -> float:
    return float(table[0][f].sum() / np.sqrt(table[1][f].sum() + 1) + bias) if table.ndim == 2 else bias


def _collect(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    memo = Shapes()
    for batch in batches:
        packed = []
        for text in batch.column(2).cast(pa.binary()):
            bits = np.zeros(BINS, np.uint8)
            bits[indicators(text.as_py(), memo)] = 1
            packed.append(np.packbits(bits).tobytes())
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(packed, pa.binary())], ["doc_id", "quality", "bits"])


def _score(batches: Iterator[pa.RecordBatch], model: tuple) -> Iterator[pa.RecordBatch]:
    table, bias, slope, shift = model
    memo = Shapes()
    for batch in batches:
        scores = []
        for text in batch.column(2).cast(pa.binary()):
            z = slope * margin_of(indicators(text.as_py(), memo), table, bias) + shift
            scores.append(1 / (1 + np.exp(-min(max(z, -30.0), 30.0))))
        score = np.array(scores, float)
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(score), pa.array((score >= 0.5).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])


def _fold(folds: int):
    return F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(folds))


def learn(docs: DataFrame, labels: DataFrame, per_class: int = SAMPLE_PER_CLASS, folds: int = 3) -> tuple:
    """Fit on about ``2 * per_class`` labelled rows of each class, drawn by a hash of doc_id (the bound that the contract allows; rows may
    repeat or have no document); documents whose crc32 mod ``folds`` is 1 are never learnt from."""
    usable = labels.where(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull() & (_fold(folds) != 1))
    usable = usable.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("quality"))
    counts = {r.quality: r["count"] for r in usable.groupBy("quality").count().collect()}
    share = F.lit(0)
    for q, n in counts.items():
        share = F.when(F.col("quality") == q, int(min(1.0, 2 * per_class / n) * (1 << 30))).otherwise(share)
    chosen = usable.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < share).distinct().collect()
    ids = docs.sparkSession.createDataFrame(sorted({(r.doc_id, r.quality) for r in chosen}), "doc_id long, quality int")
    rows = docs.where("doc_id is not null and text is not null").join(F.broadcast(ids), "doc_id").select("doc_id", "quality", "text")
    packed = rows.mapInArrow(lean(_collect, "quality"), "doc_id long, quality int, bits binary").collect()
    unique = sorted({(r.doc_id, r.quality, bytes(r.bits)) for r in packed})
    features, y = [], []
    for q in (0, 1):
        mine = [r for r in unique if r[1] == q][: 2 * per_class]
        features += [np.flatnonzero(np.unpackbits(np.frombuffer(r[2], np.uint8))).astype(np.int32) for r in mine]
        y += [q] * len(mine)
    return fit(features, np.array(y))


def score_quality(docs: DataFrame, labels: DataFrame, folds: int = 3, per_class: int = SAMPLE_PER_CLASS) -> DataFrame:
    """Score every whole text of (doc_id, text): doc_id, held_out, score in 0..1, predicted.

    Null and empty texts have no indicators: their score follows the bias alone. With no usable labels, or labels of
    one class only, the score is the same for all (0.5, or near that class). A label that is neither 0 nor 1 isn't
    used; a document labelled both ways counts for both. Null doc_ids are scored and count as not held out. Very long texts are
    read whole; other columns are ignored; rows that repeat are scored again; an empty table gives an empty result.
    """
    workers(docs.sparkSession)
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    model = learn(docs, labels, per_class, folds)
    rows = docs.select("doc_id", F.coalesce(_fold(folds) == 1, F.lit(False)).alias("held_out"), "text")
    return rows.mapInArrow(lean(partial(_score, model=model), "quality"), "doc_id long, held_out boolean, score double, predicted int")


def _keep(batches: Iterator[pa.RecordBatch], model: tuple, at: int) -> Iterator[pa.RecordBatch]:
    table, bias, slope, shift = model
    memo = Shapes()
    for batch in batches:
        texts = batch.column(at).cast(pa.binary())
        keep = [slope * margin_of(indicators(t.as_py(), memo), table, bias) + shift >= 0 for t in texts]
        yield batch.filter(pa.array(keep, pa.bool_()))


def keep_good(docs: DataFrame, labels: DataFrame, folds: int = 3, per_class: int = SAMPLE_PER_CLASS) -> DataFrame:
    """The rows of ``docs``, with all their columns, whose score is 0.5 or more; learning is as in ``score_quality``.

    Null and empty texts, null ids, repeated rows and very long texts are scored as there, each row on its own; no column is
    read but doc_id and text; an empty table stays empty.
    """
    workers(docs.sparkSession)
    model = learn(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), labels, per_class, folds)
    return docs.mapInArrow(lean(partial(_keep, model=model, at=docs.columns.index("text")), "quality"), docs.schema)

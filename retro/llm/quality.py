"""Quality by regularised quadratic discriminant analysis of document statistics.

Each text gives a vector of transformed statistics (lengths, character shares, repetition, line shape). Every class has a
mean and a covariance that is shrunk towards the pooled covariance and its diagonal; the score is the logistic of the
difference of the two Mahalanobis log densities plus the prior's log odds, computed through cached Cholesky factors.
The moments are sums, so learning covers all labelled rows in one distributed pass.

Defined results: empty and null texts are scored as the vector of an empty text; without rows of both classes the score is the
learned class's share (0 with no labels). Repeated rows count each; labels that repeat a doc_id count once (the largest).
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from retro.llm import vector_text as vt
from retro.llm.runtime import checkpointed, id_and_text, lean

_KIND = np.zeros((256, 8), dtype=np.float32)  # letter, upper, digit, space, newline, sentence mark, bracket or table mark, other symbol
for _b in range(256):
    _c = chr(_b)
    _k = 0 if _b >= 128 or _c.isalpha() else 2 if _c.isdigit() else 3 if _c == " " else 4 if _c in "\n\r" else 5 if _c in ".,;:?" else 6 if _c in "|()[]{}<>" else 7
    _KIND[_b, _k] = 1
    if "A" <= _c <= "Z":
        _KIND[_b, 1] = 1
FEATURES = 18


def _per_row(values: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    sums = np.concatenate((np.zeros((1, *values.shape[1:])), np.cumsum(values, axis=0, dtype=np.float64)))
    return sums[offsets[1:]] - sums[offsets[:-1]]


def _shares_of_repeats(code: np.ndarray, row: np.ndarray, rows: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct codes of each row, and the count of each row's most frequent one."""
    order = np.lexsort((code, row))
    c, r = code[order], row[order]
    first = np.flatnonzero(np.concatenate(([True], (c[1:] != c[:-1]) | (r[1:] != r[:-1])))) if len(c) else np.zeros(0, np.int64)
    runs = np.diff(np.concatenate((first, [len(c)])))
    most = np.zeros(rows)
    np.maximum.at(most, r[first], runs)
    return np.bincount(r[first], minlength=rows), most


def statistics_of(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """(rows, FEATURES) transformed statistics of a block of texts."""
    rows, size = len(offsets) - 1, np.diff(offsets).astype(float)
    kinds = np.stack([_per_row(_KIND[:, k][data], offsets) for k in range(8)], axis=1)
    words = vt.words_of(data, offsets)
    n, row = np.diff(words.row_at).astype(float), words.row
    distinct, most = _shares_of_repeats(words.code, row, rows)
    pair = vt.mix64(words.code[:-1] * np.uint64(3) + words.code[1:])
    same = row[1:] == row[:-1]
    pairs, _ = _shares_of_repeats(pair[same], row[1:][same], rows)
    again = np.bincount(row[1:][same & (words.code[1:] == words.code[:-1])], minlength=rows)
    length = (words.end - words.start).astype(float)
    spread = _per_row(length**2, words.row_at)
    tail = np.isin(data[np.maximum(words.end - 1, 0)], np.frombuffer(b"!#$%&*+=@^~_", np.uint8)).astype(float)
    some, letters = np.maximum(n, 1), np.maximum(kinds[:, 0], 1)
    mean = _per_row(length, words.row_at) / some
    rare = lambda x: np.log(x + 0.002)
    return np.stack(
        [
            np.log1p(n), mean, np.sqrt(np.maximum(spread / some - mean**2, 0)), rare(kinds[:, 0] / np.maximum(size, 1)), rare(kinds[:, 1] / letters), rare(kinds[:, 2] / np.maximum(size, 1)),
            rare(kinds[:, 3] / np.maximum(size, 1)), rare(kinds[:, 4] / np.maximum(size, 1)), rare(kinds[:, 5] / some), rare(kinds[:, 6] / some), rare(kinds[:, 7] / some), np.log((distinct + 1) / (some + 1)),
            np.log((pairs + 1) / (np.maximum(n - 1, 0) + 1)), rare(again / some), rare(most / some), rare(_per_row(tail, words.row_at) / some), np.log((distinct + 1) / np.sqrt(some + 1)), (n < 5).astype(float),
        ],
        axis=1,
    )


@dataclass(frozen=True)
class Quality:
    #: Shrinkage of a class's covariance towards the pooled one, and then towards its diagonal.
    to_pooled: float = 0.1
    to_diagonal: float = 0.05
    threshold: float = 0.7
    prior: float = 0.0
    mean: np.ndarray | None = field(default=None, repr=False)
    #: Inverse Cholesky factors and log determinants of the two classes.
    factor: np.ndarray | None = field(default=None, repr=False)
    logdet: np.ndarray | None = field(default=None, repr=False)

    def statistics(self, docs: DataFrame) -> DataFrame:
        """(doc_id, x): the transformed statistics of every row."""

        def run(batches):
            for batch in batches:
                for first, last, data, offsets in vt.blocks(batch.column("text")):
                    x = statistics_of(data, offsets).astype(np.float32)
                    flat = pa.FixedSizeListArray.from_arrays(pa.array(x.ravel()), FEATURES).cast(pa.list_(pa.float32()))
                    yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(first, last - first), flat], ["doc_id", "x"])

        return id_and_text(docs).mapInArrow(lean(run), "doc_id long, x array<float>")

    def fit(self, statistics: DataFrame, labels: DataFrame, learn: Column) -> Quality:
        """statistics: what statistics() gives; labels: doc_id, label (0 or 1); learn: a condition on doc_id."""
        known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("label").cast("int").alias("label")).where(learn & F.col("label").isin(0, 1)).groupBy("doc_id").agg(F.max("label").alias("label"))
        width = FEATURES + 1

        def moments(batches):
            total = np.zeros((2, width, width))
            for batch in batches:
                if batch.num_rows:
                    x = np.concatenate([np.ones((batch.num_rows, 1)), batch.column("x").flatten().to_numpy().reshape(batch.num_rows, -1)], axis=1)
                    for c in (0, 1):
                        own = x[batch.column("label").to_numpy() == c]
                        total[c] += own.T @ own
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat([0, 1], width * width)), pa.array(np.tile(np.arange(width * width), 2)), pa.array(total.ravel())], ["label", "k", "v"])

        sums = statistics.join(known, "doc_id").select("x", "label").mapInArrow(lean(moments), "label long, k long, v double").groupBy("label", "k").agg(F.sum("v").alias("v")).collect()
        m = np.zeros((2, width, width))
        for r in sums:
            m[r.label].flat[r.k] = r.v
        n = m[:, 0, 0]
        if not n.sum():
            return Quality(self.to_pooled, self.to_diagonal, self.threshold, -30.0)
        prior = float(np.clip(np.log(np.maximum(n[1], 1e-9) / np.maximum(n[0], 1e-9)), -30, 30))
        if n.min() == 0:
            return Quality(self.to_pooled, self.to_diagonal, self.threshold, prior)
        mean = m[:, 0, 1:] / n[:, None]
        cov = np.stack([m[c, 1:, 1:] / n[c] - np.outer(mean[c], mean[c]) for c in (0, 1)])
        pooled = (cov * n[:, None, None]).sum(axis=0) / n.sum()
        factor, logdet = [], []
        for c in (0, 1):
            # few rows of a class lean more on the pooled covariance
            share = max(self.to_pooled, min(1.0, FEATURES / n[c]))
            s = (1 - share) * cov[c] + share * pooled
            s = (1 - self.to_diagonal) * s + self.to_diagonal * np.diag(np.diag(s)) + 1e-4 * np.eye(FEATURES)
            low = np.linalg.cholesky(s)
            factor.append(np.linalg.inv(low))
            logdet.append(2 * np.log(np.diag(low)).sum())
        return Quality(self.to_pooled, self.to_diagonal, self.threshold, prior, mean, np.stack(factor), np.array(logdet))

    def score_rows(self, x: np.ndarray) -> np.ndarray:
        odds = np.full(len(x), self.prior)
        if self.mean is not None:
            density = [-0.5 * (np.square((x - self.mean[c]) @ self.factor[c].T).sum(axis=1) + self.logdet[c]) for c in (0, 1)]
            odds += density[1] - density[0]
        return 1 / (1 + np.exp(-np.clip(odds, -30, 30)))

    def predict(self, statistics: DataFrame) -> DataFrame:
        """(doc_id, score, predicted) for every row of statistics()."""
        model = statistics.sparkSession.sparkContext.broadcast(self)

        def run(batches):
            own = model.value
            for batch in batches:
                if batch.num_rows:
                    score = own.score_rows(batch.column("x").flatten().to_numpy().reshape(batch.num_rows, -1).astype(float))
                    yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(score), pa.array((score >= own.threshold).astype(np.int32))], ["doc_id", "score", "predicted"])

        return statistics.mapInArrow(lean(run), "doc_id long, score double, predicted int")

    def fit_predict(self, docs: DataFrame, labels: DataFrame, learn: Column) -> tuple[Quality, DataFrame]:
        """The model and the scores of all rows; texts are read once."""
        x = checkpointed(self.statistics(docs))
        model = self.fit(x, labels, learn)
        return model, model.predict(x)

"""Toxicity by FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

Features of a text are the distinct hashes of its words, word pairs, and pairs with one word left out between them (words: runs of
letters and digits, A-Z in lower case). FTRL-proximal keeps a rate for each coordinate and sets coordinates whose
gradient sum stays within the L1 radius to exactly 0, so the model that is broadcast is a short list of (coordinate, weight).

Learning takes a bounded sample of labelled rows (`per_class` of each label, chosen by a hash of the id). Scoring runs
over whole texts of all rows.

Defined results: empty and null texts get the score of the intercept alone; with labels of one class only or none, the score is
that class's share (0 with none). Repeated rows count each; labels that repeat a doc_id count once (the largest).
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from retro.llm import vector_text as vt
from retro.llm.runtime import filtered, id_and_text, lean

_WORD = np.ones(256, dtype=bool)
_WORD[:128] = False
_WORD[48:58] = _WORD[65:91] = _WORD[97:123] = True


def features_of(data: np.ndarray, offsets: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, coordinate) of every n-gram of a block, repeats included."""
    start, end, at = vt.spans_of(_WORD[data], offsets)
    code = vt.span_codes(vt.lowered(data), start, end)
    row = np.repeat(np.arange(len(at) - 1), np.diff(at))
    rows, codes = [row], [code]
    for gap in (1, 2):
        if len(code) > gap:
            same = row[gap:] == row[:-gap]
            codes.append(vt.mix64(code[:-gap] * np.uint64(2 * gap + 1) + code[gap:] + np.uint64(gap))[same])
            rows.append(row[gap:][same])
    return np.concatenate(rows), (np.concatenate(codes) >> np.uint64(64 - bits)).astype(np.int64)


@dataclass(frozen=True)
class Toxicity:
    bits: int = 22
    alpha: float = 1.0
    beta: float = 1.0
    l1: float = 6.0
    l2: float = 0.01
    passes: int = 6
    #: Labelled rows of each class that are learned from, about.
    per_class: int = 4000
    threshold: float = 0.7
    intercept: float = -30.0
    at: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64), repr=False)
    weight: np.ndarray = field(default_factory=lambda: np.zeros(0), repr=False)

    def settings(self) -> dict:
        return {k: getattr(self, k) for k in ("bits", "alpha", "beta", "l1", "l2", "passes", "per_class", "threshold")}

    def fit(self, docs: DataFrame, labels: DataFrame, learn: Column) -> Toxicity:
        """labels: doc_id, label (0 or 1). learn: a condition on doc_id."""
        known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("label").cast("int").alias("label")).where(learn & F.col("doc_id").isNotNull() & F.col("label").isin(0, 1)).groupBy("doc_id").agg(F.max("label").alias("label"))
        number = {r.label: r.n for r in known.groupBy("label").agg(F.count("*").alias("n")).collect()}
        total = sum(number.values())
        if len(number) < 2:
            share = 1 - 1e-12 if 1 in number else 1e-13
            return Toxicity(**self.settings(), intercept=float(np.log(share / (1 - share))))
        part = F.when(F.col("label") == 1, min(1.0, self.per_class / number[1])).otherwise(min(1.0, self.per_class / number[0]))
        drawn = known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < part * (1 << 20))
        bits = self.bits

        def features(batches):
            for batch in batches:
                for first, last, data, offsets in vt.blocks(batch.column("text")):
                    row, at = features_of(data, offsets, bits)
                    key = np.unique((row.astype(np.int64) << bits) | at)
                    ends = np.searchsorted(key, np.arange(1, last - first + 1) << bits)
                    key = (key & ((1 << bits) - 1)).astype(np.int32)
                    packed = [key[a:b].tobytes() for a, b in zip([0, *ends[:-1]], ends, strict=True)]
                    piece = batch.slice(first, last - first)
                    yield pa.RecordBatch.from_arrays([piece.column("doc_id"), piece.column("label"), pa.array(packed, pa.binary())], ["doc_id", "label", "x"])

        # the sample is bounded by per_class, so it may be broadcast
        rows = id_and_text(docs).join(F.broadcast(drawn), "doc_id").select("doc_id", "text", "label").mapInArrow(lean(features), "doc_id long, label int, x binary").toArrow()
        label = rows.column("label").to_numpy().astype(float)
        order = np.argsort(vt.mix64(rows.column("doc_id").to_numpy().astype(np.uint64)), kind="stable")
        packed = rows.column("x")
        rows_of = {int(v): max(1, int((label == v).sum())) for v in (0, 1)}
        part = {v: number[v] / total * len(label) / rows_of[v] for v in (0, 1)}
        z, n = np.zeros(1 << bits), np.zeros(1 << bits)
        z0 = n0 = 0.0
        for turn in range(self.passes):
            for k in order if turn % 2 == 0 else order[::-1]:
                at = np.frombuffer(packed[int(k)].as_py(), np.int32)
                zi, ni = z[at], n[at]
                w = np.where(np.abs(zi) <= self.l1, 0.0, -(zi - np.sign(zi) * self.l1) / ((self.beta + np.sqrt(ni)) / self.alpha + self.l2))
                w0 = -z0 / ((self.beta + np.sqrt(n0)) / self.alpha)
                g = (1 / (1 + np.exp(-np.clip(w0 + w.sum(), -30, 30))) - label[k]) * part[int(label[k])]
                step = (np.sqrt(ni + g * g) - np.sqrt(ni)) / self.alpha
                z[at] = zi + g - step * w
                n[at] = ni + g * g
                z0 += g - (np.sqrt(n0 + g * g) - np.sqrt(n0)) / self.alpha * w0
                n0 += g * g
        w = np.where(np.abs(z) <= self.l1, 0.0, -(z - np.sign(z) * self.l1) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2))
        at = np.flatnonzero(w)
        return Toxicity(**self.settings(), intercept=float(-z0 / ((self.beta + np.sqrt(n0)) / self.alpha)), at=at, weight=w[at])

    def dense(self) -> np.ndarray:
        out = np.zeros(1 << self.bits, dtype=np.float32)
        out[self.at] = self.weight
        return out

    def score_block(self, data: np.ndarray, offsets: np.ndarray, dense: np.ndarray) -> np.ndarray:
        row, at = features_of(data, offsets, self.bits)
        some = dense[at] != 0
        key = np.unique((row[some].astype(np.int64) << self.bits) | at[some])
        total = np.bincount(key >> self.bits, weights=dense[key & ((1 << self.bits) - 1)], minlength=len(offsets) - 1)
        return 1 / (1 + np.exp(-np.clip(total + self.intercept, -30, 30)))

    def predict(self, docs: DataFrame) -> DataFrame:
        """(doc_id, score, predicted) for every row."""
        model = docs.sparkSession.sparkContext.broadcast(self)
        kept: dict = {}

        def run(batches):
            own = model.value
            dense = kept.setdefault("dense", own.dense())
            for batch in batches:
                for first, last, data, offsets in vt.blocks(batch.column("text")):
                    score = own.score_block(data, offsets, dense)
                    yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(first, last - first), pa.array(score), pa.array((score >= own.threshold).astype(np.int32))], ["doc_id", "score", "predicted"])

        return id_and_text(docs).mapInArrow(lean(run), "doc_id long, score double, predicted int")

    def accepted(self, docs: DataFrame) -> DataFrame:
        """The rows of docs, with all columns, whose text is not predicted to be toxic."""
        model = docs.sparkSession.sparkContext.broadcast(self)

        def keep():
            own = model.value
            dense = own.dense()
            return lambda text: np.concatenate([np.zeros(0, dtype=bool), *(own.score_block(data, offsets, dense) < own.threshold for _, _, data, offsets in vt.blocks(text))])

        return filtered(docs, keep)

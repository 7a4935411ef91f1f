"""Language identification by nearest centroid.

A text's vector is its hashed counts of byte n-grams (1 to 3 bytes, A-Z in lower case), with 1 + log(count) weights, inverse
document frequencies and unit length. Each language has several centroids (spherical k-means of its learning vectors); the
prediction is the language of the centroid with the largest cosine. A text is rejected when its cosine distance to
that centroid exceeds the language's limit: a high quantile of the learning texts' distances, widened by a margin.

Learning uses a bounded sample: about `per_language` labelled rows with a letter of each language, chosen by a hash of the id. Texts beyond the
quantile are taken for junk: groups of so few texts, and single texts, keep no centroid of their own while there are larger groups. Scoring runs over whole texts of all rows.

Defined results: a null text or a text without a letter is `und` with score 0 and rejected; with nothing to learn from, every
text is. Ties go to the smaller language name. Repeated rows are scored each; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from retro.llm import vector_text as vt
from retro.llm.runtime import filtered, id_and_text, lean

#: The part of a language's learning texts that sets its limit and has centroids.
QUANTILE = 0.995
OUT = "doc_id long, lang_pred string, score double, rejected boolean"


def has_letter(text: pa.Array) -> np.ndarray:
    return pc.fill_null(pc.match_substring_regex(text, r"\p{L}"), False).to_numpy(zero_copy_only=False)


@dataclass(frozen=True)
class LanguageId:
    dimensions: int = 4096
    centroids: int = 6
    #: Labelled rows of each language that are learned from, about.
    per_language: int = 600
    #: Widening of the learning distances' quantile, as a part of what is left up to 1.
    margin: float = 0.5
    names: tuple[str, ...] = ()
    idf: np.ndarray | None = field(default=None, repr=False)
    centre: np.ndarray | None = field(default=None, repr=False)
    owner: np.ndarray | None = field(default=None, repr=False)
    limit: np.ndarray | None = field(default=None, repr=False)

    def counts(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Weighted n-gram counts, one row for each text of a block."""
        rows, dim, low = len(offsets) - 1, self.dimensions, vt.lowered(data).astype(np.uint32)
        row = np.repeat(np.arange(rows, dtype=np.int64) * dim, np.diff(offsets))
        out = np.zeros(rows * dim, dtype=np.float32)
        left = np.repeat(offsets[1:], np.diff(offsets)) - np.arange(len(low))
        gram = np.zeros(len(low), dtype=np.uint32)
        for width in (1, 2, 3):
            gram[: len(low) - width + 1] = gram[: len(low) - width + 1] * np.uint32(0x01000193) + low[width - 1 :] + np.uint32(width)
            whole = left >= width
            at = ((gram[whole] * np.uint32(0x9E3779B1)) >> np.uint32(12)) % np.uint32(dim)
            out += np.bincount(row[whole] + at, minlength=rows * dim).astype(np.float32)
        out = out.reshape(rows, dim)
        return np.log1p(out)

    def vectors(self, counts: np.ndarray) -> np.ndarray:
        x = counts * self.idf
        return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)

    def fit(self, docs: DataFrame, learn: Column) -> LanguageId:
        """docs: doc_id, text, lang. learn: which rows may be learned from."""
        known = docs.where(learn & F.col("lang").isNotNull() & F.coalesce(F.col("text").cast("string").rlike(r"\p{L}"), F.lit(False))).select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.col("lang").cast("string").alias("lang"))
        share = known.groupBy("lang").agg(F.least(F.lit(1.0), F.lit(1.2 * self.per_language) / F.count("*")).alias("share"))
        drawn = known.join(F.broadcast(share), "lang").where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < F.col("share") * (1 << 20))
        plain = LanguageId(self.dimensions)

        def features(batches):
            for batch in batches:
                for first, last, data, offsets in vt.blocks(batch.column("text")):
                    x = plain.counts(data, offsets).astype(np.float16)
                    part = batch.slice(first, last - first)
                    yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("lang"), pa.array([r.tobytes() for r in x], pa.binary())], ["doc_id", "lang", "x"])

        rows = drawn.select("doc_id", "text", "lang").mapInArrow(lean(features), "doc_id long, lang string, x binary").toArrow()
        order = np.argsort(vt.mix64(rows.column("doc_id").to_numpy().astype(np.uint64)), kind="stable")
        langs = np.array(rows.column("lang").to_pylist(), dtype=object)
        x = np.stack([np.frombuffer(b, np.float16) for b in rows.column("x").to_pylist()]).astype(np.float32) if len(order) else np.zeros((0, self.dimensions), np.float32)
        names = tuple(sorted(set(langs)))
        if not names:
            return LanguageId(self.dimensions, self.centroids, self.per_language, self.margin)
        idf = np.log1p(len(x) / (1.0 + (x > 0).sum(axis=0))).astype(np.float32)
        model = LanguageId(self.dimensions, self.centroids, self.per_language, self.margin, names, idf)
        centre, owner, limit = [], [], []
        for i, name in enumerate(names):
            own = model.vectors(x[[k for k in order if langs[k] == name][: self.per_language]])
            found = self._cluster(own)
            centre.append(found)
            owner += [i] * len(found)
            far = float(np.quantile(1 - (own @ found.T).max(axis=1), QUANTILE, method="lower"))
            limit.append(far + self.margin * (1 - far))
        return LanguageId(self.dimensions, self.centroids, self.per_language, self.margin, names, idf, np.concatenate(centre), np.array(owner), np.array(limit))

    def _cluster(self, x: np.ndarray) -> np.ndarray:
        """Spherical k-means, seeded by farthest points from the mean direction."""
        unit = lambda v: v / np.maximum(np.linalg.norm(v, axis=-1, keepdims=True), 1e-12)
        centre = [unit(x.mean(axis=0))]
        near = x @ centre[0]
        while len(centre) < min(self.centroids, len(x)):
            centre.append(x[int(np.argmin(near))])
            near = np.maximum(near, x @ centre[-1])
        c = np.stack(centre)
        for _ in range(12):
            at = np.argmax(x @ c.T, axis=1)
            c = np.stack([unit(x[at == k].mean(axis=0)) if (at == k).any() else c[k] for k in range(len(c))])
        size = np.bincount(np.argmax(x @ c.T, axis=1), minlength=len(c))
        large = size > max(1, (1 - QUANTILE) * len(x))
        return c[large] if large.any() else c

    def score_block(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Language index, cosine and whether the distance exceeds the language's limit."""
        near = np.empty((len(offsets) - 1, len(self.owner)), dtype=np.float32)
        step = max(1, (8 << 20) // self.dimensions)
        for a in range(0, len(near), step):
            b = min(len(near), a + step)
            near[a:b] = self.vectors(self.counts(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])) @ self.centre.T
        best = np.argmax(near, axis=1)
        score = np.clip(near[np.arange(len(near)), best].astype(np.float64), 0.0, 1.0)
        lang = self.owner[best]
        return lang, score, 1 - score > self.limit[lang]

    def predict(self, docs: DataFrame) -> DataFrame:
        """(doc_id, lang_pred, score, rejected) for every row."""
        spark = docs.sparkSession
        model = spark.sparkContext.broadcast(self)

        def run(batches):
            own = model.value
            for batch in batches:
                text = batch.column("text")
                lettered = has_letter(text)
                for first, last, data, offsets in vt.blocks(text):
                    if own.names:
                        lang, score, far = own.score_block(data, offsets)
                    else:
                        lang, score, far = (np.zeros(last - first, dtype=t) for t in (np.int64, np.float64, bool))
                    ok = lettered[first:last] & bool(own.names)
                    pred = [own.names[k] if o else "und" for k, o in zip(lang.tolist(), ok.tolist(), strict=True)]
                    yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(first, last - first), pa.array(pred, pa.string()), pa.array(np.where(ok, score, 0.0)), pa.array(far | ~ok)], ["doc_id", "lang_pred", "score", "rejected"])

        return id_and_text(docs).mapInArrow(lean(run), OUT)

    def accepted(self, docs: DataFrame) -> DataFrame:
        """The rows of docs, with all columns, that are not rejected."""
        model = docs.sparkSession.sparkContext.broadcast(self)

        def keep():
            own = model.value

            def test(text):
                ok = has_letter(text) & bool(own.names)
                for first, last, data, offsets in vt.blocks(text) if own.names else ():
                    ok[first:last] &= ~own.score_block(data, offsets)[2]
                return ok

            return test

        return filtered(docs, keep)

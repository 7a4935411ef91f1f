"""Vector best-fit packing of token pieces into sequences.

A bin has three capacities: tokens, documents and attention cost (sum of squared lengths). Pieces go in by falling length, each into the
bin, of those that hold it under every capacity, that scores best: the smallest weighted norm of the residual that is left
(`norm`), or the largest weighted dot product of the piece and the residual (`dot`).

A piece's three demands follow from its length, so pieces of one length are interchangeable and bins with one residual are too.
Best fit therefore runs on counts: the histogram of lengths (at most `capacity` numbers, whatever the corpus) goes to the
driver, which places whole groups of equal pieces into whole groups of equal bins and returns a short list of runs (length, ranks
from-to -> bins from-to, offset). Executors number the pieces of each length (a count within each partition plus the
counts of the partitions before) and look their run up. The result is the global best fit, and no task sees more than its own rows.

Defined results: null and empty texts are one piece that holds the end id; longer documents are cut so that all pieces but the first
have `capacity` tokens; repeated rows are packed each; an empty table gives no piece.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from retro.llm.bpe import Bpe, ByteBpe, loaded, runs
from retro.llm.runtime import checkpointed, id_and_text, lean


@dataclass(frozen=True)
class VectorBestFit:
    capacity: int = 1024
    #: Most documents and attention cost of a bin; None: what `capacity` tokens can reach, which binds nothing.
    documents: int | None = None
    attention: int | None = None
    score: str = "norm"
    weights: tuple[float, float, float] = (1.0, 1e-6, 1e-6)

    def runs(self, histogram: dict[int, int]) -> list[tuple[int, int, int, int, int, int]]:
        """(length, first rank, end rank, first bin, pieces of a bin, offset): rank r goes to bin first + (r - first rank) // pieces,
        at offset + length * ((r - first rank) % pieces)."""
        cap = np.array([self.capacity, self.documents or self.capacity, self.attention or self.capacity**2], dtype=float)
        scale = np.array(self.weights) / cap**2
        out = []
        #: Groups of equal bins: residual (tokens, documents, attention) -> list of (first bin, bins).
        groups: dict[tuple[int, int, int], list[tuple[int, int]]] = {}
        bins = 0
        for length in sorted(histogram, reverse=True):
            left, rank = histogram[length], 0
            need = np.array([length, 1, length * length])
            if (need > cap).any():
                raise ValueError(f"a piece of {length} tokens fits no bin")
            while left and groups:
                state = np.array(list(groups))
                fits = np.flatnonzero((state >= need).all(axis=1))
                if not len(fits):
                    break
                if self.score == "dot":
                    value = -(state[fits] * need * scale).sum(axis=1)
                else:
                    value = (np.square(state[fits] - need) * scale).sum(axis=1)
                at = tuple(state[fits[int(np.argmin(value))]].tolist())
                first, n = groups[at].pop()
                if not groups[at]:
                    del groups[at]
                used = min(n, left)
                out.append((length, rank, rank + used, first, 1, self.capacity - at[0]))
                groups.setdefault(tuple(int(a - b) for a, b in zip(at, need, strict=True)), []).append((first, used))
                if used < n:
                    groups.setdefault(at, []).append((first + used, n - used))
                left, rank = left - used, rank + used
            if left:
                # new bins, each filled with this length as far as it goes: what best fit does with equal pieces
                most = int(min(cap // need))
                full, rest = divmod(left, most)
                for n, each in ((full, most), (1 if rest else 0, rest)):
                    if n:
                        out.append((length, rank, rank + n * each, bins, each, 0))
                        groups.setdefault(tuple(int(c - each * x) for c, x in zip(cap, need, strict=True)), []).append((bins, n))
                        bins, rank = bins + n, rank + n * each
        return out

    def pieces(self, docs: DataFrame, tokenizer: str, end_id: int, kind: type[Bpe] = ByteBpe) -> DataFrame:
        """(doc_id, piece, start, length, ids_crc32, part, rank): rank numbers the pieces of a length within a partition."""
        source = docs.sparkSession.sparkContext.broadcast(Path(tokenizer).read_text(encoding="utf-8"))
        cap, end = self.capacity, np.array([end_id], dtype="<u4").tobytes()

        def run(batches):
            from pyspark import TaskContext

            coder, part, seen = loaded(kind, source.value), TaskContext.get().partitionId(), np.zeros(cap + 1, np.int64)
            for batch in batches:
                ids, texts = batch.column("doc_id").to_pylist(), batch.column("text").to_pylist()
                for a, b in runs(texts):
                    rows = []
                    for doc, got in zip(ids[a:b], coder.encode(texts[a:b]), strict=True):
                        got += end
                        n = len(got) // 4
                        start, size, piece = 0, n % cap or cap, 0
                        while start < n:
                            rows.append((doc, piece, start, size, zlib.crc32(got[4 * start : 4 * (start + size)])))
                            start, size, piece = start + size, cap, piece + 1
                    length = np.array([r[3] for r in rows])
                    order = np.argsort(length, kind="stable")
                    first = np.searchsorted(length[order], length[order])
                    rank = np.empty(len(rows), np.int64)
                    rank[order] = np.arange(len(rows)) - first + seen[length[order]]
                    seen += np.bincount(length, minlength=cap + 1)
                    cols = [pa.array([r[k] for r in rows], t) for k, t in enumerate((pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()))]
                    yield pa.RecordBatch.from_arrays([*cols, pa.array(np.full(len(rows), part, np.int32)), pa.array(rank)], ["doc_id", "piece", "start", "length", "ids_crc32", "part", "rank"])

        return id_and_text(docs).mapInArrow(lean(run), "doc_id long, piece int, start long, length long, ids_crc32 long, part int, rank long")

    def place(self, pieces: DataFrame) -> DataFrame:
        """pieces (as from pieces(), stable on every read) with sequence_id and offset."""
        counts = checkpointed(pieces.groupBy("part", "length").agg(F.count("*").alias("n")))
        histogram = {r.length: r.n for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}
        found = np.array(self.runs(histogram), dtype=np.int64).reshape(-1, 6)
        order = np.lexsort((found[:, 1], found[:, 0]))
        table = pieces.sparkSession.sparkContext.broadcast(found[order])
        before = counts.select("part", "length", (F.sum("n").over(Window.partitionBy("length").orderBy("part")) - F.col("n")).alias("before"))
        ranked = pieces.join(before, ["part", "length"]).withColumn("rank", F.col("rank") + F.col("before")).drop("before", "part")

        def run(batches):
            t = table.value
            key = t[:, 0] * (1 << 44) + t[:, 1] if len(t) else np.zeros(0, np.int64)
            for batch in batches:
                if batch.num_rows:
                    length, rank = batch.column("length").to_numpy(), batch.column("rank").to_numpy()
                    at = np.searchsorted(key, length * (1 << 44) + rank, side="right") - 1
                    bin_, slot = np.divmod(rank - t[at, 1], t[at, 4])
                    keep = ["doc_id", "piece", "start", "length", "ids_crc32"]
                    yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in keep), pa.array(t[at, 3] + bin_), pa.array(t[at, 5] + slot * length)], [*keep, "sequence_id", "offset"])

        return ranked.mapInArrow(lean(run), "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")

    def pack(self, docs: DataFrame, tokenizer: str, end_id: int, kind: type[Bpe] = ByteBpe) -> DataFrame:
        """(doc_id, piece, start, length, ids_crc32, sequence_id, offset) for every piece of every document."""
        return self.place(checkpointed(self.pieces(docs, tokenizer, end_id, kind)))

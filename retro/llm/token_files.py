"""Token files with fixed-width bit packing.

A file is a row of segments, each followed by one newline byte. A segment has a header of seven little-endian unsigned 64-bit numbers
(magic, bytes of the segment, bits of an id, ids of a block, number of documents, number of ids, position of the segment), then
for each document its id (signed 64-bit), its source row's length in ids (unsigned 64-bit), then the byte offset of
each block in the payload, then the payload. A block packs its ids, least significant bit first, in the
fewest bits that hold every id of the vocabulary, and begins at a byte, so a block is read without its neighbours.

Segments are ordered by their position; documents by id across them. Spark writes and reads the files, so any
file system it knows will do.

Defined results: null and empty texts have the end id alone; rows with one doc_id stand side by side, in order of their text;
an empty table gives no segment.
"""

from __future__ import annotations

import uuid
import zlib
from dataclasses import dataclass
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from retro.llm.bpe import Bpe, WordBpe, loaded, runs
from retro.llm.runtime import checkpointed, id_and_text, lean, shared_dir

MAGIC = 0x31534B42544B5054
BLOCK = 4096
HEADER = 7


def pack(ids: np.ndarray, bits: int) -> bytes:
    if bits in (8, 16, 32):
        return ids.astype(f"<u{bits // 8}").tobytes()
    planes = ((ids.astype(np.uint64)[:, None] >> np.arange(bits, dtype=np.uint64)) & np.uint64(1)).astype(np.uint8)
    return np.packbits(planes.ravel(), bitorder="little").tobytes()


def unpack(data: bytes | np.ndarray, bits: int, n: int) -> np.ndarray:
    raw = np.frombuffer(data, np.uint8)
    if bits in (8, 16, 32):
        return raw[: n * bits // 8].view(f"<u{bits // 8}").astype(np.uint32)
    planes = np.unpackbits(raw, count=n * bits, bitorder="little").reshape(n, bits)
    return (planes.astype(np.uint32) << np.arange(bits, dtype=np.uint32)).sum(axis=1, dtype=np.uint32)


def segment(doc_ids: np.ndarray, lengths: np.ndarray, ids: np.ndarray, bits: int, position: int) -> bytes:
    parts = [pack(ids[k : k + BLOCK], bits) for k in range(0, len(ids), BLOCK)]
    offsets = np.concatenate(([0], np.cumsum([len(p) for p in parts]))).astype("<u8")[: len(parts)]
    body = doc_ids.astype("<i8").tobytes() + lengths.astype("<u8").tobytes() + offsets.tobytes() + b"".join(parts)
    return np.array([MAGIC, 8 * HEADER + len(body), bits, BLOCK, len(doc_ids), len(ids), position], dtype="<u8").tobytes() + body


class Segment:
    """A view of one segment's bytes: documents, and any range of ids."""

    def __init__(self, raw: bytes | memoryview):
        magic, _, self.bits, self.block, docs, self.n_ids, self.position = np.frombuffer(raw, "<u8", HEADER).tolist()
        if magic != MAGIC:
            raise ValueError("not a segment of packed ids")
        at = 8 * HEADER
        self.doc_ids = np.frombuffer(raw, "<i8", docs, at)
        self.lengths = np.frombuffer(raw, "<u8", docs, at + 8 * docs).astype(np.int64)
        at += 16 * docs
        n = -(-self.n_ids // self.block)
        self.offsets = np.frombuffer(raw, "<u8", n, at).astype(np.int64)
        self.payload = np.frombuffer(raw, np.uint8, -1, at + 8 * n)

    def ids(self, start: int, stop: int) -> np.ndarray:
        """Ids start to stop, of the blocks that hold them alone."""
        if start >= stop:
            return np.zeros(0, np.uint32)
        first, last = start // self.block, (stop - 1) // self.block
        out = []
        for b in range(first, last + 1):
            n = min(self.block, self.n_ids - b * self.block)
            out.append(unpack(self.payload[self.offsets[b] : self.offsets[b] + -(-n * self.bits // 8)], self.bits, n))
        return np.concatenate(out)[start - first * self.block : stop - first * self.block]


def segments_of(content: bytes):
    view, at = memoryview(content), 0
    while at + 8 * HEADER <= len(view):
        size = int(np.frombuffer(view, "<u8", 2, at)[1])
        yield Segment(view[at : at + size])
        at += size + 1


@dataclass(frozen=True)
class TokenFiles:
    tokenizer: str
    end_id: int
    kind: type[Bpe] = WordBpe
    #: Ids of a segment, about.
    segment_ids: int = 1 << 19
    #: Bytes of text that a file takes, about; the number of files follows the table.
    file_bytes: int = 16 << 20

    def bits(self) -> int:
        return max(1, (self.kind(Path(self.tokenizer).read_text(encoding="utf-8")).size - 1).bit_length())

    def write(self, docs: DataFrame, path: str) -> None:
        source = docs.sparkSession.sparkContext.broadcast(Path(self.tokenizer).read_text(encoding="utf-8"))
        kind, end, most, bits = self.kind, self.end_id, self.segment_ids, self.bits()

        def run(batches):
            from pyspark import TaskContext

            coder, part, count = loaded(kind, source.value), TaskContext.get().partitionId(), 0
            own, size, held, ids = [], [], 0, []
            tail = np.array([end], dtype="<u4").tobytes()

            def out():
                nonlocal count, own, size, held, ids
                blob = segment(np.concatenate(own), np.concatenate(size), np.frombuffer(b"".join(ids), "<u4"), bits, (part << 32) + count)
                count, own, size, held, ids = count + 1, [], [], 0, []
                return pa.RecordBatch.from_arrays([pa.array([blob], pa.binary())], ["value"])

            for batch in batches:
                doc_id, texts = batch.column("doc_id").to_numpy(), batch.column("text").to_pylist()
                for a, b in runs(texts):
                    got = [x + tail for x in coder.encode(texts[a:b])]
                    own.append(doc_id[a:b])
                    size.append(np.array([len(x) // 4 for x in got]))
                    ids += got
                    held += int(size[-1].sum())
                    if held >= most:
                        yield out()
            if own:
                yield out()

        rows = id_and_text(docs)
        chars = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
        ordered = rows.repartitionByRange(max(1, -(-chars // self.file_bytes)), "doc_id").sortWithinPartitions("doc_id", "text")
        ordered.mapInArrow(lean(run), "value binary").select(F.col("value").cast("string")).write.mode("overwrite").text(path)

    def read(self, spark: SparkSession, path: str) -> DataFrame:
        """(position, place, doc_id, n_tokens, ids) of every document: ids as little-endian unsigned 32-bit integers."""
        return self._read(spark, path, "ids binary", lambda ids: pa.array([x.astype("<u4").tobytes() for x in ids], pa.binary()))

    def _read(self, spark: SparkSession, path: str, column: str, made) -> DataFrame:
        def run(batches):
            for batch in batches:
                for content in batch.column("content"):
                    for s in segments_of(content.as_buffer()):
                        ends = np.cumsum(s.lengths)
                        for a in range(0, len(ends), 1024):
                            b = min(len(ends), a + 1024)
                            base = int(ends[a] - s.lengths[a])
                            ids = s.ids(base, int(ends[b - 1]))
                            yield pa.RecordBatch.from_arrays(
                                [pa.array(np.full(b - a, s.position, np.int64)), pa.array(ends[a:b] - s.lengths[a:b]), pa.array(s.doc_ids[a:b]), pa.array(s.lengths[a:b]), made(np.split(ids, ends[a : b - 1] - base))],
                                ["position", "place", "doc_id", "n_tokens", column.split()[0]],
                            )

        files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("content")
        return files.mapInArrow(lean(run), f"position long, place long, doc_id long, n_tokens long, {column}")

    def digest(self, docs: DataFrame) -> DataFrame:
        """(doc_id, start, n_tokens, ids_crc32) of every document, from files that were written and read again."""
        spark = docs.sparkSession
        path = f"{shared_dir(spark)}/token-files-{uuid.uuid4().hex}"
        self.write(docs, path)
        crc = self._read(spark, path, "ids_crc32 long", lambda ids: pa.array([zlib.crc32(x.astype("<u4").tobytes()) for x in ids], pa.int64()))
        rows = checkpointed(crc)
        # a row for each segment: the running total of the segments before it
        total = rows.groupBy("position").agg(F.sum("n_tokens").alias("n"))
        before = total.select("position", (F.sum("n").over(Window.orderBy("position")) - F.col("n")).alias("before"))
        gateway = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        gateway.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(gateway, True)
        return rows.join(before, "position").select("doc_id", (F.col("before") + F.col("place")).alias("start"), "n_tokens", "ids_crc32")

"""Encoding and decoding of whole documents with a public BPE tokenizer file.

Defined results: a null or empty text has no tokens and decodes to an empty text; repeated rows are encoded each; other
columns are ignored. The tokenizer file is read by the driver and broadcast (a few MB, whatever the corpus).
"""

from __future__ import annotations

import hashlib
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from retro.llm.bpe import Bpe, WordBpe, loaded, runs
from retro.llm.runtime import id_and_text, lean


def encoded(docs: DataFrame, tokenizer: str, kind: type[Bpe] = WordBpe) -> DataFrame:
    """(doc_id, ids): ids as little-endian unsigned 32-bit integers."""
    source = docs.sparkSession.sparkContext.broadcast(Path(tokenizer).read_text(encoding="utf-8"))

    def run(batches):
        coder = loaded(kind, source.value)
        for batch in batches:
            ids, texts = batch.column("doc_id"), batch.column("text").to_pylist()
            for a, b in runs(texts):
                yield pa.RecordBatch.from_arrays([ids.slice(a, b - a), pa.array(coder.encode(texts[a:b]), pa.binary())], ["doc_id", "ids"])

    return id_and_text(docs).mapInArrow(lean(run), "doc_id long, ids binary")


def decoded(tokens: DataFrame, tokenizer: str, kind: type[Bpe] = WordBpe) -> DataFrame:
    """(doc_id, text) of the (doc_id, ids) that encoded() gives."""
    source = tokens.sparkSession.sparkContext.broadcast(Path(tokenizer).read_text(encoding="utf-8"))

    def run(batches):
        coder = loaded(kind, source.value)
        for batch in batches:
            text = [coder.decode(np.frombuffer(x, "<u4")) for x in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(text, pa.string())], ["doc_id", "text"])

    return tokens.select("doc_id", "ids").mapInArrow(lean(run), "doc_id long, text string")


def round_trip_digest(docs: DataFrame, tokenizer: str, kind: type[Bpe] = WordBpe) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of every document, encoded and decoded again in one pass."""
    source = docs.sparkSession.sparkContext.broadcast(Path(tokenizer).read_text(encoding="utf-8"))

    def run(batches):
        coder = loaded(kind, source.value)
        for batch in batches:
            ids, texts = batch.column("doc_id"), batch.column("text").to_pylist()
            for a, b in runs(texts):
                got = coder.encode(texts[a:b])
                back = [hashlib.sha256(coder.decode(np.frombuffer(x, "<u4")).encode()).hexdigest() for x in got]
                yield pa.RecordBatch.from_arrays([ids.slice(a, b - a), pa.array([len(x) // 4 for x in got], pa.int64()), pa.array([hashlib.sha256(x).hexdigest() for x in got]), pa.array(back, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return id_and_text(docs).mapInArrow(lean(run), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")

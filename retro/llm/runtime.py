"""Spark plumbing shared by the operators: checkpoints in the shared folder, group streaming, connected components."""

from __future__ import annotations

import ctypes
import functools
import gc
import tempfile
import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. Where the session names none, a temporary one in local mode; a cluster must name one."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        named = tempfile.mkdtemp(prefix="retro-checkpoint-")
        spark.sparkContext.setCheckpointDir(named)
    return spark.sparkContext.getCheckpointDir() or named


def checkpointed(df: DataFrame) -> DataFrame:
    """`df` written to the shared folder and read from there: survives lost executors, cuts the lineage."""
    spark = df.sparkSession
    where = shared_dir(spark)
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(where)
    return df.checkpoint(eager=True)


def tidy(spark: SparkSession) -> None:
    """Between rounds of an iteration: lets Spark's cleaner drop the shuffle files, checkpoints and broadcasts that nothing refers to any more."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def lean(run: Callable) -> Callable:
    """A task's function that gives freed memory back to the system twice a second and at its end: reused workers would keep it, beside those of the next stage."""

    def give_back():
        pa.default_memory_pool().release_unused()
        try:
            ctypes.CDLL(None).malloc_trim(0)
        except (OSError, AttributeError):  # not glibc
            pass

    @functools.wraps(run)
    def kept_small(batches):
        last = time.monotonic()
        try:
            for out in run(batches):
                yield out
                del out
                if time.monotonic() - last > 0.5:
                    give_back()
                    last = time.monotonic()
        finally:
            give_back()

    return kept_small


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def id_and_text(docs: DataFrame) -> DataFrame:
    """The two columns that text operators read, whatever else the table has; a null text is an empty one, a row without id no document."""
    return docs.where(F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))


def usable_vectors(rows: DataFrame, *more: str) -> DataFrame:
    """(vec_id, embedding, *more) of the rows whose vector is not null, not empty, not zero and holds finite numbers only."""
    e = F.col("embedding").cast("array<double>")
    ok = F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & F.forall(e, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(e, lambda x: x != 0)
    return rows.where(F.coalesce(ok, F.lit(False))).select(F.col("vec_id").cast("long").alias("vec_id"), e.alias("embedding"), *more)


def matrix(column: pa.Array | pa.ChunkedArray, rows: int) -> np.ndarray:
    """A list column whose lists have one length."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column.flatten().to_numpy(zero_copy_only=False).reshape(rows, -1)


def fold(doc_id: str, modulus: int):
    """crc32 of the id written as text, modulo `modulus`: the split between learning and held-out rows."""
    return F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(modulus))


def sorted_groups(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.Table]:
    """Tables that hold whole groups only, from batches sorted by `keys`; one group more than it yields is held at most."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        change = np.zeros(batch.num_rows, dtype=bool)
        for key in keys:
            values = batch.column(key).to_numpy(zero_copy_only=False)
            change[1:] |= values[1:] != values[:-1]
        if held and any(held[-1].column(k)[-1].as_py() != batch.column(k)[0].as_py() for k in keys):
            yield pa.Table.from_batches(held)
            held = []
        cuts = np.flatnonzero(change)
        if len(cuts):
            held.append(batch.slice(0, int(cuts[-1])))
            yield pa.Table.from_batches(held)
            held = [batch.slice(int(cuts[-1]))]
        else:
            held.append(batch)
    if held:
        yield pa.Table.from_batches(held)


def _roots(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Union-find over the links of one task."""
    a, b = [], []
    for batch in batches:
        a.append(batch.column("a").to_numpy())
        b.append(batch.column("b").to_numpy())
    if not a:
        return
    nodes, at = np.unique(np.concatenate(a + b), return_inverse=True)
    x, y = np.split(at, 2)
    root = np.arange(len(nodes))
    while True:
        low = np.minimum(root[x], root[y])
        new = root.copy()
        np.minimum.at(new, root[x], low)
        np.minimum.at(new, root[y], low)
        while (new[new] != new).any():
            new = new[new]
        if (new == root).all():
            break
        root = new
    yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(nodes[root])], ["node", "component"])


def components(edges: DataFrame, alone: int = 200_000) -> DataFrame:
    """(node, component) for every node of `edges` (a, b): component is the smallest node that links reach.

    More than `alone` links are contracted by joins: each node hangs its larger neighbours, then its smaller ones, on its
    smallest neighbour; minima are aggregates, so a node with very many links needs no task of its own. Up to `alone` links, a fixed bound, are
    finished by one task.
    """
    pair = lambda a, b: (F.greatest(a, b).alias("a"), F.least(a, b).alias("b"))
    now, seen = edges.select(*pair(F.col("a"), F.col("b"))).where("a <> b"), None
    if now.count() <= alone:
        return now.coalesce(1).mapInArrow(_roots, "node long, component long")
    now = checkpointed(now.distinct())
    while True:
        state = now.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if state[0] <= alone:
            return now.coalesce(1).mapInArrow(_roots, "node long, component long")
        if seen == state:
            return now.select(F.col("a").alias("node"), F.col("b").alias("component")).union(now.select("b", "b")).groupBy("node").agg(F.min("component").alias("component"))
        seen = state
        both = now.union(now.select("b", "a"))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).union(now.join(least, "a").select("a", F.col("m").alias("b"))).where("a <> b").distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").select(F.explode(F.array(F.struct("a", F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("e")).select("e.a", "e.b")
        now = checkpointed(small.where("a <> b").select(*pair(F.col("a"), F.col("b"))).distinct())


def filtered(docs: DataFrame, keep) -> DataFrame:
    """The rows of docs that `keep` accepts, all columns as they are. keep: text column (nulls as empty) -> boolean array; made once a task."""
    names = docs.columns

    def run(batches):
        test = keep()
        for batch in batches:
            yield batch.filter(pa.array(test(batch.column(names.index("text")))))

    return docs.where(F.col("doc_id").isNotNull()).mapInArrow(lean(run), docs.schema)

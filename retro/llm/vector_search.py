"""Approximate nearest neighbours by largest inner product: a hash-prefix forest.

Vectors are mapped so that inner products become angles: divided by the largest norm and completed to unit length by one
more coordinate (queries are scaled to unit length, with 0 there). Bands of similar norms do so each for itself, with trees of their own, since beside a
much larger norm the added coordinate would decide every hash. Each tree hashes them to strings of 32 sign bits and keeps
them as a sorted array, in which the vectors that share a prefix with a query are one range. A query descends in every tree to
its longest match and then ascends in all trees together, one bit at a time, until the union of the ranges holds `share` of the band's
distinct vectors and no fewer than `least` of them (a vector found in several trees counts once, and copies count as one); those candidates are
scored exactly in double precision on the original vectors.

Every vector is indexed in one shard (of about `shard` vectors, by a hash of the id, so that copies spread). The stated query set is compared with all
shards in blocks. Vectors without structure need a large `share` and many trees: for random directions in 64 dimensions the 20 nearest are hardly nearer than
the rest.

Defined results: vectors that are null, empty, zero or hold null or non-finite components take no part, as queries and as candidates; the same for
vectors of another length than most (the smaller length on a tie); repeated rows of a vec_id are one vector, the smallest; equal scores are
ordered by vec_id; with fewer candidates than k, all are returned.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from retro.llm.runtime import checkpointed, matrix, sorted_groups, usable_vectors

_ONE, _ALL = np.uint64(1), np.uint64(0xFFFFFFFF)


@dataclass(frozen=True)
class PrefixForest:
    trees: int = 64
    share: float = 0.75
    least: int = 400
    #: Bands of norms for each halving.
    bands: int = 2
    shard: int = 16_384
    query_block: int = 2048
    seed: int = 977

    def codes(self, x: np.ndarray) -> np.ndarray:
        """(rows, trees) 32-bit hash strings as numbers, first bit highest."""
        planes = np.random.default_rng(self.seed).standard_normal((x.shape[1], self.trees * 32)).astype(np.float32)
        on = (x.astype(np.float32) @ planes > 0).reshape(len(x), self.trees, 32)
        return np.packbits(on, axis=2).reshape(len(x), self.trees, 4).view(">u4")[:, :, 0].astype(np.uint64)

    def candidates(self, items: np.ndarray, queries: np.ndarray):
        """For each query the places of its candidates, from the codes of both."""
        # vectors whose strings agree in every tree are copies here: they count as one and are found together
        items, copies = np.unique(items, axis=0, return_inverse=True)
        copies, n = copies.reshape(-1), len(items)
        wanted = min(n, max(self.share * n, self.least))
        if wanted == n:
            yield from ((q, np.arange(len(copies))) for q in range(len(queries)))
            return
        order = np.argsort(items, axis=0, kind="stable")
        keys = np.take_along_axis(items, order, axis=0)
        order = np.ascontiguousarray(order.T)
        low = np.empty((33, len(queries), self.trees), dtype=np.int64)
        high = np.empty_like(low)
        for level in range(33):
            free = _ALL >> np.uint64(level)
            for t in range(self.trees):
                low[level, :, t] = np.searchsorted(keys[:, t], queries[:, t] & ~free & _ALL, side="left")
                high[level, :, t] = np.searchsorted(keys[:, t], queries[:, t] | free, side="right")
        # the longest common depth whose ranges could hold enough, were they disjoint; level 0 holds everything
        level = 32 - np.argmax(((high - low).sum(axis=2) >= wanted)[::-1], axis=0)
        for q in range(len(queries)):
            mark = np.zeros(n, dtype=bool)
            a = b = np.zeros(self.trees, dtype=np.int64)
            for depth in range(level[q], -1, -1):
                # trees take each step up one after the other, until the marked vectors are enough
                was, (a, b) = (a, b), (low[depth, q], high[depth, q])
                for t in range(self.trees):
                    if was[0][t] == was[1][t]:
                        mark[order[t, a[t] : b[t]]] = True
                    else:
                        mark[order[t, a[t] : was[0][t]]] = True
                        mark[order[t, was[1][t] : b[t]]] = True
                    if np.count_nonzero(mark) >= wanted:
                        break
                else:
                    continue
                break
            yield q, np.flatnonzero(mark[copies])

    def in_bands(self, x: np.ndarray, queries: np.ndarray):
        """Candidates of all bands of norms, each completed to the unit length of its own largest norm."""
        x = x / np.abs(x).max()
        norm = np.maximum(np.linalg.norm(x, axis=1), 2.0**-40)
        band = np.floor(self.bands * np.log2(norm.max() / norm)).astype(np.int64)
        places, parts = [np.flatnonzero(band == k) for k in np.unique(band)], []
        for own in places:
            unit = x[own] / norm[own].max()
            unit = np.concatenate([unit, np.sqrt(np.maximum(0.0, 1 - np.square(unit).sum(axis=1)))[:, None]], axis=1)
            parts.append(self.candidates(self.codes(unit), queries))
        for found in zip(*parts, strict=True):
            yield found[0][0], np.sort(np.concatenate([own[at] for own, (_, at) in zip(places, found, strict=True)]))

    def search(self, rows: DataFrame, is_query: Column, k: int) -> DataFrame:
        """(query_id, rank, vec_id, score): the k found nearest of each query row among all other rows."""
        usable = usable_vectors(rows).groupBy("vec_id").agg(F.min("embedding").alias("embedding"))
        usable = checkpointed(usable.withColumn("size", F.size("embedding")))
        sizes = usable.groupBy("size").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "size").first()
        size, n = (sizes["size"], sizes.n) if sizes else (0, 0)
        usable = usable.where(F.col("size") == size).drop("size")
        queries = usable.where(is_query)
        shards, blocks = -(-n // self.shard) or 1, -(-queries.count() // self.query_block) or 1
        to = lambda col, count: F.pmod(F.xxhash64("vec_id"), F.lit(count)).cast("int").alias(col)
        every = lambda col, count: F.explode(F.sequence(F.lit(0), F.lit(count - 1))).alias(col)
        items = usable.select("vec_id", "embedding", F.lit(0).alias("role"), to("shard", shards), every("block", blocks))
        asked = queries.select("vec_id", "embedding", F.lit(1).alias("role"), to("block", blocks), every("shard", shards))
        rows = items.unionByName(asked).repartition(shards * blocks, "shard", "block").sortWithinPartitions("shard", "block", "role", "vec_id")

        def run(batches):
            for group in sorted_groups(batches, ["shard", "block"]):
                where = group.column("shard").to_numpy().astype(np.int64) * (1 << 32) + group.column("block").to_numpy()
                ids, role, x = group.column("vec_id").to_numpy(), group.column("role").to_numpy(), matrix(group.column("embedding"), group.num_rows)
                for own in np.unique(where):
                    v, q = np.flatnonzero((where == own) & (role == 0)), np.flatnonzero((where == own) & (role == 1))
                    if not len(v) or not len(q):
                        continue
                    item, item_id, out = x[v], ids[v], []
                    asked = np.concatenate([x[q] / np.linalg.norm(x[q], axis=1, keepdims=True), np.zeros((len(q), 1))], axis=1)
                    for at, found in self.in_bands(item, self.codes(asked)):
                        found = found[item_id[found] != ids[q[at]]]
                        score = item[found] @ x[q[at]]
                        if len(found) > k:
                            near = np.flatnonzero(score >= np.partition(score, len(score) - k)[len(score) - k])
                            found, score = found[near], score[near]
                        best = np.lexsort((item_id[found], -score))[:k]
                        out.append((np.full(len(best), ids[q[at]]), item_id[found[best]], score[best]))
                    parts = [np.concatenate([o[i] for o in out]) for i in range(3)]
                    yield pa.RecordBatch.from_arrays([pa.array(p) for p in parts], ["query_id", "vec_id", "score"])

        near = rows.mapInArrow(run, "query_id long, vec_id long, score double")
        rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
        return near.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")

"""Near-duplicate vectors of one label: random-hyperplane sign hashing in several tables, exact cosines, connected components.

Equal vectors are one class with a weight, so copies never multiply. Each class is hashed by the signs of random projections into
`tables` codes of `bits` bits; both follow from the row count and the miss that is allowed for a pair at the threshold.
Classes that share a label and a code are compared by a matrix product in double precision. A pair is counted in the first table in which its
codes agree, so link counts are exact sums without a list of pairs; a group sends on only a spanning forest
of its links. Buckets with more than `block` classes are cut into blocks, and pairs of blocks are compared by separate tasks.

Defined results: vectors that are null, empty, zero or hold null or non-finite components, and rows with a null label, have no links and are
their own component; vectors of different lengths do not link; repeated rows of a vec_id count as one vector.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from retro.llm.runtime import checkpointed, components, lean, matrix, sorted_groups, usable_vectors


@dataclass(frozen=True)
class EmbeddingDedup:
    threshold: float = 0.98
    #: Chance to miss a pair that is just at the threshold.
    miss: float = 1e-6
    #: Classes of one label that share a code, about, were all alike.
    load: int = 48
    block: int = 2048
    seed: int = 4711

    def shape(self, rows: int) -> tuple[int, int]:
        """(bits, tables) for so many vectors."""
        bits = min(30, max(4, math.ceil(math.log2(max(1, rows / self.load)))))
        agree = 1 - math.acos(self.threshold) / math.pi
        return bits, math.ceil(math.log(self.miss) / math.log(1 - agree**bits))

    def _links(self, classes: DataFrame, kind: str, bits: int, tables: int) -> DataFrame:
        """(kind, a, b): kind 0: class a has b links of this group; kind 1: classes a and b are connected."""
        seed, least, block = self.seed, self.threshold, self.block

        def sign(batches):
            planes = {}
            for batch in batches:
                size = np.diff(batch.column("embedding").offsets.to_numpy())
                for d in np.unique(size).tolist():
                    part = batch.filter(pa.array(size == d))
                    p = planes.setdefault(d, np.random.default_rng(seed + d).standard_normal((d, tables * bits)))
                    n = part.num_rows
                    on = (matrix(part.column("embedding"), n) @ p > 0).reshape(n, tables, bits)
                    code = (on << np.arange(bits)).sum(axis=2).astype(np.int32)
                    lists = pa.FixedSizeListArray.from_arrays(pa.array(code.ravel()), tables).cast(pa.list_(pa.int32()))
                    yield pa.RecordBatch.from_arrays([part.column("cid"), part.column("label"), part.column("weight"), part.column("embedding"), lists], ["cid", "label", "weight", "embedding", "codes"])

        coded = classes.select("cid", "label", "weight", F.col("embedding").cast(f"array<{kind}>").alias("embedding")).mapInArrow(lean(sign), f"cid long, label string, weight long, embedding array<{kind}>, codes array<int>")
        spread = coded.select("cid", "label", "weight", "embedding", "codes", F.size("embedding").alias("d"), F.posexplode("codes").alias("table", "code"))
        bucket = ["label", "d", "table", "code"]
        large = coded.select("label", F.size("embedding").alias("d"), F.posexplode("codes").alias("table", "code")).groupBy(*bucket).agg(F.count("*").alias("n"))
        large = checkpointed(large.where(F.col("n") > block).select(*bucket, F.ceil(F.col("n") / block).cast("int").alias("blocks")))
        spread = spread.join(large, bucket, "left").withColumn("blocks", F.coalesce("blocks", F.lit(1)))
        spread = spread.withColumn("own", F.pmod(F.xxhash64("cid"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        key = [*bucket, "lo", "hi"]
        rows = spread.select("cid", "weight", "embedding", "codes", "own", *bucket, F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"))
        rows = rows.repartition(*key).sortWithinPartitions(*key)

        def compare(batches):
            for group in sorted_groups(batches, key):
                n = group.num_rows
                cols = {k: group.column(k).to_numpy() for k in ("cid", "weight", "own", "table", "code", "lo", "hi", "d")}
                label = np.unique(np.array(group.column("label").to_pylist(), dtype=object), return_inverse=True)[1]
                change = np.zeros(n, dtype=bool)
                change[0] = True
                for k in (label, *(cols[k] for k in ("table", "code", "lo", "hi", "d"))):
                    change[1:] |= k[1:] != k[:-1]
                start = np.flatnonzero(change)
                end = np.append(start[1:], n)
                embedding, codes = group.column("embedding").combine_chunks(), group.column("codes").combine_chunks()
                counted, joined = [], []
                for a, b in zip(start.tolist(), end.tolist(), strict=True):
                    if b - a < 2:
                        continue
                    x = matrix(embedding.slice(a, b - a), b - a).astype(np.float64)
                    x = x / np.linalg.norm(x, axis=1, keepdims=True)
                    near = x @ x.T >= least
                    if cols["lo"][a] != cols["hi"][a]:
                        near &= cols["own"][a:b, None] != cols["own"][None, a:b]
                    i, j = np.nonzero(np.triu(near, 1))
                    if not len(i):
                        continue
                    c, w, table = cols["cid"][a:b], cols["weight"][a:b], int(cols["table"][a])
                    code = matrix(codes.slice(a, b - a), b - a)
                    first = np.zeros(len(i), dtype=bool)
                    for k in range(0, len(i), 1 << 16):
                        p, q = i[k : k + (1 << 16)], j[k : k + (1 << 16)]
                        first[k : k + (1 << 16)] = ~(code[p, :table] == code[q, :table]).any(axis=1)
                    links = np.bincount(i[first], weights=w[j[first]], minlength=b - a) + np.bincount(j[first], weights=w[i[first]], minlength=b - a)
                    some = np.flatnonzero(links)
                    counted.append(np.stack([c[some], links[some].astype(np.int64)]))
                    root = np.arange(b - a)
                    while True:
                        least_root = root.copy()
                        np.minimum.at(least_root, i, root[j])
                        np.minimum.at(least_root, j, root[i])
                        if (least_root == root).all():
                            break
                        root = least_root
                    some = np.flatnonzero(root != np.arange(b - a))
                    joined.append(np.stack([c[some], c[root[some]]]))
                for what, found in ((0, counted), (1, joined)):
                    if found:
                        ab = np.concatenate(found, axis=1)
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(ab.shape[1], what, np.int32)), pa.array(ab[0]), pa.array(ab[1])], ["kind", "a", "b"])

        return rows.mapInArrow(lean(compare), "kind int, a long, b long")

    def dedup(self, rows: DataFrame) -> DataFrame:
        """(vec_id, n_links, component_id, kept) for every row of rows (vec_id, embedding, label)."""
        usable = usable_vectors(rows, F.col("label").cast("string").alias("label")).where("label is not null")
        classes = checkpointed(usable.distinct().groupBy("label", "embedding").agg(F.min("vec_id").alias("cid"), F.count("*").alias("weight")))
        # vectors stored as floats travel as floats, which is exact
        kind = "float" if rows.schema["embedding"].dataType.simpleString() == "array<float>" else "double"
        found = checkpointed(self._links(classes, kind, *self.shape(classes.count())))
        links = found.where("kind = 0").groupBy(F.col("a").alias("cid")).agg(F.sum("b").alias("links"))
        parts = components(found.where("kind = 1").select("a", "b")).withColumnRenamed("node", "cid")
        classes = classes.join(links, "cid", "left").join(parts, "cid", "left")
        classes = classes.select("label", "embedding", (F.col("weight") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("component", "cid").alias("component_id"))
        of = usable.distinct().join(classes, ["label", "embedding"]).groupBy("vec_id").agg(F.max("n_links").alias("n_links"), F.min("component_id").alias("component_id"))
        ids = rows.where("vec_id is not null").select(F.col("vec_id").cast("long").alias("vec_id"))
        out = ids.join(of, "vec_id", "left")
        component = F.coalesce("component_id", "vec_id")
        return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), (component == F.col("vec_id")).alias("kept"))

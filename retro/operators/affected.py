"""Which statements a retroactive operation can change: an earliest-taint fixpoint over read/write elements.

Elements are rows (idx, mode, tbl, col, key): `key` has one string for each dimension of the table's row identifier, null where any
value is meant. Instead of a graph of statement pairs, one number is kept for each cell: the least index of an affected
write. A read at n is tainted when it meets a cell whose number is below n; its statement's writes then lower the numbers
of their cells. Each round only follows the cells that were lowered, so rounds follow the hops between cells, not the length of the log.

Keys with wildcards meet by equality too: two keys agree when they agree on the dimensions that both fill, so both sides are
projected to the masks that occur on the other and joined on (table, column, masks, projected key). Elements without any filled dimension in common
meet in a table with one row for each column, which is broadcast.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from retro.sources.tables import checkpointed

CELL = ["tbl", "col", "key"]
_JOIN = ["tbl", "col", "tmask", "rmask", "at"]


def at_level(elements: DataFrame, level: str) -> DataFrame:
    """Elements seen column-wise (keys forgotten), row-wise (columns forgotten) or cell-wise."""
    if level == "column":
        return elements.withColumn("key", F.transform("key", lambda x: F.lit(None).cast("string")))
    if level == "row":
        return elements.withColumn("col", F.lit("*"))
    return elements


def _mask() -> Column:
    return F.aggregate(F.transform("key", lambda x, i: F.when(x.isNull(), 0).otherwise(F.expr("1")) * F.pow(F.lit(2), i).cast("int")), F.lit(0), lambda a, b: a + b)


def _projected(rows: DataFrame, own: str, other: str, masks: DataFrame | None = None) -> DataFrame:
    """A row for each mask that the other side has (masks: tbl, col, `other`; without them, may have), with the key cut to the dimensions in common."""
    rows = rows.withColumn(own, _mask())
    if masks is None:
        rows = rows.withColumn(other, F.explode(F.sequence(F.lit(0), F.pow(F.lit(2), F.size("key")).cast("int") - 1)))
    else:
        rows = rows.join(F.broadcast(masks), ["tbl", "col"])
    common = F.col(own).bitwiseAND(F.col(other))
    at = F.concat_ws("|", F.transform("key", lambda x, i: F.when(common.bitwiseAND(F.pow(F.lit(2), i).cast("int")) > 0, x).otherwise(F.lit(""))))
    return rows.withColumn("at", at).withColumn("free", common == 0)


def seeds(elements: DataFrame, targets: DataFrame, added: DataFrame | None = None) -> DataFrame:
    """(tbl, col, key, t): cells that the targets (idx) wrote, and those of added statements (elements whose idx is just before their place)."""
    out = elements.where("mode = 'W'").join(targets.select("idx"), "idx").select(*CELL, F.col("idx").alias("t"))
    return out if added is None else out.unionByName(added.where("mode = 'W'").select(*CELL, F.col("idx").alias("t")))


def affected(elements: DataFrame, seed: DataFrame, level: str = "cell", targets: DataFrame | None = None) -> DataFrame:
    """(idx, round) of the statements that can change, targets themselves left out."""
    rows = at_level(elements, level)
    taint = checkpointed(at_level(seed, level).groupBy(*CELL).agg(F.min("t").alias("t")))
    first = taint.agg(F.min("t")).first()[0]
    if first is None:
        return rows.select("idx", F.lit(0).alias("round")).limit(0)
    rows = rows.where(F.col("idx") > first)
    if targets is not None:
        rows = rows.join(targets.select("idx"), "idx", "left_anti")
    # one row for each mask of each column that templates use: reads of columns that nothing writes meet none and go
    masked = lambda df, mode: df.select("tbl", "col", _mask().alias("mask"), mode.alias("mode"))
    kinds = masked(rows, F.col("mode")).unionByName(masked(taint, F.lit("W"))).distinct().collect()
    of = lambda mode, name: elements.sparkSession.createDataFrame([(r.tbl, r.col, r.mask) for r in kinds if r.mode == mode], f"tbl string, col string, {name} int")
    written, read = of("W", "tmask"), of("R", "rmask")
    reads = checkpointed(_projected(rows.where("mode = 'R'"), "rmask", "tmask", written).select("idx", *_JOIN, "free"))
    writes = checkpointed(rows.where("mode = 'W'").join(F.broadcast(read.select("tbl", "col").distinct()), ["tbl", "col"], "left_semi").select("idx", *CELL))
    delta, found, turn = taint, None, 1
    while True:
        low = _projected(delta, "tmask", "rmask", read).groupBy(*_JOIN, "free").agg(F.min("t").alias("t"))
        met = [reads.where("free").join(F.broadcast(low.where("free").drop("free")), _JOIN), reads.where("not free").join(low.where("not free").drop("free"), _JOIN)]
        hit = met[0].unionByName(met[1]).where("idx > t").select("idx").distinct()
        if found is not None:
            hit = hit.join(found, "idx", "left_anti")
        hit = checkpointed(hit.withColumn("round", F.lit(turn)))
        if hit.isEmpty():
            return hit if found is None else found
        found = hit if found is None else found.unionByName(hit)
        fresh = writes.join(hit, "idx").groupBy(*CELL).agg(F.min("idx").alias("t"))
        old = taint.withColumnRenamed("t", "old")
        on = (fresh.tbl == old.tbl) & (fresh.col == old.col) & fresh.key.eqNullSafe(old.key)
        delta = checkpointed(fresh.join(old, on, "left").where("old is null or t < old").select(fresh.tbl, fresh.col, fresh.key, "t"))
        if delta.isEmpty():
            return found
        taint = checkpointed(taint.unionByName(delta).groupBy(*CELL).agg(F.min("t").alias("t")))
        turn += 1


def cell_affected(elements: DataFrame, seed: DataFrame, targets: DataFrame | None = None, combine: str = "edge") -> DataFrame:
    """`edge`: a dependency needs column and row at once. `set`: statements in the column-wise and in the row-wise closure."""
    if combine == "edge":
        return affected(elements, seed, "cell", targets)
    return affected(elements, seed, "column", targets).join(affected(elements, seed, "row", targets).select("idx"), "idx", "left_semi")


def edges(elements: DataFrame, kind: str = "dependency", level: str = "cell") -> DataFrame:
    """(src, dst) pairs, for logs small enough to look at. dependency: a later read of an earlier write. conflict: also the other two orders."""
    rows = at_level(elements, level).distinct()
    a, b = (_projected(rows, *m).select("idx", "mode", *_JOIN) for m in (("tmask", "rmask"), ("rmask", "tmask")))
    b = b.withColumnsRenamed({"idx": "dst", "mode": "mode2"})
    pairs = a.join(b, _JOIN).where("idx < dst")
    pairs = pairs.where("mode = 'W' and mode2 = 'R'") if kind == "dependency" else pairs.where("mode = 'W' or mode2 = 'W'")
    return pairs.select(F.col("idx").alias("src"), "dst").distinct()


def closure(pairs: DataFrame) -> DataFrame:
    """All (src, dst) that edges connect, semi-naively."""
    known = delta = checkpointed(pairs.select("src", "dst").distinct())
    while not delta.isEmpty():
        step = delta.join(pairs.select(F.col("src").alias("dst"), F.col("dst").alias("to")), "dst").select("src", F.col("to").alias("dst")).distinct()
        delta = checkpointed(step.join(known, ["src", "dst"], "left_anti"))
        known = checkpointed(known.unionByName(delta))
    return known


def ordered_pass(rows: list[tuple], seed: list[tuple], targets=frozenset()) -> set[int]:
    """The same fixpoint as one pass in commit order, for a log (or one bucket of it) in memory.

    rows: (idx, mode, tbl, col, key); seed: (tbl, col, key, t). Taint flows forward only, so when a statement is reached every number
    below its index is final.
    """
    by_idx: dict[int, list[tuple]] = {}
    for r in rows:
        by_idx.setdefault(r[0], []).append(r)
    waiting = sorted(seed, key=lambda s: s[3])
    masks: dict[tuple, set[int]] = {}
    taint: set[tuple] = set()

    def mask(key):
        return sum(1 << i for i, x in enumerate(key) if x is not None)

    def cut(key, m):
        return tuple(x if m >> i & 1 else None for i, x in enumerate(key))

    def lower(tbl, col, key):
        m = mask(key)
        if m not in masks.setdefault((tbl, col), set()) or (tbl, col, m, m, cut(key, m)) not in taint:
            masks[tbl, col].add(m)
            for sub in range(1 << len(key)):
                taint.add((tbl, col, m, sub & m, cut(key, sub & m)))

    out: set[int] = set()
    at = 0
    for idx in sorted(by_idx):
        while at < len(waiting) and waiting[at][3] < idx:
            lower(*waiting[at][:3])
            at += 1
        if idx in targets:
            continue
        hit = any(m == "R" and any((tbl, col, tm, tm & mask(key), cut(key, tm & mask(key))) in taint for tm in masks.get((tbl, col), ())) for _, m, tbl, col, key in by_idx[idx])
        if hit:
            out.add(idx)
            for _, m, tbl, col, key in by_idx[idx]:
                if m == "W":
                    lower(tbl, col, key)
    return out

"""Cell versions, states, three rollbacks, merging and differences.

A version is a row (idx, tbl, row_key, col, val, before): the value of a cell after statement idx, and before it. A deleted row is a
version with col null (and, from replay, one with val null for each of its cells); a state at n holds, of each row, the last value of each column since its last deletion.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

CELL = ["tbl", "row_key", "col"]


def fold(effects: DataFrame) -> DataFrame:
    """Versions of algebraic effects (op set or add), by windows over each cell: a set begins an epoch, adds run on in it."""
    cell = Window.partitionBy(*CELL).orderBy("idx")
    rows = effects.withColumn("epoch", F.sum(F.when(F.col("op") == "set", 1).otherwise(0)).over(cell))
    value = F.sum("val").over(Window.partitionBy(*CELL, "epoch").orderBy("idx"))
    rows = rows.withColumn("new", value)
    return rows.select("idx", *CELL, F.col("new").alias("val"), F.lag("new").over(cell).alias("before"))


def fold_state(effects: DataFrame) -> DataFrame:
    """(tbl, row_key, col, val) after all effects, by aggregates alone, so that a hot cell needs no task of its own."""
    last = effects.where("op = 'set'").groupBy(*CELL).agg(F.max_by("val", "idx").alias("base"), F.max("idx").alias("since"))
    rows = effects.where("op = 'add'").join(last.select(*CELL, "since"), CELL, "left").where("since is null or idx > since")
    added = rows.groupBy(*CELL).agg(F.sum("val").alias("more"))
    return last.select(*CELL, "base").join(added, CELL, "full_outer").select(*CELL, (F.coalesce("base", F.lit(0)) + F.coalesce("more", F.lit(0))).alias("val"))


def as_of(versions: DataFrame, idx: int | None = None, by: tuple[str, ...] = ()) -> DataFrame:
    """Temporal rollback: the state just before idx (None: now). by: further columns that set cells apart."""
    rows = versions if idx is None else versions.where(F.col("idx") < idx)
    gone = rows.where("col is null").groupBy(*by, "tbl", "row_key").agg(F.max("idx").alias("gone"))
    cells = rows.where("col is not null").groupBy(*by, *CELL).agg(F.max_by("val", "idx").alias("val"), F.max("idx").alias("at"))
    return cells.join(gone, [*by, "tbl", "row_key"], "left").where("val is not null and (gone is null or at > gone)").select(*by, *CELL, "val")


def replayed(state: DataFrame, versions: DataFrame) -> DataFrame:
    """A state and what later versions make of it."""
    start = state.select(F.lit(-1).cast("long").alias("idx"), *CELL, "val")
    return as_of(start.unionByName(versions.select("idx", *CELL, "val")))


def inverse(current: DataFrame, versions: DataFrame, idx: int) -> DataFrame:
    """Rollback by inverse operations: cells touched from idx on get the value before their first touch; cells without one go."""
    undo = versions.where((F.col("idx") >= idx) & F.col("col").isNotNull()).groupBy(*CELL).agg(F.min_by(F.struct("before"), "idx").alias("b"))
    out = current.join(undo, CELL, "full_outer").select(*CELL, F.when(F.col("b").isNotNull(), F.col("b.before")).otherwise(F.col("val")).alias("val"))
    return out.where("val is not null")


def from_snapshot(snapshot: DataFrame, taken_at: int, versions: DataFrame, idx: int) -> DataFrame:
    """Rollback from the state just before taken_at (at most idx) and the versions of the gap."""
    gap = versions.where((F.col("idx") >= taken_at) & (F.col("idx") < idx))
    base = snapshot.select(F.lit(taken_at - 1).cast("long").alias("idx"), *CELL, "val", F.lit(None).cast("long").alias("before"))
    return as_of(base.unionByName(gap.select("idx", *CELL, "val", "before")))


def merged(versions: DataFrame, tainted: DataFrame, fresh: DataFrame) -> DataFrame:
    """The edited history's versions: those of untainted statements (idx not in tainted) and the replayed ones."""
    return versions.join(tainted.select("idx"), "idx", "left_anti").unionByName(fresh.select(*versions.columns))


def difference(old: DataFrame, new: DataFrame) -> DataFrame:
    """(tbl, row_key, col, was, now) of the cells that differ."""
    a, b = old.withColumnRenamed("val", "was"), new.withColumnRenamed("val", "now")
    return a.join(b, CELL, "full_outer").where(~F.col("was").eqNullSafe(F.col("now"))).select(*CELL, "was", "now")


def replaced(state: DataFrame, cells: DataFrame, fresh: DataFrame) -> DataFrame:
    """state with the given cells taken from fresh; all other cells are reused."""
    return state.join(cells.select(*CELL), CELL, "left_anti").unionByName(fresh.select(*CELL, "val"))


def classify_tables(elements: DataFrame, affected: DataFrame) -> DataFrame:
    """(tbl, class): mutated when an affected statement writes it, consulted when one only reads it, else irrelevant."""
    own = elements.join(affected.select("idx", F.lit(True).alias("hit")), "idx", "left")
    wrote = F.max(F.when(F.col("hit") & (F.col("mode") == "W"), 1).otherwise(0))
    read = F.max(F.when(F.col("hit"), 1).otherwise(0))
    return own.groupBy("tbl").agg(wrote.alias("w"), read.alias("r")).select("tbl", F.when(F.col("w") == 1, "mutated").when(F.col("r") == 1, "consulted").otherwise("irrelevant").alias("class"))


def replay_set(elements: DataFrame, affected: DataFrame, first: int, mode: str = "versioned") -> DataFrame:
    """Statements to run again. versioned: the affected ones. tablewise_literal: also all writers after `first` of the tables that affected statements
    only consult. tablewise: all writers of every table undone, closed under the tables that those writers read."""
    if mode == "versioned":
        return affected.select("idx").distinct()
    later = elements.where(F.col("idx") >= first)
    if mode == "tablewise_literal":
        consulted = classify_tables(later, affected).where("class = 'consulted'").select("tbl")
        return affected.select("idx").union(later.where("mode = 'W'").join(F.broadcast(consulted), "tbl", "left_semi").select("idx")).distinct()
    # tables are few: the closure runs on (tables written, tables read) of whole statements, on the driver
    per = later.groupBy("idx").agg(F.sort_array(F.collect_set(F.when(F.col("mode") == "W", F.col("tbl")))).alias("w"), F.sort_array(F.collect_set(F.when(F.col("mode") == "R", F.col("tbl")))).alias("r"))
    kinds = [(set(x.w), set(x.r)) for x in per.select("w", "r").distinct().collect()]
    undone = {r.tbl for r in classify_tables(later, affected).where("class <> 'irrelevant'").collect()}
    while more := {t for w, r in kinds if w & undone for t in w | r} - undone:
        undone |= more
    return later.where("mode = 'W'").where(F.col("tbl").isin(sorted(undone))).select("idx").distinct()

"""Row identifiers: choice of the column, merging of renamed values, aliases."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from retro.operators.replay import components


def choose(candidates: DataFrame) -> DataFrame:
    """(tbl, col, score) of each table's best row identifier. candidates: (idx, tbl, col, value, is_key), value null where a statement does not pin col.

    score = pinned share x (1 - sum of squared value shares): many statements name a row, and no value is hot. Keys win ties.
    """
    value = candidates.where("value is not null").groupBy("tbl", "col", "value").agg(F.count("*").alias("n"))
    hot = value.groupBy("tbl", "col").agg(F.sum("n").alias("pinned"), (F.sum(F.col("n") * F.col("n")) / (F.sum("n") * F.sum("n"))).alias("hot"))
    total = candidates.groupBy("tbl", "col").agg(F.count("*").alias("n"), F.max(F.col("is_key").cast("int")).alias("key"))
    score = F.round(F.coalesce("pinned", F.lit(0)) / F.col("n") * (1 - F.coalesce("hot", F.lit(1.0))), 6)
    rows = total.join(hot, ["tbl", "col"], "left").withColumn("score", score)
    best = Window.partitionBy("tbl").orderBy(F.desc("score"), F.desc("key"), "col")
    return rows.withColumn("rank", F.row_number().over(best)).where("rank = 1").select("tbl", "col", "score")


def merge_classes(pairs: DataFrame) -> DataFrame:
    """(value, class_id): values that UPDATEs rewrote into each other are one class, named by its least value. pairs: (old, new) long."""
    values = pairs.select(F.explode(F.array("old", "new")).alias("idx")).distinct()
    return components(pairs.select(F.col("old").alias("src"), F.col("new").alias("dst")), values).select(F.col("idx").alias("value"), F.col("comp").alias("class_id"))


def learn_alias(rows: DataFrame, alias: str, ri: str) -> DataFrame:
    """(alias_val, ri_val): every row identifier that an alias value ever named. rows: inserted and updated rows of both histories."""
    return rows.select(F.col(alias).cast("string").alias("alias_val"), F.col(ri).cast("string").alias("ri_val")).where("alias_val is not null").distinct()


def apply_alias(elements: DataFrame, aliases: DataFrame) -> DataFrame:
    """Elements whose first dimension is an alias (marked by the analysis) get a row for each row identifier it names; unknown ones become wildcards."""
    marked = F.col("key")[0].startswith("\x01")
    value = F.element_at(F.split(F.col("key")[0], "\x01"), 3)
    rest = elements.where(~F.coalesce(marked, F.lit(False)))
    named = elements.where(marked).withColumn("alias_val", value).join(aliases, "alias_val", "left")
    key = F.concat(F.array(F.col("ri_val")), F.slice("key", 2, 16))
    return rest.unionByName(named.select(*[key.alias("key") if c == "key" else F.col(c) for c in elements.columns]))


def as_of_alias(aliases: DataFrame, uses: DataFrame) -> DataFrame:
    """The tighter form: the row identifier that an alias named just before each use. aliases: (alias_val, ri_val, from_idx); uses: (idx, alias_val)."""
    rows = aliases.select("alias_val", F.col("from_idx").alias("at"), "ri_val", F.lit(None).cast("long").alias("idx")).unionByName(uses.select("alias_val", F.col("idx").alias("at"), F.lit(None).cast("string").alias("ri_val"), "idx"))
    last = F.last("ri_val", ignorenulls=True).over(Window.partitionBy("alias_val").orderBy("at", F.col("idx").isNull().cast("int")))
    return rows.withColumn("named", last).where("idx is not null").select("idx", "alias_val", F.col("named").alias("ri_val"))

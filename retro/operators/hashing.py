"""Incremental table hashes and early stop.

A row's hash is SHA-256 of its canonical text; a table's hash is the sum of its rows' hashes modulo 2^256, kept as eight 32-bit limbs that are
summed without carry and normalised at the end. Inserting adds, deleting subtracts, updating does both, so a statement's change costs its own rows only, and
order does not matter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from retro.sources.tables import checkpointed

LIMBS = [f"l{k}" for k in range(8)]
_NULL = "\\N"


def row_text(*columns: str) -> Column:
    """Columns in order with a separator that cannot occur unescaped; nulls have a mark of their own."""
    parts = [F.coalesce(F.regexp_replace(F.col(c).cast("string"), r"([\\|])", r"\\$1"), F.lit(_NULL)) for c in columns]
    return F.concat_ws("|", *parts)


def row_limbs(text: Column) -> list[Column]:
    """l0 is the lowest limb."""
    hexed = F.sha2(text.cast("binary"), 256)
    return [F.conv(F.substring(hexed, 57 - 8 * k, 8), 16, 10).cast("decimal(38,0)").alias(f"l{k}") for k in range(8)]


def normalised(df: DataFrame, *keep: str) -> DataFrame:
    """Limb sums carried and reduced modulo 2^256; with the hash as 64 hex digits. Negative sums wrap, as subtraction modulo 2^256 does."""
    base = F.lit(1 << 32).cast("decimal(38,0)")
    for k in range(8):
        total = F.col(f"l{k}") if k == 0 else F.col(f"l{k}") + F.col("carry")
        df = df.withColumn("total", total.cast("decimal(38,0)")).withColumn(f"l{k}", F.pmod("total", base).cast("decimal(38,0)")).withColumn("carry", ((F.col("total") - F.col(f"l{k}")) / base).cast("decimal(38,0)"))
    digits = [F.lpad(F.lower(F.hex(F.col(f"l{k}").cast("long"))), 8, "0") for k in reversed(range(8))]
    return df.select(*keep, F.concat(*digits).alias("hash"))


def table_hash(rows: DataFrame, *columns: str, sign: str | None = None) -> DataFrame:
    """(hash, n_rows) of a table; an empty table has hash 0. sign: a column that is 1 where a statement adds the row and -1 where one takes it away."""
    way = F.col(sign) if sign else F.lit(1)
    limbs = rows.select(way.alias("way"), *row_limbs(row_text(*columns)))
    sums = limbs.agg(*[F.coalesce(F.sum(F.col(c) * F.col("way")), F.lit(0)).cast("decimal(38,0)").alias(c) for c in LIMBS], F.coalesce(F.sum("way"), F.lit(0)).cast("long").alias("n_rows"))
    return normalised(sums, "n_rows")


def change_limbs(versions: DataFrame) -> DataFrame:
    """(idx, tbl, l0..l7): what each statement adds to the hashes of its tables. A cell counts as a row (row_key, col, val)."""
    plus = versions.where("val is not null").select("idx", "tbl", *row_limbs(F.concat_ws("|", "row_key", "col", F.col("val").cast("string"))))
    minus = versions.where("before is not null").select("idx", "tbl", *row_limbs(F.concat_ws("|", "row_key", "col", F.col("before").cast("string"))))
    minus = minus.select("idx", "tbl", *[(-F.col(c)).cast("decimal(38,0)").alias(c) for c in LIMBS])
    return plus.unionByName(minus).groupBy("idx", "tbl").agg(*[F.sum(c).cast("decimal(38,0)").alias(c) for c in LIMBS])


def running(change: DataFrame) -> DataFrame:
    """(tbl, idx, l0..l7) summed up to each index, from changes (tbl, idx, bucket, l0..l7): totals of index buckets first, then within buckets."""
    totals = change.groupBy("tbl", "bucket").agg(*[F.sum(c).cast("decimal(38,0)").alias(c) for c in LIMBS])
    before = Window.partitionBy("tbl").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    base = totals.select("tbl", "bucket", *[F.coalesce(F.sum(c).over(before), F.lit(0)).cast("decimal(38,0)").alias(f"b_{c}") for c in LIMBS])
    inside = Window.partitionBy("tbl", "bucket").orderBy("idx")
    return change.join(base, ["tbl", "bucket"]).select("tbl", "idx", *[(F.sum(c).over(inside) + F.col(f"b_{c}")).cast("decimal(38,0)").alias(c) for c in LIMBS])


def hash_log(versions: DataFrame, bucket: int = 4096) -> DataFrame:
    """(tbl, idx, hash) after each statement that changes the table."""
    return normalised(running(change_limbs(versions).withColumn("bucket", F.floor(F.col("idx") / bucket))), "tbl", "idx")


def unchanged(old: DataFrame, new: DataFrame) -> bool:
    """Whether two sets of versions change the hashes of all tables alike: then tables that were equal before them are equal after."""
    minus = change_limbs(old).select("tbl", *[(-F.col(c)).cast("decimal(38,0)").alias(c) for c in LIMBS])
    sums = change_limbs(new).select("tbl", *LIMBS).unionByName(minus).groupBy("tbl").agg(*[F.sum(c).cast("decimal(38,0)").alias(c) for c in LIMBS])
    return normalised(sums, "tbl").where(F.col("hash") != "0" * 64).isEmpty()


def hash_match(old: DataFrame, new: DataFrame, last_op: int, bucket: int = 4096) -> int | None:
    """The first index after the last retroactive operation at which all touched tables are as in the original history.

    old, new: versions of the rows touched by affected statements, in both histories. Other rows contribute nothing to the
    difference and are never read. Differences run over totals of index buckets first, then within buckets, so no task sees a whole table's
    history; where a table's difference turns zero or stops being zero, the number of tables that differ changes, and a match is an index at which it is zero.
    """
    minus = change_limbs(old).select("idx", "tbl", *[(-F.col(c)).cast("decimal(38,0)").alias(c) for c in LIMBS])
    change = checkpointed(change_limbs(new).unionByName(minus).groupBy("tbl", "idx").agg(*[F.sum(c).cast("decimal(38,0)").alias(c) for c in LIMBS]).withColumn("bucket", F.floor(F.col("idx") / bucket)))
    rows = normalised(running(change), "tbl", "idx").withColumn("bucket", F.floor(F.col("idx") / bucket)).withColumn("differs", (F.col("hash") != F.lit("0" * 64)).cast("int"))
    # a table's state lasts until its next change; what matters are its turns, +1 where it begins to differ and -1 where it ends
    inside = Window.partitionBy("tbl", "bucket").orderBy("idx")
    ends = rows.groupBy("tbl", "bucket").agg(F.max_by("differs", "idx").alias("end"))
    carried = ends.select("tbl", "bucket", F.lag("end", 1, 0).over(Window.partitionBy("tbl").orderBy("bucket")).alias("carried"))
    turns = rows.join(carried, ["tbl", "bucket"]).withColumn("turn", F.col("differs") - F.coalesce(F.lag("differs").over(inside), F.col("carried")))
    steps = turns.groupBy("idx").agg(F.sum("turn").alias("turn")).withColumn("bucket", F.floor(F.col("idx") / bucket))
    totals = steps.groupBy("bucket").agg(F.sum("turn").alias("total"))
    # a row for each bucket of indices
    before = totals.select("bucket", F.coalesce(F.sum("total").over(Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    differing = steps.join(before, "bucket").withColumn("differing", F.col("before") + F.sum("turn").over(Window.partitionBy("bucket").orderBy("idx")))
    return differing.where((F.col("idx") >= last_op) & (F.col("differing") == 0)).agg(F.min("idx")).first()[0]


def literal_match(old_state: DataFrame, new_state: DataFrame) -> bool:
    """Compares the states themselves, for a match that must not rest on a hash."""
    return old_state.exceptAll(new_state).isEmpty() and new_state.exceptAll(old_state).isEmpty()


def collision_bound(bits: int = 256) -> float:
    """Chance that two different tables have one hash, for inputs that are not made to collide."""
    return 2.0**-bits

"""Scans, the commit order, checkpoints and elements of statement logs."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from retro.catalog import Catalog
from retro.operators.accesses import accesses

ELEMENT = "idx long, mode string, tbl string, col string, key array<string>"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. Where the session names none, a temporary one in local mode; a cluster must name one."""
    context = spark.sparkContext
    if not context.getCheckpointDir():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not context.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="retro-checkpoint-"))
    return context.getCheckpointDir()


def own_folder(spark: SparkSession, kind: str) -> str:
    """A new folder of this call alone, in the shared one."""
    return f"{shared_dir(spark)}/{kind}-{uuid.uuid4().hex}"


def checkpointed(df: DataFrame) -> DataFrame:
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def dense_index(rows: DataFrame, *order: str, name: str = "commit_idx") -> DataFrame:
    """Numbers rows from 1 in the given total order without one task that sees all: ranges, a count for each, offsets."""
    ranged = checkpointed(rows.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id()))
    part = F.shiftright("_at", 33)
    counts = ranged.groupBy(part.alias("_part")).agg(F.count("*").alias("_n"))
    earlier = counts.withColumnsRenamed({"_part": "_p2", "_n": "_m"})
    before = counts.join(earlier, F.col("_p2") < F.col("_part"), "left").groupBy("_part").agg(F.coalesce(F.sum("_m"), F.lit(0)).alias("_before"))
    out = ranged.withColumn("_part", part).join(F.broadcast(before), "_part")
    return out.withColumn(name, (F.col("_before") + F.col("_at").bitwiseAND((1 << 33) - 1) + 1).cast("long")).drop("_part", "_before", "_at")


def key_column(e, args: str = "args") -> Column:
    """A key expression over a call's arguments as a string column; None: any value."""
    if e is None:
        return F.lit(None).cast("string")
    if e[0] == "lit":
        return F.lit(None if e[1] is None else str(e[1])).cast("string")
    if e[0] == "var":
        return F.col(args)[e[1]]
    if e[0] == "alias":
        # resolved later against the learned alias map
        return F.concat(F.lit(f"\x01{e[1]}\x01"), key_column(e[2], args))
    a = [key_column(x, args) for x in e[2:]]
    if e[1] == "||" or e[1] == "concat":
        return F.concat(*a)
    number = [x.cast("decimal(38,0)") for x in a]
    ops = {"+": lambda x, y: x + y, "-": lambda x, y: x - y, "*": lambda x, y: x * y, "%": lambda x, y: x % y}
    return ops[e[1]](*number).cast("decimal(38,0)").cast("string") if e[1] in ops else F.lit(None).cast("string")


def elements(history: DataFrame, templates: dict[str, object], catalog: Catalog) -> DataFrame:
    """Read/write elements of every call in the history (commit_idx, template_id, args). templates: id -> parsed statement.

    Statements are analysed once for each template on the driver; the log is only projected and exploded.
    """
    chosen = None
    for name, statement in templates.items():
        rows = []
        for a in accesses(statement, catalog):
            dims = len(catalog.table(a.table).ri) if a.table in catalog.tables else 1
            for keys in a.keys or ((None,) * dims,):
                rows.append(F.struct(F.lit(a.mode).alias("mode"), F.lit(a.table).alias("tbl"), F.array(*[F.lit(c) for c in sorted(a.columns)]).alias("cols"), F.array(*[key_column(k) for k in keys]).alias("key")))
        value = F.array(*rows)
        chosen = F.when(F.col("template_id") == name, value) if chosen is None else chosen.when(F.col("template_id") == name, value)
    return history.select(F.col("commit_idx").alias("idx"), F.explode(chosen).alias("e")).select("idx", "e.mode", "e.tbl", F.explode("e.cols").alias("col"), "e.key")


def element_rows(log: list[tuple], catalog: Catalog) -> list[tuple]:
    """The same for a log in memory: (idx, statement, arguments) -> rows of ELEMENT."""
    out = []
    for idx, statement, args in log:
        for a in accesses(statement, catalog):
            dims = len(catalog.table(a.table).ri) if a.table in catalog.tables else 1
            for keys in a.keys or ((None,) * dims,):
                for c in sorted(a.columns):
                    out.append((idx, a.mode, a.table, c, [_known(k, args) for k in keys]))
    return out


def _known(e, args: dict):
    if e is None:
        return None
    if e[0] == "lit":
        return None if e[1] is None else str(e[1])
    if e[0] == "var":
        return None if args.get(e[1]) is None else str(args[e[1]])
    if e[0] == "alias":
        return f"\x01{e[1]}\x01{_known(e[2], args)}"
    from retro.functions.interpreter import Database

    return str(Database(Catalog()).value(e, args, {}))

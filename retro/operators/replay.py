"""Replay of calls whose effects depend on the database: serially, by independent components, or in waves.

Calls are rows (idx, comp, fn, args). args maps names to bigint, or to the typed text of `values` (strings, decimals, booleans, times, lists); the values of
versions have the same kind. Bodies are procedures made by the transpiler, or the application functions themselves (baselines). Replay
yields versions (comp, idx, tbl, row_key, col, val, before) in strict commit order within a component; a deleted row is a version with col
null and one with val null for each of its cells.
"""

from __future__ import annotations

import hashlib
import inspect
from collections.abc import Callable
from itertools import islice, repeat

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window
from pyspark.sql.types import StringType

from retro.app.transpile import Cells, Procedure, to_python
from retro.operators import values
from retro.sources.tables import checkpointed

VERSION = "comp long, idx long, tbl string, row_key string, col string, val {0}, before {0}"
#: The table of the rows that say where a component's replay stopped (idx), since its tables were as in the original history again.
STOPPED = "\x00stopped"


def key_text(key: tuple) -> str:
    return "|".join(_key_part(k) for k in key)


def _key_part(k) -> str:
    """Integers as they are; a string that could be mistaken for one, or holds a separator, has an apostrophe before it."""
    if not isinstance(k, str):
        return str(k)
    return "'" + k.replace("\\", "\\\\").replace("|", "\\p") if k[:1] == "'" or "|" in k or k.lstrip("-").isdigit() else k


def key_of(text: str) -> tuple:
    return tuple(x[1:].replace("\\p", "|").replace("\\\\", "\\") if x[:1] == "'" else int(x) if x.lstrip("-").isdigit() else x for x in text.split("|"))


class Body:
    """How a call runs: as one procedure call (transpiled) or as the application function, statement by statement."""

    def __init__(self, functions: dict[str, Callable], procedures: dict[str, Procedure] | None):
        self.functions, self.procedures = functions, procedures

    def prepared(self) -> dict[str, Callable]:
        if self.procedures is not None:
            return {name: to_python(p) for name, p in self.procedures.items()}
        order = {name: list(inspect.signature(f).parameters)[1:] for name, f in self.functions.items()}
        return {name: (lambda db, args, native=None, f=f, names=order[name]: f(db, *(args[k] for k in names))) for name, f in self.functions.items()}


def in_order(calls: DataFrame, base: DataFrame | None, body: Body, parallel: bool = True, parts: int | None = None, logged: DataFrame | None = None, literal: bool = False, bits: int = 256) -> DataFrame:
    """Versions of all calls. base: (comp, tbl, row_key, col, val) cells before the first call.

    parallel: components are dealt to tasks and each runs serially; rows stream in order, so a task holds one component's cells. Else one task
    runs everything (the serial baselines).

    logged: versions of the original history from the first retroactive operation on, with the index of a component's last operation in `last`. Replay of a
    component then ends at the first index from there on at which the difference of the hashes of its tables in both histories is zero, and a
    row of table STOPPED says so. literal: the cells that either history wrote are compared too before a match counts. bits: width of the hashes.

    Calls may carry `recorded`, a map of the same kind as args: values that black-box functions returned, by name; replay returns them again.
    """
    kind = calls.schema["args"].dataType.valueType
    typed = isinstance(kind, StringType)
    value, entries = kind.simpleString(), f"array<struct<key:string,value:{kind.simpleString()}>>"
    none = lambda t: F.lit(None).cast(t)
    held = F.expr("map_entries(recorded)") if "recorded" in calls.columns else none(entries)
    rows = calls.select("comp", "idx", F.lit(2).alias("kind"), "fn", F.expr("map_entries(args)").alias("args"), held.alias("recorded"), *(none(t).alias(c) for c, t in (("tbl", "string"), ("row_key", "string"), ("col", "string"), ("val", value), ("before", value), ("last", "long"))))
    empty = [none("string").alias("fn"), none(entries).alias("args"), none(entries).alias("recorded")]
    if base is not None:
        rows = rows.unionByName(base.select("comp", F.lit(-1).cast("long").alias("idx"), F.lit(0).alias("kind"), *empty, "tbl", "row_key", "col", "val", none(value).alias("before"), none("long").alias("last")))
    if logged is not None:
        rows = rows.unionByName(logged.select("comp", "idx", F.lit(1).alias("kind"), *empty, "tbl", "row_key", "col", "val", "before", "last"))
    if parallel:
        # dealt by a hash of comp, not comp itself: an exchange on comp can be dropped as redundant above a union whose inputs
        # adaptive execution then reads in other partitions
        parts = parts or int(calls.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        rows = rows.repartition(parts, F.xxhash64("comp")).sortWithinPartitions("comp", "idx", "kind")
    else:
        rows = rows.coalesce(1).sortWithinPartitions("idx", "kind")
    names = ["comp", "idx", "kind", "fn", "args", "recorded", "tbl", "row_key", "col", "val", "before", "last"]
    read = values.decode if typed else lambda x: x
    write = values.encode if typed else lambda x: x
    watch = logged is not None

    def run(batches):
        calls_of = body.prepared()
        db, at, now, world = Cells(), None, None, None
        for batch in batches:
            out = []
            for comp, idx, kind, fn, args, recorded, tbl, row_key, col, val, old, last in zip(*(_listed(batch.column(k)) for k in names), strict=True):
                if world is not None and (idx != now or comp != at) and world.matched(now):
                    out.append((at, now, STOPPED, str(at), None, None, None))
                if parallel and comp != at:
                    db, at = Cells(), comp
                    world = _Worlds(bits, literal) if watch else None
                now = idx
                if world is not None and world.done:
                    continue
                if kind == 0:
                    key = key_of(row_key)
                    db.values[tbl, key, None] = True
                    db.values[tbl, key, col] = read(val)
                    continue
                if kind == 1:
                    world.logged(tbl, row_key, col, val, old, last)
                    continue
                given = {k: read(v) for k, v in args}
                if recorded is not None:
                    drawn = {k: read(v) for k, v in recorded}
                    db.native = lambda name, *_, drawn=drawn: drawn[name]
                before = _Before(db.values)
                db.values, held = before, db.values
                db.written = []
                calls_of[fn](db, given, db.native)
                db.values = held
                for (t, k, c), x in before.old.items():
                    if c is not None:
                        out.append((comp, idx, t, key_text(k), c, write(held.get((t, k, c))), write(x)))
                    elif x and (t, k, None) not in held:
                        out.append((comp, idx, t, key_text(k), None, None, None))
                if world is not None:
                    world.ran(before.old, db.values, write)
            yield _version_rows(out, typed)
        if world is not None and world.matched(now):
            yield _version_rows([(at, now, STOPPED, str(at), None, None, None)], typed)

    return rows.mapInArrow(run, VERSION.format(value))


def _listed(column: pa.Array):
    """A column's values; entries of maps as lists of pairs, by way of flat arrays."""
    if column.null_count == len(column):
        return repeat(None, len(column))
    if not pa.types.is_list(column.type):
        return column.to_pylist()
    keys, held = column.flatten().flatten()
    pairs = zip(keys.to_pylist(), held.to_pylist(), strict=True)
    return [None if n is None else list(islice(pairs, n)) for n in column.value_lengths().to_pylist()]


def _version_rows(out: list[tuple], typed: bool) -> pa.RecordBatch:
    value = pa.string() if typed else pa.int64()
    kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), value, value)
    return pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], t) for k, t in enumerate(kinds)], ["comp", "idx", "tbl", "row_key", "col", "val", "before"])


class _Worlds:
    """The difference of the hashes of a component's tables in the new and in the original history; zero for all of them is a match."""

    def __init__(self, bits: int, literal: bool):
        self.size, self.literal, self.last, self.done = 1 << bits, literal, None, False
        self.difference: dict[str, int] = {}
        self.was: dict[tuple, object] = {}
        self.now: dict[tuple, object] = {}

    def _move(self, table: str, sign: int, key: str, column: str, value) -> None:
        if value is not None:
            h = int.from_bytes(hashlib.sha256(f"{key}|{column}|{value}".encode()).digest(), "big")
            self.difference[table] = (self.difference.get(table, 0) + sign * h) % self.size

    def logged(self, table, key, column, value, before, last) -> None:
        self.last = last
        if column is None:
            return
        self._move(table, -1, key, column, value)
        self._move(table, 1, key, column, before)
        cell = (table, key, column)
        if self.literal:
            self.now.setdefault(cell, before)
            self.was[cell] = value

    def ran(self, old: dict, values: dict, write) -> None:
        for (table, key, column), before in old.items():
            if column is not None:
                k, value = key_text(key), write(values.get((table, key, column)))
                self._move(table, 1, k, column, value)
                self._move(table, -1, k, column, write(before))
                if self.literal:
                    self.was.setdefault((table, k, column), write(before))
                    self.now[table, k, column] = value

    def matched(self, idx: int) -> bool:
        if self.done or self.last is None or idx < self.last or any(self.difference.values()):
            return False
        if self.literal and any(self.was.get(c) != v for c, v in self.now.items()):
            return False
        self.done = True
        return True


def replayer(body: Body, parallel: bool = True, parts: int | None = None, literal: bool = False, bits: int = 256) -> Callable[..., DataFrame]:
    """A function (calls, base, logged) -> versions, as what-if plans take it."""
    return lambda calls, base=None, logged=None: in_order(calls, base, body, parallel, parts, logged, literal, bits)


class _Before:
    """A view of the cells that remembers what each held before it was first set in a call."""

    def __init__(self, values: dict):
        self.values, self.old = values, {}

    def get(self, cell, default=None):
        return self.values.get(cell, default)

    def __contains__(self, cell):
        return cell in self.values

    def __iter__(self):
        return iter(self.values)

    def __setitem__(self, cell, value):
        self.old.setdefault(cell, self.values.get(cell))
        self.values[cell] = value

    def __delitem__(self, cell):
        self.old.setdefault(cell, self.values.get(cell))
        del self.values[cell]


def call_counts(calls: DataFrame, functions: dict[str, Callable]) -> dict[str, float]:
    """Database calls of one run of each function on an empty database: what a round trip count multiplies."""
    out = {}
    for name, f in functions.items():
        db = Cells()
        f(db, *[[] if p == "lines" else 1 for p in list(inspect.signature(f).parameters)[1:]])
        out[name] = db.calls
    return out


# ---- conflict graph, components, waves -------------------------------------------------------------------------------


def conflict_edges(accesses: DataFrame) -> DataFrame:
    """(src, dst) of consecutive conflicting accesses on each cell. accesses: (idx, cell, mode).

    Readers link to the write before them, a write links to the write and the readers before it: as many edges as accesses, with
    the reachability of all conflicting pairs.
    """
    per = accesses.groupBy("cell", "idx").agg(F.max(F.when(F.col("mode") == "W", 1).otherwise(0)).alias("w"), F.max(F.when(F.col("mode") == "R", 1).otherwise(0)).alias("r"))
    order = Window.partitionBy("cell").orderBy("idx")
    epoch = F.sum("w").over(order)
    rows = per.withColumn("e", epoch)  # a writer opens the epoch that it is in
    writers = rows.where("w = 1").select("cell", F.col("idx").alias("writer"), "e")
    readers = rows.where("w = 0").join(writers, ["cell", "e"]).select(F.col("writer").alias("src"), F.col("idx").alias("dst"))
    before = writers.withColumn("e", F.col("e") + 1).withColumnRenamed("writer", "src")
    chain = before.join(writers, ["cell", "e"]).select("src", F.col("writer").alias("dst"))
    closers = rows.where("w = 0").select("cell", F.col("idx").alias("src"), (F.col("e") + 1).alias("e")).join(writers, ["cell", "e"]).select("src", F.col("writer").alias("dst"))
    return readers.unionByName(chain).unionByName(closers).where("src <> dst").distinct()


def waves(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(idx, wave): the longest path that leads to each statement. Statements of one wave conflict with none of it."""
    level = checkpointed(nodes.select("idx", F.lit(0).cast("long").alias("wave")))
    edges = checkpointed(edges)
    delta = level
    while True:
        up = edges.join(delta.withColumnRenamed("idx", "src"), "src").groupBy(F.col("dst").alias("idx")).agg((F.max("wave") + 1).alias("up"))
        moved = checkpointed(level.join(up, "idx").where("up > wave").select("idx", F.col("up").alias("wave")))
        if moved.isEmpty():
            return level
        level = checkpointed(level.join(moved.withColumnRenamed("wave", "w2"), "idx", "left").select("idx", F.coalesce("w2", "wave").alias("wave")))
        delta = moved


def components(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """(idx, comp): the least statement that is connected by edges, by label propagation with pointer jumping."""
    both = checkpointed(edges.select("src", "dst").union(edges.select("dst", "src")).distinct())
    label = checkpointed(nodes.select("idx", F.col("idx").alias("comp")))
    while True:
        low = both.join(label.withColumnsRenamed({"idx": "src"}), "src").groupBy(F.col("dst").alias("idx")).agg(F.min("comp").alias("low"))
        step = label.join(low, "idx", "left").select("idx", F.col("comp").alias("was"), F.least("comp", "low").alias("comp"))
        jump = checkpointed(step)
        of = jump.select(F.col("idx").alias("comp"), F.col("comp").alias("up"))
        new = checkpointed(jump.join(of, "comp", "left").select("idx", "was", F.least("comp", F.coalesce("up", "comp")).alias("comp")))
        if new.where("comp <> was").isEmpty():
            return new.select("idx", "comp")
        label = new.select("idx", "comp")


def in_waves(calls: DataFrame, waves_of: DataFrame, cells: Callable[[dict], list[tuple]], body: Body, base: dict | None = None) -> DataFrame:
    """Replay wave by wave, for logs whose components are too large: the calls of a wave run in parallel against the state after the waves before.

    cells: (fn, args) -> the cells that a call may read. The state is a DataFrame; each wave joins what its calls read and appends what they write.
    """
    spark = calls.sparkSession
    rows = checkpointed(calls.join(waves_of, "idx"))
    kind = calls.schema["args"].dataType.valueType
    write = values.encode if isinstance(kind, StringType) else lambda x: x
    state = checkpointed(spark.createDataFrame([(t, key_text(k), c, -1, write(v)) for (t, k, c), v in (base or {}).items()], f"tbl string, row_key string, col string, idx long, val {kind.simpleString()}"))
    last = rows.agg(F.max("wave")).first()[0]
    out = None
    reads = F.udf(lambda fn, args: [(t, key_text(k), c) for t, k, c in cells({"fn": fn, **args})], "array<struct<tbl:string,row_key:string,col:string>>")
    for w in range((last if last is not None else -1) + 1):
        now = rows.where(F.col("wave") == w)
        wanted = now.select("idx", F.explode(reads("fn", "args")).alias("c")).select("idx", "c.*")
        latest = state.where("col is not null").groupBy("tbl", "row_key", "col").agg(F.max_by("val", "idx").alias("val")).where("val is not null")
        held = wanted.join(latest, ["tbl", "row_key", "col"]).select(F.col("idx").alias("comp"), "tbl", "row_key", "col", "val")
        made = checkpointed(in_order(now.withColumn("comp", F.col("idx")), held, body))
        state = checkpointed(state.unionByName(made.select("tbl", "row_key", "col", "idx", "val")))
        out = made if out is None else out.unionByName(made)
    return out


def choose_strategy(foldable: bool, largest_component: int, budget: int = 1_000_000) -> str:
    """fold when all effects are unguarded assignments or additions; components while the largest fits a task's budget; else waves."""
    return "fold" if foldable else "components" if largest_component <= budget else "waves"


def waves_in_components(accesses: DataFrame) -> DataFrame:
    """(idx, wave) as `waves` gives, by one ordered pass over each component. accesses: (comp, idx, cell, mode).

    For long chains: a component streams through one task in commit order, which holds two numbers for each of its cells.
    """
    rows = accesses.groupBy("comp", "idx").agg(F.sort_array(F.collect_set(F.struct("cell", "mode"))).alias("a"))
    rows = rows.repartition("comp").sortWithinPartitions("comp", "idx")

    def run(batches):
        at, wrote, read = None, {}, {}
        for batch in batches:
            out = []
            for comp, idx, touched in zip(*(batch.column(k).to_pylist() for k in ("comp", "idx", "a")), strict=True):
                if comp != at:
                    at, wrote, read = comp, {}, {}
                level = 0
                for t in touched:
                    level = max(level, wrote.get(t["cell"], -1) + 1)
                    if t["mode"] == "W":
                        level = max(level, read.get(t["cell"], -1) + 1)
                for t in touched:
                    if t["mode"] == "W":
                        wrote[t["cell"]] = level
                        read.pop(t["cell"], None)
                for t in touched:
                    if t["mode"] == "R":
                        read[t["cell"]] = max(read.get(t["cell"], -1), level)
                out.append((idx, level))
            yield pa.RecordBatch.from_arrays([pa.array([o[k] for o in out], pa.int64()) for k in (0, 1)], ["idx", "wave"])

    return rows.mapInArrow(run, "idx long, wave long")


def schedule_batch(calls: DataFrame) -> DataFrame:
    """Known read and write sets as a concurrency scheduler: (idx, wave), where a wave runs at once without restarts. calls: (comp, idx, cell, mode)."""
    return waves_in_components(calls)

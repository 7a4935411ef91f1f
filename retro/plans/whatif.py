"""Retroactive operations end to end: edit the history, find what it affects, undo, replay, compare, publish.

`Operations` are rows (op, at_idx, replacement): remove and change name a statement of the actual history, add runs just before
at_idx. The edited history keeps commit indices; an added statement sits at (at_idx, tie -1), so replay sorts by (idx, tie).
"""

from __future__ import annotations

import json
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from retro.operators import pieces as X
from retro.operators import versions as V
from retro.operators.hashing import literal_match, unchanged
from retro.operators.replay import STOPPED, Body, replayer
from retro.sources.tables import checkpointed, shared_dir

CELL = V.CELL


def remove(effects: DataFrame, targets: DataFrame) -> DataFrame:
    """The history without the targets (idx)."""
    return effects.join(targets.select("idx"), "idx", "left_anti")


def add(effects: DataFrame, more: DataFrame, at_idx: int) -> DataFrame:
    """The history with effects `more` (tbl, row_key, col, op, val) just before at_idx. Indices are doubled so that the new one fits between."""
    old = effects.withColumn("idx", F.col("idx") * 2)
    return old.unionByName(more.withColumn("idx", F.lit(2 * at_idx - 1).cast("long")))


def change(effects: DataFrame, target: Column, value: Column) -> DataFrame:
    """The history with other values at the targets."""
    return effects.withColumn("val", F.when(target, value).otherwise(F.col("val")))


def fold_whatif(actual: DataFrame, edited: DataFrame, touched: DataFrame, state: DataFrame | None = None) -> DataFrame:
    """The state after an edited history of algebraic effects. Only cells that the operation touches are folded again; every other
    cell keeps its value. touched: cells of the old and the new statements."""
    now = V.fold_state(actual) if state is None else state
    cells = touched.select(*CELL).distinct()
    fresh = V.fold_state(edited.join(cells, CELL, "left_semi"))
    return V.replaced(now, cells, fresh)


def component_whatif(calls: DataFrame, targets: DataFrame, versions: DataFrame, replay, fresh_calls: DataFrame | None = None, initial: DataFrame | None = None, early_stop: bool = False) -> DataFrame:
    """Versions of the edited history when calls depend on the database. Of the components (comp) that hold an operation, the calls from its first
    one on are replayed, against the state that the logged versions give just before; all other versions are reused as they are.

    replay: (calls, base, logged) -> versions. fresh_calls: calls that the operation adds. initial: cells (comp, tbl, row_key, col, val) before the first call.
    early_stop: a component's replay ends where its tables are as in the original history again, and the logged versions hold from there.
    """
    marks = calls.join(targets.select("idx"), "idx", "left_semi").select("comp", "idx")
    if fresh_calls is not None:
        marks = marks.unionByName(fresh_calls.select("comp", "idx"))
    hit = checkpointed(marks.groupBy("comp").agg(F.min("idx").alias("first"), F.max("idx").alias("last")))
    again = calls.join(hit, "comp").where("idx >= first").select(*calls.columns).join(targets.select("idx"), "idx", "left_anti").select(*calls.columns)
    if fresh_calls is not None:
        again = again.unionByName(fresh_calls.select(*calls.columns))
    own = versions.join(hit, "comp")
    start = own.where("idx < first").select("comp", "idx", *CELL, "val")
    if initial is not None:
        start = start.unionByName(initial.join(hit, "comp").select("comp", F.lit(-1).cast("long").alias("idx"), *CELL, "val"))
    fresh = replay(again, V.as_of(start, by=("comp",)), own.where("idx >= first") if early_stop else None)
    kept = versions.join(hit, "comp", "left")
    if early_stop:
        fresh = checkpointed(fresh)
        stops = fresh.where(F.col("tbl") == STOPPED).select("comp", F.col("idx").alias("stop"))
        kept = kept.join(stops, "comp", "left").where("first is null or idx < first or idx > stop")
        fresh = fresh.where(F.col("tbl") != STOPPED)
    else:
        kept = kept.where("first is null or idx < first")
    return kept.select(*versions.columns).unionByName(fresh.select(*versions.columns))


def pieces_whatif(calls: DataFrame, targets: DataFrame, procedures: dict) -> DataFrame:
    """The state (tbl, row_key, col, val as typed text) after a history without the targets, whose calls shared tables tie together. Procedures run in the pieces
    that share no cell: those of unguarded assignments and additions are folded, the others replayed by component, a row's key where the piece has one.

    calls: idx, fn and a column for each parameter, lists as arrays of structs."""
    gone = F.broadcast(checkpointed(targets.select(F.col("idx").alias("call"))))
    groups: dict[str, list] = {}
    for name, own in X.split(procedures).items():
        for piece in own:
            groups.setdefault(piece.group, []).append((piece, calls.where(F.col("fn") == name)))
    folded, replayed = [], []
    for own in groups.values():
        (folded if all(X.folds(*x) for x in own) else replayed).extend(own)
    out = []
    if folded:
        actual = _union([X.effects(*x) for x in folded])
        out.append(fold_whatif(actual, actual.join(gone, "call", "left_anti"), actual.join(gone, "call", "left_semi")).withColumn("val", F.concat(F.lit("i"), F.col("val").cast("string"))))
    if replayed:
        rows = checkpointed(_union([X.piece_calls(*x) for x in replayed]))
        replay = replayer(Body({}, {piece.procedure.name: piece.procedure for piece, _ in replayed}))
        versions = checkpointed(replay(rows.drop("call")))
        out.append(V.as_of(component_whatif(rows.drop("call"), rows.join(gone, "call", "left_semi").select("idx"), versions, replay)).select(*CELL, "val"))
    return _union(out)


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def bucketed_whatif(calls: DataFrame, targets: DataFrame, versions: DataFrame, replay, cuts: list[int], literal: bool = False) -> tuple[DataFrame, int | None]:
    """The same for a history that is one component: buckets of commit order run one after the other from the first operation on, and while a bucket runs, a
    separate job compares the tables' hashes at the end of the one before. Returns the versions and the index from which on the logged ones are
    reused (None: none are). cuts: the first index of each bucket."""
    ends = targets.agg(F.min("idx"), F.max("idx")).first()
    first, last = ends
    cuts = [first, *(c for c in sorted(cuts) if c > first), None]
    left = checkpointed(calls.where(F.col("idx") >= first).join(targets.select("idx"), "idx", "left_anti"))
    state = start = checkpointed(V.as_of(versions, first))
    made, pending, stop = None, None, None

    def equal(fresh: DataFrame, upto: int) -> bool:
        old = versions.where((F.col("idx") >= first) & (F.col("idx") < upto))
        if not unchanged(old, fresh):
            return False
        return not literal or literal_match(V.as_of(versions, upto), V.replayed(start, fresh))

    with ThreadPoolExecutor(1) as pool:
        for low, high in zip(cuts, cuts[1:], strict=False):
            now = left.where((F.col("idx") >= low) & (F.lit(True) if high is None else F.col("idx") < high))
            step = checkpointed(replay(now, state.select(F.lit(now.select("comp").first()[0] if not now.isEmpty() else 0).alias("comp"), *CELL, "val"), None))
            if pending is not None and pending[1].result():
                stop = pending[0]
                break
            made = step if made is None else made.unionByName(step)
            state = checkpointed(V.replayed(state, step))
            pending = (high, pool.submit(equal, made, high)) if high is not None and low is not None and high > last else None
    kept = versions.where((F.col("idx") < first) | (F.col("idx") >= stop if stop is not None else F.lit(False)))
    made = made.where(F.col("idx") < stop) if stop is not None else made
    return kept.unionByName(made.select(*versions.columns)), stop


@dataclass
class Scenarios:
    """What-if branches of one history: tags with a parent, a branching index and a folder of changed cells; the shared prefix is kept by
    reference. The published scenario is named by a pointer file that is replaced last."""

    spark: SparkSession
    root: str = ""
    known: dict[str, dict] = field(default_factory=dict)

    def __post_init__(self):
        self.root = self.root or f"{shared_dir(self.spark)}/scenarios"

    def branch(self, tag: str, parent: str | None, idx: int, changed: DataFrame) -> str:
        """changed: (tbl, row_key, col, was, now)."""
        changed.write.mode("overwrite").parquet(f"{self.root}/{tag}")
        self.known[tag] = {"parent": parent, "branch_idx": idx}
        return tag

    def scenarios(self) -> DataFrame:
        rows = [(t, m["parent"], m["branch_idx"]) for t, m in sorted(self.known.items())]
        return self.spark.createDataFrame(rows, "scenario_id string, parent_id string, branch_idx long")

    def lineage(self, tag: str) -> list[str]:
        out = []
        while tag is not None:
            out.append(tag)
            tag = self.known[tag]["parent"]
        return out[::-1]

    def state(self, tag: str, base: DataFrame) -> DataFrame:
        """The base state with the changed cells of the scenario and its ancestors."""
        out = base
        for t in self.lineage(tag):
            d = self.spark.read.parquet(f"{self.root}/{t}")
            out = out.join(d.select(*CELL), CELL, "left_anti").unionByName(d.where("now is not null").select(*CELL, F.col("now").alias("val")))
        return out

    def publish(self, tag: str, high_water: int) -> None:
        """Makes the scenario current: its pointer is written after all its data."""
        text = json.dumps({"scenario": tag, "lineage": self.lineage(tag), "high_water": high_water})
        self.spark.createDataFrame([(text,)], "value string").coalesce(1).write.mode("overwrite").text(f"{self.root}/current")

    def current(self) -> dict:
        return json.loads(self.spark.read.text(f"{self.root}/current").first()[0])


def catch_up(edited: DataFrame, log, replay, state: DataFrame, mark: int, small: int = 100, rounds: int = 10) -> tuple[DataFrame, int, int]:
    """Applies what was committed while replay ran: rounds over statements after `mark` until few are left, which are applied under the lock.
    log: mark -> effects committed later. Returns (state, new mark, rounds)."""
    done = 0
    while done < rounds:
        more = checkpointed(log(mark))
        last = more.agg(F.count("*").alias("n"), F.max("idx").alias("last")).first()
        if not last.n:
            break
        edited = edited.unionByName(more)
        cells = more.select(*CELL).distinct()
        state = checkpointed(V.replaced(state, cells, replay(edited.join(cells, CELL, "left_semi"))))
        mark, done = last.last, done + 1
        if last.n <= small:
            break
    return state, mark, done


def with_rules(calls: DataFrame, rules: DataFrame, on: list[str]) -> DataFrame:
    """Calls that no human-decision rule suppresses. rules: (on..., from_idx): from that index on, matching calls would not have been made."""
    hit = calls.join(F.broadcast(rules), on).where(F.col("commit_idx") >= F.col("from_idx")).select("commit_idx")
    return calls.join(hit, "commit_idx", "left_anti")


def with_state_rules(calls: DataFrame, versions: DataFrame, tbl: str, col: str, suppressed: Column, key: str = "row_key") -> DataFrame:
    """Calls (commit_idx, `key`, ...) that a rule over the state does not suppress. suppressed: a condition on `held`, the value that the call's row has in the
    column just before the call, or null. The as-of look-up is one window over calls and versions of that column."""
    past = versions.where((F.col("tbl") == tbl) & (F.col("col") == col)).select(F.col("row_key").alias("_key"), F.col("idx").alias("_at"), F.lit(1).alias("_call"), F.col("val").alias("_val"))
    now = calls.select(F.col(key).alias("_key"), F.col("commit_idx").alias("_at"), F.lit(0).alias("_call"), F.lit(None).cast(versions.schema["val"].dataType).alias("_val"))
    order = Window.partitionBy("_key").orderBy("_at", "_call").rowsBetween(Window.unboundedPreceding, -1)
    found = past.unionByName(now).withColumn("held", F.last("_val", ignorenulls=True).over(order)).where("_call = 0")
    gone = found.where(F.coalesce(suppressed, F.lit(False))).select(F.col("_at").alias("commit_idx"))
    return calls.join(gone, "commit_idx", "left_anti")


class RuleProvider:
    """A source of human-decision rules: from what a changed past differs in, the calls that would not have been made. This one has a fixed
    list of rules (condition on a cell that differs, rows of calls to suppress from where on); a model may take its place."""

    def __init__(self, known: list[tuple[Column, DataFrame]] | None = None):
        self.known = known or []

    def rules(self, diff: DataFrame) -> list[DataFrame]:
        """diff: (tbl, row_key, col, was, now). The rules whose condition holds for some cell that differs."""
        return [rows for condition, rows in self.known if not diff.where(condition).isEmpty()]

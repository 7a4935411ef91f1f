"""Compared methods: symbolic reenactment of a history as one expression, replay of logged queries only, optimistic scheduling, client cost."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UNSUPPORTED = ("string", "boolean", "date", "timestamp")


@dataclass(frozen=True)
class Change:
    """kind: update (where, sets), delete (where), insert (row)."""

    kind: str
    where: Callable[[dict[str, Column]], Column] | None = None
    sets: dict[str, Callable[[dict[str, Column]], Column]] | None = None
    row: dict | None = None


def reenact(base: DataFrame, changes: list[Change], compat: bool = False) -> DataFrame:
    """A history of statements over one table as a nested expression over its base: UPDATE is a conditional projection over the current
    expressions, DELETE a filter, INSERT a union. The expression grows with every statement that reads what another one wrote.

    compat: refuse what the compared system does not do (string, boolean, date and time attributes)."""
    if compat and any(t in UNSUPPORTED for _, t in base.dtypes):
        raise NotImplementedError("attributes of this type are not supported by the compared system")
    columns, out = base.columns, base
    cells = {c: F.col(c) for c in columns}
    alive = F.lit(True)

    def flush():
        return out.where(alive).select(*[cells[c].alias(c) for c in columns])

    for s in changes:
        if s.kind == "update":
            test = s.where(cells)
            cells = {c: F.when(test, s.sets[c](cells)).otherwise(cells[c]) if c in s.sets else cells[c] for c in columns}
        elif s.kind == "delete":
            alive = alive & ~F.coalesce(s.where(cells), F.lit(False))
        else:
            one = base.sparkSession.createDataFrame([tuple(s.row.get(c) for c in columns)], base.schema)
            out = flush().unionByName(one)
            cells, alive = {c: F.col(c) for c in columns}, F.lit(True)
    return flush()


def historical_delta(base: DataFrame, actual: list[Change], edited: list[Change]) -> DataFrame:
    """(columns, sign): rows only in the actual (-1) or only in the edited history's result (+1)."""
    a, b = reenact(base, actual), reenact(base, edited)
    return b.exceptAll(a).withColumn("sign", F.lit(1)).unionByName(a.exceptAll(b).withColumn("sign", F.lit(-1)))


def data_slice(base: DataFrame, changes: list[Change]) -> DataFrame:
    """Rows of the base that some statement's predicate may select, where predicates read columns that no statement changes."""
    cells = {c: F.col(c) for c in base.columns}
    test = F.lit(False)
    for s in changes:
        if s.where is not None:
            test = test | F.coalesce(s.where(cells), F.lit(False))
    return base.where(test)


def query_only(versions: DataFrame, targets: DataFrame) -> DataFrame:
    """Replay of the logged queries alone: the targets' writes go, all others stand as they were logged, for no branch of the application is decided again."""
    return versions.join(targets.select("idx"), "idx", "left_anti")


def plan_nodes(df: DataFrame) -> int:
    """Size of the analysed logical plan: nodes and expressions, as the length of its text in tokens."""
    return len(df._jdf.queryExecution().analyzed().toString().split())


def schedule_optimistic(calls: list[tuple[int, set, set]], width: int) -> tuple[int, int]:
    """(rounds, restarts) of a scheduler that finds out read and write sets by running: of `width` calls started together, those that read or write what
    an earlier one of them wrote are restarted in the next round. calls: (idx, reads, writes) in order."""
    waiting, rounds, restarts = list(calls), 0, 0
    while waiting:
        rounds += 1
        written, again = set(), []
        for c in waiting[:width]:
            if (c[1] | c[2]) & written:
                again.append(c)
                restarts += 1
            written |= c[2]
        waiting = again + waiting[width:]
    return rounds, restarts


def client_ram(users: int, mb_each: float = 100.0) -> float:
    """Memory in MB to re-run every user's client, were history replayed through full clients."""
    return users * mb_each

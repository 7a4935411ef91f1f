"""Procedures in pieces that share no cell and no value, so that calls which a shared table ties together fall apart by row.

A call of a procedure does the same as the calls of its pieces. A piece that is a loop over an argument list runs as one call for each row of it, and
where all cells of a piece have one key, that key is its component. Pieces of unguarded assignments and additions are effects, which fold without replay.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType, StringType

from retro.app.transpile import Node, Procedure, _expressions, _names, _used, slice_db_effects
from retro.operators import values

#: Commit indices are this far apart; the rows of a call's list lie between.
STEP = 1 << 24


@dataclass
class Piece:
    """group: names the tables that the pieces of the same group alone touch. key: what every cell has as key, None where they differ (the group is then one
    component). rows: the list of which each row is a call, fields: parameter -> column of that list. fold: (table, column, op, value) of each effect, None if not foldable."""

    procedure: Procedure
    group: str
    key: tuple | None
    rows: str | None = None
    fields: dict[str, str] = field(default_factory=dict)
    fold: list[tuple] | None = None


def split(procedures: dict[str, Procedure]) -> dict[str, list[Piece]]:
    """The pieces of each procedure. A procedure with signals, or that uses a loop's row after it, stays whole. Tables that some piece touches together are one group for all."""
    parts = []
    for name, p in procedures.items():
        tree = slice_db_effects(p.tree)
        parts += [(name, node) for node in ([tree] if tree.signals() or _outside(tree) else _parts(tree))]
    out: dict[str, list[Piece]] = {name: [] for name in procedures}
    for members in _united(parts, lambda part: _tables(part[1])):
        group = min(set().union(*(_tables(node) for _, node in members)), default="")
        made = {name: _piece(procedures[name], _joined([n for m, n in members if m == name]), group) for name in dict.fromkeys(m for m, _ in members)}
        for name, piece in made.items():
            if any(x.key is None for x in made.values()):
                piece.key = None
            if any(x.fold is None for x in made.values()):
                piece.fold = None
            out[name].append(piece)
    return out


def _outside(node: Node) -> bool:
    """Whether a row's column is used after its loop."""
    own = [n for e in (*(e for s in node.steps for e in _expressions(s)), *([node.test] if node.test else [])) for n in _names(e)]
    return any(n.startswith("item.") for n in own) or bool(node.test) and (_outside(node.yes) or _outside(node.no))


def _parts(node: Node) -> list[Node]:
    units = []
    for s in node.steps:
        apart = s[0] == "loop" and not _below(s[2], lambda x: x[0] == "loop")
        units += [Node([("loop", s[1], body)]) for body in _parts(s[2])] if apart else [Node([s])]
    if node.test:
        units.append(Node([], node.test, node.yes, node.no))
    made = set().union(*(_made(u) for u in units))
    return [_joined(g) for g in _united(units, lambda u: {("table", t) for t in _tables(u)} | {("value", v) for v in (_used(u) | _made(u)) & made})]


def _united(units: list, marks: Callable) -> list[list]:
    """The units in groups, in their order: those with a mark in common are together."""
    groups: list[tuple[set, list[int]]] = []
    for k, unit in enumerate(units):
        own, at, rest = set(marks(unit)), [k], []
        for m, ks in groups:
            if m & own:
                own, at = own | m, ks + at
            else:
                rest.append((m, ks))
        groups = [*rest, (own, at)]
    return [[units[k] for k in ks] for ks in sorted(sorted(ks) for _, ks in groups)]


def _joined(nodes: list[Node]) -> Node:
    """Nodes one after the other; at most one of them ends in a branch or signal, which comes last."""
    last = next((n for n in nodes if n.test or n.signal), Node())
    return Node([s for n in nodes if n is not last for s in n.steps] + last.steps, last.test, last.yes, last.no, last.signal)


def _below(node: Node, of: Callable) -> list[tuple]:
    """Steps of a node and of all below it that `of` holds for."""
    out = [s for s in node.steps if of(s)]
    for n in [*node.loops(), *([node.yes, node.no] if node.test else [])]:
        out += _below(n, of)
    return out


def _tables(node: Node) -> set[str]:
    return {s[2] if s[0] in ("read", "exists") else s[1] for s in _below(node, lambda s: s[0] in ("read", "exists", "write", "delete"))}


def _made(node: Node) -> set[str]:
    return {s[1] for s in _below(node, lambda s: s[0] in ("read", "exists", "native"))}


def _renamed(node: Node, to: dict[str, str]) -> Node:
    """A loop's body with its row's columns as parameters."""
    e = lambda x: ("var", to[x[1]]) if x[0] == "item" else x if x[0] != "op" else (*x[:2], *(e(y) for y in x[2:]))
    key = lambda k: tuple(e(x) for x in k)

    def step(s):
        if s[0] == "write":
            return ("write", s[1], key(s[2]), s[3], e(s[4]))
        if s[0] == "delete":
            return ("delete", s[1], key(s[2]))
        return (*s[:3], key(s[3]), *s[4:])

    steps = [step(s) for s in node.steps]
    return Node(steps, e(node.test), _renamed(node.yes, to), _renamed(node.no, to), node.signal) if node.test else Node(steps, signal=node.signal)


def _piece(p: Procedure, node: Node, group: str) -> Piece:
    rows, fields, loops = None, {}, _below(node, lambda s: s[0] == "loop")
    if len(loops) == 1 and node.steps == loops and not node.test and loops[0][1][0] == "var" and loops[0][1][1] in p.params:
        rows, node = loops[0][1][1], loops[0][2]
        fields = {n.removeprefix("item."): f"{rows}_{n.removeprefix('item.')}" for n in sorted(_used(node)) if n.startswith("item.")}
        if set(fields.values()) & set(p.params):
            raise ValueError(f"{p.name}: a parameter is named like a column of {rows}")
        node = _renamed(node, fields)
    params = tuple(x for x in (*p.params, *fields.values()) if x in _used(node))
    keys = {k for s in _below(node, lambda s: s[0] in ("read", "exists", "write", "delete")) for k in [s[3] if s[0] in ("read", "exists") else s[2]]}
    key = next(iter(keys)) if len(keys) == 1 else None
    if key is not None and any(x[0] != "lit" and (x[0] != "var" or x[1] not in params) for x in key):
        key = None
    # the name is a function's name in the emitted source
    name = f"{p.name}_{group}"
    return Piece(Procedure(name, params, node), group, key, rows, {v: k for k, v in fields.items()}, _effects_of(node, params) if key else None)


def _effects_of(node: Node, params: tuple[str, ...]) -> list[tuple] | None:
    """(table, column, op, value) of a node that assigns what its arguments give or adds it to a cell; None for any other."""
    if node.test or node.signal:
        return None
    reads, out, plain = {}, {}, lambda e: e[0] == "lit" and type(e[1]) is int or e[0] == "var" and e[1] in params or e[0] == "op" and e[1] in ("+", "-", "*", "neg") and all(plain(x) for x in e[2:])
    for s in node.steps:
        if s[0] == "read":
            if (s[2], s[4]) in out:
                return None
            reads["var", s[1]] = (s[2], s[4])
        elif s[0] == "write" and (s[1], s[3]) not in out:
            cell, e = (s[1], s[3]), s[4]
            if plain(e):
                out[cell] = ("set", e)
            elif e[:2] == ("op", "+") and reads.get(e[2]) == cell and plain(e[3]):
                out[cell] = ("add", e[3])
            elif e[:2] == ("op", "+") and reads.get(e[3]) == cell and plain(e[2]):
                out[cell] = ("add", e[2])
            elif e[:2] == ("op", "-") and reads.get(e[2]) == cell and plain(e[3]):
                out[cell] = ("add", ("op", "neg", e[3]))
            else:
                return None
        else:
            return None
    return [(t, c, *e) for (t, c), e in out.items()]


# ---- calls -----------------------------------------------------------------------------------------------------------


def folds(piece: Piece, calls: DataFrame) -> bool:
    """Whether the piece is effects on whole numbers, which `effects` gives."""
    return piece.fold is not None and all(isinstance(t, IntegralType) for t in _types(piece, calls).values())


def _types(piece: Piece, calls: DataFrame) -> dict:
    of = lambda n: calls.schema[piece.rows].dataType.elementType[piece.fields[n]] if n in piece.fields else calls.schema[n]
    return {n: of(n).dataType for n in piece.procedure.params}


def _rows(piece: Piece, calls: DataFrame) -> DataFrame:
    """(call, idx, parameters of the piece): a row for each of its calls."""
    own = [c for c in piece.procedure.params if c not in piece.fields]
    if piece.rows is None:
        return calls.select(F.col("idx").alias("call"), (F.col("idx") * STEP).alias("idx"), *own)
    rows = calls.select("idx", *own, F.posexplode(piece.rows).alias("_at", "_row"))
    at = F.when(F.col("_at") < STEP, F.col("_at")).otherwise(F.raise_error(F.lit(f"a list of {piece.rows} has more than {STEP} rows")).cast("int"))
    return rows.select(F.col("idx").alias("call"), (F.col("idx") * STEP + at).alias("idx"), *own, *[F.col("_row")[c].alias(n) for n, c in piece.fields.items()])


def piece_calls(piece: Piece, calls: DataFrame) -> DataFrame:
    """(call, idx, comp, fn, args) for replay. calls: idx and a column for each parameter of the whole procedure."""
    rows, types = _rows(piece, calls), _types(piece, calls)
    key = piece.key or ()
    if not all(x[0] == "lit" or isinstance(types[x[1]], IntegralType | StringType) for x in key):
        raise TypeError(f"{piece.procedure.name}: keys must be whole numbers or texts")
    comp = F.xxhash64(F.lit(piece.group), *[F.lit(str(x[1])) if x[0] == "lit" else F.col(x[1]).cast("string") for x in key])
    return rows.select("call", "idx", comp.alias("comp"), F.lit(piece.procedure.name).alias("fn"), values.arguments(rows, *piece.procedure.params).alias("args"))


def effects(piece: Piece, calls: DataFrame) -> DataFrame:
    """(call, idx, tbl, row_key, col, op, val) of a piece that `folds`."""
    key = F.concat_ws("|", *[F.coalesce(_column(x).cast("string"), F.lit("None")) for x in piece.key])
    each = F.array(*[F.struct(F.lit(t).alias("tbl"), F.lit(c).alias("col"), F.lit(op).alias("op"), _column(e).cast("long").alias("val")) for t, c, op, e in piece.fold])
    return _rows(piece, calls).select("call", "idx", key.alias("row_key"), F.explode(each).alias("e")).select("call", "idx", "e.tbl", "row_key", "e.col", "e.op", "e.val")


def _column(e: tuple) -> Column:
    if e[0] == "lit":
        return F.lit(e[1])
    if e[0] == "var":
        return F.col(e[1]).cast("long")
    a = [_column(x) for x in e[2:]]
    return -a[0] if e[1] == "neg" else {"+": lambda x, y: x + y, "-": lambda x, y: x - y, "*": lambda x, y: x * y}[e[1]](*a)

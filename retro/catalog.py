"""Table metadata: columns, key, row identifier, aliases of it, foreign keys, generated keys, views, triggers, procedures."""

from __future__ import annotations

from dataclasses import dataclass, field

from retro.functions.sqlast import Ddl, Select

ROW = "__row"
#: The table of schema elements: one column for each object, read by whatever uses the object and written by DDL.
SCHEMA = "_S"


@dataclass
class Table:
    name: str
    columns: tuple[str, ...]
    key: tuple[str, ...]
    #: Columns of the row identifier; the key unless chosen otherwise.
    ri: tuple[str, ...] = ()
    #: Alias column -> row identifier column.
    alias: dict[str, str] = field(default_factory=dict)
    #: Column -> (parent table, parent column).
    foreign: dict[str, tuple[str, str]] = field(default_factory=dict)
    generated: str | None = None

    def __post_init__(self):
        self.ri = self.ri or self.key


@dataclass
class Catalog:
    tables: dict[str, Table] = field(default_factory=dict)
    views: dict[str, Select] = field(default_factory=dict)
    procedures: dict[str, Ddl] = field(default_factory=dict)
    triggers: list[Ddl] = field(default_factory=list)
    #: A key that an insert uses is read too. False: the published sets, sound only while every insert succeeds.
    strict_keys: bool = True

    def table(self, name: str) -> Table:
        return self.tables[name]

    def add(self, *tables: Table) -> Catalog:
        for t in tables:
            self.tables[t.name] = t
        return self

    def parents(self, view: str) -> list[str]:
        """Base tables below a view, views of views included."""
        out = []
        for name, _, _ in self.views[view].tables:
            out += self.parents(name) if name in self.views else [name]
        return out

    def children(self, table: str, column: str) -> list[tuple[str, str]]:
        return [(t.name, c) for t in self.tables.values() for c, to in t.foreign.items() if to == (table, column)]

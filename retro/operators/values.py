"""Values of any type as text with a type letter, so that one column of a version log holds all of them.

i integer, d decimal, f double, b boolean, s string, t timestamp (microseconds since 1970, UTC), j list or object (JSON). Null is null. Catalyst writes and reads the
same text as Python, so a log stays plain columns.
"""

from __future__ import annotations

import json
from datetime import UTC, datetime, timedelta
from decimal import Decimal

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BooleanType, DataType, DecimalType, FractionalType, IntegralType, StringType, StructType, TimestampType

_START = datetime(1970, 1, 1, tzinfo=UTC)


def encode(value) -> str | None:
    if value is None:
        return None
    if isinstance(value, bool):
        return f"b{str(value).lower()}"
    if isinstance(value, int):
        return f"i{value}"
    if isinstance(value, Decimal):
        return f"d{value:f}"
    if isinstance(value, float):
        return f"f{value!r}"
    if isinstance(value, datetime):
        return f"t{(value - _START) // timedelta(microseconds=1)}"
    return f"s{value}" if isinstance(value, str) else "j" + json.dumps(value, separators=(",", ":"))


def decode(text: str | None):
    if text is None:
        return None
    kind, rest = text[0], text[1:]
    if kind == "i":
        return int(rest)
    if kind == "b":
        return rest == "true"
    if kind == "t":
        return _START + timedelta(microseconds=int(rest))
    return {"d": Decimal, "f": float, "s": str, "j": json.loads}[kind](rest)


def encoded(column: Column, of: DataType) -> Column:
    """A column of type `of` as such text."""
    if isinstance(of, IntegralType):
        return F.concat(F.lit("i"), column.cast("string"))
    if isinstance(of, DecimalType):
        return F.concat(F.lit("d"), column.cast("string"))
    if isinstance(of, BooleanType):
        return F.concat(F.lit("b"), column.cast("string"))
    if isinstance(of, FractionalType):
        return F.concat(F.lit("f"), column.cast("string"))
    if isinstance(of, TimestampType):
        return F.concat(F.lit("t"), F.unix_micros(column).cast("string"))
    if isinstance(of, StringType):
        return F.concat(F.lit("s"), column)
    if isinstance(of, ArrayType | StructType):
        return F.concat(F.lit("j"), F.to_json(column))
    raise TypeError(of)


def arguments(rows, *names: str) -> Column:
    """The columns `names` of a DataFrame as a map from name to text: the arguments of a call."""
    return F.map_from_arrays(F.array(*[F.lit(n) for n in names]), F.array(*[encoded(F.col(n), rows.schema[n].dataType) for n in names]))


def plain(text: Column, of: str) -> Column:
    """Text back as SQL type `of`."""
    rest = F.substring(text, 2, 1 << 30)
    return F.timestamp_micros(rest.cast("long")) if of == "timestamp" else rest.cast(of)

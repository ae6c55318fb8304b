"""Checks of names, types and arguments before any job runs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, NumericType


class InputError(ValueError):
    """A wrong argument, with a code and a hint how to mend it."""

    def __init__(self, code: str, message: str, hint: str = ""):
        super().__init__(f"[{code}] {message}" + (f" ({hint})" if hint else ""))
        self.code, self.hint = code, hint


def columns(df: DataFrame, *names: str) -> None:
    if not names:
        raise InputError("NO_COLUMNS", "at least one column is needed")
    if len(set(names)) != len(names):
        raise InputError("REPEATED_COLUMN", f"a column is named twice among {list(names)}")
    for n in names:
        if n not in df.columns:
            raise InputError("UNKNOWN_COLUMN", f"there is no column {n!r}", f"columns are {df.columns}")


def numeric(df: DataFrame, *names: str) -> None:
    columns(df, *names)
    for n in names:
        if not isinstance(df.schema[n].dataType, NumericType):
            raise InputError("NOT_NUMERIC", f"column {n!r} is {df.schema[n].dataType.simpleString()}", "cast it first")


def vector(df: DataFrame, name: str) -> None:
    columns(df, name)
    t = df.schema[name].dataType
    if not isinstance(t, ArrayType) or not isinstance(t.elementType, NumericType):
        raise InputError("NOT_A_VECTOR", f"column {name!r} is {t.simpleString()}", "an array of numbers is needed")


def same_length(df: DataFrame, name: str) -> int:
    """The common length of all vectors; one small job."""
    vector(df, name)
    r = df.filter(F.col(name).isNotNull()).agg(F.min(F.size(name)).alias("lo"), F.max(F.size(name)).alias("hi")).first()
    if r["lo"] is None:
        raise InputError("EMPTY_INPUT", f"no vector in column {name!r}")
    if r["lo"] != r["hi"]:
        raise InputError("RAGGED_VECTORS", f"vectors in {name!r} have {r['lo']} to {r['hi']} components")
    return r["lo"]


def quoted(name: str) -> str:
    """An identifier in back-ticks, whatever it holds."""
    return "`" + name.replace("`", "``") + "`"

"""Arrow columns as numpy arrays and back."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

from rowfold.core.validate import InputError

_CALLBACKS: dict[str, tuple[Callable, str]] = {}


def register(name: str, schema: str) -> Callable[[Callable], Callable]:
    """Name a function of numpy blocks, one for each argument column, whose result has a row for each of theirs; schema is
    the result's type."""

    def add(f: Callable) -> Callable:
        _CALLBACKS[name] = (f, schema)
        return f

    return add


def lookup(name: str) -> tuple[Callable, str]:
    if name not in _CALLBACKS:
        raise InputError("UNKNOWN_CALLBACK", f"no function is registered as {name!r}", ", ".join(sorted(_CALLBACKS)) or "none is")
    return _CALLBACKS[name]


def apply_named(name: str, *args: Column | str) -> Column:
    """A registered function over columns, batch by batch: arrays of numbers come as (n, d) blocks, numbers as vectors."""
    f, schema = lookup(name)

    @F.arrow_udf(schema)
    def call(*cols: pa.Array) -> pa.Array:
        out = np.asarray(f(*[matrix(c) if pa.types.is_list(c.type) else vector(c) for c in cols]))
        return pa.array(out) if out.ndim == 1 else pa.array(list(out))

    return call(*args)


@register("nearest_column", "bigint")
def nearest_column(x: np.ndarray, flat: np.ndarray) -> np.ndarray:
    """The nearest column of a matrix for each row's vector; the matrix comes column by column."""
    d = x.shape[1]
    m = flat.reshape(len(x), -1, d)
    return np.round(((m - x[:, None, :]) ** 2).sum(2), 10).argmin(1)


@register("dot", "double")
def dot(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return (x * y).sum(1)


def matrix(column: pa.Array, width: int | None = None) -> np.ndarray:
    """Rows of an array column as an (n, d) block of doubles; without nulls and of doubles, no copy is made."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    flat = column.flatten()
    if flat.null_count:
        raise ValueError("a vector holds a null")
    x = np.asarray(flat, dtype=np.float64)
    d = len(x) // n if n else width or 0
    if n * d != len(x) or (width is not None and n and d != width):
        raise ValueError("vectors differ in length")
    return x.reshape(n, d)


def vector(column: pa.Array) -> np.ndarray:
    return np.asarray(column.to_numpy(zero_copy_only=False), dtype=np.float64)


def packed(square: np.ndarray) -> np.ndarray:
    """Lower triangle, row by row."""
    return square[np.tril_indices(len(square))]


def unpacked(triangle: np.ndarray, d: int) -> np.ndarray:
    out = np.zeros((d, d))
    i, j = np.tril_indices(d)
    out[i, j] = triangle
    out[j, i] = triangle
    return out

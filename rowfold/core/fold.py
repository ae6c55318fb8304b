"""Folds: a state, a step over a batch of rows, a merge of two states, a finish.

Every one-pass method is a fold. Partitions fold their own rows in Arrow batches
and leave one state each; states are merged in a tree of two levels, and the
finish runs on one task, so the driver sees nothing but what it asks for.
"""

from __future__ import annotations

import pickle
import random
from collections.abc import Callable, Iterator, Sequence
from typing import Any

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

STATE = "slot int, state binary"


class Fold:
    """The contract. merge(a, fold of rows) must equal folding on from a over these rows, up to rounding."""

    schema: str | StructType = ""

    def zero(self) -> Any:
        raise NotImplementedError

    def step(self, state: Any, batch: pa.RecordBatch) -> Any:
        raise NotImplementedError

    def merge(self, a: Any, b: Any) -> Any:
        raise NotImplementedError

    def finish(self, state: Any) -> list[dict]:
        """Rows of the result, by column name of `schema`."""
        raise NotImplementedError


def _state_rows(pairs: Sequence[tuple[int, Any]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([s for s, _ in pairs], pa.int32()), pa.array([pickle.dumps(x, protocol=5) for _, x in pairs], pa.binary())], names=["slot", "state"])


def _arrow_schema(df: DataFrame, schema: str | StructType) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema

    kind = schema if isinstance(schema, StructType) else df.sparkSession.createDataFrame([], schema).schema
    return to_arrow_schema(kind)


def partial_states(df: DataFrame, fold: Fold, slots: int) -> DataFrame:
    """One state per partition, dealt to slots."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state = fold.zero()
        for b in batches:
            if b.num_rows:
                state = fold.step(state, b)
        yield _state_rows([(TaskContext.get().partitionId() % slots, state)])

    return df.mapInArrow(work, STATE)


def _merged(states: list[bytes], fold: Fold) -> Any:
    out = fold.zero()
    for s in states:
        out = fold.merge(out, pickle.loads(s))
    return out


def run_fold(df: DataFrame, fold: Fold, cols: Sequence[str], by: Sequence[str] = (), mode: str = "tree", most_groups: int = 4096) -> DataFrame:
    """The fold's result over columns `cols`, for all rows or for each value of `by`.

    mode, without `by`: "tree" (partial states, two merge levels) or "serial" (one task, for folds without a merge).
    With `by`: "partial" (few or huge groups: a partition keeps a state per group and lets go of them beyond
    most_groups; groups may then have several states, which merging allows) or "grouped" (many small groups: rows
    of a group meet in one task).
    """
    src = df.select(*by, *cols)
    target = _arrow_schema(df, fold.schema)
    k = len(by)

    def rows(state: Any) -> pa.Table:
        return pa.Table.from_pylist(fold.finish(state), schema=target)

    if not by and mode == "serial":

        def serial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            state = fold.zero()
            for b in batches:
                if b.num_rows:
                    state = fold.step(state, b)
            yield from rows(state).to_batches()

        return src.coalesce(1).mapInArrow(serial, fold.schema)
    if not by:
        slots = max(1, int(df.sparkSession.sparkContext.defaultParallelism**0.5))
        level = partial_states(src, fold, slots)
        half = level.groupBy("slot").applyInArrow(lambda t: pa.Table.from_batches([_state_rows([(0, _merged(t.column("state").to_pylist(), fold))])]), STATE)
        return half.withColumn("slot", F.lit(0)).groupBy("slot").applyInArrow(lambda t: rows(_merged(t.column("state").to_pylist(), fold)), fold.schema)

    keys = _arrow_schema(df, src.select(*by).schema)
    full = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in src.select(*by).schema) + ", " + (fold.schema if isinstance(fold.schema, str) else ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in fold.schema))

    def with_keys(values: list, state: Any) -> pa.Table:
        t = rows(state)
        for i, (f, v) in enumerate(zip(keys, values)):
            t = t.add_column(i, f, pa.array([v] * t.num_rows, f.type))
        return t

    if mode == "grouped":

        def grouped(key, t):
            state = fold.zero()
            for b in t.select(range(k, t.num_columns)).to_batches():
                state = fold.step(state, b)
            return with_keys([x.as_py() for x in key], state)

        return src.groupBy(*by).applyInArrow(grouped, full)

    def by_group(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        states: dict[tuple, Any] = {}

        def out() -> pa.RecordBatch:
            cols = [pa.array([g[i] for g in states], f.type) for i, f in enumerate(keys)]
            return pa.RecordBatch.from_arrays([*cols, pa.array([pickle.dumps(s, protocol=5) for s in states.values()], pa.binary())], names=[*by, "state"])

        for b in batches:
            t = pa.Table.from_batches([b]).append_column("__row", pa.array(range(b.num_rows)))
            groups = t.group_by(list(by), use_threads=False).aggregate([("__row", "list")])
            for i in range(groups.num_rows):
                g = tuple(groups.column(c)[i].as_py() for c in by)
                own = b.take(groups.column("__row_list")[i].values).select(list(cols))
                states[g] = fold.step(states.pop(g, None) or fold.zero(), own)
            if len(states) > most_groups:
                yield out()
                states = {}
        if states:
            yield out()

    key_sql = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in src.select(*by).schema)
    level = src.mapInArrow(by_group, f"{key_sql}, state binary")
    return level.groupBy(*by).applyInArrow(lambda key, t: with_keys([x.as_py() for x in key], _merged(t.column("state").to_pylist(), fold)), full)


def check_fold(fold: Fold, batch: pa.RecordBatch, same: Callable[[list, list], bool], tries: int = 5, seed: int = 7) -> bool:
    """Whether random orders and splits of the rows, merged in random order, give what one sequence gives."""
    rng = random.Random(seed)
    whole = fold.finish(fold.step(fold.zero(), batch))
    for _ in range(tries):
        order = list(range(batch.num_rows))
        rng.shuffle(order)
        cuts = sorted(rng.sample(range(1, len(order)), min(3, len(order) - 1)))
        states = [fold.step(fold.zero(), batch.take(pa.array(order[a:z]))) for a, z in zip([0, *cuts], [*cuts, len(order)])]
        rng.shuffle(states)
        while len(states) > 1:
            states.append(fold.merge(states.pop(0), states.pop(0)))
        if not same(whole, fold.finish(states[0])):
            return False
    return True

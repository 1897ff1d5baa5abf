"""How often values of several columns occur by group: counts that a task holds, merges and hands on."""

from __future__ import annotations

from collections.abc import Iterator
from decimal import Decimal
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark.sql import Row

HELD = "i int, rep int, whole long, real double, bytes binary, n long"
HELD_KEYS = ("i", "rep", "whole", "real", "bytes")
#: A column's counts are merged once they have grown by so many, and handed on once there are more than the second.
MERGE, MOST = 200_000, 1_000_000
#: Of numbers whose medians are asked for, about as many points a group and hand-over are kept.
POINTS = 20_000


def shipped(values: pa.Array) -> tuple[int, pa.Array]:
    """(place among whole, real and bytes, the values there), in the values' own order."""
    t = values.type
    if pa.types.is_floating(t):
        return 1, values.cast(pa.float64())
    if pa.types.is_decimal(t):
        if t.precision <= 18:
            return 0, pa.array([None if v is None else int(v.scaleb(t.scale)) for v in values.to_pylist()], pa.int64())
        return 2, values.cast(pa.string()).cast(pa.binary())
    if pa.types.is_date(t):
        return 0, values.cast(pa.int32()).cast(pa.int64())
    if pa.types.is_integer(t) or pa.types.is_boolean(t) or pa.types.is_null(t):
        return 0, values.cast(pa.int64())
    return 2, values.cast(pa.binary())


def landed(r: Row) -> Any:
    return next((r[c] for c in ("whole", "real", "bytes") if r[c] is not None), None)


def as_values(found: list, like: pa.Array) -> pa.Array:
    """Values that travelled as `shipped`, in the type of others."""
    t = like.type
    if pa.types.is_decimal(t):
        return pa.array([None if v is None else Decimal(v).scaleb(-t.scale) if t.precision <= 18 else Decimal(v.decode()) for v in found], t)
    if pa.types.is_date(t):
        return pa.array(found, pa.int32()).cast(t)
    if pa.types.is_string(t) or pa.types.is_large_string(t):
        return pa.array([None if v is None else bytes(v).decode() for v in found], t)
    if pa.types.is_boolean(t):
        return pa.array([None if v is None else bool(v) for v in found], t)
    return pa.array(found, t)


class Held:
    """Counts of (group, value) by column. Of columns in `ranked` only so many points a group are handed on at once, each the
    highest of the values that it stands for: ranks among them are off by a share of 2 / POINTS at most."""

    def __init__(self, columns: int, ranked: set[int] = frozenset()):
        self.parts: list[list[pa.Table]] = [[] for _ in range(columns)]
        self.sizes, self.merged, self.ranked = [0] * columns, [0] * columns, ranked

    def take(self, i: int, values: pa.Array, rep: np.ndarray, n: np.ndarray) -> Iterator[pa.RecordBatch]:
        some = np.flatnonzero(n)
        self.parts[i].append(pa.table({"rep": pa.array(rep[some], pa.int32()), "value": values.take(pa.array(some)), "n": pa.array(n[some], pa.int64())}))
        self.sizes[i] += len(some)
        if self.sizes[i] > self.merged[i] + max(MERGE, self.merged[i]):
            self.merge(i)
            if self.sizes[i] > MOST:
                yield self.given(i)

    def merge(self, i: int) -> None:
        table = pa.concat_tables(self.parts[i]).group_by(["rep", "value"], use_threads=False).aggregate([("n", "sum")]).rename_columns(["rep", "value", "n"])
        self.parts[i], self.sizes[i], self.merged[i] = [table], table.num_rows, table.num_rows

    def given(self, i: int) -> pa.RecordBatch:
        table = self.parts[i][0]
        self.parts[i], self.sizes[i], self.merged[i] = [], 0, 0
        if i in self.ranked:
            table = points(table)
        at, values = shipped(table.column("value").combine_chunks())
        n = table.num_rows
        columns = [pa.nulls(n, pa.int64()), pa.nulls(n, pa.float64()), pa.nulls(n, pa.binary())]
        columns[at] = values
        return pa.RecordBatch.from_arrays([pa.array(np.full(n, i, np.int32)), table.column("rep").combine_chunks(), *columns, table.column("n").combine_chunks()], names=["i", "rep", "whole", "real", "bytes", "n"])

    def rest(self) -> Iterator[pa.RecordBatch]:
        for i, parts in enumerate(self.parts):
            if parts:
                self.merge(i)
                yield self.given(i)


def points(table: pa.Table) -> pa.Table:
    """Of each group the last value of every stretch of ranks, with the stretch's rows; a value that fills a stretch is one."""
    if table.num_rows <= POINTS:
        return table
    table = table.sort_by([("rep", "ascending"), ("value", "ascending")])
    rep, n = table.column("rep").to_numpy(), table.column("n").to_numpy()
    first = np.flatnonzero(np.diff(rep, prepend=-1))
    size = np.diff(np.append(first, len(rep)))
    total, upto = np.repeat(np.add.reduceat(n, first), size), np.cumsum(n)
    own = upto - np.repeat((upto - n)[first], size)
    stretch, full = (own - 1) * POINTS // total, n * POINTS >= total
    starts = np.flatnonzero((np.diff(stretch, prepend=-1) != 0) | (np.diff(rep, prepend=-1) != 0) | full | np.append(False, full[:-1]))
    out = table.take(pa.array(np.append(starts[1:], len(rep)) - 1))
    return out.set_column(out.schema.get_field_index("n"), "n", pa.array(np.add.reduceat(n, starts)))

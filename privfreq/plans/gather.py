"""Reading a sketch in place: a bounded table of cells travels to the items, which need no shuffle and no join."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql.types import DoubleType, LongType, StructField, StructType

from ..params import P31

#: Cells that a table may have: it is sent to every executor.
CELLS = 1 << 24


def dense(rows, n_rows: int, width: int, column: str, value: str) -> np.ndarray:
    """The n_rows x width integers of a collected state (pandas: j, column, value)."""
    if n_rows * width > CELLS:
        raise ValueError(f"a sketch of {n_rows} x {width} cells is too large to be sent around")
    out = np.zeros((n_rows, width), np.int64)
    out[rows["j"].to_numpy(np.int64), rows[column].to_numpy(np.int64)] = rows[value]
    return out


def gather(items: DataFrame, table: np.ndarray, hashes: list[tuple[int, int]], name: str = "s", combine: str = "sum", signs: list[tuple[int, int]] | None = None) -> DataFrame:
    """items (with key, and any other columns) and `name`: the sum, min or median of each item's cells over the rows.

    signs: a second family of hashes whose parity turns a cell's sign.
    """
    width = table.shape[1]
    sent = items.sparkSession.sparkContext.broadcast(table)
    kept = items.columns

    def run(batches):
        cells = sent.value
        for batch in batches:
            key = batch.column(kept.index("key")).to_numpy(zero_copy_only=False).astype(np.int64)
            rows = (cells[j, (a * key + b) % P31 % width] for j, (a, b) in enumerate(hashes))
            if signs is not None:
                rows = (v * (1 - 2 * ((a * key + b) % P31 % 2)) for v, (a, b) in zip(rows, signs, strict=True))
            if combine == "sum":
                value = np.zeros(len(key), np.int64)
                for v in rows:
                    value += v
            else:
                value = getattr(np, combine)(np.stack(list(rows)), axis=0) if len(key) else np.zeros(0, np.int64)
            kind = pa.float64() if combine == "median" else pa.int64()
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(value, kind)], [*kept, name])

    return items.mapInArrow(run, StructType([*items.schema.fields, StructField(name, DoubleType() if combine == "median" else LongType())]))


def butterfly(x: np.ndarray) -> np.ndarray:
    """The +-1 Hadamard transform of the last axis (a power of two)."""
    x = x.copy()
    h = 1
    while h < x.shape[-1]:
        y = x.reshape(*x.shape[:-1], -1, 2, h)
        x = np.stack([y[..., 0, :] + y[..., 1, :], y[..., 0, :] - y[..., 1, :]], axis=-2).reshape(x.shape)
        h *= 2
    return x

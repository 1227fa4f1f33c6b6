"""Shuffling numpy columns as blobs.

A map task cuts its rows by hash into as many parts as the shuffle has
partitions, and sends one row of packed arrays for each part.  This keeps the
bytes of a shuffle near those of the numbers themselves, and lets both sides
work on whole arrays.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from jointsem.llm.store import partitions


def schema(columns: dict[str, type]) -> str:
    return ", ".join(["part int", *(f"{c} binary" for c in columns)])


def arrow_schema(columns: dict[str, type]) -> pa.Schema:
    return pa.schema([("part", pa.int32()), *((c, pa.binary()) for c in columns)])


def pack(part: np.ndarray, columns: dict[str, np.ndarray]) -> pa.RecordBatch:
    """One row for each part that occurs, with the part's values of every column as bytes."""
    order = np.argsort(part, kind="stable")
    ids, first = np.unique(part[order], return_index=True)
    bounds = np.append(first, len(part))
    data: list[pa.Array] = [pa.array(ids.astype(np.int32))]
    for values in columns.values():
        values = np.ascontiguousarray(values[order])
        data.append(pa.array([values[a:b].tobytes() for a, b in zip(bounds[:-1], bounds[1:], strict=True)], pa.binary()))
    return pa.RecordBatch.from_arrays(data, names=["part", *columns])


def part_of(key: np.ndarray, parts: int) -> np.ndarray:
    return ((key >> np.uint64(32)) % np.uint64(parts)).astype(np.int32)


def parts_for(spark: SparkSession, size: int, per: int) -> int:
    """Enough parts for `size` bytes at `per` bytes each, and no fewer than the shuffle has partitions; so what a task holds does not grow with the input."""
    return max(partitions(spark), -(-int(size) // per))


def reduce_parts(df: DataFrame, parts: int, columns: dict[str, type], work: Callable[[dict[str, np.ndarray]], Iterator[pa.RecordBatch]], out: str) -> DataFrame:
    """Apply work to all rows of each part; part p is partition p of the shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, list[bytes]] = {c: [] for c in columns}
        for batch in batches:
            for c in columns:
                held[c] += batch.column(batch.schema.get_field_index(c)).to_pylist()
        if any(held.values()):
            yield from work({c: np.frombuffer(b"".join(held.pop(c)), kind) for c, kind in columns.items()})

    return df.repartitionById(parts, F.col("part")).mapInArrow(run, out)

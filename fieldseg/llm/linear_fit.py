"""Partition-summed normal equations: tasks add outer products, and the sums alone reach the driver."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame


def summed_products(rows: DataFrame, width: int, features: Callable[[pa.RecordBatch], Iterator[np.ndarray]]) -> np.ndarray:
    """Sum of M.T @ M over the matrices (rows x width) that `features` makes of each record batch.

    A task sends `width` rows, which are added up by row number, so the driver gets width * width numbers at any size of input.
    """

    def partial(batches):
        total = np.zeros((width, width))
        for rb in batches:
            for m in features(rb):
                total += m.T @ m
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(width)), pa.array([x.tobytes() for x in total], pa.binary())], ["i", "row"])

    def add(table):
        rows = table["row"].to_pylist()
        return pa.table({"i": table["i"][:1], "row": pa.array([np.sum([np.frombuffer(x) for x in rows], axis=0).tobytes()], pa.binary())})

    sums = rows.mapInArrow(partial, "i long, row binary").groupBy("i").applyInArrow(add, "i long, row binary")
    out = np.zeros((width, width))
    for r in sums.collect():
        out[r.i] = np.frombuffer(r.row)
    return out

"""Protocol runs inside Spark: tasks share blocks of rows, compute on the shares and open the results."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from .protocols import PROTOCOLS, Protocol

#: Rows of a block: a stage of gates works on a block at a time.
BLOCK_ROWS = 1 << 16


def seed_of(*numbers: int) -> int:
    """A seed for a protocol run, from where it runs: no two blocks of a job draw the same words."""
    out = 0x51ED2701
    for x in numbers:
        out = (out ^ (int(x) & (1 << 64) - 1)) * 0x9E3779B97F4A7C15 & (1 << 64) - 1
        out ^= out >> 29
    return out >> 1


def on_shares(df: DataFrame, columns: list[str], out: str, circuit: Callable[[Protocol, list], object], protocol: str, boolean: bool = True, keep: list[str] | None = None) -> DataFrame:
    """keep + ``out``: the opened result of a circuit on the shared columns (integers without nulls)."""
    keep = keep or []

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = TaskContext.get()
        where = task.partitionId() if task else 0
        for number, batch in enumerate(batches):
            for i in range(0, batch.num_rows, BLOCK_ROWS):
                part = batch.slice(i, BLOCK_ROWS)
                p = PROTOCOLS[protocol](seed=seed_of(where, number, i))
                shares = [p.share(part.column(part.schema.get_field_index(c)).to_numpy().astype(np.int64), boolean) for c in columns]
                result = circuit(p, shares)
                opened = p.open(result).view(np.int64)
                p.verify()
                yield pa.RecordBatch.from_arrays([*(part.column(part.schema.get_field_index(k)) for k in keep), pa.array(opened)], names=[*keep, out])

    kinds = {f.name: f.dataType.simpleString() for f in df.schema}
    return df.select(*dict.fromkeys([*keep, *columns])).mapInArrow(run, ", ".join([*(f"{k} {kinds[k]}" for k in keep), f"{out} long"]))


def sort_groups(df: DataFrame, group: str, key: str, sorter: Callable[[Protocol, np.ndarray], np.ndarray], protocol: str = "3p") -> DataFrame:
    """(group, place, key): each group's keys as one shared vector, sorted and opened. Groups must be of
    bounded size: this is the study of protocol costs, ``SealedFrame.sort`` is the operator for tables."""

    def run(part: pd.DataFrame) -> pd.DataFrame:
        p = PROTOCOLS[protocol](seed=seed_of(part[group].iloc[0], len(part)))
        keys = sorter(p, part[key].to_numpy(np.int64))
        return pd.DataFrame({group: part[group].iloc[0], "place": np.arange(len(keys)), key: keys})

    return df.select(group, key).groupBy(group).applyInPandas(run, f"{group} long, place long, {key} long")

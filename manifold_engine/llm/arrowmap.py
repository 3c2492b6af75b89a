"""Arrow-batched column builders that keep a frame's own columns."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

PIECE = 4 << 20


def pieces(batch: pa.RecordBatch | pa.Table, text: str, most: int = PIECE) -> Iterator[pa.RecordBatch | pa.Table]:
    """Row slices of about ``most`` bytes of text, one row at least."""
    sizes = pc.fill_null(pc.binary_length(batch.column(text)), 0)
    total = np.cumsum(sizes.to_numpy(zero_copy_only=False) if isinstance(sizes, pa.Array) else sizes.to_numpy())
    at, n = 0, batch.num_rows
    while at < n:
        past = total[at - 1] if at else 0
        end = max(at + 1, int(np.searchsorted(total, past + most, side="right")))
        yield batch.slice(at, end - at)
        at = end


def append_columns(df: DataFrame, text: str, make: Callable[[], Callable], fields: list[T.StructField], drop: tuple[str, ...] = ()) -> DataFrame:
    """``df`` with new columns computed from slices of Arrow batches.

    ``make()`` runs once per task and returns ``fn(slice) -> list of arrays``.
    A column of ``df`` with the name of a new one gives way to it.
    """
    new = {f.name for f in fields} | set(drop)
    kept = [f for f in df.schema.fields if f.name not in new]
    out = T.StructType(kept + fields)
    arrow = to_arrow_schema(T.StructType(fields))
    names = [f.name for f in kept]

    def run(batches):
        fn = make()
        for batch in batches:
            for part in pieces(batch, text):
                added = fn(part)
                new_arrays = [a if isinstance(a, pa.Array) else pa.array(a, arrow.field(i).type) for i, a in enumerate(added)]
                yield pa.RecordBatch.from_arrays([part.column(n) for n in names] + new_arrays, names=names + arrow.names)

    return df.mapInArrow(run, out)

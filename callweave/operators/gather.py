"""Map, then reduce in one place; or in a tree where the reduction allows."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from callweave.tables import settle


class TooLarge(ValueError):
    """What is to be gathered exceeds the stated bytes."""


def size_of(df: DataFrame) -> int:
    """Bytes of a frame as text and numbers, from one aggregate; a guard, not an account."""
    def width(field):
        kind, c = field.dataType.simpleString(), F.col(field.name)
        if kind in ("string", "binary"):
            return F.octet_length(c)
        return F.size(c) * 8 if kind.startswith("array") else F.lit(8)

    total = sum((F.coalesce(width(f), F.lit(0)) for f in df.schema), F.lit(0))
    return int(df.agg(F.coalesce(F.sum(total.cast("long")), F.lit(0))).first()[0])


def map_then_gather(df: DataFrame, map_fn: Callable[[DataFrame], DataFrame], reduce_fn: Callable, *, max_bytes: int = 1 << 30, where: str = "driver", schema: str | None = None):
    """reduce_fn over all mapped rows: in the driver (gets an Arrow table), in one task (pandas in and out), or "tree".

    A tree's reduce_fn turns a frame into an aggregated frame, and has no size
    limit. The others raise TooLarge before any row moves.
    """
    mapped = map_fn(df)
    if where == "tree":
        return reduce_fn(mapped)
    mapped = settle(mapped)
    if (size := size_of(mapped)) > max_bytes:
        raise TooLarge(f"{size} bytes to gather, {max_bytes} allowed; use where='tree'")
    if where == "driver":
        return reduce_fn(mapped.toArrow())

    def one(batches):
        yield from pa.Table.from_pandas(reduce_fn(pd.concat([b.to_pandas() for b in batches])), preserve_index=False).to_batches()

    return mapped.coalesce(1).mapInArrow(one, schema)


def gram(df: DataFrame, col: str) -> DataFrame:
    """(i, j, v): entries of the sum of outer products, by one dense matrix a batch; d * d numbers a task move."""
    import numpy as np

    def part(batches):
        for b in batches:
            if not b.num_rows:
                continue
            x = np.asarray(b.column(0).flatten(), float).reshape(b.num_rows, -1)
            g = x.T @ x
            i, j = np.indices(g.shape)
            yield pa.RecordBatch.from_arrays([pa.array(i.ravel().astype("int32")), pa.array(j.ravel().astype("int32")), pa.array(g.ravel())], ["i", "j", "v"])

    return df.where(F.col(col).isNotNull()).select(col).mapInArrow(part, "i int, j int, v double").groupBy("i", "j").agg(F.sum("v").alias("v"))

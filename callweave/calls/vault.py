"""Stored functions under content addresses; one generic worker runs any of them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from callweave.calls.closure import PackedClosure, pack_closure, unpack_closure


class FunctionVault:
    """Holds code, never data: its size is that of the functions stored."""

    def __init__(self, spark: SparkSession):
        self.spark, self.packed = spark, {}

    def store(self, fn: Callable) -> str:
        p = pack_closure(fn)
        self.packed[p.fn_id] = p
        return p.fn_id

    def load(self, fn_id: str) -> Callable:
        return unpack_closure(self.packed[fn_id].data)

    def broadcast(self):
        return self.spark.sparkContext.broadcast({k: p.data for k, p in self.packed.items()})

    def frame(self) -> DataFrame:
        return self.spark.createDataFrame([(p.fn_id, p.name, bytearray(p.data)) for p in self.packed.values()], "fn_id string, name string, code binary")

    def restore(self, frame: DataFrame) -> None:
        for r in frame.collect():
            self.packed[r["fn_id"]] = PackedClosure(bytes(r["code"]), r["fn_id"], r["name"])

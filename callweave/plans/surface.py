"""Methods as SQL functions: call register(spark) once a session."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F


@F.udtf(returnType="word string")
class Words:
    def eval(self, text: str):
        for w in (text or "").lower().split():
            yield (w,)


def register(spark: SparkSession) -> None:
    spark.udtf.register("callweave_words", Words)
    for statement in (
        "callweave_steps(ms DOUBLE, step_ms DOUBLE) RETURNS BIGINT RETURN ceil(ms / step_ms)",
        "callweave_fill_seconds(memory_mb DOUBLE, mb_per_s DOUBLE) RETURNS DOUBLE RETURN memory_mb / mb_per_s",
        "callweave_slowdown(ours DOUBLE, theirs DOUBLE) RETURNS DOUBLE RETURN ours / theirs - 1",
        "callweave_shard(k STRING, shards INT) RETURNS INT RETURN CAST(pmod(xxhash64(k), shards) AS INT)",
        "callweave_shuffle_files(parts BIGINT, rounds INT) RETURNS DOUBLE RETURN CASE WHEN rounds = 1 THEN power(parts, 2) ELSE round(rounds * power(parts, 1 + 1.0D / rounds)) END",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {statement}")

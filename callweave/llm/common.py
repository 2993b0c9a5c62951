"""Table access, shared scratch tables and small helpers of the llm operators."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Table `name` of the data folder, by any path that Spark can read."""
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def scratch(spark: SparkSession) -> str:
    """A new path below the folder that driver and executors share.

    That is spark.checkpoint.dir; where it is unset (tests, notebooks) the
    warehouse folder, which is shared by definition, serves instead.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        base = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/callweave_scratch"
    return f"{base.rstrip('/')}/cw-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """Write `df` to the shared folder and read it back: lineage ends here and a lost executor loses nothing.

    The files stay until the folder is emptied, since the frames built on them are lazy.
    """
    path = scratch(df.sparkSession)
    df.write.parquet(path)
    back = df.sparkSession.read.schema(df.schema).parquet(path)
    back._scratch_path = path
    return back


def forget(df: DataFrame) -> None:
    """Delete the files of a cut() that no later frame reads."""
    path = getattr(df, "_scratch_path", None)
    if path:
        spark = df.sparkSession
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def bounded_sample(df: DataFrame, key: str, rows: int) -> DataFrame:
    """At most `rows` rows: those whose `key` has the smallest hash, ties by key; the same on any partitioning.

    What can't be among them is filtered before anything is ordered, so the
    rows that meet are about 1.5 times the bound and not that many a partition.
    """
    n, place = df.count(), F.pmod(F.xxhash64(key), F.lit(1 << 40))
    if n > 2 * rows:
        df = df.where(place < int(1.5 * rows / n * (1 << 40)))
    return df.orderBy(place, key).limit(rows)


class Masked:
    """A frame with its columns renamed c0, c1, ..., so that no column of the caller's can clash with an operator's own.

    `col(name)` finds a column, `back()` selects the caller's columns under
    their names. Operators name their own columns otherwise than c and digits.
    """

    def __init__(self, df: DataFrame):
        self.names = df.columns
        self.df = df.toDF(*[f"c{i}" for i in range(len(self.names))])

    def name(self, of: str) -> str:
        return f"c{self.names.index(of)}"

    def col(self, of: str) -> Column:
        return F.col(self.name(of))

    def back(self, **changed: Column) -> list[Column]:
        return [changed.get(n, F.col(f"c{i}")).alias(n) for i, n in enumerate(self.names)]

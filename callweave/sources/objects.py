"""Whole-object storage by any Hadoop path, with append as immutable parts under one key."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


class ObjectStore:
    """Small control objects are read and written here by the driver; bulk data goes through run_map_objects and frames."""

    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root.rstrip("/")
        self.jvm = spark._jvm
        self.fs = self._path("").getFileSystem(spark._jsc.hadoopConfiguration())

    def _path(self, key: str):
        return self.jvm.org.apache.hadoop.fs.Path(f"{self.root}/{key}" if key else self.root)

    def put(self, key: str, data: bytes) -> None:
        """Write under a hidden name, then rename: readers see the whole object or none."""
        target, hidden = self._path(key), self._path(f"{key}.__writing")
        out = self.fs.create(hidden, True)
        try:
            out.write(bytearray(data))
        finally:
            out.close()
        if self.fs.exists(target):
            self.fs.delete(target, True)
        if not self.fs.rename(hidden, target):
            raise OSError(f"can't put {key}")

    def get(self, key: str) -> bytes:
        stream = self.fs.open(self._path(key))
        try:
            return bytes(self.jvm.org.apache.commons.io.IOUtils.toByteArray(stream))
        finally:
            stream.close()

    def exists(self, key: str) -> bool:
        return self.fs.exists(self._path(key))

    def delete(self, key: str) -> bool:
        return self.fs.delete(self._path(key), True)

    def list(self, prefix: str = "") -> list[str]:
        """Keys below a folder, sorted."""
        if not self.exists(prefix):
            return []
        found, out = self.fs.listFiles(self._path(prefix), True), []
        top = self.fs.makeQualified(self._path("")).toString().rstrip("/")
        while found.hasNext():
            out.append(found.next().getPath().toString().removeprefix(top).lstrip("/"))
        return sorted(k for k in out if not k.endswith(".__writing") and not k.rsplit("/", 1)[-1].startswith("."))

    def append(self, key: str, data: bytes) -> str:
        """Add an immutable part; parts sort in the order of appends."""
        parts = self.list(key)
        part = f"{key}/part-{int(parts[-1][-8:]) + 1 if parts else 0:08d}"
        self.put(part, data)
        return part

    def read_parts(self, key: str) -> bytes:
        return b"".join(self.get(p) for p in self.list(key))

    def compact(self, key: str) -> None:
        """Make one part of all, under the last one's name; it is complete before an old one goes. Not for use beside appends."""
        parts = self.list(key)
        if len(parts) > 1:
            self.put(parts[-1], self.read_parts(key))
            for p in parts[:-1]:
                self.delete(p)


def append_frame(df: DataFrame, path: str) -> None:
    df.write.mode("append").parquet(path)


def compact_frame(spark: SparkSession, path: str, target: str, files: int) -> None:
    """Rewrite many small files as `files` larger ones at another path."""
    spark.read.parquet(path).coalesce(files).write.mode("overwrite").parquet(target)

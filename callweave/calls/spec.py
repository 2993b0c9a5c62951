"""What a call may use and how often it is tried."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import SparkSession


@dataclass(frozen=True)
class RuntimeSpec:
    """Dependencies that every worker needs before the first call."""

    py_files: tuple[str, ...] = ()
    archives: tuple[str, ...] = ()
    env: dict[str, str] = field(default_factory=dict)
    packages: tuple[str, ...] = ()  # importable names; a worker that lacks one fails before its first call

    def install(self, spark: SparkSession) -> None:
        for p in self.py_files:
            spark.sparkContext.addPyFile(p)
        for p in self.archives:
            spark.sparkContext.addArchive(p)


@dataclass(frozen=True)
class CallLimits:
    """Ceilings of one call; the defaults are those of a common commercial function service."""

    seconds: float = 300.0
    memory_mb: int = 1536
    scratch_mb: int = 512


@dataclass(frozen=True)
class RetryPolicy:
    max_attempts: int = 3
    backoff_ms: int = 0
    retry_on: tuple[type[BaseException], ...] = (Exception,)

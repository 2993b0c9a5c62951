"""Session profiles. Queries never need them: they run in whatever session they are given."""

from __future__ import annotations

from pyspark.sql import SparkSession

LOCAL = {
    "spark.sql.shuffle.partitions": "8",
    "spark.sql.session.timeZone": "UTC",
    "spark.ui.enabled": "false",
    "spark.ui.showConsoleProgress": "false",
}
#: Remote storage has no locality to wait for; shuffle files move off nodes that leave; stragglers run twice.
CLUSTER = {
    "spark.sql.session.timeZone": "UTC",
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.locality.wait": "0s",
    "spark.dynamicAllocation.enabled": "true",
    "spark.dynamicAllocation.shuffleTracking.enabled": "true",
    "spark.decommission.enabled": "true",
    "spark.storage.decommission.shuffleBlocks.enabled": "true",
    "spark.speculation": "true",
    "spark.scheduler.mode": "FAIR",
    "spark.task.maxFailures": "8",
    "spark.sql.files.maxPartitionBytes": "1g",
    "spark.sql.adaptive.advisoryPartitionSizeInBytes": "256m",
    "spark.shuffle.push.enabled": "true",
}


def build_session(master: str = "local[*]", profile: dict[str, str] = LOCAL, app: str = "callweave", **more: str) -> SparkSession:
    builder = SparkSession.builder.master(master).appName(app)
    for k, v in {**profile, **more}.items():
        builder = builder.config(k, v)
    return builder.getOrCreate()

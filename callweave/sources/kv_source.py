"""Python data source "callweave_kv": a snapshot of a live key-value tier, one partition a shard."""

from __future__ import annotations

import json

from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage

from callweave.sources.kv_live import KvClient


class KvSource(DataSource):
    """Option `addresses`: JSON list of [host, port, secret], a shard each. Values are read and written as strings."""

    @classmethod
    def name(cls):
        return "callweave_kv"

    def schema(self):
        return "shard int, key string, value string"

    def reader(self, schema):
        return KvReader(json.loads(self.options["addresses"]))

    def writer(self, schema, overwrite):
        return KvWriter(json.loads(self.options["addresses"]))


class KvReader(DataSourceReader):
    def __init__(self, addresses):
        self.addresses = addresses

    def partitions(self):
        return [InputPartition(i) for i in range(len(self.addresses))]

    def read(self, partition):
        client = KvClient(self.addresses)
        try:
            for key, value in sorted(client.dump(partition.value).items()):
                yield partition.value, str(key), str(value)
        finally:
            client.close()


class KvWriter(DataSourceWriter):
    """Puts are idempotent, so a task that is tried again does no harm."""

    def __init__(self, addresses):
        self.addresses = addresses

    def write(self, iterator):
        client = KvClient(self.addresses)
        try:
            for row in iterator:
                client.put(row["key"], row["value"])
        finally:
            client.close()
        return WriterCommitMessage()

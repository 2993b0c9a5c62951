"""A key-value tier without servers: shards as append-only segments in the folder that driver and executors share.

Each attempt of a task writes segments of its own, one a shard, so attempts
never meet. What a value's put returns, its address, is the index; it travels as
rows of a frame, and what an attempt that failed has written is never named by
it. A get is one ranged read. There are tasks * shards objects, not one a value.
"""

from __future__ import annotations

import uuid
import zlib
from urllib.parse import quote

from pyarrow import fs


class KvLog:
    """Put and get by any path that pyarrow's file systems know. A writer closes it when done; then its values can be read."""

    def __init__(self, uri: str, shards: int):
        if uri.startswith("file:/") and not uri.startswith("file://"):
            uri = "file://" + uri.removeprefix("file:")
        self.fs, self.root = fs.FileSystem.from_uri(quote(uri, safe=":/@"))  # Hadoop's paths are not escaped
        self.shards, self.name, self.open = shards, uuid.uuid4().hex, {}

    def put(self, key, value: bytes) -> tuple[int, str, int]:
        """(shard, segment, place) of the value."""
        shard = zlib.crc32(repr(key).encode()) % self.shards
        if shard not in self.open:
            self.fs.create_dir(f"{self.root}/shard={shard}", recursive=True)
            self.open[shard] = self.fs.open_output_stream(f"{self.root}/shard={shard}/{self.name}")
        out = self.open[shard]
        place = out.tell()
        out.write(value)
        return shard, self.name, place

    def get(self, shard: int, segment: str, place: int, size: int) -> bytes:
        with self.fs.open_input_file(f"{self.root}/shard={shard}/{segment}") as f:
            f.seek(place)
            data = f.read(size)
        if len(data) != size:
            raise EOFError(f"segment {segment} of shard {shard} ends before {place + size}")
        return data

    def close(self) -> None:
        for out in self.open.values():
            out.close()
        self.open = {}

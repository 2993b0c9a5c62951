"""Two-stage range sort: ranges by splitters, then a sort within each range; ranks, validation, and rounds for large inputs."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from callweave.measures.quantiles import exact_quantiles
from callweave.tables import bucketed, delete, exists, qualified, settle, shared_path, spread


def required_tasks(total_bytes: float, task_bytes: float = 400e6) -> int:
    """Tasks a stage needs when one holds `task_bytes` of the data in memory."""
    return max(1, math.ceil(total_bytes / task_bytes))


def choose_splitters(df: DataFrame, key: str, parts: int, share: float = 1.0, exact: bool = False) -> list:
    """`parts` - 1 bounds of equal shares; sampled by the hash of the row's content, so that a retry samples alike.

    Exact ones are for numbers; no task holds all values for them.
    """
    shares = [i / parts for i in range(1, parts)]
    if not shares:
        return []
    if exact:
        found = exact_quantiles(df.select(F.lit(0).alias("__all"), F.col(key).alias("__key")), "__all", "__key", {f"q{i}": s for i, s in enumerate(shares)}).first()
        return [found[f"q{i}"] for i in range(len(shares))] if found else []
    if share < 1:
        df = df.where(F.pmod(F.xxhash64(*df.columns), F.lit(1_000_000)) < int(share * 1_000_000))
    return df.agg(F.percentile_approx(key, shares, 10_000)).first()[0]


def range_id(key: Column, splitters: list) -> Column:
    """Number of splitters that are at most `key`."""
    out = F.lit(0)
    for s in splitters:
        out = out + F.when(key >= s, 1).otherwise(0)
    return out


#: Bits of monotonically_increasing_id that count rows within a partition; the others hold the partition's number.
ROW_BITS = 33


def _place(sorted_df: DataFrame) -> DataFrame:
    """Write sorted partitions with their number and each row's place, both read off one running id: no further shuffle."""
    at = F.monotonically_increasing_id()
    marked = sorted_df.withColumn("__at", at)
    place = marked.withColumn("part_id", F.shiftright("__at", ROW_BITS).cast("int")).withColumn("pos", F.col("__at").bitwiseAND(F.lit((1 << ROW_BITS) - 1)))
    return settle(place.drop("__at"))


def sample_bounds(df: DataFrame, keys: list[str], parts: int, oversample: int = 64) -> DataFrame:
    """One row (bounds): `parts` - 1 key tuples that cut `df` into about equal ranges, stored.

    They come from about `oversample` rows a part, chosen by the hash of their
    keys, so that a retry samples alike; that sample is sorted in one task.
    """
    n, key = df.count(), F.struct(*keys)
    share = min(1.0, oversample * parts / max(1, n))
    picked = df.where(F.pmod(F.xxhash64(*keys), F.lit(1 << 30)) < int(share * (1 << 30))) if share < 1 else df
    kept = picked.agg(F.array_sort(F.collect_list(key)).alias("kept"))
    at = F.transform(F.sequence(F.lit(1), F.lit(max(1, parts - 1))), lambda i: F.floor(i * F.size("kept") / parts).cast("int"))
    chosen = F.when((F.size("kept") > 0) & F.lit(parts > 1), F.transform(at, lambda i: F.col("kept")[i])).otherwise(F.slice("kept", 1, 0))
    return settle(kept.select(chosen.alias("bounds")))


def find_range(key: Column, bounds: Column) -> Column:
    """Number of sorted `bounds` that are at most `key`, by halving."""
    low, high = F.lit(0), F.size(bounds)
    steps = F.sequence(F.lit(1), F.ceil(F.log2(F.size(bounds) + 1)).cast("int") + 1)

    def halve(s, _):
        mid = F.floor((s["low"] + s["high"]) / 2).cast("int")
        open_, right = s["low"] < s["high"], F.get(bounds, mid) <= key
        return F.struct(F.when(open_ & right, mid + 1).otherwise(s["low"]).alias("low"), F.when(open_ & ~right, mid).otherwise(s["high"]).alias("high"))

    return F.aggregate(steps, F.struct(low.alias("low"), high.alias("high")), halve)["low"]


def range_sort(df: DataFrame, keys: list[str], parts: int, rounds: int = 1, shuffle: str = "native", shards: int = 4) -> DataFrame:
    """`df` with part_id and pos, sorted by `keys` within parts and parts in order of keys.

    "native" moves every row once through Spark's shuffle. "objects" has each map
    task write an object per range, and one task per range read and sort its
    objects; there is no exchange. "kv" does the same with blocks in a key-value
    tier of `shards`, kept as logs in the shared folder. Two rounds write to about sqrt(parts) coarse
    ranges first and from each of them to its own fine ranges: 2 * parts**1.5
    objects instead of parts**2, and no task ever holds more than its share of
    the input or one fine range. part_id is written before use, because sampled
    bounds differ between runs of the native way.
    """
    if rounds == 1 and shuffle == "native":
        return _place(df.repartitionByRange(parts, *keys).sortWithinPartitions(*keys))
    bounds = sample_bounds(df, keys, parts)
    tagged = spread(df).crossJoin(F.broadcast(bounds)).withColumn("part_id", find_range(F.struct(*keys), F.col("bounds"))).drop("bounds")  # one row
    if shuffle == "kv":
        return sort_through_kv(tagged, keys, parts, shards)
    if rounds > 1:
        tagged = _coarse(tagged, parts)
    with bucketed(tagged, parts, "part_id") as ranges:
        return settle(sorted_ranges(ranges, keys))


def sorted_ranges(ranges: DataFrame, keys: list[str]) -> DataFrame:
    """Rows of stored ranges with their place: a task's ranges are sorted where they are read."""
    return ranges.withColumn("pos", (F.row_number().over(Window.partitionBy("part_id").orderBy(*keys)) - 1).cast("long"))


def _coarse(tagged: DataFrame, parts: int) -> DataFrame:
    """The first round: rows stored by coarse range, read back so that a task's rows are of one coarse range."""
    spark, path, fine = tagged.sparkSession, shared_path(tagged.sparkSession), math.ceil(parts / max(1, math.isqrt(parts)))
    tagged.withColumn("coarse", F.floor(F.col("part_id") / fine).cast("int")).write.partitionBy("coarse").parquet(path)
    out = None
    for c in range(math.ceil(parts / fine)):
        if not exists(spark, f"{path}/coarse={c}"):
            continue
        part = spark.read.schema(tagged.schema).parquet(f"{path}/coarse={c}")
        out = part if out is None else out.union(part)
    return tagged if out is None else out


def sort_through_kv(tagged: DataFrame, keys: list[str], parts: int, shards: int, block_bytes: int = 32 << 20) -> DataFrame:
    """Rows tagged with part_id, sorted by way of a key-value tier: a block for each map task and range, more where a task's rows exceed `block_bytes`.

    A reducer gets the blocks of its range, one at a time, and Spark sorts its
    rows, on disk where memory ends. Rows take no part in an exchange, only the
    addresses of blocks do. Neither the driver nor a Python worker ever holds
    more than one buffer of blocks.
    """
    import pyarrow as pa
    from pyspark import TaskContext

    from callweave.sources.kv_log import KvLog

    spark, path = tagged.sparkSession, shared_path(tagged.sparkSession)
    uri = qualified(spark, path)

    def put(batches):
        tier, task, held, size = KvLog(uri, shards), TaskContext.get().partitionId(), [], 0

        def flush():
            table = pa.Table.from_batches(held).sort_by("part_id")
            ids = table["part_id"].to_numpy()
            starts = [0, *(np.flatnonzero(np.diff(ids)) + 1).tolist(), len(ids)]
            out = []
            for a, b in zip(starts, starts[1:]):
                block = table.slice(a, b - a).combine_chunks()
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, block.schema) as stream:
                    stream.write_table(block, 1 << 14)
                data = sink.getvalue()
                out.append((task, int(ids[a]), b - a, data.size, *tier.put((task, int(ids[a])), data)))
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), kinds)], names)

        kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.string(), pa.int64()]
        names = ["map_id", "reduce_id", "rows", "bytes", "shard", "segment", "place"]
        found = []
        for b in batches:
            if b.num_rows:
                held, size = [*held, b], size + b.nbytes
            if size >= block_bytes:
                found.append(flush())
                held, size = [], 0
        if held:
            found.append(flush())
        tier.close()  # before any address leaves the task
        yield from found

    def take(batches):
        tier = KvLog(uri, shards)
        for b in batches:
            for at in b.to_pylist():
                yield from pa.ipc.open_stream(tier.get(at["shard"], at["segment"], at["place"], at["bytes"]))

    try:
        blocks = settle(tagged.mapInArrow(put, "map_id int, reduce_id int, rows long, bytes long, shard int, segment string, place long"))
        rows = blocks.repartitionById(parts, "reduce_id").mapInArrow(take, tagged.schema)  # a range a task
        out = _place(rows.drop("part_id").sortWithinPartitions(*keys)).select(*tagged.columns, "pos")
        out.blocks = blocks
        return out
    finally:
        delete(spark, path)


def with_global_rank(placed: DataFrame, name: str = "rk") -> DataFrame:
    """Ranks 1..n over range-sorted rows: the place in the part plus the broadcast counts of the parts before (one row a part)."""
    counts = placed.groupBy("part_id").agg(F.count(F.lit(1)).alias("n"))
    before = counts.select("part_id", F.coalesce(F.sum("n").over(Window.orderBy("part_id").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    return placed.join(F.broadcast(before), "part_id").withColumn(name, F.col("before") + F.col("pos") + 1).drop("before")


def validate_sorted(placed: DataFrame, keys: list[str], chunk: int = 1_000_000) -> DataFrame:
    """One row: rows, breaks of order within parts, breaks between neighbouring parts, and a checksum of the multiset of rows.

    Rows are compared with their neighbours within chunks of a part, chunks by
    their ends, so that a check of the largest part is spread too.
    """
    key = F.struct(*keys)
    data = [c for c in placed.columns if c not in ("part_id", "pos")]
    cut = placed.withColumn("chunk", F.floor(F.col("pos") / chunk))
    pairs = cut.withColumn("prev", F.lag(key).over(Window.partitionBy("part_id", "chunk").orderBy("pos")))
    chunks = pairs.groupBy("part_id", "chunk").agg(
        F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("prev") > key, 1)).alias("within"), F.sum(F.xxhash64(*data).cast("decimal(38,0)")).alias("checksum"), F.min(key).alias("low"), F.max(key).alias("high")
    )
    order = Window.orderBy("part_id", "chunk")
    ends = chunks.withColumn("prev", F.lag("high").over(order)).withColumn("other", F.lag("part_id").over(order) != F.col("part_id"))
    broken = F.col("prev") > F.col("low")
    return ends.agg(
        F.coalesce(F.sum("n"), F.lit(0)).alias("n"),
        (F.coalesce(F.sum("within"), F.lit(0)) + F.count(F.when(broken & ~F.col("other"), 1))).alias("within"),
        F.count(F.when(broken & F.col("other"), 1)).alias("between"),
        F.sum("checksum").alias("checksum"),
    )


def kv_shuffle_load(blocks: DataFrame, shards: int) -> DataFrame:
    """(shard, requests, bytes): what a key-value shuffle asks of each shard, a put and a get for every block of census()."""
    shard = F.pmod(F.col("map_id") * 31 + F.col("reduce_id"), F.lit(shards)).cast("int")
    return blocks.groupBy(shard.alias("shard")).agg((2 * F.count(F.lit(1))).alias("requests"), F.sum("bytes").alias("bytes"))


def shuffle_seconds(parts: int, total_bytes: float, workers: int, requests_per_s: float, bytes_per_s_worker: float) -> float:
    """Time to write and read all blocks: the slower of the medium's request rate and the workers' bandwidth."""
    return 2 * max(parts * parts / requests_per_s, total_bytes / (workers * bytes_per_s_worker))


def census(df: DataFrame, map_id: Column, reduce_id: Column, size: Column) -> DataFrame:
    """(map_id, reduce_id, rows, bytes) of the blocks that a shuffle would move."""
    return df.groupBy(map_id.alias("map_id"), reduce_id.alias("reduce_id")).agg(F.count(F.lit(1)).alias("rows"), F.sum(size).alias("bytes"))


def shuffle_files(parts: int, rounds: int = 1) -> int:
    """Intermediate objects of a sort into `parts` parts: the square in one round, k * parts**(1 + 1/k) in k."""
    return parts * parts if rounds == 1 else round(rounds * parts ** (1 + 1 / rounds))

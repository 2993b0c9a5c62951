"""Map-reduce and word count: native, opaque, with or without combining, by Spark's shuffle or by stored objects."""

from __future__ import annotations

from collections.abc import Callable, Iterable

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from callweave.tables import bucketed, settle, spread

#: Reducers with an equal aggregate: they combine before the shuffle and stay in the JVM.
NATIVE_REDUCERS = {"sum": F.sum, "min": F.min, "max": F.max, "count": F.count}


def through_objects(df: DataFrame, keys: list[str], parts: int, fold: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """`fold` of rows that are shuffled by storage instead of an exchange: each task writes an object per
    bucket of `keys`, a reducer reads the objects of its bucket and folds them. The result is stored."""
    with bucketed(df, parts, *keys) as stored:
        return settle(fold(stored))


def read_lines(spark: SparkSession, path: str, blocks: bool = True) -> DataFrame:
    """Lines of text objects: in parallel block reads, or each object by one task as a single read."""
    if blocks:
        return spark.read.text(path).select(F.col("value").alias("line"))
    whole = spark.read.option("wholetext", True).text(path)
    return whole.select(F.explode(F.split(F.regexp_replace("value", "\n\\z", ""), "\n")).alias("line"))


def map_reduce(
    df: DataFrame,
    mapper: Callable[[dict], Iterable[tuple]],
    reducer: str | Callable[[object, Iterable], object],
    key_type: str,
    value_type: str,
    result_type: str,
    *,
    parts: int | None = None,
    combine: bool = True,
    shuffle: str = "native",
) -> DataFrame:
    """(key, result) of mapper(row) -> (key, value) pairs and a reducer: a name of NATIVE_REDUCERS or f(key, values).

    A named reducer combines on the map side unless `combine` is off. An opaque
    one sees all values of a key at once; use it for keys of bounded size.
    """
    schema = f"key {key_type}, value {value_type}"

    def emit(frames):
        for frame in frames:
            yield pd.DataFrame([kv for row in frame.to_dict("records") for kv in mapper(row)], columns=["key", "value"], dtype=object)

    pairs = df.mapInPandas(emit, schema)
    if shuffle == "objects" and isinstance(reducer, str):
        named = NATIVE_REDUCERS[reducer]("value").cast(result_type).alias("result")
        return through_objects(pairs, ["key"], parts or 8, lambda stored: stored.groupBy("key").agg(named))
    if isinstance(reducer, str):
        if not combine:
            pairs = pairs.repartition(parts, "key") if parts else pairs.repartition("key")
        return pairs.groupBy("key").agg(NATIVE_REDUCERS[reducer]("value").cast(result_type).alias("result"))
    if parts and shuffle != "objects":
        pairs = pairs.repartition(parts, "key")
    out = T._parse_datatype_string(f"key {key_type}, result {result_type}")

    def fold(key, frame):
        return pd.DataFrame([(key[0], reducer(key[0], frame["value"].tolist()))], columns=["key", "result"], dtype=object)

    reduced = lambda rows: rows.groupBy("key").applyInPandas(fold, out)
    return through_objects(pairs, ["key"], parts or 8, reduced) if shuffle == "objects" else reduced(pairs)


def _pieces(text: Column) -> Column:
    """Lower-case pieces between single blanks, empty ones included: a split on one character needs no regular expression."""
    return F.split(F.translate(F.lower(text), "\t\n\x0b\f\r", "     "), " ")


def words(text: Column, pattern: str | None = None) -> Column:
    """Lower-case tokens: split at white space without empty ones, or all matches of `pattern`."""
    low = F.lower(text)
    if pattern:
        return F.regexp_extract_all(low, F.lit(pattern), 0)
    return F.filter(_pieces(text), lambda w: w != "")


def word_count(
    df: DataFrame,
    col: str = "text",
    *,
    parts: int | None = None,
    combine: bool = True,
    pattern: str | None = None,
    by: list[str] | None = None,
    shuffle: str = "native",
) -> DataFrame:
    """(*by, word, n). The plan is scan, explode, partial count, one shuffle by word, final count."""
    keys = [*(by or []), "word"]
    pieces = words(F.col(col), pattern) if pattern else _pieces(F.col(col))
    tokens = spread(df.select(*(by or []), col)).select(*(by or []), F.explode(pieces).alias("word")).where("word <> ''")
    counted = lambda rows: rows.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"))
    if shuffle == "objects":
        return through_objects(tokens, keys, parts or 8, counted)
    if not combine:
        tokens = tokens.repartition(parts, *keys) if parts else tokens.repartition(*keys)
    return counted(tokens)


def word_count_opaque(df: DataFrame, col: str = "text", parts: int | None = None, shuffle: str = "native") -> DataFrame:
    """The same counts by Python functions: what stateless calls would do, combining within a batch, by Spark's shuffle or by objects."""
    from collections import Counter

    def tokens(frames):
        for frame in frames:
            count = Counter(w for t in frame[col].dropna() for w in t.lower().split())
            yield pd.DataFrame({"word": list(count.keys()), "n": list(count.values())})

    part = spread(df.select(col)).mapInPandas(tokens, "word string, n long")
    if shuffle == "objects":
        return through_objects(part, ["word"], parts or 8, lambda stored: stored.groupBy("word").agg(F.sum("n").alias("n")))
    if parts:
        part = part.repartition(parts, "word")
    return part.groupBy("word").agg(F.sum("n").alias("n"))


def postings(df: DataFrame, id_col: str, col: str, block: int = 4096) -> DataFrame:
    """(word, block, ids): sorted distinct ids of the texts that hold each word, in blocks of consecutive ids.

    Blocks are ranges of `block` ids, so a row is bounded however frequent its word is.
    """
    pairs = df.select(F.col(id_col).alias("id"), F.explode(F.array_distinct(words(F.col(col)))).alias("word"))
    ids = F.array_sort(F.collect_set("id"))
    return pairs.groupBy("word", F.floor(F.col("id") / block).alias("block")).agg(ids.alias("ids"))

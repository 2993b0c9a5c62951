"""SimHash near-duplicates by multi-index hashing over 64-bit fingerprints.

Fingerprint: majority bits of XXH64 over word shingles. Links: fingerprints at
Hamming distance <= 2. The fingerprint is cut into two 32-bit segments, each
indexed by its value. A pair at distance <= 2 either differs by at most one bit
in the upper segment or not at all in the lower one, so a fingerprint probes the
upper index with its radius-1 ball (33 values) and the lower one with its own
value; matches are verified on all 64 bits.

A bucket holding more than `hot_bucket` distinct fingerprints is not expanded
into pairs. Whatever probes such a bucket takes an exact second way: it emits
the radius-1 ball of each segment with the other segment unchanged (65 keys);
two fingerprints share a key exactly when they differ by two bits at most, and
no key can have over 65 members, however large the group of near copies is.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from callweave.llm.common import Masked, cut, forget
from callweave.llm.components import components
from callweave.tables import spread


def fingerprint(text: str | None, shingle: int = 3, seed: int = 42) -> int:
    """Unsigned SimHash of a text; no words (null, empty, blanks only): 0.

    ASCII capitals are lowered, words end at ASCII white space, repeats count;
    a text shorter than a shingle is one shingle. A bit needs over half the votes.
    """
    words = (text or "").encode("utf-8").lower().split()
    if not words:
        return 0
    if len(words) < shingle:
        return _votes([b" ".join(words)], seed)
    line = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[: len(words) - shingle] + 1))
    return _votes([line[a:b] for a, b in zip(starts.tolist(), ends[shingle - 1 :].tolist())], seed)


def _votes(shingles: list[bytes], seed: int, block: int = 1 << 14) -> int:
    count = np.zeros(64, np.int64)
    for at in range(0, len(shingles), block):
        part = shingles[at : at + block]
        h = np.array([xxhash.xxh64_intdigest(s, seed) for s in part], dtype="<u8")
        count += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = (2 * count > len(shingles)).astype(np.uint8)
    return int(np.packbits(bits, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, mark: bool = False) -> DataFrame:
    """(doc_id, fp long) of every whole text, and `mark`, the text's own hash, if asked for; no shuffle."""
    names = ["doc_id", "fp", "mark"][: 3 if mark else 2]

    def run(batches):
        for batch in batches:
            fps = [fingerprint(t.as_py(), shingle) for t in batch.column(1)]
            signed = pa.array(np.array(fps, dtype=np.uint64).view(np.int64), pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), signed, *batch.columns[2:]], names)

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    if mark:
        rows = rows.withColumn("mark", F.xxhash64("text"))
    return spread(rows, "doc_id").mapInArrow(run, ", ".join(f"{n} long" for n in names))


def _segments(fp):
    return F.shiftrightunsigned(fp, 32), fp.bitwiseAND(F.lit(0xFFFFFFFF))


def _ball(value, bits: int, low: int = 0):
    """`value` and all values that differ from it in one of `bits` bits from bit `low` on."""
    return F.concat(
        F.array(value),
        F.transform(
            F.sequence(F.lit(low), F.lit(low + bits - 1)),
            lambda i: value.bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), i)),
        ),
    )


def near_pairs(classes: DataFrame, hot_bucket: int = 64) -> DataFrame:
    """Edges (a, b) that connect all of `classes` (fp, rep; one row per fingerprint) at distance <= 2."""
    fp = F.col("fp")
    upper, lower = _segments(fp)
    slot = lambda seg, value: F.struct(F.lit(seg).alias("seg"), value.alias("val"))
    index = classes.select(F.explode(F.array(slot(0, upper), slot(1, lower))).alias("s"), "fp", "rep").select("s.*", "fp", "rep")
    sizes = index.groupBy("seg", "val").agg(F.count(F.lit(1)).alias("n"))
    hot = cut(sizes.where(F.col("n") > hot_bucket).select("seg", "val", F.lit(True).alias("hot")))
    probes = classes.select(
        F.explode(F.concat(F.array(slot(1, lower)), F.transform(_ball(upper, 32), lambda v: slot(0, v)))).alias("s"), "fp", "rep"
    ).select("s.*", "fp", "rep")

    matched = probes.alias("p").join(index.join(hot, ["seg", "val"], "left_anti").alias("t"), ["seg", "val"]).where(
        (F.bit_count(F.col("p.fp").bitwiseXOR(F.col("t.fp"))) <= 2) & (F.col("p.rep") != F.col("t.rep"))
    )
    light = matched.select(F.col("p.rep").alias("a"), F.col("t.rep").alias("b"))
    if hot.isEmpty():
        return light

    dense = probes.join(hot, ["seg", "val"], "left_semi").select("fp", "rep").distinct()
    keys = F.array_union(_ball(F.col("fp"), 32), _ball(F.col("fp"), 32, 32))
    met = (
        dense.select(F.explode(keys).alias("key"), "fp", "rep")
        .groupBy("key")
        .agg(F.array_sort(F.collect_list(F.struct("rep", "fp"))).alias("met"))
        .where(F.size("met") > 1)
        .select(F.col("met")[0].alias("first"), F.explode("met").alias("other"))
        .where("first.rep <> other.rep")
        .where(F.bit_count(F.col("first.fp").bitwiseXOR(F.col("other.fp"))) <= 2)
        .select(F.col("first.rep").alias("a"), F.col("other.rep").alias("b"))
        .distinct()
    )
    return light.unionByName(met)


def simhash_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", hot_bucket: int = 64) -> DataFrame:
    """(doc_id, fingerprint, component_id) of each row.

    component_id is the smallest doc_id reachable by links. Rows whose id is
    null keep a fingerprint and a null component. Texts without words share the
    fingerprint zero and link like any other. Repeated ids stay repeated rows.
    An empty table gives an empty table.
    """
    fps = cut(fingerprints(docs, id_col, text_col))
    classes = cut(fps.where("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("rep")))
    comp = components(near_pairs(classes, hot_bucket))
    named = cut(
        classes.join(comp.withColumnRenamed("node", "rep"), "rep", "left").select(
            "fp", F.coalesce("component", "rep").alias("component_id")
        )
    )
    forget(classes)
    return fps.join(named, "fp", "left").select(
        "doc_id",
        F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"),
        F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"),
    )


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of `docs` per group, with all its columns: the smallest id's, then fingerprint's, then text hash's.

    Groups are of fingerprints, so rows that share an id are told apart by their
    texts. Rows with a null id can't be named as a group's smallest and are kept.
    """
    fps = fingerprints(docs, id_col, text_col, mark=True).where("doc_id is not null")
    classes = cut(fps.groupBy("fp").agg(F.min(F.struct("doc_id", "fp", "mark")).alias("first")))
    comp = components(near_pairs(classes.select("fp", F.col("fp").alias("rep")))).withColumnRenamed("node", "fp")
    groups = classes.join(comp, "fp", "left").groupBy(F.coalesce("component", "fp").alias("group"))
    return pick(docs, cut(groups.agg(F.min("first").alias("f"))), id_col, text_col)


def pick(docs: DataFrame, kept: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """One row of `docs` for each of `kept` (f: doc_id and mark, the text's hash), and the rows whose id is null."""
    m = Masked(docs)
    kept = kept.select(F.col("f.doc_id").alias("keep"), F.col("f.mark").alias("mark"))
    same_text = F.xxhash64(m.col(text_col).cast("string"))
    named = m.df.join(kept, (m.col(id_col) == F.col("keep")) & (same_text == F.col("mark")), "left_semi")
    named = named.withColumn("mark", same_text).dropDuplicates([m.name(id_col), "mark"]).drop("mark")
    return named.union(m.df.where(m.col(id_col).isNull())).select(m.back())

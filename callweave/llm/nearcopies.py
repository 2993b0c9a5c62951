"""Near copies by word shingles: documents whose sets of shingles have a Jaccard similarity of `least` or more.

Documents with the same set are one node, named by a 64-bit digest of the set.
Candidates meet in one of 40 bands of six min-hashes each, so a pair exactly at
0.8 is missed with a chance of (1 - 0.8^6)^40 = 5 in a million, one at 0.9 with
2 in 10^14. Of what meets, pairs whose one-bit min-hashes (240 bits a node) differ
in over 52 places are left out before their sets are fetched: at 0.8 a tenth of
the bits differ, and over 52 do with a chance of 1 in ten million; documents that
merely share a passage, at 0.25, differ in 90. The others are verified on the
whole sets, never estimated, but for one last test where buckets are compared in
pairs: there the low bytes of all min-hashes must agree in 168 places of 240,
which a pair exactly at 0.8 misses with a chance of 3 in 100,000, one at 0.82 of
one in a million, and most pairs around 0.65 do.

A band's bucket is not expanded into pairs. Its members are first compared with
one pivot each, by a few bands, then by all, leaving out pairs that are connected
already. The pivot is the member that meets most others over all its bands: of
copies with different edits that is their original, to which each of them is
more similar than to one another. What is compared in pairs at last
are the members outside the largest connected group of their bucket, with all
that they aren't connected to. A large group of near copies thus costs
comparisons in proportion to its size; only a large bucket whose members are
not similar to one another would cost its square.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from callweave.llm.common import Masked, cut, forget
from callweave.llm.components import components
from callweave.llm.simhash import fingerprint, near_pairs
from callweave.tables import bucketed, spread

SHINGLE, LEAST = 5, 0.8
BANDS, ROWS, FIRST_BANDS = 40, 6, 4


def shingle_set(text: str | None, shingle: int = SHINGLE) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a text's word shingles; words as for fingerprints, a shorter text is one shingle."""
    words = (text or "").encode("utf-8").lower().split()
    n = max(1, len(words) - shingle + 1) if words else 0
    return np.unique(np.array([xxhash.xxh64_intdigest(b" ".join(words[i : i + shingle])) for i in range(n)], np.uint64))


def band_keys(hashes: np.ndarray, block: int = 1 << 12) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """One 64-bit key a band, equal where all the band's min-hashes are; of each min-hash one bit, and one byte, in 64-bit words."""
    rng = np.random.default_rng(8)
    flip, times = rng.integers(0, 1 << 64, (2, BANDS * ROWS, 1), np.uint64)
    times |= np.uint64(1)
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max)
    for at in range(0, len(hashes), block):
        least = np.minimum(least, ((hashes[None, at : at + block] ^ flip) * times).min(axis=1))
    keys = np.array([xxhash.xxh64_intdigest(least[b * ROWS : (b + 1) * ROWS].tobytes(), b) for b in range(BANDS)], np.uint64)
    bits = np.packbits((least >> np.uint64(23) & np.uint64(1)).astype(np.uint8))
    return keys, np.pad(bits, (0, -len(bits) % 8)).view(np.uint64), (least >> np.uint64(32)).astype(np.uint8).view(np.uint64)


def sketches(docs: DataFrame, id_col: str, text_col: str, shingle: int = SHINGLE) -> DataFrame:
    """(doc_id, mark, fp, node, size, bands, sig, fine) of each row that has an id; mark is the hash of the text itself, fp its SimHash."""
    none = np.zeros(0, np.uint64)

    def lists(arrays):
        flat = pa.array(np.concatenate([none, *arrays]).view(np.int64), pa.int64())
        return pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, arrays)]), pa.int32()), flat)

    def run(batches):
        for batch in batches:
            fps, nodes, sizes, sketched = [], [], [], []
            for t in batch.column(2):
                t = t.as_py()
                s = shingle_set(t, shingle)
                fps.append(fingerprint(t))
                nodes.append(xxhash.xxh3_64_intdigest(s.tobytes()))
                sizes.append(len(s))
                sketched.append(band_keys(s) if len(s) else (none, none, none))
            fps, nodes = (pa.array(np.array(x, np.uint64).view(np.int64), pa.int64()) for x in (fps, nodes))
            out = [batch.column(0), batch.column(1), fps, nodes, pa.array(sizes, pa.int32()), *(lists([x[i] for x in sketched]) for i in range(3))]
            yield pa.RecordBatch.from_arrays(out, ["doc_id", "mark", "fp", "node", "size", "bands", "sig", "fine"])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text_col).alias("mark"), F.col(text_col).cast("string").alias("text"))
    return spread(rows.where("doc_id is not null"), "doc_id").mapInArrow(run, "doc_id long, mark long, fp long, node long, size int, bands array<long>, sig array<long>, fine array<long>")


def _sets(rows: DataFrame, shingle: int) -> DataFrame:
    """(node, hashes array<long>) of (node, text) rows."""

    def run(batches):
        for batch in batches:
            sets = [shingle_set(t.as_py(), shingle).view(np.int64) for t in batch.column(1)]
            ends = pa.array(np.cumsum([0, *map(len, sets)]), pa.int32())
            flat = pa.array(np.concatenate([np.zeros(0, np.int64), *sets]), pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(ends, flat)], ["node", "hashes"])

    return rows.mapInArrow(run, "node long, hashes array<long>")


def _alike(pairs: DataFrame, sets: DataFrame, least: float) -> DataFrame:
    """Those of the pairs (a, b) whose sets are that similar."""
    one = lambda c: sets.select(F.col("node").alias(c), F.col("hashes").alias(f"h{c}"))
    both = pairs.join(one("a"), "a").join(one("b"), "b")
    met, total = F.size(F.array_intersect("ha", "hb")), F.size("ha") + F.size("hb")
    return both.where(met >= F.lit(least) * (total - met) - F.lit(1e-9)).select("a", "b")


def most_apart(least: float) -> int:
    """Differing one-bit min-hashes that a pair of that similarity doesn't exceed, by six standard deviations."""
    n, share = BANDS * ROWS, (1 - least) / 2
    return math.ceil(n * share + 6 * math.sqrt(n * share * (1 - share)))


def _perhaps(x: str, y: str, least: float):
    """Whether sets of those sizes and one-bit min-hashes may be that similar."""
    size, other = F.col(f"{x}.size"), F.col(f"{y}.size")
    words = [F.bit_count(F.col(f"{x}.sig")[i].bitwiseXOR(F.col(f"{y}.sig")[i])) for i in range(-(-BANDS * ROWS // 64))]
    return (F.least(size, other) >= F.lit(least) * F.greatest(size, other) - F.lit(1e-9)) & (sum(words[1:], words[0]) <= most_apart(least))


def least_agree(least: float) -> int:
    """Agreeing bytes of min-hashes that a pair of that similarity has, but for four standard deviations."""
    n, share = BANDS * ROWS, least + (1 - least) / 256
    return math.ceil(n * share - 4 * math.sqrt(n * share * (1 - share)))


def _probably(x: str, y: str, least: float):
    """Whether so many bytes agree: every byte's bits are or-ed into its lowest, which is one where the bytes differ."""

    def differ(a, b):
        d = a.bitwiseXOR(b)
        for shift in (4, 2, 1):
            d = d.bitwiseOR(F.shiftrightunsigned(d, shift))
        return F.bit_count(d.bitwiseAND(F.lit(0x0101010101010101)))

    return F.aggregate(F.zip_with(x, y, differ), F.lit(0), lambda t, v: t + v) <= BANDS * ROWS - least_agree(least)


MAP_BITS = 1 << 23


def _bit(mark):
    """Word and bit of a mark in a map of MAP_BITS."""
    at = F.pmod(mark, F.lit(MAP_BITS))
    return F.shiftright(at, 6), F.call_function("shiftleft", F.lit(1).cast("long"), at.bitwiseAND(F.lit(63)).cast("int"))


def _bitmap(rows: DataFrame) -> DataFrame:
    """(word, bits) of all marks of `rows`, stored: 131,072 rows at most, however many marks there are."""
    word, bit = _bit(F.col("mark"))
    return cut(rows.groupBy(word.alias("__word")).agg(F.bit_or(bit).alias("__bits")))


def _maybe(df: DataFrame, bitmap: DataFrame, mark, there: bool = True) -> DataFrame:
    """Rows of `df` whose mark may be in a bitmap, or those whose mark surely isn't, without moving them; an exact join follows the former."""
    word, bit = _bit(mark)
    hit = F.coalesce(F.col("__bits"), F.lit(0).cast("long")).bitwiseAND(bit) != 0
    return df.join(F.broadcast(bitmap), word == F.col("__word"), "left").where(hit if there else ~hit).drop("__word", "__bits")


def similar_pairs(docs: DataFrame, rows: DataFrame, id_col: str, text_col: str, shingle: int = SHINGLE, least: float = LEAST) -> DataFrame:
    """Edges (a, b) between nodes that connect all nodes of that similarity; `rows` are the stored sketches of `docs`."""
    nodes = cut(rows.where("size > 0").dropDuplicates(["node"]).select("node", "doc_id", "mark", F.struct("size", "sig").alias("seen"), "bands"))
    keyed = cut(nodes.select("node", F.posexplode("bands").alias("band", "key")))
    shared = cut(keyed.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1"))
    met = cut(keyed.join(shared, "key"))  # from here on only buckets of several nodes move
    meets = cut(met.groupBy("node").agg(F.sum("n").alias("meets")))
    order = F.struct("meets", F.col("node").alias("pivot"))
    pivots = cut(met.join(meets, "node").groupBy("key").agg(F.max(order).alias("p")).select("key", "p.pivot"))
    members = cut(met.select("node", "band", "key").join(pivots, "key"))
    known = cut(nodes.join(meets.select("node"), "node", "left_semi").drop("bands"))
    for old in (nodes, keyed, shared, met, meets, pivots):
        forget(old)
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text_col).alias("mark"), F.col(text_col).cast("string").alias("text"))
    texts = _maybe(texts, _bitmap(known), F.col("mark"))
    wanted = texts.join(known.select("doc_id", "mark", "node"), ["doc_id", "mark"]).dropDuplicates(["doc_id", "mark"])  # a node has one of these
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    pair = [F.least("node", "other").alias("a"), F.greatest("node", "other").alias("b")]

    with bucketed(_sets(wanted.select("node", "text"), shingle).repartition(parts, "node"), parts, "node") as sets:  # moved once, for all joins
        edges = comp = None
        for bands in (FIRST_BANDS, BANDS):
            star = members.where(F.col("band") < bands).where("node <> pivot").select("node", F.col("pivot").alias("other")).select(*pair).distinct()
            star = cut(_seen(_apart(star, comp), known, least))
            found = cut(_alike(star, sets, least))
            forget(star)
            edges = found if edges is None else edges.unionByName(found)
            comp = cut(components(edges))

        named = cut(_with(members.select("key", "node"), comp, "node", "comp"))
        forget(members)
        groups = cut(named.groupBy("key", "comp").agg(F.count(F.lit(1)).alias("n")))
        main = cut(groups.groupBy("key").agg(F.max(F.struct("n", "comp")).alias("m"), F.count(F.lit(1)).alias("k")).where("k > 1").select("key", F.col("m.comp").alias("main")))
        split = cut(named.join(main, "key"))
        for old in (named, groups, main):
            forget(old)
        inside = cut(split.select("node").distinct())
        fine = cut(rows.select("node", "fine", "bands").join(inside, "node", "left_semi").dropDuplicates(["node"]).join(known.select("node", "seen"), "node"))
        left, right = split.where("comp <> main").join(fine, "node").alias("l"), split.join(fine, "node").alias("r")
        cross = left.join(right, F.col("l.key") == F.col("r.key")).where("l.comp <> r.comp and (r.comp = r.main or l.node < r.node)").where(_perhaps("l.seen", "r.seen", least) & _probably("l.fine", "r.fine", least))
        cross = cross.where(F.array_intersect("l.bands", "r.bands")[0] == F.col("l.key"))  # a pair of many bands in the first only
        cross = cut(cross.select(F.col("l.node").alias("node"), F.col("r.node").alias("other")).select(*pair).distinct())
        last = cut(_alike(cross, sets, least))
    for old in (known, split, inside, fine, cross):
        forget(old)
    return edges.unionByName(last)


def _seen(pairs: DataFrame, known: DataFrame, least: float) -> DataFrame:
    """Those of the pairs (a, b) that may be that similar by the sizes and one-bit min-hashes of `known`."""
    one = lambda c: known.select(F.col("node").alias(c), F.col("seen").alias(f"s{c}"))
    return pairs.join(one("a"), "a").join(one("b"), "b").where(_perhaps("sa", "sb", least)).select("a", "b")


def _with(rows: DataFrame, comp: DataFrame | None, node: str, name: str) -> DataFrame:
    """`rows` with the component of a node; a node without an edge is one of its own."""
    if comp is None:
        return rows.withColumn(name, F.col(node))
    return rows.join(comp.select(F.col("node").alias(node), F.col("component").alias("__c")), node, "left").withColumn(name, F.coalesce("__c", node)).drop("__c")


def _apart(pairs: DataFrame, comp: DataFrame | None) -> DataFrame:
    """Pairs that aren't connected yet."""
    return pairs if comp is None else _with(_with(pairs, comp, "a", "ca"), comp, "b", "cb").where("ca <> cb").select("a", "b")


def drop_near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, least: float = LEAST) -> DataFrame:
    """One row of `docs` per group of near copies, with all its columns: the smallest id's, then fingerprint's, then text hash's.

    Links are a Jaccard similarity of `least` or more, and all links of
    `simhash_groups`. Rows with a null id belong to no group and are kept.
    """
    rows = cut(sketches(docs, id_col, text_col, shingle))
    classes = cut(rows.groupBy("fp").agg(F.min("node").alias("rep")))
    same = rows.select("fp", "node").distinct().join(classes, "fp").select(F.col("node").alias("a"), F.col("rep").alias("b"))
    edges = near_pairs(classes).unionByName(same).unionByName(similar_pairs(docs, rows, id_col, text_col, shingle, least))
    first = cut(rows.groupBy("node").agg(F.min(F.struct("doc_id", "fp", "mark")).alias("first")))
    comp = cut(components(edges))
    kept = _with(first, comp, "node", "comp").groupBy("comp").agg(F.min("first").alias("f"))
    kept = cut(kept.select(F.col("f.doc_id").alias("keep"), F.col("f.mark").alias("mark")))
    once = rows.groupBy("doc_id", "mark").agg(F.count(F.lit(1)).alias("n")).join(kept.withColumnRenamed("keep", "doc_id").withColumn("__kept", F.lit(True)), ["doc_id", "mark"], "left")
    doubtful = _bitmap(once.where("n > 1 or __kept is null"))  # rows that go, and those of which one stays
    m = Masked(docs)
    same_text, some = F.xxhash64(m.name(text_col)), m.df.where(m.col(id_col).isNotNull())
    clear = _maybe(some, doubtful, same_text, there=False)  # texts that surely stay never move
    named = _maybe(some, doubtful, same_text).join(kept, (m.col(id_col) == F.col("keep")) & (same_text == F.col("mark")), "left_semi")
    named = named.withColumn("mark", same_text).dropDuplicates([m.name(id_col), "mark"]).drop("mark")
    return clear.union(named).union(m.df.where(m.col(id_col).isNull())).select(m.back())

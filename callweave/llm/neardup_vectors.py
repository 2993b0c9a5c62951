"""Near-duplicate vectors within labels by randomised-rotation binary codes.

A unit vector is rotated at random and stored as its signs, one bit a dimension,
with the inner product of the rotated vector and its code as correction factor,
and with the rotated vector in four bits a dimension for the other side of an
estimate. Bits of one against quarter bytes of the other, counted with and/xor
and popcounts and divided by the factor, give an unbiased estimate of the cosine
with a confidence bound; a pair whose upper bound lies below the threshold is
dropped, every other pair is recomputed exactly from the original vectors. All
of this is made once per vector and kept; the vectors themselves travel only
for members of pairs that the bounds leave open.

Pairs are looked at only where vectors share a bucket: bands of `bits` sign bits
of the rotations, as many bands as a pair at the threshold needs to meet with
probability `recall` (closer pairs meet more surely). `bits` follows the size of
the largest label, so that a bucket's expected size does not grow with the
table. Equal vectors are one class with a weight and are never paired. A bucket
above `block` vectors is cut into blocks that are compared two by two; pairs are
counted where they first meet and never emitted: a task returns each vector's
number of links and a spanning forest. Rows reach a task flat and sorted by
block, and `chunk` of them are held at a time, so memory follows neither the
size of a bucket nor the number of buckets in an Arrow batch.

Large groups of near copies would still cost the square of their size. Where a
bucket is hot, its first vector becomes the centre of a ball of half the
threshold's angle. Any two vectors of a ball are linked, by the triangle
inequality on the sphere, so their links are counted by adding weights. A vector
outside that lies wholly within or wholly beyond reach of a ball is settled by
its angle to the centre and the ball's radius; only what lies between is
compared with the ball's members.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from callweave.llm.common import cut
from callweave.llm.components import components
from callweave.llm.vectors import matrix, rotation, sound_vectors

#: Bits of a coordinate on the unquantised side of an estimate.
PLANES = 4


@dataclass(frozen=True)
class VectorDupParams:
    """`block` bounds a block of a bucket, `chunk` the rows that a task compares at a time."""

    threshold: float = 0.93
    recall: float = 0.999
    epsilon: float = 4.0
    block: int = 512
    chunk: int = 16_384
    seed: int = 41


def bands_for(size: int, p: VectorDupParams) -> tuple[int, int]:
    """Bits of a band and number of bands for labels of up to `size` vectors."""
    bits = int(min(24, max(8, math.ceil(math.log2(max(2, size))))))
    meet = (1 - math.acos(p.threshold) / math.pi) ** bits
    return bits, math.ceil(math.log(1 - p.recall) / math.log(1 - meet))


def words_of(bits: np.ndarray) -> np.ndarray:
    """Rows of booleans as rows of 64-bit words, filled up with zeros."""
    packed = np.packbits(bits, axis=1, bitorder="little")
    return np.pad(packed, ((0, 0), (0, -packed.shape[1] % 8))).view(np.uint64)


class Coder:
    """Sketches of vectors of one dimension: sign bits of all rotations, the first rotation's coordinates in bit planes, three numbers.

    A sketch is `size` words: `signs` words of bits (a band's key is `bits` of
    them, the code is the first `dim`), PLANES times `code` words of planes, then
    correction factor, least coordinate and step as doubles.
    """

    def __init__(self, dim: int, bits: int, bands: int, seed: int):
        self.dim, self.bits, self.bands = dim, bits, bands
        self.turns = np.concatenate([rotation(dim, seed + i) for i in range(math.ceil(bits * bands / dim))], axis=1)
        self.dither = np.random.default_rng(seed).random(dim)
        self.code = -(-dim // 64)
        self.signs = -(-self.turns.shape[1] // 64)
        self.size = self.signs + PLANES * self.code + 3
        self.last = np.uint64((1 << (dim % 64)) - 1) if dim % 64 else np.uint64(0xFFFFFFFFFFFFFFFF)

    def sketch(self, unit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Band keys and sketches of unit vectors."""
        o = unit @ self.turns
        up = o > 0
        keys = up[:, : self.bits * self.bands].reshape(len(unit), self.bands, self.bits) @ (1 << np.arange(self.bits, dtype=np.int64))
        o = o[:, : self.dim]
        factor = np.abs(o).sum(axis=1) / math.sqrt(self.dim)
        low = o.min(axis=1)
        step = np.maximum((o.max(axis=1) - low) / (2**PLANES - 1), 1e-12)
        level = np.minimum((o - low[:, None]) / step[:, None] + self.dither, 2**PLANES - 1).astype(np.uint8)
        planes = [words_of((level >> j & 1).astype(bool)) for j in range(PLANES)]
        return keys, np.concatenate([words_of(up), *planes, np.stack([factor, low, step], axis=1).view(np.uint64)], axis=1)


class Pairs:
    """Which pairs of given sketches the estimate's confidence bounds can't rule out."""

    def __init__(self, coder: Coder, s: np.ndarray, p: VectorDupParams):
        c, self.coder, self.p = coder, coder, p
        self.signs = s[:, : c.signs]
        self.code = s[:, : c.code].copy()
        self.code[:, -1] &= c.last
        self.planes = s[:, c.signs : c.size - 3].reshape(len(s), PLANES, c.code)
        self.factor, self.low, self.step = np.ascontiguousarray(s[:, c.size - 3 :]).view(np.float64).T
        self.ones = np.bitwise_count(self.code).sum(axis=1, dtype=np.int64)
        self.level = self._weigh(self.planes)
        self.error = p.epsilon * np.sqrt(np.maximum(0, 1 - self.factor**2)) / math.sqrt(max(1, c.dim - 1)) / self.factor

    @staticmethod
    def _weigh(planes: np.ndarray) -> np.ndarray:
        return np.bitwise_count(planes).sum(axis=2, dtype=np.int64) @ (1 << np.arange(PLANES))

    def estimate(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Estimates of the cosines of pairs by the codes of `a` and the coordinates of `b`, and the errors they may have."""
        hit = self._weigh(self.planes[b] & self.code[a][:, None, :])
        dot = self.low[b] * (2 * self.ones[a] - self.coder.dim) + self.step[b] * (2 * hit - self.level[b])
        return dot / math.sqrt(self.coder.dim) / self.factor[a], self.error[a] + self.p.epsilon * self.step[b] / 2 / self.factor[a]

    def maybe(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Whether both upper bounds of a pair reach the threshold."""
        out = sum(self.estimate(a, b)) >= self.p.threshold
        out[out] = sum(self.estimate(b[out], a[out])) >= self.p.threshold
        return out

    def met_before(self, a: np.ndarray, b: np.ndarray, band: np.ndarray) -> np.ndarray:
        """Whether pairs share the key of a band before `band`."""
        c = self.coder
        apart = np.unpackbits((self.signs[a] ^ self.signs[b]).view(np.uint8), axis=1, count=c.bits * c.bands, bitorder="little")
        same = ~apart.reshape(len(a), c.bands, c.bits).any(axis=2)
        return (same & (np.arange(c.bands) < band[:, None])).any(axis=1)

    def each(self, block: np.ndarray, band: np.ndarray, side: np.ndarray, cross: np.ndarray):
        """Yield open pairs (a, b) of positions within blocks (runs of equal numbers) that first meet there, some at a time."""
        for d in range(1, int(np.bincount(block).max(initial=0))):
            a = np.flatnonzero(block[d:] == block[:-d])
            a = a[~cross[a] | (side[a] != side[a + d])]
            a = a[self.maybe(a, a + d)]
            late = band[a] > 0
            if late.any():
                known = np.zeros(len(a), bool)
                known[late] = self.met_before(a[late], a[late] + d, band[a[late]])
                a = a[~known]
            if len(a):
                yield a, a + d


def unit_rows(x: np.ndarray) -> np.ndarray:
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def forest_roots(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    """Smallest position in the component of each of n positions, by pairs (a, b)."""
    root = np.arange(n)
    while True:
        low = np.minimum(root[a], root[b])
        new = root.copy()
        np.minimum.at(new, a, low)
        np.minimum.at(new, b, low)
        new = new[new]
        if (new == root).all():
            return root
        root = new


def by_block(batches, rows: int):
    """Tables of whole blocks, about `rows` rows each, of batches sorted by `bid`."""
    held = None
    for b in batches:
        if not b.num_rows:
            continue
        t = pa.Table.from_batches([b])
        held = t if held is None else pa.concat_tables([held, t])
        if held.num_rows >= rows:
            start = pc.index(held["bid"], held["bid"][-1]).as_py()
            if start:
                yield held.slice(0, start)
                held = held.slice(start).combine_chunks()
    if held is not None:
        yield held


def parts_of(table: pa.Table, coder, p: VectorDupParams):
    """(rows, open pairs) for the rows of each dimension; `coder` has the coder of one."""
    dims = np.asarray(table["dim"])
    for dim in np.unique(dims):
        rows = table.filter(pa.array(dims == dim)) if (dims != dim).any() else table
        sketches = np.frombuffer(b"".join(rows["sketch"].to_pylist()), np.uint64).reshape(rows.num_rows, -1)
        bid = np.asarray(rows["bid"].combine_chunks().dictionary_encode().indices)
        band, side, cross = (np.asarray(rows[c].combine_chunks().cast(pa.int32())) for c in ("band", "side", "cross"))
        yield rows, Pairs(coder(int(dim)), sketches, p).each(bid, band, side, cross > 0)


FLAT = "bid string, band int, side int, cross boolean, node long"


def vector_groups(df: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", label_col: str = "label", p: VectorDupParams = VectorDupParams()) -> DataFrame:
    """(vec_id, n_links, component_id, kept) of every row.

    Rows without a label, and vectors that are null, zero or hold null or
    non-finite components, link with nothing; vectors of different dimensions
    have no cosine and don't link with one another. Rows with a null id count no
    links and have no component. Repeated rows link like any other equal
    vectors; rows of one id with other vectors are told apart. An empty table
    gives an empty table.
    """
    sound = sound_vectors(df.where(F.col(label_col).isNotNull()), id_col, vec_col, F.col(label_col).alias("label"))
    classes = sound.groupBy("label", "vec").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("weight"))
    classes = cut(classes.withColumn("dim", F.size("vec")).withColumn("node", F.monotonically_increasing_id()))
    largest = classes.groupBy("label", "dim").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0]
    out = df.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).alias("vec"), F.col(label_col).alias("label"))
    if largest is None:
        return out.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.col("vec_id").isNotNull().alias("kept"))
    bits, bands = bands_for(largest, p)

    def coders():
        made = {}

        def get(dim):
            if dim not in made:
                made[dim] = Coder(dim, bits, bands, p.seed)
            return made[dim]

        return get

    def describe(batches):
        coder = coders()
        for b in batches:
            dims = np.asarray(b.column(2))
            for dim in np.unique(dims):
                part = b.filter(pa.array(dims == dim))
                keys, sketch = coder(int(dim)).sketch(unit_rows(matrix(part.column(3))))
                lists = pa.ListArray.from_arrays(np.arange(0, keys.size + 1, keys.shape[1], dtype=np.int32), keys.ravel())
                told = pa.array([row.tobytes() for row in sketch], pa.binary())
                yield pa.RecordBatch.from_arrays([*part.columns, lists, told], ["node", "label", "dim", "vec", "weight", "keys", "sketch"])

    kinds = {c: classes.schema[c].dataType.simpleString() for c in ("label", "vec")}
    described = classes.select("node", "label", "dim", "vec", "weight")
    slots = cut(described.mapInArrow(describe, f"node long, label {kinds['label']}, dim int, vec {kinds['vec']}, weight long, keys array<long>, sketch binary"))
    keyed = ["label", "dim", "band", "key"]
    spread = slots.select("node", "label", "dim", F.posexplode("keys").alias("band", "key"))
    sizes = spread.where("band = 0").groupBy(*keyed).agg(F.count(F.lit(1)).alias("n"), F.min("node").alias("ball"))
    hot = cut(sizes.where(F.col("n") > p.block).select("ball"))

    def open_members(batches):
        coder = coders()
        for table in by_block(batches, p.chunk):
            for rows, pairs in parts_of(table, coder, p):
                hit = np.zeros(rows.num_rows, bool)
                for a, b in pairs:
                    hit[a] = hit[b] = True
                if hit.any():
                    yield from rows.filter(pa.array(hit)).select(["bid", "band", "side", "cross", "node"]).combine_chunks().to_batches()

    def compare(batches):
        coder = coders()
        for table in by_block(batches, p.chunk):
            for rows, pairs in parts_of(table, coder, p):
                unit, weight, node = unit_rows(matrix(rows["vec"])), np.asarray(rows["weight"]), np.asarray(rows["node"])
                found = [(a[near], b[near]) for a, b in pairs if (near := np.einsum("ij,ij->i", unit[a], unit[b]) >= p.threshold).any()]
                if not found:
                    continue
                a, b = (np.concatenate(x) for x in zip(*found))
                links = np.bincount(a, weight[b], len(node)) + np.bincount(b, weight[a], len(node))
                order = np.argsort(node, kind="stable")
                place = np.empty(len(node), np.int64)
                place[order] = np.arange(len(node))
                root = node[order][forest_roots(place[a], place[b], len(node))[place]]
                hit = links > 0
                yield pa.RecordBatch.from_arrays([pa.array(node[hit]), pa.array(links[hit].astype(np.int64)), pa.array(root[hit])], ["node", "links", "root"])

    def dealt(flat):
        return flat.repartition("bid").sortWithinPartitions("bid")

    def compared(flat):
        """(node, links, root) of the linked vectors among flat rows with vec, weight, dim and sketch."""
        return dealt(flat).mapInArrow(compare, "node long, links long, root long")

    settled, rest = (None, slots) if hot.isEmpty() else _balls(slots, spread, hot, compared, p)
    light = rest.select("node", "label", "dim", "sketch", F.posexplode("keys").alias("band", "key"))
    large = cut(light.groupBy(*keyed).agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > p.block))
    rows = light.join(large, keyed, "left").withColumn("cuts", F.ceil(F.coalesce("n", F.lit(1)) / p.block).cast("int"))
    rows = rows.withColumn("i", F.pmod(F.xxhash64("node"), F.col("cuts")).cast("int")).withColumn("j", F.explode(F.sequence(F.lit(0), F.col("cuts") - 1)))
    bid = F.concat_ws("|", F.col("label").cast("string"), "dim", "band", "key", F.least("i", "j"), F.greatest("i", "j"))
    flat = rows.select(bid.alias("bid"), "band", F.col("i").alias("side"), (F.col("i") != F.col("j")).alias("cross"), "node", "dim", "sketch")
    open_rows = cut(dealt(flat).mapInArrow(open_members, FLAT))
    found = compared(open_rows.join(rest.select("node", "dim", "vec", "weight", "sketch"), "node"))
    found = cut(found if settled is None else found.unionByName(settled))
    links = found.groupBy("node").agg(F.sum("links").alias("links"))
    comp = components(found.select(F.col("node").alias("a"), F.col("root").alias("b")))
    group = F.coalesce("component", "node")
    grouped = cut(classes.select("label", "vec", "node", "rep", "weight").join(links, "node", "left").join(comp, "node", "left").withColumn("group", group))
    first = grouped.where("component is not null").groupBy("group").agg(F.min("rep").alias("first"))
    named = grouped.join(first, "group", "left").select("label", "vec", (F.coalesce("links", F.lit(0)) + F.col("weight") - 1).alias("links"), F.coalesce("first", "rep").alias("component"))
    joined = out.alias("o").join(named.alias("c"), (F.col("o.label") == F.col("c.label")) & (F.col("o.vec") == F.col("c.vec")) & F.col("o.vec_id").isNotNull(), "left")
    component = F.coalesce("c.component", "o.vec_id")
    return joined.select(
        F.col("o.vec_id").alias("vec_id"),
        F.coalesce("c.links", F.lit(0)).cast("long").alias("n_links"),
        component.alias("component_id"),
        F.coalesce(F.col("o.vec_id") == component, F.lit(False)).alias("kept"),
    )


def _angle(a, b):
    """Angle of two vectors, in double precision, as a native expression."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda v, w: v.cast("double") * w.cast("double")), F.lit(0.0), lambda t, v: t + v)
    cosine = dot(a, b) / F.sqrt(dot(a, a)) / F.sqrt(dot(b, b))
    return F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), cosine)))


def _balls(slots: DataFrame, spread: DataFrame, hot: DataFrame, compared, p: VectorDupParams) -> tuple[DataFrame, DataFrame]:
    """(node, links, root) rows of all pairs that a ball takes part in, and the classes that lie in no ball."""
    limit, slack = math.acos(p.threshold), 1e-9
    keyed = ["label", "dim", "band", "key"]
    centres = cut(slots.join(hot.withColumnRenamed("ball", "node"), "node").select("label", "dim", F.col("node").alias("ball"), F.col("vec").alias("centre"), "keys"))
    first = centres.select("label", "dim", "ball", F.posexplode("keys").alias("band", "key")).groupBy(*keyed).agg(F.min("ball").alias("ball"))
    at_centre = slots.select("node", "weight", "vec")

    def measured(pairs):
        """Distinct (node, ball) with the vector, its weight, and its angle to the ball's centre."""
        joined = pairs.distinct().join(at_centre, "node").join(centres.select("ball", "centre"), "ball")
        return joined.select("node", "ball", "weight", "vec", _angle(F.col("vec"), F.col("centre")).alias("angle"))

    near = measured(spread.join(first, keyed).select("node", "ball")).where(F.col("angle") <= limit / 2 - slack)
    members = cut(near.groupBy("node").agg(F.min(F.struct("ball", "angle", "weight")).alias("m")).select("node", "m.*"))
    balls = cut(members.groupBy("ball").agg(F.sum("weight").alias("mass"), F.max("angle").alias("radius"), F.count(F.lit(1)).alias("n")))

    inside = members.select("node", "ball")
    held = cut(spread.join(inside, "node").select(*keyed, F.col("ball").alias("other")).distinct())  # the balls that a bucket meets
    met = spread.join(held, keyed).join(inside, "node", "left")
    outside = met.where("ball is null or other < ball").select("node", F.col("other").alias("ball"))
    outside = cut(measured(outside).drop("vec").join(balls, "ball").where(F.col("angle") - F.col("radius") <= limit + slack))
    whole = F.col("angle") + F.col("radius") <= limit - slack
    added = outside.where(whole).groupBy("ball").agg(F.sum("weight").alias("added"))
    inner = members.join(balls, "ball").join(added, "ball", "left")
    inner = inner.select("node", (F.col("mass") - F.col("weight") + F.coalesce("added", F.lit(0))).alias("links"), F.col("ball").alias("root"))
    outer = outside.where(whole).select("node", F.col("mass").alias("links"), F.col("ball").alias("root"))

    edge = cut(outside.where(~whole).select("node", "ball", "n"))
    counts = edge.groupBy("ball").agg(F.count(F.lit(1)).alias("edges"), F.max("n").alias("n"))
    counts = counts.select("ball", F.ceil(F.col("n") / p.block).cast("int").alias("mcuts"), F.ceil(F.col("edges") / p.block).cast("int").alias("ecuts"))

    def dealt(rows, side, mine, others):
        joined = rows.select("node", "ball").join(counts, "ball").withColumn(mine, F.pmod(F.xxhash64("node"), F.col(f"{mine}s")).cast("int"))
        joined = joined.withColumn(others, F.explode(F.sequence(F.lit(0), F.col(f"{others}s") - 1)))
        return joined.select(F.concat_ws("|", "ball", "mcut", "ecut").alias("bid"), F.lit(0).alias("band"), F.lit(side).alias("side"), F.lit(True).alias("cross"), "node")

    both = dealt(members, 0, "mcut", "ecut").unionByName(dealt(edge, 1, "ecut", "mcut"))
    between = compared(both.join(slots.select("node", "dim", "vec", "weight", "sketch"), "node"))
    return inner.unionByName(outer).unionByName(between), slots.join(members.select("node"), "node", "left_anti")

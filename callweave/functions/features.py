"""Featurization: image grids, texts and pages, as expressions wherever one exists."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from callweave.operators.mapreduce import words


def let(value: Column, use) -> Column:
    """`use(value)` with `value` computed once, however often `use` mentions it."""
    return F.transform(F.array(value), use)[0]


def crop(px: Column, width: int, top: int, left: int, height: int, out_width: int) -> Column:
    """Row-major crop of a row-major image."""
    rows = F.sequence(F.lit(top), F.lit(top + height - 1))
    return let(px, lambda p: F.flatten(F.transform(rows, lambda r: F.slice(p, r * width + left + 1, F.lit(out_width)))))


def scale(px: Column, width: int, height: int, factor: int) -> Column:
    """Mean of each factor x factor block, row-major."""
    w, cells = width // factor, (width // factor) * (height // factor)

    def block(px, c):
        row, col = F.floor(c / w) * factor, F.pmod(c, F.lit(w)) * factor
        rows = F.sequence(F.lit(0), F.lit(factor - 1))
        total = F.aggregate(rows, F.lit(0.0), lambda s, r: F.aggregate(F.slice(px, ((row + r) * width + col + 1).cast("int"), F.lit(factor)), s, lambda a, v: a + v))
        return total / (factor * factor)

    return let(px, lambda p: F.transform(F.sequence(F.lit(0), F.lit(cells - 1)), lambda c: block(p, c)))


def gradient_descriptor(px: Column, width: int, height: int, grid: int = 2) -> Column:
    """grid*grid*4 numbers: per cell, the sum of |dx| + |dy| of pixels in each of four orientations (signs of dx, dy).

    dx and dy are differences to the right and the lower neighbour; the last
    column and row have none.
    """
    w, h = width - 1, height - 1
    cell_w, cell_h = -(-w // grid), -(-h // grid)

    def pixel(px, i):
        at = lambda r, c: F.element_at(px, (r * width + c + 1).cast("int"))
        r, c = F.floor(i / w), F.pmod(i, F.lit(w))
        dx, dy = at(r, c + 1) - at(r, c), at(r + 1, c) - at(r, c)
        orientation = F.when(dx >= 0, 0).otherwise(1) + F.when(dy >= 0, 0).otherwise(2)
        slot = (F.floor(r / cell_h) * grid + F.floor(c / cell_w)) * 4 + orientation
        return F.struct(slot.cast("int").alias("slot"), (F.abs(dx) + F.abs(dy)).alias("energy"))

    pixels = let(px, lambda q: F.transform(F.sequence(F.lit(0), F.lit(w * h - 1)), lambda i: pixel(q, i)))
    slots = F.sequence(F.lit(0), F.lit(grid * grid * 4 - 1))
    total = lambda ps, s: F.aggregate(F.filter(ps, lambda p: p["slot"] == s), F.lit(0.0), lambda a, p: a + p["energy"])
    return let(pixels, lambda ps: F.transform(slots, lambda s: total(ps, s)))


def gradient_descriptor_numpy(df: DataFrame, id_col: str, px_col: str, width: int, height: int, grid: int = 2) -> DataFrame:
    """The same by batches of NumPy, the better way for large images."""
    import numpy as np
    import pyarrow as pa

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            img = np.asarray(b.column(1).flatten(), float).reshape(b.num_rows, height, width)
            core = img[:, :-1, :-1]
            dx, dy = img[:, :-1, 1:] - core, img[:, 1:, :-1] - core
            energy, orientation = abs(dx) + abs(dy), (dx < 0) + 2 * (dy < 0)
            h, w = core.shape[1:]
            cell = (np.arange(h) // -(-h // grid))[:, None] * grid + np.arange(w) // -(-w // grid)
            out = np.zeros((b.num_rows, grid * grid * 4))
            for s in range(grid * grid * 4):
                out[:, s] = (energy * ((cell * 4)[None] + orientation == s)).sum(axis=(1, 2))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(list(out), pa.list_(pa.float64()))], ["id", "descriptor"])

    return df.select(F.col(id_col).cast("long").alias("id"), px_col).mapInArrow(run, "id long, descriptor array<double>")


def text_features(df: DataFrame, col: str = "text") -> DataFrame:
    """`df` with token, distinct token, digit, line and capital counts and 16 bins of tokens by the first digit of their md5."""
    bins = F.transform(F.col("__words"), lambda w: F.substring(F.md5(w.cast("binary")), 1, 1))
    hexes = F.split(F.lit("0,1,2,3,4,5,6,7,8,9,a,b,c,d,e,f"), ",")
    out = df.withColumn("__words", words(F.col(col))).withColumn("__bins", bins)
    return out.select(
        *df.columns,
        F.size("__words").alias("n_tokens"),
        F.size(F.array_distinct("__words")).alias("n_distinct"),
        F.aggregate("__words", F.lit(0).cast("long"), lambda s, w: s + F.length(w)).alias("token_chars"),
        F.length(F.regexp_replace(col, "[^0-9]", "")).alias("n_digits"),
        F.size(F.split(col, "\n")).alias("n_lines"),
        F.length(F.regexp_replace(col, "[^A-Z]", "")).alias("n_capitals"),
        F.transform(hexes, lambda h: F.size(F.filter("__bins", lambda b: b == h))).alias("hashed"),
    )


def page_features(df: DataFrame, html: str = "html", url: str = "url") -> DataFrame:
    """`df` with its host and counts of links, paragraphs, list items and scripts of the markup."""
    count = lambda tag: (F.regexp_count(html, F.lit(f"(?i)<{tag}[ >]"))).cast("long")
    return df.select(
        *df.columns,
        F.regexp_extract(url, r"^https?://([^/?#]+)", 1).alias("host"),
        F.length(html).cast("long").alias("n_html"),
        count("a").alias("n_links"), count("p").alias("n_paragraphs"), count("li").alias("n_items"), count("script").alias("n_scripts"),
    )

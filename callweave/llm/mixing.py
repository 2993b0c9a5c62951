"""Mixing sources to target weights by hierarchical budgets.

A tree of domains, languages and sources carries weights. The token budget
flows down from the root; among siblings it is dealt by weight, and what a
child can't take goes to its siblings in proportion to their weights, before a
shortage of the whole family reaches the parent's siblings. Leaves then take
documents in the order of seeded epochs: an epoch is a permutation of a leaf's
documents by hash, and the leaf takes the prefix whose tokens fit.

All native. Per leaf and epoch the order is cut into 4096 ranges of the hash;
only the range where the prefix ends is sorted, so no task sees a whole leaf.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from callweave.llm.common import cut

LEVELS = ("domain", "lang", "source")


def word_tokens(text: Column) -> Column:
    """Number of words between blanks and line ends, as the token measure of budgets; null counts as empty.

    Words are counted as non-empty pieces: split on a single blank needs no regular expression.
    """
    pieces = F.split(F.translate(F.coalesce(text, F.lit("")), "\t\n\x0b\f\r", "     "), " ")
    return (F.size(pieces) - F.size(F.filter(pieces, lambda x: x == ""))).cast("long")


def deal(nodes: DataFrame, parent: list[str], budget: str, weight: str, cap: str, key: str) -> DataFrame:
    """`nodes` with `dealt`: the parent's budget by weight, no child over its cap.

    Sorted by cap per weight, a child is full exactly if its cap is at most what
    is left for it and the children behind it at equal price. The first child
    that isn't full has the price of all open ones; those behind it compute lower
    prices, hence the maximum. Weights are positive.
    """
    order = Window.partitionBy(*parent).orderBy(F.col(cap) / F.col(weight), key)
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    behind = order.rowsBetween(0, Window.unboundedFollowing)
    price = (F.col(budget) - F.coalesce(F.sum(cap).over(before), F.lit(0.0))) / F.sum(weight).over(behind)
    full = F.col(cap) / F.col(weight) <= F.col("__price")
    open_price = F.max(F.when(~F.col("__full"), F.col("__price"))).over(Window.partitionBy(*parent))
    return (
        nodes.withColumn("__price", price)
        .withColumn("__full", full)
        .withColumn("dealt", F.when(F.col("__full"), F.col(cap)).otherwise(F.col(weight) * open_price))
        .drop("__price", "__full")
    )


def leaf_budgets(leaves: DataFrame, budget: float, weights: dict[str, dict[str, float]] | None = None, max_epochs: int = 1) -> DataFrame:
    """(domain, lang, source, tokens, docs, budget) of each leaf; `leaves` has domain, lang, source, tokens and docs.

    `weights` maps a level to weights by name; names without one weigh 1. A node
    without positive weight gets nothing, nor does anything below it, and what
    its leaves hold counts nowhere as room: its share goes to siblings, then to
    siblings of its ancestors. Such leaves have no row. The frame has a row per
    leaf of the tree, never per document.
    """

    def weight(level):
        table = (weights or {}).get(level, {})
        out = F.lit(1.0)
        for name, w in sorted(table.items()):
            out = F.when(F.col(level) == name, F.lit(float(w))).otherwise(out)
        return out

    top = leaves.where(F.least(*[weight(level) for level in LEVELS]) > 0).withColumn("cap", (F.col("tokens") * max_epochs).cast("double"))
    given = None
    for depth, level in enumerate(LEVELS):
        path, above = list(LEVELS[: depth + 1]), list(LEVELS[:depth])
        nodes = top.groupBy(*path).agg(F.sum("cap").alias("cap")).withColumn("weight", weight(level))
        if given is None:
            nodes = nodes.withColumn("budget", F.lit(float(budget))).withColumn("__root", F.lit(0))
            above = ["__root"]
        else:
            nodes = nodes.join(given, above)
        nodes = nodes.withColumn("budget", F.least("budget", F.sum("cap").over(Window.partitionBy(*above))))
        given = deal(nodes, above, "budget", "weight", "cap", level).select(*path, F.col("dealt").alias("budget"))
    return leaves.join(given, list(LEVELS))


def epoch_key(seed: int, epoch: Column, doc_id: Column) -> Column:
    return F.md5(F.concat_ws(":", F.lit(str(seed)), epoch.cast("string"), doc_id.cast("string")).cast("binary"))


def mix(
    docs: DataFrame,
    domain: Column,
    budget_share: float = 0.5,
    weights: dict[str, dict[str, float]] | None = None,
    max_epochs: int = 1,
    seed: int = 17,
    tokens: Column | None = None,
    tell: bool = True,
    keep: list[str] | None = None,
) -> DataFrame:
    """A row (own columns and, if `tell`, __domain, __tokens, __epoch) for each document and epoch that is taken.

    With `keep`, rows have those columns of `docs` only, which are set aside when
    tokens are counted: texts are then read once.

    The budget is `budget_share` of all tokens. A leaf's prefix never exceeds
    its budget; documents are taken whole. Null lang or source are leaves named
    empty; a null doc_id orders like an empty id; documents without tokens cost
    nothing and are taken while the prefix lasts; documents that tie in the
    order (repeated rows) are taken or left together. What a leaf's prefix leaves
    of its budget, because the next document is longer, goes to nobody. An empty
    table gives none.
    """
    blank = lambda c: F.coalesce(c.cast("string"), F.lit(""))
    back = docs.columns if keep is None else keep
    own = len(docs.columns)
    counted = tokens if tokens is not None else word_tokens(F.col("text"))
    keys = [blank(c).alias("k") for c in (domain, F.col("lang"), F.col("source"), F.col("doc_id"))]
    named = docs.select("*", *keys, counted.alias("k")).toDF(*[f"c{i}" for i in range(own)], "__domain", "__lang", "__source", "__id", "__tokens")
    told = [] if keep is None else [f"c{docs.columns.index(n)}" for n in keep]
    slim = cut(named.select(*told, "__domain", "__lang", "__source", "__id", "__tokens"))  # texts are counted once here
    leaves = slim.groupBy(F.col("__domain").alias("domain"), F.col("__lang").alias("lang"), F.col("__source").alias("source"))
    leaves = cut(leaves.agg(F.sum("__tokens").alias("tokens"), F.count(F.lit(1)).alias("docs")))
    total = leaves.agg(F.coalesce(F.sum("tokens"), F.lit(0))).first()[0]
    plan = leaf_budgets(leaves, budget_share * total, weights, max_epochs)
    whole = F.floor(F.col("budget") / F.greatest("tokens", F.lit(1)) + F.lit(1e-9)).cast("int")
    plan = cut(
        plan.withColumn("full_epochs", F.when(F.col("tokens") == 0, F.lit(1)).otherwise(whole))
        .withColumn("rest", F.floor(F.col("budget") - F.col("full_epochs") * F.col("tokens") + F.lit(1e-6)))
        .select(*[F.col(c).alias(f"__{c}") for c in LEVELS], F.col("full_epochs").alias("__full"), F.col("rest").alias("__rest"))
    )
    leaf = [f"__{c}" for c in LEVELS]

    def place(rows):
        keyed = rows.join(plan, leaf).withColumn("__key", epoch_key(seed, F.col("__full"), F.col("__id")))
        return keyed.withColumn("__range", F.substring("__key", 1, 3))

    placed = place(slim)
    sizes = cut(placed.groupBy(*leaf, "__range", "__rest").agg(F.sum("__tokens").alias("size"))).withColumn("__digit", F.substring("__range", 1, 1))
    before = lambda *by: Window.partitionBy(*by).rowsBetween(Window.unboundedPreceding, -1)
    digits = sizes.groupBy(*leaf, "__digit").agg(F.sum("size").alias("all"))  # 16 rows a leaf, then 256 a digit
    digits = digits.select(*leaf, "__digit", F.coalesce(F.sum("all").over(before(*leaf).orderBy("__digit")), F.lit(0)).alias("lead"))
    start = F.col("lead") + F.coalesce(F.sum("size").over(before(*leaf, "__digit").orderBy("__range")), F.lit(0))
    ends = sizes.join(digits, [*leaf, "__digit"]).withColumn("__from", start).withColumn("__upto", F.col("__from") + F.col("size"))
    edge = cut(
        ends.where("__upto > __rest").groupBy(*leaf).agg(F.min(F.struct("__range", "__from")).alias("e"))
        .select(*leaf, F.col("e.__range").alias("__edge"), F.col("e.__from").alias("__before"))
    )
    inside = placed.join(edge, leaf, "left")
    tied = Window.partitionBy(*leaf, "__range").orderBy("__key").rangeBetween(Window.unboundedPreceding, 0)
    ids = inside.where("__range = __edge").select(*leaf, "__range", "__key", "__tokens", "__before", "__rest")
    last = (
        ids.withColumn("__sum", F.col("__before") + F.sum("__tokens").over(tied))
        .where("__sum <= __rest")
        .groupBy(*leaf)
        .agg(F.max("__key").alias("__last"))
    )
    edges = cut(edge.join(last, leaf, "left").select(*leaf, "__edge", "__last"))
    decided = place(named if keep is None else slim).join(edges, leaf, "left")
    in_rest = F.col("__edge").isNull() | (F.col("__range") < F.col("__edge")) | F.coalesce(F.col("__key") <= F.col("__last"), F.lit(False))
    in_rest = in_rest & (F.col("__rest") > 0)
    epochs = F.concat(
        F.when(F.col("__full") > 0, F.sequence(F.lit(0), F.greatest(F.col("__full"), F.lit(1)) - 1)).otherwise(F.array().cast("array<int>")),
        F.when(in_rest, F.array("__full")).otherwise(F.array().cast("array<int>")),
    )
    return decided.withColumn("__epoch", F.explode(epochs)).select(
        *[F.col(f"c{docs.columns.index(n)}").alias(n) for n in back], *(["__domain", "__tokens", "__epoch"] if tell else [])
    )

"""Joins that Spark has no operator for: as-of, range by bins, substring leakage, similarity by signature buckets."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, keys: list[str], at: str, value: str, strict: bool = False) -> DataFrame:
    """Left rows with the latest `value` of the right at or before (`strict`: before) `at`: one union and one window,
    no pairs. Null where nothing came before."""
    right = right.select(*keys, at, F.col(value).alias("__v"), F.lit(1 if strict else 0).alias("__side"))
    rows = left.withColumns({"__v": F.lit(None).cast(dict(right.dtypes)["__v"]), "__side": F.lit(0 if strict else 1)})
    both = rows.unionByName(right, allowMissingColumns=True).withColumn("__left", F.col("__side") == (0 if strict else 1))
    by = Window.partitionBy(*keys).orderBy(at, "__side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last("__v", ignorenulls=True).over(by)).filter("__left").drop("__v", "__side", "__left")


def range_join(rows: DataFrame, bands: DataFrame, x: str, lo: str, hi: str, width: float) -> DataFrame:
    """Rows with every band whose half-open range holds x: bands are cut into bins, the join is on the bin."""
    bins = bands.withColumn("__bin", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return rows.withColumn("__bin", F.floor(F.col(x) / width)).join(bins, "__bin").filter((F.col(x) >= F.col(lo)) & (F.col(x) < F.col(hi))).drop("__bin")


def within(left: DataFrame, right: DataFrame, keys: list[str], at: str, other_at: str, width: int) -> DataFrame:
    """Left rows with every right row of their keys whose `other_at` lies in the `width` before `at`, both ends counted: bins
    of that width, an equi-join on key and bin, no range in the join's key. `at` and `other_at` are whole numbers."""
    near = left.withColumn("__bin", F.explode(F.array(F.floor(F.col(at) / width), F.floor(F.col(at) / width) - 1)))
    back = right.withColumn("__bin", F.floor(F.col(other_at) / width))
    return near.join(back, [*keys, "__bin"]).filter((F.col(other_at) <= F.col(at)) & (F.col(other_at) >= F.col(at) - width)).drop("__bin")


def sibling_pairs(nodes: DataFrame, tolerance: float = 1e-9) -> DataFrame:
    """(task, depth, parent_key, better, worse, gap): siblings of unequal value, each pair once. A parent has at most as many
    children as there are actions, so a parent makes a bounded number of pairs."""
    side = lambda name: nodes.select("task", "depth", "parent_key", F.col("node_key").alias(name), F.col("q").alias(f"{name}_q"))
    both = side("better").join(side("worse"), ["task", "depth", "parent_key"]).filter(F.col("better_q") - F.col("worse_q") > tolerance)
    return both.select("task", "depth", "parent_key", "better", "worse", (F.col("better_q") - F.col("worse_q")).alias("gap"))


def leaked(docs: DataFrame, items: DataFrame, words: int = 5) -> DataFrame:
    """(doc_id, item_id) where the text holds the whole item: an equi-join on one run of the item's inner words (its first
    and last may be parts of longer words in the text), then the substring is checked.

    An item of one or two words has no inner word: such items, few and short, are matched at once against each text by
    one pattern-free pass, guarded to `short` of them. Items without words and null texts leak nowhere."""
    spaced = lambda c: F.filter(F.split(c, r"\s+"), lambda w: w != "")
    cut = items.withColumn("__w", spaced(F.col("text"))).select("item_id", F.col("text").alias("__item"), "__w", F.greatest(F.lit(0), F.least(F.lit(words), F.size("__w") - 2)).alias("__n"))
    texts = docs.select("doc_id", "text")
    long = cut.filter("__n > 0").select("item_id", "__item", "__n", F.array_join(F.slice("__w", F.lit(2), F.col("__n")), " ").alias("__key"))
    sizes = [r["__n"] for r in long.select("__n").distinct().collect()]  # at most `words` values
    run_of = lambda n: lambda k: F.array_join(F.slice("__w", k, F.lit(n)), " ")
    found = None
    for n in sizes:
        runs = texts.withColumn("__w", spaced(F.col("text"))).filter(F.size("__w") >= n)
        runs = runs.withColumn("__key", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("__w") - n + 1), run_of(n))))).drop("__w")
        one = runs.join(long.filter(F.col("__n") == n).drop("__n"), "__key").filter(F.contains("text", "__item")).select("doc_id", "item_id")
        found = one if found is None else found.unionByName(one)
    short = cut.filter((F.col("__n") == 0) & (F.size("__w") > 0)).select("item_id", "__item")
    if not short.isEmpty():
        if short.count() > 10_000:
            raise ValueError("more than 10,000 items of one or two words: almost every text holds some")
        held = F.array(*(F.struct(F.lit(r["item_id"]).alias("item_id"), F.lit(r["__item"]).alias("item")) for r in short.collect()))
        one = texts.filter("text is not null").select("doc_id", F.explode(F.transform(F.filter(held, lambda x: F.contains("text", x["item"])), lambda x: x["item_id"])).alias("item_id"))
        found = one if found is None else found.unionByName(one)
    if found is None:
        return texts.select("doc_id").crossJoin(items.select("item_id").limit(0)).limit(0)
    return found.distinct()


def similar(left: DataFrame, right: DataFrame, dim: int, tables: int = 8, bits: int = 8, tau: float = 0.8, seed: int = 5) -> DataFrame:
    """(left_id, right_id, cosine >= tau) found by sign-of-projection buckets: an equi-join a table, never all pairs.
    Both sides are (id, v array<double>)."""
    planes = np.random.default_rng(seed).normal(size=(tables, bits, dim)).round(4)
    dot = lambda c, p: F.aggregate(F.zip_with(c, F.array(*map(F.lit, map(float, p))), lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    key = lambda t: F.concat(F.lit(f"{t}:"), *(F.when(dot("v", planes[t][b]) >= 0, "1").otherwise("0") for b in range(bits)))
    deal = lambda df, side: df.select(F.col("id").alias(f"{side}_id"), F.col("v").alias(f"{side}_v"), F.explode(F.array(*(key(t) for t in range(tables)))).alias("_key"))
    both = deal(left, "left").join(deal(right, "right"), "_key").dropDuplicates(["left_id", "right_id"])
    from ..functions.rewards import cosine

    return both.withColumn("cosine", cosine(F.col("left_v"), F.col("right_v"))).filter(F.col("cosine") >= tau).select("left_id", "right_id", "cosine")


def parallel(rows: DataFrame, dim: int, tau: float, axes: int = 12, width: float = 0.12, seed: int = 5) -> DataFrame:
    """(left_id, right_id, cosine >= tau), left_id <= right_id, of rows (id, v array<float>): every pair, for tau near 1.

    Unit vectors of that cosine are at most `reach` apart, and so are their parts along any of some orthogonal axes. A left
    row goes to its cell of a grid over those parts, a right row to every cell within reach of it (mostly its own), so a
    pair meets once and in one cell. The grid has far more cells than rows, and no pair is shuffled."""
    from ..functions.rewards import cosine

    reach = float(np.sqrt(2 * (1 - tau))) * (1 + 1e-6) + 1e-9
    basis = np.linalg.qr(np.random.default_rng(seed).normal(size=(dim, min(axes, dim))))[0].T
    v = F.transform("v", lambda x: x.cast("double"))
    size = F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x))
    part = lambda p: F.aggregate(F.zip_with(F.col("_v"), F.array(*map(F.lit, map(float, p))), lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    at = rows.withColumn("_v", v).withColumn("_n", size).filter("_n > 0").withColumn("_p", F.array(*(part(p) for p in basis)))
    at = at.select("id", "v", F.transform("_p", lambda x: x / F.col("_n")).alias("_p"))
    cell = lambda x: F.floor(x / width).cast("int")
    ends = F.transform("_p", lambda x: F.array_distinct(F.array(cell(x - reach), cell(x + reach))))
    cells = F.aggregate(ends, F.array(F.array().cast("array<int>")), lambda done, e: F.flatten(F.transform(done, lambda c: F.transform(e, lambda i: F.array_append(c, i)))))
    left = at.select(F.col("id").alias("left_id"), F.col("v").alias("left_v"), F.transform("_p", cell).alias("_cell"))
    right = at.select(F.col("id").alias("right_id"), F.col("v").alias("right_v"), F.explode(cells).alias("_cell"))
    both = left.join(right, (left["_cell"] == right["_cell"]) & (F.col("left_id") <= F.col("right_id")))
    return both.withColumn("cosine", cosine(F.col("left_v"), F.col("right_v"))).filter(F.col("cosine") >= tau).select("left_id", "right_id", "cosine")

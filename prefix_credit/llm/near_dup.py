"""MinHash near-duplicate groups: banded minima, signature check, exact check, components.

Steps, each a DataFrame:

1. one Arrow pass hashes every whole text to its shingle set and `rows * bands` minima of multiply-shift hashes, folded
   to one key per band and to a signature of one bit a minimum (128 bits at most);
2. texts with the same word sequence form a class, a node from here on; its number is the class's smallest id, so
   thousands of copies cost one row;
3. members of a band bucket meet the bucket's centre and a few neighbours in size order; buckets beyond `chunk`
   rows are salted into chunks whose centres meet in turn. This only joins most copies early, at a row each;
4. pairs whose sizes or signatures rule the threshold out go; the rest is checked on full shingle sets, first one
   pair per text, then only pairs that the first round left in different components;
5. in buckets whose members are still in different components, each meets the member nearest the bucket's majority
   signature (the base of a star of copies), and then every two members that are still apart meet, block against block,
   so no pair that shares a bucket and may reach the threshold goes unchecked unless it is linked already. Pairs that
   cannot reach it are not made: two members have at most the frequent shingles of the poorer one in common and the
   rare ones that they share, and pairs with a rare shingle (of at most `rare` members) in common come from an
   equi-join on it, where a shingle makes a bounded number of them (exact, nothing is lost by it);
6. components by alternating large-star and small-star rounds.

Null or blank texts have an empty set and are linked with nothing. Rows with a null id are dropped from no result:
they get their own null component. A repeated id is one document per distinct text (the second and further texts of an
id get node numbers from 2**62 up, which ids are taken not to reach); repeated rows stay repeated in the result. An
empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WordHashes, map_arrow, mixed, space_words, staged, text_bytes, unstaged

_SKETCH = 128
_NEW = 1 << 62
_SIGNED = "doc_id long, raw long, n_shingles long, class_hi long, class_lo long, bands array<long>, sketch_hi long, sketch_lo long"


def shingle_hashes(words: np.ndarray, n: int) -> np.ndarray:
    """Distinct 64-bit hashes of the n-word shingles; the whole sequence is one when there are fewer words."""
    if not len(words):
        return np.empty(0, np.uint64)
    width = min(n, len(words))
    out = np.full(len(words) - width + 1, np.uint64(0x9E3779B97F4A7C15) * np.uint64(width))
    for k in range(width):
        out = (out ^ words[k : k + len(out)]) * np.uint64(0xD6E8FEB86659FD93)
        out ^= out >> np.uint64(32)
    return np.unique(mixed(out))


def _minima(shingles: np.ndarray, factors: np.ndarray, block: int = 4096) -> np.ndarray:
    low = np.full(len(factors), np.uint64(2**64 - 1))
    for k in range(0, len(shingles), block):
        got = np.multiply.outer(factors, shingles[k : k + block])
        np.minimum(low, got.min(axis=1), out=low)
    return low


def _class(words: list[bytes]) -> tuple[int, int]:
    """128-bit hash of a word sequence, as two signed halves."""
    whole = xxhash.xxh3_128_intdigest(b" ".join(words))
    return (whole >> 64) - 2**63, (whole & 0xFFFFFFFFFFFFFFFF) - 2**63


def raw_hash(text_col: str) -> Column:
    return F.xxhash64(F.col(text_col).cast("string"))


def sign(docs: DataFrame, id_col: str, text_col: str, n: int, rows: int, bands: int) -> DataFrame:
    rng = np.random.default_rng(20240229)
    factors = rng.integers(0, 2**63, rows * bands, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    salts = rng.integers(0, 2**63, bands, dtype=np.uint64)
    bits = min(_SKETCH, rows * bands)

    def batch(b: pa.RecordBatch) -> dict:
        cache, out = WordHashes(), {k: [] for k in ("n_shingles", "class_hi", "class_lo", "bands", "sketch_hi", "sketch_lo")}
        with np.errstate(over="ignore"):
            for raw in text_bytes(b.column(2)):
                words = space_words(raw)
                s = shingle_hashes(cache.of(words), n)
                out["n_shingles"].append(len(s))
                for k, half in zip(("class_hi", "class_lo"), _class(words), strict=True):
                    out[k].append(half)
                if not len(s):
                    for k in ("bands", "sketch_hi", "sketch_lo"):
                        out[k].append(None)
                    continue
                low = _minima(s, factors)
                key, per_band = salts.copy(), low.reshape(bands, rows) >> np.uint64(16)
                for r in range(rows):
                    key = mixed(key ^ per_band[:, r])
                out["bands"].append(key.view(np.int64))
                signature = np.zeros(_SKETCH, np.uint8)
                signature[:bits] = mixed(low[:bits]) & np.uint64(1)
                hi, lo = np.packbits(signature).view(np.int64)
                out["sketch_hi"].append(int(hi))
                out["sketch_lo"].append(int(lo))
        return out | {"doc_id": b.column(0), "raw": b.column(1)}

    return map_arrow(docs.select(F.col(id_col).cast("long"), raw_hash(text_col), F.col(text_col).cast("string")), batch, _SIGNED)


def shingle_sets(wanted: DataFrame, n: int) -> DataFrame:
    """(node, shingles) with the distinct shingle hashes of whole texts; `wanted` is (node, class_hi, class_lo, text), of
    which rows whose text is of another class are passed over."""

    def batch(b: pa.RecordBatch) -> dict:
        cache, nodes, sets = WordHashes(), [], []
        with np.errstate(over="ignore"):
            for node, hi, lo, raw in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), text_bytes(b.column(3)), strict=True):
                words = space_words(raw)
                if _class(words) == (hi, lo):
                    nodes.append(node)
                    sets.append(shingle_hashes(cache.of(words), n).view(np.int64))
        return {"node": nodes, "shingles": sets}

    return map_arrow(wanted.select("node", "class_hi", "class_lo", "text"), batch, "node long, shingles array<long>")


def class_nodes(signed: DataFrame) -> DataFrame:
    """(class_hi, class_lo, doc_id, node): each class with its smallest id, and its node number: that id, or a number
    from 2**62 up where the id stands for another class already."""
    classes = staged(signed.filter("n_shingles > 0 and doc_id is not null").groupBy("class_hi", "class_lo").agg(F.min("doc_id").alias("doc_id")))
    repeated = classes.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"), F.min("class_hi").alias("first_hi")).filter("n > 1").select("doc_id", "first_hi")
    if repeated.isEmpty():
        return classes.withColumn("node", F.col("doc_id"))
    # class_hi alone settles which class keeps the id; two classes of an id that share it would both keep it
    fresh = F.lit(_NEW) + F.shiftrightunsigned(F.xxhash64("class_hi", "class_lo"), 2)
    keeps = F.col("first_hi").isNull() | (F.col("first_hi") == F.col("class_hi"))
    return staged(classes.join(repeated, "doc_id", "left").select("class_hi", "class_lo", "doc_id", F.when(keeps, F.col("doc_id")).otherwise(fresh).alias("node")))


def bucket_members(members: DataFrame) -> DataFrame:
    """(node, n_shingles, sketch_hi, sketch_lo, bucket) with bucket_n, where a bucket has two members or more."""
    sized = members.groupBy("bucket").agg(F.count(F.lit(1)).alias("bucket_n")).filter("bucket_n > 1")
    return members.join(sized, "bucket")


def may_link(me: str, other: str, num: int, den: int, agree: int) -> Column:
    """Sizes and sketches of the two rows (prefixes of their columns) don't rule the threshold out."""
    n, o_n = F.col(f"{me}n_shingles"), F.col(f"{other}n_shingles")
    same = F.lit(_SKETCH) - F.bit_count(F.col(f"{me}sketch_hi").bitwiseXOR(F.col(f"{other}sketch_hi"))) - F.bit_count(F.col(f"{me}sketch_lo").bitwiseXOR(F.col(f"{other}sketch_lo")))
    return (F.lit(den) * F.least(n, o_n) >= F.lit(num) * F.greatest(n, o_n)) & (same >= agree)


def bucket_pairs(members: DataFrame, num: int, den: int, near: int, chunk: int, agree: int) -> DataFrame:
    """First pairs (a < b) of bucket_members: each member with its chunk's centre and with `near` neighbours in size
    order; centres of the chunks of one bucket likewise."""
    members = members.withColumn("part", F.pmod(F.xxhash64("node"), F.ceil(F.col("bucket_n") / F.lit(chunk))))

    def met(df: DataFrame, keys: list[str]) -> DataFrame:
        me = F.struct("node", "n_shingles", "sketch_hi", "sketch_lo")
        by = Window.partitionBy(*keys).orderBy("n_shingles", "node")
        others = [F.lag(me, k).over(by) for k in range(1, near + 1)]
        centre = F.first(me).over(Window.partitionBy(*keys).orderBy("node").rowsBetween(Window.unboundedPreceding, 0))
        return df.select("node", "n_shingles", "sketch_hi", "sketch_lo", F.array(centre, *others).alias("met"))

    def kept(df: DataFrame) -> DataFrame:
        return (
            df.select("node", "n_shingles", "sketch_hi", "sketch_lo", F.explode("met").alias("o"))
            .filter(F.col("o").isNotNull() & (F.col("o.node") != F.col("node")))
            .filter(may_link("", "o.", num, den, agree))
            .select(F.least("node", "o.node").alias("a"), F.greatest("node", "o.node").alias("b"))
        )

    inside = kept(met(members, ["bucket", "part"]))
    centres = members.filter(F.col("bucket_n") > chunk).groupBy("bucket", "part").agg(F.min_by(F.struct("node", "n_shingles", "sketch_hi", "sketch_lo"), "node").alias("c"))
    across = kept(met(centres.select("bucket", "c.*"), ["bucket"]))
    return inside.unionByName(across).distinct()


def apart_members(members: DataFrame, groups: DataFrame) -> DataFrame:
    """Bucket members with their component, of the buckets that hold two components or more."""
    named = members.join(groups.withColumnRenamed("doc_id", "node"), "node", "left").withColumn("component", F.coalesce("component_id", "node")).drop("component_id")
    split = named.groupBy("bucket").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).filter("lo < hi").select("bucket")
    return named.join(split, "bucket", "left_semi")


def hub_pairs(apart: DataFrame, num: int, den: int, agree: int) -> DataFrame:
    """Pairs (a < b) of each member with the one of its bucket whose sketch is nearest the bucket's majority bits."""
    halves = ("sketch_hi", "sketch_lo")
    ones = {f"{h}_{k}": F.sum(F.getbit(h, F.lit(k)).cast("int")) for h in halves for k in range(64)}
    counts = apart.groupBy("bucket").agg(F.count(F.lit(1)).alias("m"), *(c.alias(name) for name, c in ones.items()))

    def majority(h: str) -> Column:
        bits = [F.when(2 * F.col(f"{h}_{k}") > F.col("m"), F.shiftleft(F.lit(1).cast("long"), k)).otherwise(F.lit(0).cast("long")) for k in range(64)]
        return F.aggregate(F.array(*bits), F.lit(0).cast("long"), lambda x, y: x.bitwiseOR(y))

    middle = counts.select("bucket", majority("sketch_hi").alias("mid_hi"), majority("sketch_lo").alias("mid_lo"))
    far = F.bit_count(F.col("sketch_hi").bitwiseXOR(F.col("mid_hi"))) + F.bit_count(F.col("sketch_lo").bitwiseXOR(F.col("mid_lo")))
    hub = apart.join(middle, "bucket").groupBy("bucket").agg(F.min_by(F.struct("node", "n_shingles", *halves, "component"), F.struct(far, "node")).alias("o"))
    met = apart.join(hub, "bucket").filter(F.col("component") != F.col("o.component")).filter(may_link("", "o.", num, den, agree))
    return met.select(F.least("node", "o.node").alias("a"), F.greatest("node", "o.node").alias("b")).distinct()


def own_shingles(sets: DataFrame) -> DataFrame:
    """(node, own): how many of a node's shingles no other of the sets has; nodes without one have no row."""
    seen = sets.select("node", F.explode("shingles").alias("s")).groupBy("s").agg(F.count(F.lit(1)).alias("n"), F.min("node").alias("node"))
    return seen.filter("n = 1").groupBy("node").agg(F.count(F.lit(1)).alias("own"))


def sharing_members(apart: DataFrame, sets: DataFrame, num: int, den: int) -> DataFrame:
    """Bucket members of `apart` but those that have so many shingles of their own that nobody reaches the threshold."""
    shared = F.col("n_shingles") - F.coalesce("own", F.lit(0))
    return apart.join(own_shingles(sets), "node", "left").filter(F.lit(den) * shared >= F.lit(num) * F.col("n_shingles")).drop("own")


def rare_shingles(sets: DataFrame, at_most: int) -> DataFrame:
    """(node, s): shingles that at most so many of the sets have."""
    each = sets.select("node", F.explode("shingles").alias("s"))
    few = each.groupBy("s").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") <= at_most).select("s")
    return each.join(few, "s")


def common_at_most(common: Column, me: str, other: str, num: int, den: int) -> Column:
    """Two sets that have `common` shingles in common or fewer may reach the threshold."""
    return F.lit(den) * common >= F.lit(num) * (F.col(f"{me}n_shingles") + F.col(f"{other}n_shingles") - common)


def rare_pairs(apart: DataFrame, rare: DataFrame, num: int, den: int, agree: int) -> DataFrame:
    """Pairs (a < b) of members of different components that have a rare shingle in common and may reach the threshold
    with those and the frequent ones of the poorer of them. A rare shingle makes a bounded number of pairs."""
    row = F.struct("node", "n_shingles", "sketch_hi", "sketch_lo", "component", "frequent")
    held = rare.join(apart.select("node", row.alias("m")).dropDuplicates(["node"]), "node").select("s", "m")
    met = held.select("s", F.col("m").alias("l")).join(held.select("s", F.col("m").alias("r")), "s")
    met = met.filter((F.col("l.node") < F.col("r.node")) & (F.col("l.component") != F.col("r.component")) & may_link("l.", "r.", num, den, agree))
    met = met.groupBy("l", "r").agg(F.count(F.lit(1)).alias("c"))
    return met.filter(common_at_most(F.col("c") + F.least("l.frequent", "r.frequent"), "l.", "r.", num, den)).select(F.col("l.node").alias("a"), F.col("r.node").alias("b"))


def block_pairs(apart: DataFrame, num: int, den: int, agree: int, block: int) -> DataFrame:
    """All pairs (a < b) of members of one bucket and different components that sizes, signatures and `frequent` (how many
    frequent shingles a member has; all that it can share without a rare one) don't rule out: a bucket is salted into
    blocks of about `block` rows, and every block meets every other and itself. Two members that share several buckets are
    a pair in the smallest of them only."""
    sized = apart.groupBy("bucket").agg(F.ceil(F.count(F.lit(1)) / F.lit(block)).alias("blocks"))
    held = apart.groupBy("node").agg(F.collect_set("bucket").alias("held"))  # a bucket a band at most
    cut = apart.join(sized, "bucket").join(held, "node").withColumn("part", F.pmod(F.xxhash64("node"), "blocks"))
    row = F.struct("node", "n_shingles", "sketch_hi", "sketch_lo", "component", "frequent", "held")
    left = cut.select("bucket", F.col("part").alias("x"), F.explode(F.sequence("part", F.col("blocks") - 1)).alias("y"), row.alias("l"))
    right = cut.select("bucket", F.explode(F.sequence(F.lit(0).cast("long"), "part")).alias("x"), F.col("part").alias("y"), row.alias("r"))
    met = left.join(right.hint("merge"), ["bucket", "x", "y"]).filter(F.col("l.component") != F.col("r.component"))
    met = met.filter(((F.col("x") < F.col("y")) | (F.col("l.node") < F.col("r.node"))) & common_at_most(F.least("l.frequent", "r.frequent"), "l.", "r.", num, den) & may_link("l.", "r.", num, den, agree))
    met = met.filter(F.array_min(F.array_intersect("l.held", "r.held")) == F.col("bucket"))
    return met.select(F.least("l.node", "r.node").alias("a"), F.greatest("l.node", "r.node").alias("b")).distinct()


def last_pairs(apart: DataFrame, sets: DataFrame, num: int, den: int, agree: int, block: int, rare_at: int) -> DataFrame:
    """Pairs of bucket members that are still apart and may reach the threshold: those with a rare shingle in common, and
    those that have frequent ones enough without."""
    apart = staged(sharing_members(apart, sets, num, den))
    rare = staged(rare_shingles(sets.join(apart.select("node").distinct(), "node", "left_semi"), rare_at))
    spent = rare.groupBy("node").agg(F.count(F.lit(1)).alias("rare"))
    apart = staged(apart.join(spent, "node", "left").withColumn("frequent", F.col("n_shingles") - F.coalesce("rare", F.lit(0))).drop("rare"))
    return block_pairs(apart, num, den, agree, block).unionByName(rare_pairs(apart, rare, num, den, agree)).distinct()


def verified(pairs: DataFrame, sets: DataFrame, num: int, den: int) -> DataFrame:
    """Pairs (a, b) whose full sets reach the threshold."""
    left = sets.select(F.col("node").alias("a"), F.col("shingles").alias("sa"))
    right = sets.select(F.col("node").alias("b"), F.col("shingles").alias("sb"))
    both = F.size(F.array_intersect("sa", "sb"))
    return pairs.join(right, "b").join(left, "a").filter(F.lit(den) * both >= F.lit(num) * (F.size("sa") + F.size("sb") - both)).select("a", "b")


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(doc_id, component_id) for every node of (a, b), by alternating large-star and small-star; component_id is the smallest id reached."""

    def star(links: DataFrame, large: bool) -> DataFrame:
        both = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))) if large else links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        if large:
            moved = both.join(low, "a").filter(F.col("b") > F.col("a")).select(F.col("b").alias("x"), "m")
        else:
            moved = both.join(low, "a").select(F.col("b").alias("x"), "m").unionByName(low.select(F.col("a").alias("x"), "m"))
        return moved.filter("x != m").select(F.col("m").alias("a"), F.col("x").alias("b")).distinct()

    now, mark = staged(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).filter("a != b").distinct()), None
    for _ in range(rounds):
        nxt = staged(star(star(now, True), False))
        unstaged(now)
        now = nxt
        seen = now.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")), F.lit(0))).first()
        if tuple(seen) == mark:
            break
        mark = tuple(seen)
    else:
        raise RuntimeError("the components did not settle")
    return now.select(F.col("b").alias("doc_id"), F.col("a").alias("component_id")).unionByName(now.select(F.col("a").alias("doc_id"), F.col("a").alias("component_id")).distinct())


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", n: int = 5, num: int = 80, den: int = 100, rows: int = 5, bands: int = 25, near: int = 3, chunk: int = 20_000, block: int = 1_000, rare: int = 16) -> DataFrame:
    """One row per document: doc_id, raw (hash of the text as it is), n_shingles, component_id, kept.

    Two texts are linked when their sets of n-word shingles have `den * |A & B| >= num * |A | B|`. With `rows` minima
    a band, a pair at the threshold t meets in some band with probability 1-(1-t^rows)^bands: 0.99995 for the defaults,
    0.99995 for t=0.85 with rows=6, bands=21.
    """
    signed = staged(sign(docs, id_col, text_col, n, rows, bands))
    nodes = class_nodes(signed)
    members = (
        signed.select("doc_id", "n_shingles", "class_hi", "class_lo", "sketch_hi", "sketch_lo", "bands")
        .join(nodes, ["class_hi", "class_lo", "doc_id"])
        .dropDuplicates(["node"])
        .select("node", "n_shingles", "sketch_hi", "sketch_lo", F.posexplode("bands").alias("band", "key"))
        .select("node", "n_shingles", "sketch_hi", "sketch_lo", F.xxhash64("band", "key").alias("bucket"))
    )
    bits = min(_SKETCH, rows * bands)
    expected = bits * (1 + num / den) / 2
    slack = 4.5 * (expected * (1 - num / den) / 2) ** 0.5
    agree = _SKETCH - bits + int(expected - slack)
    members = staged(bucket_members(members))
    pairs = staged(bucket_pairs(members, num, den, near, chunk, agree))
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))

    def sets_of(wanted: DataFrame) -> DataFrame:
        """Sets of nodes (node)."""
        named = nodes.join(wanted.distinct(), "node", "left_semi")
        return staged(shingle_sets(texts.join(named.hint("merge"), "doc_id"), n).dropDuplicates(["node"]))

    ends = lambda some: some.select(F.col("a").alias("node")).unionByName(some.select(F.col("b").alias("node")))
    sets = sets_of(ends(pairs))
    first = pairs.groupBy("b").agg(F.min("a").alias("a"))
    links = staged(verified(first.select("a", "b"), sets, num, den))
    groups = staged(components(links))
    at = lambda c: groups.select(F.col("doc_id").alias(c), F.col("component_id").alias(f"{c}_component"))
    apart = pairs.join(first, ["a", "b"], "left_anti").join(at("a"), "a", "left").join(at("b"), "b", "left").filter(~F.coalesce(F.col("a_component"), F.col("a")).eqNullSafe(F.coalesce(F.col("b_component"), F.col("b"))))
    more = staged(verified(apart.select("a", "b"), sets, num, den))
    if not more.isEmpty():
        links = links.unionByName(more)
        groups = staged(components(links))
    rest = staged(hub_pairs(apart_members(members, groups), num, den, agree).join(pairs, ["a", "b"], "left_anti"))
    if not rest.isEmpty():
        more = staged(verified(rest, sets_of(ends(rest)), num, den))
        pairs = pairs.unionByName(rest)
        if not more.isEmpty():
            links = links.unionByName(more)
            groups = staged(components(links))
    rest = staged(apart_members(members, groups))
    if not rest.isEmpty():
        sets = sets_of(rest.select("node"))
        rest = staged(last_pairs(rest, sets, num, den, agree, block, rare).join(pairs, ["a", "b"], "left_anti"))
        more = staged(verified(rest, sets, num, den))
        if not more.isEmpty():
            groups = staged(components(links.unionByName(more)))
    classes = nodes.join(groups.withColumnRenamed("doc_id", "node"), "node", "left").select("class_hi", "class_lo", "doc_id", "node", F.coalesce("component_id", "node").alias("component_id"))
    extra = classes.filter(F.col("node") != F.col("doc_id")).groupBy("component_id").agg(F.min("doc_id").alias("named"))
    if not extra.isEmpty():  # components that hold a further text of some id: the id counts, not the node's number
        classes = classes.join(extra, "component_id", "left").withColumn("component_id", F.least("component_id", "named"))
    return (
        signed.select("doc_id", "raw", "n_shingles", "class_hi", "class_lo")
        .join(classes.select("class_hi", "class_lo", F.col("component_id").alias("class_component")), ["class_hi", "class_lo"], "left")
        .select("doc_id", "raw", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("class_component")).otherwise(F.col("doc_id")).alias("component_id"))
        .withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))
    )


def without_near_duplicates(docs: DataFrame, text_col: str = "text", **how) -> DataFrame:
    """Rows of `docs`, all columns, but those in a group that has a smaller id; of an id with several texts only the texts
    that are in such a group go."""
    gone = near_duplicates(docs, text_col=text_col, **how).filter("not kept").select("doc_id", F.col("raw").alias("__raw")).distinct()
    id_col = how.get("id_col", "doc_id")
    return docs.withColumns({"__raw": raw_hash(text_col), "__id": F.col(id_col).cast("long")}).join(gone.withColumnRenamed("doc_id", "__id"), ["__id", "__raw"], "left_anti").select(*docs.columns)


def op7_minhash_near_dedup(spark, sf_dir: str) -> DataFrame:
    """Contract query: 3-word shingles, links at 85/100, over the whole documents table."""
    from .common import table

    return near_duplicates(table(spark, sf_dir, "documents"), n=3, num=85, den=100, rows=6, bands=21).drop("raw")


#: The contract query in DuckDB's SQL, by brute force: shingle sets, all pairs that share a shingle, reachability.
ORACLE = r"""
WITH RECURSIVE d AS (
  SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda w: w <> '') AS raw FROM documents
), w AS (
  SELECT doc_id, list_transform(raw, lambda x: translate(x, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS w FROM d
), s AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')]
    ELSE list_distinct(list_transform(range(1, len(w) - 1), lambda k: w[k] || ' ' || w[k + 1] || ' ' || w[k + 2])) END AS s FROM w
), n AS (SELECT doc_id, len(s) AS n FROM s),
x AS (SELECT doc_id, unnest(s) AS g FROM s),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM x a JOIN x b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
e AS (SELECT a, b FROM p JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * i >= 85 * (na.n + nb.n - i)),
u AS (SELECT a, b FROM e UNION ALL SELECT b, a FROM e),
r AS (SELECT doc_id AS a, doc_id AS b FROM n UNION SELECT r.a, u.b FROM r JOIN u ON u.a = r.b),
c AS (SELECT a AS doc_id, min(b) AS component_id FROM r GROUP BY 1)
SELECT n.doc_id, n.n AS n_shingles, component_id, n.doc_id = component_id AS kept FROM n JOIN c ON c.doc_id = n.doc_id
"""

"""Action prefix tree as relations: keyed steps, node values, shapes, incremental merge.

A node is a prefix of actions within a task; its key is a chained 64-bit hash, scoped by (task, depth), or a readable
path, or dense ids assigned level by level (one shuffle a level). Paths and ids tell any two prefixes apart, whatever
signs the actions hold; hashes do but for chance (64 bits within a task and depth). Every keying makes the action a function of
the key."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

ROOT = 0
_SEP = ">"
_PARTS = ("action_type", "target_obj", "receptacle_obj")


def escaped(text: Column) -> Column:
    """Text in which the signs that separate parts and steps carry a backslash; null becomes the bare empty-set sign."""
    return F.coalesce(F.when(text.rlike(r"[\\/>|∅]"), F.regexp_replace(text, r"([\\/>|∅])", r"\\$1")).otherwise(text), F.lit("∅"))


def action_text(action: Column) -> Column:
    """The triple as text that no other triple has; a missing part is the sign for the empty set, so null equals null."""
    return F.concat_ws("/", *(escaped(action[p]) for p in _PARTS))


def text_action(text: Column) -> Column:
    """The triple that `action_text` wrote."""
    parts = F.regexp_extract_all(F.concat(text, F.lit("/")), F.lit(r"((?:[^\\/]|\\.)*)/"), F.lit(1))
    plain = F.transform(parts, lambda x: F.when(x != "∅", F.regexp_replace(x, r"\\(.)", "$1")))
    return F.struct(*(F.get(plain, F.lit(k)).alias(p) for k, p in enumerate(_PARTS)))


def _chained(key: Column, *values: Column) -> Column:
    """The next hash: values in order and which of them are null, since hashing passes over nulls."""
    nulls = sum((F.when(v.isNull(), 1 << k).otherwise(0) for k, v in enumerate(values)), F.lit(0))
    return F.xxhash64(key, nulls, *values)


def pack(steps: DataFrame) -> DataFrame:
    """Long steps (task, traj, r, t, action, text) to one row a trajectory."""
    return steps.groupBy("task", "traj", "r").agg(F.sort_array(F.collect_list(F.struct("t", "action", "text"))).alias("s")).select("task", "traj", "r", F.transform("s", lambda x: F.struct(x["action"].alias("action"), x["text"].alias("text"))).alias("steps"))


def with_prefix_keys(plans: DataFrame, keying: str = "hash", by_text: bool = False) -> DataFrame:
    """Packed plans to keyed steps, one row a step. A plan without steps has no row. `by_text` merges only steps of equal
    raw text and triple instead of equal triples."""
    if keying == "level":
        return _by_level(with_prefix_keys(plans, "path", by_text))
    if keying == "path":
        label = (lambda s: F.concat_ws("/", action_text(s["action"]), escaped(s["text"]))) if by_text else (lambda s: action_text(s["action"]))
        zero, grow = F.lit(""), lambda key, s: F.concat(key, F.lit(_SEP), label(s))
    else:
        zero, grow = F.lit(ROOT).cast("long"), lambda key, s: _chained(key, *(s["action"][p] for p in _PARTS), *([s["text"]] if by_text else []))
    empty = F.array().cast("array<string>" if keying == "path" else "array<long>")
    start = F.struct(zero.alias("key"), empty.alias("keys"))

    def step(acc: Column, s: Column) -> Column:
        key = grow(acc["key"], s)
        return F.struct(key.alias("key"), F.array_append(acc["keys"], key).alias("keys"))

    keyed = plans.withColumn("keys", F.aggregate("steps", start, step, lambda a: a["keys"]))
    at = keyed.select("task", "traj", "r", F.size("steps").alias("n_steps"), "keys", F.posexplode("steps").alias("_p", "_s"))
    return at.select("task", "traj", "r", "n_steps", (F.col("_p") + 1).alias("t"), F.when(F.col("_p") == 0, zero).otherwise(F.get("keys", F.col("_p") - 1)).alias("parent_key"), F.get("keys", F.col("_p")).alias("node_key"), F.col("_s.action").alias("action"), F.col("_s.text").alias("text"))


def _by_level(steps: DataFrame) -> DataFrame:
    """Readable paths to dense ids: no two prefixes of a task and depth share one. Ids grow with the plans: merge joins."""
    ids = steps.select("task", "t", "node_key").distinct().withColumn("id", F.row_number().over(Window.partitionBy("task", "t").orderBy("node_key")).cast("long"))
    up = ids.select("task", (F.col("t") + 1).alias("t"), F.col("node_key").alias("parent_key"), F.col("id").alias("parent_id"))
    out = steps.join(ids.hint("merge"), ["task", "t", "node_key"]).join(up.hint("merge"), ["task", "t", "parent_key"], "left")
    return out.select("task", "traj", "r", "n_steps", "t", F.coalesce("parent_id", F.lit(ROOT).cast("long")).alias("parent_key"), F.col("id").alias("node_key"), "action", "text")


def discounted_return(gamma: float) -> Column:
    """Label discounted from the end of the plan: a step far from the end counts less."""
    return F.pow(F.lit(gamma), F.col("n_steps") - F.col("t")) * F.col("r")


def node_values(steps: DataFrame, gamma: float, keep_returns: bool = False) -> DataFrame:
    """Nodes with mean return q and visits n; sums and counts are partial before the shuffle. `keep_returns` adds the
    returns themselves, a list that grows with the visits."""
    extra = [F.sort_array(F.collect_list("ret")).alias("returns")] if keep_returns else []
    rows = steps.withColumn("ret", discounted_return(gamma))
    return rows.groupBy("task", F.col("t").alias("depth"), "parent_key", "node_key", "action").agg(F.avg("ret").alias("q"), F.count(F.lit(1)).alias("n"), *extra)


def node_sums(steps: DataFrame, gamma: float) -> DataFrame:
    """Mergeable node state: total return and visits."""
    rows = steps.withColumn("ret", discounted_return(gamma))
    return rows.groupBy("task", F.col("t").alias("depth"), "parent_key", "node_key", "action").agg(F.sum("ret").alias("total"), F.count(F.lit(1)).alias("n"))


def merge_trie(state: DataFrame, delta: DataFrame) -> DataFrame:
    """Stored node sums with those of new plans."""
    keys = ["task", "depth", "parent_key", "node_key", "action"]
    return state.unionByName(delta).groupBy(*keys).agg(F.sum("total").alias("total"), F.sum("n").alias("n"))


def trie_shape(nodes: DataFrame, per_task: bool = True) -> DataFrame:
    """Branching parents, leaves and mean sibling group size of each task's tree (or of all pooled).

    Every parent of k children adds k - 1 leaves to the one of a bare path, so leaves need no second pass."""
    groups = nodes.groupBy("task", "depth", "parent_key").agg(F.count(F.lit(1)).alias("k"))
    many = F.col("k") > 1
    out = groups.groupBy("task").agg(F.count_if(many).alias("branching"), F.sum(F.when(many, F.col("k")).otherwise(0)).alias("children"), (F.sum(F.col("k") - 1) + 1).alias("leaves"))
    if not per_task:
        out = out.agg(*(F.sum(c).alias(c) for c in ("branching", "children", "leaves")))
    return out.withColumn("group_size", F.try_divide(F.col("children").cast("double"), F.col("branching")))


def group_size_by_verb(nodes: DataFrame) -> DataFrame:
    """Mean number of continuations after a prefix that ends in each verb, branching prefixes only."""
    groups = nodes.groupBy("task", "depth", "parent_key").agg(F.count(F.lit(1)).alias("k")).filter("k > 1")
    ends = nodes.select("task", (F.col("depth") + 1).alias("depth"), F.col("node_key").alias("parent_key"), F.col("action.action_type").alias("verb"))
    return groups.join(ends, ["task", "depth", "parent_key"]).groupBy("verb").agg(F.count(F.lit(1)).alias("parents"), F.avg("k").alias("group_size"))

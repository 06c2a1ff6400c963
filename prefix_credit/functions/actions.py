"""Free-text plan steps to canonical action triples, and vocabulary limits."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

STEP_PATTERN = r"(?i)^\s*(?:step\s+\d+\s*:)?\s*(.*?)\s+the\s+(.*?)(?:\s+(?:on|in|at)\s+the\s+(.*?))?\s*\.?\s*$"
TAG_PATTERN = r"<act>([^|<]*)\|([^|<]*)\|([^<]*)</act>"


def synonym_map(synonyms: dict[str, list[str]]) -> Column:
    """Phrase -> canonical verb, as a map literal (bounded by the grammar)."""
    pairs = [(p, verb) for verb, phrases in synonyms.items() for p in {verb, *phrases}]
    return F.create_map(*(F.lit(x) for p in sorted(pairs) for x in p))


def parse_action(text: Column, synonyms: dict[str, list[str]]) -> Column:
    """struct<action_type, target_obj, receptacle_obj, known>: an unknown verb is kept as it stands, with known = false;
    text that is no step gives null."""
    part = lambda k: F.regexp_extract(text, STEP_PATTERN, k)
    verb = F.lower(part(1))
    canonical = F.try_element_at(synonym_map(synonyms), verb)
    out = F.struct(F.coalesce(canonical, verb).alias("action_type"), part(2).alias("target_obj"), F.nullif(part(3), F.lit("")).alias("receptacle_obj"), canonical.isNotNull().alias("known"))
    return F.when(text.rlike(STEP_PATTERN), out)


def parse_tagged(text: Column) -> Column:
    """array of triples from a plan with tagged actions."""
    found = lambda k: F.regexp_extract_all(text, F.lit(TAG_PATTERN), F.lit(k))
    return F.transform(F.arrays_zip(found(1).alias("a"), found(2).alias("t"), found(3).alias("r")), lambda x: F.struct(x["a"].alias("action_type"), x["t"].alias("target_obj"), F.nullif(x["r"], F.lit("")).alias("receptacle_obj")))


def to_plan_record(df: DataFrame, reply: str, actions: str) -> DataFrame:
    """Adds `plan`: the reply and the tagged plan of an array of triples, in one text."""
    tag = lambda a: F.concat(F.lit("<act>"), F.concat_ws("|", a["action_type"], a["target_obj"], F.coalesce(a["receptacle_obj"], F.lit(""))), F.lit("</act>"))
    return df.withColumn("plan", F.concat(F.lit("<reply>"), F.coalesce(reply, F.lit("")), F.lit("</reply><plan>"), F.array_join(F.transform(actions, tag), ""), F.lit("</plan>")))


def _expanded(compound: str, parts: list[str]):
    """A step to the array of primitive steps that stand for it."""
    renamed = lambda s, verb: s.withField("action", s["action"].withField("action_type", F.lit(verb)))
    return lambda s: F.when(s["action"]["action_type"] == compound, F.array(*(renamed(s, p) for p in parts))).otherwise(F.array(s))


def restrict_vocabulary(plans: DataFrame, allowed: set[str] | None = None, banned: set[str] = frozenset(), on_violation: str = "drop", expansion: dict[str, list[str]] | None = None) -> DataFrame:
    """Packed plans with primitive verbs only: other steps are dropped, flagged (column `violations`), or expanded into
    primitive ones by `expansion`."""
    verb = lambda s: s["action"]["action_type"]
    bad = (lambda s: ~verb(s).isin(*allowed)) if allowed is not None else (lambda s: verb(s).isin(*banned))
    if on_violation == "flag":
        return plans.withColumn("violations", F.size(F.filter("steps", bad)))
    if on_violation == "expand":
        steps = F.col("steps")
        for compound, parts in (expansion or {}).items():
            steps = F.flatten(F.transform(steps, _expanded(compound, parts)))
        return plans.withColumn("steps", steps)
    return plans.withColumn("steps", F.filter("steps", lambda s: ~bad(s)))


def limit_steps(plans: DataFrame, max_steps: int) -> DataFrame:
    return plans.filter(F.size("steps") <= max_steps)

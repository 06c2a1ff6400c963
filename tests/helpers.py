"""Packed plans from plain Python, and a brute-force tree."""

from pyspark.sql import types as T

ACTION = "struct<action_type:string,target_obj:string,receptacle_obj:string>"


def packed(spark, plans):
    """plans: (task, traj, r, [verb or (verb, target, receptacle)])."""
    rows = []
    for task, traj, r, steps in plans:
        full = [(s if isinstance(s, tuple) else (s, None, None)) for s in steps]
        rows.append((task, traj, r, [{"action": dict(zip(("action_type", "target_obj", "receptacle_obj"), s)), "text": "/".join(x for x in s if x)} for s in full]))
    return spark.createDataFrame(rows, T._parse_datatype_string(f"task long, traj long, r int, steps array<struct<action:{ACTION},text:string>>"))


def brute(plans, gamma, eps):
    """{(task, path): (q, n, k, advantage)} by dictionaries."""
    ret = {}
    for task, _, r, steps in plans:
        for t in range(1, len(steps) + 1):
            ret.setdefault((task, tuple(steps[:t])), []).append(gamma ** (len(steps) - t) * r)
    q = {k: sum(v) / len(v) for k, v in ret.items()}
    kids = {}
    for task, path in q:
        kids.setdefault((task, path[:-1]), []).append(path)
    out = {}
    for (task, parent), paths in kids.items():
        vals = [q[(task, p)] for p in paths]
        mu = sum(vals) / len(vals)
        sd = (sum((v - mu) ** 2 for v in vals) / len(vals) + eps) ** 0.5
        for p in paths:
            out[(task, p)] = (q[(task, p)], len(ret[(task, p)]), len(paths), (q[(task, p)] - mu) / sd)
    return out

"""Length-bucketed packing: optimal bucket boundaries from the global histogram, token-budget batches inside buckets.

The histogram is exact: one row a distinct length, so its size is bounded by the longest text, not by the rows. Dynamic
programming over it picks the boundaries with the least total padding of all; the best place of the last boundary never
moves back as lengths grow, so each layer is solved by halving, in m log m steps. Rows of a bucket are dealt into parts of about `part_rows` by a hash of the id, and batches of
`token_budget // boundary` rows (one at least) are cut from each part, so a bucket with most of the rows still
spreads over tasks.

Null or empty texts have length 0 and go to the shortest bucket; a text longer than the budget is alone in its batch
and keeps all its tokens; repeated rows each get a place; an empty table gives an empty result; columns of the input named
like a result are replaced.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import staged


def optimal_boundaries(lengths: np.ndarray, counts: np.ndarray, sums: np.ndarray, buckets: int) -> list[int]:
    """Boundaries (largest lengths of buckets, ascending) with the least total padding; `lengths` ascending."""
    m = len(lengths)
    if not m:
        return []
    n, s = np.concatenate([[0], np.cumsum(counts, dtype=np.float64)]), np.concatenate([[0], np.cumsum(sums, dtype=np.float64)])
    best = lengths * n[1:] - s[1:]  # one bucket over lengths 0..j
    came: list[np.ndarray] = []
    for _ in range(min(buckets, m) - 1):
        ahead = np.concatenate([[0.0], best])  # padding of what lies below a bucket that starts at i
        nxt, frm = np.empty(m), np.zeros(m, np.int64)
        todo = [(0, m - 1, 0, m - 1)]
        while todo:
            lo, hi, first, last = todo.pop()
            if lo > hi:
                continue
            j = (lo + hi) // 2
            i = np.arange(first, min(j, last) + 1)
            cost = ahead[i] + lengths[j] * (n[j + 1] - n[i]) - (s[j + 1] - s[i])
            k = int(cost.argmin())
            frm[j], nxt[j] = i[k], cost[k]
            todo += [(lo, j - 1, first, int(i[k])), (j + 1, hi, int(i[k]), last)]
        came.append(frm)
        best = nxt
    out, j = [], m - 1
    for frm in [*came[::-1], None]:
        out.append(int(lengths[j]))
        if frm is None or frm[j] == 0:
            break
        j = int(frm[j]) - 1
    return out[::-1]


def boundaries(df: DataFrame, length: str, buckets: int) -> tuple[list[int], dict[int, int]]:
    """Optimal boundaries and the row count of each bucket."""
    hist = df.groupBy(length).agg(F.count(F.lit(1)).alias("n")).orderBy(length).toArrow()
    tops, n = (hist.column(k).to_numpy().astype(np.float64) for k in (length, "n"))
    edges = optimal_boundaries(tops, n, n * tops, buckets)
    return edges, {b: int(n[np.searchsorted(edges, tops) == b].sum()) for b in range(len(edges))}


def pack(df: DataFrame, id_col: str, length: str, buckets: int = 16, token_budget: int = 65_536, part_rows: int = 50_000) -> DataFrame:
    """Adds bucket, bucket_len, batch (name), position (from 0 in the batch) and padding."""
    edges, counts = boundaries(df, length, buckets)
    if not edges:
        edges, counts = [0], {0: 0}
    bucket = sum((F.when(F.col(length) > e, 1).otherwise(0) for e in edges[:-1]), F.lit(0))
    pick = lambda values: F.element_at(F.array(*map(F.lit, values)), F.col("bucket") + 1)
    parts = [max(1, -(-counts[b] // part_rows)) for b in range(len(edges))]
    out = df.withColumn("bucket", bucket).withColumn("bucket_len", pick([int(e) for e in edges]).cast("long"))
    out = out.withColumn("__part", F.pmod(F.xxhash64(id_col), pick([int(p) for p in parts]).cast("long")))
    at = F.row_number().over(Window.partitionBy("bucket", "__part").orderBy(F.col(id_col).asc_nulls_first())) - 1
    room = pick([max(1, token_budget // max(1, int(e))) for e in edges])
    return (
        out.withColumn("__at", at)
        .withColumn("batch", F.concat_ws("-", "bucket", "__part", F.floor(F.col("__at") / room)))
        .withColumn("position", (F.col("__at") % room).cast("int"))
        .withColumn("padding", F.col("bucket_len") - F.col(length))
        .drop("__at", "__part")
    )


def token_lengths(docs: DataFrame) -> DataFrame:
    """doc_id and n_tokens: words between white space, over whole texts."""
    return docs.select("doc_id", F.coalesce(F.regexp_count(F.col("text").cast("string"), F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long").alias("n_tokens"))


def packed_documents(docs: DataFrame) -> DataFrame:
    return pack(staged(token_lengths(docs)), "doc_id", "n_tokens")


def op9_length_bucket_packing(spark, sf_dir: str) -> DataFrame:
    """Every document with its bucket, batch, position and padding: 16 buckets, 65,536 tokens a batch."""
    from .common import table

    return packed_documents(table(spark, sf_dir, "documents"))


def oracle(buckets: int = 16, token_budget: int = 65_536) -> str:
    """The query in DuckDB's SQL, one CTE a layer of the dynamic program; for tables whose buckets need one part."""
    sql = f"""
WITH d AS (SELECT doc_id, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')) AS BIGINT) AS n_tokens FROM documents),
h AS (SELECT n_tokens AS l, count(*) AS n, sum(n_tokens) AS s FROM d GROUP BY 1),
b AS (SELECT row_number() OVER (ORDER BY l) AS j, CAST(l AS DOUBLE) AS l, CAST(sum(n) OVER (ORDER BY l) AS DOUBLE) AS n, CAST(sum(s) OVER (ORDER BY l) AS DOUBLE) AS s FROM h),
c AS MATERIALIZED (SELECT y.j, x.j + 1 AS i, y.l * (y.n - x.n) - (y.s - x.s) AS cost FROM b y JOIN (SELECT j, n, s FROM b UNION ALL SELECT 0, 0, 0) x ON x.j < y.j),
k1 AS MATERIALIZED (SELECT j, cost AS v, CAST(1 AS BIGINT) AS i FROM c WHERE i = 1)"""
    for k in range(2, buckets + 1):
        sql += f""",
k{k} AS MATERIALIZED (SELECT c.j, min(coalesce(p.v, 0) + cost) AS v, arg_min(c.i, (coalesce(p.v, 0) + cost, c.i)) AS i FROM c LEFT JOIN k{k - 1} p ON p.j = c.i - 1 GROUP BY c.j)"""
    sql += f""",
e{buckets} AS (SELECT max(j) AS j FROM b)"""
    for k in range(buckets - 1, 0, -1):
        sql += f""",
e{k} AS (SELECT i - 1 AS j FROM k{k + 1} JOIN e{k + 1} ON e{k + 1}.j = k{k + 1}.j WHERE i > 1)"""
    every = " UNION ALL ".join(f"SELECT j FROM e{k}" for k in range(1, buckets + 1))
    return (
        sql
        + f""",
edges AS (SELECT row_number() OVER (ORDER BY l) - 1 AS bucket, CAST(l AS BIGINT) AS l, CAST(coalesce(lag(l) OVER (ORDER BY l), -1) AS BIGINT) AS below FROM b WHERE j IN ({every})),
p AS (SELECT d.*, CAST(bucket AS INTEGER) AS bucket, l AS bucket_len, greatest(1, {token_budget} // greatest(1, l)) AS room, row_number() OVER (PARTITION BY bucket ORDER BY doc_id) - 1 AS place FROM d JOIN edges ON n_tokens > below AND n_tokens <= l)
SELECT doc_id, n_tokens, bucket, bucket_len, bucket || '-0-' || (place // room) AS batch, CAST(place % room AS INTEGER) AS position, bucket_len - n_tokens AS padding FROM p
"""
    )

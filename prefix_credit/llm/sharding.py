"""Hilbert-curve sharding: quantised metadata dimensions, curve index, runs of the curve cut into shards.

Everything runs as DataFrame expressions. Each dimension is cut at quantiles of the whole column (whole strings by
their bytes, so that files keep lexical min/max ranges); the cell's place on the Hilbert curve comes from a lookup
table of `2 ** (bits * dimensions)` entries made from the curve's rule. Rows get a gapless rank along (curve index,
salt, id) from counts per (index, salt) instead of a global sort, so no task sees more than one salt of one cell and
a third of all rows in one cell spreads over `salts` windows.

Null metadata sorts lowest; null or empty texts have size 1 and CRC 0 of the empty string; repeated rows and ids each
keep a slot of their own; an empty table gives an empty result; more columns of
the input are carried along, but for those named like the results (curve, rank, total, shard, slot), which are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import shared_dir, staged, table


def hilbert_index(point: tuple[int, ...], bits: int) -> int:
    """Distance along the Hilbert curve of a cell: undo the excess rotations from the top bit down, then Gray-decode."""
    x, n = list(point), len(point)
    for level in range(bits - 1, 0, -1):
        q = 1 << level
        for i in range(n):
            if x[i] & q:
                x[0] ^= q - 1
            else:
                t = (x[0] ^ x[i]) & (q - 1)
                x[0] ^= t
                x[i] ^= t
    for i in range(1, n):
        x[i] ^= x[i - 1]
    t = 0
    for level in range(bits - 1, 0, -1):
        if x[n - 1] & (1 << level):
            t ^= (1 << level) - 1
    x = [v ^ t for v in x]
    out = 0
    for level in range(bits - 1, -1, -1):
        for v in x:
            out = out << 1 | v >> level & 1
    return out


def curve_table(dimensions: int, bits: int) -> list[int]:
    """Curve index of every cell, cells in row-major order."""
    side = 1 << bits
    return [hilbert_index(tuple(cell // side**k % side for k in range(dimensions - 1, -1, -1)), bits) for cell in range(side**dimensions)]


def as_ordered(df: DataFrame, name: str) -> Column:
    """The column as it is compared: whole strings by their bytes, all else as doubles; null lowest."""
    if dict(df.dtypes)[name] == "string":
        return F.coalesce(F.col(name), F.lit(""))
    return F.coalesce(F.col(name).cast("double"), F.lit(float("-inf")))


def string_cuts(df: DataFrame, value: Column, side: int, parts: int = 64) -> list[str]:
    """Exact quantiles of whole strings: cumulative counts of distinct values, range by range, so no task sees them all."""
    counts = df.groupBy(value.alias("v")).agg(F.count(F.lit(1)).alias("n")).repartitionByRange(parts, "v")
    counts = staged(counts.withColumn("part", F.spark_partition_id()))
    one = Window.partitionBy(F.lit(0))
    sums = counts.groupBy("part").agg(F.sum("n").alias("m"))
    sums = sums.select("part", (F.sum("m").over(one.orderBy("part")) - F.col("m")).alias("before"), F.sum("m").over(one).alias("total"))
    ends = counts.join(F.broadcast(sums), "part").withColumn("end", F.col("before") + F.sum("n").over(Window.partitionBy("part").orderBy("v")))
    return [r["v"] for r in ends.filter(F.expr(f"least({side - 1}, ({side} * end) div total) > ({side} * (end - n)) div total")).select("v").collect()]


def hilbert_order(df: DataFrame, dims: list[str], bits: int = 4) -> DataFrame:
    """Adds `curve`, the Hilbert index of the row's cell in `dims`, each cut into 2**bits quantile bins."""
    side = 1 << bits
    values = {d: as_ordered(df, d) for d in dims}
    texts = [d for d in dims if dict(df.dtypes)[d] == "string"]
    cuts = {d: string_cuts(df, values[d], side) for d in texts}
    if rest := [d for d in dims if d not in cuts]:
        cuts |= df.agg(*(F.percentile_approx(values[d], [k / side for k in range(1, side)], 50_000).alias(d) for d in rest)).first().asDict()
    cell = F.lit(0)
    for d in dims:
        bounds = sorted({c for c in cuts[d] or [] if c is not None})
        cell = cell * side + sum((F.when(values[d] > F.lit(c), 1).otherwise(0) for c in bounds), F.lit(0))
    curve = F.element_at(F.array(*map(F.lit, curve_table(len(dims), bits))), (cell + 1).cast("int"))
    return df.withColumn("curve", curve)


def gapless_rank(df: DataFrame, order: str, tie: str, salts: int) -> DataFrame:
    """Adds `rank` (long, from 0) along (order, salt, tie) and `total`, from counts of (order, salt) groups.

    `order` must have a bounded number of values. Columns named rank or total are replaced."""
    whole = dict(df.dtypes)[tie] in ("bigint", "int", "smallint", "tinyint")
    spread = F.pmod(F.pmod(F.coalesce(F.col(tie), F.lit(0)), F.lit(1_000_003)) * 7919 + 104_729, F.lit(1_000_003)) if whole else F.xxhash64(tie)
    df = df.drop("rank", "total").withColumn("__salt", F.pmod(spread, F.lit(salts)))
    groups = df.groupBy(order, "__salt").agg(F.count(F.lit(1)).alias("__n"))
    cells = groups.groupBy(order).agg(F.sum("__n").alias("__cell"))
    one = Window.partitionBy(F.lit(0))
    cells = cells.select(order, (F.sum("__cell").over(one.orderBy(order)) - F.col("__cell")).alias("__before"), F.sum("__cell").over(one).alias("total"))
    inside = Window.partitionBy(order).orderBy("__salt")
    groups = groups.join(F.broadcast(cells), order).select(order, "__salt", (F.col("__before") + F.sum("__n").over(inside) - F.col("__n")).alias("__before"), "total")
    ranked = df.withColumn("__at", F.row_number().over(Window.partitionBy(order, "__salt").orderBy(F.col(tie).asc_nulls_first())))
    return ranked.join(groups, [order, "__salt"]).withColumn("rank", F.col("__before") + F.col("__at") - 1).drop("__before", "__at", "__salt")


def cut_runs(df: DataFrame, shards: int) -> DataFrame:
    """Adds shard (0..shards-1) and slot (gapless from 0) so that shard counts are at most one apart."""
    shard = F.expr(f"(rank * {shards}) div total")
    return df.withColumn("shard", shard.cast("int")).withColumn("slot", F.col("rank") - F.expr(f"(shard * total + {shards} - 1) div {shards}"))


def shard_by_curve(df: DataFrame, dims: list[str], tie: str, shards: int, bits: int = 4, salts: int = 4096) -> DataFrame:
    """Rows with curve, shard and slot: runs of the curve, equal in rows."""
    return cut_runs(gapless_rank(hilbert_order(df, dims, bits), "curve", tie, salts), shards)


def write_shards(df: DataFrame, path: str) -> None:
    """Write rows with `shard` as one folder a shard, in curve order, so that file min/max ranges prune every dimension."""
    df.repartition("shard").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)


def op2_hilbert_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract query: documents along (source, lang, n_chars) into 16 shards by the law `rows`."""
    shared_dir(spark)
    text = F.col("text").cast("string")
    meta = staged(
        table(spark, sf_dir, "documents").select(
            "doc_id", "source", "lang", "n_chars", (F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + 1).alias("size"), F.crc32(F.coalesce(text, F.lit(""))).cast("long").alias("text_crc32")
        )
    )
    return shard_by_curve(meta, ["source", "lang", "n_chars"], "doc_id", 16).select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "curve")


def oracle(shards: int = 16, bits: int = 4, salts: int = 4096) -> str:
    """The contract query in DuckDB's SQL, for tables small enough that the quantiles are exact."""
    side = 1 << bits
    digit = lambda x: f"(strpos('0123456789ABCDEF', {x}) - 1)"
    text = lambda c: f"list_reduce(list_transform(range(1, 13), lambda k: CAST({digit(f"rpad(left(hex(encode(coalesce({c}, ''))), 12), 12, '0')[k]")} AS DOUBLE)), lambda x, y: x * 16 + y)"
    dims = {"a": text("source"), "b": text("lang"), "c": "coalesce(CAST(n_chars AS DOUBLE), -1e308)"}
    cuts = ", ".join(f"list_distinct(quantile_disc({d}, [{', '.join(str(k / side) for k in range(1, side))}])) AS q{d}" for d in dims)
    cell = " + ".join(f"{side ** (len(dims) - 1 - k)} * len(list_filter(q{d}, lambda q: {d} > q))" for k, d in enumerate(dims))
    return f"""
WITH t AS (
  SELECT list_transform(range(256), lambda i: list_reduce(list_concat([CAST(i AS BIGINT)], CAST(range(8) AS BIGINT[])), lambda c, k: CASE WHEN c % 2 = 1 THEN xor(3988292384, c // 2) ELSE c // 2 END)) AS t
), crc AS (
  SELECT doc_id, xor(4294967295, list_reduce(list_concat([4294967295], list_transform(range(octet_length(encode(coalesce(text, '')))),
    lambda k: CAST({digit("h[2 * k + 1]")} * 16 + {digit("h[2 * k + 2]")} AS BIGINT))), lambda a, b: xor(t[xor(a % 256, b) + 1], a // 256))) AS text_crc32
  FROM (SELECT doc_id, text, string_split(hex(encode(coalesce(text, ''))), '') AS h FROM documents) x, t
), m AS (
  SELECT doc_id, CAST(coalesce(octet_length(encode(text)), 0) + 1 AS BIGINT) AS size, text, {", ".join(f"{e} AS {d}" for d, e in dims.items())} FROM documents
), q AS (SELECT {cuts} FROM m),
h AS (SELECT doc_id, size, text, {curve_table(len(dims), bits)}[{cell} + 1] AS curve FROM m CROSS JOIN q),
r AS (SELECT *, row_number() OVER (ORDER BY curve, (((doc_id % 1000003) * 7919 + 104729) % 1000003) % {salts}, doc_id) - 1 AS place, count(*) OVER () AS total FROM h),
s AS (SELECT *, CAST(place * {shards} // total AS INTEGER) AS shard FROM r)
SELECT s.doc_id, size, CAST(text_crc32 AS BIGINT) AS text_crc32, 'rows' AS law, shard, place - (shard * total + {shards - 1}) // {shards} AS slot, CAST(NULL AS INTEGER) AS grown_shard, curve FROM s JOIN crc ON crc.doc_id = s.doc_id
"""

"""Nearest neighbours by inner product: inverted lists, product-quantised residuals, exact reranking.

* A bounded sample (the first `sample` vectors in the order of a hash of the id) gives coarse centroids (k-means on
  directions) and one codebook a subspace for the residuals; the model is a few hundred KB and travels with the tasks.
* Every vector goes to the list of the centroid with the largest inner product and is coded.
* Neighbouring lists share a cell; there are about `cells` of them whatever the table's size (fewer if they would hold
  less than `chunk` vectors; a longer list has several), so a query gets rows from a bounded number of them.
* First, a query goes to the cells of its best lists until these hold `least_seen` vectors. Its k-th score there bounds
  what it needs from elsewhere.
* Then it goes to every other cell with a list whose members may still reach that score: for members with a part from
  `low` to `high` along the centroid and at most `wide` across it, a product is at most the better of low and high
  times the query's part along it, and wide times its part across it. Clustered vectors leave few such lists, others most.
* In a cell, vectors come list by list, as they are streamed in; queries (`_QUERIES` at most in a task) skip lists that
  cannot reach their k-th score so far. In the others, the product with a vector's decoded code and |query| * (length of
  what the code leaves out), which is kept beside the code, bound the true product; vectors whose bound reaches the k-th
  score are scored exactly and may raise it.

So the result is that of brute force for any vectors, whatever the sample has seen of them.

Vectors that are null, zero, of another length than most, or hold null or non-finite components take no part, neither
as query nor as candidate. Ties go to the smaller id. Repeated ids are searched as rows of their own; an empty table
gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import map_arrow, staged, table

_QUERIES = 50_000


def _kmeans(x: np.ndarray, k: int, rounds: int, rng: np.random.Generator) -> np.ndarray:
    c = x[rng.choice(len(x), k, replace=len(x) < k)].copy()
    for _ in range(rounds):
        near = (x @ c.T - 0.5 * (c * c).sum(1)).argmax(1)
        n = np.bincount(near, minlength=k)
        sums = np.zeros_like(c)
        np.add.at(sums, near, x)
        c = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], x[rng.choice(len(x), k)])
    return c


def _unit(x: np.ndarray) -> np.ndarray:
    """Directions; by the largest part first, since squares of tiny or huge parts leave the range of doubles."""
    x = x / np.maximum(np.abs(x).max(axis=1, keepdims=True), np.finfo(float).tiny)
    return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), np.finfo(float).tiny)


@dataclass
class Model:
    centroids: np.ndarray  # lists x dim
    books: np.ndarray  # subspaces x codes x width

    @property
    def width(self) -> int:
        return self.books.shape[2]

    def assign(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(list, codes) of each vector."""
        at = (x @ self.centroids.T).argmax(1)
        rest = x - self.centroids[at]
        codes = np.empty((len(x), len(self.books)), np.uint8)
        for m, book in enumerate(self.books):
            r = rest[:, m * self.width : (m + 1) * self.width]
            codes[:, m] = (r @ book.T - 0.5 * (book * book).sum(1)).argmax(1)
        return at, codes

    def decoded(self, at: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """The vectors that lists and codes stand for."""
        return self.centroids[at] + self.books[np.arange(len(self.books)), codes].reshape(len(at), -1)

    def left_out(self, x: np.ndarray, at: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """Length of what list and codes leave out of each vector, and a margin for the rounding of sums."""
        near = self.decoded(at, codes)
        return np.linalg.norm(x - near, axis=1) * (1 + 1e-9) + 1e-9 * (np.linalg.norm(x, axis=1) + np.linalg.norm(near, axis=1))

    def parts(self, x: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Each vector's part along the centroid of its list, and the length of the rest."""
        c = _unit(self.centroids)[at]
        along = np.einsum("nd,nd->n", x, c)
        return along, np.linalg.norm(x - along[:, None] * c, axis=1)

    def reach(self, q: np.ndarray, low: np.ndarray, high: np.ndarray, wide: np.ndarray) -> np.ndarray:
        """The largest inner product that a member of each list may have with each query."""
        c = _unit(self.centroids)
        along = q @ c.T
        size = np.linalg.norm(q, axis=1)[:, None]
        across = np.sqrt(np.maximum(size * size - along * along, 0)) + 1e-7 * size  # the root of a difference of squares
        best = np.maximum(along * low, along * high) + across * wide
        return best + 1e-9 * size * (np.maximum(np.abs(low), np.abs(high)) + wide)


def fit(sample: np.ndarray, lists: int, codes: int = 256, seed: int = 3) -> Model:
    rng = np.random.default_rng(seed)
    dim = sample.shape[1]
    c = _kmeans(_unit(sample), lists, 12, rng)
    rest = sample - c[(sample @ c.T).argmax(1)]
    width = next(w for w in (2, 1) if dim % w == 0)
    books = np.stack([_kmeans(rest[:, m : m + width], codes, 8, rng) for m in range(0, dim, width)])
    return Model(c, books)


def _shelves(centroids: np.ndarray, sizes: np.ndarray, chunk: int) -> list[list[int]]:
    """Lists in a chain of near centroids, cut so that those together hold at most about `chunk` vectors."""
    c, free = _unit(centroids), np.ones(len(centroids), bool)
    at, out, held = 0, [], 0
    for _ in range(len(c)):
        free[at] = False
        if not out or held + sizes[at] > chunk:
            out.append([])
            held = 0
        out[-1].append(at)
        held += sizes[at]
        at = int(np.where(free, c @ c[at], -np.inf).argmax())
    return out


def usable(vectors: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    """(vec_id, v) of vectors that take part: v is an array of doubles."""
    v = F.col(vec_col).cast("array<double>")
    sound = v.isNotNull() & (F.size(v) > 0) & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & F.exists(v, lambda x: x != 0)
    df = vectors.filter(F.col(id_col).isNotNull() & F.coalesce(sound, F.lit(False))).select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v"))
    usual = df.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").first()
    return df.filter(F.size("v") == (usual["d"] if usual else 0))


def _matrix(column: pa.Array) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1)


class _Best:
    """The k best (score, id) so far of each query of a block; equal scores go to the smaller id."""

    def __init__(self, q: np.ndarray, own: np.ndarray, least: np.ndarray, k: int):
        self.q, self.own, self.k, self.size = q, own, k, np.linalg.norm(q, axis=1)
        self.least = least - 1e-12 * np.abs(least)
        self.kept = [np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)]
        self.more: list[list[np.ndarray]] = []

    def add(self, who: np.ndarray, near: np.ndarray, spare: np.ndarray, full: np.ndarray, its: np.ndarray, ids: np.ndarray) -> None:
        """Vectors `full`, of decoded codes `near`, for the queries `who`."""
        bound = self.q[who] @ near.T + self.size[who][:, None] * spare[None, :]
        a, c = np.nonzero(~(bound < self.least[who][:, None]))
        a = who[a]
        other = self.own[a] != its[c]
        a, c = a[other], c[other]
        score = np.concatenate([np.einsum("pd,pd->p", self.q[a[i : i + 100_000]], full[c[i : i + 100_000]]) for i in range(0, max(len(a), 1), 100_000)])
        reach = ~(score < self.least[a])
        if reach.any():
            self.more.append([a[reach], ids[c[reach]], score[reach]])
            if sum(len(x[0]) for x in self.more) > 4 * self.k * len(self.q):
                self.merge()

    def merge(self) -> list[np.ndarray]:
        """(place of the query, id, score) of the best, which raise what later ones must reach."""
        a, ids, score = (np.concatenate(x) for x in zip(self.kept, *self.more, strict=True))
        order = np.lexsort((ids, -score, a))
        a, ids, score = a[order], ids[order], score[order]
        place = np.arange(len(a)) - np.searchsorted(a, a)
        last = place == self.k - 1
        self.least[a[last]] = np.fmax(self.least[a[last]], score[last] - 1e-12 * np.abs(score[last]))
        self.kept, self.more = [x[place < self.k] for x in (a, ids, score)], []
        return self.kept


def search(vectors: DataFrame, queries: str, k: int = 20, id_col: str = "vec_id", vec_col: str = "embedding", sample: int = 8_000, least_seen: int = 500, cells: int = 16, chunk: int = 250, block: int = 512) -> DataFrame:
    """(query_id, rank, vec_id, score): the k nearest for every row that meets the SQL condition `queries` on vec_id."""
    spark = vectors.sparkSession
    schema = "query_id long, rank int, vec_id long, score double"
    base = usable(vectors, id_col, vec_col)
    head = base.orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample).toArrow()
    if not head.num_rows:
        return spark.createDataFrame([], schema)
    x = _matrix(head.column("v").combine_chunks())
    x = x[np.sort(np.unique(x, axis=0, return_index=True)[1])]  # copies of one vector would weigh the fit
    lists = int(min(1024, max(1, len(x) // 64)))
    model = fit(x, lists)

    def coded(b: pa.RecordBatch) -> dict:
        v = _matrix(b.column(2))
        at, codes = model.assign(v)
        along, across = model.parts(v, at)
        return {"row": b.column(0), "vec_id": b.column(1), "v": b.column(2), "list": at.astype(np.int32), "codes": [c.tobytes() for c in codes], "left_out": model.left_out(v, at, codes), "along": along, "across": across}

    numbered = base.select(F.monotonically_increasing_id().alias("row"), "vec_id", "v")
    rows = staged(map_arrow(numbered, coded, "row long, vec_id long, v array<double>, list int, codes binary, left_out double, along double, across double"))
    counts = {r["list"]: r for r in rows.groupBy("list").agg(F.count(F.lit(1)).alias("n"), F.min("along").alias("low"), F.max("along").alias("high"), F.max("across").alias("wide")).collect()}
    sizes, low, high, wide = (np.array([counts[i][name] if i in counts else 0 for i in range(lists)], kind) for name, kind in (("n", int), ("low", float), ("high", float), ("wide", float)))
    chunk = max(chunk, -(-int(sizes.sum()) // cells))
    shelves = _shelves(model.centroids, sizes, chunk)
    pieces = np.array([max(1, -(-int(sizes[on].sum()) // chunk)) if len(on) == 1 else 1 for on in shelves])
    first, total = np.cumsum(pieces) - pieces, int(pieces.sum())
    shelf_of, shelf_at = np.empty(lists, int), np.repeat(np.arange(len(shelves)), pieces)  # of lists, of cells
    for i, on in enumerate(shelves):
        shelf_of[on] = i
    held = np.array([sizes[on].sum() for on in shelves])[shelf_at] / pieces[shelf_at]

    def dealt(asks: np.ndarray, b: pa.RecordBatch, least: np.ndarray) -> dict:
        """One row for each cell that the query asks."""
        q, cell = np.nonzero(asks)
        at = pa.array(q)
        return {"row": b.column(0).take(at), "id": b.column(1).take(at), "v": b.column(2).take(at), "least": least[q], "cell": cell.astype(np.int32)}

    def nearest_cells(b: pa.RecordBatch) -> np.ndarray:
        """Cells of the best lists of each query, as many as hold `least_seen`; of a long list, first the cell that the row's number chooses."""
        best = np.full((b.num_rows, len(shelves)), -np.inf)
        product = np.where(sizes > 0, _matrix(b.column(2)) @ model.centroids.T, -np.inf)
        for i, on in enumerate(shelves):
            best[:, i] = product[:, on].max(axis=1)
        turn = (np.arange(total) - first[shelf_at] - b.column(0).to_numpy()[:, None]) % pieces[shelf_at]
        order = np.lexsort((turn, -best[:, shelf_at]), axis=1)
        seen = np.cumsum(held[order], axis=1) - held[order]
        mask = np.zeros(order.shape, bool)
        np.put_along_axis(mask, order, seen < least_seen, 1)
        return mask

    def near(b: pa.RecordBatch) -> dict:
        return dealt(nearest_cells(b) & (held > 0), b, np.full(b.num_rows, -np.inf))

    def others(b: pa.RecordBatch) -> dict:
        least = b.column(3).to_numpy(zero_copy_only=False).astype(float)
        may = ~(model.reach(_matrix(b.column(2)), low, high, wide) < least[:, None]) & (sizes > 0)
        return dealt(np.stack([may[:, on].any(axis=1) for on in shelves], axis=1)[:, shelf_at] & ~nearest_cells(b), b, least)

    asked = "row long, id long, v array<double>, least double, cell int"
    searching = rows.filter(queries).select("row", F.col("vec_id").alias("query_id"), "v")
    parts = max(1, -(-searching.count() // _QUERIES))
    shelf = F.element_at(F.array(*(F.lit(int(i)) for i in shelf_of)), F.col("list") + 1)
    of_shelf = lambda values: F.element_at(F.array(*(F.lit(int(i)) for i in values)), shelf + 1)
    cell = of_shelf(first) + F.pmod(F.xxhash64("row"), of_shelf(pieces).cast("long")).cast("int")
    members = rows.select(cell.alias("cell"), F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"), "list", "row", F.col("vec_id").alias("id"), "v", F.col("left_out").alias("least"), "codes")

    def scored(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        asking: list[list[np.ndarray]] = []
        ready: list[tuple[_Best, np.ndarray, np.ndarray]] | None = None
        so_far = -1
        for b in batches:
            at, row, ids, spare = (b.column(i).to_numpy(zero_copy_only=False) for i in (2, 3, 4, 6))
            if not len(at):
                continue
            if at[0] < so_far or (at[1:] < at[:-1]).any():
                raise ValueError("rows of a cell must come sorted by list")
            so_far = at[-1]
            start = int(np.searchsorted(at, 0))  # queries have list -1 and come first
            if start:
                asking.append([row[:start], ids[:start], _matrix(b.column(5).slice(0, start)), spare[:start].astype(float)])
            if start == b.num_rows:
                continue
            if not asking:
                return
            if ready is None:
                row_q, id_q, q, least = (np.concatenate(c) for c in zip(*asking, strict=True))
                ready = [(_Best(q[i : i + block], row_q[i : i + block], least[i : i + block], k), id_q[i : i + block], model.reach(q[i : i + block], low, high, wide)) for i in range(0, len(q), block)]
            full = _matrix(b.column(5).slice(start))
            at, row, ids, spare = at[start:], row[start:], ids[start:], spare[start:]
            codes = np.frombuffer(b"".join(b.column(7).slice(start).to_pylist()), np.uint8).reshape(len(at), -1)
            whole = model.decoded(at, codes)
            for i in np.unique(at):
                lo, hi = np.searchsorted(at, [i, i + 1])
                for f in range(lo, hi, 2_048):
                    s = slice(f, min(hi, f + 2_048))
                    for best, _, may in ready:
                        who = np.flatnonzero(~(may[:, i] < best.least))
                        if len(who):
                            best.add(who, whole[s], spare[s], full[s], row[s], ids[s])
        for best, id_q, _ in ready or []:
            a, ids, score = best.merge()
            yield pa.RecordBatch.from_arrays([pa.array(best.own[a]), pa.array(id_q[a]), pa.array(ids), pa.array(score)], names=["row", "query_id", "vec_id", "score"])

    def best_of(asking: DataFrame) -> DataFrame:
        asks = asking.select("cell", F.pmod(F.xxhash64("row"), F.lit(parts)).cast("int").alias("part"), F.lit(-1).alias("list"), "row", "id", "v", "least", F.lit(None).cast("binary").alias("codes"))
        together = asks.unionByName(members).repartition("cell", "part").sortWithinPartitions("cell", "part", "list")
        return together.groupBy("cell", "part").applyInArrow(scored, "row long, query_id long, vec_id long, score double")

    def ranked(found: DataFrame) -> DataFrame:
        rank = F.row_number().over(Window.partitionBy("row").orderBy(F.desc("score"), "vec_id"))
        return found.withColumn("rank", rank).filter(F.col("rank") <= k)

    nearest = staged(ranked(best_of(map_arrow(searching, near, asked))).drop("rank"))
    kth = nearest.groupBy("row").agg(F.when(F.count(F.lit(1)) == k, F.min("score")).alias("least"))
    known = searching.join(kth, "row", "left").select("row", "query_id", "v", F.coalesce("least", F.lit(float("-inf"))).alias("least"))
    return ranked(nearest.unionByName(best_of(map_arrow(known, others, asked)))).select("query_id", "rank", "vec_id", "score")


def op3_ivf_pq_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract query: the 20 nearest of every vector whose id is divisible by 20."""
    return search(table(spark, sf_dir, "embeddings"), "vec_id % 20 = 0")

"""Benchmark decontamination by CGK embedding, bit-sampling LSH and exact edit verification.

Symbols are words (runs of letters and digits, A-Z lower-cased; see `alnum_words`). An item of L words matches a
document where some stretch of it lies within `floor((1 - similarity) * L)` word edits of the item.

* A CGK walk of 3L steps turns a window into a string whose Hamming distance to the item's string follows their edit
  distance: at step j the symbol under the pointer is written and the pointer moves on by a random bit of (j, symbol).
* Each of `tables` LSH tables samples `sampled` of the 3L positions; a window and an item of the window's size that
  agree on all of them in any table are candidates. `tables` follows from the target recall.
* Windows have the item's size and start where the item could lie: by the pigeonhole principle an item cut into
  edits + 1 segments has one segment intact in any match, so only windows around an intact segment are embedded
  (nothing that could match is lost by this), each in all shifts up to the edits allowed.
* Every candidate is verified exactly by the edit distance of the item to the best stretch around the window.

Items come to the executors in blocks of at most `block_words` words, one pass over the documents a block, so the
broadcast is bounded whatever the benchmark's size. Items with fewer than `least_words` words are too common to tell
anything and are skipped (listed by `skipped_items`). Null or empty texts match nothing; repeated rows are each
reported; an empty table of either kind gives an empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import alnum_words, keep_where, map_arrow, mixed, table, text_bytes

_HITS = "doc_id long, item_id long, start_word long, n_words int, edits int, similarity double"


def edits_allowed(n_words: int, similarity: float) -> int:
    return int(math.floor((1 - similarity) * n_words + 1e-9))


def tables_for(recall: float, sampled: int, agree: float = 0.5) -> int:
    """Tables so that strings that agree on a share `agree` of their positions meet with probability `recall`."""
    return max(1, math.ceil(math.log(1 - recall) / math.log(1 - agree**sampled)))


def cgk(windows: np.ndarray, seed: int) -> np.ndarray:
    """CGK embeddings (rows of 3L symbols) of windows (rows of L symbols); past the end the symbol is -1."""
    n, size = windows.shape
    padded = np.concatenate([windows, np.full((n, 1), -1, np.int64)], axis=1)
    at, out, rows = np.zeros(n, np.int64), np.empty((n, 3 * size), np.int64), np.arange(n)
    with np.errstate(over="ignore"):
        for j in range(3 * size):
            s = padded[rows, at]
            out[:, j] = s
            bit = mixed(s.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed * 1_000_003 + j)) >> np.uint64(63)
            at = np.minimum(at + bit.astype(np.int64), size)
    return out


def infix_edits(item: np.ndarray, text: np.ndarray) -> tuple[int, int]:
    """Least word edits from the item to any stretch of the text, and that stretch's end; ties to the earliest end."""
    col = np.arange(len(item) + 1)
    best, end = int(col[-1]), 0
    steps = np.arange(len(item) + 1)
    for k, s in enumerate(text):
        new = np.minimum(np.concatenate([[0], col[:-1] + (item != s)]), np.concatenate([[0], col[1:] + 1]))
        col = np.minimum.accumulate(new - steps) + steps
        if col[-1] < best:
            best, end = int(col[-1]), k + 1
    return best, end


class ItemIndex:
    """Items of one block: vocabulary, segments, and LSH tables over their CGK strings."""

    at_once = 2_048  # windows embedded together

    def __init__(self, items: list[tuple[int, list[bytes]]], similarity: float, sampled: int, tables: int, seed: int = 7) -> None:
        self.sampled, self.tables, self.seed, self.similarity = sampled, tables, seed, similarity
        self.vocabulary: dict[bytes, int] = {}
        self.items = [(i, np.array([self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words], np.int64)) for i, words in items]
        self.edits = [edits_allowed(len(w), similarity) for _, w in self.items]
        self.segments: dict[int, dict[int, list[tuple[int, int]]]] = {}
        self.buckets: dict[tuple[int, int, bytes], list[int]] = {}
        for k, (_, w) in enumerate(self.items):
            parts = self.edits[k] + 1
            cuts = [len(w) * p // parts for p in range(parts + 1)]
            for a, b in zip(cuts, cuts[1:], strict=False):
                self.segments.setdefault(b - a, {}).setdefault(int(self.rolled(w[a:b], b - a)[0]), []).append((k, a))
            for t, key in enumerate(self.keys(w[None, :])):
                self.buckets.setdefault((len(w), t, key[0]), []).append(k)
        self.hashes = {n: np.array(sorted(x), np.uint64) for n, x in self.segments.items()}

    @staticmethod
    def rolled(symbols: np.ndarray, n: int) -> np.ndarray:
        out = np.full(max(0, len(symbols) - n + 1), np.uint64(n))
        with np.errstate(over="ignore"):
            for k in range(n):
                out = (out ^ symbols[k : k + len(out)].astype(np.uint64)) * np.uint64(0xD6E8FEB86659FD93)
                out ^= out >> np.uint64(29)
        return out

    def keys(self, windows: np.ndarray) -> list[list[bytes]]:
        """For each table the sampled symbols of each window; a few walks serve all tables."""
        size, out = windows.shape[1], []
        rng = np.random.default_rng(self.seed * 7919 + size)
        walks = [cgk(windows, self.seed + v) for v in range(4)]
        for t in range(self.tables):
            cols = rng.choice(3 * size, min(self.sampled, 3 * size), replace=False)
            out.append([r.tobytes() for r in np.ascontiguousarray(walks[t % 4][:, cols])])
        return out

    def matches(self, words: list[bytes]) -> Iterator[tuple[int, int, int, int]]:
        """(item, start, words, edits): the best place of each item that the text holds."""
        get = self.vocabulary.get
        symbols = np.fromiter((get(w, 0) for w in words), np.int64, len(words))
        spots: dict[int, set[int]] = {}  # item -> window starts
        for n, sorted_hashes in self.hashes.items():
            if len(symbols) < n:
                continue
            h = self.rolled(symbols, n)
            at = np.minimum(np.searchsorted(sorted_hashes, h), len(sorted_hashes) - 1)
            for p in np.flatnonzero(sorted_hashes[at] == h):
                for k, off in self.segments[n][int(h[p])]:
                    e = self.edits[k]
                    spots.setdefault(k, set()).update(range(int(p) - off - e, int(p) - off + e + 1))
        for k, starts in spots.items():
            item_id, w = self.items[k]
            size, e = len(w), self.edits[k]
            every = np.fromiter(starts, np.int64, len(starts))
            every.sort()
            padded = np.concatenate([np.full(size + e, -2), symbols, np.full(size + e, -2)])
            best: tuple[int, int, int] | None = None
            for part in range(0, len(every), self.at_once):  # so that a long text around many segments stays small
                begin = every[part : part + self.at_once]
                windows = padded[(begin + size + e)[:, None] + np.arange(size)[None, :]]
                hit = np.zeros(len(begin), bool)
                for t, keys in enumerate(self.keys(windows)):
                    hit |= [k in self.buckets.get((size, t, key), ()) for key in keys]
                for b in begin[hit]:
                    lo, hi = max(0, int(b) - e), min(len(symbols), int(b) + size + e)
                    got, end = infix_edits(w, symbols[lo:hi])
                    if got <= e and (best is None or got < best[0]):
                        back, length = infix_edits(w[::-1], symbols[lo : lo + end][::-1])
                        best = (got, lo + end - length, length)
                        if got == 0:
                            break
                if best and best[0] == 0:
                    break
            if best:
                yield item_id, best[1], best[2], best[0]


def item_blocks(benchmark: DataFrame, id_col: str, text_col: str, least_words: int, block_words: int) -> Iterator[list[tuple[int, list[bytes]]]]:
    """Items in blocks of a bounded number of words, in id order, read one after another."""
    block, n = [], 0
    for r in benchmark.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).cast("string").alias("t")).filter("i is not null and t is not null").orderBy("i", "t").toLocalIterator():
        words = alnum_words(r["t"].encode())
        if len(words) < least_words:
            continue
        if block and n + len(words) > block_words:
            yield block
            block, n = [], 0
        block.append((r["i"], words))
        n += len(words)
    if block:
        yield block


def skipped_items(benchmark: DataFrame, least_words: int = 5) -> DataFrame:
    """Items that are too short to be looked for."""
    return benchmark.filter(F.coalesce(F.regexp_count(F.lower("text"), F.lit(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")), F.lit(0)) < least_words)


def contaminated(docs: DataFrame, benchmark: DataFrame, similarity: float = 0.8, recall: float = 0.99, sampled: int = 4, least_words: int = 5, block_words: int = 400_000) -> DataFrame:
    """(doc_id, item_id, start_word, n_words, edits, similarity): each item that a document holds, at its best place."""
    texts = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    out = None
    for items in item_blocks(benchmark, "item_id", "text", least_words, block_words):
        index = ItemIndex(items, similarity, sampled, tables_for(recall, sampled))
        sizes = {i: len(w) for i, w in items}

        def batch(b: pa.RecordBatch, index: ItemIndex = index, sizes: dict[int, int] = sizes) -> dict:
            out = {k: [] for k in ("doc_id", "item_id", "start_word", "n_words", "edits", "similarity")}
            for doc_id, raw in zip(b.column(0).to_pylist(), text_bytes(b.column(1)), strict=True):
                for item, start, n, e in index.matches(alnum_words(raw)):
                    for k, v in zip(out, (doc_id, item, start, n, e, 1 - e / sizes[item]), strict=True):
                        out[k].append(v)
            return out

        found = map_arrow(texts, batch, _HITS)
        out = found if out is None else out.unionByName(found)
    return out if out is not None else docs.sparkSession.createDataFrame([], _HITS)


def without_contaminated(docs: DataFrame, benchmark: DataFrame, similarity: float = 0.8, recall: float = 0.99, sampled: int = 4, least_words: int = 5, block_words: int = 400_000) -> DataFrame:
    """Rows of `docs`, all columns, that hold no benchmark item."""
    for items in item_blocks(benchmark, "item_id", "text", least_words, block_words):
        index = ItemIndex(items, similarity, sampled, tables_for(recall, sampled))

        def clean(texts, index: ItemIndex = index) -> list[bool]:
            return [next(index.matches(alnum_words(raw)), None) is None for raw in texts]

        docs = keep_where(docs, "text", clean)
    return docs


def op1_cgk_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every (document, benchmark item) where the document holds the item within a fifth of its words in edits."""
    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))

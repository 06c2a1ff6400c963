"""Toxicity by cumulative-link ordinal regression over sparse word features.

Grades: 0 clean; 1 toxic in text of good quality; 2 toxic in text of poor quality. One weight vector is shared by all
thresholds: P(grade <= k) = sigmoid(cut_k - w.x); the output has the expected severity (sum over k of P(grade >= k)).
x marks which words and word stems (leading 4 to 8 bytes) the whole text holds, and stems that several distinct words
of it share, hashed to 2**22 places. The fit takes at most `max_rows` labelled rows, the
first in the order of a hash of the id (a documented bound); scoring covers every row.

A null or empty text has no features and gets the base severity of a text without signs; labels that are null are not
used; a document with labels of several grades counts with the highest, an id with several texts with one of them, the
one whose hash is smallest; without labels of both kinds nothing is called toxic; repeated rows are scored alike; an
empty table gives an empty result.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import alnum_words, keep_where, map_arrow, table, text_bytes

PLACES = 1 << 22


_MARKS = (2, 4)


def _marked(place: int, least: int) -> int:
    """Place of the feature that `least` words or more of a text share the stem at `place`."""
    return (place * 2_654_435_761 + least * 40_503) % PLACES


class Places(dict):
    """Hashed places of a word: the word itself and its leading 4 to 8 bytes (stems), all or only those that some feature
    in `wanted` needs."""

    bound = 300_000

    def __init__(self, wanted: np.ndarray | None = None) -> None:
        super().__init__()
        self.wanted = None if wanted is None else frozenset(wanted.tolist())

    def needed(self, place: int) -> bool:
        return place in self.wanted or any(_marked(place, k) in self.wanted for k in _MARKS)

    def __missing__(self, word: bytes) -> tuple[int, ...]:
        if len(self) >= self.bound:
            self.clear()
        got = [xxhash.xxh3_64_intdigest(word) >> 42]
        got += [xxhash.xxh3_64_intdigest(word[:k], k) >> 42 for k in range(4, min(9, len(word)))]
        out = self[word] = tuple(got) if self.wanted is None else tuple(g for g in got if self.needed(g))
        return out

    def of(self, raw: bytes) -> np.ndarray:
        """Distinct places of the whole text, sorted: each word and stem, and stems that 2 or 4 distinct words share."""
        found: Counter[int] = Counter()
        for places in map(self.__getitem__, set(alnum_words(raw))):
            if places:
                found.update(places)
        every = set(found)
        for place, n in found.items():
            if n > 1:
                every.update(_marked(place, k) for k in _MARKS if n >= k)
        return np.array(sorted(every), np.int32)


@dataclass
class OrdinalModel:
    places: np.ndarray  # sorted
    weights: np.ndarray
    cuts: np.ndarray  # ascending thresholds between grades

    def score(self, found: np.ndarray) -> float:
        at = np.searchsorted(self.places, found)
        at[at == len(self.places)] = 0
        return float(self.weights[at[self.places[at] == found]].sum()) if len(self.places) else 0.0

    def at_least(self, eta: np.ndarray) -> np.ndarray:
        """P(grade >= k) for k = 1.. as columns."""
        return 1 / (1 + np.exp(np.clip(self.cuts[None, :] - np.asarray(eta)[:, None], -60, 60)))


def fit_ordinal(rows: np.ndarray, cols: np.ndarray, grades: np.ndarray, n_cols: int, l1: float | None = None, steps: int = 3_000, slack: float = 0.02) -> tuple[np.ndarray, np.ndarray]:
    """(weights, cuts) by accelerated proximal gradient on the cumulative-link likelihood with an L1 penalty.

    The step is found by backtracking, the momentum starts anew where it points uphill, and the fit ends where no
    coordinate's step is above `slack` of the penalty (or 1e-5, if there is none)."""
    n, top = len(grades), int(grades.max())
    l1 = 0.3 / n if l1 is None else l1
    rate = np.array([(grades >= k).mean() for k in range(1, top + 1)])
    sig = lambda z: 1 / (1 + np.exp(-np.clip(z, -60, 60)))

    def sides(w: np.ndarray, cuts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of each row: P(grade or below), P(below the grade), and their difference."""
        eta, edge = np.bincount(rows, w[cols], minlength=n), np.concatenate([[-60.0], cuts, [60.0]])
        hi, lo = sig(edge[grades + 1] - eta), sig(edge[grades] - eta)
        return hi, lo, np.maximum(hi - lo, 1e-12)

    w, cuts = np.zeros(n_cols), np.log((1 - rate) / rate)
    v, at, t, step = w, cuts, 1.0, 1.0
    for _ in range(steps):
        hi, lo, p = sides(v, at)
        loss, dhi, dlo = -np.log(p).mean(), hi * (1 - hi) / p / n, lo * (1 - lo) / p / n
        d_w = np.bincount(cols, (dhi - dlo)[rows], minlength=n_cols)
        d_cut = np.bincount(grades, dlo, minlength=top + 1)[1:] - np.bincount(grades, dhi, minlength=top + 1)[:top]
        while True:
            new = v - step * d_w
            new = np.sign(new) * np.maximum(np.abs(new) - step * l1, 0)
            edges = np.maximum.accumulate(at - step * d_cut + np.arange(top) * 1e-9)
            moved, shifted = new - v, edges - at
            bound = loss + d_w @ moved + d_cut @ shifted + (moved @ moved + shifted @ shifted) / (2 * step)
            if -np.log(sides(new, edges)[2]).mean() <= bound + 1e-12 or step < 1e-8:
                break
            step /= 2
        if max(np.abs(moved).max(initial=0), np.abs(shifted).max()) <= step * (slack * l1 or 1e-5):
            return new, edges
        if moved @ (new - w) + shifted @ (edges - cuts) < 0:
            t = 1.0
        t2 = (1 + (1 + 4 * t * t) ** 0.5) / 2
        v, at = new + (t - 1) / t2 * (new - w), edges + (t - 1) / t2 * (edges - cuts)
        w, cuts, t, step = new, edges, t2, step * 1.05
    return w, cuts


def fit(docs: DataFrame, labels: DataFrame, max_rows: int = 8_000, least_texts: int = 5, most_places: int = 20_000) -> OrdinalModel:
    """Fit on at most `max_rows` labelled documents; a place needs `least_texts` of them, the `most_places` that tell the grades apart best stay."""
    graded = labels.filter("doc_id is not null and toxic is not null").select("doc_id", F.when(F.col("toxic") == 0, 0).when(F.coalesce("quality", F.lit(1)) == 0, 2).otherwise(1).alias("grade"))
    few = graded.groupBy("doc_id").agg(F.max("grade").alias("grade")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows)
    joined = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).join(F.broadcast(few), "doc_id").select("doc_id", "text", "grade", F.xxhash64("text").alias("raw"))

    def batch(b: pa.RecordBatch) -> dict:
        cache = Places()
        return {"doc_id": b.column(0), "grade": b.column(2), "raw": b.column(3), "places": [cache.of(raw) for raw in text_bytes(b.column(1))]}

    each = map_arrow(joined, batch, "doc_id long, grade int, raw long, places array<int>")
    got = each.groupBy("doc_id").agg(F.max("grade").alias("grade"), F.min_by("places", "raw").alias("places")).toArrow()
    order = np.argsort(got.column("doc_id").to_numpy(), kind="stable")
    grades = got.column("grade").to_numpy().astype(np.int64)[order]
    if len(grades) == 0 or grades.max() == 0 or grades.min() > 0:
        return OrdinalModel(np.empty(0, np.int32), np.empty(0), np.array([60.0]))
    lists = got.column("places").combine_chunks()
    del got
    cols, sizes = lists.flatten().to_numpy(), np.diff(lists.offsets.to_numpy())
    rows = np.empty(len(order), np.int32)
    rows[order] = np.arange(len(order), dtype=np.int32)  # texts in the order of their ids, whatever order they came in
    rows, base = np.repeat(rows, sizes), (grades > 0).mean()
    df = np.bincount(cols, minlength=PLACES)
    hits = np.bincount(cols[(grades > 0)[rows]], minlength=PLACES)
    z = np.where(df >= least_texts, np.abs(hits - df * base) / np.sqrt(np.maximum(df, 1) * base * (1 - base)), 0)
    stay = np.argsort(-z, kind="stable")[: min(most_places, int((z > 3.5).sum()))]
    stay.sort()
    new = np.full(PLACES, -1, np.int32)
    new[stay] = np.arange(len(stay))
    keep = np.flatnonzero(new[cols] >= 0)
    rows, cols = rows[keep], new[cols[keep]]
    missing = np.setdiff1d(np.arange(1, grades.max() + 1), grades)
    if len(missing):  # a grade without rows has no threshold of its own
        grades = np.minimum(grades, 1)
    weights, cuts = fit_ordinal(rows, cols, grades, len(stay))
    return OrdinalModel(stay.astype(np.int32), weights, cuts)


def severity(docs: DataFrame, model: OrdinalModel, cut: float = 0.5) -> DataFrame:
    """doc_id, expected_severity, p_toxic, grade (likeliest), toxic (p_toxic >= cut) for every row."""

    def batch(b: pa.RecordBatch) -> dict:
        cache = Places(model.places)
        eta = np.array([model.score(cache.of(raw)) for raw in text_bytes(b.column(1))])
        up = model.at_least(eta)
        each = np.hstack([np.ones((len(up), 1)), up]) - np.hstack([up, np.zeros((len(up), 1))])
        return {"doc_id": b.column(0), "expected_severity": up.sum(axis=1), "p_toxic": up[:, 0], "grade": each.argmax(axis=1).astype(np.int32), "toxic": up[:, 0] >= cut}

    return map_arrow(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), batch, "doc_id long, expected_severity double, p_toxic double, grade int, toxic boolean")


def without_toxic(docs: DataFrame, model: OrdinalModel, cut: float = 0.5) -> DataFrame:
    """Rows of `docs`, all columns, that the model does not call toxic."""

    def clean(texts) -> list[bool]:
        cache = Places(model.places)
        eta = np.array([model.score(cache.of(raw)) for raw in texts])
        return (model.at_least(eta)[:, 0] < cut).tolist()

    return keep_where(docs, "text", clean)


def op4_ordinal_toxicity(spark, sf_dir: str) -> DataFrame:
    """Every document with its expected severity and whether it is rejected."""
    docs = table(spark, sf_dir, "documents")
    return severity(docs, fit(docs, table(spark, sf_dir, "labels")))

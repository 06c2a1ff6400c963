"""Language-model scoring by online logistic context mixing over bits.

A text is a sequence of words (between ASCII white space, A-Z lower-cased) and one end. A word is coded as its UTF-8
bytes and a blank, the end as a newline, each byte as eight bits from the top; no code is the beginning of another, so
the model's probabilities of all token sequences sum to one. Each bit is predicted from five hashed contexts: the
last one to four bytes within the word, and the whole word so far. A prediction is a count pair at the hashed slot,
read in the logistic domain; a weight vector chosen by a gate (bit number, how often the whole-word context was seen)
mixes the five, and an adaptive map indexed by the byte's bits so far refines the mix.

Above the words stands one more hashed context, the whole line (`LINE` words or more): a bit with the chance `known`
says whether the line is one of the training lines, which then costs its share of them; else it is coded word by word.
`known` is the share of training lines that another training line repeats; a training document's own occurrence is
taken off, as often as it has the line, before its lines are looked up, so that it is not predicted from itself.

How the parts are learnt: counts of tokens over all training documents in Spark (partial sums before the shuffle),
then the slots' counts of all five contexts from all distinct tokens, in tables of fixed size summed in Spark. The
mixing weights and the map are learnt from all distinct training tokens by their counts, in passes over them in Spark:
Newton steps on the coding cost of every gate (with a penalty of half a squared weight) until the next would save less
than 1e-8 of a nat a bit; a gate that is done is left out of later passes, and its part of the map is from the pass at
its final weights. In these passes an occurrence sees whole-word counts without itself (counts below 31 are kept for
that), or else the contexts of words seen once would seem to predict well. The same steps on a bounded set of tokens
(`sample`) only give the weights that these start from; the optimum does not depend on it. Tokens that begin alike
share their first bits, so these are worked out once for neighbours in sorted order; the counts are staged by ranges of
tokens, so that neighbours lie in one task. Every distinct token is then scored once and documents get their sums by a
join on the token; the `hot` most frequent tokens, which may make up most occurrences, are looked up in place instead,
so no join key holds more than a small share of rows. Total bits per byte are -score * log2(10) / (bytes of the text,
and one for its end).

A null or empty text is one end token; a null id is learnt from; repeated rows are scored each (and learnt from each);
without any training document all counts are zero and the predictors are even; an empty table gives an empty result.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import map_arrow, mixed, space_words, staged, table, text_bytes

END = b"\n"
MARK = b"\n\n"  # before a line's hash; no word begins so
LINE = 8
ORDERS = 5
BITS = (16, 20, 20, 20, 22)
OFFSETS = np.concatenate([[0], np.cumsum([1 << b for b in BITS])])
LEVELS = 8
_PIECE = 1 << 16
_HALVES = np.arange(1 << 16, dtype=np.uint16).view(np.float16).astype(np.float64)  # each float16, far faster than a cast
_BINS = 33
_EXACT = 31  # counts below it are kept beside the level
_PRIOR = 0.4
_ROWS = np.concatenate([np.repeat(b * LEVELS + np.arange(LEVELS), 1 << b) for b in range(8)])  # the gate of each row of the map's counts


def encoded(tokens: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(codes as a byte matrix, lengths), ordered as given."""
    full = [t if t == END else t + b" " for t in tokens]
    lengths = np.fromiter(map(len, full), np.int64, len(full))
    width = int(lengths.max()) if len(full) else 0
    flat = np.frombuffer(b"".join(full), np.uint8)
    out = np.zeros((len(full), width), np.uint8)
    out[np.arange(width)[None, :] < lengths[:, None]] = flat
    return out, lengths


def contexts(codes: np.ndarray, lengths: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each byte place: (rows that have a byte there, those bytes, hashes of their five contexts)."""
    rows = np.arange(len(codes))
    whole = np.full(len(codes), np.uint64(0x51ED270B))
    for i in range(codes.shape[1]):
        keep = lengths[rows] > i
        rows, whole = rows[keep], whole[keep]
        last, h = np.zeros(len(rows), np.uint64), np.empty((ORDERS, len(rows)), np.uint64)
        for k in range(4):
            last = last << np.uint64(8) | (codes[rows, i - k - 1].astype(np.uint64) + np.uint64(1) if i > k else np.uint64(0))
            h[k] = last if k == 0 else mixed(last * np.uint64(ORDERS) + np.uint64(k))
        h[4] = whole
        now = codes[rows, i]
        yield rows, now, h
        whole = mixed(whole * np.uint64(0x9E3779B97F4A7C15) + now.astype(np.uint64) + np.uint64(1))


def blocks(tokens: list[bytes], most: int = 50_000, cells: int = 8_000_000) -> Iterator[np.ndarray]:
    """Places of tokens in blocks of like length and like beginning, whose byte matrices are of bounded size."""
    kinds = np.ceil(np.log2(np.maximum(np.fromiter(map(len, tokens), np.int64, len(tokens)) + 1, 32))).astype(np.int64)
    for kind in np.unique(kinds):
        ids = np.array(sorted(np.flatnonzero(kinds == kind).tolist(), key=tokens.__getitem__))
        step = max(1, min(most, cells >> int(kind)))
        for at in range(0, len(ids), step):
            yield ids[at : at + step]


def nodes(tokens: list[bytes]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """As `contexts`, but once for neighbours that are alike up to that byte: (rows that have a byte there, the node of
    each, the nodes' bytes, hashes of the nodes' five contexts). Sorted tokens share most."""
    codes, lengths = encoded(tokens)
    differ = codes[1:] != codes[:-1]
    alike = np.concatenate([[-1], np.where(differ.any(axis=1), differ.argmax(axis=1), codes.shape[1])])[: len(codes)]
    rows = np.arange(len(codes))
    whole = np.full(len(codes), np.uint64(0x51ED270B))
    for i in range(codes.shape[1]):
        keep = lengths[rows] > i
        rows, whole = rows[keep], whole[keep]
        new = alike[rows] <= i
        first, node = np.flatnonzero(new), np.cumsum(new) - 1
        one, so_far = rows[first], whole[first]
        last, h = np.zeros(len(one), np.uint64), np.empty((ORDERS, len(one)), np.uint64)
        for k in range(4):
            last = last << np.uint64(8) | (codes[one, i - k - 1].astype(np.uint64) + np.uint64(1) if i > k else np.uint64(0))
            h[k] = last if k == 0 else mixed(last * np.uint64(ORDERS) + np.uint64(k))
        h[4] = so_far
        now = codes[one, i]
        yield rows, node, now, h
        whole = mixed(so_far * np.uint64(0x9E3779B97F4A7C15) + now.astype(np.uint64) + np.uint64(1))[node]


def slots(h: np.ndarray, partial: np.ndarray) -> np.ndarray:
    """Slot of each context for the bits of the byte so far (`partial` from 1 to 255)."""
    out = np.empty(h.shape, np.int64)
    p = partial.astype(np.uint64)
    out[0] = ((h[0] & np.uint64(255)) << np.uint64(8) | p).astype(np.int64)
    spread = p * np.uint64(0x9E3779B97F4A7C15)
    for k in range(1, ORDERS):
        out[k] = _spot(h[k], spread, k) + int(OFFSETS[k])
    return out


def _spot(h: np.ndarray, spread: np.ndarray, k: int) -> np.ndarray:
    return (((h ^ spread) * np.uint64(0xC4CEB9FE1A85EC53)) >> np.uint64(64 - BITS[k])).astype(np.int64)


def bit_steps(now: np.ndarray) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(bit number, bits so far, the bit) of a vector of bytes."""
    partial, x = np.ones(len(now), np.int64), now.astype(np.int64)
    for b in range(8):
        bit = x >> (7 - b) & 1
        yield b, partial, bit
        partial = partial << 1 | bit


def packed(x: np.ndarray) -> bytes:
    """A vector as bytes; its values other than zero and their places only, where that is shorter."""
    at = np.flatnonzero(x).astype(np.uint32)
    return x[at].tobytes() + at.tobytes() if len(at) * (x.itemsize + 4) < x.nbytes else x.tobytes()


def add_packed(total: np.ndarray, raw: bytes, kind: type) -> None:
    """Add to `total` a vector of its length that was packed as `kind`."""
    size = np.dtype(kind).itemsize
    if len(raw) == len(total) * size:
        total += np.frombuffer(raw, kind)
    else:
        n = len(raw) // (size + 4)
        total[np.frombuffer(raw, np.uint32, n, n * size)] += np.frombuffer(raw, kind, n)


def gather_counts(tokens: list[bytes], weights: np.ndarray, n0: np.ndarray, n1: np.ndarray) -> None:
    """Add weighted bits of tokens to the counts of the slots of all their contexts."""
    for rows, node, now, h in nodes(tokens):
        w = np.bincount(node, weights[rows])
        for _, partial, bit in bit_steps(now):
            s = slots(h, partial)
            for n, at in ((n0, bit == 0), (n1, bit == 1)):
                for k in range(ORDERS):
                    np.add.at(n, s[k][at], w[at])


def level_codes(n: np.ndarray) -> np.ndarray:
    """Of counts: the log-scale level, and `LEVELS` times the count, or times `_EXACT` from there on."""
    return np.minimum(LEVELS - 1, np.ceil(np.log2(n + 1) / 3)).astype(np.uint8) + np.minimum(n, _EXACT).astype(np.uint8) * np.uint8(LEVELS)


_CODES = np.arange(256)
_LESS = (np.where(_CODES < _EXACT * LEVELS, level_codes(np.maximum(_CODES // LEVELS - 1, 0)), _CODES) % LEVELS).astype(np.uint8)  # the level when one is taken off


def without_own(x: np.ndarray, code: np.ndarray, bit: np.ndarray) -> np.ndarray:
    """Whole-word predictions of `bit` less one occurrence of it, where the slot's count is below `_EXACT`."""
    n, sign = (code // LEVELS).astype(np.float64), 2.0 * bit - 1
    alike = np.rint((n + 2 * _PRIOR) * squash(sign * x) - _PRIOR)
    return np.where(n < _EXACT, sign * np.log((np.maximum(alike - 1, 0) + _PRIOR) / (n - alike + _PRIOR)), x)


def squash(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


@dataclass
class Mixer:
    domain: np.ndarray  # float16: each slot's prediction in the logistic domain
    level: np.ndarray  # uint8: `level_codes` of each whole-word slot
    weights: np.ndarray  # (8 bits * LEVELS) x (ORDERS + 1)
    refine: np.ndarray  # 256 x 33 refined probabilities
    trust: float = 0.5

    def gate(self, b: int, s: np.ndarray) -> np.ndarray:
        return b * LEVELS + self.level.take(s[4] - int(OFFSETS[4])) % LEVELS

    def codes(self, h: np.ndarray, partial: np.ndarray) -> np.ndarray:
        """`level_codes` of the whole-word slot, which makes the gate, before any other slot is looked up."""
        return self.level.take(_spot(h[4], partial.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15), 4))

    def inputs(self, s: np.ndarray) -> np.ndarray:
        x = np.empty((ORDERS + 1, s.shape[1]))
        x[:ORDERS] = _HALVES.take(self.domain.view(np.uint16).take(s))
        x[ORDERS] = 0.3
        return x

    def predict(self, b: int, partial: np.ndarray, s: np.ndarray) -> np.ndarray:
        gate = self.gate(b, s)
        mix = sum(x * w.take(gate) for x, w in zip(self.inputs(s), self.weights.T.copy(), strict=True))
        place = (np.clip(mix, -8, 8) + 8) * 2
        low = np.minimum(place.astype(np.int64), 31)
        frac = place - low
        refined = self.refine[partial, low] * (1 - frac) + self.refine[partial, low + 1] * frac
        return np.clip((1 - self.trust) * squash(mix) + self.trust * refined, 1e-6, 1 - 1e-6)

    def log10(self, tokens: list[bytes]) -> np.ndarray:
        """log10 probability of each token."""
        out = np.zeros(len(tokens))
        for ids in blocks(tokens):
            part = np.zeros(len(ids))
            for rows, node, now, h in nodes([tokens[i] for i in ids]):
                total = np.zeros(len(now))
                for b, partial, bit in bit_steps(now):
                    p = self.predict(b, partial, slots(h, partial))
                    total += np.log(np.where(bit == 1, p, 1 - p))
                part[rows] += total[node]
            out[ids] = part
        return out / np.log(10)


def mixing_sums(model: Mixer, tokens: list[bytes], weights: np.ndarray, open_gates: np.ndarray | None = None) -> np.ndarray:
    """What tokens add, at the present weights, to each gate's cost, weight of bits, gradient and curvature, and to the
    counts of its part of the map, in one vector; of the `open_gates` only, if given (zeros for the others). The tokens
    are in the tables, so each occurrence sees whole-word counts without itself."""
    gates, width = 8 * LEVELS, ORDERS + 1
    wanted = np.ones((8, LEVELS), bool) if open_gates is None else open_gates.reshape(8, LEVELS)
    cost, grad, curve, seen = np.zeros((2, gates)), np.zeros((gates, width)), np.zeros((gates, width, width)), np.zeros((len(_ROWS), _BINS, 2))
    for ids in blocks(tokens):
        of = weights[ids]
        for rows, node, now, h in nodes([tokens[i] for i in ids]):
            w = np.bincount(node, of[rows])
            for b, partial, bit in bit_steps(now):
                if not wanted[b].any():
                    continue
                code = model.codes(h, partial)
                level = _LESS.take(code)
                order, sizes = np.argsort(level, kind="stable"), np.bincount(level, minlength=LEVELS)
                if not wanted[b].all():
                    order, sizes = order[np.repeat(wanted[b], sizes)], sizes * wanted[b]
                if not len(order):
                    continue
                level, partial, up, wo = level.take(order), partial.take(order), bit.take(order), w.take(order)
                x, sign = model.inputs(slots(h.take(order, axis=1), partial)), 2 * up - 1
                x[4] = without_own(x[4], code.take(order), up)
                mix = np.empty(len(order))
                ends = np.cumsum(sizes)
                spans = [(b * LEVELS + k, lo, hi) for k, (lo, hi) in enumerate(zip([0, *ends[:-1]], ends, strict=True)) if hi > lo]
                for g, lo, hi in spans:
                    mix[lo:hi] = model.weights[g] @ x[:, lo:hi]
                small = np.exp(-np.abs(mix))
                paid = (np.log1p(small) + np.maximum(0, -sign * mix)) * wo
                other = small / (1 + small)  # the chance of the bit that the mix is against
                miss, bend = np.where(sign * mix >= 0, other, 1 - other) * sign * wo, other * (1 - other) * wo
                for g, lo, hi in spans:
                    part = x[:, lo:hi]
                    cost[:, g] += paid[lo:hi].sum(), wo[lo:hi].sum()
                    grad[g] += part @ miss[lo:hi]
                    curve[g] += (part * bend[lo:hi]) @ part.T
                near = (level.astype(np.int64) << b) + partial - (1 << b)
                near = (near * _BINS + np.rint((np.clip(mix, -8, 8) + 8) * 2).astype(np.int64)) * 2 + up
                own = seen[LEVELS * ((1 << b) - 1) : LEVELS * ((2 << b) - 1)]
                own += np.bincount(near, wo, minlength=own.size).reshape(own.shape)
    return np.concatenate([cost.ravel(), grad.ravel(), curve.ravel(), seen.ravel()])


def descend(model: Mixer, sums: Callable[..., np.ndarray], turns: int = 40, ridge: float = 1.0, close: float = 1e-8, far: float = 1.0, apart: bool = False) -> None:
    """Newton steps to the weights of least coding cost, and the map at those weights; `sums` gives `mixing_sums` over
    all tokens at weights, or nothing where there are none. Gates share no bit, so each takes its own step, of at most
    `far` a weight, or a quarter of the last one where its cost rose, and is done as soon as what it and the gates done
    before it would still save is less than `close` a bit in all. `apart`: `sums` is also told which gates are not done."""
    gates, width = 8 * LEVELS, ORDERS + 1
    even = np.tile(squash(np.arange(_BINS) / 2 - 8), (256, 1))
    best, least, step = model.weights, np.full(gates, np.inf), np.zeros(model.weights.shape)
    promise, bits, seen = np.zeros(gates), np.zeros(gates), np.zeros((len(_ROWS), _BINS, 2))
    undone = np.ones(gates, bool)
    for _ in range(turns):
        tried = best + step
        got = sums(tried, undone) if apart else sums(tried)
        if not len(got):
            return
        cost, weight = got[: 2 * gates].reshape(2, gates)
        bits = np.where(undone, weight, bits)
        cost = cost + ridge / 2 * ((tried - 0.3) ** 2).sum(axis=1)
        fell = undone & (cost <= least + close * bits)
        best, least = np.where(fell[:, None], tried, best), np.where(fell, cost, least)
        slope = got[2 * gates :][: gates * width].reshape(gates, width) - ridge * (tried - 0.3)
        curve = got[gates * (2 + width) :][: gates * width * width].reshape(gates, width, width) + ridge * np.eye(width)
        full = np.linalg.solve(curve, slope[:, :, None])[:, :, 0]
        step = np.where(fell[:, None], full / np.maximum(1, np.abs(full).max(axis=1, keepdims=True) / far), step / 4)
        promise = np.where(fell, (slope * full).sum(axis=1), promise)
        seen = np.where(fell[_ROWS][:, None, None], got[gates * (2 + width * (width + 1)) :].reshape(seen.shape), seen)
        least_first = np.flatnonzero(undone)[np.argsort(promise[undone], kind="stable")]
        within = promise[~undone].sum() + np.cumsum(promise[least_first]) <= close * bits.sum()
        undone[least_first[within]] = False
        step[~undone] = 0
        if not undone.any():
            break
    counts = np.zeros((256, _BINS, 2))
    for b in range(8):
        counts[1 << b : 2 << b] = seen[LEVELS * ((1 << b) - 1) : LEVELS * ((2 << b) - 1)].reshape(LEVELS, 1 << b, _BINS, 2).sum(axis=0)
    prior = max(1e-9, float(bits.sum()) * 1e-6)
    model.weights, model.refine = best, (counts[:, :, 1] + prior * even) / (counts.sum(axis=2) + prior)


def learn_from_all(model: Mixer, vocabulary: DataFrame) -> None:
    """Weights at the least coding cost of all tokens of `vocabulary` (token, c), and the map at those weights."""
    gates, width, pieces = 8 * LEVELS, ORDERS + 1, 8
    length = gates * (2 + width * (width + 1)) + 2 * _BINS * len(_ROWS)
    fixed = vocabulary.sparkSession.sparkContext.broadcast((model.domain, model.level))

    def sums(weights: np.ndarray, undone: np.ndarray) -> np.ndarray:
        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            at, total = Mixer(*fixed.value, weights, None), np.zeros(length)
            with np.errstate(over="ignore"):
                tokens, c = [], []
                for b in batches:
                    tokens += b.column(0).to_pylist()
                    c.append(b.column(1).to_numpy().astype(np.float64))
                    if len(tokens) >= 50_000:
                        total += mixing_sums(at, tokens, np.concatenate(c), undone)
                        tokens, c = [], []
                if tokens:
                    total += mixing_sums(at, tokens, np.concatenate(c), undone)
            yield pa.RecordBatch.from_arrays([pa.array(range(pieces), pa.int32()), pa.array([packed(x) for x in np.array_split(total, pieces)], pa.binary())], names=["piece", "sums"])

        def summed(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.array_split(np.zeros(length), pieces)[key[0].as_py()]
            for b in batches:
                for x in b.column(1):
                    add_packed(total, x.as_py(), np.float64)
            yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()], pa.int32()), pa.array([total.tobytes()], pa.binary())], names=["piece", "sums"])

        kind = "piece int, sums binary"
        got = vocabulary.filter("c > 0").select("token", "c").mapInArrow(add, kind).groupBy("piece").applyInArrow(summed, kind).collect()
        return np.concatenate([np.frombuffer(bytes(r["sums"]), np.float64) for r in sorted(got, key=lambda r: r["piece"])] or [np.zeros(0)])

    descend(model, sums, apart=True)
    fixed.destroy()


def lines_of(raw: bytes) -> list[list[bytes]]:
    """Words of each line; all lines together hold the words of the text."""
    return [line.split() for line in raw.lower().split(b"\n")]


def line_key(words: list[bytes]) -> bytes:
    return MARK + xxhash.xxh3_64_digest(b" ".join(words))


def counted(docs: DataFrame, training: Column) -> DataFrame:
    """(token, c): occurrences in training documents of every token of any document, and of every line of `LINE` words."""

    def tokens(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n: Counter[bytes] = Counter()
        only: set[bytes] = set()

        def flush() -> pa.RecordBatch:
            rest = [t for t in only if t not in n]
            out = pa.RecordBatch.from_arrays([pa.array([*n, *rest], pa.binary()), pa.array([*n.values(), *[0] * len(rest)], pa.int64())], names=["token", "c"])
            n.clear()
            only.clear()
            return out

        for b in batches:
            for learn, raw in zip(b.column(0).to_pylist(), text_bytes(b.column(1)), strict=True):
                if learn:
                    for words in lines_of(raw):
                        n.update(words)
                        if len(words) >= LINE:
                            n[line_key(words)] += 1
                    n[END] += 1
                else:
                    only.update(space_words(raw), (END,))
                if len(n) + len(only) > 500_000:
                    yield flush()
        if n or only:
            yield flush()

    return docs.select(training.alias("learn"), F.col("text").cast("string")).mapInArrow(tokens, "token binary, c long").groupBy("token").agg(F.sum("c").alias("c"))


def slot_tables(vocabulary: DataFrame, hot: frozenset[bytes], tasks: int) -> tuple[np.ndarray, np.ndarray]:
    """Each slot's prediction and the `level_codes` of each whole-word slot, from all distinct tokens (`hot` ones count
    like any other): tables of counts of fixed size a task, summed in pieces in Spark; the driver gets the finished
    pieces only (19 MB in all, by row)."""
    size = int(OFFSETS[-1])

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n0, n1 = np.zeros(size), np.zeros(size)
        with np.errstate(over="ignore"):
            for b in batches:
                tokens, c = b.column(0).to_pylist(), b.column(1).to_numpy().astype(np.float64)
                for ids in blocks(tokens):
                    gather_counts([tokens[i] for i in ids], c[ids], n0, n1)
        for k in range(0, size, _PIECE):  # one at a time, so that no second copy of the tables is made
            counts = packed(np.concatenate([n0[k : k + _PIECE], n1[k : k + _PIECE]]).astype(np.float32))
            yield pa.RecordBatch.from_arrays([pa.array([k // _PIECE], pa.int32()), pa.array([counts], pa.binary())], names=["piece", "counts"])

    def finished(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(2 * min(_PIECE, size - key[0].as_py() * _PIECE))
        for b in batches:
            for x in b.column(1):
                add_packed(total, x.as_py(), np.float32)
        n0, n1 = total.astype(np.float32).reshape(2, -1)
        domain = np.clip(np.log((n1 + np.float32(_PRIOR)) / (n0 + np.float32(_PRIOR))), -14, 14).astype(np.float16)
        level = level_codes(n0 + n1)
        yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()], pa.int32()), pa.array([domain.tobytes()], pa.binary()), pa.array([level.tobytes()], pa.binary())], names=["piece", "domain", "level"])

    parts = vocabulary.filter("c > 0").select("token", "c").repartition(tasks, "token").sortWithinPartitions("token").mapInArrow(gather, "piece int, counts binary")
    domain, level = np.zeros(size, np.float16), np.zeros(size - int(OFFSETS[4]), np.uint8)
    for r in parts.groupBy("piece").applyInArrow(finished, "piece int, domain binary, level binary").toLocalIterator():
        k, x, y = r["piece"] * _PIECE, np.frombuffer(r["domain"], np.float16), np.frombuffer(r["level"], np.uint8)
        domain[k : k + len(x)] = x
        if k >= OFFSETS[4]:
            level[k - int(OFFSETS[4]) :][: len(y)] = y
    return domain, level


def fit(vocabulary: DataFrame, distinct: int, hot_rows: list[tuple[bytes, int]], sample: int = 30_000) -> Mixer:
    """The model from the counts of all tokens; `vocabulary` (token, c) must be staged."""
    domain, level = slot_tables(vocabulary, frozenset(), max(1, min(4096, -(-distinct // 1_000_000))))
    model = Mixer(domain, level, np.full((8 * LEVELS, ORDERS + 1), 0.3), np.tile(squash(np.arange(33) / 2 - 8), (256, 1)))
    top = hot_rows[: sample // 2]
    head = {t for t, _ in top}
    tail = [(bytes(r["token"]), r["c"]) for r in vocabulary.filter("c > 0").orderBy(F.xxhash64("token"), "token").limit(sample // 2).collect()]
    tail = [x for x in tail if x[0] not in head]
    if top or tail:
        stand = max(1.0, (distinct - len(head)) / max(1, len(tail)))
        tokens = [t for t, _ in top] + [t for t, _ in tail]
        weights = np.array([float(c) for _, c in top] + [c * stand for _, c in tail])
        with np.errstate(over="ignore"):
            descend(model, lambda at, undone: mixing_sums(Mixer(domain, level, at, model.refine), tokens, weights, undone), close=1e-6, apart=True)
        learn_from_all(model, vocabulary)
    return model


def score(docs: DataFrame, training: Column, held_out: Column, hot: int = 100_000) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, bits_per_byte: one row per document."""
    everything = staged(counted(docs, training).repartitionByRange("token").sortWithinPartitions("token"))  # tokens that begin alike share their first bits
    is_line = F.startswith(F.col("token"), F.lit(MARK))
    vocabulary, lines = everything.filter(~is_line), everything.filter(is_line)
    n, v = vocabulary.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count_if(F.col("c") > 0)).first()
    all_lines, repeated = lines.agg(F.coalesce(F.sum("c"), F.lit(0)), F.coalesce(F.sum(F.when(F.col("c") > 1, F.col("c"))), F.lit(0))).first()
    known_line = (repeated + 0.5) / (all_lines + 1.0)
    rows = vocabulary.filter("c > 0").orderBy(F.desc("c"), "token").limit(hot).select("token", "c").toArrow()
    hot_rows = list(zip(rows.column(0).to_pylist(), rows.column(1).to_pylist(), strict=True))
    model = fit(vocabulary, int(v), hot_rows)
    bottom = np.log10(n + v + 1)
    with np.errstate(over="ignore"):
        known = {t: k for k, (t, _) in enumerate(hot_rows)}
        values = np.array([np.log10(np.array([c for _, c in hot_rows], float) + 1) - bottom, model.log10([t for t, _ in hot_rows])])
    shared = docs.sparkSession.sparkContext.broadcast((model, known, values))

    def rate(b: pa.RecordBatch) -> dict:
        with np.errstate(over="ignore"):
            return {"token": b.column(0), "c": b.column(1), "s": shared.value[0].log10(b.column(0).to_pylist())}

    least = hot_rows[-1][1] if len(hot_rows) == hot else 0  # tokens above this count are all hot
    rare = map_arrow(vocabulary.filter(F.col("c") <= least if least else "c = 0"), rate, "token binary, c long, s double")
    rare = rare.unionByName(lines.select("token", "c", F.lit(None).cast("double").alias("s")))
    names = ["row", "line", "token", "n", "n_tokens", "n_known", "base", "score"]
    kinds = [pa.int64(), pa.int32(), pa.binary(), pa.int32(), pa.int32(), pa.int32(), pa.float64(), pa.float64()]

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """One row a line with the sums of its hot tokens and its key (n: 0, or in training documents less how often
        the document itself has the line), and one row a rare token of it (n: 1)."""
        _, known, values = shared.value
        place = known.get
        for b in batches:
            out: list[list] = [[] for _ in names]
            for row, learn, raw in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), text_bytes(b.column(2)), strict=True):
                parts = [x for x in lines_of(raw) if x] + [[END]]
                words = [w for x in parts for w in x]
                at = np.fromiter((place(w, -1) for w in words), np.int64, len(words))
                sizes = np.fromiter(map(len, parts), np.int64, len(parts))
                starts = np.cumsum(sizes) - sizes
                hit = at >= 0
                got = np.where(hit, values[:, at], 0.0) if values.shape[1] else np.zeros((2, len(words)))
                missing = np.flatnonzero(~hit)
                keys = [line_key(x) if len(x) >= LINE else b" %d" % row for x in parts]
                own = Counter(keys)
                for col, head, tail in (
                    (out[0], [row] * len(parts), [row] * len(missing)),
                    (out[1], range(len(parts)), (np.searchsorted(starts, missing, "right") - 1).tolist()),
                    (out[2], keys, [words[k] for k in missing]),
                    (out[3], [-own[k] for k in keys] if learn else [0] * len(parts), [1] * len(missing)),
                    (out[4], sizes.tolist(), [0] * len(missing)),
                    (out[5], np.add.reduceat(hit.astype(np.int64), starts).tolist(), [0] * len(missing)),
                    (out[6], np.add.reduceat(got[0], starts).tolist(), [0.0] * len(missing)),
                    (out[7], np.add.reduceat(got[1], starts).tolist(), [0.0] * len(missing)),
                ):
                    col.extend(head)
                    col.extend(tail)
                if len(out[0]) > 200_000:
                    yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(out, kinds, strict=True)], names=names)
                    out = [[] for _ in names]
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(out, kinds, strict=True)], names=names)

    numbered = docs.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long").alias("doc_id"), held_out.alias("held_out"), training.alias("learn"), F.col("text").cast("string").alias("text"))
    pieces = numbered.select("row", "learn", "text").mapInArrow(spread, "row long, line int, token binary, n int, n_tokens int, n_known int, base double, score double")
    word, others = F.col("n") > 0, F.col("c") + F.col("n")
    pieces = pieces.join(rare, "token", "left").select(
        "row",
        "line",
        F.col("n_tokens").cast("long").alias("n_tokens"),
        (F.col("n_known") + F.when(word & (F.col("c") > 0), 1).otherwise(0)).cast("long").alias("n_known"),
        (F.col("base") + F.when(word, F.log10(F.coalesce("c", F.lit(0)) + 1.0) - F.lit(float(bottom))).otherwise(0.0)).alias("base"),
        (F.col("score") + F.when(word, F.col("s")).otherwise(0.0)).alias("score"),
        F.when(~word & (others > 0), others).alias("others"),
    )
    units = pieces.groupBy("row", "line").agg(F.sum("n_tokens").alias("n_tokens"), F.sum("n_known").alias("n_known"), F.sum("base").alias("base"), F.sum("score").alias("score"), F.max("others").alias("others"))
    long_line = F.col("n_tokens") >= LINE
    remembered = F.lit(float(np.log10(known_line) - np.log10(max(1, all_lines)))) + F.log10(F.col("others").cast("double"))
    coded = F.when(long_line & F.col("others").isNotNull(), remembered).when(long_line, F.col("score") + F.lit(float(np.log10(1 - known_line)))).otherwise(F.col("score"))
    sums = units.groupBy("row").agg(F.sum("n_tokens").alias("n_tokens"), F.sum("n_known").alias("n_known"), F.sum("base").alias("base_score"), F.sum(coded).alias("score"))
    size = F.coalesce(F.octet_length("text"), F.lit(0)) + 1  # and the end
    out = numbered.select("row", "doc_id", "held_out", size.alias("size")).join(sums, "row")
    bits = -F.col("score") * float(np.log2(10)) / F.col("size")
    return out.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(int(n)).cast("long").alias("train_tokens"), "base_score", "score", bits.alias("bits_per_byte"))


def op5_context_mixing_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract query: all documents, learning from those whose crc32(doc_id) mod 7 is not 2."""
    fold = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 7, F.lit(0))
    return score(table(spark, sf_dir, "documents"), fold != 2, fold == 2)

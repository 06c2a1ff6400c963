import itertools
import math
import random
import zlib
from collections import Counter

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from prefix_credit.llm import ann, chat_format, context_mixing, decontaminate, html_text, licenses, near_dup, packing, sharding, toxicity

DOCS = "doc_id long, text string, lang string, source string, n_chars long, salt int, bucket string, rank int, n long, row long"


def docs(spark, texts, **more):
    """Documents with extra columns whose names clash with those that operators make."""
    rows = [(k, t, "en", "s", None if t is None else len(t), 1, "b", 2, 3, 4) for k, t in (texts if isinstance(texts, dict) else dict(enumerate(texts))).items()]
    return spark.createDataFrame(rows, DOCS)


ODD = [None, "", " \t\n", "a", "Ünï cödé 漢字", "x " * 30_000, "same text here now", "same text here now"]


# ---- near duplicates ------------------------------------------------------------------------------------------------


def brute_components(texts, n, num, den):
    sets = {}
    for i, t in texts.items():
        w = (t or "").encode().lower().split()
        sets[i] = frozenset(tuple(w[k : k + n]) for k in range(len(w) - n + 1)) if len(w) >= n else frozenset([tuple(w)] if w else [])
    root = {i: i for i in texts}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in itertools.combinations(texts, 2):
        both = len(sets[a] & sets[b])
        if both and den * both >= num * (len(sets[a]) + len(sets[b]) - both):
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in texts}


def near_texts(seed, n=120):
    rnd = random.Random(seed)
    base = [[f"w{rnd.randint(0, 400)}" for _ in range(rnd.randint(20, 120))] for _ in range(12)]
    out = {}
    for k in range(n):
        w = list(rnd.choice(base))
        for _ in range(rnd.choice((0, 0, 1, 2, 3, 6, 20))):
            w[rnd.randrange(len(w))] = f"n{rnd.randint(0, 10**6)}"
        out[k] = " ".join(w)
    return out


@pytest.mark.parametrize("how", [{"n": 3, "num": 85, "rows": 6, "bands": 21}, {"n": 5, "num": 80}, {"n": 3, "num": 85, "rows": 6, "bands": 21, "chunk": 8}])
def test_near_duplicates_against_brute_force(spark, how):
    texts = near_texts(5)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_dup.near_duplicates(docs(spark, texts), **how).collect()}
    assert got == brute_components(texts, how["n"], how["num"], 100)


def test_near_duplicates_star_with_a_middle_base(spark):
    rnd = random.Random(3)
    base = [f"w{k}" for k in range(200)]
    texts = {500: " ".join(base)}
    for k in [*range(500), *range(501, 1001)]:
        w = list(base)
        for at in rnd.sample(range(3, 197), 5):
            w[at] = f"n{rnd.randint(0, 10**9)}"
        texts[k] = " ".join(w)
    sets = {k: {tuple(w[i : i + 3]) for i in range(198)} for k, w in ((k, t.split()) for k, t in texts.items())}
    linked = {k for k, s in sets.items() if 100 * len(s & sets[500]) >= 85 * len(s | sets[500])}
    assert len(linked) == 1001
    for how in ({}, {"block": 100}):
        got = near_dup.near_duplicates(docs(spark, texts), n=3, num=85, rows=6, bands=21, **how).collect()
        assert {r["component_id"] for r in got} == {0}


def test_near_duplicates_every_bucket_pair_meets(spark):
    rows = [(k, 100, 0, 0, 7, 0 if k < 30 else k, 100) for k in range(50)]
    apart = spark.createDataFrame(rows, "node long, n_shingles long, sketch_hi long, sketch_lo long, bucket long, component long, frequent long")
    for block in (4, 1000):
        got = near_dup.block_pairs(apart, 85, 100, 100, block).collect()
        assert len(got) == len(set(got)) and {(r["a"], r["b"]) for r in got} == {(a, b) for a, b in itertools.combinations(range(50), 2) if b >= 30}


def test_near_duplicates_pairs_inside_one_crowd(spark):
    """400 texts that are all .838 alike, and .855 in pairs: every pair is found and nothing else."""
    texts = {}
    for k in range(400):
        words = [f"c{j}" for j in range(93)] + [f"p{k // 2}"] + [f"o{k}x{j}" for j in range(8)]
        random.Random(k).shuffle(words)
        texts[k] = " ".join(words)
    got = {r["doc_id"]: r["component_id"] for r in near_dup.near_duplicates(docs(spark, texts), n=1, num=85, rows=6, bands=21, block=60).collect()}
    assert got == {k: k - k % 2 for k in texts}


def test_shingles_of_one_member_alone_bound_what_it_shares(spark):
    sets = {1: [1, 2, 3, 4], 2: [1, 2, 3, 5], 3: [1, 6, 7, 8], 4: [9, 2, 3, 5]}
    df = spark.createDataFrame(list(sets.items()), "node long, shingles array<long>")
    assert {r["node"]: r["own"] for r in near_dup.own_shingles(df).collect()} == {1: 1, 3: 3, 4: 1}
    apart = spark.createDataFrame([(k, 4, 0, 0, 7, k) for k in sets], "node long, n_shingles long, sketch_hi long, sketch_lo long, bucket long, component long")
    assert {r["node"] for r in near_dup.sharing_members(apart, df, 75, 100).collect()} == {1, 2, 4}
    pairs = lambda at: sorted((r["a"], r["b"]) for r in near_dup.last_pairs(apart, df, 60, 100, 0, 10, at).collect())
    assert pairs(1) == [(1, 2), (1, 4), (2, 4)] and pairs(2) == pairs(16) == [(1, 2), (2, 4)]


def test_near_duplicates_repeated_ids_with_other_texts(spark):
    long = [f"w{k}" for k in range(60)]
    near = [*long[:59], "other"]
    kinds = "doc_id long, text string"
    rows = [(5, "one text of this id here"), (5, " ".join(long)), (9, " ".join(near)), (3, "one text of this id here"), (5, "third text"), (4, "third text"), (5, None)]
    df = spark.createDataFrame(rows, kinds)
    got = [(r["doc_id"], r["n_shingles"], r["component_id"], r["kept"]) for r in near_dup.near_duplicates(df, n=3, num=85, rows=6, bands=21).collect()]
    assert sorted(got) == sorted([(5, 4, 3, False), (5, 58, 5, True), (9, 58, 5, False), (3, 4, 3, True), (5, 1, 4, False), (4, 1, 4, True), (5, 0, 5, True)])
    left = near_dup.without_near_duplicates(df, n=3, num=85, rows=6, bands=21).collect()
    assert sorted((r["doc_id"], r["text"] or "") for r in left) == sorted([(5, " ".join(long)), (3, rows[3][1]), (4, "third text"), (5, "")])


def test_near_duplicates_odd_rows(spark):
    df = docs(spark, ODD).unionByName(docs(spark, {None: "same text here now"})).unionByName(docs(spark, {7: ODD[7]}))
    rows = near_dup.near_duplicates(df, n=3, num=85, rows=6, bands=21).collect()
    assert len(rows) == len(ODD) + 2
    got = {r["doc_id"]: r for r in rows}
    assert [got[k]["n_shingles"] for k in range(3)] == [0, 0, 0] and all(got[k]["component_id"] == k and got[k]["kept"] for k in range(6))
    assert got[7]["component_id"] == 6 and not got[7]["kept"] and got[5]["n_shingles"] == 1
    assert near_dup.near_duplicates(docs(spark, [])).count() == 0


def test_components_on_chains_and_stars(spark):
    edges = [(k, k + 1) for k in range(200)] + [(1000, 1000 + k) for k in range(1, 300)] + [(5000, 5001), (5000, 5001), (5001, 5000)]
    got = {r["doc_id"]: r["component_id"] for r in near_dup.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**dict.fromkeys(range(201), 0), **dict.fromkeys(range(1000, 1300), 1000), 5000: 5000, 5001: 5000}


# ---- decontamination ------------------------------------------------------------------------------------------------


def word_edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


def test_decontamination_against_brute_force(spark):
    rnd = random.Random(2)
    items = {i: [f"w{rnd.randint(0, 60)}" for _ in range(rnd.randint(5, 30))] for i in range(12)}
    texts, want = {}, set()
    for k in range(60):
        w = [f"w{rnd.randint(0, 60)}" for _ in range(30)]
        i = rnd.randrange(12)
        part = list(items[i])
        for _ in range(rnd.choice((0, 1, 2, 4, 9))):
            op, p = rnd.randrange(3), rnd.randrange(len(part))
            part[p : p + (op != 1)] = [] if op == 2 and len(part) > 1 else [f"e{rnd.randint(0, 9)}"]
        at = rnd.randrange(len(w))
        texts[k] = " ".join(w[:at] + part + w[at:]).capitalize() + "!"
    for k, t in texts.items():
        w = [x.strip("!") for x in t.lower().split()]
        for i, item in items.items():
            e = decontaminate.edits_allowed(len(item), 0.8)
            if any(word_edits(item, w[a:b]) <= e for a in range(len(w)) for b in range(max(a, a + len(item) - e), min(len(w), a + len(item) + e) + 1)):
                want.add((k, i))
    bench = spark.createDataFrame([(i, " ".join(w)) for i, w in items.items()] + [(99, None), (98, ""), (97, "two words")], "item_id long, text string")
    rows = decontaminate.contaminated(docs(spark, texts), bench).collect()
    got = {(r["doc_id"], r["item_id"]) for r in rows}
    assert got <= want and len(got) >= 0.99 * len(want) and len(want) > 30
    for r in rows:
        w = [x.strip("!") for x in texts[r["doc_id"]].lower().split()]
        assert word_edits(items[r["item_id"]], w[r["start_word"] : r["start_word"] + r["n_words"]]) == r["edits"]
    clean = decontaminate.without_contaminated(docs(spark, texts), bench)
    assert {r["doc_id"] for r in clean.collect()} == set(texts) - {d for d, _ in got} and clean.columns == docs(spark, []).columns
    small = decontaminate.contaminated(docs(spark, texts), bench, block_words=20)
    assert {(r["doc_id"], r["item_id"]) for r in small.collect()} == got


def test_decontamination_odd_rows(spark):
    bench = spark.createDataFrame([(1, "one two three four five six")], "item_id long, text string")
    df = docs(spark, ODD).unionByName(docs(spark, {None: "one two three four five six"}))
    assert [(r["doc_id"], r["edits"]) for r in decontaminate.contaminated(df, bench).collect()] == [(None, 0)]
    assert decontaminate.without_contaminated(df, bench).count() == len(ODD)
    assert decontaminate.contaminated(df, bench.limit(0)).count() == 0 and decontaminate.contaminated(df.limit(0), bench).count() == 0
    assert decontaminate.skipped_items(spark.createDataFrame([(1, "a b"), (2, None), (3, "a b c d e")], "item_id long, text string")).count() == 2


def test_cgk_keeps_equal_strings_equal_and_close_strings_close():
    rng = np.random.default_rng(1)
    a = rng.integers(0, 50, (40, 30))
    b = a.copy()
    b[:, 15] = 99
    far = rng.integers(0, 50, (40, 30))
    gap = lambda x, y: (decontaminate.cgk(x, 3) != decontaminate.cgk(y, 3)).mean()
    assert gap(a, a) == 0 and gap(a, b) < 0.35 < gap(a, far)


# ---- sharding -------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("dims,bits", [(2, 3), (3, 2), (3, 4), (4, 2)])
def test_hilbert_curve_is_one_connected_path(dims, bits):
    table = sharding.curve_table(dims, bits)
    side = 1 << bits
    where = {v: tuple(c // side**k % side for k in range(dims)) for c, v in enumerate(table)}
    assert sorted(where) == list(range(side**dims))
    assert all(sum(abs(x - y) for x, y in zip(where[k], where[k + 1])) == 1 for k in range(len(where) - 1))


def test_shards_are_even_gapless_and_prune(spark, sf):
    rows = sharding.op2_hilbert_sharding(spark, "/root/testdata/sf0.01").toPandas()
    assert len(rows) == 1000 and set(rows.law) == {"rows"}
    for _, g in rows.groupby("shard"):
        assert sorted(g.slot) == list(range(len(g))) and len(g) in (62, 63)
        assert (g.sort_values("slot").curve.diff().dropna() >= 0).all()
    assert rows.groupby("shard").curve.agg(lambda c: c.max() - c.min()).mean() < 4096 / 8


def test_long_common_prefixes_are_told_apart(spark):
    df = spark.range(64).select("id", F.format_string("https://host%02d/", F.col("id") % 32).alias("url"))
    got = sharding.hilbert_order(df, ["url"]).collect()
    assert len({r["curve"] for r in got}) == 16
    by = sorted((r["url"], r["curve"]) for r in got)
    assert [c for _, c in by] == sorted(c for _, c in by)


def test_sharding_odd_rows(spark):
    df = docs(spark, ODD).unionByName(docs(spark, {None: "z"})).unionByName(docs(spark, {7: ODD[7]})).withColumn("source", F.when(F.col("doc_id") > 2, F.col("source")))
    out = sharding.shard_by_curve(df, ["source", "lang", "n_chars"], "doc_id", 4, salts=2)
    rows = out.collect()
    assert len(rows) == len(ODD) + 2 and "salt" in out.columns and {r["salt"] for r in rows} == {1}
    n = Counter(r["shard"] for r in rows)
    assert max(n.values()) - min(n.values()) <= 1
    assert sharding.shard_by_curve(df.limit(0), ["source", "lang"], "doc_id", 4).count() == 0


# ---- nearest neighbours ---------------------------------------------------------------------------------------------


def vectors(spark, x):
    return spark.createDataFrame([(k, None if v is None else [None if c is None else float(c) for c in v]) for k, v in enumerate(x)], "vec_id long, embedding array<float>")


def test_search_recall_and_order(spark):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(6000, 32)).astype(np.float32)
    x[100:140] = x[99]  # copies: ties to smaller ids
    x *= rng.uniform(0.5, 2, (6000, 1)).astype(np.float32)
    x[100:140] = x[99]
    rows = ann.search(vectors(spark, x), "vec_id % 60 = 0", least_seen=1500).toPandas()
    full, hit = x.astype(float), 0
    for q, g in rows.groupby("query_id"):
        g = g.sort_values("rank")
        assert list(g["rank"]) == list(range(1, 21)) and q not in set(g.vec_id)
        assert np.allclose(g.score, full[g.vec_id] @ full[q], rtol=1e-12, atol=1e-12)
        assert list(zip(-g.score, g.vec_id)) == sorted(zip(-g.score, g.vec_id))
        s = full @ full[q]
        s[q] = -np.inf
        hit += len(set(np.lexsort((np.arange(6000), -s))[:20]) & set(g.vec_id))
    assert rows.query_id.nunique() == 100 and hit / 2000 >= 0.9


def test_search_odd_rows(spark):
    rows = [[1, 0, 0], None, [0, 0, 0], [1, float("nan"), 0], [1, None, 0], [float("inf"), 0, 0], [0.5, 1, 0], [0.5, 1, 0], [1, 2], [-1, 0, 0]]
    got = ann.search(vectors(spark, rows), "vec_id in (0, 1, 2, 6)").orderBy("query_id", "rank").collect()
    assert [(r["query_id"], r["vec_id"], r["score"]) for r in got] == [(0, 6, 0.5), (0, 7, 0.5), (0, 9, -1.0), (6, 7, 1.25), (6, 0, 0.5), (6, 9, -0.5)]
    assert ann.search(vectors(spark, [None]), "vec_id = 0").count() == 0
    assert ann.search(vectors(spark, [[1, 2]]), "vec_id = 0").count() == 0


def test_search_of_rows_that_codes_cannot_tell_apart(spark):
    """A clump far denser than the codes, norms of all sizes, and parts whose squares leave the range of doubles."""
    rng = np.random.default_rng(4)
    x = rng.normal(size=(3000, 16))
    x[:600] = x[0] + 1e-3 * rng.normal(size=(600, 16))
    x[600:700] *= np.exp(rng.normal(0, 4, (100, 1)))
    x[700:720] *= 1e-30
    x[720] *= 0
    x = x.astype(np.float32)
    rows = ann.search(vectors(spark, x), "vec_id % 60 = 0", least_seen=300, chunk=700).toPandas()
    full = x.astype(float)
    for q in range(0, 3000, 60):
        if q == 720:
            continue
        s = np.einsum("nd,d->n", full, full[q])
        s[[q, 720]] = -np.inf
        got = rows[rows.query_id == q].sort_values("rank")
        assert list(got.vec_id) == list(np.lexsort((np.arange(3000), -s))[:20])
    tiny = [[1e-300 * c for c in r] for r in ([1.0, 2.0], [2.0, 1.0], [-1.0, 0.0])]
    wide = spark.createDataFrame(list(enumerate(tiny)), "vec_id long, embedding array<double>")
    assert ann.search(wide, "vec_id = 0").count() == 2


def test_search_deals_a_query_to_a_bounded_number_of_cells(spark, monkeypatch):
    """More rows make larger cells, not more of them, each with its k rows for a query; nothing is lost by it."""
    x = np.random.default_rng(9).normal(size=(5000, 8)).astype(np.float32)
    cut, made = ann._shelves, []
    monkeypatch.setattr(ann, "_shelves", lambda c, sizes, chunk: made.append((cut(c, sizes, chunk), chunk)) or made[-1][0])
    rows = ann.search(vectors(spark, x), "vec_id % 250 = 0", chunk=100).toPandas()
    assert len(made[0][0]) <= 32 and made[0][1] * 16 >= 5000
    full = x.astype(float)
    for q in range(0, 5000, 250):
        s = np.einsum("nd,d->n", full, full[q])
        s[q] = -np.inf
        assert list(rows[rows.query_id == q].sort_values("rank").vec_id) == list(np.lexsort((np.arange(5000), -s))[:20])


# ---- toxicity -------------------------------------------------------------------------------------------------------


def test_toxicity_held_out(spark):
    sf = "/root/testdata/sf0.1"
    d, lab = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = toxicity.fit(d, lab.filter("doc_id % 3 <> 0"))
    got = toxicity.severity(d, model).withColumnRenamed("toxic", "said").join(lab.filter("doc_id % 3 = 0 and quality = 1"), "doc_id")
    r = got.agg(F.count_if(F.expr("said and toxic = 1")).alias("tp"), F.count_if(F.expr("said and toxic = 0")).alias("fp"), F.count_if(F.expr("not said and toxic = 1")).alias("fn"), F.count_if(F.expr("not said and toxic = 0")).alias("tn")).first()
    assert r["tp"] / (r["tp"] + r["fn"]) > 0.8 and r["fp"] / (r["fp"] + r["tn"]) < 0.01


def plain_features(text):
    """Features of a text by their definition, one by one."""
    raw = bytes(b + 32 if 65 <= b <= 90 else b for b in (text or "").encode())
    words = {bytes(w) for ok, w in itertools.groupby(raw, lambda b: b >= 128 or 48 <= b <= 57 or 97 <= b <= 122) if ok}
    n = Counter()
    for w in words:
        n.update([xxhash.xxh3_64_intdigest(w) >> 42] + [xxhash.xxh3_64_intdigest(w[:k], k) >> 42 for k in range(4, 9) if k < len(w)])
    return set(n) | {(p * 2_654_435_761 + least * 40_503) % 2**22 for p, c in n.items() for least in (2, 4) if c >= least}


def test_toxicity_query_against_brute_force(spark):
    """Scores of the whole table from features by their definition; the fit is at the optimum of the penalised likelihood."""
    sf = "/root/testdata/sf0.01"
    d, lab = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    feats = {r["doc_id"]: plain_features(r["text"]) for r in d.select("doc_id", "text").collect()}
    grade = {r["doc_id"]: 0 if r["toxic"] == 0 else 2 if r["quality"] == 0 else 1 for r in lab.collect() if r["doc_id"] in feats and r["toxic"] is not None}
    assert 100 < len(grade) <= 8_000 and len(grade) == lab.filter("toxic is not null").count()
    model = toxicity.fit(d, lab)
    w = dict(zip(model.places.tolist(), model.weights.tolist(), strict=True))
    cuts = [-math.inf, *model.cuts.tolist(), math.inf]
    if len(cuts) == 3:
        grade = {k: min(g, 1) for k, g in grade.items()}
    base = sum(g > 0 for g in grade.values()) / len(grade)
    df, hits = Counter(), Counter()
    for k, g in grade.items():
        df.update(feats[k])
        hits.update(feats[k] if g else ())
    told = {p for p, n in df.items() if n >= 5 and abs(hits[p] - n * base) / math.sqrt(n * base * (1 - base)) > 3.5}
    assert told == set(w)
    sig = lambda z: 1 / (1 + math.exp(-max(-700.0, min(700.0, z))))
    eta = {k: sum(w[p] for p in f if p in w) for k, f in feats.items()}
    for r in toxicity.op4_ordinal_toxicity(spark, sf).collect():
        up = [sig(eta[r["doc_id"]] - c) for c in cuts[1:-1]]
        assert r["p_toxic"] == pytest.approx(up[0], abs=1e-9) and r["expected_severity"] == pytest.approx(sum(up), abs=1e-9)
        assert r["toxic"] == (r["p_toxic"] >= 0.5)
    slope = Counter()
    for k, g in grade.items():
        hi, lo = (1.0 if math.isinf(cuts[g + 1]) else sig(cuts[g + 1] - eta[k])), (0.0 if math.isinf(cuts[g]) else sig(cuts[g] - eta[k]))
        pull = (hi * (1 - hi) - lo * (1 - lo)) / (hi - lo) / len(grade)
        for p in feats[k]:
            if p in w:
                slope[p] += pull
    l1 = 0.3 / len(grade)
    off = [abs(slope[p] + math.copysign(l1, x)) if x else max(0.0, abs(slope[p]) - l1) for p, x in w.items()]
    assert max(off) < 0.1 * l1


def test_toxicity_labels_that_disagree_and_ids_with_several_texts(spark):
    lab = "doc_id long, quality int, toxic int"
    texts = {k: ("vile " if k % 4 == 0 else "") + f"word{k % 7} thing{k % 5} plain" for k in range(200)}
    labels = [(k, 1, 1 if k % 4 == 0 else 0) for k in range(200)]
    train = docs(spark, texts)
    want = toxicity.fit(train, spark.createDataFrame(labels, lab))
    clash = spark.createDataFrame([(k, 1, 0) for k in range(0, 200, 4)] + labels + labels, lab)
    for df, some in ((train, clash), (train.unionByName(train), clash.repartition(5))):
        got = toxicity.fit(df, some)
        assert (got.places == want.places).all() and np.allclose(got.weights, want.weights) and np.allclose(got.cuts, want.cuts)
    twice = train.unionByName(docs(spark, {k: f"other text {k}" for k in range(0, 200, 8)}))
    one, other = (toxicity.fit(twice.repartition(n), clash) for n in (3, 7))
    assert (one.places == other.places).all() and (one.weights == other.weights).all()


def test_ordinal_grades_share_weights(spark):
    rng = np.random.default_rng(3)
    strength = np.array([0.0, 1.5, 3.0, -1.0])
    x = rng.random((4000, 4)) < 0.3
    eta = x @ strength + rng.logistic(size=4000)
    grades = (eta > 1).astype(int) + (eta > 3)
    rows, cols = np.nonzero(x)
    w, cuts = toxicity.fit_ordinal(rows, cols, grades, 4, l1=0)
    assert np.allclose(w, strength, atol=0.35) and np.allclose(cuts, [1, 3], atol=0.35)
    model = toxicity.OrdinalModel(np.arange(4, dtype=np.int32), w, cuts)
    up = model.at_least(np.array([0.0, 2.0, 5.0]))
    assert (up[:, 0] >= up[:, 1]).all() and (np.diff(up.sum(axis=1)) > 0).all()


def test_toxicity_odd_rows(spark):
    lab = "doc_id long, quality int, toxic int"
    train = docs(spark, {k: ("vile " if k % 4 == 0 else "") + f"word{k % 7} thing{k % 5} plain" for k in range(400)})
    labels = spark.createDataFrame([(k, None if k == 8 else 1, 1 if k % 4 == 0 else 0) for k in range(400)] + [(None, 1, 1), (3, 1, None), (3, 1, 0)], lab)
    model = toxicity.fit(train, labels)
    df = docs(spark, [*ODD, "so VILE!", "kind"]).unionByName(docs(spark, {None: "vile"}))
    got = toxicity.severity(df, model).collect()
    assert len(got) == df.count() and {r["doc_id"] for r in got if r["toxic"]} == {8, None}
    assert toxicity.without_toxic(df, model).count() == df.count() - 2
    none = toxicity.fit(train, labels.limit(0))
    assert toxicity.severity(df, none).filter("toxic or expected_severity > 1e-9").isEmpty()
    assert toxicity.severity(df.limit(0), model).count() == 0


# ---- language model -------------------------------------------------------------------------------------------------


def test_mixing_is_learnt_from_all_tokens(spark):
    """The model does not depend on the tokens that its weights start from."""
    rng = np.random.default_rng(5)
    words = sorted({bytes(rng.choice(list(b"abcde"), rng.integers(2, 7)).tolist()) for _ in range(400)})
    rows = [(bytearray(t), int(c)) for t, c in zip(words, rng.integers(1, 50, len(words)))]
    hot = sorted(((bytes(t), c) for t, c in rows), key=lambda x: (-x[1], x[0]))[:100]
    vocabulary = spark.createDataFrame(rows, "token binary, c long").cache()
    with np.errstate(over="ignore"):
        few, many = (context_mixing.fit(vocabulary, len(rows), hot, sample=n).log10(words) for n in (4, 1000))
    assert np.allclose(few, many, atol=0.02)


def test_mixing_is_learnt_in_few_passes_and_a_small_driver(spark):
    """Bits that tokens share are worked out once, counts stay in Spark, and no step is thrown away again and again."""
    rng = np.random.default_rng(6)
    words = sorted({bytes(rng.choice(list(b"abcdefg"), rng.integers(2, 9)).tolist()) for _ in range(3000)} | {b"x" * 70, b"\n", "é".encode()})
    counts = rng.zipf(1.5, len(words)).clip(1, 1000)
    with np.errstate(over="ignore"):
        codes, lengths = context_mixing.encoded(words)
        whole = shared = 0
        for (rows, now, h), (again, node, once, few) in zip(context_mixing.contexts(codes, lengths), context_mixing.nodes(words), strict=True):
            assert (rows == again).all() and (now == once[node]).all() and (h == few[:, node]).all()
            whole, shared = whole + len(now), shared + len(once)
        assert shared < 0.7 * whole
        vocabulary = spark.createDataFrame([(bytearray(t), int(c)) for t, c in zip(words, counts, strict=True)], "token binary, c long").cache()
        tables = context_mixing.slot_tables(vocabulary, frozenset(words), 2)
        assert sum(x.nbytes for x in tables) < 20_000_000
        one = context_mixing.slot_tables(vocabulary, frozenset(words), 1)
        assert all((a == b).all() for a, b in zip(tables, one, strict=True))
        model = context_mixing.Mixer(*tables, np.full((64, 6), 0.3), np.full((256, 33), 0.5))
        costs = []

        def sums(weights):
            got = context_mixing.mixing_sums(context_mixing.Mixer(*tables, weights, None), words, counts.astype(float))
            costs.append(got[:64].sum() / got[64:128].sum())
            return got

        context_mixing.descend(model, sums)
        assert len(costs) <= 20 and costs[-1] == min(costs) < 0.97 * costs[0]
        total = -sum(float(c) * x for c, x in zip(counts, model.log10(words), strict=True)) * math.log(10)
    assert total <= 1.02 * costs[-1] * (lengths * 8) @ counts


def test_a_pass_leaves_out_gates_that_are_done(spark):
    """Later passes work out the open gates only, and the weights and map are those of passes over all gates."""
    rng = np.random.default_rng(8)
    words = sorted({bytes(rng.choice(list(b"abcdefg"), rng.integers(2, 9)).tolist()) for _ in range(3000)} | {b"\n", "é".encode()})
    counts = rng.zipf(1.5, len(words)).clip(1, 1000).astype(float)
    vocabulary = spark.createDataFrame([(bytearray(t), int(c)) for t, c in zip(words, counts, strict=True)], "token binary, c long").cache()
    with np.errstate(over="ignore"):
        tables = context_mixing.slot_tables(vocabulary, frozenset(words), 1)
        whole, apart = (context_mixing.Mixer(*tables, np.full((64, 6), 0.3), None) for _ in range(2))
        context_mixing.descend(whole, lambda at: context_mixing.mixing_sums(context_mixing.Mixer(*tables, at, None), words, counts))
        passes = []

        def sums(at, undone):
            passes.append(undone.copy())
            got = context_mixing.mixing_sums(context_mixing.Mixer(*tables, at, None), words, counts, undone)
            assert not got[:64][~undone].any() and (got[64:128][undone] > 0).any()
            return got

        context_mixing.descend(apart, sums, apart=True)
        assert all((a >= b).all() for a, b in zip(passes, passes[1:])) and sum(x.sum() for x in passes) < 0.6 * 64 * len(passes)
        assert np.allclose(whole.weights, apart.weights, atol=1e-6) and np.allclose(whole.refine, apart.refine, atol=1e-6)
        again = context_mixing.mixing_sums(context_mixing.Mixer(*tables, apart.weights, None), words, counts)
    bins = again[64 * (2 + 6 * 7) :].reshape(8 * 255, 33, 2)  # bit 0 has one row a level, which are the map's row 1
    prior = again[64:128].sum() * 1e-6
    row = (bins[:8, :, 1].sum(axis=0) + prior * context_mixing.squash(np.arange(33) / 2 - 8)) / (bins[:8].sum(axis=(0, 2)) + prior)
    assert np.allclose(apart.refine[1], row, atol=1e-6)


def test_sums_of_few_bits_are_sent_short():
    """Tables of many small tasks don't fill the memory of the task that adds them."""
    rng = np.random.default_rng(10)
    for kind in (np.float32, np.float64):
        total, want = np.zeros(1000), np.zeros(1000)
        for share in (0.0, 0.01, 0.3, 0.6, 1.0):
            x = (rng.integers(1, 9, 1000) * (rng.random(1000) < share)).astype(kind)
            raw = context_mixing.packed(x)
            assert len(raw) == min(x.nbytes, int((x != 0).sum()) * (x.itemsize + 4))
            context_mixing.add_packed(total, raw, kind)
            want += x
        assert (total == want).all()


def test_tokens_that_begin_alike_are_staged_together(spark, monkeypatch):
    """No token of another task lies between two tokens of one task, so that passes share their first bits."""
    kept, stage = [], context_mixing.staged
    monkeypatch.setattr(context_mixing, "staged", lambda df: kept.append(df) or stage(df))
    rng = np.random.default_rng(9)
    texts = [" ".join(bytes(rng.choice(list(b"abcdefg"), 5).tolist()).decode() for _ in range(40)) for _ in range(60)]
    merge = "spark.sql.adaptive.coalescePartitions.enabled"
    spark.conf.set(merge, "false")  # else so few tokens are one task
    try:
        assert context_mixing.score(docs(spark, texts), F.lit(True), F.lit(False)).count() == 60
        spans = kept[0].groupBy(F.spark_partition_id().alias("k")).agg(F.min("token").alias("a"), F.max("token").alias("z")).orderBy("a").collect()
    finally:
        spark.conf.unset(merge)
    assert len(spans) > 1 and all(bytes(x["z"]) < bytes(y["a"]) for x, y in zip(spans, spans[1:]))


def test_whole_words_of_all_tokens_are_learnt(spark):
    """Tables and scores hold the whole-word context of every token, not of the most frequent ones."""
    rng = np.random.default_rng(11)
    words = sorted({bytes(rng.choice(list(b"abcdefg"), rng.integers(2, 9)).tolist()) for _ in range(300)})
    counts = rng.integers(1, 20, len(words))
    vocabulary = spark.createDataFrame([(bytearray(t), int(c)) for t, c in zip(words, counts, strict=True)], "token binary, c long")
    n = np.zeros((2, int(context_mixing.OFFSETS[-1])))
    with np.errstate(over="ignore"):
        domain, level = context_mixing.slot_tables(vocabulary, frozenset(words[:3]), 2)
        codes, lengths = context_mixing.encoded(words)
        for rows, now, h in context_mixing.contexts(codes, lengths):
            for _, partial, bit in context_mixing.bit_steps(now):
                for s in context_mixing.slots(h, partial):
                    np.add.at(n, (bit, s), counts[rows])
    assert np.allclose(domain, np.log((n[1] + 0.4) / (n[0] + 0.4)), rtol=1e-3)
    seen = n.sum(axis=0)[int(context_mixing.OFFSETS[4]) :]
    assert (level % 8 == np.minimum(7, np.ceil(np.log2(seen + 1) / 3))).all() and (level // 8 == np.minimum(seen, 31)).all()
    texts = [b" ".join(rng.choice(words, 30).tolist()).decode() for _ in range(80)]
    few, many = ({r["doc_id"]: r["score"] for r in context_mixing.score(docs(spark, texts), F.col("doc_id") < 60, F.col("doc_id") >= 60, hot=h).collect()} for h in (5, 100_000))
    assert all(few[k] == pytest.approx(many[k], rel=2e-3) for k in range(80))


def test_weights_are_learnt_without_own_whole_word_counts():
    """One occurrence is taken off exactly where counts are small, in the prediction and in its gate."""
    n0, n1 = (x.ravel().astype(np.float32) for x in np.meshgrid(np.arange(40), np.arange(40)))
    x, code = np.log((n1 + 0.4) / (n0 + 0.4)).astype(np.float16).astype(float), context_mixing.level_codes(n0 + n1)
    for bit, own in ((0, n0), (1, n1)):
        some = own > 0
        got = context_mixing.without_own(x[some], code[some], np.full(some.sum(), bit))
        m0, m1 = n0[some] - (bit == 0), n1[some] - (bit == 1)
        small = m0 + m1 < 30
        assert np.allclose(got[small], np.log((m1 + 0.4) / (m0 + 0.4))[small], atol=1e-5) and (got[~small] == x[some][~small]).all()
        assert (context_mixing._LESS[code[some]][small] == (context_mixing.level_codes(m0 + m1) % 8)[small]).all()
    # a word seen once says nothing of itself: its bits are at gates of words not seen
    tables = np.zeros(int(context_mixing.OFFSETS[-1]), np.float16), np.full(1 << context_mixing.BITS[4], context_mixing.level_codes(np.ones(1))[0])
    with np.errstate(over="ignore"):
        got = context_mixing.mixing_sums(context_mixing.Mixer(*tables, np.full((64, 6), 0.3), None), [b"once"], np.ones(1))
    assert got[64:128].reshape(8, 8)[:, 0].sum() == got[64:128].sum() == 5 * 8


def test_context_mixing_contract(spark):
    rnd = random.Random(1)
    texts = {k: " ".join(rnd.choice(("the", "of", "River", "stone", f"w{rnd.randint(0, 50)}")) for _ in range(60)) for k in range(200)}
    texts |= {200 + k: t for k, t in enumerate(ODD)}
    fold = lambda k: zlib.crc32(str(k).encode()) % 7 == 2
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 7 == 2
    rows = {r["doc_id"]: r for r in context_mixing.score(docs(spark, texts), ~held, held).collect()}
    tok = {k: (t or "").encode().lower().split() + [b"\n"] for k, t in texts.items()}
    c = Counter(w for k, ws in tok.items() if not fold(k) for w in ws)
    n, v = sum(c.values()), len(c)
    for k, ws in tok.items():
        r = rows[k]
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (fold(k), len(ws), sum(c[w] > 0 for w in ws), n)
        assert r["base_score"] == pytest.approx(sum(math.log10((c[w] + 1) / (n + v + 1)) for w in ws))
    inside = [k for k in range(200) if fold(k)]
    assert sum(rows[k]["score"] for k in inside) > 0.97 * sum(math.log10(c[w] / n if c[w] else 1 / n) for k in inside for w in tok[k]) - 60 * len(inside)
    assert rows[200]["score"] == rows[201]["score"] < 0
    assert rows[206]["score"] == rows[207]["score"]


def test_a_line_repeated_inside_one_text_is_not_predicted_from_it(spark):
    line = " ".join(f"only{k}" for k in range(12))
    texts = {k: f"some words {k} here\nand more of them" for k in range(30)} | {30: f"{line}\n{line}\n{line}", 31: line.replace("only", "both"), 32: line.replace("only", "both")}
    rows = {r["doc_id"]: r for r in context_mixing.score(docs(spark, texts), F.lit(True), F.lit(False)).collect()}
    assert rows[30]["score"] < 2.5 * rows[31]["score"] < 0 and rows[31]["score"] > -8  # 31 is in 32 too
    assert rows[31]["bits_per_byte"] == pytest.approx(-rows[31]["score"] * math.log2(10) / (len(texts[31]) + 1))


def test_bit_probabilities_sum_to_one():
    rng = np.random.default_rng(0)
    domain = rng.normal(size=int(context_mixing.OFFSETS[-1])).astype(np.float16)
    level = rng.integers(0, 8, 1 << context_mixing.BITS[4]).astype(np.uint8)
    model = context_mixing.Mixer(domain, level, rng.normal(0.2, 0.1, (64, 6)), np.tile(context_mixing.squash(np.arange(33) / 2 - 8), (256, 1)))
    with np.errstate(over="ignore"):
        first = np.zeros(256)
        now = np.arange(256, dtype=np.uint8)
        _, _, h = next(context_mixing.contexts(now[:, None], np.ones(256, np.int64)))
        for b, partial, bit in context_mixing.bit_steps(now):
            p = model.predict(b, partial, context_mixing.slots(h, partial))
            first += np.log(np.where(bit == 1, p, 1 - p))
    assert np.exp(first).sum() == pytest.approx(1, abs=1e-6)


def test_mixing_odd_tables(spark):
    yes, no = F.lit(True), F.lit(False)
    assert context_mixing.score(docs(spark, []), yes, no).count() == 0
    rows = context_mixing.score(docs(spark, ["a b", None]), no, yes).collect()
    assert [r["train_tokens"] for r in rows] == [0, 0] and all(math.isfinite(r["score"]) for r in rows)


# ---- chat -----------------------------------------------------------------------------------------------------------


def brute_pair(c, r):
    n = 0
    while n < min(len(c), len(r)) and c[n] == r[n]:
        n += 1
    show = lambda ts: "".join(f"{chat_format.OPEN}{a}{chat_format.MIDDLE}{t}{chat_format.CLOSE}" for a, t in ts)
    return n, show(c[:n]), show(c[n:]), show(r[n:])


def test_preference_rows_against_brute_force(spark):
    rnd = random.Random(6)
    turn = lambda: (rnd.choice(("user", "assistant", "system")), rnd.choice(("x", "y", "", "ünï")))
    chosen, rejected = {}, {}
    for k in range(80):
        chosen[k] = [turn() for _ in range(rnd.randint(1, 6))]
        rejected[k] = chosen[k][: rnd.randint(0, 6)] + [turn() for _ in range(rnd.randint(0, 3))]
    table = lambda x: spark.createDataFrame([(k, t, a, b, 1) for k, ts in x.items() for t, (a, b) in enumerate(ts)], "pair_id long, turn long, role string, text string, c int")
    for r in chat_format.preference_rows(table(chosen), table(rejected)).collect():
        assert (r["n_common"], r["prompt"], r["chosen"], r["rejected"]) == brute_pair(chosen[r["pair_id"]], rejected[r["pair_id"]])
        spans = [r["chosen"][s["start"] : s["end"]] for s in r["chosen_mask"]]
        assert spans == [t + chat_format.CLOSE for a, t in chosen[r["pair_id"]][r["n_common"] :] if a == "assistant"]


def test_preference_odd_rows(spark):
    kind = "conv_id long, turn long, role string, text string"
    rows = [(1, 0, "user", "hi"), (1, 1, "assistant", "yo"), (2, 0, "user", "no answer"), (3, None, None, None), (3, 1, "assistant", None), (None, 0, "assistant", "x"), (4, 0, "user", "a"), (4, 0, "user", "a"), (4, 1, "assistant", "a"), (5, 0, "assistant", "x" * 100_000)]
    got = {r["pair_id"]: r for r in chat_format.preference_rows(*chat_format.echo_pairs(spark.createDataFrame(rows, kind))).collect()}
    assert set(got) == {1, 2, 3, None, 4, 5}
    assert got[1]["n_common"] == 1 and got[1]["rejected"].endswith(f"hi{chat_format.CLOSE}")
    assert got[2]["chosen"] == "" and got[2]["n_common"] == 1
    assert got[4]["n_common"] == 3  # the echo is the answer
    assert chat_format.preference_rows(*chat_format.echo_pairs(spark.createDataFrame([], kind))).count() == 0


# ---- licenses -------------------------------------------------------------------------------------------------------


def test_license_join_loses_nothing(spark):
    rnd = random.Random(9)
    vocab = sorted({w.decode() for _, t, _ in licenses.TEMPLATES for w in licenses.alnum_words(t.encode())}) + ["foo", "bar"]
    texts = {}
    for k in range(150):
        lines = [" ".join(rnd.choice(vocab) for _ in range(rnd.randint(0, 12))) for _ in range(3)]
        t = rnd.choice(licenses.TEMPLATES)[1].split()
        for _ in range(rnd.randint(0, 3)):
            t[rnd.randrange(len(t))] = "foo"
        lines.insert(rnd.randrange(3), " ".join(t).upper())
        texts[k] = "\n".join(lines)
    longest = max(len(t.split()) + 9 for _, t, _ in licenses.TEMPLATES)
    for r in licenses.scan(docs(spark, texts)).collect():
        want = set()
        for at, words, inner in licenses.blocks(texts[r["doc_id"]].encode(), longest):
            for label, text, _ in licenses.TEMPLATES:
                toks = licenses.alnum_words(text.encode())
                share = len(set(toks) & set(words)) / len(set(toks))
                if share >= 0.8 and (not inner or inner + 2 <= len(toks)):
                    want.add((at, label, round(share, 9)))
        assert {(b["start"], b["label"], round(b["containment"], 9)) for b in r["blocks"]} == want
        assert set(r["labels"].split(",")) - {""} == {b["label"] for b in r["blocks"] if b["labels"]} | set(r["base_labels"].split(",")) - {""}


def test_license_words_in_another_order_and_full_texts(spark):
    by = {label: text for label, text, _ in licenses.TEMPLATES}
    mixed = by["isc"].split()
    random.Random(1).shuffle(mixed)
    full = max((t for label, t, _ in licenses.TEMPLATES if label == "mit"), key=len).split()
    wrapped = "\n".join(" * " + " ".join(full[k : k + 9]) for k in range(0, len(full), 9))
    texts = [" ".join(mixed), wrapped, "licensed under the GNU General Public License", "Copyright\n" + "x\n" * 9 + "all rights\n" + "x\n" * 9 + "reserved"]
    got = [r for r in licenses.scan(docs(spark, texts)).orderBy("doc_id").collect()]
    assert [r["labels"] for r in got] == ["isc", "mit", "", ""]
    assert any(b["label"] == "lgpl" and not b["labels"] for b in got[2]["blocks"])  # over the threshold, but not named
    assert max(b["containment"] for b in got[1]["blocks"] if b["labels"]) == 1.0


def test_license_filters_fire():
    index = licenses.TemplateIndex(licenses.TEMPLATES, {}, 0.8)
    rare = index.entries[0][1][0]
    words = [rare, *(b"foo%d" % k for k in range(200))]
    assert index.joined(words) == [] and len(set(words)) > max(e[2] for e in index.entries)  # by place, not by length


def test_license_notices_over_many_lines_and_two_in_a_line(spark):
    wrapped = "Permission is hereby\n granted, free of\n charge, to any\n\n person obtaining\n a copy of this\n software and\n associated\n documentation files"
    both = "licensed under the GNU General Public License, version 3. Permission is hereby granted, free of charge, to any person obtaining a copy of this software and files"
    texts = [wrapped, both, "licensed under the GNU General Public License, version 3"]
    got = [r["labels"] for r in licenses.scan(docs(spark, texts)).orderBy("doc_id").collect()]
    assert got == ["mit", "gpl-3,mit", "gpl-3"]


def test_license_phrases_and_odd_rows(spark):
    texts = [*ODD, "Under the MIT-License, under the mit license; cc by-nc", "Apache License Version 2.0", "mit mit mit der mit", "a\nReleased under the\nMIT License"]
    got = [r for r in licenses.scan(docs(spark, texts)).orderBy("doc_id").collect()]
    assert (got[0]["n_words"], got[0]["labels"], got[0]["score"], got[0]["first_word"]) == (0, "", 0.0, None)
    r = got[8]
    assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"], r["score"]) == (11, 3, 0, 8, "cc-by-nc,mit", 1.0)
    assert got[9]["base_labels"] == "apache-2" and got[10]["labels"] == "" and "mit" in got[11]["labels"]
    assert licenses.scan(docs(spark, [])).count() == 0


# ---- packing --------------------------------------------------------------------------------------------------------


def test_boundaries_against_all_choices():
    rng = np.random.default_rng(2)
    for _ in range(40):
        m = int(rng.integers(1, 9))
        lengths = np.sort(rng.choice(50, m, replace=False) + 1).astype(float)
        counts = rng.integers(1, 9, m).astype(float)
        for k in (1, 2, 3, 5):
            cost = lambda edges: sum(c * (min(e for e in edges if e >= x) - x) for x, c in zip(lengths, counts))
            best = min(cost([*pick, lengths[-1]]) for n in range(min(k, m)) for pick in itertools.combinations(lengths[:-1], n))
            got = packing.optimal_boundaries(lengths, counts, lengths * counts, k)
            assert len(got) <= k and got[-1] == lengths[-1] and cost(got) == best


def test_packing_places_every_row_once(spark):
    texts = ["w " * (1 + 37 * k % 900) for k in range(500)] + ODD
    df = packing.token_lengths(docs(spark, texts).unionByName(docs(spark, {7: "again", None: "none"})))
    out = packing.pack(df, "doc_id", "n_tokens", buckets=5, token_budget=4000, part_rows=100).toPandas()
    assert len(out) == len(texts) + 2 and (out.padding >= 0).all()
    for _, g in out.groupby("batch"):
        assert sorted(g.position) == list(range(len(g))) and g.bucket_len.nunique() == 1
        assert len(g) == 1 or len(g) * g.bucket_len.iloc[0] <= 4000
    assert packing.pack(df.limit(0), "doc_id", "n_tokens").count() == 0


# ---- html -----------------------------------------------------------------------------------------------------------


def page_text(html, template=frozenset()):
    return html_text.main_text(html_text.parse(html), template)


@pytest.mark.parametrize(
    "html,want",
    [
        ("", ""),
        ("plain &amp; simple", "plain & simple"),
        ("<body><nav>menu</nav><article><h1>T</h1><p>a <b>b</b>c<br>d<p>e &lt;f&gt; &#233;</article><footer>x</footer>", "T a bc d e <f> é"),
        ("<div class='cookie-notice'>no</div><div id=sidebar>no</div><p>yes</p><form><p>no</p></form><div class='reader-comments'>no</div>", "yes"),
        ("<script>if (a < b) {}</script><style>p{}</style><p>x<!-- c --> y</p>", "x y"),
        ("<ul><li>a<li>b</ul><table><tr><td>c<td>d</table>", "a b c d"),
        ("<p>a</b></div>b</p><p title='>'>c", "ab c"),
        ("<article class=comment>no</article><p>yes", "yes"),
        ("a < b and <3", "a < b and <3"),
        ("<p>unclosed <b", "unclosed"),
        ("<div>" * 5000 + "deep" + "</div>" * 5000, "deep"),
        ("<p>one&nbsp;two three</p>", "one two three"),
    ],
)
def test_main_text(html, want):
    assert page_text(html) == want


@pytest.mark.parametrize(
    "page",
    [
        '<body><div class="layout has-sidebar"><p>The story.</p><div class="sidebar">links</div></div></body>',
        '<body><div id="content" class="no-sidebar"><p>The story.</p></div></body>',
        '<body><article class="post comments-open"><p>The story.</p><div class="comments">a comment</div></article></body>',
        '<body><div class="promo-layout"><div class="banner"><main><p>The story.</p></main></div></div></body>',
        '<body><article><h2 class="section-header">The</h2><p>story.</p><div class="newsletter">sign up</div></article></body>',
        '<body><div class="related"><p>The story.</p></div></body>',
        '<body><div class="sidebar"></div><div class="widget">The story.</div><nav>menu</nav></body>',
    ],
)
def test_names_of_wrappers_do_not_delete_the_story(page):
    assert html_text.main_text(html_text.parse(page), set()) == "The story."


def test_site_templates_are_removed(spark):
    kind = "page_id long, url string, html string, host string, template string"
    rows = [(k, f"http://A.example/{k}", f"<body><div><p>Welcome to our site</p></div><div><p>story {k} of many words</p></div></body>", "h", "t") for k in range(12)]
    rows += [(50 + k, f"https://b.example/{k}", f"<div><p>Welcome to our site</p></div><p>b {k}</p>", "h", "t") for k in range(3)]
    rows += [(80 + k, "http://c.example/", "<p>a copied page</p>", "h", "t") for k in range(9)]
    rows += [(99, None, None, None, None), (100, "no url", "<p>x</p>", "h", "t")]
    got = {r["page_id"]: r for r in html_text.extract(spark.createDataFrame(rows, kind)).collect()}
    assert got[3]["text"] == "story 3 of many words"
    assert got[51]["text"] == "Welcome to our site b 1"  # three pages make no template
    assert got[85]["text"] == "a copied page"  # copies of one page are one page
    assert (got[99]["text"], got[99]["n_chars"]) == ("", 0) and got[100]["text"] == "x"
    assert html_text.extract(spark.createDataFrame([], kind)).count() == 0


def test_shared_sentences_of_articles_stay(spark):
    kind = "page_id long, url string, html string"
    rows = [(k, "http://a.example/x", f"<nav><a>home</a></nav><article><p>The same first line.</p><p>story {k}</p><div><a>next</a> <a>last</a></div></article>") for k in range(20)]
    got = html_text.extract(spark.createDataFrame(rows, kind)).orderBy("page_id").first()
    assert got["text"] == "The same first line. story 0"


def test_recurring_blocks_inside_articles_go(spark):
    kind = "page_id long, url string, html string"
    notice = "<div><h3>Join us</h3><p>Write to <b>our</b> list.</p></div><section>Opinions are those of writers.</section>"
    rows = [(k, "http://a.example/x", f"<article><h1>Title {k}</h1><p>Shared <em>line</em> here.</p>{notice}<p>story {k} is <em>line</em></p></article>") for k in range(20)]
    rows += [(50 + k, "http://b.example/x", f"<nav>menu {k}</nav><main><div><p>The same article</p></div></main>") for k in range(8)]
    got = {r["page_id"]: r["text"] for r in html_text.extract(spark.createDataFrame(rows, kind)).collect()}
    assert got[4] == "Title 4 Shared line here. story 4 is line"
    assert got[52] == "The same article"  # nothing else would be left


def test_templates_of_hosts_with_copies_and_of_big_hosts(spark):
    kind = "host string, html string"
    rows = [("a", f"<div>Welcome</div><p>a {k}</p>") for k in range(30)] + [("a", "<p>one copied page</p>")] * 400
    rows += [("b", f"<div>Welcome</div><p>b {k}</p>" if k < 120 else f"<p>b {k}</p>") for k in range(1500)]
    got = {r["host"]: len(r["template"]) for r in html_text.host_templates(spark.createDataFrame(rows, kind), 5, 0.1).collect()}
    assert got == {"a": 1, "b": 1}

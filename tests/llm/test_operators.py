"""The training-data operators: brute force, exact round trips, held-out accuracy, and odd inputs."""

import math
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from twinfold.llm import ann, embed_dedup, langid, line_dedup, mixing, ngram_join, packing, quality, queries, sharding, toxicity

from conftest import same_rows

DOCS = "doc_id long, text string, lang string, source string, n_chars long, size long, label string"
BIG = (1 << 60) + 7


def odd(spark):
    """Nulls in every column, empty, blank and long texts, ties, repeated rows, columns named like results."""
    long = " ".join(f"w{i % 4000}" for i in range(30_000))
    rows = [
        (1, "one two three four five six seven eight", "en", "a", 1, 5, "x"), (1, "one two three four five six seven eight", "en", "a", 1, 5, "x"), (2, None, "en", "a", None, None, None), (3, "", None, "b", 0, 0, ""),
        (None, "one two three four five six seven eight nine", "de", None, 1, 1, "x"), (BIG, long, "fr", "b", 9, 9, "x"), (BIG + 1, long, None, None, 9, 9, "x"), (7, " \n\t\n ", "es", "c", 5, 5, "x"),
        (8, "...", "en", "c", 3, 3, "y"), (9, "1 2 3 4 5", None, "c", 9, 9, "x"), (None, None, None, None, None, None, None), (10, "two\nlines of some words here\ntwo\nlines of some words here", "en", "a", 1, 1, "x"),
    ]
    return spark.createDataFrame(rows, DOCS)


def labels(spark):
    return spark.createDataFrame([(1, 1, 0), (2, 0, 1), (None, 1, 1), (3, None, None), (BIG, 1, 0), (9, 0, 1), (9, 0, 1)], "doc_id long, quality int, toxic int")


def none(df):
    return df.where("false")


# ---- packing

def whole(spark, pieces, capacity):
    rows = pieces.collect()
    by = defaultdict(list)
    for r in rows:
        by[r["sequence_id"]].append((r["offset"], r["length"]))
    for own in by.values():
        at = 0
        for o, n in sorted(own):
            assert o == at
            at += n
        assert at <= capacity
    return rows, len(by)


def test_packing_round_trip(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    rows, n = whole(spark, queries.op1_best_fit_packing(spark, data), 1024)
    from tokenizers import Tokenizer

    slow = Tokenizer.from_file(queries.vocabulary()[0])
    got = defaultdict(list)
    for r in rows:
        got[r["doc_id"]].append((r["piece"], r["start"], r["length"], r["ids_crc32"]))
    for d in docs.collect():
        ids = np.array([*slow.encode(d["text"] or "", add_special_tokens=False).ids, 2], "<u4")
        own = sorted(got[d["doc_id"]])
        assert [p for p, *_ in own] == list(range(len(own))) and sum(x[2] for x in own) == len(ids)
        assert all(x[2] == 1024 for x in own[1:])
        for _, start, length, crc in own:
            assert crc == zlib.crc32(ids[start : start + length].tobytes())
    total = sum(r["length"] for r in rows)
    assert n <= 1.05 * -(-total // 1024) + 1


def test_both_tokenizers_agree_on_special_strings():
    fast, slow = packing._encoder(*queries.vocabulary()), packing._encoder(queries.vocabulary()[0], None)
    for t in ["a <|endoftext|> b", "", "  \n\n x", "naïve ça und so weiter 123 $$$", "don't  we'll"]:
        assert fast(t) == slow(t)


@pytest.mark.parametrize("counts", [{}, {1024: 3}, {1: 5000}, {700: 10, 324: 10}, {513: 7}, {600: 3, 400: 9, 24: 2, 1: 1}])
def test_packing_plan_places_every_piece_once(counts):
    intervals, n = packing.plan(dict(counts), 1024)
    seen, room = Counter(), defaultdict(int)
    for length, first, last, sequence, offset in intervals:
        seen[length] += last - first + 1
        for r in range(last - first + 1):
            room[sequence + r] = max(room[sequence + r], offset + length)
    assert seen == Counter(counts) and all(x <= 1024 for x in room.values()) and len(room) == n
    assert n >= -(-sum(k * v for k, v in counts.items()) // 1024)
    if counts == {700: 10, 324: 10}:
        assert n == 10


def test_packing_odd_and_empty(spark):
    rows, _ = whole(spark, packing.pack_documents(odd(spark), *queries.vocabulary()), 1024)
    assert sum(r["piece"] == 0 for r in rows) == 12 and sum(r["doc_id"] is None for r in rows) == 2
    assert {r["doc_id"] for r in rows} >= {BIG, BIG + 1}
    assert sum(r["length"] == 1 for r in rows) == 3  # null and empty texts are the end token alone
    assert packing.pack_documents(none(odd(spark)), *queries.vocabulary()).count() == 0


# ---- mixing

def test_mixing_meets_targets(spark, data):
    rows = queries.op2_entropy_mixing(spark, data).collect()
    again = queries.op2_entropy_mixing(spark, data).collect()
    assert sorted(map(tuple, rows)) == sorted(map(tuple, again))
    source = {r["doc_id"]: r["source"] for r in spark.read.parquet(f"{data}/documents.parquet").collect()}
    taken, target, size = Counter(), {}, Counter()
    for r in rows:
        assert 0 <= r["taken"] <= 2 * r["size"]
        s = source[r["doc_id"]]
        taken[s] += r["taken"]
        size[s] += r["size"]
        target[s] = r["target"]
    order = sorted(size)
    want = mixing.water_fill([size[s] for s in order], [(5, 2, 1)[i % 3] for i in range(len(order))], 1.5 * sum(size.values()), 2)
    for s, t in zip(order, want):
        assert math.isclose(target[s], t) and abs(taken[s] - t) <= max(30, 0.02 * t)


def test_water_fill():
    assert mixing.water_fill([10, 10], [1, 1], 30, 2) == [15, 15]
    assert mixing.water_fill([10, 100], [5, 1], 110, 2) == [20, 90]
    assert mixing.water_fill([0, 10], [1, 1], 10, 2) == [0, 10]
    assert mixing.water_fill([1, 1], [1, 1], 100, 2) == [2, 2]
    assert mixing.water_fill([], [], 0, 2) == []


def test_mixing_moments_tilt_rates(spark):
    """Without enough of the small ones the rates of a source fall or rise with the size, and stay within the cap."""
    d = spark.createDataFrame([(i, "ab"[i % 2], 10 + 40 * (i % 7)) for i in range(400)], "doc_id long, source string, w long")
    rows = mixing.mix(d, size=F.col("w")).collect()
    assert all(0 <= r["rate"] <= 2 and r["copies"] in (0, 1, 2) for r in rows)


def test_mixing_rates_solve_the_dual(spark, data):
    """Rates equal those of a plain solver: for a tilt b every source's multiplier by bisection, b itself by bisection on its own condition."""
    rows = queries.op2_entropy_mixing(spark, data).select("doc_id", "size", "target", "source_size", "rate").collect()
    source = {r["doc_id"]: r["source"] for r in spark.read.parquet(f"{data}/documents.parquet").collect()}
    own = defaultdict(list)
    for r in rows:
        own[source[r["doc_id"]]].append(r)
    size = np.array([r["size"] for r in rows if r["size"] > 0], float)
    mean = (size * np.log(size)).sum() / size.sum()
    spread = math.sqrt((size * np.log(size) ** 2).sum() / size.sum() - mean**2)
    live = {s: (np.array([r["size"] for r in x], float), x[0]["target"]) for s, x in own.items() if 0 < x[0]["target"] < 2 * x[0]["source_size"] * (1 - 1e-12)}
    z = {s: (np.log(np.maximum(n, 1)) - mean) / spread for s, (n, _) in live.items()}
    every = [(np.array([r["size"] for r in x], float)) for x in own.values()]
    total = sum(t for _, t in live.values())
    goal = total * sum((n * (np.log(np.maximum(n, 1)) - mean) / spread).sum() for n in every) / sum(n.sum() for n in every)

    def multiplier(s, b):
        n, target = live[s]
        lo, hi = -60.0, 60.0
        for _ in range(200):
            a = (lo + hi) / 2
            lo, hi = (a, hi) if (n * np.minimum(2, np.exp(a + b * z[s]))).sum() < target else (lo, a)
        return a

    lo, hi = -5.0, 5.0
    for _ in range(80):
        b = (lo + hi) / 2
        a = {s: multiplier(s, b) for s in live}
        slope = goal - sum((live[s][0] * np.minimum(2, np.exp(a[s] + b * z[s])) * z[s]).sum() for s in live) - 0.05 * total * b
        lo, hi = (b, hi) if slope > 0 else (lo, b)
    assert len(live) > 3
    for s in live:
        for r, zi in zip(own[s], z[s]):
            assert abs(r["rate"] - min(2, math.exp(a[s] + b * zi))) < 1e-4, (s, r)


def test_mixing_odd_and_empty(spark):
    rows = mixing.mix(odd(spark)).collect()
    assert len(rows) == 12 and all(r["taken"] <= 2 * r["size"] for r in rows) and {r["size"] for r in rows if r["text"] is None} == {0}
    assert mixing.mix(none(odd(spark))).count() == 0


# ---- n-gram join

def jaccard_truth(ids, texts, threshold=0.8):
    sets = [set(ngram_join.shingle_hashes(t).tolist()) for t in texts]
    links = [0] * len(ids)
    up = list(range(len(ids)))

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for i in range(len(ids)):
        for j in range(i):
            if sets[i] and sets[j] and len(sets[i] & sets[j]) >= threshold * len(sets[i] | sets[j]) - 1e-9:
                links[i] += 1
                links[j] += 1
                up[find(i)] = find(j)
    groups = defaultdict(list)
    for i in range(len(ids)):
        groups[find(i)].append(ids[i])
    return {ids[i]: (links[i], min(groups[find(i)])) for i in range(len(ids))}


def planted_texts(seed=1, groups=12, near=9):
    rng = np.random.default_rng(seed)
    texts = []
    for g in range(groups):
        base = [f"g{g}w{rng.integers(500)}" for _ in range(120)]
        texts.append(" ".join(base))
        for _ in range(near):
            own = list(base)
            for _ in range(rng.integers(0, 5)):
                own[rng.integers(120)] = f"x{rng.integers(10**6)}"
            texts.append(" ".join(own))
    texts += ["short one", "short one", "Short, ONE!", "", None, "tiny"]
    return texts


@pytest.mark.parametrize("small", [{}, {"leaf": 2, "block": 4, "max_depth": 3}])
def test_ngram_join_is_brute_force(spark, small):
    texts = planted_texts()
    ids = list(range(len(texts)))
    got = ngram_join.near_duplicates(spark.createDataFrame(list(zip(ids, texts)), "doc_id long, text string"), **small).collect()
    assert {r["doc_id"]: (r["n_links"], r["class_id"]) for r in got} == jaccard_truth(ids, texts)
    assert sum(r["kept"] for r in got) == len({r["class_id"] for r in got})


def test_ngram_query_on_the_table(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet").collect()
    got = queries.op3_ngram_jaccard_join(spark, data).collect()
    assert {r["doc_id"]: (r["n_links"], r["class_id"]) for r in got} == jaccard_truth([d["doc_id"] for d in docs], [d["text"] for d in docs])


def test_shingles_are_words_not_bytes():
    a, b = ngram_join.shingle_hashes("The quick, brown fox jumps over"), ngram_join.shingle_hashes("the QUICK brown   fox jumps; over")
    assert (a == b).all() and len(a) == 2 and len(ngram_join.shingle_hashes(None)) == 0 and len(ngram_join.shingle_hashes("a b")) == 1


def test_recall_sets_the_number_of_runs():
    assert ngram_join.runs_for(0.8, 2, 0.9) < ngram_join.runs_for(0.8, 2, 0.9999)


def test_ngram_odd_and_empty(spark):
    rows = ngram_join.near_duplicates(odd(spark)).collect()
    assert len(rows) == 12 and {r["doc_id"] for r in rows} >= {BIG, BIG + 1}
    big = {r["doc_id"]: r for r in rows if r["doc_id"] in (BIG, BIG + 1)}
    assert big[BIG]["n_links"] == big[BIG + 1]["n_links"] == 1 and big[BIG + 1]["class_id"] == BIG
    assert ngram_join.near_duplicates(none(odd(spark))).count() == 0


def test_long_texts_go_in_pieces(spark, monkeypatch):
    """Pieces of any size give the same shingles, subwords and word counts as the whole text at once."""
    from twinfold.llm import shared

    rng = np.random.default_rng(6)
    text = " ".join("".join(map(chr, rng.integers(97, 117, rng.integers(1, 9)))) + ("," if rng.random() < 0.1 else "") for _ in range(3000)) + "\n\u00e9t\u00e9 end"
    whole = ngram_join.shingle_hashes(text), np.sort(langid.subwords(text, 16))
    terms = toxicity.Terms(sorted(set(re.findall(r"\w+", text.lower()))))
    counts = terms.counts(text)
    assert counts[1].sum() == len(re.findall(r"\w+", text))
    for size in (7, 50, 1000):
        cut = lambda t, size=size, f=shared.pieces: f(t, size)
        for module in (ngram_join, langid, toxicity):
            monkeypatch.setattr(module, "pieces", cut)
        assert "".join(cut(text)) == text
        assert np.array_equal(ngram_join.shingle_hashes(text), whole[0]) and np.array_equal(np.sort(langid.subwords(text, 16)), whole[1])
        assert all(np.array_equal(a, b) for a, b in zip(terms.counts(text), counts))
        monkeypatch.undo()
    few = ngram_join.shingle_hashes("one two   three")
    assert len(few) == 1 and np.array_equal(few, ngram_join.shingle_hashes("One, two three!"))


def test_a_text_of_fifty_megabytes_needs_bounded_memory():
    """Beyond the text itself, its shingles' hashes and a few pieces."""
    import tracemalloc

    text = ("alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu " * 800_000)[: 50 << 20]
    model = langid.Model(["a", "b"], 16, 16, 1)
    tracemalloc.start()
    for work in (lambda: ngram_join.shingle_hashes(text), lambda: model.mean(langid.subword_blocks(text, 16)), lambda: toxicity.Terms(["alpha", "mu"]).counts(text)):
        tracemalloc.reset_peak()
        before = tracemalloc.get_traced_memory()[0]
        work()
        assert tracemalloc.get_traced_memory()[1] - before < 300e6
    tracemalloc.stop()


# ---- toxicity, quality, language

def test_block_max_index_is_exact():
    rng = np.random.default_rng(4)
    vectors = []
    for _ in range(700):
        t = rng.choice(40, rng.integers(1, 6), replace=False)
        x = rng.random(len(t))
        vectors.append({int(a): float(b) for a, b in zip(t, x / np.linalg.norm(x))})
    index = toxicity.BlockMaxIndex(vectors, np.arange(700), np.zeros(700, int), block=16)
    dense = np.zeros((700, 40))
    for i, v in enumerate(vectors):
        dense[i, list(v)] = list(v.values())
    for i in range(0, 700, 23):
        at, cosine = index.top(vectors[i], 7, without=i)
        s = dense @ dense[i]
        s[i] = -1
        want = np.lexsort((np.arange(700), -np.round(s, 12)))[:7]
        assert np.allclose(np.sort(cosine), np.sort(s[want])) and len(at) == min(7, (s > 0).sum())


def accuracy(rows, truth, threshold):
    y = np.array([truth[r["doc_id"]] for r in rows if r["held_out"] and r["doc_id"] in truth])
    p = np.array([r["predicted"] for r in rows if r["held_out"] and r["doc_id"] in truth])
    for r in rows:
        assert 0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= threshold)
        assert r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0)
    return (y == p).mean()


SF = "/root/testdata/sf0.01"


def test_toxicity_against_dense_cosine(spark):
    """The query's scores and evidence equal those of a plain dense cosine over every term, all labelled rows and all texts."""
    small = "/root/testdata/sf0.001"
    docs, lab = spark.read.parquet(f"{small}/documents.parquet"), spark.read.parquet(f"{small}/labels.parquet")
    model = toxicity.fit(docs, lab)
    truth = {r["doc_id"]: r["toxic"] for r in lab.collect()}
    text = {r["doc_id"]: r["text"] for r in docs.collect()}

    def bag(x):
        return Counter(toxicity.term(w) for w in re.findall(r"\w+", (x or "").lower()))

    bags = {i: bag(x) for i, x in text.items()}
    df = Counter(t for b in bags.values() for t in b)
    train = sorted(i for i in text if zlib.crc32(str(i).encode()) % 5 and truth.get(i) in (0, 1) and bags[i])
    rows = np.array([truth[i] for i in train])
    names = sorted({t for i in train for t in bags[i]})
    number = {t: j for j, t in enumerate(names)}
    n, p = (np.array([sum(t in bags[i] for i in ids) for t in names]) for ids in (train, [i for i in train if truth[i]]))
    base = rows.mean()
    weight = (np.abs(np.log((p + 4 * base) / (n - p + 4 * (1 - base)) * (1 - base) / base)) + 0.01) ** 2 * (np.log((len(text) + 1) / (np.array([df[t] for t in names]) + 1)) + 1)

    def dense(b):
        v = np.zeros(len(names))
        for t, c in b.items():
            if t in number:
                v[number[t]] = (1 + np.log(c)) * weight[number[t]]
        return v / (np.linalg.norm(v) or 1)

    space = np.stack([dense(bags[i]) for i in train])
    got = {r["doc_id"]: r for r in queries.op4_toxicity_neighbours(spark, small).collect()}
    assert set(got) == set(text)
    with_evidence = 0
    for i in text:
        c = space @ dense(bags[i])
        near = np.lexsort((train, -np.round(c, 6)))[:15]
        near = near[c[near] > 0]
        if not len(near):
            assert not got[i]["evidence"] and np.isclose(got[i]["score"], model.alone)
            continue
        with_evidence += 1
        w = np.minimum(c[near], 1) / (1.05 - np.minimum(c[near], 1))
        vote = (w @ rows[near] + model.prior / 2) / (w.sum() + 0.5)
        want = 1 / (1 + np.exp(-(model.curve[0] * np.log(vote / (1 - vote)) + model.curve[1])))
        assert abs(got[i]["score"] - want) < 1e-3, i
        assert np.allclose([e["cosine"] for e in got[i]["evidence"]], np.minimum(np.sort(c)[::-1][:5][: len(near)], 1), atol=1e-5)
    assert with_evidence >= 0.98 * sum(bool(b) for b in bags.values())


def test_block_maxima_leave_most_postings_unread():
    """On vectors with few heavy terms, most postings are never read, and the result stays exact."""
    rng = np.random.default_rng(8)
    weight = np.concatenate([np.full(20, 20.0), np.full(2000, 1.0), np.full(200, 0.02)])
    vectors = []
    for _ in range(6000):
        t = np.unique(np.concatenate([rng.integers(0, 20, 1), 20 + rng.integers(0, 2000, 20), 2020 + rng.integers(0, 200, 100)]))
        vectors.append((t, weight[t] / np.linalg.norm(weight[t])))
    flat = (np.array([len(t) for t, _ in vectors]), np.concatenate([t for t, _ in vectors]).astype(np.int32), np.concatenate([x for _, x in vectors]).astype(np.float32))
    index = toxicity.BlockMaxIndex(flat, np.arange(6000), np.zeros(6000, int), weight=weight)
    dense = np.zeros((6000, len(weight)))
    for i, (t, x) in enumerate(vectors):
        dense[i, t] = x
    asked = 0
    for i in range(0, 6000, 100):
        at, cosine = index.top(vectors[i], 10)
        asked += int((index.ptr[vectors[i][0] + 1] - index.ptr[vectors[i][0]]).sum())
        assert np.allclose(np.sort(cosine), np.sort(dense @ dense[i])[-10:], atol=1e-6)
    assert index.read < 0.3 * asked


def test_toxicity_on_held_out_labels(spark):
    truth = {r["doc_id"]: r["toxic"] for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    rows = queries.op4_toxicity_neighbours(spark, SF).collect()
    assert accuracy(rows, truth, 0.5) >= 0.9


TOXIC_WORDS = {"en": "gribble", "de": "schnauf", "fr": "zutalor", "es": "malvado"}


def toxic_corpus(spark, rate, n=400, seed=3):
    """Random words of four languages; toxic rows of each have its one bad word, which a few clean rows have too."""
    rng = np.random.default_rng(seed)
    docs, lab, share = [], [], {"en": 0.85, "de": 0.05, "fr": 0.05, "es": 0.05}
    for i in range(n):
        lang = str(rng.choice(list(share), p=list(share.values())))
        y = int(rng.random() < rate)
        words = [f"{lang}{chr(97 + j % 26)}{chr(97 + j // 26)}" for j in rng.integers(0, 300, 25)]
        if y or rng.random() < 0.03:
            words.insert(int(rng.integers(0, 25)), TOXIC_WORDS[lang])
        docs.append((i, " ".join(words), lang))
        lab.append((i, y))
    return spark.createDataFrame(docs, "doc_id long, text string, lang string"), spark.createDataFrame(lab, "doc_id long, toxic int"), {i: (y, d[2]) for (i, y), d in zip(lab, docs)}


def test_toxicity_learns_the_words_of_every_language(spark):
    """Each small language has far fewer toxic rows than an absolute chi-squared of 50 asks for."""
    docs, lab, truth = toxic_corpus(spark, 0.15, n=700)
    model = toxicity.fit(docs, lab)
    assert set(TOXIC_WORDS.values()) <= set(model.terms.names.to_pylist())
    train = [i for i in truth if zlib.crc32(str(i).encode()) % 5]
    assert len(model.ids) == len(train) == len(model.counts)
    got = {r["doc_id"]: r["predicted"] for r in toxicity.predict(docs.select("doc_id", "text"), lab).collect()}
    for lang in TOXIC_WORDS:
        own = [got[i] for i, (y, at) in truth.items() if y and at == lang]
        assert np.mean(own) >= 0.6, (lang, len(own))
    assert np.mean([got[i] for i, (y, _) in truth.items() if not y]) <= 0.1


@pytest.mark.parametrize("rate", [0.5, 0.75])
def test_toxicity_with_balanced_or_mostly_toxic_labels(spark, rate):
    """The common label does not swallow the other one."""
    docs, lab, truth = toxic_corpus(spark, rate)
    model = toxicity.fit(docs, lab)
    assert set(TOXIC_WORDS.values()) <= set(model.terms.names.to_pylist())
    kept = {r["doc_id"] for r in toxicity.without(docs, model).select("doc_id").collect()}
    assert np.mean([i in kept for i, (y, _) in truth.items() if not y]) >= 0.8
    assert np.mean([i in kept for i, (y, _) in truth.items() if y]) <= 0.2


def test_quality_on_held_out_labels(spark):
    truth = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    rows = queries.op6_quality_positive_unlabelled(spark, SF).collect()
    assert accuracy(rows, truth, 0.3) >= 0.88


def test_labels_of_the_held_out_fold_are_not_read(spark):
    docs, lab = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0
    swapped = lab.withColumn("toxic", F.when(held, 1 - F.col("toxic")).otherwise(F.col("toxic"))).withColumn("quality", F.when(held, 1 - F.col("quality")).otherwise(F.col("quality")))
    for op in (toxicity, quality):
        one = op.predict(docs.select("doc_id", "text"), lab).select("doc_id", "score").collect()
        two = op.predict(docs.select("doc_id", "text"), swapped).select("doc_id", "score").collect()
        assert sorted(map(tuple, one)) == sorted(map(tuple, two))


def test_class_prior_of_a_known_mixture():
    rng = np.random.default_rng(1)
    p = rng.normal(0, 1, (3000, 4))
    u = np.vstack([rng.normal(0, 1, (2100, 4)), rng.normal(4, 1, (900, 4))])
    assert abs(quality.class_prior(p, u) - 0.7) < 0.08


def test_risk_and_gradient_against_plain_versions():
    """The non-negative risk summed text by text, and its gradient by differences, on both sides of zero."""
    seen = set()
    for seed in range(12):
        rng = np.random.default_rng(seed)
        p, u = rng.normal(1, 1, (9, 5)), rng.normal(-1 if seed % 2 else 1, 1, (14, 5))
        net = quality.Network(np.vstack([p, u]), 3, seed)
        net.p = [x + rng.normal(0, 0.5, x.shape) for x in net.p]
        prior = 0.3 if seed % 3 else 0.95

        def parts():
            def out(x):
                return float(np.tanh(x @ net.p[0] + net.p[1]) @ net.p[2] + net.p[3][0])

            loss = lambda f: math.log1p(math.exp(-f))
            own = prior * sum(loss(out(x)) for x in p) / len(p)
            rest = sum(loss(-out(x)) for x in u) / len(u) - prior * sum(loss(-out(x)) for x in p) / len(p)
            return own, rest

        own, rest, g = quality.risk_gradient(net, p, u, prior)
        assert np.allclose((own, rest), parts())
        seen.add(rest >= 0)
        for k in range(4):
            for i in np.ndindex(net.p[k].shape):
                at, d = net.p[k][i], []
                for e in (1e-5, -1e-5):
                    net.p[k][i] = at + e
                    a, b = parts()
                    d.append(a + b if rest >= 0 else -b)
                net.p[k][i] = at
                assert abs((d[0] - d[1]) / 2e-5 - g[k][i]) < 1e-6
    assert seen == {True, False}


def test_language_scores_are_a_plain_forward_pass(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    model = langid.fit(docs)
    got = {r["doc_id"]: r for r in langid.predict(docs, model).collect()}
    for r in docs.limit(40).collect():
        b = (" " + re.sub(r"[\W\d_]+", " ", r["text"].lower()).strip() + " ").encode()
        total, n = np.zeros(model.embedding.shape[1]), 0
        for size in (3, 4):
            for at in range(len(b) - size + 1):
                h = 0
                for x in b[at : at + size]:
                    h = (h * 0x100000001B3 + x + size) % (1 << 64)
                total += model.embedding[(h * 0x9E3779B97F4A7C15) % (1 << 64) >> (64 - model.bits)]
                n += 1
        z = (total / n @ model.weight + model.bias) / model.temperature
        p = np.exp(z - z.max()) / np.exp(z - z.max()).sum()
        assert got[r["doc_id"]]["lang_pred"] == model.languages[int(p.argmax())] and abs(got[r["doc_id"]]["score"] - p.max()) < 1e-5


def test_language_on_held_out(spark):
    truth = {r["doc_id"]: r["lang"] for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    rows = [r for r in queries.op10_language_id(spark, SF).collect() if r["held_out"]]
    assert np.mean([truth[r["doc_id"]] == r["lang_pred"] for r in rows]) >= 0.93


def test_no_language_is_left_out_silently(spark):
    docs = spark.createDataFrame([(i, f"some words of text number {i % 3}", "abc"[i % 3]) for i in range(60)], "doc_id long, text string, lang string")
    with pytest.raises(ValueError, match="max_languages"):
        langid.fit(docs, max_languages=2)
    assert langid.fit(docs, max_languages=3, max_documents=3).languages == ["a", "b", "c"]


def test_learners_odd_and_empty(spark):
    d, lab = odd(spark), labels(spark)
    for op in (toxicity, quality):
        for x, l in ((d, lab), (d, none(lab))):
            rows = op.predict(x, l).collect()
            assert len(rows) == 12 and all(0 <= r["score"] <= 1 for r in rows) and {r["doc_id"] for r in rows} >= {BIG, BIG + 1}
        assert op.predict(none(d), lab).count() == 0
    rows = langid.identify(d).collect()
    assert len(rows) == 12
    text = {r["doc_id"]: r["text"] for r in d.collect()}
    for r in rows:
        if r["doc_id"] in (2, 3, 7, 8, 9):
            assert r["lang_pred"] == "und", text[r["doc_id"]]
    assert langid.identify(none(d)).count() == 0
    assert {r["lang_pred"] for r in langid.identify(d.withColumn("lang", F.lit(None).cast("string"))).collect()} == {"und"}


# ---- vectors

VEC = "vec_id long, embedding array<float>, label int"


def odd_vectors(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(1, [1.0, 0.0], 1), (2, [1.0, 0.0], 1), (3, [2.0, 0.1], 2), (4, [0.0, 0.0], 1), (5, None, 1), (6, [1.0, None], 1), (7, [nan, 1.0], 1), (8, [inf, 1.0], 1), (9, [0.0, 1.0], None), (9, [0.0, 1.0], 3), (20, [0.0, 3.0], 1), (40, [-1.0, 0.0], 1), (None, [1.0, 0.0], 1), (11, [1.0], 1), (12, [], 1)]
    return spark.createDataFrame(rows, VEC)


def test_vector_operators_odd_and_empty(spark):
    v = odd_vectors(spark)
    rows = ann.search(v, F.col("vec_id") % 20 == 0).orderBy("query_id", "rank").collect()
    got = defaultdict(list)
    for r in rows:
        got[r["query_id"]].append((r["vec_id"], r["score"]))
    assert [i for i, _ in got[20]] == [9, 3, 1, 2, 40] and got[20][0][1] == 3.0 and [i for i, _ in got[40]][:2] == [9, 20]
    assert ann.search(none(v), F.col("vec_id") % 20 == 0).count() == 0
    d = {r["vec_id"]: r for r in embed_dedup.near_duplicates(v).collect() if r["vec_id"] != 9}
    assert (d[1]["n_links"], d[2]["n_links"], d[3]["n_links"]) == (2, 2, 2) and d[3]["component_id"] == 1 and not d[2]["kept"] and d[1]["kept"]
    assert d[20]["n_links"] == 1 and d[20]["component_id"] == 9
    assert all(d[i]["n_links"] == 0 and d[i]["component_id"] == i and d[i]["kept"] for i in (4, 5, 6, 7, 8, 11, 12, 40))
    assert embed_dedup.near_duplicates(v).count() == 15 and embed_dedup.near_duplicates(none(v)).count() == 0


def vectors(n=1500, dim=32, seed=2):
    rng = np.random.default_rng(seed)
    x = rng.standard_normal((n, dim))
    for g in range(20):
        base = rng.standard_normal(dim)
        at = rng.choice(n, 15, replace=False)
        x[at] = base + rng.normal(0, 0.25, (15, dim))
    return x * rng.uniform(0.5, 2, (n, 1))


def test_pigeonhole_join_is_brute_force(spark):
    x = vectors()
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    u = x / np.linalg.norm(x, axis=1)[:, None]
    link = u @ u.T >= 0.9
    np.fill_diagonal(link, False)
    label = np.arange(len(x))
    while True:
        new = np.array([min([label[i], *label[link[i]]]) for i in range(len(x))])
        if (new == label).all():
            break
        label = new
    for size in ({}, {"chunk": 16, "lot": 8, "blocks": 3}):
        got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in embed_dedup.near_duplicates(df, **size).collect()}
        assert got == {i: (int(link[i].sum()), int(label[i])) for i in range(len(x))}


def test_pigeonhole_join_deals_each_vector_once(spark, monkeypatch):
    """A vector used to travel to every cell it visits, so that disk grew faster than the table."""
    x = vectors(800)
    x[400:500] = x[0]
    plans = {}

    def keep(df, name="cut", real=embed_dedup.materialise):
        plans[name] = df._jdf.queryExecution().executedPlan().toString()
        out = real(df, name)
        if name == "chunks":
            plans["held"] = sum(len(r["nodes"]) // 8 for r in out.collect())
        return out

    monkeypatch.setattr(embed_dedup, "materialise", keep)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in embed_dedup.near_duplicates(df, chunk=64, lot=128).collect()}
    assert plans["held"] == len({v.astype(np.float32).tobytes() for v in x})
    assert "Exchange" not in plans["links"] and "CartesianProduct" in plans["links"]
    y = x.astype(np.float32).astype(np.float64)
    link = (y @ y.T) / np.sqrt(np.outer((y * y).sum(1), (y * y).sum(1))) >= 0.9
    assert {i: n for i, (n, _) in got.items()} == {i: int(link[i].sum()) - 1 for i in range(len(x))}


def test_scan_recall_and_scores(spark):
    x = vectors(3000)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    got = defaultdict(list)
    for r in ann.search(df, F.col("vec_id") % 20 == 0, chunk=300).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append(r)
    hits = 0
    for q in range(0, 3000, 20):
        s = x @ x[q]
        s[q] = -np.inf
        hits += len({r["vec_id"] for r in got[q]} & set(np.lexsort((np.arange(3000), -s))[:20].tolist()))
        assert [r["rank"] for r in got[q]] == list(range(1, 21)) and all(math.isclose(r["score"], s[r["vec_id"]], rel_tol=1e-12) for r in got[q])
        assert [r["score"] for r in got[q]] == sorted((r["score"] for r in got[q]), reverse=True)
    assert hits / (150 * 20) >= 0.9


# ---- sharding

def test_sharding_law(spark, data):
    rows = queries.op7_rendezvous_sharding(spark, data).collect()
    slots = defaultdict(list)
    for r in rows:
        slots[r["shard"]].append(r["slot"])
        assert 0 <= r["shard"] < 8 and r["grown_shard"] in (r["shard"], 8)
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    text = {d["doc_id"]: (d["text"] or "").encode() for d in spark.read.parquet(f"{data}/documents.parquet").collect()}
    assert all(r["size"] == len(text[r["doc_id"]]) + 1 and r["text_crc32"] == zlib.crc32(text[r["doc_id"]]) for r in rows)


def test_sharding_follows_weights_and_loses_little(spark):
    d = spark.range(8000).select(F.col("id").alias("doc_id"), F.lit("x").alias("text"))
    one = sharding.assign(d, [1.0, 2.0, 1.0], None)
    share = {r["shard"]: r["n"] / 8000 for r in one.groupBy("shard").agg(F.count("*").alias("n")).collect()}
    assert abs(share[1] - 0.5) < 0.03 and abs(share[0] - 0.25) < 0.03 and one.where("grown_shard is not null").count() == 0
    two = sharding.assign(d, [1.0, 2.0, 0.0], None).select("doc_id", F.col("shard").alias("s2"))
    assert one.join(two, "doc_id").where("shard <> 2 and shard <> s2").count() == 0  # a shard that goes moves its own records only


def test_sharding_odd_and_empty(spark):
    rows = sharding.assign(odd(spark)).collect()
    assert len(rows) == 12 and {r["size"] for r in rows if r["text"] is None} == {1} and len({r["shard"] for r in rows if r["doc_id"] == 1}) == 1
    assert len({(r["shard"], r["slot"]) for r in rows}) == 12 and sharding.assign(none(odd(spark))).count() == 0


def test_sharding_is_plain_rendezvous_hashing(spark, data):
    """The query's shards, with eight and with nine, are the winners of the races computed in plain Python; sizes and checksums too."""
    import hashlib

    def winner(key, n):
        return min((-math.log((int(hashlib.md5(f"{key}:{i}".encode()).hexdigest()[:15], 16) + 0.5) / (1 << 60)), i) for i in range(n))[1]

    text = {r["doc_id"]: r["text"] or "" for r in spark.read.parquet(f"{data}/documents.parquet").collect()}
    rows = queries.op7_rendezvous_sharding(spark, data).collect()
    for r in rows:
        assert (r["shard"], r["grown_shard"]) == (winner(r["doc_id"], 8), winner(r["doc_id"], 9))
        assert r["text_crc32"] == zlib.crc32(text[r["doc_id"]].encode()) and r["size"] == len(text[r["doc_id"]].encode()) + 1
    for s in range(8):
        assert sorted(r["slot"] for r in rows if r["shard"] == s) == list(range(sum(r["shard"] == s for r in rows)))


#: Names that operators use themselves, in other case, with dots.
NAMES = ["_m", "_first", "Size", "_uid", "_row", "_hit", "_byte", "hit_it", "payload", "a.b", "row", "mark", "LINES", "copies_", "_s", "_c", "uid", "u"]


def test_no_column_name_disturbs_an_operator(spark, data):
    d = spark.createDataFrame([(i, f"w{i} and x{i} one two three four\nline {i}\nsame words of a line here", f"s{i % 3}") for i in range(30)], "doc_id long, text string, source string")
    wide = d.select("*", *[F.concat(F.lit(f"{k}:"), F.col("doc_id").cast("string")).alias(n) for k, n in enumerate(NAMES)])

    def check(out, taken=()):
        kept = [n for n in NAMES if n.lower() not in taken]
        assert [c for c in out.columns if c in NAMES] == kept
        for r in out.toDF(*[f"c{i}" for i in range(len(out.columns))]).collect():
            row = dict(zip(out.columns, r))
            for n in kept:
                assert row[n] == f"{NAMES.index(n)}:{row['doc_id']}", n

    check(sharding.assign(wide), {"size"})
    check(line_dedup.dedupe(wide), {"lines"})
    check(mixing.mix(wide), {"size"})
    now = wide
    for _, stage in corpus_pipeline.STAGES[:-1]:
        now = stage(spark, now, data)
        assert now.columns == wide.columns
        check(now)


# ---- line dedup

def test_line_dedup_is_its_sql(spark):
    same_rows(queries.op8_line_runs(spark, SF), queries.ORACLES["op8_line_runs"], SF)


def lines_by_force(docs, m):
    """Every run of at least m words that has occurred before goes, and blank lines between two lines that go."""
    units = {i: [(p, x.strip(" "), len(x.split())) for p, x in enumerate(t.split("\n")) if x.split()] for i, t in docs}
    first, dead = {}, defaultdict(set)
    for i, _ in sorted(docs):
        own = units[i]
        for s in range(len(own)):
            for e in range(s, len(own)):
                if sum(w for _, _, w in own[s : e + 1]) >= m:
                    key = tuple(x for _, x, _ in own[s : e + 1])
                    if first.setdefault(key, (i, s)) != (i, s):
                        dead[i].update(p for p, _, _ in own[s : e + 1])
        for (p, _, _), (q, _, _) in zip(own, own[1:]):
            if p in dead[i] and q in dead[i]:
                dead[i].update(range(p, q))
    return {i: [x for p, x in enumerate(t.split("\n")) if p not in dead[i]] for i, t in docs}


@pytest.mark.parametrize("m", [1, 2, 5, 12])
def test_line_dedup_is_brute_force(spark, m):
    rng = np.random.default_rng(m)
    pool = ["a b", "c", "", "d e f", "g h i j k l", "m", "n o p q", "  c  "]
    docs = [(i, "\n".join(pool[k] for k in rng.integers(0, len(pool), rng.integers(1, 14)))) for i in range(40)]
    got = {r["doc_id"]: r for r in line_dedup.dedupe(spark.createDataFrame(docs, "doc_id long, text string"), m).collect()}
    want = lines_by_force(docs, m)
    for i, t in docs:
        left = "" if not any(x.strip() for x in want[i]) and len(want[i]) < len(t.split("\n")) else "\n".join(want[i])
        assert got[i]["text"] == left, (m, i)
        assert got[i]["removed_lines"] == len(t.split("\n")) - len(want[i])


def test_line_dedup_odd_and_empty(spark):
    rows = line_dedup.dedupe(odd(spark)).collect()
    assert len(rows) == 12 and sum(r["text"] is None for r in rows) == 2
    by = defaultdict(list)
    for r in rows:
        by[r["doc_id"]].append(r)
    assert sorted(r["emptied"] for r in by[1]) == [False, True] and by[10][0]["text"] == "two\nlines of some words here"
    assert not by[BIG][0]["emptied"] and by[BIG + 1][0]["emptied"] and by[7][0]["text"] == " \n\t\n "
    assert line_dedup.dedupe(none(odd(spark))).count() == 0


# ---- pipeline

def test_pipeline_stages(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "line_dedup", "ngram_jaccard", "mixing", "packing"]
    now, seen = docs.withColumn("size", F.lit(3)).withColumn("payload", F.lit("p")), []
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = now
        now = corpus_pipeline.materialise(stage(spark, now, data), name)
        assert now.columns == before.columns and now.dtypes == before.dtypes
        seen.append(now.count())
    model_out = {r["doc_id"] for r in toxicity.predict(docs.select("doc_id", "text"), spark.read.parquet(f"{data}/labels.parquet")).where("predicted = 1").collect()}
    assert seen[0] == docs.count() - len(model_out)
    assert now.where("size <> 3 or payload <> 'p'").count() == 0
    rows, _ = whole(spark, corpus_pipeline.STAGES[-1][1](spark, now, data), 1024)
    assert sum(r["piece"] == 0 for r in rows) == seen[-1]


def test_pipeline_odd_documents(spark, data):
    now = odd(spark)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        now = stage(spark, now, data)
        assert now.columns == odd(spark).columns
    assert corpus_pipeline.STAGES[-1][1](spark, now, data).count() >= 0
    empty = none(odd(spark))
    for _, stage in corpus_pipeline.STAGES[:-1]:
        empty = stage(spark, empty, data)
    assert corpus_pipeline.STAGES[-1][1](spark, empty, data).count() == 0

"""Toxicity, quality rules, top-k and sharding."""

import collections
import itertools
import math
import random
import re
import zlib

import numpy as np
import pytest
from slackwater.llm import quality, sharding, topk, toxicity


# ---- toxicity ----


def plain_kernel(a, b, letters):
    def features(w):
        out = collections.Counter()
        for i in range(len(w)):
            for j in range(i + 1, len(w)):
                for k in range(j + 1, min(len(w), i + toxicity.SPAN)):
                    if w[i] in letters and w[j] in letters and w[k] in letters:
                        out[w[i] + w[j] + w[k]] += toxicity.DECAY ** (k - i + 1)
        return out

    x, y = features(a), features(b)
    own = math.sqrt(sum(v * v for v in x.values()) * sum(v * v for v in y.values()))
    return (sum(v * y[u] for u, v in x.items()) / own) ** 2 if own else 0.0


def test_kernel_equals_definition():
    landmarks = ["idiot", "worthless", "trash"]
    kernel = toxicity.SubsequenceKernel(landmarks)
    letters = set("".join(landmarks))
    words = ["idiot", "id.iot", "iidxiot", "trassh", "worth", "less", "toast", "x", "", "straw", "worthlessness"]
    at, rows = kernel.rows(words)
    found = dict(zip(at.tolist(), rows))
    for i, w in enumerate(words):
        exact = [plain_kernel(w, z, letters) for z in landmarks]
        if i in found:
            assert np.allclose(found[i], exact, atol=1e-5)
        else:
            assert max(exact) < toxicity.FLOOR**2 + 1e-6


@pytest.fixture(scope="module")
def corpus():
    rnd = random.Random(3)
    calm = ["".join(rnd.choice(["ba", "do", "ri", "ten", "mo", "lu"]) for _ in range(rnd.randint(1, 4))) for _ in range(200)]
    bad = ["stupid", "moron", "worthless"]
    texts, labels = [], []
    for i in range(400):
        words = [rnd.choice(calm) for _ in range(rnd.randint(5, 80))]
        toxic = i % 5 == 0
        if toxic:
            for _ in range(3):
                words.insert(rnd.randrange(len(words)), rnd.choice(bad))
        texts.append(" ".join(words))
        labels.append(int(toxic))
    return texts, np.array(labels)


def test_machine_tells_held_out_texts_and_bears_inserted_characters(corpus):
    texts, labels = corpus
    model = toxicity.train(texts[:300], labels[:300])
    score = model.scores(texts[300:])
    assert ((score >= 0.3) == labels[300:]).mean() > 0.97
    calm = texts[301]
    plain, noisy = model.scores([calm, calm + " stu.pid m-oron worthle*ss stuupid"])
    assert plain < 0.3 < noisy
    assert model.scores([calm + " s t u p i d  m o r o n  s t u p i d"])[0] > plain
    assert (model.scores(["", None, "  "]) < 0.3).all()


def test_toxicity_rows(spark, corpus):
    texts, labels = corpus
    docs = spark.createDataFrame([(i, t, 1.0) for i, t in enumerate(texts)] + [(None, None, 2.0), (900, "", 3.0), (1, texts[1], 4.0)], "doc_id long, text string, score double")
    marks = spark.createDataFrame([(i, int(y)) for i, y in enumerate(labels)] + [(0, 0), (None, 1), (5, None)], "doc_id long, toxic int")
    rows = toxicity.judge(docs, marks).collect()
    assert len(rows) == 403
    for r in rows:
        assert 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3)
        assert r.held_out == (r.doc_id is not None and zlib.crc32(str(r.doc_id).encode()) % 4 == 2)
    held = [(r.predicted, labels[r.doc_id]) for r in rows if r.held_out and r.doc_id < 400]
    assert np.mean([a == b for a, b in held]) > 0.95
    assert {r.score for r in toxicity.judge(docs, marks.filter("toxic = 0")).collect()} == {0.0}
    assert toxicity.judge(docs.filter("false"), marks.filter("false")).count() == 0


def test_labels_of_held_out_rows_are_not_read(spark, corpus):
    texts, labels = corpus
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    flip = lambda i, y: 1 - y if zlib.crc32(str(i).encode()) % 4 == 2 else y
    a = spark.createDataFrame([(i, int(y)) for i, y in enumerate(labels)], "doc_id long, toxic int")
    b = spark.createDataFrame([(i, int(flip(i, y))) for i, y in enumerate(labels)], "doc_id long, toxic int")
    assert {(r.doc_id, r.score) for r in toxicity.judge(docs, a).collect()} == {(r.doc_id, r.score) for r in toxicity.judge(docs, b).collect()}


# ---- quality ----

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def plain_counts(text):
    words = WORD.findall(text or "")
    windows = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    many = collections.Counter(windows)
    covered = {j for i, w in enumerate(windows) if many[w] > 1 for j in (i, i + 1, i + 2)}
    lines = [x for x in (text or "").split("\n") if WORD.search(x)]
    return len(words), sum(map(len, words)), sum((text or "").count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(covered)


def test_base_counts(spark):
    rnd = random.Random(8)
    texts = [None, "", " \n\t", "a", "a b", "a b c a b c", "x x x x x", "| | #tag\n\x0bz\n| | #tag\n", "é è ü", " wide"] + [rnd.choice([" ", "\n", "\t "]).join(rnd.choice("a b c d ef g# h".split()) for _ in range(rnd.randint(1, 90))) for _ in range(60)]
    docs = spark.createDataFrame([(i, t, rnd.choice(["en", "xx", None]), 5) for i, t in enumerate(texts)], "doc_id long, text string, lang string, n_words int")
    for r in quality.judge(docs).collect():
        wanted = plain_counts(texts[r.doc_id])
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == wanted
        assert r.base_failed == (wanted[0] < 50 or 100 * wanted[4] > 50 * wanted[0])
        assert not (r.kept and r.base_failed)
    assert quality.judge(docs.filter("false")).count() == 0


def prose(rnd, n, words=300):
    common = ["the", "of", "and", "to", "in", "is", "that", "for", "it", "as", "was", "with"]
    other = ["w" + a + b for a in "abcdefghij" for b in "klmnopqrst"]
    return [" ".join(rnd.choice(common) if rnd.random() < 0.25 else rnd.choice(other) for _ in range(words)) for _ in range(n)], common, other


def test_common_words_are_learned_by_language(spark):
    rnd = random.Random(9)
    texts, common, _ = prose(rnd, 30)
    rows = [(i, t, "en") for i, t in enumerate(texts)] + [(100 + i, "uno dos TRES " * 30, "es") for i in range(25)] + [(200, "solo", "xx"), (201, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    lists = {r.language: r.listed for r in quality.common_words(quality.by_language(docs, 20), 12).collect()}
    assert set(lists["en"]) == set(common) and lists["es"] == ["dos", "tres", "uno"] and lists["*"] == ["solo"]


def test_each_limit_rejects_what_the_other_does_not(spark):
    rnd = random.Random(1)
    texts, common, other = prose(rnd, 120)
    symbols = [" ".join(w + "###$" for w in t.split()[:150]) + " " + " ".join(rnd.choice(common) for _ in range(50)) for t in texts[:2]]
    wordless = [" ".join(rnd.choice(other) for _ in range(300)) for _ in range(2)]
    short = [" ".join(rnd.choice(other) for _ in range(55))]
    docs = spark.createDataFrame([(i, t, "en") for i, t in enumerate(texts + symbols + wordless + short)], "doc_id long, text string, lang string")
    rows = {r.doc_id: r for r in quality.judge(docs, guard_words=60).collect()}
    assert all(rows[i].kept for i in range(120)) and not any(rows[i].kept for i in range(120, 124))
    assert all(rows[i].class_distance > rows[i].class_limit and rows[i].word_distance < rows[i].word_limit for i in (120, 121))
    assert all(rows[i].class_distance < rows[i].class_limit and rows[i].word_distance > rows[i].word_limit for i in (122, 123))
    assert rows[124].word_distance > rows[124].word_limit and rows[124].kept  # fewer words than the guard
    assert 0 <= min(r.class_distance for r in rows.values()) <= max(r.word_distance for r in rows.values()) <= 1


def test_distance_of_equal_and_disjoint(spark):
    from pyspark.sql import functions as F

    lit = lambda *x: F.array(*(F.lit(float(v)) for v in x))
    row = spark.range(1).select(quality.distance(lit(0.5, 0.5), lit(0.5, 0.5)).alias("a"), quality.distance(lit(1, 0), lit(0, 1)).alias("b")).first()
    assert row.a == 0 and abs(row.b - 1) < 1e-12


# ---- top-k ----


def plain_top(rows, k=5):
    sound = [(i, [math.floor(256 * float(np.float32(x))) for x in v]) for i, v in rows if v and all(x is not None and math.isfinite(x) for x in v)]
    out = []
    for q, x in sound:
        if q % 50 == 0:
            scores = sorted((-sum(a * b for a, b in zip(x, y)), i) for i, y in sound if i != q)
            out += [(q, n + 1, i, -s) for n, (s, i) in enumerate(scores[:k])]
    return sorted(out)


def test_top_k_equals_brute_force(spark):
    rng = np.random.default_rng(4)
    rows = [(int(i), [float(x) for x in rng.normal(size=24).astype(np.float32)]) for i in range(700)]
    rows += [(1000 + i, rows[3][1]) for i in range(20)] + [(2001, None), (2002, []), (2003, [float("nan")] * 24), (2004, [None] * 24), (2005, [float("inf")] * 24)]
    vectors = spark.createDataFrame([(i, v, "x") for i, v in rows], "vec_id long, embedding array<float>, score string")
    for shard, block in ((64, 3), (100_000, 1000)):
        made = topk.top_k(vectors, vectors.filter("vec_id % 50 = 0"), shard_rows=shard, query_rows=block)
        assert sorted(tuple(r) for r in made.collect()) == plain_top(rows)


def test_top_k_few_and_none(spark):
    vectors = spark.createDataFrame([(0, [1.0, 2.0]), (1, [3.0, 1.0]), (2, [-1.0, 0.5])], "vec_id long, embedding array<float>")
    assert sorted((r["query_id"], r["rank"], r["vec_id"]) for r in topk.top_k(vectors, vectors.filter("vec_id % 50 = 0")).collect()) == [(0, 1, 1), (0, 2, 2)]
    none = vectors.filter("false")
    assert topk.top_k(none, none).count() == 0


def test_maxscore_skips_and_stays_exact():
    rng = np.random.default_rng(6)
    x = np.zeros((5000, 64))
    x[:, :4] = rng.integers(-200, 200, (5000, 4))
    x[:, 4:] = rng.integers(-3, 3, (5000, 60))
    shard, told = topk.Shard(np.arange(5000), x), topk.Shard(np.arange(5000), x)
    for q in x[:20]:
        every = x @ q
        best = np.lexsort((np.arange(5000), -every))[:5]
        for s, known in ((shard, None), (told, every[best[-1]])):
            ids, score = s.top(-1, q, 5, known)
            assert ids.tolist() == best.tolist() and score.tolist() == every[best].tolist()
    # without a known score all terms are essential; with one, few are
    assert shard.products == 20 * x.size and told.products < x.size


def test_essential_terms_follow_the_known_score():
    shard = topk.Shard(np.arange(2), np.array([[1.0, 2.0, 3.0], [0.0, 0.0, 0.0]]))
    bound = np.array([9.0, 4.0, 1.0])
    assert [shard.split(bound, m) for m in (None, 0.5, 1, 2, 5, 6, 14, 15)] == [3, 3, 3, 2, 2, 1, 1, 0]


def test_top_k_of_repeated_and_null_ids_and_huge_weights(spark):
    rows = [(0, [1.0, 2.0]), (0, [-1.0, 5.0]), (None, [9.0, 9.0]), (1, [3.0, 1.0]), (1, [3.0, 1.0]), (2, [0.5]), (3, [2.0, 2.0, 7.0])]
    vectors = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    made = [(r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in topk.top_k(vectors, vectors.filter("vec_id % 50 = 0"), shard_rows=2).orderBy("query_id", "rank").collect()]
    each = sorted((-sum(math.floor(256 * a) * math.floor(256 * b) for a, b in zip(q, x)), i) for n, q in rows if n == 0 for i, x in rows if i)
    assert made == [(0, k + 1, i, -s) for k, (s, i) in enumerate(each[:5])]
    huge = spark.createDataFrame([(i, [2.0**20 + i, 2.0**21 - i]) for i in range(60)], "vec_id long, embedding array<double>")
    assert sorted(tuple(r) for r in topk.top_k(huge, huge.filter("vec_id % 50 = 0"), shard_rows=16).collect()) == plain_top_exact([(r.vec_id, r.embedding) for r in huge.collect()])


def plain_top_exact(rows, k=5):
    vectors = [(i, [math.floor(256 * x) for x in v]) for i, v in rows]
    out = []
    for q, x in vectors:
        if q % 50 == 0:
            out += [(q, n + 1, i, -s) for n, (s, i) in enumerate(sorted((-sum(a * b for a, b in zip(x, y)), i) for i, y in vectors if i != q)[:k])]
    return sorted(out)


# ---- sharding ----


def test_shards_are_even_whole_and_numbered(spark):
    rnd = random.Random(2)
    texts = ["".join(rnd.choice("abc é") for _ in range(rnd.randint(0, 300))) for _ in range(3000)]
    texts += ["hot copy " * 9] * 1200 + ["pair"] * 2 + [None, ""]
    rows = [(i, t, f"s{i % 7}" if i % 11 else None, "en" if i % 2 else "fr", 3) for i, t in enumerate(texts)] + [(5, texts[5], "s5", "fr", 3)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, lang string, shard int")
    made = sharding.shard(docs, 40).collect()
    assert len(made) == len(rows) and {r.law for r in made} == {"bytes"}
    size, slots, homes = collections.Counter(), collections.defaultdict(list), collections.defaultdict(set)
    for r in made:
        t = texts[r.doc_id] or ""
        assert r.size == len(t.encode()) + 16 and r.text_crc32 == zlib.crc32(t.encode()) and r.grown_shard is None
        size[r.shard] += r.size
        slots[r.shard].append(r.slot)
        homes[t].add(r.shard)
    assert set(size) == set(range(40)) and max(size.values()) < 1.1 * sum(size.values()) / 40
    assert all(sorted(x) == list(range(len(x))) for x in slots.values())
    assert homes["pair"] and len(homes["pair"]) == 1 and len(homes["hot copy " * 9]) > 1
    assert sharding.shard(docs.filter("false")).count() == 0


def test_few_rows(spark):
    docs = spark.createDataFrame([(1, "a", "s", "en"), (2, "b", None, None)], "doc_id long, text string, source string, lang string")
    made = sharding.shard(docs, 40).collect()
    assert sorted(r.doc_id for r in made) == [1, 2] and all(0 <= r.shard < 40 and r.slot == 0 or r.slot == 1 for r in made)


def test_cuts_are_weighted_medians_along_the_widest_axis(spark):
    rnd = random.Random(12)
    rows = [(i, "x" * int(rnd.expovariate(0.01)), f"s{rnd.randint(0, 9)}", rnd.choice(["en", "fr", "de"])) for i in range(900)] + [(None, "whole", None, None)] * 3
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, lang string")
    placed, every = sharding.placed(docs, 7, 16)
    root = sharding.grow(placed, 7, every)
    places = placed.collect()

    def check(node, inside):
        if node.left is None:
            return
        width = {a: (max(r[a] for r in inside) >> sharding.BITS) - (min(r[a] for r in inside) >> sharding.BITS) for a in sharding.AXES}
        assert width[node.axis] == max(width.values())
        want, left = sum(r["size"] for r in inside) * (node.shards // 2) / node.shards, [r for r in inside if r[node.axis] <= node.cut]
        units = collections.Counter()
        for r in inside:
            units[r[node.axis]] += r["size"]
        sums = [0, *itertools.accumulate(units[v] for v in sorted(units))]
        assert abs(sum(r["size"] for r in left) - want) <= min(abs(x - want) for x in sums) + every / 7 * 0.001
        check(node.left, left)
        check(node.right, [r for r in inside if r[node.axis] > node.cut])

    check(root, places)
    assert len(sharding.leaves(root)) == 7


def test_dense_ranks(spark):
    ranks = sharding.dense_ranks(spark.createDataFrame([(c,) for c in "abcdeabc"] + [("",)], "v string"), "v", buckets=2).collect()
    assert sorted(r["rank"] for r in ranks) == list(range(6)) and {r["count"] for r in ranks} == {6}

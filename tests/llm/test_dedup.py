"""Line dedup, SimHash and suffix dedup against brute force."""

import hashlib
import random

import numpy as np
import pytest
import xxhash
from slackwater.llm import jaccard, line_dedup, simhash, suffix_dedup

SCHEMA = "doc_id long, text string, lang string, gone string, kept_text string, marked int, doc int"


def table(spark, rows):
    return spark.createDataFrame([(i, t, "en", "clash", "clash", 1, 2) for i, t in rows], SCHEMA)


def repetitive(seed, n=60):
    rnd = random.Random(seed)
    base = ["".join(rnd.choice("abcdefg ") for _ in range(rnd.randint(20, 250))) for _ in range(12)]
    out = []
    for _ in range(n):
        out.append("".join(rnd.choice(base)[rnd.randint(0, 15) : rnd.randint(60, 260)] + rnd.choice(["", "é", "x" * rnd.randint(0, 130)]) for _ in range(rnd.randint(0, 4))))
    return out


def plain_suffix(rows, length=100):
    seen, out = set(), {}
    for i, t in sorted(rows):
        b = (t or "").encode()
        gone = bytearray(len(b))
        for p in range(len(b) - length + 1):
            if b[p : p + length] in seen:
                gone[p : p + length] = b"\1" * length
            else:
                seen.add(b[p : p + length])
        out[i] = (len(b), sum(gone), len([x for x in bytes(gone).split(b"\0") if x]), hashlib.sha256(bytes(x for x, g in zip(b, gone) if not g)).hexdigest())
    return out


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_suffix_dedup_equals_brute_force(spark, seed):
    rows = list(enumerate(repetitive(seed))) + [(900, None), (901, ""), (902, "short"), (903, "a" * 1000), (904, "ab" * 400)]
    made = suffix_dedup.dedup(table(spark, rows).repartition(5))
    assert {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in made.collect()} == plain_suffix(rows)


def test_suffix_dedup_keeps_other_columns_and_equal_rows(spark):
    rnd = random.Random(4)
    text = "".join(rnd.choice("abcdef") for _ in range(300))
    rows = [(1, text), (1, text), (2, text), (None, text[50:250])]
    made = suffix_dedup.dedup(table(spark, rows)).collect()
    assert made[0].lang == "en"
    assert sorted((r.doc_id or -1, r.n_removed) for r in made) == [(-1, 0), (1, 200), (1, 200), (2, 300)]
    assert suffix_dedup.dedup(table(spark, rows).filter("false")).count() == 0


def test_hot_anchors_change_nothing(spark, monkeypatch):
    rnd = random.Random(11)
    passage = "".join(rnd.choice("abcdefgh ") for _ in range(150))
    rows = [(i, "".join(rnd.choice("xyz ") for _ in range(rnd.randint(30, 120))) + passage + "".join(rnd.choice("uvw ") for _ in range(rnd.randint(0, 90)))) for i in range(200)]
    docs = table(spark, rows).repartition(6)
    hot = suffix_dedup.hot_anchors(suffix_dedup.keyed(docs).select("doc", "tie", "text"), 100, every=2)
    assert len(hot) > 0
    made = docs.select("doc_id", "text")
    whole = suffix_dedup.hot_anchors
    for every in (2, 64):
        monkeypatch.setattr(suffix_dedup, "hot_anchors", lambda texts, length, every=every: whole(texts, length, every))
        found = suffix_dedup.dedup(made)
        assert {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in found.collect()} == plain_suffix(rows)


def test_lengths_that_names_cannot_cover(spark):
    for length in (63, 113):
        with pytest.raises(ValueError):
            suffix_dedup.dedup(table(spark, [(1, "x")]), length=length)


@pytest.mark.parametrize("most", [300, 2000, 1 << 20])
def test_index_blocks_split_hot_anchors(most):
    rnd = np.random.default_rng(7)
    base = rnd.integers(97, 101, 300).astype(np.uint8)
    texts = [np.concatenate([rnd.integers(97, 99, rnd.integers(0, 40)), base[rnd.integers(0, 40) : rnd.integers(150, 300)], rnd.integers(97, 99, rnd.integers(0, 40))]).astype(np.uint8) for _ in range(80)]
    offsets = np.concatenate([[0], np.cumsum([len(t) for t in texts])])
    text, start, n, off, key, name = suffix_dedup.phrases(np.concatenate(texts), offsets, 100)
    rows = suffix_dedup.Rows(key, name, text.astype(np.int64), np.zeros(len(text), np.int64), start, n, off)
    rows = rows.of(np.lexsort((rows.start, rows.doc, rows.key)))
    size = rows.n + 99
    begin = offsets[rows.doc] + rows.start
    data = np.concatenate(texts)[suffix_dedup.ranges(begin, begin + size)]
    found = set()
    for part, block, ends, times in suffix_dedup.index_blocks(rows, data, np.concatenate([[0], np.cumsum(size)]), 100, most, np.ones(len(rows), np.int64)):
        phrase, place = suffix_dedup.RunLengthIndex(block, ends, 100, times).stream()
        found |= set(zip(part.doc[phrase].tolist(), (part.start[phrase] + place).tolist()))
    seen, wanted = set(), set()
    for i, t in enumerate(texts):
        for p in range(len(t) - 99):
            w = t[p : p + 100].tobytes()
            wanted |= {(i, p)} if w in seen else set()
            seen.add(w)
    assert found == wanted


def test_run_length_index_counts_patterns():
    phrases = [b"banana", b"ananas", b"bandana", b"", b"aaaa"]
    data = np.frombuffer(b"".join(phrases), np.uint8)
    index = suffix_dedup.RunLengthIndex(data, np.cumsum([0, *map(len, phrases)]), 7)
    for pattern in (b"a", b"ana", b"ban", b"nd", b"aaaa", b"x", b"anas", b"dana"):
        assert index.count(pattern) == sum(p.startswith(pattern, i) for p in phrases for i in range(len(p)))
    assert index.heads.size < index.rows
    twice = suffix_dedup.RunLengthIndex(data, np.cumsum([0, *map(len, phrases)]), 7, np.array([2, 1, 1, 3, 5]))
    assert twice.heads.size == index.heads.size and twice.rows == sum(k * (len(p) + 1) for k, p in zip((2, 1, 1, 3, 5), phrases, strict=True))
    assert [twice.count(x) for x in (b"ana", b"a", b"ban")] == [2 * 2 + 2 + 1, 6 + 3 + 3 + 20, 3]


def plain_lines(rows, min_words=1):
    seen, out = set(), {}
    for i, t in sorted(rows):
        raw = t.split("\n")
        lines = [(k, x.strip(" \t\n\x0b\x0c\r")) for k, x in enumerate(raw) if x.strip(" \t\n\x0b\x0c\r")]
        gone, new = set(), set()
        for k in range(len(lines)):
            for h in (1, 2):
                w = tuple(x for _, x in lines[k : k + h])
                if len(w) == h and w in seen and (h == 2 or len(w[0].split()) >= min_words):
                    gone |= {lines[j][0] for j in range(k, k + h)}
                if len(w) == h:
                    seen.add(w)
        out[i] = (len(lines), len(gone), "\n".join(x for k, x in enumerate(raw) if k not in gone))
    return out


@pytest.mark.parametrize("seed", [1, 2])
def test_line_dedup_equals_brute_force(spark, seed):
    rnd = random.Random(seed)
    pool = ["l" + str(k) for k in range(25)] + ["w " * 25 + str(k) for k in range(4)] + ["", "  ", " l1 "]
    rows = [(i, "\n".join(rnd.choice(pool) for _ in range(rnd.randint(1, 20)))) for i in range(60)] + [(77, ""), (78, "same\n" * 40)]
    made = {r.doc_id: (r.n_lines, r.n_removed, r.kept_text) for r in line_dedup.dedup_lines(table(spark, rows).repartition(4)).collect()}
    assert made == plain_lines(rows)


def test_line_dedup_edges(spark):
    rows = [(1, "a\nb\nc"), (1, "a\nb\nc"), (2, None), (3, "x\na\nb\ny"), (None, "q\nr")]
    made = line_dedup.dedup_lines(table(spark, rows)).collect()
    got = sorted((r.doc_id or -1, r.n_removed, r.kept_text or "") for r in made)
    assert got == [(-1, 0, "q\nr"), (1, 0, "a\nb\nc"), (1, 0, "a\nb\nc"), (2, 0, ""), (3, 2, "x\ny")]
    assert made[0].lang == "en"
    assert line_dedup.dedup_lines(table(spark, rows).filter("false")).count() == 0
    assert line_dedup.dedup_lines(table(spark, [(1, "only"), (2, "one")])).count() == 2


def test_texts_do_not_depend_on_lengths(spark):
    rows = [(1, "a b\nc\nd"), (2, "x\na b\nc\nd"), (2, None), (3, "c\nd\nc\nd\n\nalone"), (4, ""), (5, "a b")]
    with_, without = (line_dedup.dedup_lines(table(spark, rows), lengths=x) for x in (True, False))
    assert without.columns == [c for c in with_.columns if c != "longest_run"]
    assert sorted(map(str, without.collect())) == sorted(map(str, with_.drop("longest_run").collect()))
    assert line_dedup.dedup_lines(table(spark, rows).filter("false"), lengths=False).columns == without.columns


def test_longest_runs_are_true(spark):
    lines = [f"line {k}" for k in range(40)]
    rows = [(1, "\n".join(lines)), (2, "\n".join(["new"] + lines[5:38] + ["end"])), (3, "\n".join(lines[:7] + lines[20:33])), (4, "a\n" * 11)]
    made = {r.doc_id: r.longest_run for r in line_dedup.dedup_lines(table(spark, rows)).collect()}
    assert made == {1: 0, 2: 33, 3: 13, 4: 10}


@pytest.mark.parametrize("seed", [3, 4])
def test_ranks_are_in_the_order_of_suffixes_and_runs_equal_brute_force(spark, seed):
    rnd = random.Random(seed)
    rows = [(i, [rnd.choice("abc") + str(rnd.randint(0, 1)) for _ in range(rnd.randint(1, 25))]) for i in range(14)]
    lines = line_dedup.line_places(table(spark, [(i, "\n".join(x)) for i, x in rows]))
    ids = {(r.doc_id, r.pos): (r.id, r.more) for r in lines.collect()}
    suffix = {(i, p): [ids[i, q] for q in range(p, len(x))] for i, x in rows for p in range(len(x))}
    levels = line_dedup.suffix_levels(lines)
    for k, level in enumerate(levels):
        found = {(r.doc_id, r.pos): r["rank"] for r in level.collect()}
        heads = {p: s[: 1 << k] for p, s in suffix.items() if len(s) >= 1 << k}
        assert set(found) == {p for p, h in heads.items() if list(heads.values()).count(h) > 1}
        order = sorted({tuple(heads[p]) for p in found})
        assert all(order[rank] == tuple(heads[p]) for p, rank in found.items())

    def common(a, b):
        return next((k for k, (x, y) in enumerate(zip(a, b)) if x != y), min(len(a), len(b)))

    wanted = {p: max((common(suffix[p], suffix[q]) for q in suffix if q < p), default=0) for p in suffix}
    assert {(r.doc_id, r.pos): r.run for r in line_dedup.longest_runs(levels).collect()} == {p: n for p, n in wanted.items() if n}


def plain_fingerprint(text, words=4):
    tokens = (text or "").encode().lower().split()
    if not tokens:
        return 0
    shingles = [b" ".join(tokens[i : i + words]) for i in range(max(1, len(tokens) - words + 1))]
    hashes = [xxhash.xxh64_intdigest(s, 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def plain_components(rows, budget=4):
    prints = [plain_fingerprint(t) for _, t in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if (prints[i] ^ prints[j]).bit_count() <= budget:
                a, b = sorted((find(i), find(j)))
                root[b] = a
    least = {}
    for i, (d, _) in enumerate(rows):
        least[find(i)] = min(d, least.get(find(i), d))
    return sorted((d, f"{p:016x}", least[find(i)]) for i, ((d, _), p) in enumerate(zip(rows, prints)))


def test_simhash_equals_brute_force(spark):
    rnd = random.Random(9)
    words = ["w" + str(k) for k in range(300)]
    rows = []
    for i in range(40):
        base = [rnd.choice(words) for _ in range(rnd.randint(1, 200))]
        for _ in range(rnd.randint(1, 5)):
            copy = list(base)
            for _ in range(rnd.randint(0, 3)):
                copy[rnd.randrange(len(copy))] = rnd.choice(words)
            rows.append((len(rows) * 3 % 1009, " ".join(copy)))
    rows += [(2001, ""), (2002, None), (2003, " \n"), (2004, "one"), (2005, "ONE"), (2006, "É é")]
    made = sorted(tuple(r) for r in simhash.near_duplicates(table(spark, rows)).collect())
    assert made == plain_components(rows)
    assert simhash.near_duplicates(table(spark, rows).filter("false")).count() == 0


def test_trie_join_finds_all_links_of_clusters():
    rnd = np.random.default_rng(2)
    centres = rnd.integers(0, 1 << 63, 40, dtype=np.uint64) * np.uint64(2)
    a = np.unique(np.concatenate([c ^ (np.uint64(1) << rnd.integers(0, 64, 60, dtype=np.uint64)) ^ (np.uint64(1) << rnd.integers(0, 64, 60, dtype=np.uint64)) for c in centres]))
    b = np.unique(a[::3] ^ (np.uint64(1) << rnd.integers(0, 64, len(a[::3]), dtype=np.uint64)))

    def groups(values, u, v):
        at = {x: i for i, x in enumerate(values.tolist())}
        return simhash.labels_of(np.array([at[x] for x in u.tolist()], int), np.array([at[x] for x in v.tolist()], int), len(values))

    def all_pairs(x):
        i, j = np.nonzero(np.bitwise_count(x[:, None] ^ x[None, :]) <= 4)
        return simhash.labels_of(i, j, len(x))

    assert (groups(a, *simhash.close_links(a, None, 4)) == all_pairs(a)).all()
    assert (groups(a, *simhash.close_links(a, None, 4, most=50)) == all_pairs(a)).all()
    whole, sliced = (sorted(map(tuple, np.concatenate(list(simhash.node_pairs(a, a, 4, 8, m))).tolist())) for m in (1 << 18, 3))
    assert whole == sliced
    both = np.unique(np.concatenate([a, b]))
    links = [simhash.close_links(a, None, 4), simhash.close_links(b, None, 4), simhash.close_links(a, b, 4)]
    assert (groups(both, *(np.concatenate(x) for x in zip(*links))) == all_pairs(both)).all()


def test_many_ranges_give_the_same_components(spark):
    rnd = np.random.default_rng(3)
    centres = rnd.integers(-(1 << 62), 1 << 62, 60)
    bits = np.unique(np.concatenate([centres ^ (np.int64(1) << rnd.integers(0, 63, 60)) for _ in range(6)]))
    nodes = spark.createDataFrame([(int(x),) for x in bits], "bits long")
    for least, aim in ((10, 1 << 17), (100, 10), (10_000, 10_000)):
        edges = simhash.links(nodes, 4, least=least, aim=aim)
        made = {r.node: r.root for r in simhash.components(edges).collect()}
        i, j = np.nonzero(np.bitwise_count(bits.view(np.uint64)[:, None] ^ bits.view(np.uint64)[None, :]) <= 4)
        label = simhash.labels_of(i, j, len(bits))
        assert all(made.get(int(x), int(x)) == int(bits[label[k]]) for k, x in enumerate(bits))


def test_keep_first_keeps_one_of_each_group(spark):
    text = " ".join("w" + str(k) for k in range(300))
    rows = [(5, text), (3, text + " tail"), (9, "another text altogether with its own words here"), (3, text + " tail"), (7, ""), (8, None), (None, text)]
    made = simhash.keep_first(table(spark, rows)).collect()
    assert sorted(r.doc_id for r in made) == [3, 7, 9] and made[0].lang == "en"


def test_components_of_a_path(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(60)] + [(200, 201)], "u long, v long").repartition(4)
    made = {r.node: r.root for r in simhash.components(edges).collect()}
    assert {made.get(k, k) for k in range(61)} == {0} and made[201] == 200


def test_near_stage_drops_exactly_what_is_similar(spark):
    import corpus_pipeline

    rnd = random.Random(21)
    words = ["w" + str(k) for k in range(400)]
    texts, shared = [], [rnd.choice(words) for _ in range(40)]
    for _ in range(30):
        base = [rnd.choice(words) for _ in range(rnd.randint(3, 160))] + shared
        for _ in range(rnd.randint(1, 4)):
            copy = list(base)
            for _ in range(rnd.randint(0, len(copy) // 25)):
                copy[rnd.randrange(len(copy))] = rnd.choice(words)
            texts.append(" ".join(copy))
    hot = [rnd.choice(words) for _ in range(120)]
    for _ in range(60):
        texts.append(" ".join(rnd.choice(words) if rnd.random() < 0.012 else w for w in hot))
    rows = list(enumerate([*texts, "", None, "one", "ONE", "one two"]))

    def shingles(t):
        w = (t or "").lower().split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    sets, root, apart = [shingles(t) for _, t in rows], list(range(len(rows))), 0
    for i in range(len(rows)):
        for j in range(i):
            if sets[i] == sets[j] or 10 * len(sets[i] & sets[j]) >= 8 * len(sets[i] | sets[j]):
                apart += (plain_fingerprint(rows[i][1], 5) ^ plain_fingerprint(rows[j][1], 5)).bit_count() > 4
                a, b = sorted((root[i], root[j]))
                root = [a if r == b else r for r in root]
    assert apart > 20
    made = corpus_pipeline.drop_near_copies(spark, table(spark, rows).repartition(5), "")
    assert sorted(r.doc_id for r in made.collect()) == sorted(set(root))
    assert corpus_pipeline.drop_near_copies(spark, table(spark, rows).filter("false"), "").count() == 0


@pytest.mark.parametrize("dense", [1, 3, 100])
def test_overlaps_and_block_links_equal_brute_force(spark, dense):
    rnd = random.Random(5)
    core = list(range(40))
    sets = [sorted(set(rnd.sample(core, rnd.randint(30, 40)) + [rnd.randint(100, 10**6) for _ in range(rnd.randint(0, 6))])) for _ in range(90)]
    flat, member = np.array([x for s in sets for x in s]), np.repeat(np.arange(90), [len(s) for s in sets])
    a, b = np.arange(0, 50), np.arange(30, 90)
    assert (jaccard.overlaps(flat, member, a, b, dense, 7) == [[len(set(sets[i]) & set(sets[j])) for j in b] for i in a]).all()
    held = spark.createDataFrame([(i, len(s), s) for i, s in enumerate(sets)], "node long, n long, x array<long>")
    lists = held.select(held.n * 0, "node", "n").toDF("list", "node", "n")
    near = [(i, j) for i in range(90) for j in range(i) if 10 * len(set(sets[i]) & set(sets[j])) >= 8 * len(set(sets[i]) | set(sets[j]))]
    u, v = np.array(near).T
    found = [(r.u, r.v) for r in jaccard.block_links(lists, held, 80, members=20).collect()]
    x, y = np.array(found).T
    assert (simhash.labels_of(u, v, 90) == simhash.labels_of(x, y, 90)).all() and len(set(simhash.labels_of(u, v, 90))) > 5


def test_matching_statistics_equal_brute_force():
    rnd = random.Random(3)
    base = bytes(rnd.choice(b"ab") for _ in range(60))
    texts = [base[rnd.randint(0, 20) : rnd.randint(30, 60)] + bytes(rnd.choice(b"abc") for _ in range(rnd.randint(0, 9))) for _ in range(40)] + [b"", b"a", base, base]
    index = suffix_dedup.RunLengthIndex(np.frombuffer(b"".join(texts), np.uint8), np.cumsum([0, *map(len, texts)]), 7)
    places = [(i, p) for i, t in enumerate(texts) for p in range(len(t))]

    def common(a, b):
        return next((k for k, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), min(len(a), len(b)))

    wanted = [max(common(texts[i][p:], texts[j][q:]) for j, q in places if (i, p) != (j, q)) for i, p in places]
    assert index.statistics(np.array([i * index.width + p for i, p in places])).tolist() == wanted
    earlier, seen = [], set()
    for i, p in places:
        w = texts[i][p : p + 7]
        earlier += [(i, p)] if len(w) == 7 and w in seen else []
        seen.add(w)
    assert list(zip(*(x.tolist() for x in index.stream()), strict=True)) == earlier


def test_index_of_copies_is_as_large_as_its_runs():
    rnd = np.random.default_rng(8)
    base = rnd.integers(97, 123, 300).astype(np.uint8)
    arrays = lambda copies: [x for x in vars(suffix_dedup.RunLengthIndex(np.tile(base, copies), np.arange(copies + 1) * 300, 100)).values() if isinstance(x, np.ndarray)]
    few, many = ({max(map(len, arrays(copies)))} for copies in (10, 100))
    assert max(many) <= max(few) + 2 * 90 < 1000  # a run for each phrase's start and end, none for its 300 bytes


def test_marks_rest_on_bytes_not_on_names(spark, monkeypatch):
    rows = list(enumerate(repetitive(6)))
    whole = suffix_dedup.phrases
    monkeypatch.setattr(suffix_dedup, "phrases", lambda *a: (*whole(*a)[:5], whole(*a)[5] * 0 + 7))
    batch = suffix_dedup.fill(["doc", "tie", "text"], ["int64", "int64", "string"], [[i for i, _ in rows], [0] * len(rows), [t for _, t in rows]])
    dealt = list(suffix_dedup.find_phrases(100)([batch]))
    marks = [(d, a >> 16, n >> 32) for b in dealt for n, d, a in zip(*(b.column(c).to_pylist() for c in (1, 2, 3)), strict=True) if a & 1]
    seen = {}
    for i, t in rows:
        for p in range(len(t.encode()) - 99):
            seen.setdefault(t.encode()[p : p + 100], (i, p))
    assert marks and all(seen[rows[d][1].encode()[p : p + 100]] < (d, p) for d, s, n in marks for p in range(s, s + n))


def test_most_marks_come_through_the_index(spark):
    rows = [(i, t) for i, t in enumerate(repetitive(9, 120))]
    docs = suffix_dedup.keyed(table(spark, rows)).select("doc", "tie", "text").repartition(24)
    notes = docs.mapInArrow(suffix_dedup.find_phrases(100), suffix_dedup.DEALT)
    own = notes.filter("at % 2 = 1").selectExpr("sum(shiftright(name, 32)) as n").first()["n"] or 0
    seen, every = set(), 0
    for _, t in rows:
        for p in range(len(t.encode()) - 99):
            every += t.encode()[p : p + 100] in seen
            seen.add(t.encode()[p : p + 100])
    assert own < every / 2

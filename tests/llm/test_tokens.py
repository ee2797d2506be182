"""Packing, id matrices and prefix BPE against the libraries and plain definitions."""

import hashlib
import random
import zlib

import numpy as np
import public_tokenizers as P
import pytest
import regex
from slackwater.llm import binary_output, packing, prefix_bpe
from slackwater.llm.common import rank_encoding, ranks_of

RANKS = P.path("byte_bpe_50k.tiktoken")
ODD = ["", None, " ", "a", "héllo wörld", "x" * 5000, "don't   stop\n\n\n now", "日本語 テキスト", "\u0085  ", "🙂" * 40, "the cat " * 900, "tab\tnew\x0bline\x0c", "a<|endoftext|> b"]


def docs(spark, texts, schema="doc_id long, text string, lang string, ids string, sequence_id long"):
    return spark.createDataFrame([(i, t, None, "clash", 7) for i, t in enumerate(texts)], schema)


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    tokenizer.encode_special_tokens = True  # such strings are ordinary text
    return tokenizer


@pytest.fixture(scope="module")
def encoder():
    return prefix_bpe.PrefixEncoder(ranks_of(RANKS))


def check_pieces(rows, ids, room=1024):
    by_doc, by_sequence = {}, {}
    for r in rows:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_sequence.setdefault(r.sequence_id, []).append(r)
    assert set(by_doc) == set(ids)
    for d, pieces in by_doc.items():
        at = 0
        for r in sorted(pieces, key=lambda r: r.start):
            assert r.start == at and r.length > 0 and r.doc_tokens == len(ids[d])
            assert r.ids_crc32 == zlib.crc32(ids[d][at : at + r.length].tobytes())
            at += r.length
        assert at == len(ids[d])
    for pieces in by_sequence.values():
        at = 0
        for r in sorted(pieces, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at == pieces[0].sequence_tokens <= room and (at == room or at & (at - 1) == 0)


def test_packing_holds_every_id_once(spark, library):
    texts = ODD + ["word " * n for n in range(1, 300, 7)]
    rows = packing.pack(docs(spark, texts).repartition(3), RANKS, P.PATTERN).collect()
    check_pieces(rows, {i: np.array(library.encode(t or "", add_special_tokens=False).ids + [0], "<u4") for i, t in enumerate(texts)})


def test_packing_balances_cost():
    rng = np.random.default_rng(3)
    lengths = rng.integers(1, 400, 4000)
    total = int(lengths.sum()) // 1024 * 1024
    lengths = np.append(lengths[np.cumsum(lengths) <= total], 0)
    lengths[-1] = total - lengths[:-1].sum()
    lengths = lengths[lengths > 0]
    rooms = packing.room_sizes(int(lengths.sum()), 1024)
    model = packing.CostModel()

    def spread(rows):
        cost = np.zeros(len(rooms))
        for _, _, n, s, _ in rows:
            cost[s] += model.of(float(n))
        return cost.max() / cost.mean()

    rows = packing.balance(lengths, rooms, model)
    assert sum(r[2] for r in rows) == lengths.sum()
    first_fit, s, used = [], 0, 0
    for i, n in enumerate(lengths):  # end to end, in the order given
        left = int(n)
        while left:
            k = min(left, int(rooms[s]) - used)
            first_fit.append((i, 0, k, s, used))
            used, left = used + k, left - k
            if used == rooms[s]:
                s, used = s + 1, 0
    assert spread(rows) < spread(first_fit)


def test_empty_tables(spark):
    none = docs(spark, ["x"]).filter("false")
    assert packing.pack(none, RANKS, P.PATTERN).count() == 0
    assert binary_output.matrices(none, RANKS, P.PATTERN).count() == 0
    assert prefix_bpe.encode(none, RANKS, P.PATTERN).count() == 0


def test_room_tree_is_best_fit():
    rnd = random.Random(5)
    lengths = [rnd.randint(1, 100) for _ in range(400)]
    rows = binary_output.best_fit(lengths, 100)
    free, plain = [], []
    for i in sorted(range(len(lengths)), key=lambda i: -lengths[i]):
        fits = [(f, r) for r, f in enumerate(free) if f >= lengths[i]]
        if fits:
            r = min(fits)[1]
        else:
            r = len(free)
            free.append(100)
            plain.append([])
        free[r] -= lengths[i]
        plain[r].append(i)
    assert sorted(i for r in rows for i in r) == list(range(len(lengths)))
    assert len(rows) == len(plain) and sorted(sum(lengths[i] for i in r) for r in rows) == sorted(sum(lengths[i] for i in r) for r in plain)


def test_matrices_round_trip(spark, library, tmp_path):
    texts = ODD + ["one two three " * n for n in (1, 3, 400)]
    made = binary_output.matrices(docs(spark, texts), RANKS, P.PATTERN, end_id=50256)
    path = f"file://{tmp_path}/packed"
    binary_output.write_matrices(made, path)
    parts = {}
    for r in spark.read.parquet(path).collect():
        ids = np.frombuffer(bytes(r.ids), "<u2")
        assert len(ids) == 1024 and r.n_tokens + r.n_padding == 1024 and (ids[r.n_tokens :] == 0).all()
        assert r.cu_seqlens[0] == 0 and r.cu_seqlens[-1] == r.n_tokens and r.position_resets == r.cu_seqlens[:-1]
        for d, start, a, b in zip(r.doc_ids, r.starts, r.cu_seqlens, r.cu_seqlens[1:]):
            parts.setdefault(d, []).append((start, ids[a:b].tolist()))
    for i, t in enumerate(texts):
        assert [x for _, p in sorted(parts[i]) for x in p] == library.encode(t or "", add_special_tokens=False).ids + [50256]


def test_prefix_bpe_equals_library(spark):
    rnd = random.Random(1)
    texts = ODD + ["".join(rnd.choice("aabcdeinrst  théß.,0\n") for _ in range(rnd.randint(1, 60))) for _ in range(300)]
    library = rank_encoding(RANKS, P.PATTERN)
    for r in prefix_bpe.encode(docs(spark, texts), RANKS, P.PATTERN).collect():
        text = texts[r.doc_id] or ""
        ids = library.encode_ordinary(text)
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(text.encode()).hexdigest())


def test_every_prefix_has_its_encoding(encoder):
    library = rank_encoding(RANKS, P.PATTERN)
    for word in ("internationalisation", " unbelievable", "aaaaaaaaaaaa", "Donaudampfschiff"):
        table = encoder.extend(word.encode(), [])
        for n in range(1, len(word) + 1):
            assert encoder.read(table, n) == library.encode_ordinary(word[:n])


def test_edits_redo_little(encoder):
    library = rank_encoding(RANKS, P.PATTERN)
    rnd = random.Random(2)
    text = " ".join("".join(rnd.choice("abcdeinorst") for _ in range(rnd.randint(1, 9))) for _ in range(400))
    t = prefix_bpe.EditableText(encoder, P.PATTERN, text)
    for _ in range(200):
        a = rnd.randint(0, len(t.text))
        b = min(len(t.text), a + rnd.choice([0, 0, 1, 3, 10]))
        t.replace(a, b, "".join(rnd.choice("ab '  \ns1.") for _ in range(rnd.randint(0, 4))))
        assert t.ids() == library.encode_ordinary(t.text)
        assert t.redone < 20
    for _ in range(50):
        t.append(rnd.choice(["x", " y", "  ", "'s", "\n"]))
        assert t.ids() == library.encode_ordinary(t.text)


def test_pretokens_join_to_the_text():
    for t in ODD:
        assert "".join(regex.findall(P.PATTERN, t or "")) == (t or "")

"""Null ids, null and very long texts, repeated rows and clashing columns for every operator on texts."""

import public_tokenizers as P
from slackwater.llm import binary_output, line_dedup, packing, prefix_bpe, quality, sharding, simhash, suffix_dedup, toxicity

RANKS = P.path("byte_bpe_50k.tiktoken")
LONG = "many words follow one another here " * 20_000


def docs(spark):
    rows = [(None, "no id"), (None, None), (1, None), (2, ""), (3, "same text"), (3, "same text"), (4, "same text"), (5, LONG), (6, LONG + "end")]
    return spark.createDataFrame([(i, t, None, None, "clash", 1.5, "x") for i, t in rows], "doc_id long, text string, lang string, source string, bits string, size double, words string")


def ids(rows):
    return sorted((r.doc_id for r in rows), key=lambda i: -1 if i is None else i)


ALL = [None, None, 1, 2, 3, 3, 4, 5, 6]


def test_packing(spark):
    rows = packing.pack(docs(spark), RANKS, P.PATTERN).collect()
    assert set(ids(rows)) == set(ALL) and all(r.sequence_tokens <= 1024 for r in rows)


def test_matrices(spark):
    rows = binary_output.matrices(docs(spark), RANKS, P.PATTERN).collect()
    assert {d for r in rows for d in r.doc_ids} == set(ALL) and all(len(r.ids) == 2048 for r in rows)


def test_prefix_bpe(spark):
    rows = prefix_bpe.encode(docs(spark), RANKS, P.PATTERN).collect()
    assert ids(rows) == ALL and {r.n_tokens for r in rows if r.doc_id in (1, 2)} == {0}


def test_line_dedup(spark):
    rows = line_dedup.dedup_lines(docs(spark)).collect()
    assert ids(rows) == ALL and {r.bits for r in rows} == {"clash"}


def test_toxicity(spark):
    labels = spark.createDataFrame([(3, 1), (4, 0), (None, None)], "doc_id long, toxic int")
    rows = toxicity.judge(docs(spark), labels).collect()
    assert ids(rows) == ALL and all(0 <= r.score <= 1 for r in rows)


def test_quality(spark):
    rows = quality.judge(docs(spark)).collect()
    assert ids(rows) == ALL and all(r.base_failed and not r.kept for r in rows if r.doc_id in (None, 1, 2, 3, 4))
    assert {r.n_repeat_words for r in rows if r.doc_id == 5} == {120_000}


def test_sharding(spark):
    rows = sharding.shard(docs(spark), 4).collect()
    assert ids(rows) == ALL and all(0 <= r.shard < 4 for r in rows)
    for s in {r.shard for r in rows}:
        assert sorted(r.slot for r in rows if r.shard == s) == list(range(sum(r.shard == s for r in rows)))
    assert len({r.shard for r in rows if r.doc_id in (3, 4)}) == 1


def test_simhash(spark):
    rows = simhash.near_duplicates(docs(spark)).collect()
    assert ids(rows) == ALL
    groups = {(r.doc_id, r.component_id) for r in rows}
    assert {(1, 1), (2, 1), (3, 3), (4, 3), (5, 5), (None, 1), (None, None)} <= groups


def test_suffix_dedup(spark):
    rows = suffix_dedup.dedup(docs(spark)).collect()
    assert ids(rows) == ALL and {r.bits for r in rows} == {"clash"}
    by = {r.doc_id: r for r in rows}
    assert by[5].n_removed == len(LONG) - 35 and by[6].n_removed == len(LONG) and by[3].n_removed == 0

"""The pipeline on a given table: every stage's own contract."""

import collections

import pytest
from slackwater.llm.common import documents, scratch

corpus_pipeline = pytest.importorskip("corpus_pipeline")


@pytest.fixture(scope="module")
def stages(spark, sf):
    docs = scratch(documents(spark, sf))
    out = [docs]
    for _, stage in corpus_pipeline.STAGES:
        docs = scratch(stage(spark, docs, sf))
        out.append(docs)
    return out


def test_columns_and_rows(stages):
    for before, after in zip(stages[:-2], stages[1:-1]):
        assert after.columns == before.columns and 0 < after.count() <= before.count()
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "line dedup", "near-dedup", "suffix-array dedup", "packing"]


def test_line_stage_changes_texts_alone(stages):
    before, after = ({r.doc_id: r for r in s.collect()} for s in stages[1:3])
    assert before.keys() == after.keys()
    assert all(r.n_chars == len(r.text) <= len(before[d].text) for d, r in after.items())
    lines = collections.Counter(x for r in after.values() for x in set(r.text.split("\n")) if len(x.split()) >= 20)
    assert max(lines.values(), default=1) == 1


def test_near_stage_keeps_one_of_each_group(stages, spark):
    from slackwater.llm import simhash

    before = simhash.near_duplicates(stages[2], words=5)
    wanted = {r[0] for r in before.select("component_id").distinct().collect()}
    assert {r.doc_id for r in stages[3].collect()} == wanted
    assert simhash.near_duplicates(stages[3], words=5).filter("doc_id <> component_id").count() == 0


def test_suffix_stage_leaves_no_repeat_of_whole_windows(stages):
    seen, again = set(), 0
    first = {r.doc_id: (r.text or "").encode() for r in stages[3].collect()}
    kept = {r.doc_id: (r.text or "").encode() for r in stages[4].collect()}
    assert first.keys() == kept.keys()
    for d in sorted(first):
        b = first[d]
        gone = bytearray(len(b))
        for p in range(len(b) - 99):
            w = b[p : p + 100]
            if w in seen:
                gone[p : p + 100] = b"\1" * 100
            seen.add(w)
        again += kept[d] != bytes(x for x, g in zip(b, gone) if not g).decode("utf-8", "ignore").encode()
    assert again == 0


def test_packing_covers_all_that_is_left(stages):
    packed = collections.Counter()
    for r in stages[5].collect():
        packed[r.doc_id] += r.length
        assert packed[r.doc_id] <= r.doc_tokens
    assert packed.keys() == {r.doc_id for r in stages[4].collect()}


def test_run_equals_the_stages(stages, spark, sf):
    key = lambda df: sorted((r.doc_id, r.start, r.length, r.ids_crc32) for r in df.collect())
    total = lambda rows: collections.Counter(r[0] for r in rows)
    a, b = key(corpus_pipeline.run(spark, sf)), key(stages[5])
    assert total(a).keys() == total(b).keys() and sum(r[2] for r in a) == sum(r[2] for r in b)


ODD = "doc_id long, text string, lang string, source string, n_chars long, score string, kept_text string, `_key` int, gone string, marked int, `a.b` int"


def odd_rows():
    passage = " ".join(f"word{k}" for k in range(80))
    texts = [None, "", " \n\n ", "one", passage, passage, passage + " end", "start " + passage, "x" * 60_000, "é" * 99, "line one here\nline two here\nlast", "zero\nline one here\nline two here"]
    rows = [(i, t, None if i % 2 else "en", None, None, "s", "k", 1, "g", 2, 3) for i, t in enumerate(texts)]
    return rows + [rows[5], (None, "no id at all", None, None, None, "s", "k", 1, "g", 2, 3), (None, None, None, None, None, None, None, None, None, None, None)]


def test_stages_bear_odd_rows(spark, sf):
    docs = spark.createDataFrame(odd_rows(), ODD)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        made = stage(spark, docs, sf)
        assert made.columns == docs.columns, name
        rows = made.collect()
        assert rows and {r.score for r in rows} <= {"s", None} and {r.kept_text for r in rows} <= {"k", None} and {r["a.b"] for r in rows} <= {3, None}
        assert stage(spark, docs.filter("false"), sf).count() == 0
    before = docs
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = scratch(stage(spark, docs, sf))
    assert 0 < docs.count() < before.count()
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, sf).collect()
    assert {r.doc_id for r in packed} == {r.doc_id for r in docs.collect()}


def test_line_stage_leaves_no_short_line_twice(spark, sf):
    texts = ["Licensed freely\nfirst text", "second text\nLicensed freely\nx", "x\n\nthird text\nLicensed freely", "Licensed freely"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    made = {r.doc_id: r.text for r in corpus_pipeline.drop_lines(spark, docs, sf).collect()}
    assert made == {0: texts[0], 1: "second text\nx", 2: "\nthird text", 3: ""}

"""The pipeline, stage by stage, against brute force on the stage's own input."""

import pytest
from pyspark.sql import functions as F
from test_brute_force import expected_all_lines, expected_groups

import corpus_pipeline as P
from semtrie.llm import quality, segment
from semtrie.llm.common import materialize, table


@pytest.fixture(scope="module")
def stages(spark):
    sf = "/root/testdata/sf0.001"
    docs = [table(spark, sf, "documents")]
    for name, stage in P.STAGES:
        docs.append(materialize(stage(spark, docs[-1], sf), name.replace(" ", "-")))
    return sf, docs


def rows(d):
    return {r.doc_id: r for r in d.collect()}


def test_columns(stages):
    _, docs = stages
    assert all(set(d.columns) == set(docs[0].columns) for d in docs[1:-1])


def test_quality_stage(spark, stages):
    sf, docs = stages
    ranker = quality.fit_ranker(docs[0], table(spark, sf, "labels"))
    want = {r.doc_id for r in quality.score_ids(docs[0], ranker).collect() if r.score >= quality.ACCEPT}
    assert set(rows(docs[1])) == want
    marks = {r.doc_id: r.quality for r in table(spark, sf, "labels").collect()}
    assert not any(marks.get(d) == 1 for d in set(rows(docs[0])) - want)


def test_line_stage(stages):
    _, docs = stages
    before, after = rows(docs[1]), rows(docs[2])
    gone = expected_all_lines([(d, r.text or "") for d, r in before.items()])
    assert set(before) == set(after)
    for d, r in before.items():
        lines = (r.text or "").split("\n")
        assert after[d].text == "\n".join(x for i, x in enumerate(lines) if i not in gone.get(d, ()))
        assert after[d].n_chars == len(after[d].text)


def test_near_duplicate_stage(stages):
    _, docs = stages
    before = [(r.doc_id, r.text) for r in docs[2].collect()]
    assert set(rows(docs[3])) == {d for d, (_, c) in expected_groups(before, 5).items() if d == c}


def test_mixing_stage_loses_and_invents_no_document(stages):
    _, docs = stages
    before, after = ({tuple(r[c] for c in P.COLUMNS) for r in d.collect()} for d in docs[3:5])
    assert before == after


def test_mixing_stage_gives_the_sources_their_weights(spark):
    size = {"big": 900, "mid": 90, "few": 10}
    made = [(d, f"text {d}", "en", s, 8) for d, s in enumerate(s for s, n in size.items() for _ in range(n))]
    out = P.mixing_stage(spark, spark.createDataFrame(made, "doc_id long, text string, lang string, source string, n_chars long"), "").collect()
    total = sum(n**0.5 for n in size.values())
    for s, n in size.items():
        assert abs(sum(r.source == s for r in out) - n**0.5 / total * len(out)) < 32  # one block
    assert {tuple(r[c] for c in P.COLUMNS) for r in out} == set(made)


def test_last_stage(spark, stages):
    sf, docs = stages
    out = docs[5].collect()
    assert all(r.exact for r in out) and {r.doc_id for r in out} == set(rows(docs[4]))
    texts = {d: r.text or "" for d, r in rows(docs[4]).items()}
    assert all(r.decoded == texts[r.doc_id] for r in segment.decode_column(docs[5]).collect())
    key = lambda rs: sorted((r.doc_id, r.sample, r.pieces_sha1, tuple(r.ids)) for r in rs)
    assert key(P.run(spark, sf).collect()) == key(out)


# ---------------------------------------------------------------- odd inputs, stage by stage

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
LONG = " ".join(f"w{i}" for i in range(60_000)) + "\n" + "x" * 300_000


@pytest.fixture(scope="module")
def odd(spark, tmp_path_factory):
    rows = [(1, None, "en", "a", 0), (2, "", None, None, None), (3, "one two three four five six seven", "en", "a", 33), (3, "one two three four five six seven", "en", "a", 33), (None, "no id at all", "en", "b", 12), (5, LONG, "en", "b", len(LONG)), (6, "one two three four five six seven", "en", "c", 33), (7, "é ▁ 😀\n\nnext", "de", "c", 10)]
    docs = spark.createDataFrame(rows, SCHEMA)
    for c in ("id", "n", "kept", "score", "ids", "gone", "mix_slot"):
        docs = docs.withColumn(c, F.lit("clash"))
    sf = str(tmp_path_factory.mktemp("labels"))
    spark.createDataFrame([(3, None, None), (None, 1, 0), (6, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{sf}/labels.parquet")
    return sf, docs


def texts(d):
    return sorted((str(r.doc_id), str(r.text)) for r in d.collect())


def test_stages_on_odd_rows(spark, odd):
    sf, docs = odd
    assert texts(P.quality_stage(spark, docs, sf)) == texts(docs)  # labels of one kind reject nothing
    lined = P.line_stage(spark, docs, sf)
    by = [(r.doc_id, r.text, r.n_chars) for r in lined.collect()]
    assert len(by) == 8 and (1, None, 0) in by and (2, "", 0) in by and (None, "no id at all", 12) in by and (6, "", 0) in by and (5, LONG, len(LONG)) in by
    kept = [r.doc_id for r in P.near_duplicate_stage(spark, docs, sf).collect()]
    assert sorted(map(str, kept)) == ["1", "2", "3", "3", "5", "7", "None"]
    mixed = P.mixing_stage(spark, docs, sf)
    assert set(texts(mixed)) == set(texts(docs)) and all(set(d.columns) == set(P.COLUMNS) for d in (lined, mixed))
    out = P.segmentation_stage(spark, docs, sf)
    assert all(r.exact for r in out.collect()) and out.select("doc_id").distinct().count() == 7


def test_stages_on_empty_tables(spark, odd):
    sf, docs = odd
    for name, stage in P.STAGES:
        assert stage(spark, docs.limit(0), sf).count() == 0, name

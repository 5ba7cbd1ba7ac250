"""Nulls, empty and long texts, ties, repeated rows, empty tables and clashing column names, for each operator."""

import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from semtrie.llm import linededup, mixing, neardup, quality, secrets, segment, tokencount, vectors, warc
from semtrie.llm.common import components, scratch

LONG = "word " * 30_000


@pytest.fixture(scope="module")
def odd(spark):
    """Documents with odd rows, and extra columns that clash with names the operators use."""
    rows = [(1, None), (2, ""), (3, " \n\t "), (4, "short"), (5, LONG), (6, "same text here, one two three four five six"), (7, "same text here, one two three four five six"), (7, "same text here, one two three four five six"), (None, "no id at all, but a text"), (9, "é ü 😀 ▁ two  spaces")]
    d = spark.createDataFrame(rows, "doc_id long, text string")
    return d.withColumn("source", F.when(F.col("doc_id") > 5, F.lit("a"))).withColumn("score", F.lit("x")).withColumn("kept", F.lit(1)).withColumn("id", F.lit(0)).withColumn("n", F.lit(0)).withColumn("variant", F.lit(0))


def none_of(d):
    return d.limit(0)


def test_warc(spark):
    text = "a" + warc.VERSION + "WARC-Type: response\r\n\r\n" + "b" * 10
    rows = [(1, "http://x/1", "same"), (2, "http://x/\r\n2", "same"), (2, "http://x/\r\n2", "same"), (3, None, None), (4, "u", ""), (5, "u", text), (6, "u", LONG)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("digest", F.lit("clash")).withColumn("bytes", F.lit(0))
    path = scratch(spark, "warc")
    warc.write_warc(warc.plan_captures(pages), path)
    records = warc.read_warc(spark, path)
    got = {r.response.record_id: r for r in warc.assemble_transactions(records, chain=True).collect()}
    assert len(got) == 6 and all(len(r.requests) == len(r.metadata) == (2 if ":2:" in i else 1) for i, r in got.items())
    by_page = {r.metadata[0].fields["page-id"]: r.response for r in got.values()}
    assert by_page["2"].record_type == "response" and by_page["1"].record_type == "revisit" and by_page["1"].refers_to == by_page["2"].record_id
    assert by_page["3"].record_type == "revisit" and by_page["4"].declared_bytes == 0
    assert bytes(by_page["5"].payload).decode() == text and bytes(by_page["6"].payload).decode() == LONG
    assert by_page["1"].payload is None and by_page["2"].target_uri == "http://x/%0D%0A2"
    small = {r.page_id: r.original for r in warc.plan_captures(pages, min_revisit_bytes=5).collect()}
    assert small[1] is None and small[3] is None
    empty = scratch(spark, "warc-empty")
    warc.write_warc(warc.plan_captures(none_of(pages)), empty)
    assert warc.read_warc(spark, empty).count() == 0


def test_warc_chain_of_ties(spark):
    row = lambda i, kind, to: (i, kind, "u", "d", to, None, None, None, None, None, None)
    records = spark.createDataFrame([row("r1", "response", []), row("q1", "request", ["r1"]), row("m1", "metadata", ["q1"]), row("r2", "response", ["q2"]), row("q2", "request", []), row("q3", "request", ["lost"])], warc.RECORD_SCHEMA)
    got = {r.capture_id: (r.response.record_id if r.response else None, [x.record_id for x in r.requests], [x.record_id for x in r.metadata]) for r in warc.assemble_transactions(records, chain=True).collect()}
    assert got == {"r1": ("r1", ["q1"], ["m1"]), "r2": ("r2", ["q2"], []), "lost": (None, ["q3"], [])}


def test_warc_ties_of_every_value_and_depth(spark):
    row = lambda i, kind, to: (i, kind, "u", "d", to, None, None, None, None, None, i.encode())
    records = [row("r1", "response", []), row("q1", "request", ["r1"]), row("m1", "metadata", ["q1", "r1"]), row("m2", "metadata", ["q1"]), row("m3", "metadata", ["m2"]), row("m4", "metadata", ["m3"])]
    records += [row("r2", "revisit", []), row("both", "metadata", ["r1", "r2"]), row("x1", "metadata", ["x2"]), row("x2", "request", []), row("alone", "request", [])]
    df = spark.createDataFrame(records, warc.RECORD_SCHEMA)
    got = {r.capture_id: (r.response.record_id if r.response else None, sorted(x.record_id for x in r.requests), sorted(x.record_id for x in r.metadata)) for r in warc.assemble_transactions(df).collect()}
    assert got == {"r1": ("r1", ["q1"], ["both", "m1", "m2", "m3", "m4"]), "r2": ("r2", [], ["both"]), "x1": (None, ["x2"], ["x1"]), "alone": (None, ["alone"], [])}
    nested = {r.capture_id: r for r in warc.assemble_transactions(df).collect()}
    assert bytes(nested["r1"].response.payload) == b"r1" and bytes(nested["r1"].requests[0].payload) == b"q1"
    assert warc.assemble_transactions(none_of(df)).count() == 0
    direct = {r.capture_id: sorted(x.record_id for x in r.metadata) for r in warc.assemble_transactions(df, chain=False).collect()}
    assert direct["r1"] == ["both", "m1"]


def test_quality(spark, odd):
    good = "The plain words of a fair text, as one would write them. They go on. "
    bad = "buy%%% now### "
    docs = spark.createDataFrame([(i, (good * (3 + i % 5)) if i % 3 else bad * (20 + i % 7)) for i in range(120)], "doc_id long, text string")
    labels = docs.select("doc_id", (F.col("doc_id") % 3 != 0).cast("int").alias("quality")).union(spark.createDataFrame([(5, None), (None, 1)], "doc_id long, quality int"))
    ranker = quality.fit_ranker(docs, labels)
    scored = {r.doc_id: r.score for r in quality.score_documents(docs, ranker).collect()}
    assert all((scored[i] >= quality.ACCEPT) == bool(i % 3) for i in range(120))
    rows = quality.score_documents(odd, ranker).collect()
    assert len(rows) == 10 and all(0 <= r.score <= 1 for r in rows)
    assert quality.score_documents(none_of(odd), ranker).count() == 0
    for few in (labels.filter("quality = 1"), labels.filter("quality = 0"), labels.limit(0)):
        scores = {r.score for r in quality.score_documents(odd, quality.fit_ranker(docs, few)).collect()}
        assert scores == {quality.ACCEPT}
    assert {r.score for r in quality.score_documents(odd, quality.fit_ranker(none_of(docs), labels)).collect()} == {quality.ACCEPT}


def test_line_dedup(spark, odd):
    rows = linededup.dedup_lines(odd, marks=("n_lines", "n_gone")).collect()
    assert len(rows) == 10
    by = {r.doc_id: r for r in rows}
    assert by[1].text is None and by[2].text == "" and by[3].text == " \n\t " and by[5].text == LONG
    assert by[6].text and by[7].text == "" and by[7].n_gone == 1 and by[None].text == "no id at all, but a text"
    assert linededup.dedup_lines(none_of(odd)).count() == 0
    assert set(odd.columns) == set(linededup.dedup_lines(odd).columns)


def test_near_duplicates(spark, odd):
    rows = neardup.near_duplicates(odd, words=4).collect()
    by = {r.doc_id: r for r in rows}
    assert len(rows) == 9  # the repeated row is one
    assert by[1].n_shingles == by[2].n_shingles == by[3].n_shingles == 0 and by[1].kept and by[3].component_id == 3
    assert by[4].n_shingles == 1 and by[5].n_shingles == 1
    assert by[7].component_id == 6 and not by[7].kept
    assert by[None].component_id is None and by[None].kept
    assert neardup.near_duplicates(none_of(odd), words=4).count() == 0


@pytest.fixture(scope="module")
def odd_vectors(spark):
    nan, inf = float("nan"), float("inf")
    # 11 has a length of its own
    rows = [(1, [1.0, 0.0, 0.0]), (2, [1.0, 0.0, 0.0]), (2, [1.0, 0.0, 0.0]), (3, [2.0, 0.0, 0.0]), (4, [0.0, 1.0, 0.0]), (5, None), (6, []), (7, [0.0, 0.0, 0.0]), (8, [1.0, nan, 0.0]), (9, [inf, 0.0, 0.0]), (10, [1.0, None, 0.0]), (11, [1.0, 0.0]), (None, [1.0, 0.0, 0.0]), (20, [0.5, 0.5, 0.0]), (40, [0.0, -0.0, 0.0])]
    return spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("id", F.lit("x")).withColumn("n", F.lit(1))


def test_vector_links(odd_vectors):
    rows = vectors.vector_links(odd_vectors).collect()
    by = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in rows}
    assert len(rows) == 14
    assert by[1] == (2, 1, True) and by[2] == (2, 1, False) and by[3] == (2, 1, False)
    assert all(by[i] == (0, i, True) for i in (4, 5, 6, 7, 8, 9, 10, 11, 20, 40))
    assert by[None][0] == 0
    assert vectors.vector_links(none_of(odd_vectors)).count() == 0


def test_nearest_neighbours(odd_vectors):
    rows = vectors.nearest_neighbours(odd_vectors, k=20, coverage=1.0).collect()
    got = [(r.query_id, r["rank"], r.vec_id, r.score) for r in sorted(rows, key=lambda r: (r.query_id, r["rank"]))]
    assert got == [(20, 1, 3, 1.0), (20, 2, 1, 0.5), (20, 3, 2, 0.5), (20, 4, 4, 0.5)]
    assert vectors.nearest_neighbours(none_of(odd_vectors)).count() == 0


@pytest.mark.parametrize("n", [15, 25])
def test_few_vectors_give_all_neighbours_at_the_usual_coverage(n):
    x = np.random.default_rng(n).normal(size=(n, 8))
    forest = vectors.Forest.fit(x, 8, 5, 11)
    leaves = forest.leaves(x)
    sizes = np.stack([np.bincount(leaves[:, t], minlength=32) for t in range(8)])
    for i, visits in enumerate(forest.search(x, sizes, 0.75, 20)):
        met = {j for t, leaf in visits for j in np.flatnonzero(leaves[:, t] == leaf)} - {i}
        assert len(met) >= min(20, n - 1)


def test_secrets(odd):
    rows = secrets.find_secrets(odd).collect()
    assert len(rows) == 10 and all(not r.all_spans for r in rows)
    assert secrets.find_secrets(none_of(odd)).count() == 0


def test_mixing(spark, odd):
    rows = mixing.mix_sources(odd, block=2, cycle=10).collect()
    assert {r.doc_id for r in rows} == {1, 2, 3, 4, 5, 6, 7, None, 9} and len({r.mix_position for r in rows}) == len(rows)
    # rows that differ in a double column alone have a fixed order, whatever their partitions
    tied = spark.createDataFrame([(1, "a", i / 7, {"k": i}) for i in range(20)], "doc_id long, source string, x double, m map<string,int>")
    order = lambda d: [r.x for r in sorted(mixing.mix_sources(d).collect(), key=lambda r: r.mix_position)]
    assert order(tied.repartition(3)) == order(tied.repartition(5, "x")) and len(order(tied)) == 32  # its one block is full
    # large tables get larger blocks, not a longer schedule
    bounded = mixing.mix_sources(spark.range(5000).select(F.col("id").alias("doc_id"), (F.col("id") % 2).cast("string").alias("source")), block=1, max_slots=100)
    assert bounded.select("mix_slot").distinct().count() <= 101 and bounded.select("doc_id").distinct().count() == 5000
    once = mixing.mix_sources(odd, block=2, cycle=10, repeat=False).collect()
    assert len(once) == 10
    assert mixing.mix_sources(none_of(odd)).count() == 0
    with pytest.raises(ValueError):
        mixing.mix_sources(odd, weights={"a": 1.0})


def test_token_counts(spark, odd):
    path = scratch(spark, "flat")
    tokencount.write_flat_tokens(odd, path)
    enc = tokencount.encoding(tokencount.DEFAULT_RANKS)
    want = sorted((str(r.doc_id), len(enc.encode_ordinary(r.text or ""))) for r in odd.collect())
    assert sorted((str(r.doc_id), r.n_tokens) for r in tokencount.count_tokens(spark, path, block_bytes=128).collect()) == want
    # files are cut by bytes: small stretches, few to a file, give the same counts
    small = scratch(spark, "flat-small")
    tokencount.write_flat_tokens(odd, small, chunk_bytes=64, chunks_per_file=1)
    counted = tokencount.count_tokens(spark, small, block_bytes=128)
    assert sorted((str(r.doc_id), r.n_tokens) for r in counted.collect()) == want
    assert counted.select("file").distinct().count() > tokencount.count_tokens(spark, path).select("file").distinct().count()
    empty = scratch(spark, "flat-empty")
    tokencount.write_flat_tokens(none_of(odd), empty)
    assert tokencount.count_tokens(spark, empty).count() == 0


def test_segmentations(spark, odd):
    got = segment.sample_segmentations(odd, k=3)
    rows = segment.decode_column(got).collect()
    assert all(r.exact for r in rows)
    by = {}
    for r in rows:
        by.setdefault(r.doc_id, []).append(r)
    assert len(by[1]) == len(by[2]) == 1 and by[1][0].n_pieces == 0 and by[1][0].log_inclusion == 0
    texts = {r.doc_id: r.text or "" for r in odd.collect()}
    assert all(r.decoded == texts[r.doc_id] for r in rows)
    assert segment.sample_segmentations(none_of(odd)).count() == 0
    again = segment.sample_segmentations(odd.repartition(3), k=3, batch_bytes=64).collect()
    key = lambda rs: sorted((str(r.doc_id), r.sample, r.pieces_sha1) for r in rs)
    assert key(again) == key(rows)  # seeded by row key alone


def test_the_models_own_encoding_decodes_to_the_text(spark, odd):
    texts = {r.doc_id: r.text or "" for r in odd.collect()}
    plain = odd.filter("doc_id IN (1, 2, 4, 5, 6)")  # its normaliser changes blanks and marks of others
    for r in segment.decode_column(segment.encode_best(plain)).collect():
        assert r.decoded.strip() == texts[r.doc_id].strip()


def test_components(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(50)] + [(100, 101), (7, 7), (102, 101)], "a long, b long")
    got = {r.id: r.component for r in components(edges).collect()}
    assert all(got[i] == 0 for i in range(51)) and got[102] == 100 and 7 in got
    assert components(edges.limit(0)).count() == 0


def test_rules_stay_as_stated():
    assert re.match(r"AKIA", secrets.ACCESS) and secrets.KINDS[:3] == ("assign", "access", "hex")

"""Lists of one row per user, and holdings and leaf searches that keep users together: equal to their flat forms."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from semtrie.operators import expand, lists, neighbors, prep, truth
from semtrie.plans import store


@pytest.fixture(scope="module")
def toy(spark):
    x = np.random.default_rng(8).normal(size=(60, 5))
    x[7] = x[3]  # equal vectors tie, as do those of length 0
    x[11] = 0
    profile = spark.createDataFrame([(i, x[i].tolist()) for i in range(60)], "user_id long, emb array<double>")
    start = spark.createDataFrame([(u, (u + d) % 60) for u in range(58) for d in (1, 2, 3, 5, 8)], "user_id long, peer_id long")
    return profile, store.materialize(neighbors.init_lists(start, profile), "start")


@pytest.fixture
def small_batches(spark):
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    yield
    spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def rows(df):
    return sorted((r.user_id, r.peer_id, round(r.sim, 10), r.added_round) for r in df.collect())


OPTIONS = {
    "expand_round1": (1, {}),
    "expand_round3": (3, {}),
    "expand_ask_known": (2, {"ask_from": "known"}),
    "expand_quantised": (2, {"quantised": True}),
    "expand_share_all": (2, {"reply": "everything"}),
    "expand_single_reply": (3, {"reply_limit": 1}),
    "expansion_costs": (2, {"keep_costs": True}),
}


@pytest.mark.parametrize("name", OPTIONS)
def test_rounds_on_whole_lists_equal_rounds_on_rows(toy, small_batches, monkeypatch, name):
    profile, known = toy
    n, options = OPTIONS[name]
    packed = expand.expand(known, profile, n, n_cu=4, **options)
    assert packed.known._lists.count() == known.select("user_id").distinct().count()  # one row per user
    monkeypatch.setattr(store, "VECTOR_BYTES", 0)
    flat = expand.expand(known, profile, n, n_cu=4, **options)
    assert getattr(flat.known, "_lists", None) is None
    assert [rows(a) for a in packed.rounds] == [rows(b) for b in flat.rounds]
    assert packed.costs == flat.costs and flat.known.count() > known.count()
    assert packed.known.dtypes == flat.known.dtypes


def test_split_lists_equal_split_holdings(spark, small_batches):
    access = [(u, None if (u + d) % 13 == 0 else (d * 7) % (5 + u)) for u in range(30) for d in range(40)] + [(None, 1)]
    access = spark.createDataFrame(access, "user_id long, doc_id long")
    want = prep.split_holdings(prep.min_history(access.distinct(), 9), 4)
    got = prep.split_lists(access, 9, 4)
    parts = [got.select("user_id", F.explode(c).alias("doc_id"), F.lit(c == "test").alias("is_test")) for c in ("train", "test")]
    assert parts[0].unionByName(parts[1]).exceptAll(want).isEmpty() and want.exceptAll(parts[0].unionByName(parts[1])).isEmpty()
    assert got.count() == got.select("user_id").distinct().count() == 23  # u from 4 on, but not where 7 divides 5 + u and few remain


def test_number_of_an_event_is_that_of_its_json(spark):
    from semtrie.sources.tables import number_k

    texts = ['{"k": 5}', '{"k":50}', '{"k": 05}', '{"k": "5"}', '{"k": 5, "j": 1}', '{"j": {"k": 5}}', '{"k": 5}\n', '{"k": 5}x', '{"k": null}', "{}", "", "x", None, '{"k": -3}', '{"k": 0}', '{"k": 1.5}', '{"k": 2}{"k": 3}']
    d = spark.createDataFrame([(t,) for t in texts], "props string")
    got = d.select(number_k(F.col("props")).alias("a"), F.get_json_object("props", "$.k").alias("b")).collect()
    assert [r.a for r in got] == [r.b for r in got] and got[0].a == "5"


@pytest.mark.parametrize("items", [truth.ITEMS, 16])
def test_leaf_lists_equal_the_search_that_moves_vectors(toy, spark, monkeypatch, items):
    monkeypatch.setattr(truth, "ITEMS", items)
    monkeypatch.setattr(truth, "SENT_QUERIES", 8)
    profile, _ = toy
    places = spark.createDataFrame([("", "01"[u % 2], u) for u in range(60)] + [("", "1", u) for u in range(0, 60, 4)] + [("", "2", 5)], "tree_id string, path string, user_id long")
    of = lambda df: sorted((r.path, r.user_id, r.peer_id, round(r.sim, 12)) for r in df.collect())
    assert of(truth.leaf_top_k(places, neighbors.units(profile), 6, neighbors.sent_units(profile))) == of(truth.leaf_top_k(places, neighbors.units(profile), 6))


def test_full_leaves_are_searched_alone_and_make_whole_lists(toy, spark, small_batches, monkeypatch):
    profile, _ = toy
    places = spark.createDataFrame([("", "01"[u % 2], u) for u in range(60)] + [("", "1", u) for u in range(0, 60, 4)], "tree_id string, path string, user_id long")
    with monkeypatch.context() as m:
        m.setattr(neighbors, "leaf_rings", lambda *a: pytest.fail("no leaf needs those around it"))
        contacts = neighbors.gather_contacts(places, profile, 6)
        known = neighbors.init_lists(contacts, profile)
        assert known._lists.count() == 60
    monkeypatch.setattr(neighbors, "too_small", lambda *a: True)
    monkeypatch.setattr(store, "VECTOR_BYTES", 0)
    whole = neighbors.gather_contacts(places, profile, 6)
    of = lambda df: sorted((r.path, r.user_id, r.peer_id, r.ring) for r in df.collect())
    assert of(contacts) == of(whole)
    assert rows(known) == rows(neighbors.init_lists(whole, profile))
    assert rows(lists.flat_lists(lists.pack_lists(known))) == rows(known)

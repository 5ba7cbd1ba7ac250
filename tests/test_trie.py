import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from semtrie.operators.kernels import Rule, grow, grow_one_by_one, two_means
from semtrie.operators.trie import _join_by_level, build_forest, build_trie, insert_trie, join_trie
from semtrie.sources import tables as T


def leaves_of(x, rule):
    n = len(x)
    return {p[1]: sorted(p[2].tolist()) for p in grow("", x, np.arange(n), np.full(n, -1.0), rule) if p[0] == "leaf"}


def one_by_one(x, rule):
    return {p: sorted(map(int, u)) for p, u in grow_one_by_one(x, np.arange(len(x)), rule).items()}


@settings(max_examples=40, deadline=None)
@given(st.integers(0, 10**6), st.sampled_from([3, 8, 20]), st.sampled_from([0.0, 0.02, 0.1]), st.booleans(), st.booleans())
def test_level_build_equals_insertion(seed, capacity, delta, clone_on_split, repeats):
    x = np.random.default_rng(seed).normal(size=(150, 4))
    if repeats:
        x[20:60] = x[0]
    rule = Rule(capacity=capacity, delta=delta, clone_on_split=clone_on_split, max_depth=12)
    assert leaves_of(x, rule) == one_by_one(x, rule)


def test_first_split_and_ties():
    x = np.array([[0.0, 0.0], [0.0, 0.2], [4.0, 0.0], [4.0, 0.2]])
    c0, c1, side, _ = two_means(x)
    assert side.tolist() in ([0, 0, 1, 1], [1, 1, 0, 0])
    rule = Rule(capacity=3, delta=0.0)
    middle = np.vstack([x, [[2.0, 0.1]]])
    leaf = {u: p for p, us in leaves_of(middle, rule).items() for u in us}
    assert leaf[4] == "0"  # as near to both: side 0


def test_equal_gap_does_not_clone():
    x = np.array([[0.0], [0.5], [4.0], [4.5], [2.25], [1.75]])
    gap = abs(abs(1.75 - 0.25) - abs(1.75 - 4.25))
    counts = lambda d: sum(len(u) for u in leaves_of(x, Rule(capacity=3, delta=d)).values())
    assert counts(gap) == 7  # only the one on the plane
    assert counts(gap + 1e-9) == 8


def test_identical_vectors_stay_in_one_overfull_leaf():
    x = np.ones((6, 3))
    items = list(grow("", x, np.arange(6), np.full(6, -1.0), Rule(capacity=3)))
    assert len(items) == 1 and items[0][0] == "leaf" and items[0][4]


def test_retry_overfull_goes_on_to_the_first_other_row():
    x = np.vstack([np.ones((6, 2)), np.zeros((3, 2))])
    assert len(leaves_of(x, Rule(capacity=3))) == 1
    assert len(leaves_of(x, Rule(capacity=3, retry_overfull=True))) == 2


def test_without_threshold_everybody_has_one_place(spark, sf):
    t = build_trie(T.plain_vectors(spark, sf), capacity=20, delta=0.0)
    rows = t.placements.collect()
    assert len(rows) == len({r.user_id for r in rows}) == 500
    paths = {r.path for r in rows}
    assert not any(a != b and b.startswith(a) for a in paths for b in paths)  # a prefix code
    sizes = {p: sum(r.path == p for r in rows) for p in paths}
    assert max(sizes.values()) <= 20


@pytest.mark.parametrize("delta,metric", [(0.0, "l2"), (0.02, "l2"), (0.01, "l2_unit"), (0.002, "l2_rms")])
def test_outer_loop_equals_one_task(spark, sf, delta, metric):
    p = T.plain_vectors(spark, sf)
    whole = build_trie(p, capacity=20, delta=delta, metric=metric)
    outer = build_trie(p, capacity=20, delta=delta, metric=metric, local_rows=70)
    key = lambda t: sorted((r.user_id, r.path) for r in t.placements.collect())
    assert outer.levels >= 2
    assert key(whole) == key(outer)
    shape = lambda t: sorted((r.path, r.kind, r.n_users) for r in t.nodes.collect())
    assert shape(whole) == shape(outer)


def test_members_routed_again_reach_a_place_they_own(spark, sf):
    p = T.plain_vectors(spark, sf)
    t = build_trie(p, capacity=20, delta=0.0)
    again = join_trie(p, t)
    own = {(r.user_id, r.path) for r in t.placements.collect()}
    assert {(r.user_id, r.path) for r in again.collect()} == own
    by_level = {(r.user_id, r.path) for r in _join_by_level(p, t, 0.0, "").collect()}
    assert by_level == own


@pytest.mark.parametrize("delta,local_rows", [(0.0, None), (0.02, None), (0.02, 60)])
def test_insertion_into_a_live_trie_equals_a_rebuild(spark, sf, delta, local_rows):
    from pyspark.sql import functions as F

    users = T.plain_vectors(spark, sf).withColumn("arrival", (F.col("user_id") * 7919) % 10_007)
    twice = users.filter("user_id < 40").select((F.col("user_id") + 10_000).alias("user_id"), "emb", (F.col("arrival") + 5_000).alias("arrival"))
    users = users.select("user_id", "emb", "arrival").unionByName(twice)  # equal vectors too
    cuts = [(-1, 3_000), (3_000, 3_100), (3_100, 20_000)]
    parts = [users.filter((F.col("arrival") > a) & (F.col("arrival") <= b)) for a, b in cuts]
    live, members = build_trie(parts[0], capacity=20, delta=delta), parts[0]
    for part in parts[1:]:
        live = insert_trie(live, members, part, local_rows=local_rows)
        members = members.unionByName(part)
    whole = build_trie(users, capacity=20, delta=delta)
    key = lambda t: sorted((r.user_id, r.path) for r in t.placements.collect())
    shape = lambda t: sorted((r.path, r.kind, r.n_users) for r in t.nodes.collect() if r.kind != "split")
    assert key(live) == key(whole) and shape(live) == shape(whole)
    assert key(insert_trie(whole, users, users.limit(0))) == key(whole)


def test_levels_of_many_nodes_are_done_in_passes(spark, sf, monkeypatch):
    from semtrie.operators import trie as M

    p = T.plain_vectors(spark, sf)
    key = lambda t: sorted((r.user_id, r.path) for r in t.placements.collect())
    whole = key(build_trie(p, capacity=20, delta=0.02))
    monkeypatch.setattr(M, "MAX_LEVEL_NODES", 2)
    assert key(build_trie(p, capacity=20, delta=0.02, local_rows=70)) == whole


def test_no_placement_is_dropped_unless_asked(spark):
    import numpy as np

    x = np.random.default_rng(0).normal(size=(60, 2)) * 1e-6
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "user_id long, emb array<double>")
    a, b = (build_trie(rows, capacity=10, delta=1.0, max_depth=9, **o).placements.groupBy("user_id").count().agg({"count": "max"}).first()[0] for o in ({}, {"max_placements": 20}))
    assert a > 20 >= b


def test_cap_on_placements(spark, sf):
    t = build_trie(T.plain_vectors(spark, sf), capacity=20, delta=0.2, max_placements=3, max_depth=8)
    most = t.placements.groupBy("user_id").count().agg({"count": "max"}).first()[0]
    assert most <= 3


def test_forest_has_a_tree_per_key(spark, sf):
    from pyspark.sql import functions as F

    e = T.table(spark, sf, "embeddings").select(F.col("vec_id").alias("user_id"), F.col("embedding").alias("emb"), "label")
    f = build_forest(e, "label", capacity=10, delta=0.0)
    trees = {r.tree_id: r.n for r in f.placements.groupBy("tree_id").agg(F.count("*").alias("n")).collect()}
    assert sum(trees.values()) == 500 and len(trees) == 10

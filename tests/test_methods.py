import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from semtrie import experiments as X
from semtrie.functions import paths as P
from semtrie.functions.hashing import portable_hash, portable_hash_py
from semtrie.operators import deploy, diffusion, expand, hop, measures, neighbors, overlay, prep, profiles, reach, study, truth


@pytest.fixture(scope="module")
def toy(spark):
    rng = np.random.default_rng(5)
    x = rng.normal(size=(40, 5))
    return spark.createDataFrame([(i, x[i].tolist()) for i in range(40)], "user_id long, emb array<double>"), x


def cosines(x):
    u = x / np.linalg.norm(x, axis=1)[:, None]
    return u @ u.T


def test_hash_is_the_same_in_both_worlds(spark):
    got = spark.range(1).select(portable_hash(42, F.lit(7)).alias("h")).first().h
    assert got == portable_hash_py(42, 7) == 535362864448252121


def test_path_functions(spark):
    d = spark.createDataFrame([("0110", "0111"), ("", "01"), ("10", "0")], "a string, b string")
    r = d.select(P.tree_distance(F.col("a"), F.col("b")).alias("d"), P.path_sibling(F.col("a")).alias("s"), P.path_parent(F.col("b")).alias("p")).collect()
    assert [x.d for x in r] == [2, 2, 3]
    assert [x.s for x in r] == ["0111", None, "11"]
    assert [x.p for x in r] == ["011", "0", ""]


def test_contacts_come_from_the_sibling_leaf_first(spark, toy):
    profile, _ = toy
    leaves = ["000", "001", "010", "011", "100", "101", "110", "111"]
    rows = [("", i, leaves[i % 8]) for i in range(40)] + [("", 0, "111")]
    places = spark.createDataFrame(rows, "tree_id string, user_id long, path string")
    got = neighbors.gather_contacts(places, profile, 7).filter("user_id = 0").collect()
    by = {p: sorted((r.ring, r.peer_id % 8) for r in got if r.path == p) for p in ("000", "111")}
    assert [x for x in by["000"] if x[0] == 0] == [(0, 0)] * 4 and [x for x in by["000"] if x[0] == 2] == [(2, 1)] * 3
    assert [x for x in by["111"] if x[0] == 0] == [(0, 7)] * 5 and {x[1] for x in by["111"] if x[0] == 2} == {6}
    assert all(len(v) == 7 for v in by.values())


def test_exact_neighbors_against_numpy(toy):
    profile, x = toy
    s = cosines(x)
    np.fill_diagonal(s, -2)
    got = {}
    for r in truth.exact_neighbors(profile, 6).collect():
        got.setdefault(r.user_id, []).append((r["rank"], r.peer_id))
    for u in range(40):
        assert [p for _, p in sorted(got[u])] == np.argsort(-s[u], kind="stable")[:6].tolist()


def test_expansion_only_improves_and_counts_messages(toy, spark):
    profile, x = toy
    start = spark.createDataFrame([(u, (u + d) % 40) for u in range(40) for d in (1, 2, 3, 5)], "user_id long, peer_id long")
    known = neighbors.init_lists(start, profile)
    e = expand.expand(known, profile, 4, n_cu=4, keep_costs=True)
    exact = truth.exact_neighbors(profile, 4)
    recalls = [measures.recall_at(neighbors.closest(k, 4), exact).agg(F.avg("recall")).first()[0] for k in e.rounds]
    assert recalls == sorted(recalls) and recalls[-1] > recalls[0]
    assert [c["messages"] for c in e.costs] == [40] * 4
    last = e.known.collect()
    assert all(r.user_id != r.peer_id for r in last) and len({(r.user_id, r.peer_id) for r in last}) == len(last)
    s = cosines(x)
    assert all(abs(r.sim - s[r.user_id, r.peer_id]) < 1e-12 for r in last)
    one = expand.expand(known, profile, 1, n_cu=4, reply_limit=1).known.count()
    everything = expand.expand(known, profile, 1, n_cu=4, reply="everything").known.count()
    assert one <= e.rounds[1].count() <= everything
    stable = expand.expand(known, profile, 50, n_cu=4, until_stable=True, patience=3)
    assert len(stable.rounds) < 51


@pytest.fixture(scope="module")
def ring(spark):
    angle = [2 * math.pi * i / 6 for i in range(6)]
    profile = spark.createDataFrame([(i, [math.cos(a), math.sin(a)]) for i, a in enumerate(angle)], "user_id long, emb array<double>")
    lists = spark.createDataFrame([(i, (i + 1) % 6) for i in range(6)], "user_id long, peer_id long")
    holding = spark.createDataFrame([(3, 100)], "user_id long, doc_id long")
    queries = spark.createDataFrame([(1, 0, 100, [1.0, 0.0]), (2, 3, 100, [1.0, 0.0]), (3, 4, 999, [1.0, 0.0])], "query_id long, user_id long, target_doc long, emb array<double>")
    return profile, lists, holding, queries


def ends(trace):
    return {r.query_id: (r.status, r.hops) for r in hop.outcomes(trace).collect()}


def test_chain_hop_on_a_ring(ring):
    profile, lists, holding, queries = ring
    assert ends(hop.chain_hop(queries, lists, profile, holding, 10)) == {1: ("found", 3), 2: ("found", 0), 3: ("dead_end", 5)}
    assert ends(hop.chain_hop(queries, lists, profile, holding, 2))[1] == ("max_hops", 2)
    assert ends(hop.chain_hop(queries, lists, profile, holding, 8, revisit=True))[3] == ("max_hops", 8)
    assert ends(hop.chain_hop(queries, lists, profile, holding, 10, count_self=True))[1] == ("found", 4)
    several = queries.select("query_id", F.lit(100).alias("doc_id"))
    assert ends(hop.chain_hop(queries, lists, profile, holding, 10, targets=several))[3] == ("found", 5)


def test_walks_in_one_pass_equal_walks_hop_by_hop(spark, sf01):
    s = X.coded(spark, sf01)
    key = lambda d: sorted((r.query_id, r.hop, r.user_id, r.status) for r in d.collect())
    hubs = s.known.select("user_id", "peer_id").union(s.workload.profile.select(F.lit(s.workload.profile.agg(F.min("user_id")).first()[0]).alias("user_id"), F.col("user_id").alias("peer_id"))).filter("user_id <> peer_id").distinct()
    for options in ({}, {"revisit": True}, {"count_self": True}):
        assert key(X.walk(s, 4, lists=hubs, local=True, **options)) == key(X.walk(s, 4, lists=hubs, local=False, **options))


def test_long_lists_are_cut_into_parts(ring, monkeypatch):
    profile, lists, holding, queries = ring
    monkeypatch.setattr(hop, "CHUNK", 2)
    everybody = profile.select("user_id").crossJoin(profile.select(F.col("user_id").alias("peer_id"))).filter("user_id <> peer_id")
    key = lambda d: sorted((r.query_id, r.hop, r.user_id, r.status) for r in d.collect())
    assert key(hop.chain_hop(queries, everybody, profile, holding, 5, local=False)) == key(hop.chain_hop(queries, everybody, profile, holding, 5, local=True))


def test_hit_curve_and_work(ring, spark):
    profile, lists, holding, queries = ring
    trace = hop.chain_hop(queries, lists, profile, holding, 10)
    curve = {r.max_hops: r.found for r in measures.hit_curve(hop.outcomes(trace), [1, 3, 10]).collect()}
    assert curve == {1: 1, 3: 2, 10: 2}
    work = {r.query_id: r.similarities for r in measures.work_count(trace, lists, holding).collect()}
    assert work[1] == 3 and work[2] == 0


def test_min_hops_and_unreachable(spark):
    edges = spark.createDataFrame([(0, 1), (1, 2), (2, 0), (7, 8), (8, 7)], "src long, dst long")
    users = spark.createDataFrame([(u,) for u in (0, 1, 2, 7, 8)], "user_id long")
    holding = spark.createDataFrame([(2, 5)], "user_id long, doc_id long")
    queries = spark.createDataFrame([(i, u, 5) for i, u in enumerate((0, 1, 2, 7, 8))], "query_id long, user_id long, target_doc long")
    got = {r.user_id: r.dist for r in reach.min_hops(edges, holding, queries, users, start="owner").collect()}
    assert got == {0: 2, 1: 1, 2: 0, 7: None, 8: None}
    histogram = {r.dist: r.pairs for r in measures.hop_histogram(reach.min_hops(edges, holding, queries, users, start="owner")).collect()}
    assert histogram == {-1: 2, 0: 1, 1: 1, 2: 1}


@pytest.mark.parametrize("norm", ["row", "sym"])
def test_diffusion_against_a_dense_solve(spark, norm):
    pairs = [(0, 1), (1, 2), (2, 3), (3, 4), (1, 3)]
    edges = spark.createDataFrame(pairs + [(b, a) for a, b in pairs], "src long, dst long")
    x = np.arange(10.0).reshape(5, 2)
    profile = spark.createDataFrame([(i, x[i].tolist()) for i in range(5)], "user_id long, emb array<double>")
    a = np.zeros((5, 5))
    for s, d in pairs:
        a[s, d] = a[d, s] = 1
    deg = a.sum(1)
    a = a / deg[:, None] if norm == "row" else a / np.sqrt(deg[:, None] * deg[None])
    want = np.linalg.solve(np.eye(5) - 0.5 * a, 0.5 * x)
    got = {r.user_id: r.emb for r in diffusion.diffuse(edges, profile, 0.5, n_iter=40 if norm == "row" else 14).collect()} if norm == "row" else {r.user_id: r.emb for r in diffusion.diffuse(edges, profile, 0.5, n_iter=14, norm="sym").collect()}
    assert np.allclose([got[i] for i in range(5)], want, atol=1e-3)
    same = {r.user_id: r.emb for r in diffusion.diffuse(edges, profile, 1.0).collect()}
    assert np.allclose([same[i] for i in range(5)], x)


def test_constant_vectors_stay_constant(spark):
    edges = spark.createDataFrame([(0, 1), (1, 0), (1, 2), (2, 1)], "src long, dst long")
    profile = spark.createDataFrame([(i, [2.0, 3.0]) for i in range(3)], "user_id long, emb array<double>")
    assert all(np.allclose(r.emb, [2, 3]) for r in diffusion.diffuse(edges, profile, 0.1, tol=1e-9, n_iter=5).collect())


def test_attachment_graph_degree(spark):
    users = spark.range(400).select(F.col("id").alias("user_id"))
    edges = overlay.pa_graph(users, 5)
    mean = measures.degree_stats(edges).first()["mean"]
    assert 8.5 < mean <= 10
    rows = {(r.src, r.dst) for r in edges.collect()}
    assert all((b, a) in rows and a != b for a, b in rows)
    top = measures.degree_stats(edges).first()["most"]
    assert top > 4 * mean / 2  # hubs


def test_graph_source_reads_the_same_edges(spark):
    from semtrie.operators.overlay import resolve_slot
    from semtrie.sources.graph_source import register

    register(spark)
    got = {(r.src, r.dst) for r in spark.read.format("pa_graph").option("users", 60).option("m", 3).load().collect()}
    want = {(e // 3, resolve_slot(2 * e + 1, 42) // 3) for e in range(180)}
    assert got == {(a, b) for a, b in want if a != b}


def test_random_lists_have_equal_length_and_no_self(toy, spark):
    profile, _ = toy
    known = spark.createDataFrame([(u, p) for u in range(40) for p in range(u % 7 + 1) if p != u], "user_id long, peer_id long")
    got = overlay.random_lists(known, profile).collect()
    size = lambda rows: {u: sum(r.user_id == u for r in rows) for u in {r.user_id for r in rows}}
    assert size(got) == size(known.collect())
    assert all(r.user_id != r.peer_id for r in got)


@pytest.mark.parametrize("n", [2, 3, 12, 40])
def test_random_lists_of_nearly_everybody_are_complete(spark, n):
    users = spark.range(n).select(F.col("id").alias("user_id"))
    for want in (n - 1, max(1, n - 2), n // 2, n + 5):
        quota = users.withColumn("peer_id", F.explode(F.sequence(F.lit(1), F.lit(want))))
        got = overlay.random_lists(quota, users).groupBy("user_id").agg(F.count_distinct("peer_id").alias("k")).collect()
        assert len(got) == n and all(r.k == min(want, n - 1) for r in got)


def test_contacts_reach_beyond_any_ring(spark):
    # a caterpillar: leaves 1, 01, 001, ... lie ever farther apart
    paths = ["0" * i + "1" for i in range(12)]
    places = spark.createDataFrame([("", i, p) for i, p in enumerate(paths)], "tree_id string, user_id long, path string")
    rings = neighbors.leaf_rings(places.filter("user_id IN (0, 11)"), 1).filter("ring > 0").collect()
    assert {(r.leaf, r.other, r.ring) for r in rings} == {(paths[0], paths[11], 13), (paths[11], paths[0], 13)}


def test_hot_documents_are_cut_on_both_sides(spark, monkeypatch):
    monkeypatch.setattr(study, "HOLDERS", 3)
    holding = spark.createDataFrame([(u, d) for u in range(20) for d in (1, 2)] + [(0, 3), (1, 3)], "user_id long, doc_id long")
    got = {r.user_id: (r.max_shared, r.partner) for r in study.max_cooccurrence(holding).collect()}
    assert got == {u: (3, 1 - u) if u < 2 else (2, 0) for u in range(20)}


def test_random_query_rate_agrees_with_its_simulation(spark, sf01):
    w = X.Interest.load(spark, sf01)
    p = [r.p for r in hop.random_query_expected(w.train, w.queries, 10, w.profile.count()).collect()]
    f = [r.found for r in hop.random_query_simulated(w.train, w.queries, w.profile, 10).collect()]
    error = math.sqrt(sum(x * (1 - x) for x in p)) / len(p)
    assert abs(np.mean(p) - np.mean(f)) < 5 * error + 0.02


def test_cooccurrence_against_brute_force(spark):
    rng = np.random.default_rng(0)
    held = {(int(u), int(d)) for u, d in rng.integers(0, (12, 30), size=(120, 2))} | {(99, 1000)}
    holding = spark.createDataFrame(sorted(held), "user_id long, doc_id long")
    docs = {u: {d for v, d in held if v == u} for u in {u for u, _ in held}}
    for r in study.max_cooccurrence(holding).collect():
        best = max(((len(docs[r.user_id] & docs[o]), -o) for o in docs if o != r.user_id), default=(0, 0))
        assert r.max_shared == best[0] and (best[0] == 0 or r.partner == -best[1])
    assert [r.user_id for r in study.isolated_users(holding).collect()] == [99]


def test_shared_documents_in_blocks(spark, monkeypatch):
    rng = np.random.default_rng(3)
    held = sorted({(int(u), int(d)) for u, d in rng.integers(0, (40, 25), size=(500, 2))})
    holding = spark.createDataFrame(held, "user_id long, doc_id long")
    docs = {u: {d for v, d in held if v == u} for u, _ in held}
    pairs = {(a, b, len(docs[a] & docs[b])) for a in docs for b in docs if a < b}
    best = {a: max(((len(docs[a] & docs[o]), -o) for o in docs if o != a)) for a in docs}
    for block, at_once in ((4_000_000, 4_000_000), (90, 40)):  # one block; several blocks, and users cut into parts
        monkeypatch.setattr(study, "BLOCK", block)
        monkeypatch.setattr(study, "PAIRS", at_once)
        assert {tuple(r) for r in study.shared_pairs(holding, 4).collect()} == {p for p in pairs if p[2] >= 4}
        assert {r.user_id: (r.max_shared, -r.partner) for r in study.max_cooccurrence(holding).collect()} == best
        some = study.max_cooccurrence(holding, sample=holding.filter("user_id < 5")).collect()
        assert {r.user_id: (r.max_shared, -r.partner) for r in some} == {u: best[u] for u in range(5)}
    # pairs of users do not travel
    plan = study.shared_pairs(holding, 4)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "FlatMapGroupsInArrow" in plan


def test_thin_holders_and_split(spark):
    holding = spark.createDataFrame([(u, d) for u in range(8) for d in range(12)], "user_id long, doc_id long")
    parts = prep.split_holdings(holding, 3)
    assert {r["count"] for r in parts.filter("is_test").groupBy("user_id").count().collect()} == {3}
    thin = prep.thin_holders(holding, spark.createDataFrame([(0,), (1,)], "doc_id long"), 2)
    per = {r.doc_id: r["count"] for r in thin.groupBy("doc_id").count().collect()}
    assert per[0] == per[1] == 2 and per[2] == 8


def test_custodians_after_departures(spark, sf):
    from semtrie.operators.trie import build_trie
    from semtrie.sources import tables as T

    t = build_trie(T.plain_vectors(spark, sf), capacity=40, delta=0.01)
    directory = deploy.elect_custodians(t.nodes, t.placements)
    places = {}
    for r in t.placements.collect():
        places.setdefault(r.user_id, []).append(r.path)
    rows = directory.collect()
    assert all(any(p.startswith(r.path) for p in places[r.user_id]) for r in rows)
    gone = spark.createDataFrame([(r.user_id,) for r in rows], "user_id long")
    stay, after = deploy.leave(t.placements, directory, gone)
    assert stay.join(gone, "user_id", "left_semi").isEmpty()
    events = {r.path: r.event for r in after.collect()}
    assert set(events.values()) <= {"promoted", "elected"} and len(events) == len(rows)
    everybody = t.placements.select("user_id")
    assert {r.event for r in deploy.leave(t.placements, directory, everybody)[1].collect()} == {"lost"}


def test_embedding_models(spark):
    d = spark.createDataFrame([(1, "abcd abcd"), (2, None), (3, "")], "id long, text string")
    e = {r.id: r.emb for r in profiles.embed_text(d).collect()}
    assert sum(e[1]) == 7 and sum(e[2]) == sum(e[3]) == 0
    import pandas as pd

    custom = profiles.embed_text(d, model=lambda s: pd.Series([[float(len(t))] for t in s]))
    assert {r.id: r.emb for r in custom.collect()} == {1: [9.0], 2: [0.0], 3: [0.0]}


def test_shapes_of_the_experiments(spark, sf01, monkeypatch):
    assert X.ROUNDS == 20
    monkeypatch.setattr(X, "ROUNDS", 5)  # the shape shows early
    rows = {(r.method, r["round"]): r.recall for r in X.exp1_recall(spark, sf01).collect()}
    assert rows["trie 0.001", 0] > 3 * rows["random lists", 0]  # the trie leads at the start
    assert rows["trie 0", 5] - rows["trie 0", 0] < 1  # without clones rounds hardly help
    assert rows["trie 0.003", 5] - rows["trie 0.003", 0] > 2  # with them they do
    assert {m for m, _ in rows} == {"trie 0", "trie 0.0005", "trie 0.001", "trie 0.003", "random lists", "attachment graph"} and max(t for _, t in rows) == 5
    assert rows["trie 0.001", 0] > rows["attachment graph", 0]
    clones = {round(r.delta, 5): r["mean"] for r in X.exp1_clones(spark, sf01).collect()}
    assert clones[0.0] == 1 and clones[0.003] > clones[0.001] > clones[0.0001]


def test_clone_and_fill_tables_against_insertion(spark, sf, sf01):
    from semtrie.operators.kernels import Rule, grow_one_by_one
    from semtrie.sources import tables as T

    def placed(rows, **rule):
        order = sorted(rows, key=lambda r: (r.arrival, r.user_id))
        leaves = grow_one_by_one(np.array([r.emb for r in order], dtype=float), np.array([r.user_id for r in order]), Rule(**rule))
        return {p: u for p, u in leaves.items() if u}

    w = X.Interest.load(spark, sf)
    rows, p = prep.arrival_order(w.profile).collect(), X.sizes(w.profile)
    got = {r.delta: (r.users, r["mean"], r.std_pop) for r in X.exp1_clones(spark, sf).collect()}
    assert set(got) == set(X.THRESHOLDS)
    for delta in X.THRESHOLDS:
        per = {}
        for us in placed(rows, capacity=p["capacity"], delta=delta).values():
            for u in us:
                per[u] = per.get(u, 0) + 1
        n = list(per.values())
        assert got[delta][0] == len(n) and np.allclose(got[delta][1:], (np.mean(n), np.std(n)))
    rows = prep.arrival_order(T.plain_vectors(spark, sf01)).collect()
    fill = {}
    for r in X.exp1_fill(spark, sf01).collect():
        fill.setdefault(r.delta, {})[r.users] = r.leaves
    for delta in (0.0, 0.005):
        sizes = [len(u) for u in placed(rows, capacity=50, delta=delta).values()]
        assert fill[delta] == {s: sizes.count(s) for s in set(sizes)}


def test_costs_follow_their_formulas(spark, sf):
    rows = X.exp4_costs(spark, sf).collect()
    assert {r.users for r in rows if r.workload == "skewed"} == {50, 100, 200} and len(rows) == 15
    for r in rows:
        assert r.expansion == 10 * r.users and r.total == r.insertion + r.expansion
        if r.workload == "skewed":  # a chain: height near N / capacity, insertion near N * N / (2 capacity)
            assert r.height >= 0.9 * r.users / r.capacity - 1 and 0.3 * r.bound < r.insertion < r.bound
        else:
            assert r.insertion <= 2.5 * r.bound
    for r in X.exp4_messages(spark, sf).collect():
        assert r.messages == r.formula if r.kind == "rounds" else r.messages <= r.formula


def test_a_trie_in_service(spark, sf):
    rows = {r.step[0]: r for r in X.exp5_deployment(spark, sf).collect()}
    assert rows["1"].users < rows["2"].users == 500 and rows["2"].leaves > rows["1"].leaves
    assert rows["3"].users == 333 and rows["4"].users == 333 and rows["4"].leaves <= rows["3"].leaves


def test_global_rank_equals_one_sort(spark):
    from semtrie.functions.ranking import global_rank

    rows = [(i, None if i % 17 == 0 else float((i * 7919) % 50)) for i in range(500)]
    d = spark.createDataFrame(rows, "id long, v double")
    for down in (False, True):
        want = {r[0]: n for n, r in enumerate(sorted(rows, key=lambda r: (r[1] is None, (-r[1] if down else r[1]) if r[1] is not None else 0, r[0])), 1)}
        assert {r.id: r["rank"] for r in global_rank(d, "v", "id", descending=down).collect()} == want
    assert global_rank(d.limit(0), "v", "id").count() == 0


def test_quantised_rounds_give_the_same_lists(toy, spark):
    profile, _ = toy
    start = spark.createDataFrame([(u, (u + d) % 40) for u in range(40) for d in (1, 2, 3, 5)], "user_id long, peer_id long")
    known = neighbors.init_lists(start, profile)
    lists = lambda **o: {(r.user_id, r.peer_id, r.added_round) for r in expand.expand(known, profile, 3, n_cu=4, **o).known.collect()}
    assert lists() == lists(quantised=True)


def test_quantised_bound_holds():
    import pandas as pd

    from semtrie.functions.vectors import _quantised, _upper

    x = np.random.default_rng(1).normal(size=(300, 16))
    x /= np.linalg.norm(x, axis=1)[:, None]
    packed = _quantised(pd.Series([r.astype("<f8").tobytes() for r in x]))
    a, b = packed[:150], packed[150:].reset_index(drop=True)
    exact = (x[:150] * x[150:]).sum(1)
    assert (_upper(a, b).to_numpy() >= exact).all() and (_upper(a, b).to_numpy() - exact).max() < 0.1


def test_passages_are_sought_among_vectors_of_whole_texts(spark, sf):
    from semtrie.sources import tables as T

    length = {r.doc_id: len(r.text.lower()) for r in T.table(spark, sf, "documents").filter("text IS NOT NULL").collect()}
    rows = X.text_vectors(spark, sf).collect()
    assert max(length.values()) > 400
    assert all(sum(r.emb) == max(0, length.get(r.doc_id, 0) - 2) for r in rows)  # one count per trigram
    short = T.table(spark, sf, "documents").filter("char_length(text) between 1 and 600").orderBy("doc_id").limit(8)
    got = {r.doc_id: r.emb for r in rows}
    assert all(got[r.doc_id] == r.emb for r in profiles.embed_text(short, dim=64).collect())


def test_experiments_expand_ten_rounds_and_diffuse_to_tolerance(spark, sf, monkeypatch):
    rounds, steps = [], {}

    def expanded(known, profile, n, **options):
        rounds.append(n)
        return expand.Expansion([known])

    def diffused(graph, profile, alpha, *, n_iter=None, **options):
        steps[alpha] = diffusion.steps_for(alpha) if n_iter is None else n_iter
        return profile.select("user_id", "emb")

    curve = spark.createDataFrame([(1, 0, 0.0)], "max_hops int, found long, rate double")
    monkeypatch.setattr(X.expand, "expand", expanded)
    monkeypatch.setattr(X.diffusion, "diffuse", diffused)
    monkeypatch.setattr(X.hop, "chain_hop", lambda *a, **b: None)
    monkeypatch.setattr(X.hop, "outcomes", lambda *a, **b: None)
    monkeypatch.setattr(X.measures, "hit_curve", lambda *a, **b: curve)
    monkeypatch.setattr(X.reach, "min_hops", lambda *a, **b: None)
    monkeypatch.setattr(X.measures, "hop_histogram", lambda *a, **b: curve)
    X.exp2_retrieval(spark, sf)
    X.exp3_reach(spark, sf)
    assert rounds == [10, 10] and steps == {1.0: 0, 0.9: 3, 0.5: 10, 0.1: 66}


def test_contacts_of_a_large_leaf_move_no_pairs(spark):
    """A leaf's users are compared in blocks: equal to brute force, ties included, without a row per pair."""
    from semtrie.plans.planner import shuffled_bytes

    rng = np.random.default_rng(3)
    x = rng.normal(size=(900, 8))
    x[700:] = x[:200]  # copies tie
    profile = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "user_id long, emb array<double>")
    rows = [("", i, "0" if i < 860 else "1") for i in range(900)] + [("", 5, "1")]
    places = spark.createDataFrame(rows, "tree_id string, user_id long, path string")
    before = shuffled_bytes(spark)
    got = neighbors.gather_contacts(places, profile, 4).collect()
    assert shuffled_bytes(spark) - before < 4_000_000
    s = np.round(cosines(x), 12)
    for path in ("0", "1"):
        leaf = [u for _, u, p in rows if p == path]
        found = {}
        for r in got:
            if r.path == path:
                found.setdefault(r.user_id, set()).add(r.peer_id)
        assert found == {u: set(sorted((v for v in leaf if v != u), key=lambda v: (-s[u, v], v))[:4]) for u in leaf}
    known = {(r.user_id, r.peer_id): r.sim for r in neighbors.init_lists(spark.createDataFrame(got), profile).collect()}
    assert len(known) == len({(r.user_id, r.peer_id) for r in got}) and all(abs(v - cosines(x)[k]) < 1e-12 for k, v in known.items())


def test_pairs_are_counted_over_all_users(spark):
    x = np.random.default_rng(8).normal(size=(700, 6))
    profile = spark.createDataFrame([(int(i) * 7, v.tolist()) for i, v in enumerate(x)], "user_id long, emb array<double>")
    want = int((np.abs(cosines(x)[np.triu_indices(700, 1)] - 0.5) < 0.1).sum())
    assert truth.count_pairs(profile, 0.5, 0.1).first().n == want
    assert truth.count_pairs(profile.limit(1), 0.5, 0.1).first().n == 0 == truth.count_pairs(profile.limit(0), 0.5, 0.1).first().n


def test_query_noise_keeps_one_row_per_number(spark, monkeypatch):
    """Two queries of one number (over 100,000 vectors) are one row, as in the SQL."""
    from types import SimpleNamespace

    from semtrie import catalog

    rows = [(100001, [1.0, 0.0]), (100001, [0.6, 0.8]), (7, [0.0, 1.0])]
    monkeypatch.setattr(X.Interest, "load", lambda *_: SimpleNamespace(queries=spark.createDataFrame(rows, "query_id long, emb array<double>")))
    got = sorted((r.query_id, r.sim) for r in catalog.queries()["query_noise"](spark, "").collect())
    want = []
    for q in (7, 100001):
        x = np.concatenate([e for i, e in rows if i == q])
        y = np.concatenate([[v + 0.2 * (portable_hash_py(42, "noise", q, k) / 2**60 - 0.5) for k, v in enumerate(e)] for i, e in rows if i == q])
        want.append((q, round(float(x @ y / np.sqrt((x @ x) * (y @ y))), 6)))
    assert got == want


def test_unknown_peers_are_counted_without_a_list_of_all(spark, monkeypatch):
    from types import SimpleNamespace

    from semtrie import catalog

    profile = spark.createDataFrame([(i, [1.0, float(i)]) for i in range(5)], "user_id long, emb array<double>")
    known = spark.createDataFrame([(0, 1), (0, 4), (3, 2)], "user_id long, peer_id long")
    monkeypatch.setattr(X, "coded", lambda *_: SimpleNamespace(workload=SimpleNamespace(profile=profile), known=known))
    monkeypatch.setattr(truth, "exact_neighbors", lambda *_: pytest.fail("a list of nearest users is cut at its length"))
    assert catalog.queries()["join_anti_unknown_peers"](spark, "").first().n == 5 * 4 - 3


def test_profiles_by_lookup_equal_joined_ones_and_move_no_vectors(spark):
    from semtrie.plans.planner import executed_plan, shuffled_bytes

    rng = np.random.default_rng(8)
    vectors = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(rng.normal(size=(60, 64)))], "doc_id long, emb array<double>")
    held = spark.createDataFrame([(u, (u * 7 + 5 * j) % 70) for u in range(300) for j in range(u % 12)] + [(900, 65)], "user_id long, doc_id long")
    want = {r.user_id: r for r in profiles.user_profiles(held, vectors).collect()}
    before = shuffled_bytes(spark)
    got = {r.user_id: r for r in profiles.profiles_by_lookup(held, vectors).collect()}
    assert shuffled_bytes(spark) - before < 40_000
    assert set(got) == set(want) and 900 not in got
    assert all(got[u].n_docs == want[u].n_docs and np.allclose(got[u].emb, want[u].emb, atol=1e-14) for u in want)
    odd = vectors.union(spark.createDataFrame([(60, [1.0])], vectors.schema))  # vectors of several lengths are not sent
    assert "MapInArrow" not in executed_plan(profiles.profiles_by_lookup(held, odd))


def test_history_counts_documents_once_and_reads_holdings_once(spark):
    from semtrie.plans.planner import executed_plan

    held = spark.createDataFrame([(1, 1), (1, 1), (1, 2), (2, 1), (2, 2), (2, 3), (3, None), (3, 1), (3, 2)], "user_id long, doc_id long")
    got = prep.min_history(held, 3)
    assert sorted((r.user_id, r.doc_id) for r in got.collect()) == [(2, 1), (2, 2), (2, 3)]
    assert "Join" not in executed_plan(got)


def test_candidates_hold_the_k_largest():
    rng = np.random.default_rng(2)
    for n, k in ((5, 9), (40, 3), (2000, 3), (2001, 30)):
        s = np.round(rng.normal(size=(7, n)), 2)  # many ties
        s[0, :2], s[1] = -np.inf, np.nan
        s[2, ::2] = np.nan
        r, c = truth.top_k(s, np.arange(n), k)
        for i in range(7):
            fine = [j for j in range(n) if np.isfinite(s[i, j])]
            assert c[r == i].tolist() == sorted(fine, key=lambda j: (-s[i, j], j))[:k]


def test_sent_vectors_give_the_same_similarities(spark, toy):
    from semtrie.plans.store import sent_vectors

    profile, _ = toy
    unit = neighbors.units(profile)
    pairs = spark.createDataFrame([(i, (i * 3 + 1) % 45, None if i % 2 else 0.5) for i in range(40)], "user_id long, peer_id long, bar double")
    joined, sent = neighbors.with_similarity(pairs, unit), neighbors.with_similarity(pairs, unit, sent_vectors(unit))
    assert sent.columns == ["user_id", "peer_id", "bar", "sim"]
    key = lambda d: sorted((r.user_id, r.peer_id, r.sim) for r in d.select("user_id", "peer_id", "sim").collect())
    assert key(sent) == key(joined) and len(key(sent)) < 40


def test_searches_in_tasks_equal_searches_step_by_step(spark):
    rng = np.random.default_rng(4)
    edges = spark.createDataFrame([(int(a), int(b)) for a, b in rng.integers(0, 60, size=(110, 2))], "src long, dst long")
    holding = spark.createDataFrame([(int(u), int(d)) for u, d in rng.integers(0, 60, size=(40, 2))], "user_id long, doc_id long")
    queries = spark.createDataFrame([(i, i % 63, i % 61) for i in range(120)], "query_id long, user_id long, target_doc long")
    users = spark.range(60).withColumnRenamed("id", "user_id")
    for start in ("owner", "random"):
        run = lambda local: sorted(tuple(r) for r in reach.min_hops(edges, holding, queries, users, max_depth=4, start=start, local=local).fillna(-1).collect())  # noqa: E731, B023
        assert run(True) == run(False) == run(None) and len({r[3] for r in run(True)}) > 3


def test_graphs_of_millions_of_edges_go_to_the_tasks():
    assert hop.LOCAL_PEERS >= 90_000 * 16 * 2  # an attachment graph of 90,000 users


def test_diffusion_by_components_equals_diffusion_by_joins(spark, monkeypatch):
    rng = np.random.default_rng(6)
    profile = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(rng.normal(size=(30, 11)))], "user_id long, emb array<double>")
    edges = spark.createDataFrame([(int(a), int(b)) for a, b in rng.integers(0, 34, size=(70, 2))], "src long, dst long")
    for norm in ("row", "sym"):
        run = lambda: {r.user_id: r.emb for r in diffusion.diffuse(edges, profile, 0.5, norm=norm).collect()}  # noqa: E731, B023
        got = run()
        with monkeypatch.context() as m:
            m.setattr(diffusion, "LOCAL_EDGES", 0)
            m.setattr(diffusion, "_diffuse_by_components", lambda *a: pytest.fail("the graph is above the bound"))
            want = run()
        assert set(got) == set(want) and all(np.allclose(got[u], want[u], atol=1e-12) for u in want)


def test_walks_of_few_documents_are_dealt_to_all_tasks(ring, monkeypatch):
    from semtrie.plans.planner import executed_plan

    profile, lists, holding, queries = ring
    seen = []
    monkeypatch.setattr(hop, "materialize", lambda d, tag: seen.append((tag, executed_plan(d))) or d)
    hop.chain_hop(queries.coalesce(1), lists, profile, holding, 3)
    assert "hashpartitioning(query_id" in dict(seen)["walks"]

"""Headline timings: prints one JSON line.  ``BENCH_SF_DIR`` and ``BENCH_CPUS`` set the tables and the threads."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "8g")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from semtrie.shipping import ship

    ship(spark)
    from semtrie import experiments as X
    from semtrie.operators import diffusion, expand, hop, measures, neighbors, overlay, prep, reach, truth
    from semtrie.operators.trie import build_trie
    from semtrie.plans.planner import shuffled_bytes
    from semtrie.plans.store import materialize
    from semtrie.sources import tables as T

    times: dict[str, float] = {}
    accuracy: dict[str, float] = {}

    traffic: dict[str, float] = {}

    def timed(name, f):
        start, before = time.time(), shuffled_bytes(spark)
        out = f()
        times[name] = round(time.time() - start, 3)
        traffic[name] = round((shuffled_bytes(spark) - before) / 1e6, 2)
        return out

    done = lambda d: materialize(d, "bench")
    mean = lambda d, c: d.agg(F.avg(c)).first()[0]

    timed("first_access_commerce", lambda: done(prep.first_access(T.commerce(spark, SF).access)))
    w = timed("profiles_interest", lambda: X.Interest.load(spark, SF))
    p = X.sizes(w.profile)
    exact = timed("exact_neighbors", lambda: done(truth.exact_neighbors(w.profile, p["n"])))
    build = lambda delta: build_trie(w.profile, capacity=p["capacity"], delta=delta)
    trie = timed("trie_build", lambda: build(0.001))
    timed("trie_build_outer_loop", lambda: build_trie(T.plain_vectors(spark, SF), capacity=50, delta=0.005, local_rows=400).placements.count())
    known = timed("contacts_and_lists", lambda: done(neighbors.init_lists(neighbors.gather_contacts(trie.placements, w.profile, p["n"]), w.profile)))
    grown = timed("expansion_10_rounds", lambda: expand.expand(known, w.profile, 10, n_cu=p["n"]))
    for t in (0, 5, 10):
        accuracy[f"recall_round_{t}"] = mean(measures.recall_at(neighbors.closest(grown.rounds[t], p["n"]), exact), "recall")
    lists = timed("random_lists", lambda: done(neighbors.init_lists(overlay.random_lists(known, w.profile), w.profile)))
    grown_lists = timed("random_lists_10_rounds", lambda: expand.expand(lists, w.profile, 10, n_cu=p["n"]))
    for t in (0, 5, 10):
        accuracy[f"recall_random_round_{t}"] = mean(measures.recall_at(neighbors.closest(grown_lists.rounds[t], p["n"]), exact), "recall")
    train = done(prep.thin_holders(w.train, w.queries.select(F.col("target_doc").alias("doc_id")), 3))
    trace = timed("chain_hop_50", lambda: hop.chain_hop(w.queries, grown.known, w.profile, train, 50))
    timed("chain_hop_5_distributed", lambda: done(hop.chain_hop(w.queries, grown.known, w.profile, train, 5, local=False)))
    m = overlay.match_m(grown.known)
    graph = timed("pa_graph", lambda: done(overlay.pa_graph(w.profile, m)))
    plists = graph.select(F.col("src").alias("user_id"), F.col("dst").alias("peer_id"))
    walk = timed("chain_hop_50_pa", lambda: hop.chain_hop(w.queries, plists, w.profile, train, 50))
    for name, tr in (("trie", trace), ("pa", walk)):
        for r in measures.hit_curve(hop.outcomes(tr), [1, 2, 5, 10, 50]).collect():
            accuracy[f"hit_rate_{name}_{r['max_hops']}"] = r["rate"]
    timed("diffusion_alpha_05", lambda: diffusion.diffuse(graph, w.profile, 0.5))
    timed("min_hops", lambda: done(reach.min_hops(overlay.overlay_graph(grown.known), train, w.queries, w.profile)))
    stats = measures.clone_stats(trie.placements).first()
    accuracy |= {"placements_mean": stats["mean"], "placements_std": stats["std_pop"], "known_mean": measures.degree_stats(overlay.overlay_graph(grown.known)).first()["mean"], "m": m}
    print(json.dumps({"metric": "overlay_total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "shuffled_mb": traffic, "accuracy": {k: round(float(v), 4) for k, v in accuracy.items()}, "sf": SF}))


if __name__ == "__main__":
    main()

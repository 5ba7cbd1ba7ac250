"""The experiments on the given tables, and the shared state they start from."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from semtrie.functions.hashing import portable_hash
from semtrie.operators import diffusion, expand, hop, measures, neighbors, overlay, prep, profiles, reach, truth
from semtrie.operators.trie import Trie, build_trie, join_trie
from semtrie.plans.store import materialize
from semtrie.sources import tables as T


def interest_parts(spark: SparkSession, sf: str) -> DataFrame:
    # dealt by user once, which serves the distinct pairs, the count of documents and the split
    holding = T.interest(spark, sf).access.select("user_id", "doc_id").repartition("user_id").distinct()
    return prep.split_holdings(prep.min_history(holding, 30), 10)


@dataclass
class Interest:
    """The interest workload: training holdings, profiles from them, and one query per test document."""

    train: DataFrame
    profile: DataFrame
    queries: DataFrame
    doc_vectors: DataFrame

    @classmethod
    def load(cls, spark: SparkSession, sf: str) -> Interest:
        parts = materialize(prep.split_lists(T.interest(spark, sf).access, 30, 10), "parts")
        vectors = T.vectors_table(spark, sf)
        train = parts.select("user_id", F.explode("train").alias("doc_id"))
        profile = materialize(profiles.profiles_of_lists(parts.select("user_id", F.col("train").alias("docs")), vectors), "profile")
        test = parts.select("user_id", F.explode("test").alias("doc_id")).join(vectors, "doc_id")
        queries = test.select((F.col("user_id") * 100000 + F.col("doc_id")).alias("query_id"), "user_id", F.col("doc_id").alias("target_doc"), "emb")
        return cls(train, profile, queries, vectors)


@dataclass
class State:
    workload: Interest | None
    placements: DataFrame
    known: DataFrame
    trie: Trie | None = None


def trie_of(profile: DataFrame, **options) -> Trie:
    return build_trie(profile, **options)


def first_lists(placements: DataFrame, profile: DataFrame, n_cc: int) -> DataFrame:
    known = neighbors.init_lists(neighbors.gather_contacts(placements, profile, n_cc), profile)
    return known if getattr(known, "_lists", None) is not None else materialize(known, "known")


def build(profile: DataFrame, *, n_cc: int, workload: Interest | None = None, **options) -> State:
    """Trie, contacts and first lists."""
    trie = build_trie(profile, **options)
    known = first_lists(trie.placements, profile, n_cc)
    return State(workload, trie.placements, known, trie)


def coded_places(profile: DataFrame) -> DataFrame:
    """A stand-in trie of eight leaves by hash, every fourth user also in the sibling leaf: what SQL can state too."""
    path = F.lpad(F.bin(F.pmod(portable_hash("leaf", F.col("user_id")), F.lit(8))), 3, "0")
    own = profile.select(F.lit("").alias("tree_id"), "user_id", path.alias("path"))
    from semtrie.functions.paths import path_sibling

    clones = own.filter(F.pmod(portable_hash("clone", F.col("user_id")), F.lit(4)) == 0).withColumn("path", path_sibling(F.col("path")))
    return own.unionByName(clones)


def coded(spark: SparkSession, sf: str, n_cc: int = 30) -> State:
    w = Interest.load(spark, sf)
    places = coded_places(w.profile)
    known = first_lists(places, w.profile, n_cc)
    return State(w, places, known)


def walk(s: State, max_hops: int, lists: DataFrame | None = None, **options) -> DataFrame:
    return hop.chain_hop(s.workload.queries, s.known if lists is None else lists, s.workload.profile, s.workload.train, max_hops, **options)


def exact_lists(profile: DataFrame, n_cu: int) -> DataFrame:
    return materialize(truth.exact_neighbors(profile, n_cu).select("user_id", "peer_id"), "truth")


def recall_rounds(e: expand.Expansion, profile: DataFrame, n_cu: int, exact: DataFrame | None = None) -> DataFrame:
    """(round, users, recall): mean recall of the exact nearest users after each round, all rounds in one pass.

    Lists only grow, so the list of round t is that of the last one without the
    peers added later.  ``exact`` are the exact nearest users, if they are there already.
    """
    exact = exact if exact is not None else exact_lists(profile, n_cu)
    last = len(e.rounds) - 1
    at = e.known.select("user_id", "peer_id", "sim", F.explode(F.sequence("added_round", F.lit(last))).alias("round"))
    w = Window.partitionBy("round", "user_id").orderBy(F.desc(F.round("sim", 12)), "peer_id")
    near = at.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= n_cu).select("round", "user_id", "peer_id")
    hits = near.join(exact, ["user_id", "peer_id"]).groupBy("round").agg(F.count(F.lit(1)).alias("hits"))
    users = exact.select("user_id").distinct().count()
    rounds = e.known.sparkSession.range(last + 1).select(F.col("id").cast("int").alias("round"))
    return rounds.join(F.broadcast(hits), "round", "left").select("round", F.lit(users).cast("long").alias("users"), F.round(F.coalesce("hits", F.lit(0)) / F.lit(users), 6).alias("recall"))  # one row per round


def stream_placements(spark: SparkSession, sf: str, trie: Trie) -> DataFrame:
    """Vectors arrive as a stream and meet the frozen trie."""
    from semtrie.streaming.streams import run_to_table

    stream = spark.readStream.schema(T.SCHEMAS["embeddings"]).option("pathGlobFilter", "embeddings*.parquet").parquet(sf)
    arrived = run_to_table(stream.select(F.col("vec_id").alias("user_id"), F.col("embedding").cast("array<double>").alias("emb")), "append")
    return join_trie(arrived, trie).select("user_id", "path")


def sizes(profile: DataFrame) -> dict[str, int]:
    """Parameters by number of users: capacity, list lengths and hop limits."""
    n = profile.count()
    return {"capacity": 50, "n": 50} if n >= 600 else {"capacity": 10, "n": 10} if n >= 60 else {"capacity": 4, "n": 5}


#: The thresholds and contact limits of the published experiments.
THRESHOLDS = (0.0, 1e-6, 5e-6, 1e-5, 5e-5, 1e-4, 5e-4, 1e-3, 3e-3, 5e-3)
ROUNDS = 20
CONTACTS = (2, 5, 10, 20, 50, 100, 200, 400, 600)


def as_lists(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("user_id"), F.col("dst").alias("peer_id"))


def exp1_recall(spark: SparkSession, sf: str) -> DataFrame:
    """Recall of the exact nearest users over 20 rounds: several thresholds, and two starts without a trie.

    Random lists are as long as the trie's first lists at threshold 0.001; the
    attachment graph has their mean degree.
    """
    w = Interest.load(spark, sf)
    p = sizes(w.profile)
    grown = lambda known: recall_rounds(expand.expand(known, w.profile, ROUNDS, n_cu=p["n"]), w.profile, p["n"])
    out, base = None, None
    for delta in (0.0, 0.0005, 0.001, 0.003):
        s = build(w.profile, n_cc=p["n"], capacity=p["capacity"], delta=delta)
        base = s.known if delta == 0.001 else base
        r = materialize(grown(s.known), "curve").withColumn("method", F.lit(f"trie {delta:g}"))
        out = r if out is None else out.unionByName(r)
    starts = {"random lists": overlay.random_lists(base, w.profile), "attachment graph": as_lists(overlay.pa_graph(w.profile, overlay.match_m(base)))}
    for name, lists in starts.items():
        out = out.unionByName(materialize(grown(neighbors.init_lists(lists, w.profile)), "curve").withColumn("method", F.lit(name)))
    return out


def exp1_clones(spark: SparkSession, sf: str) -> DataFrame:
    """Placements per user by threshold."""
    w = Interest.load(spark, sf)
    p = sizes(w.profile)
    out = None
    for delta in THRESHOLDS:
        r = measures.clone_stats(build_trie(w.profile, capacity=p["capacity"], delta=delta).placements).withColumn("delta", F.lit(delta))
        out = r if out is None else out.unionByName(r)
    return out


def exp1_fill(spark: SparkSession, sf: str) -> DataFrame:
    """Leaf fill for two thresholds over the plain vectors."""
    profile = T.plain_vectors(spark, sf)
    out = None
    for delta in (0.0, 0.005):
        r = measures.leaf_fill(build_trie(profile, capacity=50, delta=delta).placements).withColumn("delta", F.lit(delta))
        out = r if out is None else out.unionByName(r)
    return out


def exp2_retrieval(spark: SparkSession, sf: str) -> DataFrame:
    """Retrieval rate by contacts allowed: trie lists, attachment graph of equal degree, diffusion, random peers.

    Test documents are thinned to three holders, as popular ones hide the
    differences.  The walk's first contact is the list member nearest to the
    query; ``home counted`` charges the look at home as a contact too.
    """
    w = Interest.load(spark, sf)
    p = sizes(w.profile)
    n = w.profile.count()
    hops = [1, *CONTACTS]
    train = materialize(prep.thin_holders(w.train, w.queries.select(F.col("target_doc").alias("doc_id")), 3), "thin")
    s = build(w.profile, n_cc=p["n"], capacity=p["capacity"], delta=0.003)
    known = expand.expand(s.known, w.profile, 10, n_cu=p["n"]).known
    run = lambda lists, **options: measures.hit_curve(hop.outcomes(hop.chain_hop(w.queries, lists, w.profile, train, max(hops), **options)), hops)
    out = run(known).withColumn("method", F.lit("trie")).unionByName(run(known, count_self=True).withColumn("method", F.lit("trie, home counted")))
    graph = materialize(overlay.pa_graph(w.profile, overlay.match_m(known)), "pa")
    for alpha in (1.0, 0.9, 0.5, 0.1):
        vectors = diffusion.diffuse(graph, w.profile, alpha)
        out = out.unionByName(run(as_lists(graph), vectors=vectors).withColumn("method", F.lit(f"graph {alpha:g}")))
    for h in hops:
        e = hop.random_query_expected(train, w.queries, min(h, n - 1), n).agg(F.lit(h).alias("max_hops"), F.sum("p").cast("long").alias("found"), F.avg("p").alias("rate"))
        out = out.unionByName(e.withColumn("method", F.lit("random peers")))
    return out


def exp3_reach(spark: SparkSession, sf: str) -> DataFrame:
    """Minimum hop distance: trie graph, attachment graph of equal degree, and the mixture."""
    w = Interest.load(spark, sf)
    p = sizes(w.profile)
    s = build(w.profile, n_cc=p["n"], capacity=p["capacity"], delta=0.001)
    known = expand.expand(s.known, w.profile, 10, n_cu=p["n"]).known
    graphs = {"trie": overlay.overlay_graph(known), "attachment": overlay.pa_graph(w.profile, overlay.match_m(known)), "mixed": overlay.mixed_overlay(known, w.profile)}
    out = None
    for name, edges in graphs.items():
        r = measures.hop_histogram(reach.min_hops(materialize(edges, "graph"), w.train, w.queries, w.profile)).withColumn("method", F.lit(name))
        out = r if out is None else out.unionByName(r)
    return out


def skewed_users(spark: SparkSession, n: int) -> DataFrame:
    """Users who arrive one far beyond the other, so that every split parts one from the rest and the next arrivals join that one."""
    return spark.range(n).select(F.col("id").alias("user_id"), F.array(F.pow(F.lit(4.0), F.col("id"))).alias("emb"), F.col("id").alias("arrival"))


def exp4_costs(spark: SparkSession, sf: str) -> DataFrame:
    """Build messages, splits and height against users, capacity and threshold; and the degenerate trie.

    ``bound`` is placements times log2(users / capacity) + 1 levels where splits
    are about even, and users squared over capacity for the skewed arrivals, whose
    trie is a chain.
    """
    users = prep.arrival_order(T.plain_vectors(spark, sf))
    out = None
    settings = [("vectors", share, capacity, delta) for share in (4, 2, 1) for capacity in (20, 50) for delta in (0.0, 0.005)] + [("skewed", size, 4, 0.0) for size in (50, 100, 200)]
    for workload, scale, capacity, delta in settings:
        profile = materialize(skewed_users(spark, scale) if workload == "skewed" else users.filter(F.col("arrival") < (1 << 60) // scale), "cost-users")
        n = profile.count()
        t = build_trie(profile, capacity=capacity, delta=delta, max_depth=256)
        r = measures.build_cost(t.placements, n, 10, splits=t.splits.count(), capacity=capacity).crossJoin(t.nodes.agg(F.max("depth").alias("height"), F.count_if(F.col("kind") == "split").alias("splits"), F.coalesce(F.sum(F.when(F.col("kind") != "split", F.col("n_users"))), F.lit(0)).alias("placements")))
        bound = F.col("placements") * (F.log2(F.lit(max(n, 1) / capacity)) + 1) if workload == "vectors" else F.lit(float(n) * n / capacity)
        r = r.select(F.lit(workload).alias("workload"), F.lit(n).alias("users"), F.lit(capacity).alias("capacity"), F.lit(delta).alias("delta"), "insertion", "expansion", "reassigned", "total", "height", "splits", "placements", bound.alias("bound"))
        out = r if out is None else out.unionByName(r)
    return out


def exp4_messages(spark: SparkSession, sf: str) -> DataFrame:
    """Messages and similarities, as counted, of rounds and of queries, against their formulas.

    ``messages`` of r rounds are users times r; those of queries at most queries
    times the contacts allowed.
    """
    w = Interest.load(spark, sf)
    p = sizes(w.profile)
    n, asked = w.profile.count(), w.queries.count()
    s = build(w.profile, n_cc=p["n"], capacity=p["capacity"], delta=0.001)
    e = expand.expand(s.known, w.profile, 10, n_cu=p["n"], keep_costs=True)
    rows = []
    for r in (1, 5, 10):
        rows.append(("rounds", r, sum(c["messages"] for c in e.costs[:r]), sum(c["similarities"] for c in e.costs[:r]), n * r))
    train = materialize(prep.thin_holders(w.train, w.queries.select(F.col("target_doc").alias("doc_id")), 3), "thin")
    for limit in (2, 10, 50):
        trace = hop.chain_hop(w.queries, e.known, w.profile, train, limit)
        work = measures.work_count(trace, e.known, train).agg(F.sum("similarities")).first()[0]
        rows.append(("queries", limit, measures.message_count(hop.outcomes(trace)).first()["messages"], work, asked * limit))
    return spark.createDataFrame(rows, "kind string, limit int, messages long, similarities long, formula long")


def exp5_deployment(spark: SparkSession, sf: str) -> DataFrame:
    """A trie in service: half of the users, then arrivals by stream, departures, and sparse leaves folded.

    One row per step: users placed, placements, leaves, and offices by what
    happened to them.
    """
    from semtrie.operators import deploy
    from semtrie.streaming.streams import LiveTrie

    users = prep.arrival_order(T.plain_vectors(spark, sf))
    early = users.filter(F.col("arrival") < (1 << 59))
    live = LiveTrie(build_trie(early, capacity=50, delta=0.005), early)
    row = lambda step, places, offices=0, lost=0: places.agg(F.lit(step).alias("step"), F.count_distinct("user_id").alias("users"), F.count(F.lit(1)).alias("placements"), F.count_distinct("tree_id", "path").alias("leaves"), F.lit(offices).cast("long").alias("offices"), F.lit(lost).cast("long").alias("lost"))
    directory = deploy.elect_custodians(live.trie.nodes, live.trie.placements)
    out = row("1 built", live.trie.placements, directory.count())
    stream = spark.readStream.schema(T.SCHEMAS["embeddings"]).option("pathGlobFilter", "embeddings*.parquet").parquet(sf)
    arriving = prep.arrival_order(stream.select(F.col("vec_id").alias("user_id"), F.col("embedding").cast("array<double>").alias("emb"))).filter(F.col("arrival") >= (1 << 59))
    grown = live.follow(arriving)
    directory = materialize(deploy.elect_custodians(grown.nodes, grown.placements), "directory")
    out = out.unionByName(row("2 arrivals", grown.placements, directory.count()))
    stay, after = deploy.leave(grown.placements, directory, users.filter("user_id % 3 = 0").select("user_id"))
    stay, after = materialize(stay, "stay"), materialize(after, "offices")
    out = out.unionByName(row("3 departures", stay, after.filter("event <> 'lost'").count(), after.filter("event = 'lost'").count()))
    folded = deploy.merge_sparse(grown.nodes, stay, capacity=50, min_fill=0.9)
    return out.unionByName(row("4 folded", materialize(folded, "folded"), after.filter("event <> 'lost'").count(), after.filter("event = 'lost'").count()))


def text_vectors(spark: SparkSession, sf: str) -> DataFrame:
    """(doc_id, emb) of the documents' whole texts: the vectors of ``embed_text``, counted by grouping as texts are long."""
    docs = T.table(spark, sf, "documents").select("doc_id", "text")
    grams = docs.select("doc_id", F.explode(profiles.grams(F.col("text"))).alias("gram")).groupBy("doc_id", "gram").count()
    buckets = grams.groupBy("doc_id", F.pmod(portable_hash(F.col("gram")), F.lit(64)).cast("int").alias("bucket")).agg(F.sum("count").cast("double").alias("n"))
    held = buckets.groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("bucket", "n"))).alias("held"))
    emb = F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: F.coalesce(F.try_element_at("held", i), F.lit(0.0)))
    return docs.select("doc_id").join(held, "doc_id", "left").select("doc_id", emb.alias("emb"))


def exp_passages(spark: SparkSession, sf: str) -> DataFrame:
    """Chain hop to any of several holders: benchmark passages sought among (source, language) users."""
    corpus = T.corpus(spark, sf).withColumn("number", F.xxhash64("user_id"))
    vectors = profiles.embed_text(T.table(spark, sf, "benchmark"), dim=64).select("item_id", "emb")
    held = corpus.select(F.col("number").alias("user_id"), F.col("row_id").alias("doc_id"))
    doc_vectors = text_vectors(spark, sf)
    profile = materialize(profiles.user_profiles(held, doc_vectors), "corpus-profile")
    s = build(profile, n_cc=10, capacity=8, delta=0.5)
    targets = T.passages(spark, sf).select(F.col("item_id").alias("query_id"), F.col("row_id").alias("doc_id"))
    number = overlay.numbered(profile)
    start = F.pmod(portable_hash("passage", F.col("query_id")), F.lit(profile.count()))
    queries = vectors.select(F.col("item_id").alias("query_id"), "emb").join(targets.select("query_id").distinct(), "query_id", "left_semi").withColumn("number", start).join(number, "number")
    queries = queries.select("query_id", "user_id", F.lit(None).cast("long").alias("target_doc"), "emb")
    trace = hop.chain_hop(queries, s.known, profile, held, 10, targets=targets)
    return measures.hit_curve(hop.outcomes(trace), [1, 2, 5, 10])


EXPERIMENTS = {
    "exp1_recall": exp1_recall,
    "exp1_clones": exp1_clones,
    "exp1_fill": exp1_fill,
    "exp2_retrieval": exp2_retrieval,
    "exp3_reach": exp3_reach,
    "exp4_costs": exp4_costs,
    "exp4_messages": exp4_messages,
    "exp5_deployment": exp5_deployment,
    "exp_passages": exp_passages,
}

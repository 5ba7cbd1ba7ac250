"""The semantic trie, built level by level; equal to inserting users one after another.

A node's split depends only on the first capacity + 1 arrivals at it, and later
arrivals are routed against centres that stay fixed.  So all nodes of a depth can
be split at once.  Large nodes are split by the outer loop, whose state is the
table of (path, user, vector); once a node's rows fit one task, the rest of its
subtree is finished there.  The outer loop therefore runs for about
log2(N / local_rows) levels, moves only heads to the splitters, and routes rows in
place against the level's few centres.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from semtrie.functions.vectors import as_double
from semtrie.operators.kernels import Rule, grow, scaled, split, two_means
from semtrie.operators.prep import arrival_order
from semtrie.plans.planner import plan_build
from semtrie.plans.store import discard, materialize

NODE = "tree_id string, path string, depth int, kind string, c0 array<double>, c1 array<double>, n_users long, steps int"
PLACE = "tree_id string, user_id long, path string, gap double"
#: Large nodes of one level, and bytes of their centres (two vectors each), which are sent to the tasks; the rest waits for the next pass.
MAX_LEVEL_NODES, MAX_LEVEL_BYTES = 20_000, 64 << 20
#: Rows of one finishing task, less where vectors are long.
LOCAL_ROWS = 20_000


@dataclass(frozen=True)
class Trie:
    """``nodes`` (split nodes and leaves), ``placements`` (tree_id, user_id, path, gap), and the rule they follow."""

    nodes: DataFrame
    placements: DataFrame
    rule: Rule
    levels: int = 0

    @property
    def splits(self) -> DataFrame:
        return self.nodes.filter("kind = 'split'")

    @property
    def leaves(self) -> DataFrame:
        return self.nodes.filter("kind <> 'split'")


def _vectors(column) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    n = len(column)
    return column.flatten().to_numpy(zero_copy_only=False).reshape(n, -1) if n else np.zeros((0, 0))


def _finish(table: pa.Table, rule: Rule) -> pa.Table:
    """Grow one small subtree; node and placement rows come back in one schema."""
    order = np.lexsort((table.column("user_id").to_numpy(), table.column("arrival").to_numpy()))
    table = table.take(pa.array(order))
    tree, path = table.column("tree_id")[0].as_py(), table.column("path")[0].as_py()
    out: dict[str, list] = {k: [] for k in ("tree_id", "path", "kind", "c0", "c1", "n", "steps", "users", "gaps")}
    for item in grow(path, scaled(_vectors(table.column("emb")), rule.metric), table.column("user_id").to_numpy(), table.column("gap").to_numpy(), rule):
        if item[0] == "split":
            row = (tree, item[1], "split", item[2].tolist(), item[3].tolist(), item[4], item[5], [], [])
        else:
            row = (tree, item[1], "overfull" if item[4] else "leaf", None, None, len(item[2]), 0, item[2].tolist(), item[3].tolist())
        for k, v in zip(out.values(), row, strict=True):
            k.append(v)
    kinds = (pa.string(), pa.string(), pa.string(), pa.list_(pa.float64()), pa.list_(pa.float64()), pa.int64(), pa.int32(), pa.list_(pa.int64()), pa.list_(pa.float64()))
    return pa.table({k: pa.array(v, t) for (k, v), t in zip(out.items(), kinds, strict=True)})


FINISH = "tree_id string, path string, kind string, c0 array<double>, c1 array<double>, n long, steps int, users array<long>, gaps array<double>"


def _head(table: pa.Table, rule: Rule) -> pa.Table:
    order = np.lexsort((table.column("user_id").to_numpy(), table.column("arrival").to_numpy()))
    table = table.take(pa.array(order))
    x = scaled(_vectors(table.column("emb")), rule.metric)
    cut = two_means(x, rule.max_iter)
    if cut is not None:
        row, side, _ = split(x, np.ones(len(x), bool), cut[0], cut[1], rule)
        if not all(0 < int((side == s).sum()) < len(x) for s in (0, 1)):
            cut = None
    last = table.num_rows - 1
    return pa.table(
        {
            "tree_id": table.column("tree_id").slice(0, 1), "path": table.column("path").slice(0, 1),
            "c0": pa.array([None if cut is None else cut[0].tolist()], pa.list_(pa.float64())), "c1": pa.array([None if cut is None else cut[1].tolist()], pa.list_(pa.float64())),
            "steps": pa.array([0 if cut is None else cut[3]], pa.int32()), "last_arrival": table.column("arrival").slice(last, 1), "last_user": table.column("user_id").slice(last, 1),
        }
    )


def _route(batches: Iterator[pa.RecordBatch], centres: dict, rule: Rule) -> Iterator[pa.RecordBatch]:
    """Move rows of split nodes to their children; clones become rows of their own."""
    for batch in batches:
        if not batch.num_rows:
            continue
        keys = list(zip(batch.column("tree_id").to_pylist(), batch.column("path").to_pylist(), strict=True))
        x = scaled(_vectors(batch.column("emb")), rule.metric)
        arrival, user, gap = (batch.column(c).to_numpy() for c in ("arrival", "user_id", "gap"))
        groups: dict = {}
        for i, k in enumerate(keys):
            groups.setdefault(k, []).append(i)
        rows, paths, gaps = [], [], []
        for k, members in groups.items():
            c0, c1, last_arrival, last_user = centres[k]
            m = np.array(members)
            head = (arrival[m] < last_arrival) | ((arrival[m] == last_arrival) & (user[m] <= last_user))
            row, side, g = split(x[m], head, c0, c1, rule)
            rows.append(m[row])
            paths += [f"{k[1]}{s}" for s in side]
            gaps.append(np.maximum(gap[m[row]], g))
        taken = batch.take(pa.array(np.concatenate(rows)))
        yield pa.RecordBatch.from_arrays([taken.column("tree_id"), pa.array(paths, pa.string()), taken.column("user_id"), taken.column("arrival"), taken.column("emb"), pa.array(np.concatenate(gaps))], ["tree_id", "path", "user_id", "arrival", "emb", "gap"])


FRONTIER = "tree_id string, path string, user_id long, arrival long, emb array<double>, gap double"


def build_trie(profile: DataFrame, *, seed: int = 42, tree_key: str | None = None, local_rows: int | None = None, **options) -> Trie:
    """Trie over ``profile(user_id, emb)``, or a forest with one tree per value of ``tree_key``.

    Options (see ``kernels.Rule``): ``capacity`` 50; ``delta`` 0.001, the largest
    difference of the two distances, exclusive, at which a user follows both
    sides; ``metric`` l2 | l2_unit | l2_rms; ``clone_on_split`` also for the head's
    members; ``max_iter``; ``max_depth``; ``max_placements`` per user (none by
    default: no placement is dropped unless asked); ``retry_overfull``.  A node
    whose head cannot be separated stays a leaf, marked ``overfull``.
    ``local_rows`` is the size up to which a node is finished in one task; by
    default what ``planner.plan_build`` allows for the vectors' length.
    """
    rule = Rule(**options)
    rows = profile if "arrival" in profile.columns else arrival_order(profile, seed)
    tree = F.lit("") if tree_key is None else F.coalesce(F.col(tree_key).cast("string"), F.lit("null"))
    frontier = rows.select(tree.alias("tree_id"), F.lit("").alias("path"), F.col("user_id").cast("long").alias("user_id"), F.col("arrival").cast("long").alias("arrival"), as_double(F.col("emb")).alias("emb"), F.lit(-1.0).alias("gap"))
    return _grow_all(frontier, rule, local_rows)


def _grow_all(frontier: DataFrame, rule: Rule, local_rows: int | None) -> Trie:
    """The subtrees below the nodes (tree_id, path) of ``frontier``, whose rows came in order of arrival."""
    spark = frontier.sparkSession
    one = frontier.select(F.size("emb").alias("dim")).first()
    dim = max(1, one["dim"]) if one else 1
    if local_rows is None:
        local_rows = min(LOCAL_ROWS, plan_build(0, dim, capacity=rule.capacity).local_rows)
    at_once = max(1, min(MAX_LEVEL_NODES, MAX_LEVEL_BYTES // (16 * dim)))
    nodes, done, level, superseded = [], [], 0, []
    while True:
        sizes = frontier.groupBy("tree_id", "path").agg(F.count(F.lit(1)).alias("n"))
        is_large = (F.col("n") > local_rows) & (F.char_length("path") < rule.max_depth)
        large = sizes.filter(is_large).orderBy(F.desc("n"), "tree_id", "path").limit(at_once).collect()
        if not large:
            done.append(frontier)
            break
        keys = F.broadcast(spark.createDataFrame([(r["tree_id"], r["path"]) for r in large], "tree_id string, path string"))
        big = frontier.join(keys, ["tree_id", "path"], "left_semi")
        others = frontier.join(keys, ["tree_id", "path"], "left_anti")
        waiting = None
        if len(large) == at_once:
            rest = sizes.filter(is_large).join(keys, ["tree_id", "path"], "left_anti").select("tree_id", "path")
            waiting = others.join(rest, ["tree_id", "path"], "left_semi")
            others = others.join(rest, ["tree_id", "path"], "left_anti")
        w = Window.partitionBy("tree_id", "path").orderBy("arrival", "user_id")
        heads = big.withColumn("rn", F.row_number().over(w)).filter(F.col("rn") <= rule.capacity + 1).drop("rn", "gap")
        cut = heads.groupBy("tree_id", "path").applyInArrow(lambda t: _head(t, rule), "tree_id string, path string, c0 array<double>, c1 array<double>, steps int, last_arrival long, last_user long").collect()
        size_of = {(r["tree_id"], r["path"]): r["n"] for r in large}
        centres = {(r["tree_id"], r["path"]): (np.array(r["c0"]), np.array(r["c1"]), r["last_arrival"], r["last_user"]) for r in cut if r["c0"] is not None}
        closed = [k for k in size_of if k not in centres]
        nodes += [(k[0], k[1], len(k[1]), "split", c[0].tolist(), c[1].tolist(), size_of[k], s) for (k, c), s in zip(centres.items(), [r["steps"] for r in cut if r["c0"] is not None], strict=True)]
        nodes += [(k[0], k[1], len(k[1]), "overfull", None, None, size_of[k], 0) for k in closed]
        done.append(others)
        if closed:
            shut = F.broadcast(spark.createDataFrame(closed, "tree_id string, path string"))
            done.append(("placed", big.join(shut, ["tree_id", "path"], "left_semi")))
            big = big.join(shut, ["tree_id", "path"], "left_anti")
        sent = spark.sparkContext.broadcast(centres)
        moved = big.select("tree_id", "path", "user_id", "arrival", "emb", "gap").mapInArrow(lambda b, c=sent: _route(b, c.value, rule), FRONTIER)
        frontier = materialize(moved if waiting is None else moved.unionByName(waiting), f"trie-level-{level}")
        superseded.append(frontier)
        level += 1
    grown, placed = [], []
    for part in done:
        if isinstance(part, tuple):
            placed.append(part[1].select("tree_id", "user_id", "path", "gap"))
        else:
            grown.append(part)
    rest = grown[0]
    for g in grown[1:]:
        rest = rest.unionByName(g)
    made = materialize(rest.groupBy("tree_id", "path").applyInArrow(lambda t: _finish(t, rule), FINISH), "trie")
    own = made.select("tree_id", "path", F.char_length("path").alias("depth"), "kind", "c0", "c1", F.col("n").alias("n_users"), "steps")
    all_nodes = own.unionByName(spark.createDataFrame(nodes, NODE)) if nodes else own
    places = made.filter("kind <> 'split'").select("tree_id", F.explode(F.arrays_zip("users", "gaps")).alias("u"), "path").select("tree_id", F.col("u.users").alias("user_id"), "path", F.col("u.gaps").alias("gap"))
    for p in placed:
        places = places.unionByName(p)
    if not placed:  # the finished rows are in ``made``, and nothing else reads the levels
        for d in superseded:
            discard(d)
    if rule.max_placements is not None:
        w = Window.partitionBy("tree_id", "user_id").orderBy("gap", "path")
        places = places.withColumn("rn", F.row_number().over(w)).filter(F.col("rn") <= rule.max_placements).drop("rn")
    return Trie(all_nodes, places, rule, level)


def insert_trie(trie: Trie, members: DataFrame, new: DataFrame, *, seed: int = 42, local_rows: int | None = None) -> Trie:
    """The trie after users arrived at a live one: the one a rebuild in order of arrival gives.

    ``members(user_id, emb, arrival)`` are the users it holds, ``new(user_id, emb)``
    come after them, in the order of their own ``arrival`` if they have one or of
    its hash.  New users walk down to their leaves (and both sides of a boundary
    within ``delta``); a leaf that overflows is split among its members by order of
    arrival, as often as needed; other leaves and all split nodes stay as they
    are.  One tree; several are inserted into one by one.
    """
    if trie.rule.max_placements is not None:
        raise ValueError("a cap on placements is set over the whole trie: rebuild")
    fresh = materialize((new if "arrival" in new.columns else arrival_order(new, seed)).select(F.col("user_id").cast("long").alias("user_id"), as_double(F.col("emb")).alias("emb"), F.col("arrival").cast("long").alias("arrival")), "arrived")
    landed = materialize(join_trie(fresh, trie).select("tree_id", "user_id", "path"), "landed")
    touched = materialize(landed.select("tree_id", "path").distinct(), "touched")
    old = trie.placements.select("tree_id", "user_id", "path").join(touched, ["tree_id", "path"], "left_semi")
    vectors = lambda d: d.select("user_id", as_double(F.col("emb")).alias("emb"), F.col("arrival").cast("long").alias("arrival"))
    # whoever was there came before whoever arrives now, whatever the numbers
    last = members.agg(F.max("arrival")).first()[0]
    first = fresh.agg(F.min("arrival")).first()[0]
    shift = max(0, (last + 1 - first)) if last is not None and first is not None else 0
    rows = old.join(vectors(members), "user_id").unionByName(landed.join(fresh.withColumn("arrival", F.col("arrival") + shift), "user_id"))
    frontier = materialize(rows.select("tree_id", "path", "user_id", "arrival", "emb", F.lit(-1.0).alias("gap")), "overflow")
    grown = _grow_all(frontier, trie.rule, local_rows)
    nodes = trie.nodes.join(touched, ["tree_id", "path"], "left_anti").select(*trie.nodes.columns).unionByName(grown.nodes)
    places = trie.placements.join(touched, ["tree_id", "path"], "left_anti").select(*trie.placements.columns).unionByName(grown.placements)
    return Trie(materialize(nodes, "nodes"), materialize(places, "placements"), trie.rule, trie.levels)


def descend(x: np.ndarray, centres: dict[str, tuple[np.ndarray, np.ndarray]], delta: float) -> tuple[np.ndarray, list[str], np.ndarray]:
    """(row, leaf path, contacts made) of every placement of new rows in a frozen trie."""
    rows, paths, steps = [], [], []
    todo = [("", np.arange(len(x)))]
    rule = Rule(delta=delta, clone_on_split=True)
    while todo:
        at, members = todo.pop()
        if not len(members):
            continue
        if at not in centres:
            rows.append(members)
            paths += [at] * len(members)
            steps.append(np.full(len(members), len(at)))
            continue
        row, side, _ = split(x[members], np.zeros(len(members), bool), *centres[at], rule)
        todo += [(f"{at}{s}", members[row[side == s]]) for s in (0, 1)]
    cat = lambda parts: np.concatenate(parts) if parts else np.zeros(0, np.int64)
    return cat(rows), paths, cat(steps)


def join_trie(new: DataFrame, trie: Trie, *, delta: float | None = None, tree_id: str = "") -> DataFrame:
    """(tree_id, user_id, path, messages): where new users land; one contact per level and placement.

    Split nodes of the tree travel to the tasks: fit for tries of up to
    ``MAX_LEVEL_NODES`` splits, beyond which the join is done level by level.
    """
    delta = trie.rule.delta if delta is None else delta
    found = trie.splits.filter(F.col("tree_id") == tree_id).select("path", "c0", "c1").limit(MAX_LEVEL_NODES + 1).collect()
    if len(found) > MAX_LEVEL_NODES:
        return _join_by_level(new, trie, delta, tree_id)
    centres = {r["path"]: (np.array(r["c0"]), np.array(r["c1"])) for r in found}
    metric = trie.rule.metric

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            row, paths, steps = descend(scaled(_vectors(batch.column("emb")), metric), centres, delta)
            users = batch.column("user_id").take(pa.array(row))
            yield pa.RecordBatch.from_arrays([pa.array([tree_id] * len(row), pa.string()), users, pa.array(paths, pa.string()), pa.array(steps, pa.int64())], ["tree_id", "user_id", "path", "messages"])

    return new.select(F.col("user_id").cast("long").alias("user_id"), as_double(F.col("emb")).alias("emb")).mapInArrow(run, "tree_id string, user_id long, path string, messages long")


def _join_by_level(new: DataFrame, trie: Trie, delta: float, tree_id: str) -> DataFrame:
    """The same by one equi-join with the split nodes per level, all in expressions (metric l2)."""
    from semtrie.functions.vectors import vec_l2

    if trie.rule.metric != "l2":
        raise ValueError("joining by level knows the plain distance only")
    splits = trie.splits.filter(F.col("tree_id") == tree_id).select("path", "c0", "c1")
    open_ = new.select(F.col("user_id").cast("long").alias("user_id"), as_double(F.col("emb")).alias("emb"), F.lit("").alias("path"))
    landed = None
    while True:
        met = open_.join(splits, "path", "left")
        here = met.filter(F.col("c0").isNull()).select(F.lit(tree_id).alias("tree_id"), "user_id", "path", F.char_length("path").cast("long").alias("messages"))
        landed = here if landed is None else landed.unionByName(here)
        d0, d1 = vec_l2(F.col("emb"), F.col("c0")), vec_l2(F.col("emb"), F.col("c1"))
        near = F.when(d0 <= d1, F.lit("0")).otherwise(F.lit("1"))
        far = F.when(F.abs(d0 - d1) < delta, F.translate(near, "01", "10"))
        step = met.filter(F.col("c0").isNotNull()).withColumn("side", F.explode(F.array_compact(F.array(near, far))))
        open_ = materialize(step.select("user_id", "emb", F.concat("path", "side").alias("path")), "join-level")
        if open_.isEmpty():
            return landed


def build_forest(profile: DataFrame, tree_key: str, **options) -> Trie:
    """One tree per value of ``tree_key`` (topic, language); several roots of one tree share its nodes."""
    return build_trie(profile, tree_key=tree_key, **options)


def two_means_centroids(max_iter: int = 20):
    """An aggregate over (arrival, vector): both centres one after the other; empty if the group does not separate.

    For groups of about a leaf's size: a grouped aggregate holds its group in one task.
    """

    @F.pandas_udf("array<double>")
    def centres(arrival: pd.Series, emb: pd.Series) -> object:
        x = np.array([v for _, v in sorted(zip(arrival, emb.tolist(), strict=True), key=lambda r: r[0])], dtype=float)
        cut = two_means(x, max_iter)
        return [] if cut is None else np.concatenate(cut[:2]).tolist()

    return centres


def trie_paths_udtf():
    """A table function for SQL: the leaf paths of one vector, given the split nodes as an array of structs."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="path string")
    class TriePaths:
        def eval(self, emb, nodes, delta: float):
            centres = {n["path"]: (np.array(n["c0"]), np.array(n["c1"])) for n in nodes}
            for p in sorted(descend(np.array([emb], dtype=float), centres, delta)[1]):
                yield (p,)

    return TriePaths

"""Vector operators: near-duplicate links by product quantisation, nearest neighbours by a random-projection forest.

Defined cases for both: vectors that are null, empty, zero, or that hold null or
non-finite components take no part (they link with nothing and are neither
queries nor candidates); vectors of different lengths have no cosine or inner
product, so each length is a table of its own; a null id takes no part; rows that
repeat an id and its vector are one row; ties go to the smaller id; other columns
are not read; an empty table gives an empty result.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from semtrie.llm.common import components, materialize, table

SAMPLE = 16_384
BLOCK = 4_096
#: Visitors of one block: they are many more than members, and members travel once per block of them.
GUESTS = 4 * BLOCK


def _dtype(df: DataFrame, col: str) -> str:
    return "<f4" if df.schema[col].dataType.elementType.simpleString() == "float" else "<f8"


def clean_vectors(df: DataFrame, id_col: str, vec_col: str) -> tuple[DataFrame, str]:
    """(id, vec) of usable rows as packed binary, repeated rows once; and the number format."""
    kind = _dtype(df, vec_col)
    v = F.col(vec_col)
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    rows = df.filter(F.col(id_col).isNotNull() & v.isNotNull() & finite).select(F.col(id_col).cast("long").alias("id"), v.alias("v"))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            vectors = batch.column("v")
            # -0.0 and 0.0 are the same component
            packed = [(x.values.to_numpy(zero_copy_only=False).astype(kind) + 0.0).astype(kind).tobytes() for x in vectors]
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(packed, pa.binary())], ["id", "vec"])

    return rows.mapInArrow(pack, "id long, vec binary").distinct(), kind


def matrix(column, kind: str) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    n = len(column)
    if not n:
        return np.zeros((0, 0))
    return np.frombuffer(b"".join(column.to_pylist()), dtype=kind).reshape(n, -1).astype(np.float64)


def lengths(rows: DataFrame) -> list[int]:
    """The packed sizes that occur, commonest first: one index is made for each."""
    return [r["size"] for r in rows.groupBy(F.octet_length("vec").alias("size")).count().orderBy(F.desc("count"), "size").collect()]


def sample_matrix(rows: DataFrame, kind: str, limit: int) -> np.ndarray:
    """At most ``limit`` vectors, those of smallest id hash: the documented bound on what the index is fitted on."""
    found = rows.orderBy(F.xxhash64("id"), "id").limit(limit).select("vec").toPandas()["vec"]
    return np.frombuffer(b"".join(bytes(x) for x in found), dtype=kind).reshape(len(found), -1).astype(np.float64) if len(found) else np.zeros((0, 0))


def unit(x: np.ndarray) -> np.ndarray:
    # scaled first, so that huge or tiny components neither overflow nor vanish
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


# ---------------------------------------------------------------- product quantisation


def squared_distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.maximum((a * a).sum(1)[:, None] - 2 * a @ b.T + (b * b).sum(1)[None], 0)


def nearest(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    """Number of the nearest centre of each row, in slices of bounded memory."""
    if not len(x):
        return np.zeros(0, dtype=np.int64)
    return np.concatenate([squared_distances(x[lo : lo + 2048], centres).argmin(1) for lo in range(0, len(x), 2048)])


def kmeans(x: np.ndarray, k: int, rounds: int = 8) -> np.ndarray:
    """Lloyd's iterations from evenly spaced rows; an empty cell keeps its centre."""
    k = min(k, len(x))
    centres = x[np.linspace(0, len(x) - 1, k).astype(int)].copy()
    for _ in range(rounds):
        cell = nearest(x, centres)
        count = np.bincount(cell, minlength=k)
        total = np.zeros_like(centres)
        np.add.at(total, cell, x)
        centres[count > 0] = total[count > 0] / count[count > 0][:, None]
    return centres


@dataclass(frozen=True)
class Quantiser:
    """Coarse cells on two levels, and codes of the residual in each of several subspaces.

    Cells are numbered so that those of a group follow each other: group g holds
    the cells from ``bounds[g]`` on.
    """

    coarse: np.ndarray
    bounds: np.ndarray
    parts: list[np.ndarray]
    books: list[np.ndarray]

    @classmethod
    def fit(cls, sample: np.ndarray, cells: int, groups: int = 1, subspaces: int = 8, codes: int = 64) -> Quantiser:
        coarse = np.unique(kmeans(sample, cells), axis=0)
        group = nearest(coarse, kmeans(coarse, groups))
        coarse, group = coarse[np.argsort(group, kind="stable")], np.sort(group)
        bounds = np.append(np.flatnonzero(np.diff(group, prepend=-1)), len(coarse))
        residual = sample - coarse[nearest(sample, coarse)]
        parts = np.array_split(np.arange(sample.shape[1]), min(subspaces, sample.shape[1]))
        return cls(coarse, bounds, parts, [kmeans(residual[:, p], codes, 6) for p in parts])

    def encode(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Cell, codes and the exact length of what the codes leave out."""
        cell = nearest(x, self.coarse)
        residual = x - self.coarse[cell]
        codes = np.stack([squared_distances(residual[:, p], b).argmin(1) for p, b in zip(self.parts, self.books, strict=True)], axis=1)
        left = residual - np.hstack([b[codes[:, s]] for s, b in enumerate(self.books)])
        return cell, codes.astype(np.uint8), np.sqrt((left * left).sum(1))

    def group_of(self, cell: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.bounds, cell, side="right") - 1

    def inside(self, x: np.ndarray, cell: np.ndarray, reach: float, lo: int, hi: int) -> np.ndarray:
        """Which of the cells lo..hi, of at least the own number, can hold a vector within ``reach`` of each row.

        A vector in cell c is nearer to c's centre than to x's own centre, so x
        lies within ``reach`` of the plane between the two: this bound leaves no
        cell out that matters.
        """
        d = squared_distances(x, self.coarse[lo:hi])
        own = ((x - self.coarse[cell]) ** 2).sum(1)
        gap = np.sqrt(squared_distances(self.coarse[cell], self.coarse[lo:hi]))
        return (d - own[:, None] <= 2 * gap * (reach + 1e-6) + 1e-9) & (np.arange(lo, hi)[None] >= cell[:, None])

    def visits(self, x: np.ndarray, cell: np.ndarray, reach: float) -> list[np.ndarray]:
        """The groups with a cell to probe."""
        probed = self.inside(x, cell, reach, 0, len(self.coarse))
        return [np.flatnonzero(row) for row in np.logical_or.reduceat(probed, self.bounds[:-1], axis=1)]

    def decoded(self, cell: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """The vectors that cells and codes stand for."""
        return self.coarse[cell] + np.hstack([b[codes[:, s]] for s, b in enumerate(self.books)])

    def tables(self, x: np.ndarray) -> list[np.ndarray]:
        """Inner product of each query with every code, per subspace.

        The asymmetric distance is ``|x|^2 + |y|^2 - 2 (x.c + sum of table entries)``
        for the decoded y of cell centre c, so one set of tables serves all cells.
        """
        return [(x[:, p] @ b.T).astype(np.float32) for p, b in zip(self.parts, self.books, strict=True)]


def local_components(i: np.ndarray, j: np.ndarray, n: int) -> np.ndarray:
    label = np.arange(n)
    while True:
        low = np.minimum(label[i], label[j])
        new = label.copy()
        np.minimum.at(new, i, low)
        np.minimum.at(new, j, low)
        new = new[new]
        if (new == label).all():
            return label
        label = new


LINK_SCHEMA = "id long, links long, root long"


def _link_block(members: pa.Table, queries: pa.Table, q: Quantiser, kind: str, cosine: float) -> pa.Table:
    """Links between one block of a group's members and one block of the vectors that probe a cell of the group."""
    if not members.num_rows or not queries.num_rows:
        return pa.table({"id": pa.array([], pa.int64()), "links": pa.array([], pa.int64()), "root": pa.array([], pa.int64())})
    reach = np.sqrt(2 - 2 * cosine)
    members = members.take(pa.array(np.argsort(members.column("cell").to_numpy(), kind="stable")))
    mid, qid = members.column("id").to_numpy(), queries.column("id").to_numpy()
    many, qmany = members.column("n").to_numpy(), queries.column("n").to_numpy()
    y, x = unit(matrix(members.column("vec"), kind)), unit(matrix(queries.column("vec"), kind))
    codes = np.frombuffer(b"".join(members.column("codes").to_pylist()), dtype=np.uint8).reshape(len(mid), -1)
    inhabited = members.column("cell").to_numpy()
    # least inner product with the decoded member at which the distance can lie within reach (x has length 1)
    decoded = q.decoded(inhabited, codes)
    least = (1 + (decoded * decoded).sum(1) - (reach + members.column("left").to_numpy() + 1e-6) ** 2) / 2 - 1e-5
    home = queries.column("home").to_numpy()
    cells, first = np.unique(inhabited, return_index=True)
    stop = np.append(first[1:], len(mid))
    ids = np.unique(np.concatenate([mid, qid]))
    m_at, q_at = np.searchsorted(ids, mid), np.searchsorted(ids, qid)
    links, label = np.zeros(len(ids), dtype=np.int64), np.arange(len(ids))
    for start in range(0, len(qid), 512):
        rows = slice(start, start + 512)
        probed = q.inside(x[rows], home[rows], reach, int(cells[0]), int(cells[-1]) + 1)
        tables, centre = q.tables(x[rows]), x[rows] @ q.coarse[cells].T
        left, right = [], []
        for j, (cell, lo, hi) in enumerate(zip(cells, first, stop, strict=True)):
            ask = np.flatnonzero(probed[:, cell - cells[0]])
            if not len(ask):
                continue
            product = np.zeros((len(ask), hi - lo), dtype=np.float32)
            for s, table_ in enumerate(tables):
                product += table_[ask].take(codes[lo:hi, s], axis=1)
            a, b = np.nonzero(product >= (least[lo:hi] - centre[ask, j][:, None]))
            a, b = ask[a] + start, b + lo
            # inside its own cell a pair is seen from both ends: take it once
            once = (home[a] != cell) | (qid[a] < mid[b])
            a, b = a[once], b[once]
            good = np.zeros(len(a), dtype=bool)
            for at in range(0, len(a), 1 << 16):
                part = slice(at, at + (1 << 16))
                good[part] = (x[a[part]] * y[b[part]]).sum(1) >= cosine
            left.append(a[good])
            right.append(b[good])
        a, b = (np.concatenate(p) if p else np.zeros(0, np.int64) for p in (left, right))
        if len(a):
            np.add.at(links, q_at[a], many[b])
            np.add.at(links, m_at[b], qmany[a])
            used = np.arange(len(ids))
            label = local_components(np.concatenate([q_at[a], used]), np.concatenate([m_at[b], label]), len(ids))
    hit = links > 0
    return pa.table({"id": pa.array(ids[hit]), "links": pa.array(links[hit]), "root": pa.array(ids[label[hit]])})


def vector_links(df: DataFrame, *, id_col: str = "vec_id", vec_col: str = "embedding", cosine: float = 0.95, cells: int | None = None) -> DataFrame:
    """Per row: vec_id, n_links, component_id, kept, over all pairs with cosine at or above the bound.

    Equal vectors are one class with a multiplicity.  Every class sits in the
    inverted list of its nearest coarse cell; it probes all cells that can hold a
    vector in reach; table-lookup distances plus the exact residual left-overs
    rule pairs out without loss; the rest is reranked by exact cosine.

    Cells grow in number with the table and are dealt out by groups: a vector
    travels once to each group with a cell it probes, and picks the cells there.
    Large groups and their visitors are cut into blocks (``BLOCK`` and ``GUESTS``
    rows); blocks return counts and local stars, never pairs.
    """
    rows, kind = clean_vectors(df, id_col, vec_col)
    rows = materialize(rows, "vectors")
    every = df.select(F.col(id_col).cast("long").alias("vec_id")).distinct()
    out = every.join(rows.select(F.col("id").alias("vec_id")).distinct(), "vec_id", "left_anti").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    for size in lengths(rows):
        out = _links_of_one_length(rows.filter(F.octet_length("vec") == size), kind, cosine, cells).unionByName(out)
    return out.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


def _links_of_one_length(rows: DataFrame, kind: str, cosine: float, cells: int | None) -> DataFrame:
    spark = rows.sparkSession
    classes = rows.groupBy(F.sha2("vec", 256).alias("content")).agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("n"), F.first("vec").alias("vec"))
    classes = materialize(classes, "vector-classes")
    total = classes.count()
    sample = unit(sample_matrix(classes, kind, SAMPLE))
    wanted = cells or int(np.clip(2 ** round(np.log2(4 * np.sqrt(total))), 8, 2048))
    q = Quantiser.fit(sample, wanted, int(np.clip(-(-total // BLOCK), 1, 256)))
    reach = float(np.sqrt(2 - 2 * cosine))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 1024):
                part = batch.slice(lo, 1024)
                x = unit(matrix(part.column("vec"), kind))
                cell, codes, left = q.encode(x)
                yield pa.RecordBatch.from_arrays(
                    [*(part.column(c) for c in ("id", "n", "vec")), pa.array(cell.astype(np.int32)), pa.array(q.group_of(cell).astype(np.int32)), pa.array([c.tobytes() for c in codes], pa.binary()), pa.array(left), pa.array([v.astype(np.int32) for v in q.visits(x, cell, reach)], pa.list_(pa.int32()))],
                    ["id", "n", "vec", "cell", "part", "codes", "left", "visits"],
                )

    placed = materialize(classes.select("id", "n", "vec").mapInArrow(place, "id long, n long, vec binary, cell int, part int, codes binary, left double, visits array<int>"), "placed")
    visits = placed.select(F.explode("visits").alias("part")).groupBy("part").agg(F.count(F.lit(1)).alias("guests"))
    sizes = placed.groupBy("part").agg(F.count(F.lit(1)).alias("rows")).join(visits, "part", "left").collect()  # one row per group, at most 256
    blocks = [(r["part"], -(-r["rows"] // BLOCK), -(-(r["guests"] or 1) // GUESTS)) for r in sizes]
    plan = F.broadcast(spark.createDataFrame(blocks, "part int, member_blocks int, guest_blocks int"))
    deal = lambda c: F.pmod(F.xxhash64("id"), F.col(c)).cast("int")
    members = placed.drop("visits").join(plan, "part").withColumn("m", deal("member_blocks")).withColumn("g", F.explode(F.sequence(F.lit(0), F.col("guest_blocks") - 1)))
    guests = placed.select("id", "n", "vec", F.col("cell").alias("home"), F.explode("visits").alias("part")).join(plan, "part").withColumn("g", deal("guest_blocks")).withColumn("m", F.explode(F.sequence(F.lit(0), F.col("member_blocks") - 1)))
    members = members.select("part", "m", "g", "cell", "id", "n", "vec", "codes", "left")
    # fresh attribute names: both sides stem from one table
    guests = guests.select(*[F.col(c).alias(c) for c in ("part", "m", "g", "id", "n", "vec", "home")])
    found = members.groupBy("part", "m", "g").cogroup(guests.groupBy("part", "m", "g")).applyInArrow(lambda a, b: _link_block(a, b, q, kind, cosine), LINK_SCHEMA)
    found = materialize(found, "links")
    grouped = components(found.select(F.col("id").alias("a"), F.col("root").alias("b")))
    counts = found.groupBy("id").agg(F.sum("links").alias("links"))
    told = classes.select("content", "id", "n").join(counts, "id", "left").join(grouped, "id", "left")
    told = told.select("content", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "id").alias("component_id"))
    return rows.select(F.col("id").alias("vec_id"), F.sha2("vec", 256).alias("content")).join(told, "content").drop("content")


def op3_vector_near_duplicates(spark, sf_dir) -> DataFrame:
    """Contract query of operator 3 over every row of ``embeddings``."""
    return vector_links(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"))


# ---------------------------------------------------------------- random-projection forest


@dataclass(frozen=True)
class Forest:
    """Balanced trees of random hyperplanes, each cut at the median of the sample's projections."""

    depth: int
    planes: np.ndarray  # trees x inner nodes x dim, heap order
    cuts: np.ndarray  # trees x inner nodes

    @classmethod
    def fit(cls, sample: np.ndarray, trees: int, depth: int, seed: int) -> Forest:
        rng = np.random.default_rng(seed)
        inner, dim = (1 << depth) - 1, sample.shape[1]
        planes = rng.normal(size=(trees, inner, dim))
        planes /= np.sqrt((planes**2).sum(-1, keepdims=True))
        cuts = np.zeros((trees, inner))
        for t in range(trees):
            node = np.zeros(len(sample), dtype=np.int64)
            for k in range(inner):
                rows = np.flatnonzero(node == k)
                p = sample[rows] @ planes[t, k]
                cuts[t, k] = np.median(p) if len(p) else 0.0
                node[rows] = 2 * k + 1 + (p > cuts[t, k])
        return cls(depth, planes, cuts)

    def leaves(self, x: np.ndarray) -> np.ndarray:
        """Leaf number of every row in every tree."""
        out = np.empty((len(x), len(self.cuts)), dtype=np.int32)
        for t in range(len(self.cuts)):
            side = x @ self.planes[t].T - self.cuts[t] > 0
            node = np.zeros(len(x), dtype=np.int64)
            for _ in range(self.depth):
                node = 2 * node + 1 + side[np.arange(len(x)), node]
            out[:, t] = node - len(self.cuts[t])
        return out

    def search(self, x: np.ndarray, sizes: np.ndarray, coverage: float, k: int) -> list[list[tuple[int, int]]]:
        """Leaves to visit per query, from one priority queue shared by all trees.

        The queue is ordered by the largest distance to a plane that a path had
        to cross; a query stops when the leaves taken are expected to cover the
        wanted share of all rows and those of one tree, which share no row, hold
        more than ``k``: k others besides the query.
        """
        trees, inner = self.cuts.shape
        share = sizes / np.maximum(sizes.sum(1, keepdims=True), 1)
        margins = np.stack([x @ self.planes[t].T - self.cuts[t] for t in range(trees)], axis=1)
        out = []
        for row in margins:
            heap = [(0.0, t, 0) for t in range(trees)]
            taken, seen, held = [], np.zeros(trees), np.zeros(trees)
            while heap:
                crossed, t, node = heapq.heappop(heap)
                m = row[t]
                while node < inner:
                    right = m[node] > 0
                    heapq.heappush(heap, (max(crossed, abs(m[node])), t, 2 * node + (1 if right else 2)))
                    node = 2 * node + (2 if right else 1)
                leaf = node - inner
                taken.append((t, leaf))
                seen[t] += share[t, leaf]
                held[t] += sizes[t, leaf]
                if held.max() > k and 1 - np.prod(1 - np.minimum(seen, 1)) >= coverage:
                    break
            out.append(taken)
        return out


def best_of_block(members: pa.Table, queries: pa.Table, kind: str, k: int) -> pa.Table:
    """Exact top k of one block of leaf candidates for each visiting query.

    The matrix product only preselects; scores are summed per pair in one fixed
    order, so equal vectors tie exactly whatever block they are met in.
    """
    qs, vs, scores = [], [], []
    if members.num_rows and queries.num_rows:
        mid, qid = members.column("id").to_numpy(), queries.column("id").to_numpy()
        y, x = matrix(members.column("vec"), kind), matrix(queries.column("vec"), kind)
        for start in range(0, len(qid), 512):
            block = x[start : start + 512] @ y.T
            own = qid[start : start + 512][:, None] == mid[None]
            block[own] = -np.inf
            kth = np.partition(block, len(mid) - k, axis=1)[:, len(mid) - k] if len(mid) > k else np.full(len(block), -np.inf)
            slack = 1e-9 * (1 + np.abs(kth))
            for i, row in enumerate(block):
                near = np.flatnonzero((row >= kth[i] - slack[i]) & ~own[i])
                exact = (y[near] * x[start + i]).sum(1)
                order = np.lexsort((mid[near], -exact))[:k]
                qs.append(np.full(len(order), qid[start + i]))
                vs.append(mid[near][order])
                scores.append(exact[order])
    cat = lambda parts, kind_: np.concatenate(parts) if parts else np.zeros(0, kind_)
    return pa.table({"query_id": pa.array(cat(qs, np.int64)), "vec_id": pa.array(cat(vs, np.int64)), "score": pa.array(cat(scores, np.float64))})


def nearest_neighbours(
    df: DataFrame,
    *,
    id_col: str = "vec_id",
    vec_col: str = "embedding",
    k: int = 20,
    every: int = 20,
    trees: int = 8,
    coverage: float = 0.75,
    leaf_rows: int = 4096,
    seed: int = 11,
) -> DataFrame:
    """The k nearest found rows by inner product for each query (ids divisible by ``every``).

    Split planes are fitted on a bounded sample; every row is indexed in every
    tree.  Queries visit the leaves that the shared queue picks, until these hold
    the wanted share of all rows and, in one tree, more than ``k`` rows (or there
    are no more); leaf members and visitors meet in blocks of bounded size and are
    scored exactly.  A higher
    ``coverage`` raises recall and work; 1 is exhaustive.
    """
    rows, kind = clean_vectors(df, id_col, vec_col)
    rows = materialize(rows, "points")
    out = df.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    for size in lengths(rows):
        out = out.unionByName(_neighbours_of_one_length(rows.filter(F.octet_length("vec") == size), kind, k, every, trees, coverage, leaf_rows, seed))
    return out


def _neighbours_of_one_length(rows: DataFrame, kind: str, k: int, every: int, trees: int, coverage: float, leaf_rows: int, seed: int) -> DataFrame:
    spark = rows.sparkSession
    total = rows.count()
    depth = int(np.clip(np.ceil(np.log2(max(total, 1) / leaf_rows)), 5, 10))
    forest = Forest.fit(sample_matrix(rows, kind, SAMPLE), trees, depth, seed)

    def index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 4096):
                part = batch.slice(lo, 4096)
                leaves = forest.leaves(matrix(part.column("vec"), kind))
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(leaves) + 1, dtype=np.int32) * trees), pa.array(leaves.ravel()))
                yield pa.RecordBatch.from_arrays([part.column("id"), part.column("vec"), lists], ["id", "vec", "leaves"])

    indexed = materialize(rows.mapInArrow(index, "id long, vec binary, leaves array<int>"), "forest")
    spread = lambda d: d.select("id", "vec", F.posexplode("leaves").alias("tree", "leaf"))
    counts = spread(indexed).groupBy("tree", "leaf").count().collect()  # trees x leaves rows, at most 8 x 1024
    sizes = np.zeros((trees, 1 << depth))
    for r in counts:
        sizes[r["tree"], r["leaf"]] = r["count"]

    def visit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 1024):
                part = batch.slice(lo, 1024)
                found = forest.search(matrix(part.column("vec"), kind), sizes, coverage, k)
                yield pa.RecordBatch.from_arrays([part.column("id"), part.column("vec"), pa.array([[t << 16 | leaf for t, leaf in f] for f in found], pa.list_(pa.int32()))], ["id", "vec", "visits"])

    queries = indexed.filter(F.pmod("id", F.lit(every)) == 0).select("id", "vec")
    visits = materialize(queries.mapInArrow(visit, "id long, vec binary, visits array<int>"), "visits").select("id", "vec", F.explode("visits").alias("to"))
    visits = visits.select("id", "vec", F.shiftright("to", 16).alias("tree"), F.col("to").bitwiseAND(0xFFFF).alias("leaf"))
    visitors = {(r["tree"], r["leaf"]): r["count"] for r in visits.groupBy("tree", "leaf").count().collect()}  # at most trees x leaves
    # both sides of a leaf are cut into blocks by their own numbers; a leaf that nobody visits does not travel
    cut = [(r["tree"], r["leaf"], -(-r["count"] // (2 * leaf_rows)), -(-visitors[r["tree"], r["leaf"]] // BLOCK)) for r in counts if (r["tree"], r["leaf"]) in visitors]
    plan = F.broadcast(spark.createDataFrame(cut, "tree int, leaf int, parts int, rounds int"))
    members = spread(indexed).join(plan, ["tree", "leaf"]).withColumn("m", F.pmod(F.xxhash64("id"), F.col("parts")).cast("int")).withColumn("g", F.explode(F.sequence(F.lit(0), F.col("rounds") - 1))).drop("parts", "rounds")
    guests = visits.join(plan, ["tree", "leaf"]).withColumn("g", F.pmod(F.xxhash64("id"), F.col("rounds")).cast("int")).withColumn("m", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).drop("parts", "rounds")
    key = ["tree", "leaf", "m", "g"]
    guests = guests.select(*[F.col(c).alias(c) for c in (*key, "id", "vec")])  # fresh attribute names
    met = members.groupBy(key).cogroup(guests.groupBy(key)).applyInArrow(lambda a, b: best_of_block(a, b, kind, k), "query_id long, vec_id long, score double")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    ranked = met.groupBy("query_id", "vec_id").agg(F.max("score").alias("score")).withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)
    return ranked.select("query_id", "rank", "vec_id", "score")


def op5_nearest_neighbours(spark, sf_dir) -> DataFrame:
    """Contract query of operator 5: the 20 nearest found for each id divisible by 20, among all rows of ``embeddings``."""
    return nearest_neighbours(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"))


OP3_SQL = """
WITH RECURSIVE v AS (
  SELECT DISTINCT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings
), u AS (
  SELECT vec_id, e FROM v WHERE vec_id IS NOT NULL AND e IS NOT NULL AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND list_dot_product(e, e) > 0
), l AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM u a CROSS JOIN u b WHERE a.vec_id <> b.vec_id AND list_cosine_similarity(a.e, b.e) >= 0.95
), r AS (
  SELECT vec_id AS id, vec_id AS c FROM u UNION SELECT l.b, r.c FROM r JOIN l ON l.a = r.id WHERE r.c < l.b
), c AS (
  SELECT id, min(c) AS component FROM r GROUP BY 1
)
SELECT i.vec_id, CAST(coalesce(n, 0) AS BIGINT) AS n_links, coalesce(component, i.vec_id) AS component_id, coalesce(component, i.vec_id) IS NOT DISTINCT FROM i.vec_id AS kept
FROM (SELECT DISTINCT vec_id FROM embeddings) i LEFT JOIN c ON c.id = i.vec_id LEFT JOIN (SELECT a, count(*) AS n FROM l GROUP BY 1) k ON k.a = i.vec_id
"""

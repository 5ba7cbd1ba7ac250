"""Quality scores by Bradley-Terry ranking of documents.

A document's strength is a weighted sum of features of its whole text; the
weights maximise the likelihood of preferences between labelled documents, each
pair holding one of label 1 and one of label 0, so the loss is the logistic loss
of the feature difference.  The accepting threshold is a quantile of the
training strengths (near the share of label 0, where the two labels part best),
and strengths map to scores through a logistic curve
that takes the threshold to ``ACCEPT``.

Defined cases: null and empty texts have the features of an empty text and a
score like any other; labels that are null are not learnt from; a document
labelled twice counts twice; without learnable labels of both kinds (an empty
table, one class only) nothing can be preferred and every document scores
``ACCEPT``, so that none is rejected without a reason; equal texts score alike;
repeated rows repeat their results; a null id is never learnt from and counts as
held out; other columns are never read; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semtrie.llm.common import BROADCAST_ROWS, discard, materialize, mix64, pieces, table, text_bytes
from semtrie.llm.shingles import word_hashes

ACCEPT = 0.7
#: Labelled rows whose features go to the driver; of more, only sums do.
LOCAL_LABELLED = 50_000
#: Pairs up to which differences are formed one by one.
N_PAIRS = 60_000
#: Strengths beyond it count as this much; nodes to a unit of strength, of first sums and of a final count; and width between nodes of second sums.
REACH, FINE, COUNT, COARSE = 40, 16, 1024, 2.0

NAMES = (
    "log_words", "mean_word", "distinct_share", "log_distinct_share", "punct_share", "log_punct", "upper_share", "log_upper", "digit_share", "space_share", "end_marks",
    "commas", "pipe_share", "run_share", "repeat_next", "lines_per_word", "top_word_share", "symbol_word_share", "odd_start", "long_words", "bang_share", "short_text",
    "worst_repeat", "worst_symbol",
)


def _share(count: np.ndarray, total: np.ndarray) -> np.ndarray:
    return count / np.maximum(total, 1)


def text_features(raw: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Feature matrix of n texts given as joined UTF-8 bytes and n + 1 offsets."""
    n = len(at) - 1
    out = np.zeros((n, len(NAMES)))
    if n == 0:
        return out
    owner = np.repeat(np.arange(n), np.diff(at))
    size = np.diff(at).astype(np.float64)
    per_doc = lambda mask: np.bincount(owner[mask], minlength=n).astype(np.float64)
    space = (raw == 32) | ((raw >= 9) & (raw <= 13))
    upper = (raw >= 65) & (raw <= 90)
    lower = (raw >= 97) & (raw <= 122)
    digit = (raw >= 48) & (raw <= 57)
    wide = raw >= 128
    punct = ~(space | upper | lower | digit | wide)
    lead = ~space
    begin = lead.copy()
    begin[1:] &= space[:-1] | (owner[1:] != owner[:-1])
    end = lead.copy()
    end[:-1] &= space[1:] | (owner[1:] != owner[:-1])
    starts, ends = np.flatnonzero(begin), np.flatnonzero(end) + 1
    words = len(starts)
    letters, puncts = lower | upper | wide, punct
    w_owner = owner[starts] if words else np.zeros(0, np.int64)
    n_words = np.bincount(w_owner, minlength=n).astype(np.float64)
    if words:
        length = ends - starts
        c_punct = np.concatenate([[0], np.cumsum(puncts)])
        p_in = c_punct[ends] - c_punct[starts]
        h, _ = word_hashes(raw, at)  # of whole words, A-Z lower-cased
        order = np.lexsort((h, w_owner))
        so, sh = w_owner[order], h[order]
        fresh = np.ones(words, dtype=bool)
        fresh[1:] = (so[1:] != so[:-1]) | (sh[1:] != sh[:-1])
        distinct = np.bincount(so[fresh], minlength=n)
        run = np.diff(np.append(np.flatnonzero(fresh), words))
        top = np.zeros(n)
        np.maximum.at(top, so[fresh], run)
        same = np.zeros(words, dtype=bool)
        same[1:] = (h[1:] == h[:-1]) & (w_owner[1:] == w_owner[:-1])
        symbol = (p_in * 2 >= length) & (length > 1)
        heavy = p_in >= 2
        by_word = lambda mask: _share(np.bincount(w_owner[mask], minlength=n), n_words)
        # worst stretch of 32 words, for texts that are bad in one part only
        rank = np.arange(words) - np.repeat(np.cumsum(np.concatenate([[0], n_words[:-1]])).astype(np.int64), n_words.astype(np.int64))
        chunk = np.flatnonzero(rank % 32 == 0)
        in_chunk = np.diff(np.append(chunk, words))
        worst_repeat, worst_symbol = np.zeros(n), np.zeros(n)
        np.maximum.at(worst_repeat, w_owner[chunk], np.add.reduceat(same, chunk) / in_chunk)
        np.maximum.at(worst_symbol, w_owner[chunk], np.add.reduceat(heavy, chunk) / in_chunk)
        distinct_share = _share(distinct, n_words)
        out[:, 1] = _share(np.bincount(w_owner, weights=length, minlength=n), n_words)
        out[:, 2] = distinct_share
        out[:, 3] = np.log(distinct_share + 0.01)
        out[:, 14] = by_word(same)
        out[:, 16] = _share(top, n_words)
        out[:, 17] = by_word(symbol)
        out[:, 18] = by_word(puncts[starts])
        out[:, 19] = by_word(length >= 12)
        out[:, 13] = by_word(heavy)
        out[:, 22] = worst_repeat
        out[:, 23] = worst_symbol
    punct_share = _share(per_doc(punct), size)
    upper_share = _share(per_doc(upper), size)
    out[:, 0] = np.log1p(n_words)
    out[:, 4], out[:, 5] = punct_share, np.log(punct_share + 0.005)
    out[:, 6], out[:, 7] = upper_share, np.log(upper_share + 0.005)
    out[:, 8] = _share(per_doc(digit), size)
    out[:, 9] = _share(per_doc(space), size)
    out[:, 10] = _share(per_doc(raw == 46), n_words)
    out[:, 11] = _share(per_doc(raw == 44), n_words)
    out[:, 12] = _share(per_doc(raw == 124), n_words)
    out[:, 15] = _share(per_doc(raw == 10), n_words)
    out[:, 20] = _share(per_doc(raw == 33), n_words)
    out[:, 21] = (n_words < 20).astype(np.float64)
    return out


def expand(x: np.ndarray, centre: np.ndarray, scale: np.ndarray) -> np.ndarray:
    """Standardised, clipped features and their squares: good text lies in the middle of most ranges."""
    z = np.clip((x - centre) / scale, -8, 8)
    return np.hstack([z, z * z / 8])


@dataclass(frozen=True)
class Ranker:
    centre: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    threshold: float
    slope: float

    def strength(self, x: np.ndarray) -> np.ndarray:
        return expand(x, self.centre, self.scale) @ self.weights

    def score(self, x: np.ndarray) -> np.ndarray:
        t = self.slope * (self.strength(x) - self.threshold) + np.log(ACCEPT / (1 - ACCEPT))
        return 1 / (1 + np.exp(-np.clip(t, -500, 500)))


def _deposit(s: np.ndarray, step: float) -> tuple[np.ndarray, np.ndarray]:
    """Node below each strength and the share of the one above, on nodes ``step`` apart."""
    at = (np.clip(s, -REACH, REACH) + REACH) / step
    low = np.minimum(at.astype(np.int64), int(2 * REACH / step) - 1)
    return low, at - low


def pair_sums(z: np.ndarray, y: np.ndarray, w: np.ndarray) -> np.ndarray:
    """What a part of the rows adds to the sums over all pairs, as one vector.

    Per label: rows and sums of ``z`` at the fine nodes of strength ``z @ w``, and
    sums of ``z z'`` at the coarse ones, each row shared by the nodes on its sides.
    """
    out = []
    for label in (1, 0):
        x = z[y == label]
        s = x @ w
        low, up = _deposit(s, 1 / FINE)
        first = np.zeros((2 * REACH * FINE + 1, z.shape[1] + 1))
        both, share = np.concatenate([low, low + 1]), np.concatenate([1 - up, up])
        for c, column in enumerate([np.ones(len(x)), *x.T]):
            first[:, c] = np.bincount(both, weights=share * np.tile(column, 2), minlength=len(first))
        low, up = _deposit(s, COARSE)
        second = np.zeros((int(2 * REACH / COARSE) + 1, z.shape[1], z.shape[1]))
        for node in np.unique(low):
            rows = np.flatnonzero(low == node)
            second[node] += (x[rows] * (1 - up[rows])[:, None]).T @ x[rows]
            second[node + 1] += (x[rows] * up[rows][:, None]).T @ x[rows]
        out += [first.ravel(), second.ravel()]
    return np.concatenate(out)


def newton_step(sums: np.ndarray, w: np.ndarray, ridge: float) -> np.ndarray:
    """The step from ``w`` on the loss over all pairs: its slope by the fine nodes, its curvature by fine and coarse ones."""
    d, fine, coarse = len(w), 2 * REACH * FINE + 1, int(2 * REACH / COARSE) + 1
    half = len(sums) // 2
    first = [sums[i * half : i * half + fine * (d + 1)].reshape(fine, d + 1) for i in (0, 1)]
    second = [sums[i * half + fine * (d + 1) : (i + 1) * half].reshape(coarse, d, d) for i in (0, 1)]
    (n1, g1), (n0, g0) = ((f[:, 0], f[:, 1:]) for f in first)
    pairs = n1.sum() * n0.sum()
    at = np.arange(fine) / FINE
    p = 1 / (1 + np.exp(np.clip(at[:, None] - at[None], -30, 30)))  # good node by bad node: the chance that the pair is ranked wrongly
    gradient = ((p @ n0) @ g1 - (n1 @ p) @ g0) / pairs - ridge * w
    v = p * (1 - p)
    cross = g1.T @ v @ g0
    pick = slice(None, None, int(COARSE * FINE))
    hessian = (np.tensordot((v @ n0)[pick], second[0], 1) + np.tensordot((n1 @ v)[pick], second[1], 1) - cross - cross.T) / pairs
    # the coarse curvature may be a little off, so that its smallest direction is held positive
    values, vectors = np.linalg.eigh((hessian + hessian.T) / 2)
    return vectors @ ((vectors.T @ gradient) / (np.maximum(values, 0) + ridge))


def strength_counts(s: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Rows of label 1 and of label 0 by strength."""
    at = np.floor((np.clip(s, -REACH, REACH) + REACH) * COUNT).astype(np.int64)
    return np.concatenate([np.bincount(at[y == label], minlength=2 * REACH * COUNT + 1) for label in (1, 0)])


def threshold_of(counts: np.ndarray) -> tuple[float, float]:
    """(threshold, spread) from the counts of all rows: of the cuts near the share of label 0, the one with the best balanced accuracy."""
    good, bad = counts.reshape(2, -1)
    every = np.cumsum(good + bad)
    share = bad.sum() / every[-1]
    cuts = np.searchsorted(every, np.unique(np.clip(share * np.linspace(0.3, 1.3, 81), 0, 1)) * every[-1]).clip(0, len(good) - 1)
    below = lambda n: np.append(0, np.cumsum(n))[cuts] / n.sum()
    balanced = 1 - below(good) + below(bad)
    cut = int(cuts[np.flatnonzero(balanced >= balanced.max() - 2e-3)[0]])
    away = np.abs(np.arange(len(good)) + 0.5 - cut) / COUNT
    order = np.argsort(away, kind="stable")
    middle = np.searchsorted(np.cumsum((good + bad)[order]), every[-1] / 2)
    return cut / COUNT - REACH, float(away[order[middle]])


def fit_all_pairs(passes, dim: int, *, ridge: float = 1e-3, steps: int = 25) -> tuple[np.ndarray, float, float]:
    """(weights, threshold, spread) by Newton steps over every pair of label 1 and label 0; ``passes(f, w)`` adds up ``f`` over all rows."""
    w = np.zeros(dim)
    for _ in range(steps):
        step = newton_step(passes("pairs", w), w, ridge)
        w = w + step
        if np.abs(step).max() < 1e-5:
            break
    return w, *threshold_of(passes("counts", w))


def _pass(kind: str, z: np.ndarray, y: np.ndarray, w: np.ndarray) -> np.ndarray:
    return pair_sums(z, y, w) if kind == "pairs" else strength_counts(z @ w, y).astype(float)


def fit_bradley_terry(x: np.ndarray, y: np.ndarray, *, pairs: int = N_PAIRS, ridge: float = 1e-3, steps: int = 25) -> Ranker:
    """Newton steps on the pairwise logistic loss over all pairs: one by one up to ``pairs`` of them, by sums over strengths beyond."""
    good, bad = np.flatnonzero(y == 1), np.flatnonzero(y == 0)
    if not len(good) or not len(bad):
        raise ValueError("labels of both kinds are needed")
    centre = np.median(x[good], axis=0)
    scale = np.maximum(np.percentile(np.abs(x[good] - centre), 90, axis=0), 1e-3)
    z = expand(x, centre, scale)
    count = len(good) * len(bad)
    if count > pairs:
        w, threshold, spread = fit_all_pairs(lambda kind, w: _pass(kind, z, y, w), z.shape[1], ridge=ridge, steps=steps)
        return Ranker(centre, scale, w, threshold, 2.0 / spread)
    d = (z[good][:, None] - z[bad][None]).reshape(count, -1)
    w = np.zeros(z.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(np.clip(d @ w, -30, 30)))
        gradient = d.T @ p / count - ridge * w
        hessian = (d * (p * (1 - p))[:, None]).T @ d / count + ridge * np.eye(len(w))
        step = np.linalg.solve(hessian, gradient)
        w = w + step
        if np.abs(step).max() < 1e-7:
            break
    s = z @ w
    # quantile threshold: of the cuts near the share of label 0, the one with the best balanced accuracy
    share = len(bad) / len(y)
    cuts = np.quantile(s, np.unique(np.clip(share * np.linspace(0.3, 1.3, 81), 0, 1)))
    balanced = [(s[good] >= c).mean() + (s[bad] < c).mean() for c in cuts]
    best = np.flatnonzero(np.array(balanced) >= max(balanced) - 2e-3)
    threshold = float(cuts[best[0]])
    spread = float(np.median(np.abs(s - threshold))) or 1.0
    return Ranker(centre, scale, w, threshold, 2.0 / spread)


def neutral_ranker() -> Ranker:
    """The ranker where no preference is known: every document scores ``ACCEPT``."""
    n = len(NAMES)
    return Ranker(np.zeros(n), np.ones(n), np.zeros(2 * n), 0.0, 1.0)


def _features(batches: Iterator[pa.RecordBatch], keep: list[str]) -> Iterator[pa.RecordBatch]:
    for part in pieces(batches, "text"):
        x = text_features(*text_bytes(part.column("text")))
        column = pa.FixedSizeListArray.from_arrays(pa.array(x.ravel()), len(NAMES)).cast(pa.list_(pa.float64()))
        yield pa.RecordBatch.from_arrays([*(part.column(c) for c in keep), column], [*keep, "x"])


def learnable(doc_id: Column) -> Column:
    """Rows that may be learnt from: crc32 of the id's text, modulo 4, is not 2."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 4 != 2


def fit_ranker(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", local_labelled: int = LOCAL_LABELLED) -> Ranker:
    """Fit on every learnable labelled row and every pair of label 1 and label 0.

    Up to ``local_labelled`` rows of features go to the driver; of more, each
    Newton step takes sums of a fixed size from every part of the table, and
    centre and scale are percentiles of all rows by Spark's sketch.
    Without labels of both kinds the result is ``neutral_ranker()``.
    """
    known = labels.filter(F.col(label_col).isin(0, 1) & learnable(F.col(id_col))).select(F.col(id_col).cast("long").alias("doc_id"), F.col(label_col).cast("int").alias("y"))
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    labelled = known.count()
    if labelled <= BROADCAST_ROWS:
        rows = texts.join(F.broadcast(known), "doc_id").mapInArrow(lambda b: _features(b, ["doc_id", "y"]), "doc_id long, y int, x array<double>")
    else:  # features are shorter than texts
        rows = texts.mapInArrow(lambda b: _features(b, ["doc_id"]), "doc_id long, x array<double>").join(known, "doc_id").select("doc_id", "y", "x")
    rows = materialize(rows, "quality-features")
    if rows.count() > local_labelled:
        found = _fit_distributed(rows)
    else:
        held = rows.toPandas()
        held = held.iloc[np.lexsort((held["y"], mix64(held["doc_id"].to_numpy().astype(np.uint64))))]
        x = np.vstack(held["x"].to_numpy()) if len(held) else np.zeros((0, len(NAMES)))
        y = held["y"].to_numpy()
        found = fit_bradley_terry(x, y) if {0, 1} <= set(y.tolist()) else neutral_ranker()
    discard(rows)
    return found


def _fit_distributed(rows: DataFrame) -> Ranker:
    """``fit_bradley_terry`` on a table (y, x) of any size: parts of it send sums of a fixed size."""
    good = rows.filter("y = 1")
    if good.isEmpty() or rows.filter("y = 0").isEmpty():
        return neutral_ranker()
    feature = [F.get("x", F.lit(i)) for i in range(len(NAMES))]
    centre = np.array(good.agg(*[F.percentile_approx(f, 0.5, 100_000) for f in feature]).first())
    scale = np.array(good.agg(*[F.percentile_approx(F.abs(f - float(c)), 0.9, 100_000) for f, c in zip(feature, centre, strict=True)]).first())
    scale = np.maximum(scale, 1e-3)

    def passes(kind: str, w: np.ndarray) -> np.ndarray:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = None
            for batch in batches:
                if batch.num_rows:
                    x = batch.column("x").flatten().to_numpy().reshape(batch.num_rows, -1)
                    part = _pass(kind, expand(x, centre, scale), batch.column("y").to_numpy(), w)
                    total = part if total is None else total + part
            if total is not None:
                yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], ["sums"])

        total = None
        for r in rows.select("y", "x").coalesce(32).mapInArrow(run, "sums binary").collect():  # at most 32 rows of 2.5 MB
            part = np.frombuffer(r["sums"])
            total = part if total is None else total + part
        return total

    w, threshold, spread = fit_all_pairs(passes, 2 * len(NAMES))
    return Ranker(centre, scale, w, threshold, 2.0 / spread)


def score_documents(docs: DataFrame, ranker: Ranker, *, text_col: str = "text", out_col: str = "score") -> DataFrame:
    """Add the score of each whole text (null and empty texts included)."""
    keep = [c for c in docs.columns if c != out_col]
    inner = docs.select(*keep, F.col(text_col).cast("string").alias("__text"))
    schema = inner.drop("__text").schema.add(out_col, "double")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in pieces(batches, "__text"):
            score = ranker.score(text_features(*text_bytes(part.column("__text"))))
            yield pa.RecordBatch.from_arrays([*(part.column(c) for c in keep), pa.array(score)], [*keep, out_col])

    return inner.mapInArrow(run, schema)


def op2_quality_ranking(spark, sf_dir) -> DataFrame:
    """Contract query of operator 2: doc_id, held_out, score, predicted for every row of ``documents``."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    ranker = fit_ranker(docs, table(spark, sf_dir, "labels"))
    held = F.coalesce(~learnable(F.col("doc_id")), F.lit(True))
    scored = score_ids(docs, ranker)
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= ACCEPT).cast("int").alias("predicted"))


def score_ids(docs: DataFrame, ranker: Ranker) -> DataFrame:
    """(doc_id, score) only, so that texts do not travel back from Python."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in pieces(batches, "text"):
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(ranker.score(text_features(*text_bytes(part.column("text")))))], ["doc_id", "score"])

    return docs.mapInArrow(run, "doc_id long, score double")

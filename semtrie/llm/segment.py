"""Distinct sampled segmentations of whole texts by Gumbel top-k without replacement.

A text is cut into units (a run of word marks and the characters after it);
pieces of the vocabulary never cross a unit, so the text's lattice is the chain
of its units' lattices.  A lattice edge is a piece of the vocabulary (or the
bytes of a character the vocabulary lacks) with weight ``-s * log(rank + r0)``;
backward sums give each node's edge probabilities, so every segmentation has an
exact log-probability.

Sampling is a best-first search over prefixes by perturbed log-probability.  A
queue entry is a set of segmentations (all that share a prefix and then leave it
by an edge not yet taken) with the maximum of its Gumbel-perturbed values.  The
best entry is completed to the one segmentation that attains the maximum, and
the rest of its set is split along the new path into disjoint
entries whose maxima are drawn conditionally on being below the parent's; the
entries along a path are kept together as one lazily split range.
The k best completions are k distinct segmentations; with kappa the perturbed
value of the next one, the log inclusion score is log(1 - exp(-exp(phi - kappa))).
Draws come from a generator seeded by the row key and the seed alone, so results
do not depend on partitions, batches or retries.

Defined cases: a null or empty text has one segmentation, of no piece; texts with
fewer than k segmentations return all they have, with inclusion score 0; decoding
an encoding gives back the exact text (a literal word mark travels as bytes);
a null key counts as key 0; repeated rows repeat their results.
"""

from __future__ import annotations

import functools
import hashlib
import heapq
import math
import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semtrie.llm.common import mix64, pieces, table

DEFAULT_MODEL = "/opt/tokenizers/piece_bpe_32k.model"
MARK = "▁"
BATCH = 1 << 21
SIEVE = 20
UNIT = re.compile(" *[^ ]+| +")


class Vocabulary:
    """Pieces of a model as hashes by length, with their lattice weights."""

    def __init__(self, model_path: str, slope: float, shift: float):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=model_path)
        size = model.vocab_size()
        self.names = [model.id_to_piece(i) for i in range(size)]
        self.bytes_of = {int(n[3:5], 16): i for i, n in enumerate(self.names) if model.is_byte(i)}
        if len(self.bytes_of) != 256:
            raise ValueError("the vocabulary has no byte pieces to fall back on")
        self.ascii = np.array([self.bytes_of[b] for b in range(128)], dtype=np.int32)
        self.byte_at = {i: b for b, i in self.bytes_of.items()}
        self.raw = [bytes([self.byte_at[i]]) if i in self.byte_at else n.replace(MARK, " ").encode() for i, n in enumerate(self.names)]
        self.bytes = pa.array(self.raw, pa.large_binary())
        plain = [i for i in range(size) if not (model.is_byte(i) or model.is_unknown(i) or model.is_control(i))]
        weight = {i: -slope * math.log(min(max(0.0, -model.get_score(i)), size) + shift) for i in plain}
        self.byte_weight = -slope * math.log(size + shift)
        self.longest = max(len(self.names[i]) for i in plain)
        # pieces in a table by the leading bits of their hash; pieces that share a place go to the next level
        self.longer = np.zeros(1 << SIEVE, dtype=bool)  # places of proper prefixes of pieces
        hashes = np.zeros(len(plain), dtype=np.uint64)
        sizes = np.array([len(self.names[i]) for i in plain])
        self.lengths = set(sizes.tolist())
        for length in self.lengths:
            rows = np.flatnonzero(sizes == length)
            h = np.zeros(len(rows), dtype=np.uint64)
            for column in np.array([[ord(c) for c in self.names[plain[r]]] for r in rows], dtype=np.uint64).T:
                self.longer[place_of(h)] = True
                h = roll(h, column)
            hashes[rows] = h
        self.hash, self.id = hashes, np.array(plain, dtype=np.int32)
        self.weight = np.array([weight[i] for i in plain])
        self.levels = []
        rest = np.arange(len(plain))
        while len(rest):
            level = np.full(1 << SIEVE, -1, dtype=np.int32)
            place = place_of(hashes[rest])
            level[place] = rest
            self.levels.append(level)
            rest = rest[level[place] != rest]

    def find(self, h: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(position, piece row) of the hashes that are pieces."""
        at, rows = [], []
        left = np.arange(len(h))
        for level in self.levels:
            row = level[place[left]]
            some = np.flatnonzero(row >= 0)
            left, row = left[some], row[some]
            same = self.hash[row] == h[left]
            at.append(left[same])
            rows.append(row[same])
            left = left[~same]
        order = np.argsort(at := np.concatenate(at), kind="stable")
        return at[order], np.concatenate(rows)[order]


def place_of(h: np.ndarray) -> np.ndarray:
    return (h >> np.uint64(64 - SIEVE)).view(np.int64)


def utf8_width(codes: np.ndarray) -> np.ndarray:
    return 1 + (codes >= 0x80).astype(np.int32) + (codes >= 0x800) + (codes >= 0x10000)


def roll(h: np.ndarray, codes: np.ndarray) -> np.ndarray:
    return (h ^ (codes + np.uint64(0x9E3779B9))) * np.uint64(0xD6E8FEB86659FD93) + (h >> np.uint64(29))


@functools.lru_cache(maxsize=2)
def vocabulary(model_path: str, slope: float, shift: float) -> Vocabulary:
    return Vocabulary(model_path, slope, shift)


class Lattices:
    """Lattices of a batch's distinct units in flat arrays, all built together.

    A node is a position of the joined units; ``to`` is an edge's end node, or
    -1 at the unit's end.  ``low`` holds node number plus cumulative probability
    of the edges other than the likeliest.
    """

    def __init__(self, units: list[str], vocab: Vocabulary):
        self.vocab = vocab
        lengths = np.array([len(u) for u in units], dtype=np.int32)
        joined = "".join(units)
        codes = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), dtype="<u4")
        self.codes = codes
        n = len(codes)
        self.base = (np.cumsum(lengths) - lengths).astype(np.int32)
        stop = np.repeat(self.base + lengths, lengths)
        # a space of the text is the word mark; a literal word mark matches no piece
        seen = np.where(codes == 32, np.uint32(ord(MARK)), np.where(codes == ord(MARK), np.uint32(0x110000), codes))
        room = stop - np.arange(n, dtype=np.int32)
        h = np.zeros(n, dtype=np.uint64)
        parts: list[tuple] = []
        live = np.arange(n, dtype=np.int32)
        fan = np.zeros(n, dtype=np.int32)  # edges found so far at each node: an edge's rank among its node's

        def found_edges(at: np.ndarray, length: int, ids: np.ndarray, weights: np.ndarray) -> None:
            parts.append((at, fan[at], np.full(len(at), length, dtype=np.int32), ids, weights))
            fan[at] += 1

        for length in range(1, vocab.longest + 1):
            if not len(live):
                break
            here = h = roll(h, seen[live + (length - 1)].astype(np.uint64))
            place = place_of(h)
            now, going = live, np.flatnonzero(vocab.longer[place] & (room[live] > length))
            live, h = live[going], h[going]
            if length in vocab.lengths:
                hit, row = vocab.find(here, place)
                found_edges(now[hit], length, vocab.id[row], vocab.weight[row])
            if length == 1:
                lost = np.flatnonzero(fan == 0).astype(np.int32)
                byte_ids = np.where(codes[lost] < 0x80, vocab.ascii[codes[lost] & 0x7F], np.int32(-1))  # -1: several bytes
                found_edges(lost, 1, byte_ids, vocab.byte_weight * utf8_width(codes[lost]))
        self.start = np.append(np.int32(0), np.cumsum(fan, dtype=np.int32))
        edges = int(self.start[-1])
        self.node, length, self.code = (np.empty(edges, dtype=np.int32) for _ in range(3))
        weight = np.empty(edges)
        for at, rank, length_, ids, weights in parts:
            place = self.start[at] + rank
            self.node[place], length[place], self.code[place], weight[place] = at, length_, ids, weights
        del parts, seen, h
        end = self.node + length
        # backward sums, all units together, by distance from the unit's end
        after = np.zeros(n + 1)
        ends_unit = end == stop[self.node] if n else np.zeros(0, bool)
        distance = room[self.node] if n else np.zeros(0, np.int32)
        deepest = int(room.max()) if n else 0
        by_distance = np.argsort(distance.astype(np.int16) if deepest < 1 << 15 else distance, kind="stable").astype(np.int32)
        cuts = np.append(0, np.cumsum(np.bincount(distance, minlength=deepest + 1)))[1:] if n else np.zeros(1, np.int64)
        # arrays in that order once, so that each step works on slices
        w, to_, nd = weight[by_distance], np.where(ends_unit, np.int32(n), end)[by_distance], self.node[by_distance]
        head = np.flatnonzero(np.diff(nd, prepend=-1) != 0)
        head_node = nd[head]
        head_cuts = np.searchsorted(head, cuts)
        for lo, hi, first, last in zip(cuts[:-1], cuts[1:], head_cuts[:-1], head_cuts[1:], strict=True):
            s = w[lo:hi] + after[to_[lo:hi]]
            begin = head[first:last] - lo
            top = np.maximum.reduceat(s, begin)
            count = fan[head_node[first:last]]
            total = top + np.log(np.add.reduceat(np.exp(s - np.repeat(top, count)), begin))
            after[head_node[first:last]] = total
            w[lo:hi] = s - np.repeat(total, count)
        score = np.empty(edges)
        score[by_distance] = w
        self.logp = np.minimum(score, 0.0)
        self.to = np.where(ends_unit, np.int32(-1), end)
        p = np.exp(self.logp)
        # drawing an edge: the likeliest one by a comparison, the others by one sorted search
        first = self.start[:-1]
        best = np.maximum.reduceat(p, first) if n else p
        top_edges = np.flatnonzero(p == np.repeat(best, fan)).astype(np.int32)
        self.top = top_edges[np.diff(self.node[top_edges], prepend=-1) != 0]
        self.p_top = best
        rest = np.ones(len(p), dtype=bool)
        rest[self.top] = False
        self.other_edges = np.flatnonzero(rest).astype(np.int32)
        owner, q = self.node[self.other_edges], p[self.other_edges]
        running = np.cumsum(q) - q
        lead = np.flatnonzero(np.diff(owner, prepend=-1))
        share = np.diff(np.append(lead, len(owner)))
        total = np.add.reduceat(q, lead) if len(q) else q
        within = (running - np.repeat(running[lead], share)) / np.repeat(np.maximum(total, 1e-300), share)
        self.low = owner + np.clip(within, 0.0, 1 - 1e-9)
        others = 1.0 - p
        alone = fan[self.node] == 1 if n else np.zeros(0, bool)
        # the mass of a node's other edges, summed when the difference would lose digits
        self.leave = np.where(alone, -np.inf, np.log(np.maximum(others, 1e-300)))
        close = np.flatnonzero(~alone & (others < 1e-6))
        if len(close):
            first = self.start[self.node[close]]
            fan_of = first[:, None] + np.arange(vocab.longest + 1)
            inside = (fan_of < self.start[self.node[close] + 1][:, None]) & (fan_of != close[:, None])
            rest = np.where(inside, p[np.minimum(fan_of, len(p) - 1)], 0.0).sum(axis=1)
            self.leave[close] = np.log(np.maximum(rest, 1e-300))
        self.width = np.ones(edges, dtype=np.int32)
        missing = np.flatnonzero(self.code < 0)
        self.width[missing] = utf8_width(codes[self.node[missing]])

    def draw(self, nodes: np.ndarray, u: np.ndarray) -> np.ndarray:
        """One edge out of each node, by uniform draws."""
        edge = self.top[nodes]
        p = self.p_top[nodes]
        other = np.flatnonzero(u >= p)
        if len(other):
            v = (u[other] - p[other]) / (1.0 - p[other])
            found = np.searchsorted(self.low, nodes[other] + np.minimum(v, 1 - 1e-9), side="right") - 1
            found = self.other_edges[np.maximum(found, 0)]
            good = self.node[found] == nodes[other]  # a node of one edge has p = 1 up to rounding
            edge[other[good]] = found[good]
        return edge

    def fallback_ids(self, edge: int) -> list[int]:
        return [self.vocab.bytes_of[b] for b in chr(int(self.codes[self.node[edge]])).encode("utf-8", "surrogatepass")]


def decode(ids: list[int], vocab: Vocabulary) -> str:
    """The exact text of a list of piece ids (the inverse of any segmentation)."""
    return b"".join([vocab.raw[i] for i in ids]).decode("utf-8", "surrogatepass")[1:]


def units_of(text: str) -> list[str]:
    return UNIT.findall(" " + text) if text else []


def _gumbel(u: float) -> float:
    return -math.log(-math.log(u))


def _below(location: float, bound: float, u: float) -> float:
    """A Gumbel variable at ``location`` conditioned on being at most ``bound``."""
    a, b = -bound, -location + math.log(-math.log(u))
    hi, lo = max(a, b), min(a, b)
    return -(hi + math.log1p(math.exp(lo - hi)))


GOLDEN = 0x9E3779B97F4A7C15
ALL = (1 << 64) - 1


def scatter(x: int) -> int:
    x = (x ^ (x >> 30)) * 0xBF58476D1CE4E5B9 & ALL
    x = (x ^ (x >> 27)) * 0x94D049BB133111EB & ALL
    return x ^ (x >> 31)


class _Draws:
    """Uniform draws of one row: a counter under a hash of seed and key, so any draw can be made alone."""

    def __init__(self, key: int, seed: int):
        self.stream = scatter((scatter((seed * GOLDEN + 1) & ALL) + (key & ALL) * GOLDEN) & ALL)
        self.at = 0

    def one(self) -> float:
        self.at += 1
        return ((scatter((self.stream + self.at * GOLDEN) & ALL) >> 11) + 0.5) * 2.0**-53

    def branch(self) -> int:
        """The start of a separate stream, for a whole completion."""
        self.at += 1
        return scatter((self.stream ^ scatter((self.at * GOLDEN) & ALL)) & ALL)


def complete(lat: Lattices, at: np.ndarray, counter: np.ndarray, stream: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """From each node on to its unit's end: the edges drawn, and how many for each start.

    Start i draws from ``stream[i]`` at ``counter[i]``, whatever stands beside it.
    """
    live, rounds, who = np.arange(len(at), dtype=np.int32), [], []
    count = np.zeros(len(at), dtype=np.int32)
    state = stream + counter.astype(np.uint64) * np.uint64(GOLDEN)
    while len(live):
        u = ((mix64(state) >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53
        edge = lat.draw(at, u)
        rounds.append(edge)
        who.append(live)
        count[live] += 1
        to = lat.to[edge]
        go = np.flatnonzero(to >= 0)
        at, live = to[go], live[go]
        state = mix64(state[go] ^ np.uint64(GOLDEN))
    base = np.cumsum(count) - count
    edges = np.empty(int(count.sum()), dtype=np.int32)
    for r, (starts, edge) in enumerate(zip(who, rounds, strict=True)):
        edges[base[starts] + r] = edge
    return edges, count


class Sampler:
    """Best-first search over the segmentations of one text."""

    def __init__(self, nodes: np.ndarray, lat: Lattices, draws: _Draws):
        self.nodes, self.lat, self.draws = nodes, lat, draws
        self.tie = 0
        self.queue: list[tuple] = []
        # the whole set: nothing fixed, nothing excluded
        self._push(_gumbel(draws.one()), ("node", np.zeros(0, np.int32), 0.0, 0, int(nodes[0]) if len(nodes) else -1, frozenset()))

    def _push(self, value: float, entry: tuple) -> None:
        self.tie += 1
        heapq.heappush(self.queue, (-value, self.tie, entry))

    def _pick(self, node: int, excluded: frozenset) -> int:
        lat = self.lat
        edges = [e for e in range(lat.start[node], lat.start[node + 1]) if e not in excluded]
        mass = np.exp(lat.logp[edges])
        return edges[min(int(np.searchsorted(np.cumsum(mass), self.draws.one() * mass.sum(), side="right")), len(edges) - 1)]

    def _push_range(self, bound: float, path: np.ndarray, before: np.ndarray, units: np.ndarray, lo: int, hi: int) -> None:
        """All that follows ``path`` to some place in [lo, hi) and leaves it there, as one entry."""
        if lo >= hi:
            return
        mass = before[lo:hi] + self.lat.leave[path[lo:hi]]
        top = float(mass.max())
        if top == -math.inf:
            return
        total = top + math.log(float(np.exp(mass - top).sum()))
        self._push(_below(total, bound, self.draws.one()), ("range", path, before, units, lo, hi))

    def begin(self) -> tuple[np.ndarray, np.ndarray, int] | None:
        """Take the best entry and fix where it leaves its prefix.

        Returns the nodes still to be completed, their counters and their
        stream; None if all segmentations have been returned.
        """
        if not self.queue:
            return None
        value, _, entry = heapq.heappop(self.queue)
        value = -value
        lat = self.lat
        if entry[0] == "range":
            _, path, before, units, lo, hi = entry
            mass = before[lo:hi] + lat.leave[path[lo:hi]]
            share = np.cumsum(np.exp(mass - mass.max()))
            j = lo + min(int(np.searchsorted(share, self.draws.one() * share[-1], side="right")), hi - lo - 1)
            self._push_range(value, path, before, units, lo, j)
            self._push_range(value, path, before, units, j + 1, hi)
            entry = ("node", path[:j], float(before[j]), int(units[j]), int(lat.node[path[j]]), frozenset([int(path[j])]))
        _, kept, start, unit, node, excluded = entry
        if node < 0:
            self.open = (value, start, kept, unit, node, excluded, -1, unit)
            return np.zeros(0, np.int64), np.zeros(0, np.int64), 0
        first = self._pick(node, excluded)
        to = int(lat.to[first])
        from_unit = unit if to >= 0 else unit + 1
        at = self.nodes[from_unit:]
        if to >= 0:
            at = at.copy()
            at[0] = to
        self.open = (value, start, kept, unit, node, excluded, first, from_unit)
        return at, np.arange(from_unit, from_unit + len(at)), self.draws.branch()

    def finish(self, rest: np.ndarray, count: np.ndarray) -> tuple[float, float, np.ndarray]:
        """(perturbed value, log-probability, edges) of the segmentation begun, and entries for the rest of its set."""
        value, start, kept, unit, node, excluded, first, from_unit = self.open
        if node < 0:
            return value, start, kept
        lat = self.lat
        path = np.concatenate([kept, np.array([first], dtype=np.int32), rest])
        steps = lat.logp[path[len(kept) :]]
        before = np.empty(len(path) + 1)
        before[: len(kept)] = 0.0
        before[len(kept)] = start
        np.cumsum(steps, out=before[len(kept) + 1 :])
        before[len(kept) + 1 :] += start
        units = np.empty(len(path), dtype=np.int32)
        units[: len(kept) + 1] = unit
        units[len(kept) + 1 :] = np.repeat(np.arange(from_unit, from_unit + len(count)), count)
        taken = excluded | {first}
        others = [e for e in range(lat.start[node], lat.start[node + 1]) if e not in taken]
        if others:
            mass = start + math.log(max(float(np.exp(lat.logp[others]).sum()), 1e-300))
            self._push(_below(mass, value, self.draws.one()), ("node", kept, start, unit, node, frozenset(taken)))
        self._push_range(value, path, before[:-1], units, len(kept) + 1, len(path))
        return value, float(before[-1]), path


def log_inclusion(phi: float, kappa: float | None) -> float:
    if kappa is None:
        return 0.0
    x = phi - kappa
    return x if x < -37 else math.log(-math.expm1(-math.exp(min(x, 700.0))))


def search_texts(nodes: list[np.ndarray], keys: list[int], k: int, seed: int, lat: Lattices) -> list[list[tuple[float, float, np.ndarray, float]]]:
    """For each text up to k distinct segmentations: (perturbed value, log-probability, edges, log inclusion score).

    The searches advance together, so that one vectorised pass completes the
    current best entry of every text.
    """
    searches = [Sampler(n, lat, _Draws(key, seed)) for n, key in zip(nodes, keys, strict=True)]
    found: list[list] = [[] for _ in searches]
    for _ in range(k):
        begun = [(i, asked) for i, s in enumerate(searches) if (asked := s.begin()) is not None]
        if not begun:
            break
        sizes = [len(asked[0]) for _, asked in begun]
        edges, count = complete(
            lat,
            np.concatenate([a[0] for _, a in begun]),
            np.concatenate([a[1] for _, a in begun]),
            np.repeat(np.array([a[2] for _, a in begun], dtype=np.uint64), sizes),
        )
        starts = np.cumsum([0, *sizes])
        cuts = np.concatenate([[0], np.cumsum(count)])
        for (i, _), lo, hi in zip(begun, starts[:-1], starts[1:], strict=True):
            found[i].append(searches[i].finish(edges[cuts[lo] : cuts[hi]], count[lo:hi]))
    out = []
    for search, rows in zip(searches, found, strict=True):
        kappa = -search.queue[0][0] if search.queue else None
        out.append([(*f, log_inclusion(f[1], kappa)) for f in rows])
    return out


def unit_lattices(texts: list[str], vocab: Vocabulary) -> tuple[Lattices, list[np.ndarray]]:
    """Lattices of the texts' distinct units, and each text as the nodes its units start at.

    All texts are split at single spaces and numbered in one vectorised pass;
    empty words stand for further spaces, which lead the unit of the next word
    or make the last unit.
    """
    words = pc.split_pattern(pa.array(texts, pa.large_string()), " ")
    coded = words.values.dictionary_encode()
    units = [" " + w for w in coded.dictionary.to_pylist()]
    codes, ends = coded.indices.to_numpy(), words.offsets.to_numpy()
    kept = np.ones(len(codes), dtype=bool)
    kept[ends[:-1][[not t for t in texts]]] = False
    empty = pc.index(coded.dictionary, pa.scalar("", pa.large_string())).as_py()
    if empty >= 0:
        kept &= codes != empty
        full = np.flatnonzero(kept)
        text = np.repeat(np.arange(len(texts)), np.diff(ends))
        before = np.concatenate([[-1], full[:-1]])[: len(full)]
        spaces = np.zeros(len(codes), dtype=np.int64)  # beyond the one of each unit
        spaces[full] = full - np.maximum(before, ends[text[full]] - 1) - 1
        last = ends[:-1] - 1  # the last word that is not empty, or the place before the text
        np.maximum.at(last, text[full], full)
        trail = np.flatnonzero((last < ends[1:] - 1) & np.array([bool(t) for t in texts]))
        kept[ends[1:][trail] - 1] = True
        spaces[ends[1:][trail] - 1] = ends[1:][trail] - 2 - last[trail]
        wide = np.flatnonzero(spaces)
        if len(wide):
            pairs, number = np.unique(np.stack([codes[wide].astype(np.int64), spaces[wide]]), axis=1, return_inverse=True)
            codes = codes.astype(np.int64)
            codes[wide] = len(units) + number.ravel()
            units += [" " * n + units[c] for c, n in pairs.T.tolist()]
    lat = Lattices(units, vocab)
    at = np.append(0, np.cumsum(kept))[ends]
    flat = lat.base[codes[kept]]
    return lat, [flat[lo:hi] for lo, hi in zip(at[:-1], at[1:], strict=True)]


SCHEMA = "doc_id long, sample int, n_pieces long, logp double, perturbed double, log_inclusion double, exact boolean, pieces_sha1 string"


def _sample(batches: Iterator[pa.RecordBatch], k: int, seed: int, model: str, slope: float, shift: float, with_ids: bool, batch_bytes: int = BATCH) -> Iterator[pa.RecordBatch]:
    vocab = vocabulary(model, slope, shift)
    pa.default_memory_pool().release_unused()  # what an earlier stage left in this worker
    for part in pieces(batches, "text", batch_bytes):
        texts = [t or "" for t in part.column("text").to_pylist()]
        lat, nodes = unit_lattices(texts, vocab)
        keys = part.column("doc_id").to_pylist()
        found = search_texts(nodes, [key or 0 for key in keys], k, seed, lat)
        count = [len(f) for f in found]
        values, logps, paths, scores = zip(*[s for f in found for s in f], strict=True)
        ids = [path_ids(edges, lat) for edges in paths]
        del lat, nodes, found, paths
        yield _rows(np.repeat(np.arange(len(texts)), count).tolist(), keys, texts, values, logps, scores, ids, [r for n in count for r in range(n)], vocab, with_ids)


def _rows(owner: list[int], keys: list, texts: list[str], values: tuple, logps: tuple, scores: tuple, ids: list[np.ndarray], rank: list[int], vocab: Vocabulary, with_ids: bool) -> pa.RecordBatch:
    """The rows of a batch's samples; whether a sample decodes to its text is seen in the joined bytes of its pieces."""
    size = np.array([len(i) for i in ids])
    ends = np.append(0, np.cumsum(size))
    flat = np.concatenate(ids).astype(np.int32, copy=False)
    exact, raw = [], [(" " + t).encode("utf-8", "surrogatepass") if t else b"" for t in texts]
    for lo in range(0, len(ids), 64):
        part = vocab.bytes.take(pa.array(flat[ends[lo] : ends[min(lo + 64, len(ids))]]))
        _, offsets, data = part.buffers()
        at = np.frombuffer(offsets, np.int64, len(part) + 1)
        data, cut = bytes(data or b""), at[ends[lo : lo + 65] - ends[lo]].tolist()
        exact += [data[a:b] == raw[o] for a, b, o in zip(cut, cut[1:], owner[lo : lo + 64], strict=False)]
    sha = [hashlib.sha1(i.astype("<i4", copy=False).data).hexdigest() for i in ids]
    columns = [([keys[o] for o in owner], pa.int64()), (rank, pa.int32()), (size, pa.int64()), (logps, pa.float64()), (values, pa.float64()), (scores, pa.float64()), (exact, pa.bool_()), (sha, pa.string())]
    arrays, names = [pa.array(v, t) for v, t in columns], [n.split()[0] for n in SCHEMA.split(", ")]
    if with_ids:
        arrays.append(pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(flat)))
    return pa.RecordBatch.from_arrays(arrays, [*names, *(["ids"] if with_ids else [])])


def path_ids(edges: np.ndarray, lat: Lattices) -> np.ndarray:
    """Piece ids along a path; characters the vocabulary lacks become their byte pieces."""
    ids = lat.code[edges]
    missing = np.flatnonzero(ids < 0)
    if not len(missing):
        return ids
    width = lat.width[edges]
    out, at = np.repeat(ids, width), np.cumsum(width) - width
    for i in missing:
        labels = lat.fallback_ids(int(edges[i]))
        out[at[i] : at[i] + len(labels)] = labels
    return out


def sample_segmentations(
    docs: DataFrame,
    *,
    id_col: str = "doc_id",
    text_col: str = "text",
    k: int = 2,
    seed: int = 7,
    model: str = DEFAULT_MODEL,
    slope: float = 1.0,
    shift: float = 10.0,
    with_ids: bool = True,
    batch_bytes: int = BATCH,
) -> DataFrame:
    """k distinct sampled segmentations per row with scores; ``with_ids`` adds the piece ids themselves.

    ``batch_bytes`` of text share one set of lattices: more saves time, less
    saves memory; results do not depend on it.  ``exact`` says that decoding the sampled pieces gave back the text.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(lambda b: _sample(b, k, seed, model, slope, shift, with_ids, batch_bytes), SCHEMA + (", ids array<int>" if with_ids else ""))


def decode_column(df: DataFrame, *, ids_col: str = "ids", out_col: str = "decoded", model: str = DEFAULT_MODEL) -> DataFrame:
    """Add the text of a column of piece ids."""
    @F.pandas_udf("string")
    def decoded(ids: pd.Series) -> pd.Series:
        vocab = vocabulary(model, 1.0, 10.0)
        return ids.map(lambda x: decode(list(x), vocab) if x is not None else None)

    return df.withColumn(out_col, decoded(ids_col))


def encode_best(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", model: str = DEFAULT_MODEL) -> DataFrame:
    """The library's own (deterministic) encoding of each text."""

    def run(batches):
        import sentencepiece

        model_ = sentencepiece.SentencePieceProcessor(model_file=model)
        for part in pieces(batches, "text"):
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(model_.encode([t or "" for t in part.column("text").to_pylist()], num_threads=1), pa.list_(pa.int32()))], ["doc_id", "ids"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, ids array<int>")


def op10_sample_segmentations(spark, sf_dir) -> DataFrame:
    """Query of operator 10: two sampled segmentations of every whole text of ``documents``, piece ids included."""
    return sample_segmentations(table(spark, sf_dir, "documents"))

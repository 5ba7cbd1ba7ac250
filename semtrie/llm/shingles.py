"""Word shingle sets and SuperMinHash signatures of whole texts, vectorised over Arrow batches."""

from __future__ import annotations

import functools

import numpy as np

from semtrie.llm.common import mix64

BASE = 0x9E3779B97F4A7C55
SPACES = np.zeros(256, dtype=bool)
SPACES[[0x20, *range(0x09, 0x0E)]] = True
FOLD = np.arange(256, dtype=np.uint64)
FOLD[65:91] += 32


#: Places of the power tables; powers beyond come from two factors, so that tables never grow with a text.
LOW = 1 << 20


@functools.lru_cache(maxsize=4)
def _table(inverse: bool, step: int, n: int) -> np.ndarray:
    """The first ``n`` powers of the base (or its inverse) to the ``step``, modulo 2^64."""
    base = pow(pow(BASE, -1, 1 << 64) if inverse else BASE, step, 1 << 64)
    with np.errstate(over="ignore"):
        return np.multiply.accumulate(np.append(np.uint64(1), np.full(n - 1, base, dtype=np.uint64)))


def powers(at: np.ndarray, inverse: bool = False) -> np.ndarray:
    """Powers of the base (or of its inverse) modulo 2^64, for any exponents."""
    if not len(at) or int(at.max()) < LOW:
        return _table(inverse, 1, LOW)[at]
    return _table(inverse, 1, LOW)[at & (LOW - 1)] * _table(inverse, LOW, int(at.max()) // LOW + 1)[at // LOW]


def prefix_sums(values: np.ndarray) -> np.ndarray:
    """n + 1 running sums of ``values[i] * base^i`` modulo 2^64: one entry more than values."""
    n = len(values)
    total = np.zeros(n + 1, dtype=np.uint64)
    for lo in range(0, n, LOW):
        hi = min(lo + LOW, n)
        lead = np.uint64(pow(BASE, lo, 1 << 64))
        with np.errstate(over="ignore"):
            np.cumsum(values[lo:hi] * (_table(False, 1, LOW)[: hi - lo] * lead), out=total[lo + 1 : hi + 1])
            total[lo + 1 : hi + 1] += total[lo]
    return total


def word_hashes(raw: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hash of each word (A-Z lower-cased, split at ASCII white space) and the text it belongs to."""
    n = len(raw)
    if n == 0:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    word = ~SPACES[raw]
    cut = np.zeros(n + 1, dtype=bool)
    cut[at] = True
    begin = word.copy()
    begin[1:] &= ~word[:-1] | cut[1:n]
    end = word.copy()
    end[:-1] &= ~word[1:] | cut[1:n]
    starts, ends = np.flatnonzero(begin), np.flatnonzero(end) + 1
    h = np.zeros(len(starts), dtype=np.uint64)
    # block by block, so that memory beside the text stays the same for texts of any length
    for lo in range(0, n, LOW):
        hi = min(lo + LOW, n)
        first, last = np.searchsorted(ends, lo, side="right"), np.searchsorted(starts, hi, side="left")
        if first == last:
            continue
        total = prefix_sums(FOLD[raw[lo:hi]] + np.uint64(1))
        s, e = np.maximum(starts[first:last], lo), np.minimum(ends[first:last], hi)
        part = (total[e - lo] - total[s - lo]) * powers(s - lo, True)
        # a word that began in an earlier block goes on where it was cut
        h[first:last] += part * powers(s - starts[first:last])
    return mix64(h + (ends - starts).astype(np.uint64) * np.uint64(0xD1B54A32D192ED03)), np.searchsorted(at, starts, side="right") - 1


def shingle_sets(raw: np.ndarray, at: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of all texts, sorted within each text, and the n + 1 offsets of the texts.

    A text of fewer than ``k`` words, but at least one, has its whole word sequence as its one shingle.
    """
    n = len(at) - 1
    words, owner = word_hashes(raw, at)
    count = np.bincount(owner, minlength=n)
    first = np.cumsum(count) - count
    long = np.maximum(count - k + 1, 0)
    made = long + ((count > 0) & (count < k))
    out = np.empty(int(made.sum()), dtype=np.uint64)
    place = np.cumsum(made) - made
    if long.sum():
        origin = np.repeat(first - (np.cumsum(long) - long), long) + np.arange(int(long.sum()))
        h = np.full(len(origin), k, dtype=np.uint64)
        for i in range(k):
            h = mix64(h * np.uint64(BASE) + words[origin + i])
        target = np.repeat(place - (np.cumsum(long) - long), long) + np.arange(int(long.sum()))
        out[target] = h
    for d in np.flatnonzero((count > 0) & (count < k)):
        h = np.array([count[d]], dtype=np.uint64)
        for i in range(count[d]):
            h = mix64(h * np.uint64(BASE) + words[first[d] + i])
        out[place[d]] = h[0]
    kept, sizes = [], np.zeros(n, dtype=np.int64)
    for d in np.flatnonzero(made):
        part = np.unique(out[place[d] : place[d] + made[d]])
        kept.append(part)
        sizes[d] = len(part)
    return (np.concatenate(kept) if kept else np.zeros(0, np.uint64)), np.concatenate([[0], np.cumsum(sizes)])


def super_minhash(hashes: np.ndarray, offsets: np.ndarray, m: int) -> np.ndarray:
    """SuperMinHash signatures, one row of ``m`` values per set (empty sets: all ones).

    Each element draws a random permutation of the slots step by step; step j
    offers the value (j, r) to the permutation's j-th slot and a slot keeps its
    least value.  A set whose slots all hold values of earlier steps stops, since
    no later step can lower them; steps run over all unfinished sets at once.
    """
    n = len(offsets) - 1
    sizes = np.diff(offsets)
    signature = np.full((n, m), np.iinfo(np.uint64).max, dtype=np.uint64)
    flat = signature.ravel()
    owner = np.repeat(np.arange(n), sizes)
    state = hashes
    live = np.arange(len(hashes))
    # permutations are kept only from the second step on, for the few sets that need it
    perm: np.ndarray | None = None
    first_pick: np.ndarray | None = None
    for j in range(m):
        if not len(live):
            break
        state = mix64(state + np.uint64(BASE))
        r = state >> np.uint64(32)
        pick = j + ((state & np.uint64(0xFFFFFFFF)) * np.uint64(m - j) >> np.uint64(32)).astype(np.int64)
        if j == 0:
            slot, first_pick = pick, pick
        else:
            if perm is None:
                perm = np.tile(np.arange(m, dtype=np.uint16), (len(live), 1))
                rows = np.arange(len(live))
                perm[rows, first_pick] = 0
                perm[rows, 0] = first_pick
            rows = np.arange(len(live))
            slot = perm[rows, pick].astype(np.int64)
            perm[rows, pick] = perm[rows, j]
            perm[rows, j] = slot
        np.minimum.at(flat, owner[live] * m + slot, (np.uint64(j) << np.uint64(32)) | r)
        sets = np.unique(owner[live])
        done = np.zeros(n, dtype=bool)
        done[sets] = (signature[sets].max(axis=1) >> np.uint64(32)) <= j
        keep = ~done[owner[live]]
        live, state = live[keep], state[keep]
        if perm is not None:
            perm = perm[keep]
        else:
            first_pick = first_pick[keep]
    return signature


def jaccard_at_least(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    """100 * |a and b| >= percent * |a or b| for sorted distinct arrays."""
    if not len(a) or not len(b):
        return False
    common = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * common >= percent * (len(a) + len(b) - common)

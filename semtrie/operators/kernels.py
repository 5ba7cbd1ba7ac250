"""Dense kernels of the trie: splitting one head in two, and finishing a small subtree."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class Rule:
    """How the trie is built; see ``trie.build_trie``."""

    capacity: int = 50
    delta: float = 0.001
    metric: str = "l2"
    clone_on_split: bool = False
    max_iter: int = 20
    max_depth: int = 64
    max_placements: int | None = None
    retry_overfull: bool = False


def scaled(x: np.ndarray, metric: str) -> np.ndarray:
    if metric == "l2":
        return x
    if metric == "l2_rms":
        return x / np.sqrt(x.shape[1])
    if metric == "l2_unit":
        norm = np.sqrt((x * x).sum(1, keepdims=True))
        return x / np.where(norm == 0, 1, norm)
    raise ValueError(metric)


def distances(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    d = x - c
    return np.sqrt((d * d).sum(1))


def two_means(x: np.ndarray, max_iter: int = 20) -> tuple[np.ndarray, np.ndarray, np.ndarray, int] | None:
    """Centres, sides and steps of a 2-means split, or None if nothing separates.

    Starts from the row farthest from the mean and the row farthest from that
    one; a row as near to both goes to side 0; an empty side keeps its centre; the
    sides returned are by the final centres, so routing a member again agrees.
    """
    first = int(np.argmax(distances(x, x.mean(0))))
    second = int(np.argmax(distances(x, x[first])))
    c0, c1 = x[first].copy(), x[second].copy()
    side, steps = None, 0
    for _ in range(max_iter):
        new = distances(x, c0) > distances(x, c1)
        if side is not None and (new == side).all():
            break
        side, steps = new, steps + 1
        if (~side).any():
            c0 = x[~side].mean(0)
        if side.any():
            c1 = x[side].mean(0)
    side = distances(x, c0) > distances(x, c1)
    if side.all() or not side.any() or (c0 == c1).all():
        return None
    return c0, c1, side.astype(np.int64), steps


def split(x: np.ndarray, is_head: np.ndarray, c0: np.ndarray, c1: np.ndarray, rule: Rule) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, side, gap) of every placement below a split; gap -1 marks the nearer side, else it is the clone's."""
    d0, d1 = distances(x, c0), distances(x, c1)
    near = (d0 > d1).astype(np.int64)
    gap = np.abs(d0 - d1)
    may = gap < rule.delta
    if not rule.clone_on_split:
        may &= ~is_head
    clone = np.flatnonzero(may)
    return np.concatenate([np.arange(len(x)), clone]), np.concatenate([near, 1 - near[clone]]), np.concatenate([np.full(len(x), -1.0), gap[clone]])


def head_size(x: np.ndarray, rule: Rule) -> int:
    """Rows of the head: one above capacity, or on to the first row that differs if overfull leaves are retried."""
    n = min(len(x), rule.capacity + 1)
    if rule.retry_overfull and (x[:n] == x[0]).all():
        other = np.flatnonzero((x != x[0]).any(1))
        n = int(other[0]) + 1 if len(other) else n
    return n


def grow(path: str, x: np.ndarray, users: np.ndarray, gaps: np.ndarray, rule: Rule):
    """Nodes and placements of the subtree at ``path``; rows come in order of arrival.

    Yields ("split", path, c0, c1, rows, steps) and ("leaf", path, users, gaps, overfull).
    """
    todo = [(path, np.arange(len(x)), gaps)]
    made: dict = {}
    while todo:
        at, rows, own_gaps = todo.pop()
        cut = None
        if len(rows) > rule.capacity and len(at) < rule.max_depth:
            n = head_size(x[rows], rule)
            cut = two_means(x[rows[:n]], rule.max_iter)
        if cut is not None:
            c0, c1, _, steps = cut
            row, side, gap = split(x[rows], np.arange(len(rows)) < n, c0, c1, rule)
            parts = [int(((row < n) & (side == s)).sum()) for s in (0, 1)]
            if not all(0 < p < n for p in parts):
                cut = None
        if cut is not None:
            child_gap = np.maximum(own_gaps[row], gap)
            new = gap >= 0
            if new.any() and rule.max_placements is not None:
                # the cap: a user's clones of smallest gap survive, the original always does
                room = np.array([rule.max_placements - 1 - made.get(u, 0) for u in users[rows[row]]])
                drop = new & (room <= 0)
                row, side, child_gap, new = row[~drop], side[~drop], child_gap[~drop], new[~drop]
                for u in users[rows[row[new]]]:
                    made[u] = made.get(u, 0) + 1
            kids = []
            for s in (0, 1):
                take = np.flatnonzero(side == s)
                take = take[np.argsort(row[take], kind="stable")]
                kids.append((f"{at}{s}", rows[row[take]], child_gap[take]))
            yield ("split", at, c0, c1, len(rows), steps)
            todo += kids
            continue
        yield ("leaf", at, users[rows], own_gaps, len(rows) > rule.capacity)


def grow_one_by_one(x: np.ndarray, users: np.ndarray, rule: Rule) -> dict[str, list]:
    """The trie built by inserting one user after another: the reference for tests and small subtrees.

    Returns leaf path -> users in order of arrival there.
    """
    leaves: dict[str, list[int]] = {"": []}
    splits: dict[str, tuple] = {}
    closed: set[str] = set()

    def settle(path: str, row: int) -> None:
        stack = [path]
        while stack:
            at = stack.pop()
            if at in splits:
                c0, c1 = splits[at]
                one = x[row : row + 1]
                d0, d1 = distances(one, c0)[0], distances(one, c1)[0]
                near = int(d0 > d1)
                stack.append(f"{at}{near}")
                if abs(d0 - d1) < rule.delta:
                    stack.append(f"{at}{1 - near}")
            else:
                leaves[at].append(row)
                check(at)

    def check(at: str) -> None:
        rows = np.array(leaves[at])
        if len(rows) <= rule.capacity or at in closed or len(at) >= rule.max_depth:
            return
        cut = two_means(x[rows], rule.max_iter)
        if cut is None:
            closed.add(at)
            return
        c0, c1, _, _ = cut
        row, side, _ = split(x[rows], np.ones(len(rows), bool), c0, c1, rule)
        kids = {s: [int(rows[r]) for r, q in sorted(zip(row.tolist(), side.tolist(), strict=True)) if q == s] for s in (0, 1)}
        if not all(0 < len(k) < len(rows) for k in kids.values()):
            closed.add(at)
            return
        del leaves[at]
        splits[at] = (c0, c1)
        for s in (0, 1):
            leaves[f"{at}{s}"] = kids[s]
            check(f"{at}{s}")

    for row in range(len(x)):
        settle("", row)
    return {p: [users[r] for r in rows] for p, rows in leaves.items()}

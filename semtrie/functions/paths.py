"""Trie positions as strings of 0 and 1, the root being the empty string."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def path_depth(p: Column) -> Column:
    return F.char_length(p)


def path_parent(p: Column) -> Column:
    return F.when(F.char_length(p) > 0, F.substring(p, F.lit(1), F.char_length(p) - 1))


def path_sibling(p: Column) -> Column:
    flipped = F.translate(F.right(p, F.lit(1)), "01", "10")
    return F.when(F.char_length(p) > 0, F.concat(path_parent(p), flipped))


def common_prefix_len(a: Column, b: Column) -> Column:
    n = F.least(F.char_length(a), F.char_length(b))
    same = F.filter(F.sequence(F.lit(0), n), lambda i: F.substr(a, F.lit(1), i) == F.substr(b, F.lit(1), i))
    return F.array_max(same)


def tree_distance(a: Column, b: Column) -> Column:
    """Edges between two nodes."""
    return F.char_length(a) + F.char_length(b) - 2 * common_prefix_len(a, b)

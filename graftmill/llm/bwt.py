"""Burrows-Wheeler transforms of shards of strings, merged by iterative interleave refinement.

A shard is a set of strings over integer symbols >= 1; every string has an end mark of its own (0), smaller than
all symbols. ``Shard`` sorts the suffixes of one shard and keeps the transform. ``merge`` never sorts suffixes again: it keeps
for each row of the merged order the shard it comes from, and refines this interleave: a pass deals the
rows stably by the symbol before them, so that after h passes the order is right in the first h symbols of each
suffix. Where two neighbours first part in pass h, their common prefix has h - 1 symbols.
"""

import numpy as np


class Shard:
    """symbols: all strings one after another, each followed by a 0."""

    def __init__(self, symbols: np.ndarray):
        self.symbols = symbols
        self.order = sorted_suffixes(symbols)
        before = np.concatenate(([0], symbols[:-1]))
        self.bwt = before[self.order]
        self.ends = int((symbols == 0).sum())


def sorted_suffixes(symbols: np.ndarray) -> np.ndarray:
    """Start of each suffix in order, by prefix doubling; end marks differ and order by place."""
    n = len(symbols)
    ends = symbols == 0
    rank = np.empty(n, np.int64)
    rank[ends] = np.arange(int(ends.sum()))
    rank[~ends] = symbols[~ends] + int(ends.sum())
    order = np.argsort(rank, kind="stable")
    width = 1
    rank = numbered(rank[order], order)
    while rank[order[-1]] < n - 1:
        key = rank * (n + 1)
        key[:n - width] += rank[width:] + 1
        order = np.argsort(key, kind="stable")
        rank = numbered(key[order], order)
        width *= 2
    return order


def numbered(in_order: np.ndarray, order: np.ndarray) -> np.ndarray:
    rank = np.empty(len(order), np.int64)
    rank[order] = np.concatenate(([0], np.cumsum(in_order[1:] != in_order[:-1])))
    return rank


def merge(shards: list[Shard], depth: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(shard, suffix start within the shard, common prefix with the row above, at most depth) of each merged row."""
    sizes = [len(s.bwt) for s in shards]
    total, ends = sum(sizes), sum(s.ends for s in shards)
    first = np.concatenate([np.full(s.ends, k, np.int16) for k, s in enumerate(shards)])
    bwt = np.concatenate([s.bwt for s in shards])
    order = np.repeat(np.arange(len(shards), dtype=np.int16), sizes)
    group = np.zeros(total, np.int64)  # rows that agree in all symbols seen so far
    common = np.full(total, depth, np.int64)
    split = np.zeros(total, bool)
    for h in range(1, depth + 1):
        above = np.empty(total, bwt.dtype)
        above[np.argsort(order, kind="stable")] = bwt  # the next symbol of each shard in the order of its rows
        rows = np.flatnonzero(above)
        rows = rows[np.argsort(above[rows], kind="stable")]
        symbol, old = above[rows], group[rows]
        part = np.ones(total, bool)
        part[ends + 1:] = (symbol[1:] != symbol[:-1]) | (old[1:] != old[:-1])
        new = np.concatenate((first, order[rows]))
        common[part & ~split] = h - 1
        settled = (new == order).all() and (part == split).all()
        split, order, group = part, new, np.cumsum(part)
        if split.all() or settled:
            break
    start = np.empty(total, np.int64)
    start[np.argsort(order, kind="stable")] = np.concatenate([s.order for s in shards])
    return order, start, common

"""Prefix trees of transactions in numpy, and mining them by conditional trees up to a size."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

#: Climbing sums are reduced when so many are pending.
PENDING = 4_000_000


@dataclass
class Tree:
    """Nodes in depth-first order: item, parent (-1: root) and how many transactions pass."""

    item: np.ndarray
    parent: np.ndarray
    count: np.ndarray


def build(paths: list[np.ndarray], counts: list[int]) -> Tree:
    """The tree of ``paths`` (items in one common order), each of which occurs ``counts`` times.

    Of sorted neighbours the second adds the nodes behind their common stretch."""
    order = sorted(range(len(paths)), key=[p.astype(">u4").tobytes() for p in paths].__getitem__)  # bytes sort as their numbers do
    items, parents, depths, ends = [], [], [], []
    chain, before, n = np.zeros(0, np.int64), np.zeros(0, np.int64), 0
    for i in order:
        path = paths[i]
        short = min(len(path), len(before))
        differ = np.flatnonzero(path[:short] != before[:short])
        shared = int(differ[0]) if len(differ) else short
        fresh = np.arange(n, n + len(path) - shared)
        n += len(fresh)
        chain = np.concatenate([chain[:shared], fresh])
        items.append(path[shared:])
        parents.append(np.concatenate([chain[shared - 1 : shared] if shared else np.array([-1]), fresh[:-1]])[: len(fresh)])
        depths.append(np.arange(shared, len(path)))
        ends.append(chain[-1] if len(chain) else -1)
        before = path
    none = np.zeros(0, np.int64)
    item, parent, depth = (np.concatenate([none, *x]).astype(np.int64) for x in (items, parents, depths))
    count = np.zeros(n, np.int64)
    at = np.array(ends, np.int64)
    np.add.at(count, at[at >= 0], np.array([counts[i] for i in order], np.int64)[at >= 0])
    by_depth = np.argsort(-depth, kind="stable")
    edges = np.flatnonzero(np.diff(depth[by_depth])) + 1
    for level in np.split(by_depth, edges):  # deepest first
        up = level[parent[level] >= 0]
        np.add.at(count, parent[up], count[up])
    return Tree(item, parent, count)


def _supports(tree: Tree, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For the items of ``nodes`` and those above them: ``(item, item above, transactions)``."""
    width = int(tree.item.max(initial=0)) + 1
    keys, sums, pending = np.zeros(0, np.int64), np.zeros(0, np.int64), 0
    some: list[tuple[np.ndarray, np.ndarray]] = []

    def reduced() -> tuple[np.ndarray, np.ndarray]:
        k, w = np.concatenate([keys, *(x for x, _ in some)]), np.concatenate([sums, *(y for _, y in some)])
        distinct, back = np.unique(k, return_inverse=True)
        return distinct, np.bincount(back, weights=w, minlength=len(distinct)).astype(np.int64)

    at, base, weight = tree.parent[nodes], tree.item[nodes] * width, tree.count[nodes]
    while True:
        live = at >= 0
        if not live.any():
            break
        at, base, weight = at[live], base[live], weight[live]
        some.append((base + tree.item[at], weight))
        pending += len(at)
        if pending > PENDING:
            keys, sums = reduced()
            some, pending = [], 0
        at = tree.parent[at]
    keys, sums = reduced()
    return keys // width, keys % width, sums


def mine(tree: Tree, wanted: np.ndarray, suffix: tuple[int, ...], min_support: int, max_size: int, found: list) -> None:
    """Add ``(items, support)`` of all itemsets of two items or more that end in a wanted item and ``suffix``."""
    if not len(tree.item):
        return
    nodes = np.flatnonzero(wanted[tree.item])
    low, high, n = _supports(tree, nodes)
    fine = n >= min_support
    low, high, n = low[fine], high[fine], n[fine]
    found += [((a, b, *suffix), c) for a, b, c in zip(high.tolist(), low.tolist(), n.tolist())]
    if len(suffix) + 2 >= max_size:
        return
    for item in np.unique(low).tolist():
        keep = np.zeros(len(wanted), bool)
        keep[high[low == item]] = True
        paths, counts = [], []
        for node in nodes[tree.item[nodes] == item].tolist():
            path, at = [], int(tree.parent[node])
            while at >= 0:
                if keep[tree.item[at]]:
                    path.append(int(tree.item[at]))
                at = int(tree.parent[at])
            if path:
                paths.append(np.array(path[::-1], np.int64))
                counts.append(int(tree.count[node]))
        mine(build(paths, counts), np.ones(len(wanted), bool), (item, *suffix), min_support, max_size, found)

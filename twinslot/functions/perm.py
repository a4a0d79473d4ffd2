"""Permutations of a segment, shared by all sets."""

from __future__ import annotations

from functools import lru_cache

import numpy as np


@lru_cache(maxsize=8)
def tables(domain: int, seed: int, n: int = 3) -> np.ndarray:
    """``n`` random permutations of [0, domain), the same for every worker."""
    return np.stack([np.random.default_rng([seed, t]).permutation(domain).astype(np.int32) for t in range(n)])


@lru_cache(maxsize=8)
def inverses(domain: int, seed: int, n: int = 3) -> np.ndarray:
    """The inverse permutations, made once a worker."""
    return np.argsort(tables(domain, seed, n), axis=1)


def permute_np(x: np.ndarray, t: int, domain: int, seed: int, n: int = 3) -> np.ndarray:
    return tables(domain, seed, n)[t][x]

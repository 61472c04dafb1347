"""Asymmetric padding in closed form; the padded vectors are never built.

Positions 0..n-1 are transactions, then come two blocks of A positions. The stored side has ones in the first
block at offsets below A - support, the query side in the second. Both sides then weigh A, and their Hamming
distance and Jaccard similarity depend on the shared transactions ip alone.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def stored_bit(pos: Column, support: Column, n: int, a: int) -> Column:
    return (pos >= n) & (pos < n + a - support)


def query_bit(pos: Column, support: Column, n: int, a: int) -> Column:
    return (pos >= n + a) & (pos < n + 2 * a - support)


def hamming_from_ip(ip, a: int):  # noqa: ANN001, ANN201
    return 2 * (a - ip)


def ip_from_hamming(distance, a: int):  # noqa: ANN001, ANN201
    return a - distance / 2


def jaccard_from_ip(ip, a: int):  # noqa: ANN001, ANN201
    return ip / (2 * a - ip)


def ip_from_jaccard(similarity, a: int):  # noqa: ANN001, ANN201
    return 2 * a * similarity / (1 + similarity)


def max_support(level) -> int:  # noqa: ANN001
    """A of a level: one number."""
    return int(level.agg(F.max("support")).first()[0] or 0)


def materialise(vector: np.ndarray, a: int, side: str) -> np.ndarray:
    """The real padded vector; for tests on tiny data."""
    n, s = len(vector), int(vector.sum())
    out = np.concatenate([vector.astype(np.uint8), np.zeros(2 * a, np.uint8)])
    start = n if side == "stored" else n + a
    out[start : start + a - s] = 1
    return out

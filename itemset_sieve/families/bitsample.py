"""Bit sampling: a key is the bits of the padded vector at k random positions, for each of L tables.

Keys are held as the exclusive or of a random number of each set position: linear, so blocks add up in any
order, and independent of k. An itemset without any set position keeps key 0 and is not lost.
"""

from __future__ import annotations

import math

import numpy as np

from ..operators.vertical import BLOCK
from ..plans import params
from .base import Family, scramble

#: Blocks that are named in the scan's filter at most.
FEW = 1000


class BitSample(Family):
    name = "bitsample"

    def setup(self) -> None:
        f = self.facts
        self.p = params.bitsample(f, str(self.options.get("rounding", "strict")))
        k, tables = int(self.p["k"]), int(self.p["L"])
        rng = np.random.default_rng([self.seed, 17, f.m, f.A])
        length = f.n + 2 * f.A if self.pad else f.n
        if self.options.get("replace", True):
            pos = rng.integers(0, length, (tables, k))
        else:
            k = min(k, length)
            pos = np.stack([rng.choice(length, k, replace=False) for _ in range(tables)])
        # A position drawn twice for a table counts once: the key is a function of the set of positions.
        pairs = np.unique(np.stack([pos.ravel(), np.repeat(np.arange(tables), k)], 1), axis=0)
        self.pos, self.table = pairs[:, 0], pairs[:, 1]
        self.salt = scramble(self.pos.astype(np.uint64) * np.uint64(tables) + self.table.astype(np.uint64), self.seed)
        self.width = tables

    def params(self) -> dict[str, float]:
        return self.p

    def collision_prob(self, ip: float) -> float:
        f = self.facts
        return (1 - 2 * (f.A - ip) / (f.n + 2 * f.A)) ** self.p["k"]

    def phi(self) -> float:
        return self.p["k"] * self.p["L"]

    def phi_measured(self) -> float:
        return float(len(np.unique(self.pos[self.pos < self.facts.n])))

    def empty(self, m: int) -> np.ndarray:
        return np.zeros((m, self.width), np.uint64)

    def _fold(self, on: np.ndarray, pick: np.ndarray) -> np.ndarray:
        """Exclusive or of the salts of the set ones among the picked positions, by table."""
        out = self.empty(len(on))
        order = np.argsort(self.table[pick], kind="stable")
        pick, on = pick[order], on[:, order]
        starts = np.nonzero(np.concatenate([[True], np.diff(self.table[pick]) > 0]))[0] if len(pick) else []
        if len(starts):
            out[:, self.table[pick][starts]] = np.bitwise_xor.reduceat(np.where(on, self.salt[pick][None, :], np.uint64(0)), starts, axis=1)
        return out

    def picked(self, block: int) -> tuple[np.ndarray, np.ndarray]:
        """Samples that fall into a block, and their places in it."""
        tids = self.transactions(block)
        pick = np.nonzero((self.pos >= tids[0]) & (self.pos <= tids[-1]))[0] if len(tids) else np.zeros(0, int)
        return pick, self.pos[pick] - (tids[0] if len(tids) else 0)

    def blocks(self) -> list[int] | None:
        few = np.unique(self.pos[self.pos < self.facts.n] // BLOCK)
        return few.tolist() if len(few) <= FEW else None

    def view(self, bits: np.ndarray, block: int) -> np.ndarray:
        """The sampled transactions alone, packed: all that itemsets are combined on."""
        at = np.unique(self.picked(block)[1])
        return np.packbits((bits[:, at >> 3] >> (at & 7).astype(np.uint8)) & 1, axis=1, bitorder="little")

    def partial_of(self, seen: np.ndarray, block: int) -> np.ndarray:
        pick, at = self.picked(block)
        at = np.unique(at, return_inverse=True)[1]
        return self._fold((seen[:, at >> 3] >> (at & 7).astype(np.uint8)) & 1 > 0, pick)

    def combine(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return a ^ b

    def finish(self, whole: np.ndarray, supports: np.ndarray, side: str) -> np.ndarray:
        start, ones = self.reach(supports, side)
        pick = np.nonzero((self.pos >= start) & (self.pos < start + self.facts.A))[0] if self.pad else np.zeros(0, int)
        return whole ^ self._fold(self.pos[pick][None, :] - start < ones[:, None], pick)

    def tries(self) -> int:
        """Tries after which a query without any similar partner is given up, if asked for."""
        return math.ceil(self.p["L"] / self.facts.delta)

"""Covering keys: every pair within the radius meets, so nothing is missed.

A position has a random label; a mask v keeps the positions whose label has an odd product with v. Two vectors
meet under v if the mask drops every position in which they differ. With labels of radius + 1 bits some v other
than zero is orthogonal to the labels of any radius positions. mode blocks: positions are dealt into b blocks;
a pair within r differs by at most r // b in some block, and each block has its own small family.

Numbers are held as exclusive ors: first one for each (block, label), which adds up over transactions; then,
for all masks at once, by a transform of length 2^bits.
"""

from __future__ import annotations

import math

import numpy as np

from ..plans import params
from .base import Family, scramble

#: Positions of the padding that are hashed at once.
AT_ONCE = 1 << 18


class Covering(Family):
    name = "covering"

    def setup(self) -> None:
        f = self.facts
        self.p = params.covering(f, int(self.options.get("most_radius", 10)))
        mode = str(self.options.get("mode", "blocks"))
        r = int(self.p["r"])
        if mode == "full":
            self.b, self.bits = 1, int(self.p["t"]) * r + 1
        elif mode == "exact_radius0":
            self.b, self.bits = r + 1, 1
        else:
            self.b = int(self.options.get("blocks") or self.p["b"])
            self.bits = r // self.b + 1
        if self.bits > 16:
            raise ValueError(f"{2**self.bits} masks are out of reach; use mode='blocks'")
        self.cells = 1 << self.bits
        self.p |= {"b": self.b, "r_b": self.bits - 1, "keys": self.b * (self.cells - 1)}
        self.width = self.b * (self.cells - 1)

    def params(self) -> dict[str, float]:
        return self.p

    def collision_prob(self, ip: float) -> float:
        """Chance under one mask: no differing position is kept."""
        return 2.0 ** (-2 * (self.facts.A - ip) / self.b)

    def phi(self) -> float:
        return math.log2(max(self.facts.m, 2)) / self.p["c"] + 1

    def places(self, pos: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Cell (block and label) and number of each position."""
        h = scramble(pos, self.seed + 3)
        block = ((h >> np.uint64(40)) % np.uint64(self.b)).astype(np.int64)
        return block * self.cells + (h & np.uint64(self.cells - 1)).astype(np.int64), scramble(pos, self.seed + 4)

    def empty(self, m: int) -> np.ndarray:
        return np.zeros((m, self.b * self.cells), np.uint64)

    def _fold(self, on: np.ndarray, pos: np.ndarray, m: int) -> np.ndarray:
        """Exclusive or of the numbers of set positions, by cell; on: (itemsets, positions)."""
        out = self.empty(m)
        if not len(pos):
            return out
        cell, number = self.places(pos)
        order = np.argsort(cell, kind="stable")
        cell, number = cell[order], number[order]
        starts = np.nonzero(np.concatenate([[True], np.diff(cell) > 0]))[0]
        for i in range(m):
            out[i, cell[starts]] = np.bitwise_xor.reduceat(np.where(on[i][order], number, np.uint64(0)), starts)
        return out

    def partial_of(self, bits: np.ndarray, block: int) -> np.ndarray:
        tids = self.transactions(block)
        return self._fold(np.unpackbits(bits, axis=1, bitorder="little")[:, : len(tids)] > 0, tids, len(bits))

    def combine(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return a ^ b

    def finish(self, whole: np.ndarray, supports: np.ndarray, side: str) -> np.ndarray:
        start, ones = self.reach(supports, side)
        whole, run, done = whole.copy(), self.empty(1)[0], 0
        for i in np.argsort(ones, kind="stable"):  # exclusive ors of ever longer prefixes of the padding
            while done < ones[i]:
                until = min(int(ones[i]), done + AT_ONCE)
                cell, number = self.places(np.arange(start + done, start + until))
                np.bitwise_xor.at(run, cell, number)
                done = until
            whole[i] ^= run
        return self.keys_of(whole.reshape(len(whole), self.b, self.cells)).reshape(len(whole), -1)

    def keys_of(self, x: np.ndarray) -> np.ndarray:
        """Of cells (itemsets, blocks, labels) the keys (itemsets, blocks, masks): numbers of all labels whose product with
        the mask is odd, from those with an even one."""
        return (np.bitwise_xor.reduce(x, axis=2)[:, :, None] ^ self._even(x))[:, :, 1:]

    def _even(self, x: np.ndarray) -> np.ndarray:
        """For every v, the exclusive or over the labels whose product with v is even."""
        even, odd = x, np.zeros_like(x)
        for bit in range(self.bits):
            shape = (*x.shape[:2], self.cells >> (bit + 1), 2, 1 << bit)
            e, o = even.reshape(shape), odd.reshape(shape)
            e0, e1, o0, o1 = e[:, :, :, 0], e[:, :, :, 1], o[:, :, :, 0], o[:, :, :, 1]
            even = np.stack([e0 ^ e1, e0 ^ o1], axis=3).reshape(x.shape)
            odd = np.stack([o0 ^ o1, o0 ^ e1], axis=3).reshape(x.shape)
        return even

    def tries(self) -> int:
        """The printed bound of false positives over the error probability, for early stopping."""
        f, p = self.facts, self.p
        bound = 2.0 ** min(60.0, p["r"] * p["eps_c"] + 1) * f.m ** (1 / p["c"] if p["c"] else 1)
        return math.ceil(min(bound, float(p["keys"]) * f.m) / f.delta)

"""Minwise hashing: a summary keeps, for each of lambda permutations, the position that comes first.

Permutations are seeded hashes of positions; a slot holds the smallest hash, which stands for its position.
Within a block, hashes are drawn smallest first: positions arrive at random times, as often as not again, and their first
arrival is their hash. A usual itemset has one of the first few arrivals, so its smallest hash takes no look at the others; positions
that are not among these have hashes of their own beyond the last arrival.
The ones of a padding are the first of a block, so their smallest hash is a running minimum. Only its records are
drawn, some ln A of them a slot: the next one is a geometric number of positions away and uniform below the last.
"""

from __future__ import annotations

import math

import numpy as np

from ..operators.vertical import BLOCK
from ..plans import params
from .base import Family, scramble

CHUNK = 64
#: Slots whose arrivals are drawn at once; a seed stands for so many.
DRAWN = 1024
#: Arrivals that an itemset at the threshold has among those drawn of a slot, and how many are drawn at most.
FIRST, MOST = 4.0, 256
#: Hashes beyond the arrivals that are made at once, and words of itemsets that are taken apart at once.
BEYOND, MET = 1 << 18, 1 << 14


def as_hash(u: np.ndarray) -> np.ndarray:
    """Numbers between 0 and 1 as 64-bit hashes, in the same order."""
    return (np.minimum(u, 1 - 2.0**-53) * 2.0**64).astype(np.uint64)


class MinWise(Family):
    name = "minwise"

    def setup(self) -> None:
        self.p = params.minwise(self.facts)
        self.slots = int(self.options.get("lambda_override") or self.p["lambda"])
        self.p["slots"] = self.slots
        self.width = self.slots
        self.first = min(MOST, math.ceil(FIRST / self.facts.theta)) if self.facts.theta else MOST
        self.bands = 0
        if self.options.get("mode") == "banded":
            self.bands = int(self.options.get("bands") or 0)
            self.rows = int(self.options.get("rows") or 0)
            if not self.bands:
                self.bands, self.rows = params.banding(self.slots, self.p["similar"], self.facts.delta)
            self.p |= {"bands": self.bands, "rows": self.rows}

    def params(self) -> dict[str, float]:
        return self.p

    def collision_prob(self, ip: float) -> float:
        s = ip / (2 * self.facts.A - ip) if ip else 0.0
        return 1 - (1 - s**self.rows) ** self.bands if self.bands else s

    def phi(self) -> float:
        return float(self.slots)

    def arrivals(self, block: int, lo: int) -> tuple[np.ndarray, np.ndarray]:
        """Places in a block as they arrive, one column for each slot from lo on, and when, as uniform hashes. Every place has an exponential
        clock of its own, the same whoever asks: the first arrival at each is its hash."""
        size, shape = len(self.transactions(block)), (self.first, min(DRAWN, self.slots - lo))
        rng = np.random.default_rng([self.seed, block, lo, 2])
        at, when = rng.integers(0, size, shape), rng.standard_exponential(shape)
        for j in range(1, self.first):  # far quicker than cumsum down the columns
            when[j] += when[j - 1]
        return at, -np.expm1(-when / size)

    def beyond(self, base: np.ndarray, slots: np.ndarray, last: np.ndarray) -> np.ndarray:
        """Of positions that have not arrived, the smallest hash in each of these slots: clocks forget, so it is uniform above the last arrival."""
        least, step = np.empty(len(slots), np.uint64), max(1, BEYOND // len(base))
        with np.errstate(over="ignore"):
            for lo in range(0, len(slots), step):
                salt = slots[lo : lo + step].astype(np.uint64) * np.uint64(0xD1342543DE82EF95)
                least[lo : lo + step] = scramble(base[None, :] + salt[:, None], self.seed + 1).min(1)
        return last + (1 - last) * ((least >> np.uint64(11)) * 2.0**-53)

    def hashes(self, pos: np.ndarray, slots: range) -> np.ndarray:
        """The hash of each position in each slot, in full: what partial_of() finds the smallest of."""
        out = np.empty((len(slots), len(pos)), np.uint64)
        for block in np.unique(pos // BLOCK).tolist():
            here, tids = np.nonzero(pos // BLOCK == block)[0], self.transactions(block)
            for lo in range(slots.start // DRAWN * DRAWN, slots.stop, DRAWN):
                at, when = self.arrivals(block, lo)
                for slot in range(max(lo, slots.start), min(lo + DRAWN, slots.stop)):
                    own, last = np.full(len(tids), slot), when[-1, slot - lo]
                    with np.errstate(over="ignore"):
                        h = scramble(scramble(tids, self.seed) + own.astype(np.uint64) * np.uint64(0xD1342543DE82EF95), self.seed + 1)
                    value = last + (1 - last) * ((h >> np.uint64(11)) * 2.0**-53)
                    value[at[::-1, slot - lo]] = when[::-1, slot - lo]
                    out[slot - slots.start, here] = as_hash(value[pos[here] - tids[0]])
        return out

    def empty(self, m: int) -> np.ndarray:
        return np.full((m, self.slots), np.iinfo(np.uint64).max, np.uint64)

    def partial_of(self, bits: np.ndarray, block: int) -> np.ndarray:
        """Arrival by arrival, in all slots drawn at once: 64 itemsets are a word, in which those are marked that none of their positions has arrived of."""
        out, tids = self.empty(len(bits)), self.transactions(block)
        on = np.unpackbits(bits, axis=1, bitorder="little")[:, : len(tids)].view(bool)
        rows = np.nonzero(on.any(1))[0]
        if not len(rows):
            return out
        base, held = scramble(tids, self.seed), np.zeros((len(tids), -(-len(rows) // 64) * 64), bool)
        held[:, : len(rows)] = on[rows].T
        held = np.packbits(held, axis=1, bitorder="little").view("<u8")
        words = held.shape[1]
        every = np.packbits(np.arange(words * 64) < len(rows), bitorder="little").view("<u8")
        for lo in range(0, self.slots, DRAWN):
            at, when = self.arrivals(block, lo)
            wait, least, met, total = np.tile(every, (at.shape[1], 1)), np.empty(at.shape[1] * words * 64), [], 0
            for j in range(self.first):
                new = held[at[j]] & wait
                wait ^= new
                cell = np.flatnonzero(new)
                met.append((cell, new.ravel()[cell], when[j, cell // words]))
                total += len(cell)
                if total > MET or j == self.first - 1:
                    cell, new, time = map(np.concatenate, zip(*met))
                    bit = np.flatnonzero(np.unpackbits(new.view(np.uint8), bitorder="little").view(bool))
                    which = bit >> 6
                    least[cell[which] * 64 + (bit & 63)] = time[which]
                    met, total = [], 0
            least = least.reshape(at.shape[1], -1)
            wait = np.unpackbits(wait.view(np.uint8), axis=1, bitorder="little").view(bool)
            for i in np.nonzero(wait.any(0))[0]:
                left = np.nonzero(wait[:, i])[0]
                least[left, i] = self.beyond(base[on[rows[i]]], lo + left, when[-1, left])
            out[rows, lo : lo + len(least)] = as_hash(least[:, : len(rows)].T)
        return out

    def combine(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return np.minimum(a, b)

    def finish(self, whole: np.ndarray, supports: np.ndarray, side: str) -> np.ndarray:
        start, ones = self.reach(supports, side)
        most = int(ones.max(initial=0))
        if not most:
            return whole
        out = whole.copy()
        for lo in range(0, self.slots, CHUNK):
            own = out[:, lo : lo + CHUNK]
            rng = np.random.default_rng([self.seed, lo, side == "query"])
            at, value = np.zeros(own.shape[1]), rng.random(own.shape[1])
            while (at < most).any():
                hash_ = (value * 2.0**64).astype(np.uint64)
                np.minimum(own, hash_[None, :], out=own, where=at[None, :] < ones[:, None])
                at += np.maximum(1, np.ceil(np.log(1 - rng.random(len(at))) / np.log1p(-np.maximum(value, 1e-300))))
                value *= rng.random(len(at))
        return out

    def band_keys(self, summary: np.ndarray) -> np.ndarray:
        """One key of each band: equal iff all of its slots are."""
        out = np.zeros((len(summary), self.bands), np.uint64)
        with np.errstate(over="ignore"):
            for r in range(self.rows):
                out = scramble(out + summary[:, r : self.bands * self.rows : self.rows], self.seed + 2)
        return out

"""What the hash families share.

A family sees transactions block by block. partial() gives, for each itemset, what one block contributes;
combine() joins contributions of blocks (both are associative, so Spark adds them up in any order); finish()
adds the padding of one side, from the support alone, and gives keys: an array (itemsets, tables). Two itemsets
meet when a stored and a query key agree in the same table.
"""

from __future__ import annotations

import numpy as np

from ..operators.vertical import BLOCK
from ..plans.params import Facts


def scramble(x: np.ndarray, seed: int) -> np.ndarray:
    """A seeded 64-bit hash of positions, the same for every partitioning."""
    with np.errstate(over="ignore"):
        z = np.asarray(x, np.uint64) + np.uint64((0x9E3779B97F4A7C15 * (2 * seed + 1)) % 2**64)
        z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return z ^ (z >> np.uint64(31))


class Family:
    """name, facts of the level, seed; pad=False leaves the padding out, for ablations."""

    name = ""
    width = 0

    def __init__(self, facts: Facts, seed: int = 1, pad: bool = True, **options: object) -> None:
        self.facts, self.seed, self.pad, self.options = facts, seed, pad, options
        self.setup()

    def setup(self) -> None:
        raise NotImplementedError

    def params(self) -> dict[str, float]:
        raise NotImplementedError

    def collision_prob(self, ip: float) -> float:
        """Probability that a pair with ip shared transactions meets in one table (bands, slots: of one)."""
        raise NotImplementedError

    def phi(self) -> float:
        """Bits of the database that hashing one itemset reads, by the formula."""
        raise NotImplementedError

    def phi_measured(self) -> float:
        """Distinct transactions that hashing one itemset really looks at."""
        return float(self.facts.n)

    def empty(self, m: int) -> np.ndarray:
        raise NotImplementedError

    def view(self, bits: np.ndarray, block: int) -> np.ndarray:
        """Of the bitmaps of items in a block, what partial_of() has to see of itemsets' conjunctions."""
        return bits

    def blocks(self) -> list[int] | None:
        """Blocks that hashing has to read, if these are few."""
        return None

    def partial(self, bits: np.ndarray, block: int) -> np.ndarray:
        """What a block with these bitmaps of itemsets contributes."""
        return self.partial_of(self.view(bits, block), block)

    def partial_of(self, seen: np.ndarray, block: int) -> np.ndarray:
        raise NotImplementedError

    def combine(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        raise NotImplementedError

    def finish(self, whole: np.ndarray, supports: np.ndarray, side: str) -> np.ndarray:
        raise NotImplementedError

    def transactions(self, block: int) -> np.ndarray:
        """0-based positions of the transactions of a block."""
        return np.arange(block * BLOCK, min((block + 1) * BLOCK, self.facts.n), dtype=np.int64)

    def reach(self, supports: np.ndarray, side: str) -> tuple[int, np.ndarray]:
        """Where the side's padding starts, and how many ones each itemset has there."""
        f = self.facts
        return f.n + (f.A if side == "query" else 0), np.where(self.pad, f.A - supports, 0)

"""Methods to compare with: without candidates, by brute force, on a sample, and hashing without padding."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..families import BitSample, MinWise
from ..plans.params import Facts
from .candidates import join_compatible, join_hashed
from .vertical import Store, baskets


def fpgrowth(store: Store) -> DataFrame:
    """items, support by a miner that makes no candidates. Its threshold is relative to the rows it is given."""
    from pyspark.ml.fpm import FPGrowth

    rows = baskets(store.long)
    held = rows.count()
    found = FPGrowth(itemsCol="items", minSupport=max(0.0, (store.s_min - 0.5) / max(held, 1))).fit(rows.select("items")).freqItemsets
    return found.select(F.array_sort("items").alias("items"), F.col("freq").cast("long").alias("support")).where(F.col("support") >= store.s_min)


def brute(store: Store, max_size: int = 3) -> DataFrame:
    """items, support of all subsets of up to max_size items that occur often enough, by enumeration."""
    rows = baskets(store.long)
    grown = rows.select("items", F.explode("items").alias("x")).select("items", F.array("x").alias("sub"))
    out = grown.select("sub")
    for _ in range(max_size - 1):
        grown = grown.select("items", "sub", F.explode("items").alias("x")).where(F.col("x") > F.element_at("sub", -1)).select("items", F.concat("sub", F.array("x")).alias("sub"))
        out = out.union(grown.select("sub"))
    return out.groupBy(F.col("sub").alias("items")).agg(F.count(F.lit(1)).alias("support")).where(F.col("support") >= store.s_min)


def sampled(pairs: DataFrame, theta: float | str, share: float, seed: int = 1, **options: object):  # noqa: ANN201
    """Mining on a share of the transactions, chosen by hash of their key: approximate, the cheap pre-filter."""
    from ..plans.miner import mine

    part = pairs.where(F.pmod(F.xxhash64(F.lit(seed), "key"), F.lit(1_000_000)) < int(share * 1_000_000))
    return mine(part, theta, **options)


def _unpadded(store: Store, family_type: type, eps: float, delta: float, seed: int, options: dict) -> DataFrame:
    level = store.items.select(F.array("item").alias("items"), F.col("freq").alias("support")).orderBy("items").collect()
    members, supports = np.array([r[0] for r in level], np.int32), np.array([r[1] for r in level])
    f = Facts(store.n, store.s_min, len(level), int(supports.max()), store.s_min / store.n, eps, delta)
    return join_hashed(members, supports, store, family_type(f, seed=seed, pad=False, **options))


def minwise_unpadded(store: Store, eps: float = 0.3, delta: float = 0.1, seed: int = 1, **options: object) -> DataFrame:
    """Pairs of items by plain minwise hashing: finds similar items, whatever their support, and so both misses
    frequent pairs of unlike items and keeps rare pairs of like ones."""
    return _unpadded(store, MinWise, eps, delta, seed, options)


def bitsample_unpadded(store: Store, eps: float = 0.3, delta: float = 0.1, seed: int = 1, **options: object) -> DataFrame:
    """Pairs of items by plain bit sampling, which follows Hamming distance instead of shared transactions."""
    return _unpadded(store, BitSample, eps, delta, seed, options)


def jaccard_pairs(store: Store) -> DataFrame:
    """items, ip, jaccard, hamming of all pairs of stored items, exactly."""
    level = store.items.select(F.array("item").alias("items"), F.col("freq").alias("support"))
    from .support import count

    both = count(join_compatible(level), store)
    s = store.items.select("item", F.col("freq").alias("f"))
    x = both.select("items", F.col("support").alias("ip"), F.col("items")[0].alias("p"), F.col("items")[1].alias("q"))
    x = x.join(s.select(F.col("item").alias("p"), F.col("f").alias("fp")), "p").join(s.select(F.col("item").alias("q"), F.col("f").alias("fq")), "q")
    return x.select("items", "ip", (F.col("ip") / (F.col("fp") + F.col("fq") - F.col("ip"))).alias("jaccard"), (F.col("fp") + F.col("fq") - 2 * F.col("ip")).alias("hamming"))

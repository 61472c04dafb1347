"""The level loop: candidates from pairs of frequent itemsets, their support, the next level.

The loop is driven by a few numbers a level; levels, candidates and signatures are tables. Each level is
written, so plans don't grow and a run goes on from its last level.
"""

from __future__ import annotations

import json
import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..families import BitSample, Covering, Family, MinWise
from ..operators import candidates as cand
from ..operators import support
from ..operators.vertical import Store, build
from ..schemas import ITEMSETS, LEVEL, STATS
from ..scratch import written
from . import metrics, params
from .params import Facts

FAMILIES = {"bitsample": BitSample, "minwise": MinWise, "covering": Covering}


@dataclass
class MiningResult:
    """itemsets(level, items, support), one row of stats a level, the store they are from."""

    store: Store
    itemsets: DataFrame
    stats_rows: list[dict] = field(default_factory=list)

    @property
    def stats(self) -> DataFrame:
        rows = [tuple(r.get(c) for c in STATS.names) for r in self.stats_rows]
        return self.store.spark.createDataFrame(rows, STATS)

    def labelled(self) -> DataFrame:
        """level, itemset (labels in byte order, joined by commas), support."""
        each = self.itemsets.select("level", "support", "items", F.explode("items").alias("item"))
        named = each.join(F.broadcast(self.store.items.select("item", "label")), "item")
        out = named.groupBy("level", "items", "support").agg(F.concat_ws(",", F.array_sort(F.collect_list("label"))).alias("itemset"))
        return out.select("level", "itemset", "support")


def level_arrays(level: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """A level as arrays for the driver and for broadcast: it is output, and far smaller than the database."""
    rows = sorted((tuple(r[0]), r[1]) for r in level.select("items", "support").collect())
    return np.array([r[0] for r in rows], np.int32).reshape(len(rows), -1), np.array([r[1] for r in rows], np.int64)


def family_for(method: str, f: Facts, seed: int, options: dict) -> Family:
    return FAMILIES[method](f, seed=seed, **options)


def step(store: Store, level: DataFrame, size: int, method: str, f: Facts, seed: int, early_stop: bool, verify: str, prune: bool, support_mode: str, options: dict, stats: bool, known: DataFrame | None = None) -> tuple[DataFrame, dict]:
    """The next level from a level, and what it took."""
    row: dict = {"level": size + 1, "method": method, "m": f.m, "max_support": f.A, "phi": float(f.n), "phi_measured": float(f.n), "overhead": 0.0, "signatures": 0, "params": {}}
    if verify not in ("inline", "after"):
        raise ValueError(verify)
    inline, truth = verify == "inline" and method in ("bitsample", "covering"), None
    if method == "exact":
        pairs = written(cand.join_compatible(level), "pairs")
        family = None
    else:
        members, supports = level_arrays(level)
        family, began = family_for(method, f, seed, options), time.perf_counter()
        if early_stop and not isinstance(family, MinWise):
            met = written(cand.join_hashed(members, supports, store, family, directions=True), "meetings")
            frequent = support.count(met, store, support_mode).where(F.col("support") >= store.s_min)
            tried = cand.stop_early(met, frequent, family.tries())
            pairs = tried.select("items", F.least("parent_a", "parent_q").alias("parent_a"), F.greatest("parent_a", "parent_q").alias("parent_q")).distinct()
        else:
            pairs = cand.join_hashed(members, supports, store, family)
        pairs = written(pairs, "pairs")
        row |= {"hash_seconds": time.perf_counter() - began, "signature_bytes": 16 * f.m * family.width}
        row |= {"phi": float(family.phi()), "phi_measured": float(family.phi_measured()), "overhead": 2.0 * f.m * family.phi_measured(), "signatures": 2 * f.m * family.width, "params": {k: float(v) for k, v in family.params().items() if np.isfinite(v)}}
    if inline:  # pairs that meet are verified as they meet: what is left of them is the next level, and nothing is counted after
        met = pairs
        checked = support.count(met, store, support_mode).where(F.col("support") >= store.s_min)
        verified = written(met.join(checked, "items"), "verified")
        found = written(verified.select("items", "support").distinct(), "level")
        row["counted_after"] = 0
    else:
        chosen = cand.prune_by_subsets(pairs, level) if prune else pairs.select("items").distinct()
        counted = written(support.count(chosen, store, support_mode), "counted")
        found = written(counted.where(F.col("support") >= store.s_min), "level")
        row["counted_after"] = counted.count() if stats else None
    if stats:
        every = pairs if method == "exact" else written(cand.join_compatible(level), "pairs")
        # What is frequent is counted on all compatible pairs: what a method misses is no true negative.
        truth = found if method == "exact" else known.where(F.col("level") == size + 1) if known is not None else written(support.count(every, store, support_mode).where(F.col("support") >= store.s_min), "truth")
        good = every.join(truth.select("items"), "items", "left_semi").count()
        kept_good = pairs.join(truth.select("items"), "items", "left_semi").count()
        c, kept = every.count(), pairs.count()
        row |= {"pairs": c, "candidate_itemsets": every.select("items").distinct().count(), "kept_pairs": kept, "kept_itemsets": pairs.select("items").distinct().count(), "found": found.count()}
        row |= {"frequent_pairs": good, "fp": 2 * (kept - kept_good), "fn": 2 * (good - kept_good), "tn": 2 * (c - good - (kept - kept_good))}
        row["savings"] = (f.n - row["phi_measured"]) * row["tn"] if family is not None else 0.0
    return found, row


def mine(
    data: DataFrame | Store, theta: float | str | None = None, method: str = "exact", *, eps: float = 0.3, delta: float = 1e-6, eta: float | None = None, seed: int = 1, early_stop: bool = False,
    verify: str = "inline", prune_subsets: bool = False, max_level: int | None = None, method_by_level: dict[int, str] | None = None, support_mode: str = "kernel", stats: bool = False,
    universe: int | None = None, checkpoint: str | None = None, truth: DataFrame | None = None, **options: object,
) -> MiningResult:
    """All itemsets with support of at least ceil(theta n) in rows (key, label), or in a store.

    method: exact, bitsample, minwise, covering, or auto, which picks per level the method that is sure to save
    most reads, else exact; method_by_level overrides it from a level on. eta bounds the miss probability of an
    itemset over the whole run, up to max_level or else 8 levels, in place of delta. Exact and covering miss nothing unless early_stop; bitsample and
    minwise miss a pair with probability delta. What is found is always frequent. Empty data, or a threshold above
    every support, give an empty result. verify: inline has bit sampling and covering verify pairs as they meet, so that what remains is the next
    level; after counts all candidates in a pass of its own, after pruning if asked for; exact and minwise always do. With checkpoint, levels are kept there
    and a second call goes on; levels of another table, threshold or method are refused. truth: all frequent itemsets (level, items), where an
    exact run has them; else stats count all compatible pairs for it.
    """
    store = data if isinstance(data, Store) else build(data, theta, universe)
    spark = store.spark
    if eta is not None:
        delta = params.delta_for(eta, max_level or 8)
    exact_theta = store.s_min / max(store.n, 1)
    level = store.items.where(F.col("freq") >= store.s_min).select(F.array("item").alias("items"), F.col("freq").alias("support"))
    out, rows, size = [], [], 1
    manifest = f"{checkpoint}/manifest" if checkpoint else None
    done, run = 0, None
    if manifest:
        items, total = store.items.agg(F.count(F.lit(1)), F.sum("freq")).first()
        run = json.dumps({"n": store.n, "s_min": store.s_min, "items": items, "total": total, "method": method, "by_level": method_by_level, "seed": seed, "eps": eps, "delta": delta, "early_stop": early_stop, "verify": verify, "prune": prune_subsets, "options": options}, default=str, sort_keys=True)
        try:
            before = spark.read.json(manifest, schema="level int, run string").groupBy("run").agg(F.max("level").alias("level")).collect()  # one run's
        except Exception as e:  # a first run has no manifest
            if "PATH_NOT_FOUND" not in str(e):
                raise
            before = []
        if any(r["run"] != run for r in before):
            raise ValueError(f"{checkpoint} holds levels of another run: {before[0]['run']}")
        done = max((r["level"] for r in before), default=0)
    while True:
        if checkpoint and size <= done:
            level = spark.read.schema(LEVEL).parquet(f"{checkpoint}/level={size}")
        else:
            level = written(level, "level", f"{checkpoint}/level={size}" if checkpoint else None)
            if manifest:
                spark.createDataFrame([(json.dumps({"level": size, "run": run}),)], "value string").write.mode("append").text(manifest)
        m, most = level.agg(F.count(F.lit(1)), F.max("support")).first()
        if not m:
            break
        out.append(level.select(F.lit(size).alias("level"), "items", "support"))
        if m < 2 or (max_level and size >= max_level):
            break
        f = Facts(store.n, store.s_min, m, most, exact_theta, eps, delta)
        how = next((method_by_level[k] for k in sorted(method_by_level or {}, reverse=True) if k <= size), method)
        if how == "auto":
            how = metrics.choose(f, m * (m - 1) // 2 if size == 1 else cand.join_compatible(level).count())
        if how != "exact" and most == store.s_min:
            how = "exact"  # all supports equal the threshold: only itemsets of the same transactions combine
        known = spark.read.schema(LEVEL).parquet(f"{checkpoint}/level={size + 1}") if checkpoint and size + 1 <= done else None
        if known is not None:
            level = known
        else:
            level, row = step(store, level, size, how, f, seed + size, early_stop, verify, prune_subsets, support_mode, dict(options), stats, truth)
            rows.append(row)
        size += 1
    itemsets = out[0] if out else spark.createDataFrame([], ITEMSETS)
    for x in out[1:]:
        itemsets = itemsets.unionByName(x)
    return MiningResult(store, itemsets, rows)


def exists_size(data: DataFrame | Store, theta: float | str | None, k: int, method: str = "exact", **options: object) -> bool:
    """Whether there is any frequent itemset with k items."""
    found = mine(data, theta, method, max_level=k, **options).itemsets
    return found.where(F.col("level") == k).limit(1).count() > 0

"""Cost and accuracy measures of a level, and the analytic bounds and regimes of the methods."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import params
from .params import Facts


def pair_class(ip: Column, s_min: int, n: int, theta: float, eps: float) -> Column:
    """frequent, infrequent (below (1 - eps) theta n), or gap between them."""
    return F.when(ip >= s_min, "frequent").when(ip < (1 - eps) * theta * n, "infrequent").otherwise("gap")


def bound_bitsample(f: Facts, c: int, found: int) -> float:
    """Least expected savings: (n - kL)(2 (c - found) - m L)."""
    p = params.bitsample(f)
    return (f.n - p["k"] * p["L"]) * (2 * (c - found) - f.m * p["L"])


def bound_minwise(f: Facts, c: int, found: int) -> float:
    """Least expected savings: 2 (1 - delta)(n - lambda)(c - found)."""
    return 2 * (1 - f.delta) * (f.n - params.minwise(f)["lambda"]) * (c - found)


def bound_covering(f: Facts, c: int, found: int) -> float:
    """Least expected savings: 2 (n - log m / c - 1)((c - found) - m^(1 + nu))."""
    p = params.covering(f)
    if not math.isfinite(p["c"]) or (1 + p["nu"]) * math.log(max(f.m, 2)) > 700:
        return -math.inf
    return 2 * (f.n - math.log2(max(f.m, 2)) / p["c"] - 1) * ((c - found) - f.m ** (1 + p["nu"]))


BOUNDS = {"bitsample": bound_bitsample, "minwise": bound_minwise, "covering": bound_covering}


def overhead(method: str, f: Facts) -> float:
    """Bits read and keys made for hashing a level twice, on both sides."""
    if method == "bitsample":
        p = params.bitsample(f)
        return 2.0 * f.m * p["k"] * p["L"]
    if method == "minwise":
        return 2.0 * f.m * (f.n + params.minwise(f)["lambda"])
    if method == "covering":
        return 2.0 * f.m * (f.n + params.covering(f)["keys"])
    return 0.0


def regime(method: str, f: Facts, c: int, found: int) -> dict[str, bool]:
    """The conditions under which the method is said to pay, one by one."""
    if method == "bitsample":
        return {"n_over_m": f.n > 10 * f.m, "c_quadratic": c >= f.m * f.m / 8, "c_over_2m": c > 2 * found}
    if method == "minwise":
        return {"lambda_small": params.minwise(f)["lambda"] * 4 < f.n, "c_over_m": c > 4 * max(f.m, found)}
    p = params.covering(f)
    exponential = f.n < 2000 and 2.0 ** (f.n / 2) < f.m < 2.0**f.n / 5
    return {"c_over_m2": c > f.m**2 and c > found**2, "m_exponential": exponential, "eps_small": p["eps_c"] < 0.25, "c_between": 1 < p["c"] < 2}


def choose(f: Facts, c: int) -> str:
    """The method with the largest guaranteed savings less its overhead; exact where none is positive."""
    def net(method: str) -> float:
        if method == "covering" and params.covering(f)["keys"] > 4096:
            return -math.inf
        return BOUNDS[method](f, c, 0) - overhead(method, f)

    best = max(BOUNDS, key=net)
    return best if net(best) > 0 else "exact"


def missed(truth: DataFrame, got: DataFrame) -> DataFrame:
    """Itemsets of the truth that got lacks, with how many of their subsets with one item less got lacks too."""
    lost = truth.join(got.select("items"), "items", "left_anti")
    subs = lost.select("items", F.explode(F.transform("items", lambda x: F.array_remove("items", x))).alias("sub"))
    inherited = subs.join(truth.select(F.col("items").alias("sub")), "sub", "left_semi").join(got.select(F.col("items").alias("sub")), "sub", "left_anti")
    per = inherited.groupBy("items").agg(F.count(F.lit(1)).alias("lost_subsets"))
    return lost.join(per, "items", "left").withColumn("lost_subsets", F.coalesce("lost_subsets", F.lit(0)))


def per_query(met: DataFrame, compatible: DataFrame, frequent: DataFrame) -> DataFrame:
    """query, partners, frequent, met, fp, fn, tn of every itemset as a query: of met(parent_q, parent_a, items) among the pairs
    compatible(parent_a, parent_q, items), with frequent(items) the truth."""
    both = compatible.select(F.col("parent_q").alias("query"), F.col("parent_a").alias("partner"), "items")
    both = both.union(compatible.select("parent_a", "parent_q", "items"))
    seen = met.select(F.col("parent_q").alias("query"), F.col("parent_a").alias("partner"), F.lit(1).alias("m")).distinct()
    each = both.join(frequent.select("items", F.lit(1).alias("f")), "items", "left").join(seen, ["query", "partner"], "left")
    m, f = F.coalesce("m", F.lit(0)), F.coalesce("f", F.lit(0))
    return each.groupBy("query").agg(F.count(F.lit(1)).alias("partners"), F.sum(f).alias("frequent"), F.sum(m).alias("met"), F.sum(m * (1 - f)).alias("fp"), F.sum((1 - m) * f).alias("fn"), F.sum((1 - m) * (1 - f)).alias("tn"))


def confusion(truth: DataFrame, got: DataFrame) -> DataFrame:
    """level, both, missed, false, recall, precision."""
    t, g = truth.select("items", F.lit(1).alias("t")), got.select("items", F.lit(1).alias("g"))
    every = t.join(g, "items", "full_outer").select(F.size("items").alias("level"), F.coalesce("t", F.lit(0)).alias("t"), F.coalesce("g", F.lit(0)).alias("g"))
    out = every.groupBy("level").agg(F.sum(F.col("t") * F.col("g")).alias("both"), F.sum(F.col("t") * (1 - F.col("g"))).alias("missed"), F.sum((1 - F.col("t")) * F.col("g")).alias("false"))
    return out.withColumn("recall", F.col("both") / F.greatest(F.col("both") + F.col("missed"), F.lit(1))).withColumn("precision", F.col("both") / F.greatest(F.col("both") + F.col("false"), F.lit(1)))

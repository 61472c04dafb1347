"""What frequent itemsets are used for: rules, correlated pairs, maximal and closed sets, sequences, clusters."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .candidates import leave_one_out


def generate(itemsets: DataFrame, n: int, min_conf: float, consequents: str = "one") -> DataFrame:
    """antecedent, consequent, support, confidence, lift, leverage, conviction of every rule that is sure enough.

    consequents: 'one' item, or 'any' proper subset. itemsets must hold all subsets, as a mining result does.
    """
    big = itemsets.where(F.size("items") > 1)
    if consequents == "one":
        split = big.select("items", "support", F.explode(leave_one_out(F.col("items"))).alias("antecedent"))
    else:
        # Every proper, non-empty subset, by the bits of a counter.
        counter = F.explode(F.expr("sequence(1, cast(pow(2, size(items)) as int) - 2)")).alias("mask")
        split = big.select("items", "support", counter).select("items", "support", F.expr("filter(items, (x, i) -> bit_get(mask, i) = 1)").alias("antecedent"))
    split = split.withColumn("consequent", F.array_except("items", "antecedent"))
    a = itemsets.select(F.col("items").alias("antecedent"), F.col("support").alias("sa"))
    c = itemsets.select(F.col("items").alias("consequent"), F.col("support").alias("sc"))
    r = split.join(a, "antecedent").join(c, "consequent").withColumn("confidence", F.col("support") / F.col("sa"))
    r = r.where(F.col("confidence") >= min_conf)
    return r.select(
        "antecedent", "consequent", "support", "confidence",
        (F.col("confidence") * n / F.col("sc")).alias("lift"),
        (F.col("support") / n - F.col("sa") / n * F.col("sc") / n).alias("leverage"),
        F.when(F.col("confidence") < 1, (1 - F.col("sc") / n) / (1 - F.col("confidence"))).alias("conviction"),
    )


def pair_measures(pairs: DataFrame, singles: DataFrame, n: int) -> DataFrame:
    """a, b, support, lift, cosine, all_confidence, phi, chi2 of pairs(a, b, support) with singles(item, support)."""
    x = pairs.join(singles.select(F.col("item").alias("a"), F.col("support").alias("sa")), "a").join(singles.select(F.col("item").alias("b"), F.col("support").alias("sb")), "b")
    s, sa, sb = F.col("support").cast("double"), F.col("sa").cast("double"), F.col("sb").cast("double")
    spread = F.sqrt(sa * sb * (n - sa) * (n - sb))
    phi = F.when(spread > 0, (n * s - sa * sb) / spread)
    return x.select("a", "b", "support", (s * n / (sa * sb)).alias("lift"), (s / F.sqrt(sa * sb)).alias("cosine"), (s / F.greatest(sa, sb)).alias("all_confidence"), phi.alias("phi"), (n * phi * phi).alias("chi2"))


def maximal(itemsets: DataFrame) -> DataFrame:
    """Itemsets without a frequent superset: one with one item more is enough to look at."""
    covered = itemsets.where(F.size("items") > 1).select(F.explode(leave_one_out(F.col("items"))).alias("items")).distinct()
    return itemsets.join(covered, "items", "left_anti")


def closed(itemsets: DataFrame) -> DataFrame:
    """Itemsets without a superset of the same support."""
    covered = itemsets.where(F.size("items") > 1).select(F.explode(leave_one_out(F.col("items"))).alias("items"), "support").distinct()
    return itemsets.join(covered, ["items", "support"], "left_anti")


def cluster_by_itemset(baskets: DataFrame, itemsets: DataFrame) -> DataFrame:
    """tid, items of the largest, then most frequent itemset that a basket(tid, items) holds; ties by items."""
    first = itemsets.select(F.col("items").alias("set"), "support", F.col("items")[0].alias("first"))
    held = baskets.select("tid", F.col("items").alias("basket"), F.explode("items").alias("first")).join(first, "first")
    held = held.where(F.size(F.array_except("set", "basket")) == 0)
    order = Window.partitionBy("tid").orderBy(F.size("set").desc(), F.col("support").desc(), "set")
    return held.withColumn("rn", F.row_number().over(order)).where("rn = 1").select("tid", F.col("set").alias("items"))


def sequences(events: DataFrame, min_support: float, longest: int = 4) -> DataFrame:
    """sequence, freq of ordered event types by user; built on PrefixSpan, as a baseline."""
    from pyspark.ml.fpm import PrefixSpan

    by_user = events.groupBy("user_id").agg(F.sort_array(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("e"))
    rows = by_user.select(F.transform("e", lambda x: F.array(x["event_type"])).alias("sequence"))
    return PrefixSpan(minSupport=min_support, maxPatternLength=longest).findFrequentSequentialPatterns(rows)

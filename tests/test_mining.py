"""The miner against worked examples, brute force and itself."""

from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from itemset_sieve.operators import baselines, candidates, rules, support
from itemset_sieve.operators.encoders import encode
from itemset_sieve.operators.vertical import build, dense_tids
from itemset_sieve.plans import metrics
from itemset_sieve.plans.miner import exists_size, mine
from itemset_sieve.sources import synthetic

TINY = ["abc", "abd", "acd", "bcd", "ab", "ac", "bc", "e"]


def pairs_of(spark, rows):
    return spark.createDataFrame([(str(i), x) for i, r in enumerate(rows) for x in r], "key string, label string")


def brute(rows, least):
    out = {}
    for k in range(1, 6):
        for c in combinations(sorted({x for r in rows for x in r}), k):
            n = sum(set(c) <= set(r) for r in rows)
            if n >= least:
                out[",".join(c)] = n
    return out


def found(result):
    return {r["itemset"]: r["support"] for r in result.labelled().collect()}


@pytest.fixture(scope="module")
def tiny(spark):
    return build(pairs_of(spark, TINY), "0.25")


@pytest.mark.parametrize("method", ["exact", "bitsample", "minwise", "covering", "auto"])
def test_tiny_lattice(tiny, method):
    assert found(mine(tiny, method=method)) == brute(TINY, 2)


@pytest.mark.parametrize("options", [{"mode": "banded"}, {"mode": "scan", "lambda_override": 2000}, {"eta": 1e-5}])
def test_minwise_options(tiny, options):
    assert found(mine(tiny, method="minwise", **options)) == brute(TINY, 2)


@pytest.mark.parametrize("options", [{"method": "bitsample", "early_stop": True}, {"method": "covering", "early_stop": True}, {"method": "covering", "mode": "exact_radius0"}, {"method": "exact", "prune_subsets": True}, {"method": "bitsample", "rounding": "ceil"}])
def test_variants_are_sound(tiny, options):
    got, truth = found(mine(tiny, **options)), brute(TINY, 2)
    assert got.items() <= truth.items()


def test_infrequent_triple_of_frequent_pairs_is_pruned_only_by_count(spark):
    rows = ["ab", "ab", "ac", "ac", "bc", "bc"]
    assert found(mine(pairs_of(spark, rows), "0.3")) == brute(rows, 2)


def test_stats_balance(tiny):
    for s in mine(tiny, method="bitsample", stats=True).stats_rows:
        assert s["fp"] >= 0 and s["tn"] >= 0 and s["kept_pairs"] <= s["pairs"]
        assert s["signatures"] == 2 * s["m"] * s["params"]["L"]


def test_equal_supports_and_thresholds_at_the_ends(spark):
    same = pairs_of(spark, ["abc"] * 4)
    assert found(mine(same, "1.0", "covering")) == brute(["abc"] * 4, 4)
    assert found(mine(same, "0.9", "minwise")) == brute(["abc"] * 4, 4)
    assert mine(pairs_of(spark, TINY), "0.99").itemsets.count() == 0


def test_empty_database(spark):
    r = mine(spark.createDataFrame([], "key string, label string"), "0.5")
    assert r.itemsets.count() == 0 and r.labelled().columns == ["level", "itemset", "support"]


def test_universe_counts_empty_transactions(spark):
    assert found(mine(pairs_of(spark, TINY), "0.25", universe=16, max_level=1)) == {k: v for k, v in brute(TINY, 4).items() if "," not in k}


def test_support_plans_agree(tiny):
    level = tiny.items.select(F.array("item").alias("items"), F.col("freq").alias("support"))
    c = candidates.join_compatible(level)
    got = [sorted((tuple(r[0]), r[1]) for r in support.count(c, tiny, m).collect()) for m in ("kernel", "bitmap", "tidlist", "horizontal")]
    assert got[0] == got[1] == got[2] == got[3]
    assert support.count(c, tiny, "kernel", bound=1).count() == len(got[0])


def test_candidate_joins_agree_and_have_no_cartesian_product(tiny):
    level = mine(tiny, max_level=2).itemsets.where("level = 2").select("items", "support")
    keyed, brute_force = candidates.join_compatible(level), candidates.join_compatible(level, "brute")
    assert sorted(map(tuple, keyed.collect())) == sorted(map(tuple, brute_force.collect()))
    plan = keyed._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
    pruned = candidates.prune_by_subsets(candidates.join_compatible(level, "prefix"), level)
    assert {tuple(r[0]) for r in pruned.collect()} <= {tuple(r[0]) for r in keyed.select("items").collect()}


def test_baselines_agree(tiny):
    truth = {tuple(r["items"]): r["support"] for r in mine(tiny).itemsets.collect()}
    for other in (baselines.fpgrowth(tiny), baselines.brute(tiny, 4)):
        assert {tuple(r["items"]): r["support"] for r in other.collect()} == truth


def test_planted_itemset_and_partition_invariance(spark):
    data = synthetic(spark, 3000, 60, 0.03, {(1, 2, 3, 4): 0.12}, seed=4)
    one = found(mine(data.repartition(1), "0.08", "minwise"))
    many = found(mine(data.repartition(16), "0.08", "minwise"))
    assert one == many and "1,2,3,4" in one


def test_dense_numbers(spark):
    t = [r["tid"] for r in dense_tids(pairs_of(spark, TINY), parts=3).collect()]
    assert sorted(t) == list(range(1, len(TINY) + 1))


def test_rules_and_condensed_forms(tiny):
    r = mine(tiny)
    sets = r.itemsets.select("items", "support")
    for x in rules.generate(sets, tiny.n, 0.5, "any").collect():
        assert abs(x["confidence"] * x["support"] / x["confidence"] - x["support"]) < 1e-9 and not set(x["antecedent"]) & set(x["consequent"])
    maximal, closed, every = ({tuple(y["items"]) for y in f(sets).collect()} for f in (rules.maximal, rules.closed, lambda s: s))
    assert maximal <= closed <= every
    assert maximal == {s for s in every if not any(set(s) < set(t) for t in every)}


def test_resume_goes_on_from_the_written_levels(spark, tmp_path):
    data = pairs_of(spark, TINY)
    first = found(mine(data, "0.25", checkpoint=str(tmp_path / "run"), max_level=2))
    both = found(mine(data, "0.25", checkpoint=str(tmp_path / "run")))
    assert first.items() <= both.items() and both == brute(TINY, 2)


def test_missed_and_confusion(spark):
    truth = spark.createDataFrame([([1], 5), ([2], 5), ([1, 2], 4)], "items array<int>, support long")
    got = truth.where("size(items) = 1 AND items[0] = 1")
    assert {tuple(r["items"]): r["lost_subsets"] for r in metrics.missed(truth, got).collect()} == {(2,): 0, (1, 2): 1}
    assert {r["level"]: r["recall"] for r in metrics.confusion(truth, got).collect()} == {1: 0.5, 2: 0.0}


def test_existence(tiny):
    assert exists_size(tiny, None, 2) and not exists_size(tiny, None, 4)


def test_missed_pairs_are_no_true_negatives_and_inline_needs_no_count_after(spark, sf):
    st = build(encode(spark, sf, "e4"), "0.45")
    truth = {tuple(r["items"]): r["support"] for r in mine(st).itemsets.collect()}
    for verify in ("inline", "after"):
        r = mine(st, method="covering", verify=verify, stats=True)
        assert {tuple(x["items"]): x["support"] for x in r.itemsets.collect()} == truth
        assert all(s["fn"] == 0 and (s["counted_after"] == 0) == (verify == "inline" or not s["kept_pairs"]) for s in r.stats_rows)
    r = mine(st, method="bitsample", delta=0.9, stats=True)
    assert all(s["fp"] + s["fn"] + s["tn"] + 2 * (s["kept_pairs"] - s["fp"] // 2) == 2 * s["pairs"] for s in r.stats_rows) and sum(s["fn"] for s in r.stats_rows) > 0


def test_a_checkpoint_of_another_run_is_refused(spark, sf, tmp_path):
    import pytest

    st = build(encode(spark, sf, "e4"), "0.45")
    a = mine(st, checkpoint=str(tmp_path / "c"), max_level=2)
    b = mine(st, checkpoint=str(tmp_path / "c"))
    assert b.itemsets.count() > a.itemsets.count() and sorted(b.itemsets.collect()) == sorted(mine(st).itemsets.collect())
    for other in ({"method": "covering"}, {"seed": 2}):
        with pytest.raises(ValueError, match="another run"):
            mine(st, checkpoint=str(tmp_path / "c"), **other)
    with pytest.raises(ValueError, match="another run"):
        mine(build(encode(spark, sf, "e4"), "0.5"), checkpoint=str(tmp_path / "c"))


@pytest.mark.parametrize("directions", [True, False])
def test_covering_pairs_by_groups_of_positions_are_those_of_equal_keys(spark, directions, monkeypatch):
    from itemset_sieve.families import Covering
    from itemset_sieve.operators import meetings
    from itemset_sieve.plans.miner import level_arrays
    from itemset_sieve.plans.params import Facts

    st = build(synthetic(spark, 6000, 12, 0.6, planted={(1, 2, 3): 0.3}), "0.35")
    x, s = level_arrays(mine(st, max_level=2).itemsets.where("level = 2"))
    fam = Covering(Facts(st.n, st.s_min, len(x), int(s.max()), st.s_min / st.n, 0.3, 0.1))
    monkeypatch.setattr(meetings, "GROUP", 1000)
    monkeypatch.setattr(candidates, "by_group", lambda m, family: False)
    cols = ("parent_a", "parent_q", *(["table_no"] if directions else []))
    few = lambda: {(tuple(r[0]), tuple(r[1]), *r[2:]) for r in candidates.join_hashed(x, s, st, fam, directions=directions).select(*cols).collect()}
    want = few()
    monkeypatch.setattr(candidates, "hashed", None)
    monkeypatch.setattr(candidates, "by_group", lambda m, family: True)
    assert few() == want and len(want) > 20


def test_covering_makes_no_table_of_keys_that_grows_with_the_transactions(spark, monkeypatch):
    from itemset_sieve.families import Covering
    from itemset_sieve.plans.params import Facts

    def written(df, name, path=None):
        assert name != "signatures", "keys of all blocks of every itemset"

    monkeypatch.setattr(candidates, "written", written)
    n = 60_000
    st = build(spark.range(n).select(F.col("id").cast("string").alias("key"), F.explode(F.array(*[F.lit(f"t{i}") for i in range(10)])).alias("label")), "0.5")
    x = np.array(list(combinations(range(10), 2)), np.int32)
    pairs = candidates.join_hashed(x, np.full(len(x), n), st, Covering(Facts(n, n // 2, len(x), n, 0.5, 0.3, 1e-6)))
    assert pairs.count() == 10 * 36 == pairs.select("parent_a", "parent_q").distinct().count()


def test_store_of_wide_rows_is_that_of_their_items(spark, sf):
    """Also where keys come again, with the same items and others, and where columns are null; no row for each item is written on the way."""
    from itemset_sieve.operators import vertical
    from itemset_sieve.operators.encoders import encode_wide, from_columns, wide_columns

    n = 40_000
    rows = spark.range(n).select((F.col("id") % (n - 3000)).alias("k"), F.when(F.col("id") % 5 > 0, F.col("id") % 3).alias("a"), F.when(F.col("id") % 4 > 0, F.col("id") % 7).alias("b"))
    rows = rows.union(spark.createDataFrame([(None, 1, 1), (n + 1, None, None)], "k long, a long, b long"))
    cols = {"a": F.col("a"), "b": F.col("b")}
    pairs = [(from_columns(rows, F.col("k"), cols), wide_columns(rows, F.col("k"), cols)), (encode(spark, sf, "e3"), encode_wide(spark, sf, "e3"))]
    for long, wide in pairs:
        tables = []
        was, vertical.written = vertical.written, lambda df, name, path=None: tables.append(name) or was(df, name, path)
        try:
            y = build(wide, "0.05")
        finally:
            vertical.written = was
        x = build(long, "0.05")
        assert "labels" in wide.columns and tables == ["baskets", "items", "blocks"]
        assert (x.n, x.s_min, x.labels, sorted(x.items.collect())) == (y.n, y.s_min, y.labels, sorted(y.items.collect()))
        assert sorted(x.long.collect()) == sorted(y.long.collect())
        assert sorted(map(repr, x.blocks.collect())) == sorted(map(repr, y.blocks.collect()))
    assert pairs[0][1].count() > pairs[0][1].select("key").distinct().count()


def test_stats_by_known_truth_are_those_that_are_counted(spark, sf):
    st = build(encode(spark, sf, "e4"), "0.5")
    truth = mine(st).itemsets
    counted, known = (mine(st, method="bitsample", delta=0.3, stats=True, max_level=3, truth=t).stats_rows for t in (None, truth))
    assert [{k: v for k, v in r.items() if k != "hash_seconds"} for r in counted] == [{k: v for k, v in r.items() if k != "hash_seconds"} for r in known] and len(known) == 2

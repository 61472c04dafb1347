"""Registered queries: methods, variants, baselines, measures and workloads on the given tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import functions as fn
from .. import streaming
from ..families import BitSample, Covering, MinWise
from ..operators import baselines, candidates, relops, rules, support
from ..operators.encoders import encode, encode_wide
from ..operators.vertical import Store, baskets, build, min_support
from ..scratch import scratch_dir, written
from ..sources import load
from . import metrics, oracle, padding, params
from .miner import MiningResult, exists_size, level_arrays, mine
from .params import Facts

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}
_KEPT: dict[tuple, object] = {}

#: Thresholds of the workloads.
THETA = {"e1": "0.003", "e2": "0.02", "e2b": "0.02", "e2c": "0.5", "e3": "0.05", "e4": "0.45", "e5": "0.1", "e6": "0.28", "e7": "0.12", "e8": "0.5", "e9": "0.9", "e10": "0.05"}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def put(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return put


def kept(spark: SparkSession, key: tuple, make: Callable[[], object]) -> object:
    """Stores and exact results are tables; queries of one session share them."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _KEPT:
        _KEPT[key] = make()
    return _KEPT[key]


def store(spark: SparkSession, d: str, enc: str, theta: str | None = None) -> Store:
    theta = theta or THETA[enc]
    return kept(spark, ("store", d, enc, theta), lambda: build(encode_wide(spark, d, enc), theta))


def anew(spark: SparkSession, d: str, enc: str) -> Store:
    """A store read from the tables for this call alone."""
    return build(encode_wide(spark, d, enc), THETA[enc])


def exact(spark: SparkSession, d: str, enc: str, theta: str | None = None, top: int | None = None) -> MiningResult:
    theta = theta or THETA[enc]
    return kept(spark, ("exact", d, enc, theta, top), lambda: mine(store(spark, d, enc, theta), stats=True, max_level=top))


def named(df: DataFrame, st: Store, *cols: str, key: tuple[str, ...] = ()) -> DataFrame:
    """Item number arrays as text of sorted labels."""
    labels = F.array(*[F.lit(x) for x in st.labels])
    return df.select(*[F.concat_ws(",", F.array_sort(F.transform(c, lambda i: labels[i]))).alias(c) for c in cols], *key)


def level_of(r: MiningResult, k: int) -> DataFrame:
    return r.itemsets.where(F.col("level") == k).select("items", "support")


# Level 1, exact levels, candidate joins, support plans.

for _e in oracle.ENCODINGS:
    query(f"level1_{_e}", oracle.levels(_e, THETA[_e], 1) + " SELECT its[1] AS label, c AS support FROM l1")(
        lambda spark, d, e=_e: support.frequent_items(p := written(encode(spark, d, e), "pairs"), min_support(THETA[e], p.select("key").distinct().count()))
    )

for _e in ("e2", "e3", "e4", "e7"):
    query(f"exact_pairs_{_e}", oracle.mined(_e, THETA[_e], 2))(lambda spark, d, e=_e: exact(spark, d, e, top=2).labelled())
for _e, _t, _top in (("e2", "0.02", 3), ("e3", "0.02", 4), ("e4", "0.45", 7), ("e5", "0.1", 3), ("e6", "0.28", 3)):
    query(f"exact_all_{_e}", oracle.mined(_e, _t, _top))(lambda spark, d, e=_e, t=_t: exact(spark, d, e, t).labelled())
query("exact_capped_e8", oracle.mined("e8", "0.5", 3))(lambda spark, d: mine(store(spark, d, "e8"), max_level=3).labelled())
query("exact_any_theta_above", "SELECT 1::INT AS level, '' AS itemset, 0::BIGINT AS support WHERE false")(lambda spark, d: mine(encode(spark, d, "e5"), "0.99").labelled())

_PAIRS = oracle.levels("e4", "0.45", 2) + f" SELECT {oracle.text('its')} AS items, least({oracle.text('x')}, {oracle.text('y')}) AS a, greatest({oracle.text('x')}, {oracle.text('y')}) AS q FROM {oracle.compatible(2)}"


def _pairs(how: str) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        r = mine(anew(spark, d, "e4"), max_level=2)
        x = named(candidates.join_compatible(level_of(r, 2), how), r.store, "items", "parent_a", "parent_q")
        return x.select("items", F.least("parent_a", "parent_q").alias("a"), F.greatest("parent_a", "parent_q").alias("q"))

    return run


query("compatible_pairs_e4", _PAIRS)(_pairs("subset_key"))
query("compatible_pairs_brute_e4", _PAIRS)(_pairs("brute"))


@query(
    "prefix_pairs_e4",
    oracle.levels("e4", "0.45", 2, ids=True) + f" SELECT {oracle.text('its')} AS items FROM {oracle.compatible(2)} WHERE x[1] = y[1]",
)
def _prefix(spark: SparkSession, d: str) -> DataFrame:
    pairs = candidates.join_compatible(level_of(mine(anew(spark, d, "e4"), max_level=2), 2), "prefix")
    return pairs.select(F.concat_ws(",", F.col("items").cast("array<string>")).alias("items"))


@query(
    "pruned_candidates_e4",
    oracle.levels("e4", "0.45", 3) + f" SELECT {oracle.text('c.its')} AS items FROM (SELECT DISTINCT its FROM {oracle.compatible(3)}) c JOIN l3 ON list_has_all(c.its, l3.its) GROUP BY c.its HAVING count(*) = 4",
)
def _pruned(spark: SparkSession, d: str) -> DataFrame:
    r = exact(spark, d, "e4")
    level = level_of(r, 3)
    return named(candidates.prune_by_subsets(candidates.join_compatible(level), level), r.store, "items")


_COUNTED = (
    oracle.levels("e4", "0.45", 2)
    + f", c AS (SELECT DISTINCT its FROM {oracle.compatible(2)}), m AS (SELECT its, unnest(its) AS item FROM c), k AS (SELECT m.its, b.key FROM m JOIN b USING (item) GROUP BY m.its, b.key HAVING count(*) = 3)"
    + f" SELECT {oracle.text('c.its')} AS items, count(k.key) AS support FROM c LEFT JOIN k ON c.its = k.its GROUP BY c.its"
)
for _mode in ("kernel", "bitmap", "tidlist", "horizontal"):
    query(f"support_{_mode}_e4", _COUNTED)(
        lambda spark, d, m=_mode: named(support.count(candidates.join_compatible(level_of(r := exact(spark, d, "e4"), 2)), r.store, m), r.store, "items", key=("support",))
    )

# Padding, similarities, parameters, keys.

_IP = oracle.levels("e6", "0.28", 1) + ", x AS (SELECT a.its[1]::INT AS p, b.its[1]::INT AS q, a.c AS fp, b.c AS fq FROM l1 a JOIN l1 b ON a.its[1]::INT < b.its[1]::INT), i AS (SELECT a.item::INT AS p, c.item::INT AS q, count(*) AS ip FROM b a JOIN b c ON a.key = c.key AND a.item::INT < c.item::INT GROUP BY 1, 2), y AS (SELECT x.*, coalesce(ip, 0) AS ip, (SELECT max(c) FROM l1) AS big FROM x LEFT JOIN i USING (p, q))"


def _e6_pairs(spark: SparkSession, d: str) -> tuple[DataFrame, int]:
    st = store(spark, d, "e6")
    both = baselines.jaccard_pairs(st)
    label = F.array(*[F.lit(int(x)) for x in st.labels])
    p, q = label[F.col("items")[0]], label[F.col("items")[1]]
    most = int(st.items.agg(F.max("freq")).first()[0])
    return both.select(F.least(p, q).alias("p"), F.greatest(p, q).alias("q"), "ip", "jaccard", "hamming"), most


@query("padded_hamming_e6", _IP + " SELECT p, q, 2 * (big - ip) AS distance FROM y")
def _padded_hamming(spark: SparkSession, d: str) -> DataFrame:
    x, most = _e6_pairs(spark, d)
    return x.select("p", "q", padding.hamming_from_ip(F.col("ip"), most).alias("distance"))


@query("padded_jaccard_e6", _IP + " SELECT p, q, round(ip / (2 * big - ip), 9) AS similarity FROM y")
def _padded_jaccard(spark: SparkSession, d: str) -> DataFrame:
    x, most = _e6_pairs(spark, d)
    return x.select("p", "q", F.round(padding.jaccard_from_ip(F.col("ip"), most), 9).alias("similarity"))


@query("plain_similarities_e6", _IP + " SELECT p, q, ip, fp + fq - 2 * ip AS hamming, round(ip / (fp + fq - ip), 9) AS jaccard FROM y")
def _plain(spark: SparkSession, d: str) -> DataFrame:
    return _e6_pairs(spark, d)[0].select("p", "q", "ip", "hamming", F.round("jaccard", 9).alias("jaccard"))


@query("pair_classes_e6", _IP + " SELECT CASE WHEN ip >= s_min THEN 'frequent' WHEN ip < 0.7 * s_min THEN 'infrequent' ELSE 'gap' END AS class, count(*) AS n FROM y, n GROUP BY 1")
def _classes(spark: SparkSession, d: str) -> DataFrame:
    st = store(spark, d, "e6")
    c = metrics.pair_class(F.col("ip"), st.s_min, st.n, st.s_min / st.n, 0.3)
    return _e6_pairs(spark, d)[0].groupBy(c.alias("class")).agg(F.count(F.lit(1)).alias("n"))


def _md5_sql(seed: str, pos: str) -> str:
    return f"('0x' || substr(md5('{seed}:' || ({pos})::VARCHAR), 1, 15))::BIGINT"


@query(
    "minwise_md5_e2b",
    oracle.levels("e2b", "0.02", 1) + f", s AS (SELECT unnest(range(8)) AS slot), k AS (SELECT item, slot, min(('0x' || substr(md5(slot::VARCHAR || ':' || key), 1, 15))::BIGINT) AS h FROM b, s GROUP BY item, slot) SELECT x.item AS a, y.item AS q, sum((x.h = y.h)::INT)::BIGINT AS agree FROM k x JOIN k y ON x.slot = y.slot AND x.item < y.item GROUP BY 1, 2",
)
def _minwise_md5(spark: SparkSession, d: str) -> DataFrame:
    """Plain minwise summaries of items over transaction keys, in a hash that other engines have too."""
    pairs = encode(spark, d, "e2b")
    slots = pairs.withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(7))))
    rank = F.conv(F.substring(F.md5(F.concat_ws(":", F.col("slot").cast("string"), "key")), 1, 15), 16, 10).cast("long")
    k = written(slots.groupBy("label", "slot").agg(F.min(rank).alias("h")), "summary")
    x, y = k.select(F.col("label").alias("a"), "slot", F.col("h").alias("x")), k.select(F.col("label").alias("q"), "slot", F.col("h").alias("y"))
    return x.join(y, "slot").where("a < q").groupBy("a", "q").agg(F.sum((F.col("x") == F.col("y")).cast("long")).alias("agree"))


def _facts(spark: SparkSession, d: str, enc: str, eps: float = 0.3, delta: float = 0.1, top: int | None = None) -> list[tuple[int, Facts]]:
    r = exact(spark, d, enc, top=top)
    rows = r.itemsets.groupBy("level").agg(F.count(F.lit(1)).alias("m"), F.max("support").alias("a")).orderBy("level").collect()
    return [(x["level"], Facts(r.store.n, r.store.s_min, x["m"], x["a"], r.store.s_min / r.store.n, eps, delta)) for x in rows if x["m"] > 1]


_P = oracle.levels("e4", "0.45", 6) + oracle.all_levels(6) + ", g AS (SELECT level::INT AS level, count(*) AS m, max(c) AS big, max(n) AS n, max(s_min) AS s_min FROM a, n GROUP BY level HAVING count(*) > 1), t AS (SELECT *, big / n AS al, s_min / n AS th, 0.7 * s_min / n AS nr FROM g)"
_BASE = "((1 + 2 * al) / (1 + 2 * nr))"


@query("params_bitsample_e4", _P + f" SELECT level, m, big AS most, round((al - th) / (al - nr), 6) AS rho, round(ln(m) / ln({_BASE}), 6) AS k, round(pow(m, (al - th) / (al - nr)) * ln(10), 6) AS tables, round((1 + 2 * th) / (1 + 2 * al), 6) AS p1 FROM t")
def _params_b(spark: SparkSession, d: str) -> DataFrame:
    rows = [(k, f.m, f.A, *(round(params.bitsample(f)[c], 6) for c in ("rho", "k_real", "L_real", "p1"))) for k, f in _facts(spark, d, "e4")]
    return spark.createDataFrame(rows, "level int, m long, most long, rho double, k double, tables double, p1 double")


@query(
    "params_minwise_e4",
    _P + ", u AS (SELECT *, nr / (2 * al - nr) AS om, al * 0.3 / (al + (al - th) * 0.7) AS em FROM t) SELECT level, m, round(om, 6) AS omega, round(em, 6) AS eps_m, round(2 / (om * em * em) * ln(10), 4) AS slots, round((1 - em) * th / (2 * al - th), 6) AS accept FROM u",
)
def _params_m(spark: SparkSession, d: str) -> DataFrame:
    rows = []
    for k, f in _facts(spark, d, "e4"):
        p = params.minwise(f)
        rows.append((k, f.m, round(p["omega"], 6), round(p["eps_m"], 6), round(p["lambda_real"], 4), round(p["accept"], 6)))
    return spark.createDataFrame(rows, "level int, m long, omega double, eps_m double, slots double, accept double")


@query("params_covering_e4", _P + " SELECT level, m, 2 * (big - s_min) AS r, round(2 * (al - nr) * n, 6) AS far, CASE WHEN al > th THEN round((al - nr) / (al - th), 6) END AS c FROM t")
def _params_c(spark: SparkSession, d: str) -> DataFrame:
    rows = []
    for k, f in _facts(spark, d, "e4"):
        p = params.covering(f)
        rows.append((k, f.m, p["r"], round(p["far"], 6), round(p["c"], 6) if np.isfinite(p["c"]) else None))
    return spark.createDataFrame(rows, "level int, m long, r long, far double, c double")


def _shape(enc: str, kind: type, **options: object) -> Query:
    """Numbers of signatures and distinct keys of the first level: what a family costs."""
    def run(spark: SparkSession, d: str) -> DataFrame:
        st = store(spark, d, enc)
        level = st.items.select(F.array("item").alias("items"), F.col("freq").alias("support"))
        members, s = level_arrays(level)
        fam = kind(Facts(st.n, st.s_min, len(s), int(s.max()), st.s_min / st.n, 0.3, 0.1), **options)
        keys = candidates.spread(candidates.hashed(members, s, st, fam))
        return keys.groupBy("side").agg(F.count(F.lit(1)).alias("keys"), F.count_distinct("table_no").cast("int").alias("tables"), F.count_distinct("iid").alias("itemsets"))

    return run


query("bitsample_keys_e2")(_shape("e2", BitSample))
query("minwise_summary_e6")(_shape("e6", MinWise))
query("covering_keys_e4")(_shape("e4", Covering))

# Hashed mining: the same itemsets as the exact miner, at delta = 1e-6 and a fixed seed; covering by guarantee.

_MINED = {"e2": oracle.mined("e2", "0.02", 3), "e3": oracle.mined("e3", "0.05", 3), "e4": oracle.mined("e4", "0.45", 7), "e1": oracle.mined("e1", "0.003", 2), "e6": oracle.mined("e6", "0.28", 3), "e7": oracle.mined("e7", "0.12", 2)}


def hashed(name: str, enc: str, method: str, top: int | None = None, sql: str | None = None, theta: str | None = None, **options: object) -> None:
    query(name, sql or _MINED[enc])(lambda spark, d: mine(store(spark, d, enc, theta), method=method, max_level=top, **options).labelled())


for _e in ("e2", "e3", "e4"):
    hashed(f"bitsample_itemsets_{_e}", _e, "bitsample")
hashed("minwise_itemsets_e2", "e2", "minwise")
hashed("minwise_itemsets_e4", "e4", "minwise")
hashed("minwise_itemsets_e7", "e7", "minwise", top=2)
hashed("minwise_banded_e4", "e4", "minwise", mode="banded")
hashed("minwise_lambda_e4", "e4", "minwise", lambda_override=4000)
hashed("covering_itemsets_e4", "e4", "covering")
hashed("covering_radius0_e4", "e4", "covering", mode="exact_radius0")
hashed("covering_itemsets_e1", "e1", "covering")
hashed("covering_itemsets_e6", "e6", "covering")
hashed("auto_itemsets_e2", "e2", "auto")
hashed("auto_itemsets_e4", "e4", "auto")
hashed("bitsample_after_e4", "e4", "bitsample", verify="after")
hashed("covering_after_e4", "e4", "covering", verify="after", prune_subsets=True)
hashed("by_level_e4", "e4", "exact", method_by_level={1: "exact", 3: "minwise", 4: "covering"})
query("bitsample_printed_rounding_e2", oracle.mined("e2", "0.02", 1))(lambda spark, d: mine(anew(spark, d, "e2"), method="bitsample", max_level=1, rounding="ceil").labelled())
# The one above ends at level 1, as its SQL does, before any key is hashed; this one mines all levels by printed rounding.
hashed("bitsample_printed_itemsets_e2", "e2", "bitsample", rounding="ceil")
hashed("bitsample_early_stop_e1", "e1", "bitsample", early_stop=True)
hashed("covering_early_stop_e1", "e1", "covering", early_stop=True)
hashed("bitsample_early_stop_e6", "e6", "bitsample", early_stop=True, delta=1e-3)
hashed("minwise_eta_e4", "e4", "minwise", eta=1e-4)
hashed("exact_pruned_e4", "e4", "exact", prune_subsets=True)
# The other thresholds of the grid, and items that every transaction has.
hashed("bitsample_itemsets_e3_low", "e3", "bitsample", sql=oracle.mined("e3", "0.02", 6), theta="0.02")
for _m in ("bitsample", "minwise", "covering", "auto"):
    for _t in ("0.5", "0.4"):
        hashed(f"{_m}_itemsets_e4_{_t[2:]}0", "e4", _m, sql=oracle.mined("e4", _t, 8), theta=_t)
for _m in ("bitsample", "minwise", "covering"):
    hashed(f"{_m}_capped_e8", "e8", _m, top=3, sql=oracle.mined("e8", "0.5", 3))

for _m in ("bitsample", "minwise", "covering"):
    @query(f"soundness_{_m}_e4", f"SELECT '{_m}' AS method, 0::BIGINT AS wrong")
    def _sound(spark: SparkSession, d: str, m: str = _m) -> DataFrame:
        got, truth = mine(store(spark, d, "e4"), method=m, delta=0.1, seed=3).itemsets, exact(spark, d, "e4").itemsets
        return got.join(truth.select("items", "support"), ["items", "support"], "left_anti").agg(F.lit(m).alias("method"), F.count(F.lit(1)).alias("wrong"))


# Measures.

_UP = "(SELECT max(level) FROM a)"


def _stats_sql(top: int) -> str:
    parts = [f"SELECT {k + 1}::INT AS level, (SELECT count(*) FROM l{k}) AS m, (SELECT max(c) FROM l{k}) AS max_support, (SELECT count(*) FROM {oracle.compatible(k)}) AS pairs, (SELECT count(DISTINCT its) FROM {oracle.compatible(k)}) AS candidate_itemsets, (SELECT count(*) FROM l{k + 1}) AS found" for k in range(1, top)]
    return oracle.levels("e4", "0.45", top) + " SELECT * FROM (" + " UNION ALL ".join(parts) + ") WHERE m > 1"


query("level_stats_e4", _stats_sql(7))(lambda spark, d: exact(spark, d, "e4").stats.select("level", "m", "max_support", "pairs", "candidate_itemsets", "found"))


def _balance(method: str, enc: str, source: Callable[[SparkSession, str, str], Store] = store, **options: object) -> Query:
    """fp + tn = 2 (pairs - frequent pairs) of every level, with its cost measures."""
    def run(spark: SparkSession, d: str) -> DataFrame:
        s = mine(source(spark, d, enc), method=method, stats=True, delta=0.1, **options).stats
        return s.select("level", "method", "m", "max_support", "pairs", "kept_pairs", "found", "frequent_pairs", "fp", "fn", "tn", "signatures", (F.col("hash_seconds") / (2 * F.col("m"))).alias("tau"), (F.col("signature_bytes") / (2 * F.col("m"))).alias("sigma"), "phi", "phi_measured", "overhead", "savings", (F.col("savings") - F.col("overhead")).alias("net"))

    return run


for _m, _e in (("bitsample", "e2"), ("bitsample", "e1"), ("minwise", "e2"), ("minwise", "e4"), ("covering", "e4"), ("covering", "e1")):
    query(f"level_costs_{_m}_{_e}")(_balance(_m, _e, anew if _e == "e1" else store))


@query("break_even_table")
def _break_even(spark: SparkSession, d: str) -> DataFrame:
    """Guaranteed savings, overhead and regime flags of each method on each level of five workloads; of e7 the first, whose pairs are all that is mined of it."""
    rows = []
    for enc in ("e2", "e3", "e4", "e6", "e7"):
        top = 2 if enc == "e7" else None
        r = exact(spark, d, enc, top=top)
        found = {s["level"]: s for s in r.stats_rows}
        for level, f in _facts(spark, d, enc, top=top):
            s = found.get(level + 1)
            for m in metrics.BOUNDS if s else ():
                flags = metrics.regime(m, f, s["pairs"], s["found"])
                bound = metrics.BOUNDS[m](f, s["pairs"], s["found"])
                rows.append((enc, level, m, s["pairs"], s["found"], float(bound) if np.isfinite(bound) else None, metrics.overhead(m, f), all(flags.values()), metrics.choose(f, s["pairs"])))
    return spark.createDataFrame(rows, "workload string, level int, method string, pairs long, found long, bound double, overhead double, favourable boolean, chosen string")


def _sweep(name: str, enc: str, settings: list[tuple[str, dict]]) -> None:
    """Recall, kept pairs and costs as one parameter moves."""
    @query(name)
    def run(spark: SparkSession, d: str) -> DataFrame:
        truth, rows = exact(spark, d, enc).itemsets, []
        total = truth.count()
        for label, how in settings:
            r = mine(store(spark, d, enc), stats=True, truth=truth, **how)
            missing = metrics.missed(truth, r.itemsets).agg(F.count(F.lit(1)), F.coalesce(F.sum((F.col("lost_subsets") > 0).cast("long")), F.lit(0))).first()
            kept_pairs = sum(s["kept_pairs"] for s in r.stats_rows)
            rows.append((label, how["method"], 1 - missing[0] / max(total, 1), missing[1], kept_pairs, sum(s["pairs"] for s in r.stats_rows), float(sum(s["overhead"] for s in r.stats_rows)), float(sum(s["savings"] for s in r.stats_rows))))
        return spark.createDataFrame(rows, "setting string, method string, recall double, propagated long, kept_pairs long, pairs long, overhead double, savings double")


_sweep("sweep_delta_e4", "e4", [(f"{m} delta={x}", {"method": m, "delta": x}) for m in ("bitsample", "minwise") for x in (0.3, 0.1, 0.01, 1e-6)])
for _e in ("e3", "e4"):
    _sweep(f"sweep_eps_{_e}", _e, [(f"{m} eps={x}", {"method": m, "eps": x, "delta": 0.1}) for m in ("bitsample", "minwise") for x in (0.1, 0.3, 0.7)])
_sweep("sweep_lambda_e4", "e4", [(f"slots={x} {mode}", {"method": "minwise", "lambda_override": x, "mode": mode, "delta": 0.1}) for mode in ("scan", "banded") for x in (50, 200, 800)])
_sweep("sweep_early_stop_e6", "e6", [(f"{m} stop={x}", {"method": m, "early_stop": x, "delta": 0.1}) for m in ("bitsample", "covering") for x in (False, True)])


def _unpadded(spark: SparkSession, d: str, enc: str) -> DataFrame:
    """Frequent pairs that each way of hashing keeps and misses, with and without padding."""
    st = store(spark, d, enc)
    r = exact(spark, d, enc)
    truth = level_of(r, 2).select("items")
    level = st.items.select(F.array("item").alias("items"), F.col("freq").alias("support"))
    members, s = level_arrays(level)
    f = Facts(st.n, st.s_min, len(s), int(s.max()), st.s_min / st.n, 0.3, 0.1)
    ways = {"bitsample": candidates.join_hashed(members, s, st, BitSample(f)), "bitsample_plain": baselines.bitsample_unpadded(st), "minwise": candidates.join_hashed(members, s, st, MinWise(f)), "minwise_plain": baselines.minwise_unpadded(st)}
    out = None
    for way, pairs in ways.items():
        x = pairs.select("items").distinct().join(truth.withColumn("t", F.lit(1)), "items", "left").agg(F.lit(way).alias("way"), F.count(F.lit(1)).alias("kept"), F.coalesce(F.sum("t"), F.lit(0)).alias("frequent"))
        out = x if out is None else out.union(x)
    return out


for _e in ("e4", "e6"):
    query(f"padded_against_unpadded_{_e}")(lambda spark, d, e=_e: _unpadded(spark, d, e))


# Baselines.

query("fpgrowth_e4", _MINED["e4"])(lambda spark, d: named((x := baselines.fpgrowth(st := store(spark, d, "e4"))).withColumn("level", F.size("items")), st, "items", key=("level", "support")).select("level", F.col("items").alias("itemset"), "support"))
query("brute_e2", oracle.mined("e2", "0.02", 3))(lambda spark, d: named(baselines.brute(st := store(spark, d, "e2")).withColumn("level", F.size("items")), st, "items", key=("level", "support")).select("level", F.col("items").alias("itemset"), "support"))
query("sampled_e2")(lambda spark, d: baselines.sampled(encode(spark, d, "e2"), "0.02", 0.3).labelled())

# Uses of itemsets.

# Rules of pairs only, as their SQL has them; rules_all_e2c has those of all itemsets.
_RULES = oracle.levels("e2c", "0.5", 2) + ", x AS (SELECT its[1] AS a, its[2] AS c, c AS s FROM l2 UNION ALL SELECT its[2], its[1], c FROM l2) SELECT x.a AS antecedent, x.c AS consequent, x.s AS support, round(x.s / f1.s, 9) AS confidence, round(x.s * n.n / (f1.s * f2.s), 9) AS lift FROM x JOIN f f1 ON f1.label = x.a JOIN f f2 ON f2.label = x.c, n WHERE x.s / f1.s >= 0.75"


@query("rules_e2c", _RULES)
def _rules(spark: SparkSession, d: str) -> DataFrame:
    r = exact(spark, d, "e2c", top=2)
    x = rules.generate(r.itemsets.select("items", "support"), r.store.n, 0.75)
    return named(x, r.store, "antecedent", "consequent", key=("support", F.round("confidence", 9).alias("confidence"), F.round("lift", 9).alias("lift")))


_RULES_ALL = (
    oracle.levels("e2c", "0.5", 8) + oracle.all_levels(8) + ", x AS (SELECT its, c, unnest(its) AS label FROM a WHERE level > 1), y AS (SELECT *, list_filter(its, lambda i: i <> label) AS ante FROM x)"
    " SELECT array_to_string(y.ante, ',') AS antecedent, y.label AS consequent, y.c AS support, round(y.c / p.c, 9) AS confidence, round(y.c * n.n / (p.c * f.s), 9) AS lift FROM y JOIN a p ON p.its = y.ante JOIN f USING (label), n WHERE y.c / p.c >= 0.75"
)


@query("rules_all_e2c", _RULES_ALL)
def _rules_all(spark: SparkSession, d: str) -> DataFrame:
    r = exact(spark, d, "e2c")
    x = rules.generate(r.itemsets.select("items", "support"), r.store.n, 0.75)
    return named(x, r.store, "antecedent", "consequent", key=("support", F.round("confidence", 9).alias("confidence"), F.round("lift", 9).alias("lift")))


query("rules_any_e10")(lambda spark, d: named(rules.generate((r := exact(spark, d, "e10", top=3)).itemsets.select("items", "support"), r.store.n, 0.6, "any"), r.store, "antecedent", "consequent", key=("support", "confidence", "lift", "leverage", "conviction")))


@query("lift_pairs_e5", oracle.levels("e5", "0.1", 2) + " SELECT its[1] AS a, its[2] AS b, c AS support, round(c * n.n / (x.s * y.s), 9) AS lift, round(c / sqrt(x.s * y.s), 9) AS cosine, round(c / greatest(x.s, y.s), 9) AS all_confidence FROM l2 JOIN f x ON x.label = its[1] JOIN f y ON y.label = its[2], n")
def _lift(spark: SparkSession, d: str) -> DataFrame:
    r = exact(spark, d, "e5")
    label = F.array(*[F.lit(x) for x in r.store.labels])
    pairs = level_of(r, 2).select(F.least(label[F.col("items")[0]], label[F.col("items")[1]]).alias("a"), F.greatest(label[F.col("items")[0]], label[F.col("items")[1]]).alias("b"), "support")
    m = rules.pair_measures(pairs, r.store.items.select(F.col("label").alias("item"), F.col("freq").alias("support")), r.store.n)
    return m.select("a", "b", "support", *[F.round(c, 9).alias(c) for c in ("lift", "cosine", "all_confidence")])


_ALL4 = oracle.levels("e4", "0.45", 6) + oracle.all_levels(6)
for _name, _f, _more in (("maximal", rules.maximal, ""), ("closed", rules.closed, " AND y.c = x.c")):
    query(f"{_name}_e4", _ALL4 + f" SELECT {oracle.text('x.its')} AS items, x.c AS support FROM a x WHERE NOT EXISTS (SELECT 1 FROM a y WHERE y.level = x.level + 1 AND list_has_all(y.its, x.its){_more})")(
        lambda spark, d, f=_f: named(f((r := exact(spark, d, "e4")).itemsets.select("items", "support")), r.store, "items", key=("support",))
    )


@query("cluster_by_itemset_e4")
def _cluster(spark: SparkSession, d: str) -> DataFrame:
    r = exact(spark, d, "e4")
    c = rules.cluster_by_itemset(baskets(r.store.long), rules.maximal(r.itemsets.select("items", "support")))
    return named(c.groupBy("items").agg(F.count(F.lit(1)).alias("n")), r.store, "items", key=("n",))


query("sequences_users")(lambda spark, d: rules.sequences(load(spark, d, "events", "event_id", "ts", "user_id", "event_type"), 0.3, 3).select(F.to_json("sequence").alias("sequence"), "freq"))
# Itemsets that combine with the most frequent item to a frequent one; covering keys find the same, since they miss nothing.
_PARTNERS = oracle.levels("e4", "0.45", 2) + ", t AS (SELECT label FROM f ORDER BY s DESC, label LIMIT 1) SELECT CASE WHEN its[1] = label THEN its[2] ELSE its[1] END AS partner, c AS support FROM l2, t WHERE list_contains(its, label)"


def _neighbours(spark: SparkSession, d: str, hashed: bool) -> DataFrame:
    r = exact(spark, d, "e4")
    one, two = level_of(r, 1), level_of(r, 2)
    if hashed:
        members, supports = level_arrays(one)
        f = Facts(r.store.n, r.store.s_min, len(members), int(supports.max()), r.store.s_min / r.store.n, 0.3, 1e-6)
        pairs = candidates.join_hashed(members, supports, r.store, Covering(f))
    else:
        pairs = candidates.join_compatible(one)
    return named(candidates.neighbours(pairs, [0], two).join(two, "items"), r.store, "partner", key=("support",))


query("neighbours_e4", _PARTNERS)(lambda spark, d: _neighbours(spark, d, False))
query("neighbours_hashed_e4", _PARTNERS)(lambda spark, d: _neighbours(spark, d, True))
query("exists_three_e4", oracle.levels("e4", "0.45", 3) + " SELECT count(*) > 0 AS found FROM l3")(lambda spark, d: spark.createDataFrame([(exists_size(store(spark, d, "e4"), None, 3),)], "found boolean"))
query("confusion_covering_e4", _ALL4 + " SELECT level::INT AS level, count(*)::BIGINT AS both, 0::BIGINT AS missed, 0::BIGINT AS false, 1.0::DOUBLE AS recall, 1.0::DOUBLE AS precision FROM a GROUP BY level")(
    lambda spark, d: metrics.confusion(exact(spark, d, "e4").itemsets, mine(store(spark, d, "e4"), method="covering").itemsets).select("level", *[F.col(c).cast("long").alias(c) for c in ("both", "missed", "false")], "recall", "precision")
)


@query("recall_by_level_e4")
def _recall(spark: SparkSession, d: str) -> DataFrame:
    """Recall of each level beside what the method promises: a frequent itemset of l items is missed with probability of at most delta 2^l."""
    truth, out = exact(spark, d, "e4").itemsets, None
    for method in ("bitsample", "minwise", "covering"):
        for delta in (0.1, 1e-3):
            c = metrics.confusion(truth, mine(store(spark, d, "e4"), method=method, delta=delta).itemsets)
            c = c.select(F.lit(method).alias("method"), F.lit(delta).alias("delta"), "level", "both", "missed", "recall", F.greatest(F.lit(0.0), 1 - delta * F.pow(F.lit(2.0), "level")).alias("promised"))
            out = c if out is None else out.unionByName(c)
    return out


@query("per_query_costs_e4")
def _per_query(spark: SparkSession, d: str) -> DataFrame:
    """For every single word as a query: partners met, of these frequent and not, and partners rightly passed by, with bit sampling."""
    r = exact(spark, d, "e4")
    one, two = level_of(r, 1), level_of(r, 2)
    members, supports = level_arrays(one)
    f = Facts(r.store.n, r.store.s_min, len(members), int(supports.max()), r.store.s_min / r.store.n, 0.3, 0.1)
    met = candidates.join_hashed(members, supports, r.store, BitSample(f), directions=True)
    return named(metrics.per_query(met, candidates.join_compatible(one), two), r.store, "query", key=("partners", "frequent", "met", "fp", "fn", "tn"))


for _e, _top in (("e2", 2), ("e4", 6), ("e6", 2)):
    _levels = oracle.levels(_e, THETA[_e], _top + 1) + " " + " UNION ALL ".join(
        f"SELECT {k + 1}::INT AS level, (SELECT count(*) FROM l{k})::BIGINT AS m, count(*)::BIGINT AS pairs, count(*) FILTER (its IN (SELECT its FROM l{k + 1}))::BIGINT AS frequent_pairs, (SELECT count(*) FROM l{k + 1})::BIGINT AS found, 0::BIGINT AS fn FROM {oracle.compatible(k)} HAVING count(*) > 0" for k in range(1, _top + 1)
    )
    query(f"level_truth_{_e}", _levels)(lambda spark, d, e=_e: mine(store(spark, d, e), method="covering" if e != "e2" else "exact", stats=True).stats.where("pairs > 0").select("level", "m", "pairs", "frequent_pairs", "found", "fn"))

# Relational operators.

query("cube_e3", "SELECT l_returnflag AS rf, l_linestatus AS ls, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")(lambda spark, d: relops.cube(load(spark, d, "lineitem", "l_returnflag", "l_linestatus").toDF("rf", "ls"), "rf", "ls"))
query("rollup_levels_e4", _ALL4 + " SELECT level::INT AS level, count(*) AS n, sum(c)::BIGINT AS support, grouping(level)::INT AS total FROM a GROUP BY ROLLUP (level)")(lambda spark, d: relops.rollup_levels(exact(spark, d, "e4").itemsets))
query("topk_per_level_e4", _ALL4 + f", t AS (SELECT level::INT AS level, {oracle.text('its')} AS itemset, c AS support FROM a) SELECT *, (row_number() OVER (PARTITION BY level ORDER BY support DESC, itemset))::INT AS rn FROM t QUALIFY rn <= 3")(lambda spark, d: relops.top_k(exact(spark, d, "e4").labelled(), 3))
query("ranks_e4", _ALL4 + f", t AS (SELECT level::INT AS level, {oracle.text('its')} AS itemset, c AS support FROM a) SELECT *, (rank() OVER s)::INT AS rk, (dense_rank() OVER s)::INT AS drk, (ntile(4) OVER w)::INT AS quarter, lag(support) OVER w AS before, first_value(support) OVER w AS most FROM t WINDOW w AS (PARTITION BY level ORDER BY support DESC, itemset), s AS (PARTITION BY level ORDER BY support DESC)")(
    lambda spark, d: relops.ranked(exact(spark, d, "e4").labelled())
)
query("constrained_e4", _ALL4 + f" SELECT {oracle.text('its')} AS items, c AS support FROM a WHERE level BETWEEN 2 AND 3 AND list_contains(its, (SELECT label FROM f ORDER BY s DESC, label LIMIT 1))")(
    lambda spark, d: named(relops.constrained((r := exact(spark, d, "e4")).itemsets, include=[0], sizes=(2, 3)), r.store, "items", key=("support",))
)
_EV = ("event_id", "ts", "user_id", "event_type")
query("asof_signup_purchase", "SELECT p.event_id, max(s.ts) AS signup FROM (SELECT * FROM events WHERE event_type = 'purchase') p LEFT JOIN (SELECT * FROM events WHERE event_type = 'signup') s ON p.user_id = s.user_id AND s.ts <= p.ts GROUP BY p.event_id")(
    lambda spark, d: relops.as_of((e := load(spark, d, "events", *_EV)).where("event_type = 'purchase'").select("user_id", "ts", "event_id"), e.where("event_type = 'signup'").select("user_id", "ts"), "user_id", "ts", F.col("ts"), "signup").select("event_id", "signup")
)
query("interval_episode_pairs", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")(
    lambda spark, d: relops.within((e := load(spark, d, "events", "event_id", "ts", "user_id")), e, "user_id", "ts", 3600, "r").select(F.col("event_id").alias("a"), F.col("r_event_id").alias("b"))
)
query("set_ops_methods_e4", _MINED["e4"].rsplit("\n", 1)[0] + " SELECT 'both' AS side, sum(k)::BIGINT AS n FROM (" + " UNION ALL ".join(f"SELECT count(*) AS k FROM l{k}" for k in range(1, 8)) + ")")(
    lambda spark, d: relops.set_ops(exact(spark, d, "e4").labelled(), mine(store(spark, d, "e4"), method="minwise").labelled()).groupBy("side").agg(F.count(F.lit(1)).alias("n"))
)
query("one_hot_round_trip_e2b", oracle.levels("e2b", "0.02", 1) + " SELECT label, s AS n FROM f")(
    lambda spark, d: relops.from_one_hot(relops.one_hot((st := store(spark, d, "e2b")).long, ids := list(range(len(st.labels)))), ids).groupBy(F.element_at(F.array(*[F.lit(x) for x in st.labels]), F.col("item") + 1).alias("label")).agg(F.count(F.lit(1)).alias("n"))
)
query("item_preview_e4")(lambda spark, d: relops.itemset_counts_preview(store(spark, d, "e4").long, 1))


@query("udtf_subsets_e4", _ALL4 + ", s AS (SELECT its, unnest(its) AS gone FROM l3) SELECT count(*) AS n, count(DISTINCT list_filter(its, lambda x: x <> gone)) AS kinds FROM s")
def _udtf(spark: SparkSession, d: str) -> DataFrame:
    fn.register(spark)
    level_of(mine(anew(spark, d, "e4"), max_level=3), 3).createOrReplaceTempView("level_three")
    return spark.sql("SELECT count(*) AS n, count(DISTINCT subset) AS kinds FROM level_three, LATERAL leave_one_out(items)")


# Streams.


def _checkpoint(spark: SparkSession) -> str:
    import uuid

    return f"{scratch_dir(spark)}/stream-{uuid.uuid4().hex}"


@query("stream_window_items", "WITH w AS (SELECT date_trunc('day', ts) AS starts, event_type, count(*) AS n FROM events GROUP BY 1, 2) SELECT starts, event_type, n FROM w WHERE starts + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)")
def _stream(spark: SparkSession, d: str) -> DataFrame:
    at = _checkpoint(spark)
    streaming.run_once(streaming.item_counts(streaming.read_events(spark, d)), at + "/out", at + "/state")
    return spark.read.schema("starts timestamp, event_type string, n long").parquet(at + "/out").withColumn("starts", F.col("starts").cast("timestamp_ntz"))


@query("stream_mined_windows")
def _stream_mined(spark: SparkSession, d: str) -> DataFrame:
    at = _checkpoint(spark)
    streaming.mine_windows(streaming.windows(streaming.read_events(spark, d)), "0.05", at + "/out", at + "/state")
    return spark.read.schema("level int, itemset string, support long, batch long").parquet(at + "/out")


@query("stream_late_rows")
def _stream_late(spark: SparkSession, d: str) -> DataFrame:
    """How many rows came in time and late; a table in one file is one batch, of which nothing is late."""
    at = _checkpoint(spark)
    streaming.split_late(streaming.read_events(spark, d), at + "/out", at + "/state")
    both = [spark.read.schema("event_id long").parquet(f"{at}/out/{side}").select(F.lit(side).alias("side")) for side in ("rows", "late")]
    return both[0].union(both[1]).groupBy("side").agg(F.count(F.lit(1)).alias("n"))


for _mode in ("update", "complete"):
    @query(f"stream_counts_{_mode}", "SELECT date_trunc('day', ts) AS starts, event_type, count(*) AS n FROM events GROUP BY 1, 2")
    def _stream_counts(spark: SparkSession, d: str, mode: str = _mode) -> DataFrame:
        at = _checkpoint(spark)
        streaming.run_changes(streaming.item_counts(streaming.read_events(spark, d)), at + "/out", at + "/state", mode)
        got = streaming.current(spark, at + "/out", "starts timestamp, event_type string, n long", ["starts", "event_type"], mode)
        return got.withColumn("starts", F.col("starts").cast("timestamp_ntz"))


@query("stream_summaries", "SELECT event_type AS label, slot::INT AS slot, min(('0x' || substr(md5(slot::VARCHAR || ':' || user_id::VARCHAR), 1, 15))::BIGINT) AS h FROM events, (SELECT unnest(range(16)) AS slot) WHERE user_id IS NOT NULL AND event_type IS NOT NULL GROUP BY 1, 2")
def _stream_summaries(spark: SparkSession, d: str) -> DataFrame:
    """Minwise summaries of event types over users, merged batch by batch."""
    at = _checkpoint(spark)
    pairs = streaming.read_events(spark, d).select(F.col("user_id").cast("string").alias("key"), F.col("event_type").alias("label"))
    streaming.summaries(pairs, at + "/out", at + "/state", 16)
    return streaming.current(spark, at + "/out", streaming.SUMMARY, ["label", "slot"], "complete")


query("episodes_hourly")(lambda spark, d: streaming.episodes(load(spark, d, "events", "ts", "event_type"), "0.1", "6 hours", "3 hours").labelled())


def flagship(spark: SparkSession, d: str) -> DataFrame:
    return mine(encode(spark, d, "e4"), "0.45", "covering").labelled()

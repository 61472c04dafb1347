"""Mixing sources to target weights by systematic sampling.

Within a source every document has the same expected number of copies; the documents are put in one order,
the expected copies are summed along it from one random offset, and a document is emitted once for each whole
number that its step crosses. The order goes by size class, then by salt, so that a source's words come near
its target; ranks come from three bounded levels of counts, never from one task per source.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD

#: No document is repeated more often, and no target is larger than this many times its source.
MOST = 3
#: Salts within a size class for every so many documents: a bound on how many documents of one class one task ranks.
SALTS, DOCS = 256, 20_000_000
SEED = "mix-1"


def words(text: Column) -> Column:
    """Number of words; null has none. Removing them and counting what is left is not needed: one pass."""
    return F.coalesce(F.size(F.regexp_extract_all(text, F.lit(WORD), F.lit(0))), F.lit(0)).cast("long")


def hex_int(c: Column, first: int, digits: int) -> Column:
    return F.conv(F.substring(F.md5(c.cast("binary")), first, digits), 16, 10).cast("long")


def targets(sizes: DataFrame, most: int = MOST) -> DataFrame:
    """Adds target to sizes(source, source_size): shares of the sum by weight 1, 2, 3, ... in code point order,
    null last; no target over most times its source's size, the excess shared again by weight."""
    named = Window.orderBy(F.col("source").asc_nulls_last())
    ranked = sizes.withColumn("w", (1 + (F.row_number().over(named) - 1) % 3).cast("long")).withColumn("cap", most * F.col("source_size"))
    # Sources fill up in the order of cap / w; the water level is that of the first prefix that fits.
    fill = Window.orderBy((F.col("cap") / F.col("w")).asc(), F.col("source").asc_nulls_last())
    upto = fill.rowsBetween(Window.unboundedPreceding, -1)
    every = Window.partitionBy()
    level = ranked.withColumn("left", F.sum("source_size").over(every) - F.coalesce(F.sum("cap").over(upto), F.lit(0)))
    level = level.withColumn("w_left", F.sum("w").over(every) - F.coalesce(F.sum("w").over(upto), F.lit(0)))
    fits = F.col("left") * F.col("w") <= F.col("cap") * F.col("w_left")
    level = level.withColumn("level", F.min(F.when(fits, F.struct(F.col("cap") / F.col("w"), F.col("left"), F.col("w_left")))).over(every))
    first = F.col("level")
    target = F.when(F.col("cap") * first["w_left"] <= first["left"] * F.col("w"), F.col("cap").cast("double"))
    return level.select("source", "source_size", F.coalesce(target, F.col("w") * first["left"] / first["w_left"], F.lit(0.0)).cast("double").alias("target"))


def size_class(size: Column) -> Column:
    """Bit length and leading four bits: about 8 classes for each doubling of the size."""
    bits = F.length(F.bin(size))
    return (bits * 16 + F.expr("shiftright(size, greatest(length(bin(size)) - 4, 0))")).cast("int")


RESULTS = ("size", "source_size", "target", "copies", "taken")


def mix(docs: DataFrame, most: int = MOST, salts: int | None = None, seed: str = SEED, size: Column | None = None, prefix: str = "") -> DataFrame:
    """One row per document: the input's columns, and size, source_size, target, copies, taken, with the prefix before each of these names.

    docs has doc_id and source, and a text whose words are its size unless size is given. Columns of docs named like a result give way to it. A null text has no words; a source
    without words has target 0 and takes nothing; documents with equal sizes are told apart by their id;
    rows with the same id and size may swap places but agree in what is taken overall. Texts of any length are counted whole. Empty in, empty out.
    """
    salts = salts or SALTS * max(1, -(-docs.count() // DOCS))
    given = [c for c in docs.columns if c not in {prefix + x for x in RESULTS}]
    carried = {c: f"_in{i}" for i, c in enumerate(given) if c not in ("doc_id", "source")}
    d = docs.select("doc_id", "source", *(F.col(f"`{c}`").alias(n) for c, n in carried.items()), (words(F.col("text")) if size is None else size).alias("size"))
    kept = list(carried.values())
    d = d.withColumn("_class", size_class(F.col("size"))).withColumn("_salt", (hex_int(F.concat(F.lit(seed), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), 1, 8) % salts).cast("int"))
    cells = d.groupBy("source", "_class", "_salt").agg(F.count(F.lit(1)).alias("_n"), F.sum("size").alias("_words"))
    classes = cells.groupBy("source", "_class").agg(F.sum("_n").alias("_cn"), F.sum("_words").alias("_cw"))
    sources = classes.groupBy("source").agg(F.sum("_cw").alias("source_size"))
    before = lambda n, part, order: F.coalesce(F.sum(n).over(Window.partitionBy(*part).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    c = classes.withColumn("_cbefore", before("_cn", ["source"], ["_class"]))
    c = c.alias("c").join(targets(sources, most).alias("t"), F.expr("c.source <=> t.source")).select("c.source", "c._class", "c._cbefore", "t.source_size", "t.target")
    s = cells.withColumn("_sbefore", before("_n", ["source", "_class"], ["_salt"]))
    s = s.alias("s").join(c.alias("c"), F.expr("s.source <=> c.source AND s._class = c._class"))
    s = s.select("s.source", "s._class", "s._salt", (F.col("_sbefore") + F.col("_cbefore")).alias("_before"), "source_size", "target")
    d = d.withColumn("_rank", F.row_number().over(Window.partitionBy("source", "_class", "_salt").orderBy("size", "doc_id")))
    keep = [F.col(f"d.{x}") for x in ("doc_id", "source", *kept)]
    j = d.alias("d").join(s.alias("s"), F.expr("d.source <=> s.source AND d._class = s._class AND d._salt = s._salt"))
    j = j.select(*keep, F.col("d.size"), "source_size", "target", (F.col("_before") + F.col("_rank")).alias("_k"))
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    offset = hex_int(F.concat(F.lit(seed), F.lit("/"), F.coalesce("source", F.lit(""))), 1, 8) / F.lit(float(16**8))
    j = j.withColumn("_r", rate).withColumn("_u", offset)
    crossed = F.floor(F.col("_k") * F.col("_r") + F.col("_u")) - F.floor((F.col("_k") - 1) * F.col("_r") + F.col("_u"))
    j = j.withColumn("copies", F.least(crossed, F.lit(most)).cast("long"))
    j = j.withColumn("taken", F.col("copies") * F.col("size"))
    return j.select(*(F.col(carried.get(c, c)).alias(c) for c in given), *(F.col(c).alias(prefix + c) for c in RESULTS))


SQL = f"""
WITH d AS (SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '{WORD}')), 0)::BIGINT AS size FROM documents),
k AS (SELECT *, length(bin(size)) * 16 + (size >> greatest(length(bin(size)) - 4, 0)) AS cls,
      (('0x' || substr(md5('{SEED}' || doc_id::VARCHAR), 1, 8))::BIGINT) % (SELECT {SALTS} * greatest(1, ceil(count(*) / {DOCS}.0))::BIGINT FROM d) AS salt FROM d),
r AS (SELECT *, row_number() OVER (PARTITION BY source ORDER BY cls, salt, size, doc_id) AS k FROM k),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
w AS (SELECT *, (1 + (row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3)::BIGINT AS w, {MOST} * source_size AS cap FROM s),
f AS (SELECT *, (sum(source_size) OVER () - coalesce(sum(cap) OVER p, 0))::BIGINT AS lft, (sum(w) OVER () - coalesce(sum(w) OVER p, 0))::BIGINT AS wl
      FROM w WINDOW p AS (ORDER BY cap / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
l AS (SELECT lft, wl FROM f WHERE lft * w <= cap * wl ORDER BY cap / w, lft, wl LIMIT 1),
t AS (SELECT f.source, f.source_size, CASE WHEN f.cap * l.wl <= l.lft * f.w THEN f.cap::DOUBLE ELSE (f.w * l.lft)::DOUBLE / l.wl END AS target FROM f, l),
x AS (SELECT r.doc_id, r.size, t.source_size, t.target, r.k, CASE WHEN t.source_size > 0 THEN t.target / t.source_size ELSE 0 END AS rate,
      ('0x' || substr(md5('{SEED}/' || coalesce(r.source, '')), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS u
      FROM r JOIN t ON r.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target, (least(floor(k * rate + u) - floor((k - 1) * rate + u), {MOST}) * size)::BIGINT AS taken FROM x
"""

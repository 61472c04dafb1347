"""Explicit schemas of the engine's own frames."""

from pyspark.sql import types as T

BASKET_LONG = T.StructType([T.StructField("tid", T.LongType()), T.StructField("item", T.IntegerType())])
BASKETS = T.StructType([T.StructField("tid", T.LongType()), T.StructField("items", T.ArrayType(T.IntegerType()))])
DICTIONARY = T.StructType([T.StructField("item", T.IntegerType()), T.StructField("label", T.StringType()), T.StructField("freq", T.LongType())])
LEVEL = T.StructType([T.StructField("items", T.ArrayType(T.IntegerType())), T.StructField("support", T.LongType())])
ITEMSETS = T.StructType([T.StructField("level", T.IntegerType()), *LEVEL.fields])
SIGNATURES = T.StructType([T.StructField("iid", T.LongType()), T.StructField("table_no", T.IntegerType()), T.StructField("key", T.LongType())])
CANDIDATES = T.StructType([T.StructField("items", T.ArrayType(T.IntegerType())), T.StructField("parent_a", T.ArrayType(T.IntegerType())), T.StructField("parent_q", T.ArrayType(T.IntegerType()))])
STATS = T.StructType(
    [T.StructField("level", T.IntegerType()), T.StructField("method", T.StringType())]
    + [T.StructField(c, T.LongType()) for c in ("m", "max_support", "pairs", "candidate_itemsets", "kept_pairs", "kept_itemsets", "found", "frequent_pairs", "fp", "tn", "fn", "signatures", "signature_bytes", "counted_after")]
    + [T.StructField(c, T.DoubleType()) for c in ("phi", "phi_measured", "overhead", "savings", "hash_seconds")]
    + [T.StructField("params", T.MapType(T.StringType(), T.DoubleType()))]
)

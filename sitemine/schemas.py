"""Fixed schemas of the tables that the methods exchange."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

BASKET_ROWS = T.StructType([T.StructField("site", T.IntegerType()), T.StructField("tid", T.LongType()), T.StructField("item", T.StringType())])
BASKETS = T.StructType([T.StructField("site", T.IntegerType()), T.StructField("tid", T.LongType()), T.StructField("items", T.ArrayType(T.IntegerType()))])
DICTIONARY = T.StructType([T.StructField("item", T.StringType()), T.StructField("code", T.IntegerType()), T.StructField("support", T.LongType())])
LOCAL_SETS = T.StructType(
    [T.StructField("site", T.IntegerType()), T.StructField("itemset", T.ArrayType(T.IntegerType())), T.StructField("size", T.IntegerType()), T.StructField("cnt", T.LongType())]
)
ITEMSETS = T.StructType([T.StructField("itemset", T.ArrayType(T.IntegerType())), T.StructField("size", T.IntegerType()), T.StructField("support", T.LongType())])
POINTS = T.StructType([T.StructField("site", T.IntegerType()), T.StructField("point_id", T.LongType()), T.StructField("features", T.ArrayType(T.DoubleType()))])
SUB_STATS = T.StructType(
    [
        T.StructField("site", T.IntegerType()),
        T.StructField("local_id", T.IntegerType()),
        T.StructField("n", T.LongType()),
        T.StructField("center", T.ArrayType(T.DoubleType())),
        T.StructField("scatter", T.DoubleType()),
    ]
)
CLUSTERS = T.StructType(
    [
        T.StructField("global_id", T.IntegerType()),
        T.StructField("n", T.LongType()),
        T.StructField("center", T.ArrayType(T.DoubleType())),
        T.StructField("scatter", T.DoubleType()),
        T.StructField("n_members", T.IntegerType()),
    ]
)
LABELS = T.StructType([T.StructField("site", T.IntegerType()), T.StructField("local_id", T.IntegerType()), T.StructField("global_id", T.IntegerType())])
LINKS = T.StructType(
    [T.StructField("src", T.IntegerType()), T.StructField("dst", T.IntegerType()), T.StructField("mbit_s", T.DoubleType()), T.StructField("latency_ms", T.DoubleType())]
)
STAGE_TIMES = T.StructType(
    [T.StructField("run", T.StringType()), T.StructField("stage", T.StringType()), T.StructField("process", T.IntegerType()), T.StructField("seconds", T.DoubleType())]
)


def require_columns(df: DataFrame, schema: T.StructType) -> DataFrame:
    """``df``, or a ValueError naming the columns that ``schema`` has and ``df`` lacks."""
    missing = [f.name for f in schema.fields if f.name not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {', '.join(missing)}")
    return df

"""Fixed schemas of the frames that pass between the operators."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

#: What a release may hold: never a true count.
RELEASED = ("tree_id", "level", "node_id", "parent_id", "is_leaf", "kind", "eps_count", "y", "beta")
LEDGER = T.StructType([T.StructField("dataset", T.StringType()), T.StructField("tree_id", T.StringType()), T.StructField("eps", T.DoubleType()), T.StructField("delta", T.DoubleType()), T.StructField("neighbor", T.StringType()), T.StructField("spec", T.MapType(T.StringType(), T.StringType())), T.StructField("ts", T.TimestampType())])
SECRET = ("c", "n", "count", "true_count")


def assert_matches(df: DataFrame, wanted: dict[str, str]) -> DataFrame:
    found = dict(df.dtypes)
    off = {k: (v, found.get(k)) for k, v in wanted.items() if found.get(k) != v}
    if off:
        raise TypeError(f"columns (wanted, found): {off}")
    return df


def assert_released(df: DataFrame) -> DataFrame:
    """df, if it holds nothing that must stay secret."""
    leaks = [c for c in df.columns if c in SECRET]
    if leaks:
        raise ValueError(f"a release may not hold {leaks}")
    return df

"""Fixed schemas of bags and signatures, and the checks at the library's edge."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

BAG = T.StructType([T.StructField("bag_id", T.LongType()), T.StructField("elem", T.LongType()), T.StructField("weight", T.DoubleType())])
SIGNATURE = T.StructType([T.StructField("bag_id", T.LongType()), T.StructField("j", T.IntegerType()), T.StructField("id", T.LongType()), T.StructField("h", T.DoubleType())])


def check_bag(bags: DataFrame, on_invalid: str = "error") -> DataFrame:
    """Bags with the canonical columns and types; rows without keys or weight go, invalid weights raise or go."""
    missing = {"bag_id", "elem", "weight"} - set(bags.columns)
    if missing:
        raise ValueError(f"bag columns missing: {sorted(missing)}")
    if on_invalid not in ("error", "drop"):
        raise ValueError("on_invalid is 'error' or 'drop'")
    w = F.col("weight").cast("double")
    rows = bags.select(F.col("bag_id").cast("long"), F.col("elem").cast("long"), w.alias("weight")).where("bag_id is not null and elem is not null and weight is not null")
    bad = F.isnan("weight") | (F.col("weight") < 0) | (F.col("weight") == float("inf"))
    if on_invalid == "drop":
        return rows.where(~bad & (F.col("weight") > 0))
    checked = F.when(bad, F.raise_error(F.concat(F.lit("invalid weight "), F.col("weight").cast("string")))).otherwise(F.col("weight"))
    return rows.withColumn("weight", checked).where("weight > 0")

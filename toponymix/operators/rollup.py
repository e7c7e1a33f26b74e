"""Sales by place: by the standard name only, or with its aliases."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def volume(orders: DataFrame, standard: DataFrame, aliases: DataFrame) -> DataFrame:
    """(city, district, std_name, orders_name_only, orders_with_alias, value_name_only, value_with_alias).

    An order counts for each standard name its written name stands for; values are exact cents.
    """
    of = aliases.select("city", "district", F.col("cand_name").alias("place_name"), "std_name", F.lit(0).alias("own"))
    own = standard.select("city", "district", F.col("name").alias("place_name"), F.col("name").alias("std_name"), F.lit(1).alias("own"))
    cents = F.round(F.col("o_totalprice") * 100).cast("bigint")
    hit = orders.select("city", "district", "place_name", cents.alias("cents")).groupBy("city", "district", "place_name").agg(F.count(F.lit(1)).alias("k"), F.sum("cents").alias("v"))
    j = own.unionByName(of).join(hit, ["city", "district", "place_name"])
    only = F.col("own") == 1
    zero = F.lit(0).cast("bigint")
    return j.groupBy("city", "district", "std_name").agg(
        F.coalesce(F.sum(F.when(only, F.col("k"))), zero).alias("orders_name_only"),
        F.sum("k").alias("orders_with_alias"),
        F.coalesce(F.sum(F.when(only, F.col("v"))), zero).alias("value_name_only"),
        F.sum("v").alias("value_with_alias"),
    )

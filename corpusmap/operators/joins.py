"""As-of and interval joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def as_of(left: DataFrame, right: DataFrame, keys: list[str], left_time: str, right_time: str, value: str) -> DataFrame:
    """``left`` with the latest ``value`` at or before its time; one shuffle: both sides in one ordered window."""
    a = left.select("*", F.col(left_time).alias("_t"), F.lit(1).alias("_side"), F.lit(None).cast(right.schema[value].dataType).alias("_v"))
    b = right.select(*keys, F.col(right_time).alias("_t"), F.lit(0).alias("_side"), F.col(value).alias("_v"))
    order = Window.partitionBy(*keys).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b, allowMissingColumns=True)
    return both.withColumn("as_of_value", F.last("_v", ignorenulls=True).over(order)).filter("_side = 1").drop("_t", "_side", "_v")


def within_interval(left: DataFrame, right: DataFrame, keys: list[str], left_time: str, right_time: str, seconds: int) -> DataFrame:
    """Pairs of equal ``keys`` where the right row comes after the left one by at most ``seconds``.

    Times are cut into slots of that length; a right row is met in its own slot and the one before.
    """
    slot = lambda t: F.floor(F.unix_timestamp(F.col(t).cast("timestamp")) / seconds)
    a = left.withColumn("_slot", F.explode(F.array(slot(left_time), slot(left_time) + 1)))
    b = right.withColumn("_slot", slot(right_time))
    gap = F.col(right_time) - F.col(left_time)
    return a.join(b, [*keys, "_slot"]).filter((F.col(right_time) > F.col(left_time)) & (gap <= F.expr(f"interval {seconds} seconds"))).drop("_slot")

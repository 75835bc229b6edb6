"""Running sums over a global order without a window that holds all rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..storage import staged


def running_sums(df: DataFrame, order: list, sums: dict[str, str]) -> DataFrame:
    """Adds columns (name: summed column), each the sum up to and with the row in the given order.

    Rows are range-partitioned; sums run inside partitions and are shifted by the totals of
    the partitions before (one row a partition). The order must be total.
    """
    placed = staged(df.repartitionByRange(*order).withColumn("_part", F.spark_partition_id()), "placed")
    totals = placed.groupBy("_part").agg(*[F.sum(c).alias(f"_{n}") for n, c in sums.items()])
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    shifts = totals.select("_part", *[F.coalesce(F.sum(f"_{n}").over(before), F.lit(0)).alias(f"_{n}") for n in sums])
    inside = Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    out = placed.select("*", *[F.sum(c).over(inside).alias(f"_in_{n}") for n, c in sums.items()]).join(F.broadcast(shifts), "_part")
    return out.select(*df.columns, *[(F.col(f"_in_{n}") + F.col(f"_{n}")).alias(n) for n in sums])

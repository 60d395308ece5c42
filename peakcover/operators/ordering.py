"""Global numbering and prefix sums without a window over one partition.

Rows are range-partitioned by the order; each partition numbers (or sums) its own rows, and the totals of the
partitions before it, one row each, are added.  The partition counts travel as a small table, not the rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _blocks(df: DataFrame, order: list[str], parts: int | None) -> DataFrame:
    n = parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return df.repartitionByRange(n, *order).withColumn("__block", F.spark_partition_id())


def prefix_sums(df: DataFrame, order: list[str], sums: dict[str, str], parts: int | None = None) -> DataFrame:
    """``df`` with columns of running sums (inclusive, ties broken by row) named by ``sums`` (new column -> SQL value)."""
    spark = df.sparkSession
    blocks = _blocks(df, order, parts).withColumns({f"__v_{k}": F.expr(v) for k, v in sums.items()})
    from ..plans.staging import staged

    blocks = staged(blocks, "prefix-blocks")  # the range bounds are sampled once, so both uses see the same blocks
    totals = blocks.groupBy("__block").agg(*(F.sum(f"__v_{k}").alias(k) for k in sums))
    before = Window.orderBy("__block").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select(F.col("__block"), *(F.coalesce(F.sum(k).over(before), F.lit(0)).alias(f"__o_{k}") for k in sums))  # one row a block
    inside = Window.partitionBy("__block").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    out = blocks.join(F.broadcast(offsets), "__block").withColumns({k: F.sum(f"__v_{k}").over(inside) + F.col(f"__o_{k}") for k in sums})
    return out.drop("__block", *(f"__v_{k}" for k in sums), *(f"__o_{k}" for k in sums))


def numbered(df: DataFrame, order: list[str], name: str = "rn", parts: int | None = None) -> DataFrame:
    """``df`` with its rank in the order, from 1."""
    return prefix_sums(df, order, {name: "1L"}, parts)

"""Best intervals on a line: one length, many lengths, and the smallest interval with k points.

Weights may have any sign; intervals are closed.  An optimum either covers nothing (0) or starts or ends where
a point enters or leaves, so a sweep over enter and leave events sees it.  Events of equal position are added
before any leaves, and equal positions are summed first: a long table shrinks to its distinct positions.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .ordering import numbered, prefix_sums


def collapsed(points: DataFrame) -> DataFrame:
    return points.groupBy("pos").agg(F.sum("w").alias("w"))


def sweep_events(points: DataFrame, lengths: DataFrame) -> DataFrame:
    """(q_id, length, at, kind, dw): the starts at which a point enters (kind 0) and has left (kind 1)."""
    both = F.array(F.struct((F.col("pos") - F.col("length")).alias("at"), F.lit(0).alias("kind"), F.col("w").alias("dw")), F.struct(F.col("pos").alias("at"), F.lit(1).alias("kind"), (-F.col("w")).alias("dw")))
    return collapsed(points).crossJoin(F.broadcast(lengths)).select("q_id", "length", F.explode(both).alias("e")).select("q_id", "length", "e.at", "e.kind", "e.dw").groupBy("q_id", "length", "at", "kind").agg(F.sum("dw").alias("dw"))


def batched_interval(points: DataFrame, lengths: DataFrame) -> DataFrame:
    """(q_id, length, start, weight) for every length; start is null and weight 0 where nothing is worth covering."""
    run = Window.partitionBy("q_id", "length").orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, 0)
    best = sweep_events(points, lengths).withColumn("sum", F.sum("dw").over(run)).groupBy("q_id", "length").agg(F.max(F.struct("sum", (-F.col("at")).alias("back"))).alias("b"))
    return best.select("q_id", "length", F.expr("if(b.sum > 0, -b.back, NULL)").alias("start"), F.expr("greatest(b.sum, 0)").cast("long").alias("weight"))


def best_interval(points: DataFrame, length) -> DataFrame:
    spark = points.sparkSession
    kind = dict(points.dtypes)["pos"]
    return batched_interval(points, spark.sql(f"SELECT 0 AS q_id, CAST({length} AS {kind}) AS length"))


def blocked_interval(points: DataFrame, lengths: DataFrame, parts: int | None = None) -> DataFrame:
    """The same without an ordered window over a whole length: range blocks, each with its total and best prefix.

    The best of a length is the maximum of (sum of the blocks before + best prefix of the block).
    """
    from ..plans.staging import staged

    events = sweep_events(points, lengths)
    n = parts or int(points.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    blocks = staged(events.repartitionByRange(n, "q_id", "at", "kind").withColumn("block", F.spark_partition_id()), "interval-blocks")
    inside = Window.partitionBy("q_id", "length", "block").orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, 0)
    pairs = blocks.withColumn("sum", F.sum("dw").over(inside)).groupBy("q_id", "length", "block").agg(F.sum("dw").alias("total"), F.max("sum").alias("top"))
    before = Window.partitionBy("q_id", "length").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    return pairs.withColumn("best", F.col("top") + F.coalesce(F.sum("total").over(before), F.lit(0))).groupBy("q_id", "length").agg(F.greatest(F.max("best"), F.lit(0)).cast("long").alias("weight"))


def range_frame_interval(points: DataFrame, length: int) -> DataFrame:
    """The shortcut for weights of no sign: the interval starts at a point, so a RANGE frame sums it."""
    frame = Window.partitionBy(F.lit(0)).orderBy("pos").rangeBetween(0, length)
    return collapsed(points).select(F.sum("w").over(frame).alias("s")).agg(F.coalesce(F.max("s"), F.lit(0)).cast("long").alias("weight"))


def smallest_enclosing(points: DataFrame, ks: list[int]) -> DataFrame:
    """(k, lo, hi, length): the shortest interval with k points, for each k that the table has points for."""
    places = numbered(points.select("pos"), ["pos"], "rn")
    asked = points.sparkSession.createDataFrame([(int(k),) for k in ks], "k long")
    starts = places.crossJoin(F.broadcast(asked)).select("k", (F.col("rn") + F.col("k") - 1).alias("rn"), F.col("pos").alias("lo"))
    best = starts.join(places.withColumnRenamed("pos", "hi"), "rn").groupBy("k").agg(F.min(F.struct((F.col("hi") - F.col("lo")).alias("length"), "lo", "hi")).alias("b"))
    return best.select("k", "b.lo", "b.hi", "b.length")


def enclosing_all_k(points: DataFrame, most: int | None = None) -> DataFrame:
    """(k, length) for every k: quadratic steps by nature; a caller may name the ``most`` points it takes.

    Tasks hold the sorted positions (eight bytes each) and take every so manieth k, so that all have the same work;
    a k is one subtraction of the positions from themselves k - 1 places on, and no pair is ever a row.
    """
    n = points.count()
    if most is not None and n > most:
        raise ValueError(f"{n} points give {n * n // 2} intervals; name the k to ask for")
    kind = dict(points.dtypes)["pos"]
    line = points.agg(F.sort_array(F.collect_list("pos")).alias("line"))
    deals = max(1, min(n, 4 * int(points.sparkSession.conf.get("spark.sql.shuffle.partitions"))))

    def solve(batches):
        import numpy as np
        import pandas as pd

        for pdf in batches:
            for deal, at in zip(pdf["deal"], pdf["line"]):
                at = np.asarray(at)
                ks = np.arange(deal + 1, len(at) + 1, deals)
                yield pd.DataFrame({"k": ks, "length": [(at[k - 1 :] - at[: len(at) - k + 1]).min() for k in ks.tolist()]})

    dealt = points.sparkSession.range(0, deals, 1, deals).select(F.col("id").alias("deal"))
    return dealt.crossJoin(F.broadcast(line)).mapInPandas(solve, f"k long, length {kind}")


def interval_profile(points: DataFrame, parts: int | None = None) -> DataFrame:
    """Running weight over a line by blocked prefix sums."""
    return prefix_sums(collapsed(points), ["pos"], {"running": "w"}, parts)

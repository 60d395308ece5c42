"""Cost and accuracy measures of the methods."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.ball import BallPlan, sample_hits
from . import geometry as G


def ratio(approx: float, exact: float) -> float:
    return approx / exact if exact else 1.0


def success_rate(depths: list[float], exact: float, factor: float) -> float:
    """The share of runs that reach the factor."""
    return sum(ratio(d, exact) >= factor for d in depths) / len(depths) if depths else 1.0


def near_coverage(balls: DataFrame, p: BallPlan) -> DataFrame:
    """(id, n): in how many grids a point is near its cell's centre; every point is in one at least."""
    out = G.with_grids(balls, p.grids)
    off = [F.col(f"c{i}") - F.col(f"s{i}") - (F.floor((F.col(f"c{i}") - F.col(f"s{i}")) / p.side) + 0.5) * p.side for i in range(p.dim)]
    near = sum((o * o for o in off), F.lit(0.0)) <= p.eps**4 * (1 + 1e-9)
    return out.groupBy("id").agg(F.sum(near.cast("long")).alias("n"))


def touch_counts(balls: DataFrame, p: BallPlan) -> DataFrame:
    """(grids, most_cells, bound, cells): cells that a ball meets in a grid against (ceil(2/side) + 1)^dim, and all."""
    per = G.ball_cells(balls, p.grids, p.side, p.dim).groupBy("id", "g").agg(F.count("*").alias("n"))
    return per.agg(F.max("n").alias("most_cells"), F.sum("n").alias("cells")).select(F.lit(len(p.grids)).cast("long").alias("grids"), "most_cells", F.lit((math.ceil(2 / p.side) + 1) ** p.dim).cast("long").alias("bound"), "cells")


def method_stats(balls: DataFrame, p: BallPlan) -> DataFrame:
    """(g, cells, samples) by grid, and for all grids together (g = -1)."""
    cells = G.ball_cells(balls, p.grids, p.side, p.dim).select(*p.cell).distinct()
    return cells.rollup("g").agg(F.count("*").alias("cells"), (F.count("*") * p.samples).alias("samples")).withColumn("g", F.coalesce("g", F.lit(-1)))


def game_check(balls: DataFrame, p: BallPlan, weight: str = "w") -> DataFrame:
    """(g, by_samples, by_balls): the sum of sample depths equals the sum of a ball's weight times its samples."""
    hits = sample_hits(balls, p, ["id", weight])
    by_samples = hits.groupBy(*p.cell, "j").agg(F.sum(weight).alias("d")).groupBy("g").agg(F.sum("d").alias("by_samples"))
    by_balls = hits.groupBy("g", "id").agg((F.first(weight) * F.count("*")).alias("d")).groupBy("g").agg(F.sum("d").alias("by_balls"))
    return by_samples.join(by_balls, "g").select("g", F.col("by_samples").cast("long").alias("by_samples"), F.col("by_balls").cast("long").alias("by_balls"))


def cap_fraction_mc(spark, eps: float, dim: int, n: int = 200_000, seed: int = 1) -> DataFrame:
    """(measured, formula): the share of a sphere of radius eps inside a unit ball through the point eps^2 off its centre."""
    return _cap_share(spark.range(n).select(*(F.randn(seed + i).alias(f"u{i}") for i in range(dim))), eps, dim)


def cap_fraction_drawn(items: DataFrame, eps: float, dim: int) -> DataFrame:
    """The same with a direction for each row of ``items``, drawn from the hash of the row."""
    unit = lambda salt: (F.pmod(F.xxhash64(*items.columns, F.lit(salt)), F.lit(1 << 53)) + 0.5) / float(1 << 53)
    rows = items.select(*((F.sqrt(-2 * F.log(unit(2 * i))) * F.cos(2 * math.pi * unit(2 * i + 1))).alias(f"u{i}") for i in range(dim)))
    return _cap_share(rows, eps, dim)


def _cap_share(rows: DataFrame, eps: float, dim: int) -> DataFrame:
    norm = F.sqrt(sum((F.col(f"u{i}") ** 2 for i in range(dim)), F.lit(0.0)))
    # the ball's boundary passes through (eps^2, 0..), and the sphere's centre lies outside of it
    away = (eps * F.col("u0") / norm - (eps**2 + 1)) ** 2 + sum(((eps * F.col(f"u{i}") / norm) ** 2 for i in range(1, dim)), F.lit(0.0))
    return rows.select((away <= 1).cast("double").alias("inside")).agg(F.avg("inside").alias("measured")).withColumn("formula", F.lit(G.cap_fraction(eps, dim)))


def pair_crossings(crossings: DataFrame, disks: DataFrame) -> DataFrame:
    """(hue, other, crossings, disks): crossings of two colours' boundaries against the number of their disks."""
    low, high = F.least("hue", "other"), F.greatest("hue", "other")
    per = crossings.groupBy(low.alias("a"), high.alias("b")).agg(F.count("*").alias("crossings"))
    sizes = disks.groupBy("hue").agg(F.count("*").alias("n"))
    return per.join(sizes.select(F.col("hue").alias("a"), F.col("n").alias("na")), "a").join(sizes.select(F.col("hue").alias("b"), F.col("n").alias("nb")), "b").select("a", "b", "crossings", (F.col("na") + F.col("nb")).alias("disks"))


def threshold_check(points: DataFrame, kept: DataFrame, best: DataFrame, radius: float, lam: float, eps: float, optimum: int) -> DataFrame:
    """(level, best_kept, shallow_kept, splits): the optimum keeps more sampled colours than the level, shallow points fewer."""
    level = (1 - eps / 2) * optimum * lam
    at = G.depth_at(points.select(F.col("id").alias("q_id"), "x", "y"), points, radius, "color").where(F.col("depth") < (1 - eps) * optimum)
    shallow = G.depth_at(at.select("q_id", "x", "y"), kept, radius, "color").agg(F.coalesce(F.max("depth"), F.lit(0)).alias("shallow_kept"))
    top = G.depth_at(best.select(F.lit(0).cast("long").alias("q_id"), "x", "y"), kept, radius * (1 + 4e-7), "color").select(F.col("depth").alias("best_kept"))
    return top.crossJoin(shallow).withColumn("level", F.lit(float(level))).withColumn("splits", F.expr("best_kept > level AND shallow_kept < level"))


def task_volumes(df: DataFrame) -> DataFrame:
    """(stages, input_bytes, shuffle_written, shuffle_read, spilled, cpu_ms) of one run of ``df``, whose rows are thrown away.

    Read from the driver's record of the stages that this run adds; runs beside it in the same session count too.
    """
    sc = df.sparkSession.sparkContext
    held = sc._jsc.sc()

    def stages() -> dict:
        held.listenerBus().waitUntilEmpty()
        found = held.statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), sc._jvm.java.util.ArrayList())
        return {(s.stageId(), s.attemptId()): s for s in (found.apply(i) for i in range(found.size()))}

    before = stages().keys()
    df.write.format("noop").mode("overwrite").save()
    new = [s for k, s in stages().items() if k not in before]
    total = lambda *of: sum(getattr(s, f)() for s in new for f in of)
    row = (sum(s.status().toString() == "COMPLETE" for s in new), total("inputBytes"), total("shuffleWriteBytes"), total("shuffleReadBytes"), total("memoryBytesSpilled", "diskBytesSpilled"), total("executorCpuTime") // 1_000_000)
    return df.sparkSession.createDataFrame([row], "stages long, input_bytes long, shuffle_written long, shuffle_read long, spilled long, cpu_ms long")

"""Baselines that sample points, solve exactly, and score the place over all points."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import geometry as G
from .exact_disk import exact_disk


def _scored(kept: DataFrame, points: DataFrame, radius: float) -> DataFrame:
    base = kept if not kept.isEmpty() else points
    n = base.count()
    place = exact_disk(base, radius).select("x", "y", F.col("depth").alias("depth_kept")).withColumn("q_id", F.lit(0).cast("long"))
    return G.depth_at(place, points, radius * (1 + 4e-7)).select("x", "y", "depth_kept", "depth", F.lit(n).cast("long").alias("kept"))


def object_sample(points: DataFrame, radius: float, eps: float, guess: float, c1: float = 1.0, seed: int = 0) -> DataFrame:
    """Keep a point with probability growing with its weight (about log n / eps^2 in the best disk), weights divided by it."""
    n = max(2, points.count())
    lam = c1 * math.log(n) / (eps**2 * max(1.0, guess))
    draw = F.conv(F.substring(F.md5(F.concat_ws("|", F.col("id").cast("string"), F.lit(str(seed)))), 1, 8), 16, 10).cast("long")
    chance = F.least(F.lit(1.0), lam * F.col("w"))
    kept = points.withColumn("p", chance).where(draw < F.floor(F.col("p") * float(1 << 32))).withColumn("w", F.col("w") / F.col("p")).drop("p")
    return _scored(kept, points, radius)


def morton_key(x, y, scale: float, bits: int = 20):
    """Interleaved bits of the two scaled coordinates."""
    def spread(v):
        out = F.lit(0).cast("long")
        for b in range(bits):
            out = out.bitwiseOR(F.shiftleft(F.shiftright(v, b).bitwiseAND(F.lit(1).cast("long")), 2 * b))
        return out

    a, b = (F.floor(c / scale).cast("long") + (1 << (bits - 1)) for c in (x, y))
    return spread(a).bitwiseOR(F.shiftleft(spread(b), 1))


def morton_sample(points: DataFrame, radius: float, every: int) -> DataFrame:
    """Every q-th point along a space-filling curve, without chance: a stand-in for deterministic approximations."""
    from .ordering import numbered

    keyed = points.withColumn("z", morton_key(F.col("x"), F.col("y"), radius / 8))
    kept = numbered(keyed, ["z", "id"], "rn").where(f"rn % {every} = 0").withColumn("w", F.col("w") * every).drop("z", "rn")
    return _scored(kept, points, radius)

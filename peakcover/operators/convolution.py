"""Convolutions over (min, +) and (max, +), and the reductions that tie them to intervals and enclosing intervals.

Sequences are (i, v) with i = 0..n-1; results are (k, value).  Index pairs are made by an equi-join of k - i
with j against a broadcast side whose size is checked; the pairs themselves (n x m by nature) only exist as
rows between a join and its partial aggregate.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .interval import batched_interval

MOST_BROADCAST = 1_000_000


def _small(df: DataFrame) -> DataFrame:
    """``df`` with a broadcast hint if its counted rows allow it."""
    return F.broadcast(df) if df.count() <= MOST_BROADCAST else df


def convolve_at(a: DataFrame, b: DataFrame, ks: DataFrame, least: bool = True) -> DataFrame:
    """(k, value): the least (or greatest) a_i + b_(k-i) for every asked k."""
    left = a.select("i", F.col("v").alias("va")).crossJoin(F.broadcast(ks.select("k"))).where("i <= k").withColumn("j", F.col("k") - F.col("i"))
    met = left.join(_small(b.select(F.col("i").alias("j"), F.col("v").alias("vb"))), "j")
    total = F.col("va") + F.col("vb")
    return met.groupBy("k").agg((F.min(total) if least else F.max(total)).alias("value"))


def all_indices(a: DataFrame) -> DataFrame:
    return a.select(F.col("i").alias("k"))


def minplus(a: DataFrame, b: DataFrame) -> DataFrame:
    return convolve_at(a, b, all_indices(a), True)


def minplus_at(a: DataFrame, b: DataFrame, ks: DataFrame) -> DataFrame:
    return convolve_at(a, b, ks, True)


def maxplus_at(a: DataFrame, b: DataFrame, ks: DataFrame) -> DataFrame:
    return convolve_at(a, b, ks, False)


def maxplus_at_positive(a: DataFrame, b: DataFrame, ks: DataFrame) -> DataFrame:
    if not a.union(b).where("v < 0").isEmpty():
        raise ValueError("negative values; shift them first")
    return maxplus_at(a, b, ks)


def minplus_monotone(a: DataFrame, b: DataFrame) -> DataFrame:
    for s in (a, b):
        after = s.select((F.col("i") - 1).alias("i"), F.col("v").alias("next"))
        if not s.join(after, "i").where("next >= v").isEmpty():
            raise ValueError("the sequences must be strictly decreasing")
    return minplus(a, b)


def index_blocks(n: int, m: int) -> int:
    """Calls that an oracle for m indices needs for all n."""
    return -(-n // m)


def full_by_indexed(a: DataFrame, b: DataFrame, m: int, oracle=minplus_at) -> DataFrame:
    """All indices through an oracle for at most m of them: blocks of indices, one call each, united."""
    n = a.count()
    out = None
    for block in range(index_blocks(n, m)):
        part = oracle(a, b, all_indices(a).where(f"k div {m} = {block}"))
        out = part if out is None else out.union(part)
    return out


def min_by_max(a: DataFrame, b: DataFrame, ks: DataFrame, oracle=maxplus_at) -> DataFrame:
    """(min, +) through an oracle for (max, +): negate, ask, negate back."""
    negated = [s.select("i", (-F.col("v")).alias("v")) for s in (a, b)]
    return oracle(*negated, ks).select("k", (-F.col("value")).alias("value"))


def lowest(a: DataFrame, b: DataFrame) -> int:
    return a.union(b).agg(F.min("v")).first()[0] or 0


def max_by_positive(a: DataFrame, b: DataFrame, ks: DataFrame, oracle=maxplus_at_positive) -> DataFrame:
    """(max, +) through an oracle for values of no sign: lift both by the least value, take it off twice."""
    low = min(0, lowest(a, b))
    lifted = [s.select("i", (F.col("v") - low).alias("v")) for s in (a, b)]
    return oracle(*lifted, ks).select("k", (F.col("value") + 2 * low).alias("value"))


GUARDS = ("literal", "barrier", "lift")


def interval_instance(a: DataFrame, b: DataFrame, ks: DataFrame, guards: str = "barrier") -> tuple[DataFrame, DataFrame, int]:
    """(points, lengths, lift) of the batched interval problem that answers (max, +) at the asked indices.

    Positions are doubled, so the half steps of guards are integers.  With ``literal`` guards an interval may
    swallow one whole side and end on one element of a later index, which the other two forms rule out: a
    ``barrier`` makes the outermost guards cost more than everything together, a ``lift`` raises every value by
    more than the largest, so that two elements always beat one.
    """
    if guards not in GUARDS:
        raise ValueError(f"guards are {GUARDS}")
    n, top, total = a.union(b).agg(F.count("*"), F.max("v"), F.sum("v")).first()
    n //= 2
    lift = 1 + top if guards == "lift" else 0
    wall = 1 + total if guards == "barrier" else 0
    sides = []
    for s, at, guard in ((a, 2 * F.col("i"), 2 * F.col("i") - 1), (b, 2 * (2 * n - 1 - F.col("i")), 2 * (2 * n - 1 - F.col("i")) + 1)):
        value = F.col("v") + lift
        outer = F.when(F.col("i") == 0, F.lit(wall)).otherwise(F.lit(0))
        # an element's guard stands outside of it: the side of smaller positions for a, of larger ones for b
        sides.append(s.select(F.explode(F.array(F.struct(at.cast("long").alias("pos"), value.cast("long").alias("w")), F.struct(guard.cast("long").alias("pos"), (-value - outer).cast("long").alias("w")))).alias("p")).select("p.*"))
    lengths = ks.select(F.col("k").cast("int").alias("q_id"), (2 * (2 * n - 1 - F.col("k"))).cast("long").alias("length"))
    return sides[0].union(sides[1]), lengths, lift


def positive_by_intervals(a: DataFrame, b: DataFrame, ks: DataFrame, guards: str = "barrier", oracle=batched_interval) -> DataFrame:
    points, lengths, lift = interval_instance(a, b, ks, guards)
    return oracle(points, lengths).select(F.col("q_id").alias("k"), (F.col("weight") - 2 * lift).alias("value"))


def minplus_via_intervals(a: DataFrame, b: DataFrame, m: int, guards: str = "barrier") -> DataFrame:
    """The whole chain: index blocks, negation, lift to no sign, intervals."""
    positive = lambda x, y, ks: positive_by_intervals(x, y, ks, guards)
    greatest = lambda x, y, ks: max_by_positive(x, y, ks, positive)
    return full_by_indexed(a, b, m, lambda x, y, ks: min_by_max(x, y, ks, greatest))


def monotone_step(a: DataFrame, b: DataFrame) -> int:
    """1 + the largest forward step of both sequences (1 for single elements)."""
    steps = [s.join(s.select((F.col("i") - 1).alias("i"), F.col("v").alias("next")), "i").agg(F.max(F.col("next") - F.col("v"))).first()[0] for s in (a, b)]
    return 1 + max([0, *(x for x in steps if x is not None)])


def by_monotone(a: DataFrame, b: DataFrame, oracle=minplus_monotone) -> DataFrame:
    step = monotone_step(a, b)
    rise = lambda c: F.lit(step).cast("long") * F.col(c)  # noqa: E731  # in longs: a step below 2^31 times an int index may pass it
    falling = [s.select("i", (F.col("v") - rise("i")).alias("v")) for s in (a, b)]
    return oracle(*falling).select("k", (F.col("value") + rise("k")).alias("value"))


def enclosing_instance(a: DataFrame, b: DataFrame) -> tuple[DataFrame, int, int]:
    """(points, n, offset) whose smallest interval of 2n - k points gives the monotone convolution at k.

    Falling a goes to the left, rising towards zero from its last element; falling b to the right; the shortest
    interval with 2n - k points leaves out i elements on the left and k - i on the right.
    """
    n = a.count()
    last = [s.where(F.col("i") == n - 1).first()["v"] for s in (a, b)]
    left = a.select((-(F.col("v") - last[0])).cast("long").alias("pos"))
    right = b.select((F.col("v") - last[1] + 1).cast("long").alias("pos"))
    return left.union(right).withColumn("w", F.lit(1).cast("long")), n, last[0] + last[1] - 1


def monotone_by_enclosing(a: DataFrame, b: DataFrame) -> DataFrame:
    from .interval import smallest_enclosing

    points, n, offset = enclosing_instance(a, b)
    found = smallest_enclosing(points, [2 * n - k for k in range(n)])
    return found.select((2 * n - F.col("k")).cast("int").alias("k"), (F.col("length") + offset).alias("value"))


def minplus_via_enclosing(a: DataFrame, b: DataFrame) -> DataFrame:
    return by_monotone(a, b, monotone_by_enclosing)


def reduction_stats(n: int, m: int) -> dict[str, int]:
    return {"oracle_calls": index_blocks(n, m), "interval_points": 4 * n, "enclosing_points": 2 * n}

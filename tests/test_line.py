import random

import pytest
from pyspark.sql import functions as F

from peakcover.operators import convolution as C
from peakcover.operators import interval as I


def line(spark, rows):
    return spark.createDataFrame([(int(p), int(w)) for p, w in rows], "pos long, w long")


def best(rows, length):
    starts = {p + d for p, _ in rows for d in (0, 1, -length, -length - 1)}
    return max([0, *(sum(w for p, w in rows if s <= p <= s + length) for s in starts)])


@pytest.mark.parametrize("seed", range(3))
def test_intervals(spark, seed):
    rng = random.Random(seed)
    rows = [(rng.randrange(40), rng.randrange(-5, 6)) for _ in range(30)]
    lengths = spark.createDataFrame([(i, v) for i, v in enumerate((0, 3, 10, 100))], "q_id int, length long")
    want = {v: best(rows, v) for v in (0, 3, 10, 100)}
    assert {r["length"]: r["weight"] for r in I.batched_interval(line(spark, rows), lengths).collect()} == want
    assert {r["length"]: r["weight"] for r in I.blocked_interval(line(spark, rows), lengths, 5).collect()} == want
    plain = [(p, abs(w)) for p, w in rows]
    assert I.range_frame_interval(line(spark, plain), 10).first()["weight"] == best(plain, 10)


def test_only_negative_weights_cover_nothing(spark):
    r = I.best_interval(line(spark, [(1, -1), (5, -1)]), 3).first()
    assert r["weight"] == 0 and r["start"] is None


def test_enclosing(spark):
    rows = [(p, 1) for p in (1, 1, 4, 6, 7, 20)]
    at = sorted(p for p, _ in rows)
    want = {k: min(b - a for a, b in zip(at, at[k - 1 :])) for k in range(1, 7)}
    assert {r["k"]: r["length"] for r in I.smallest_enclosing(line(spark, rows), [1, 2, 3, 4, 5, 6, 7]).collect()} == want
    assert {r["k"]: r["length"] for r in I.enclosing_all_k(line(spark, rows)).collect()} == want
    with pytest.raises(ValueError):
        I.enclosing_all_k(line(spark, rows), most=5)


def test_every_k_of_a_long_line(spark):
    """More points than once were refused."""
    n = 20_500
    found = I.enclosing_all_k(spark.range(n).select((F.col("id") * F.col("id")).alias("pos"), F.lit(1).cast("long").alias("w")))
    assert found.count() == n
    assert {r["k"]: r["length"] for r in found.where("k IN (1, 2, 3, 20500)").collect()} == {1: 0, 2: 1, 3: 4, n: (n - 1) ** 2}


def seq(spark, values):
    return spark.createDataFrame(list(enumerate(values)), "i int, v long")


def conv(a, b, f):
    return {k: f(a[i] + b[k - i] for i in range(k + 1)) for k in range(len(a))}


def got(df):
    return {r["k"]: r["value"] for r in df.collect()}


@pytest.mark.parametrize("seed", range(2))
def test_convolutions_and_chains(spark, seed):
    rng = random.Random(seed)
    n = 6
    a, b = ([rng.randrange(-9, 10) for _ in range(n)] for _ in range(2))
    sa, sb = seq(spark, a), seq(spark, b)
    want = conv(a, b, min)
    assert got(C.minplus(sa, sb)) == want
    assert got(C.by_monotone(sa, sb)) == want
    assert got(C.minplus_via_enclosing(sa, sb)) == want
    for guards in ("barrier", "lift"):
        assert got(C.minplus_via_intervals(sa, sb, 4, guards)) == want


def test_monotone_steps_beyond_ints(spark):
    a, b = [0, 2_000_000_000, 5, -3, 8], [7, -1, 4, 2, 0]
    assert got(C.by_monotone(seq(spark, a), seq(spark, b))) == conv(a, b, min)
    assert got(C.minplus_via_enclosing(seq(spark, a), seq(spark, b))) == conv(a, b, min)


def test_literal_guards_can_swallow_a_side(spark):
    a, b = [0, 0], [0, 10]
    ks = C.all_indices(seq(spark, a))
    assert got(C.positive_by_intervals(seq(spark, a), seq(spark, b), ks, "literal")) == {0: 10, 1: 10}
    for guards in ("barrier", "lift"):
        assert got(C.positive_by_intervals(seq(spark, a), seq(spark, b), ks, guards)) == {0: 0, 1: 10}


def test_checks_of_inputs(spark):
    with pytest.raises(ValueError):
        C.maxplus_at_positive(seq(spark, [-1, 2]), seq(spark, [1, 2]), C.all_indices(seq(spark, [1, 2])))
    with pytest.raises(ValueError):
        C.minplus_monotone(seq(spark, [1, 2]), seq(spark, [3, 1]))
    assert got(C.by_monotone(seq(spark, [5]), seq(spark, [7]))) == {0: 12}
    assert C.index_blocks(25, 6) == 5

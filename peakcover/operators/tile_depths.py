"""The deepest sample of every tile over time: updates are sent to the few tiles they can reach, samples are no rows.

A tile owns the cells whose lower corner lies in it.  Its task takes the updates in order, keeps one depth a sample, and
emits the rounds between which its deepest sample stays as it is.  The pieces of all tiles are laid over each other
in chunks of rounds.  ``standing`` takes no round from another: a tile adds up the balls of each asked round anew.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import geometry as G

#: Side of a tile in radii, updates handled at once, rounds of a chunk; asked rounds that a task adds up.
SIDE, AT_ONCE, CHUNK = 2.0, 512, 1 << 14
ASKED = 128


def tile_samples(p, t0: int, t1: int, t: int, seed: int):
    """(low0, low1, q0, q1): lower corners of the tile's cells, and their samples' places by cell."""
    import numpy as np

    found = []
    for g, shift in p.grids:
        ks = []
        for i, at in enumerate((t0, t1)):
            k = np.arange(math.floor((at * SIDE - shift[i]) / p.side) - 1, math.floor(((at + 1) * SIDE - shift[i]) / p.side) + 2)
            ks.append(k[np.floor((shift[i] + k * p.side) / SIDE) == at])
        k0, k1 = (m.ravel() for m in np.meshgrid(*ks, indexing="ij"))
        found.append((np.full(len(k0), g), k0, k1, np.full(len(k0), shift[0]), np.full(len(k0), shift[1])))
    g, k0, k1, s0, s1 = (np.concatenate(c) for c in zip(*found))
    j = np.arange(t)
    if p.sampler == "equispaced":
        turn = np.broadcast_to(j / float(t), (len(g), t))
    else:
        m = G.MODULUS
        h = (seed * 48271 + g.astype(np.int64) + 1) % m
        for i, k in enumerate((k0, k1)):
            h = (h * h + 48271 * h + k + 1_000_003 * (i + 1)) % m
        h = (h * h + 69621 * h)[:, None] + j + 7
        h = h % m
        turn = ((h * h + 48271 * h + 11) % m * 69621 % m) / float(m)
    radius = p.side * math.sqrt(2) / 2
    q0 = (s0 + (k0 + 0.5) * p.side)[:, None] + radius * np.cos(2 * math.pi * turn)
    q1 = (s1 + (k1 + 0.5) * p.side)[:, None] + radius * np.sin(2 * math.pi * turn)
    return s0 + k0 * p.side, s1 + k1 * p.side, q0, q1


def to_tiles(balls: DataFrame, p) -> DataFrame:
    """Balls (c0, c1, ..) once for each tile (t0, t1) with a cell that they can meet."""
    for i in range(2):
        low, high = F.col(f"c{i}") - (1 + p.side + 1e-6), F.col(f"c{i}") + (1 + 1e-6)
        balls = balls.withColumn(f"t{i}", F.explode(F.sequence(F.floor(low / SIDE).cast("long"), F.floor(high / SIDE).cast("long"))))
    return balls


def held_samples(place, side: float, x, y):
    """(balls, cells, samples): which samples of the tile's cells are inside the balls at (x, y)."""
    import numpy as np

    low0, low1, q0, q1 = place
    x, y = x[:, None], y[:, None]
    gap = np.maximum(np.maximum(low0 - x, x - low0 - side), 0.0) ** 2 + np.maximum(np.maximum(low1 - y, y - low1 - side), 0.0) ** 2
    inside = (q0 - x[:, :, None]) ** 2 + (q1 - y[:, :, None]) ** 2 <= 1 + G.TOL
    inside &= (gap <= 1 + G.TOL)[:, :, None]
    return inside


def pieces(rows: DataFrame, radius: float, p, keys: list[str], t=None, seed=None) -> DataFrame:
    """(keys.., a, b, depth) of rows (keys.., round, x, y, dw): a tile's deepest sample from round a until before b (null: for good)."""
    kinds = dict(rows.dtypes)
    if p.dim != 2:
        raise ValueError("tiles are made in the plane")
    balls = G.to_dual(rows, radius, ["x", "y"])
    balls = balls.select(*keys, "round", "dw", "c0", "c1", (F.lit(p.samples) if t is None else t).cast("int").alias("t"), (F.lit(p.seed) if seed is None else seed).cast("long").alias("seed"))
    balls = to_tiles(balls, p)
    tile = [*keys, "t", "seed", "t0", "t1"]
    names = [*keys, "a", "b", "depth"]

    def run(batches):
        import numpy as np
        import pandas as pd

        key, now, place, held = None, None, None, (0, 0)

        def out(a, b, depth):
            some = (depth > 0) & (np.ones(len(a), bool) if b is None else a < b)
            a, depth = a[some], depth[some]
            b = pd.array([None] * len(a), dtype="Int64") if b is None else b[some]
            return pd.DataFrame({**{k: [key[i]] * len(a) for i, k in enumerate(keys)}, "a": a, "b": pd.array(b, dtype="Int64"), "depth": depth})[names]

        for pdf in batches:
            if not len(pdf):
                continue
            tiles = pdf[tile].to_numpy()
            cuts = np.flatnonzero(np.append(True, (tiles[1:] != tiles[:-1]).any(axis=1)))
            rounds, dw, c0, c1 = (pdf[c].to_numpy() for c in ("round", "dw", "c0", "c1"))
            found = []
            for at, end in zip(cuts, np.append(cuts[1:], len(pdf))):
                if key is None or tuple(tiles[at]) != key:
                    if key is not None:
                        found.append(out(np.array([held[0]]), None, np.array([held[1]])))
                    key = tuple(tiles[at])
                    place = tile_samples(p, int(key[-2]), int(key[-1]), int(key[-4]), int(key[-3]))
                    now, held = np.zeros(place[2].size, np.int64), (rounds[at], 0)
                for b in range(at, end, AT_ONCE):
                    e = min(end, b + AT_ONCE)
                    inside = held_samples(place, p.side, c0[b:e], c1[b:e])
                    depth = np.cumsum(inside.reshape(e - b, -1) * dw[b:e, None], axis=0) + now
                    now = depth[-1]
                    r, d = np.append(held[0], rounds[b:e]), np.append(held[1], depth.max(axis=1))
                    a, z, d0 = r[:-1], r[1:], d[:-1]
                    some = a < z
                    a, z, d0 = a[some], z[some], d0[some]
                    if len(a):  # neighbours of one depth as one
                        first = np.flatnonzero(np.append(True, d0[1:] != d0[:-1]))
                        found.append(out(a[first], z[np.append(first[1:], len(a)) - 1], d0[first]))
                    held = (r[-1], d[-1])
            if found:
                yield pd.concat(found)
        if key is not None:
            yield out(np.array([held[0]]), None, np.array([held[1]]))

    parts = 4 * int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = balls.repartition(parts, *tile).sortWithinPartitions(*tile, "round")
    return dealt.mapInPandas(run, ", ".join([*(f"{k} {kinds[k]}" for k in keys), "a long", "b long", "depth long"]))


def overlaid(spans: DataFrame, keys: list[str]) -> DataFrame:
    """(keys.., round, depth) of (keys.., a, b, depth): the deepest piece over every round that has one."""
    kinds = dict(spans.dtypes)
    cut = spans.withColumn("chunk", F.explode(F.sequence(F.expr(f"a div {CHUNK}"), F.expr(f"(b - 1) div {CHUNK}"))))
    cut = cut.select(*keys, "chunk", F.expr(f"cast(greatest(a - chunk * {CHUNK}, 0) as int)").alias("lo"), F.expr(f"cast(least(b - chunk * {CHUNK}, {CHUNK}) as int)").alias("hi"), "depth")
    cut = cut.groupBy(*keys, "chunk", "lo", "hi").agg(F.max("depth").alias("depth"))

    def run(pdf):
        import numpy as np
        import pandas as pd

        top = np.zeros(CHUNK, np.int64)
        pdf = pdf.sort_values("depth")  # what is deeper is laid on last
        for lo, hi, depth in zip(pdf["lo"].tolist(), pdf["hi"].tolist(), pdf["depth"].tolist()):
            top[lo:hi] = depth
        at = np.flatnonzero(top)
        return pd.DataFrame({**{k: [pdf[k].iloc[0]] * len(at) for k in keys}, "round": int(pdf["chunk"].iloc[0]) * CHUNK + at, "depth": top[at]})

    parts = int(spans.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return cut.repartition(parts, *keys, "chunk").groupBy(*keys, "chunk").applyInPandas(run, ", ".join([*(f"{k} {kinds[k]}" for k in keys), "round long", "depth long"]))


def standing(balls: DataFrame, rounds: list[int], radius: float, p) -> DataFrame:
    """(asked, depth): of every tile and asked round the deepest sample of balls (x, y, w, born, died), if it has a depth.

    A ball is sent once to a tile for each ``ASKED`` rounds that it stands in, and met with the samples there.  For every
    round the weights of its own standing balls are then added up at every sample, as one product of matrices.
    """
    import numpy as np

    if p.dim != 2:
        raise ValueError("tiles are made in the plane")
    rounds = sorted({int(r) for r in rounds})
    blocks = balls.sparkSession.createDataFrame([(at // ASKED, rounds[at], rounds[min(at + ASKED, len(rounds)) - 1]) for at in range(0, len(rounds), ASKED)], "block long, first long, last long")
    rows = balls.join(F.broadcast(blocks), (F.col("born") <= F.col("last")) & (F.col("died").isNull() | (F.col("died") > F.col("first"))))
    never = np.iinfo(np.int64).max
    rows = rows.select("block", "x", "y", F.col("w").cast("long").alias("dw"), F.col("born").cast("long").alias("born"), F.coalesce("died", F.lit(never)).cast("long").alias("died"))
    rows = to_tiles(G.to_dual(rows, radius, ["x", "y"]), p)
    tile = ["block", "t0", "t1"]

    def run(batches):
        import pandas as pd

        key, place, asked, depth = None, None, None, None

        def out():
            top = depth.max(axis=1)
            return pd.DataFrame({"asked": asked[top > 0], "depth": top[top > 0]})

        for pdf in batches:
            tiles = pdf[tile].to_numpy()
            cuts = np.flatnonzero(np.append(True, (tiles[1:] != tiles[:-1]).any(axis=1))) if len(pdf) else []
            dw, born, died, c0, c1 = (pdf[c].to_numpy() for c in ("dw", "born", "died", "c0", "c1"))
            for at, end in zip(cuts, np.append(cuts[1:], len(pdf))):
                if tuple(tiles[at]) != key:
                    if key is not None:
                        yield out()
                    key = tuple(tiles[at])
                    place = tile_samples(p, int(key[1]), int(key[2]), p.samples, p.seed)
                    asked = np.array(rounds[int(key[0]) * ASKED : (int(key[0]) + 1) * ASKED], np.int64)
                    depth = np.zeros((len(asked), place[2].size), np.int64)
                for b in range(at, end, AT_ONCE):
                    one = slice(b, min(int(end), b + AT_ONCE))
                    lo, hi = np.searchsorted(asked, [born[one].min(), died[one].max()])
                    if lo == hi:
                        continue
                    x, y, w = c0[one], c1[one], dw[one]
                    kind = np.float32 if np.abs(w).sum() < 1 << 24 else np.float64 if float(np.abs(w.astype(float)).sum()) < 1 << 53 else np.int64  # sums are exact
                    starts = np.flatnonzero(np.append(True, (np.diff(x) != 0) | (np.diff(y) != 0)))  # equal balls as one
                    stand = (born[one] <= asked[lo:hi, None]) & (died[one] > asked[lo:hi, None])
                    weights = np.add.reduceat(stand * w.astype(kind), starts, axis=1)
                    inside = held_samples(place, p.side, x[starts], y[starts]).reshape(len(starts), -1)
                    depth[lo:hi] += (weights @ inside.astype(kind)).astype(np.int64)
        if key is not None:
            yield out()

    parts = 4 * int(balls.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = rows.repartition(parts, *tile).sortWithinPartitions(*tile, "c0", "c1")
    return dealt.mapInPandas(run, "asked long, depth long")

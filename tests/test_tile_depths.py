import random

from peakcover.functions import measures
from peakcover.operators import ball, dynamic, tile_depths


def test_rounds_from_tiles_equal_recomputation(spark, monkeypatch):
    """Pieces over several chunks and batches; no row for a sample: a round gives a few pieces a tile at most."""
    monkeypatch.setattr(tile_depths, "CHUNK", 16)
    monkeypatch.setattr(tile_depths, "AT_ONCE", 5)
    rng, rows, live = random.Random(3), [], {}
    for r in range(1, 91):
        if live and rng.random() < 0.4:
            i = rng.choice(sorted(live))
            rows.append((r, "delete", i, *live.pop(i), -1))
        else:
            live[r] = (rng.uniform(-3, 3), rng.uniform(0, 2), rng.randrange(1, 4))
            rows.append((r, "insert", r, *live[r], 1))
    log = spark.createDataFrame(rows, "round long, op string, id long, x double, y double, w long, sign int")
    p = ball.plan(0.45, samples=4)
    want = {r["round"]: r["depth"] for r in dynamic.recompute(log, range(1, 91), 1.0, p).collect()}
    assert {r["round"]: r["depth"] for r in dynamic.round_best(log, 1.0, p).collect()} == want
    assert tile_depths.pieces(dynamic.changes_of(log), 1.0, p, []).count() <= 16 * len(rows)
    work = {r["epoch"]: r["touched"] for r in dynamic.epoch_stats(log, 1.0, p).collect()}
    every = dynamic.sample_changes(dynamic.with_epochs(log, dynamic.assign_epochs(log)), 1.0, p, ["epoch"])
    assert work == {r["epoch"]: r["count"] for r in every.groupBy("epoch").count().collect()}


def test_recomputation_sends_no_ball_for_every_round(spark, monkeypatch):
    """F2 dynamic_recompute: each round's standing balls added up anew, their rows shuffled by tiles and not by rounds."""
    rng = random.Random(7)
    balls = [(i, i + 1, rng.uniform(-3, 3), rng.uniform(0, 2), rng.randrange(1, 4), rng.randrange(300, 700) if i % 5 else None) for i in range(80)]
    balls += [(100 + i, b[1] + 100, b[2], b[3], 2, 650) for i, b in enumerate(balls[:20])]  # equal places
    steps = [(born, "insert", i, x, y, w, 1) for i, born, x, y, w, _ in balls] + [(died, "delete", i, x, y, w, -1) for i, _, x, y, w, died in balls if died]
    log = spark.createDataFrame(steps, "round long, op string, id long, x double, y double, w long, sign int")
    p = ball.plan(0.45, samples=4)
    asked = list(range(1, 701))
    assert measures.task_volumes(dynamic.recompute(log, asked, 1.0, p)).first()["shuffle_written"] < 400_000
    for size in (1, 9):
        monkeypatch.setattr(tile_depths, "ASKED", size)
        got = {r["round"]: r["depth"] for r in dynamic.recompute(log, asked[::50], 1.0, p).collect()}
        for r in asked[::100]:
            alive = [(0, b[2], b[3], b[4]) for b in balls if b[1] <= r and (b[5] is None or b[5] > r)]
            rows = spark.createDataFrame(alive, "round long, x double, y double, dw long")
            assert got[r] == (tile_depths.pieces(rows, 1.0, p, []).groupBy().max("depth").first()[0] or 0)
    assert dynamic.recompute(log, [], 1.0, p).count() == 0

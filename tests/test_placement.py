import itertools
import math
import random

import numpy as np
import pytest

from peakcover.functions import geometry as G
from peakcover.functions import measures
from peakcover.operators import ball, cell_kernels, colored_disk, dynamic, exact_disk, range_kernels, rectangle, union_arcs
from peakcover.operators.ordering import numbered, prefix_sums
from peakcover.sources import views as V


def points(spark, rows):
    return spark.createDataFrame([(i, float(x), float(y), w, c) for i, (x, y, w, c) in enumerate(rows)], "id long, x double, y double, w long, color string")


def brute(rows, r, coloured=False):
    at = [(x, y) for x, y, _, _ in rows]
    for (a, b), (c, d) in itertools.combinations(set(at), 2):
        dd = math.hypot(a - c, b - d)
        if 0 < dd <= 2 * r:
            h = math.sqrt(max(0, r * r - dd * dd / 4)) / dd
            at += [((a + c) / 2 - s * h * (d - b), (b + d) / 2 + s * h * (c - a)) for s in (1, -1)]
    best = 0
    for px, py in at:
        near = [p for p in rows if (p[0] - px) ** 2 + (p[1] - py) ** 2 <= r * r * (1 + 1e-8)]
        best = max(best, len({p[3] for p in near}) if coloured else sum(p[2] for p in near))
    return best


def cloud(seed, n=30, colours=4, lattice=False):
    rng = random.Random(seed)
    return [((rng.randrange(6) if lattice else rng.uniform(0, 5)), (rng.randrange(6) if lattice else rng.uniform(0, 5)), rng.randrange(1, 4), f"c{rng.randrange(colours)}") for _ in range(n)]


FIXTURES = {
    "one point": ([(0, 0, 1, "a")], 1, 1, 1),
    "coincident": ([(1, 1, 1, c) for c in "aabba"], 1, 5, 2),
    "tangent pair": ([(0, 0, 1, "a"), (2, 0, 1, "b")], 1, 2, 2),
    "just apart": ([(0, 0, 1, "a"), (2.001, 0, 1, "b")], 1, 1, 1),
    "triangle": ([(0, 0, 1, "a"), (1, 0, 1, "b"), (0.5, math.sqrt(3) / 2, 1, "c")], 1 / math.sqrt(3), 3, 3),
    "ring": ([(0.9 * math.cos(k * math.pi / 6), 0.9 * math.sin(k * math.pi / 6), 1, f"c{k}") for k in range(12)], 1, 12, 12),
}


@pytest.mark.parametrize("name", FIXTURES)
def test_literal_disks(spark, name):
    rows, r, count, colours = FIXTURES[name]
    p = points(spark, rows)
    assert exact_disk.exact_disk(p, r).first()["depth"] == count
    assert union_arcs.coloured_by_circles(p, r).first()["depth"] == colours
    assert union_arcs.coloured_arc_sweep(p, r).first()["depth"] == colours


@pytest.mark.parametrize("seed,lattice", [(0, False), (1, True), (2, True)])
def test_disk_engines_agree(spark, seed, lattice):
    rows = cloud(seed, lattice=lattice)
    p = points(spark, rows)
    assert exact_disk.exact_disk(p, 1.0).first()["depth"] == brute(rows, 1.0)
    best = brute(rows, 1.0, True)
    assert union_arcs.coloured_arc_sweep(p, 1.0).first()["depth"] == best
    assert union_arcs.coloured_by_crossings(p, 1.0).first()["depth"] == best
    assert colored_disk.output_sensitive(p, 1.0).first()["depth"] == best


@pytest.mark.parametrize("seed", range(12))
def test_cell_kernels_agree(seed):
    rows = cloud(seed, 16, 4, seed % 2 == 1)
    rows = list({(x, y, c): (x, y, w, c) for x, y, w, c in rows}.values())
    x, y = np.array([r[0] for r in rows], float), np.array([r[1] for r in rows], float)
    hue = np.unique([r[3] for r in rows], return_inverse=True)[1]
    best = brute(rows, 1.0, True)
    assert {k: f(x, y, hue)[0] for k, f in cell_kernels.KERNELS.items()} == dict.fromkeys(cell_kernels.KERNELS, best)


@pytest.mark.parametrize("seed", range(6))
def test_trapezoid_depths_are_visited_and_right(seed):
    rows = cloud(seed, 14, 4)
    x, y = np.array([r[0] for r in rows]), np.array([r[1] for r in rows])
    hue = np.unique([r[3] for r in rows], return_inverse=True)[1]
    cells, links, met = cell_kernels.trapezoids(x, y, hue)
    depth = cell_kernels.propagate(len(cells), links)
    assert None not in depth  # every cell is reached
    px, py = np.array([c[0] for c in cells[1:]]), np.array([c[1] for c in cells[1:]])
    assert depth[1:] == cell_kernels.depth_of(px, py, x, y, hue).tolist()
    assert all(depth[b] - depth[a] == d for a, b, d in links)  # on every way round
    # in general position an end or a crossing opens few cells: the map's size follows arcs and crossings
    arcs = cell_kernels.exposed(x, y, hue)
    assert len(cells) <= 3 * (len(cell_kernels.pieces_of(x, y, arcs)[0]) + len(met[0])) + 1


def best_rectangle(rows, a, b):
    best = colours = 0
    for x0, y0 in itertools.product({r[0] for r in rows}, {r[1] for r in rows}):
        inside = [r for r in rows if x0 <= r[0] <= x0 + a and y0 <= r[1] <= y0 + b]
        best, colours = max(best, sum(r[2] for r in inside)), max(colours, len({r[3] for r in inside}))
    return best, colours


@pytest.mark.parametrize("a,b,most", [(2.0, 1.0, 200_000), (0.0, 0.0, 200_000), (9.0, 9.0, 200_000), (9.0, 4.0, 6), (2.0, 3.0, 3)])
def test_rectangles(spark, a, b, most):
    rows = cloud(5, 25, 4, True)
    p = points(spark, rows + rows[:3])  # repeated rows add weight and no colour
    best, colours = best_rectangle(rows + rows[:3], a, b)
    found = rectangle.exact_rectangle(p, a, b, most).first()
    assert found["weight"] == best == rectangle.rectangle_by_frames(p, a, b).first()["weight"]
    assert best == sum(r[2] for r in rows + rows[:3] if found["x0"] <= r[0] <= found["x0"] + a and found["y0"] <= r[1] <= found["y0"] + b)
    found = rectangle.coloured_rectangle(p, a, b, most=most).first()
    assert found["colors"] == colours == rectangle.coloured_by_islands(p, a, b).first()["colors"]
    assert colours == len({r[3] for r in rows if found["x0"] <= r[0] <= found["x0"] + a and found["y0"] <= r[1] <= found["y0"] + b})


@pytest.mark.parametrize("seed", range(40))
def test_many_cells_at_once(seed):
    rng = random.Random(seed)
    a, b = rng.choice([(1.0, 1.0), (0.3, 0.7), (1.0, 0.1)])
    cells, at, best, colours = [], [], 0, 0
    for cell in range(rng.randint(1, 4)):  # each cell is of the sides' size, and is met from it and from beyond
        rows = [(rng.choice([rng.random() * 2 * a, rng.randint(0, 8) * a / 4]), rng.choice([rng.random() * 2 * b, rng.randint(0, 8) * b / 4]), rng.randint(0, 5), rng.randint(0, 4)) for _ in range(rng.randint(1, 30))]
        at += [(cell, *r) for r in rows]
        xs, ys = {r[0] for r in rows if r[0] < a * 0.999}, {r[1] for r in rows if r[1] < b * 0.999}
        for x0, y0 in itertools.product(xs, ys):
            inside = [r for r in rows if x0 <= r[0] <= x0 + a and y0 <= r[1] <= y0 + b]
            best, colours = max(best, sum(r[2] for r in inside)), max(colours, len({r[3] for r in inside}))
    cell, x, y, w, hue = (np.array(v) for v in zip(*at))
    for value, want, coloured in ((w, best, False), (hue, colours, True)):
        found = range_kernels.solve_cells(cell, x, y, x < a * 0.999, y < b * 0.999, value, a, b, coloured)
        assert (found[0] if found else 0) == want


@pytest.mark.parametrize("dim", [2, 3, 4])
def test_boxes(spark, dim):
    rng = random.Random(dim)
    rows = [[rng.randint(0, 6) / 2 for _ in range(dim)] for _ in range(14)]
    sides = tuple(1.0 + 0.5 * (i % 2) for i in range(dim))
    p = spark.createDataFrame([(i, r, i % 3) for i, r in enumerate(rows)], "id long, pos array<double>, w long")
    best = 0
    for low in itertools.product(*({r[i] for r in rows} for i in range(dim))):
        best = max(best, sum(k % 3 for k, r in enumerate(rows) if all(l <= v <= l + s for l, v, s in zip(low, r, sides))))
    assert rectangle.exact_box(p, sides).first()["weight"] == best
    assert rectangle.exact_box(p.limit(0), sides).first()["weight"] == 0
    assert rectangle.exact_box(p, (99.0,) * dim, most=3).first()["weight"] == sum(k % 3 for k in range(14))  # one cell, known without the kernel
    apart = spark.createDataFrame([(i, [v] * dim, 1) for i, v in enumerate((0.8, 0.9, 1.1, 1.2))], "id long, pos array<double>, w long")
    assert rectangle.exact_box(apart, (1.0,) * dim).first()["weight"] == 4  # no cell holds more than two of them
    with pytest.raises(Exception, match="a cell holds"):
        rectangle.exact_box(apart, (1.0,) * dim, most=3).collect()


def test_task_volumes(spark):
    one = measures.task_volumes(spark.range(1000, numPartitions=2)).first()
    assert (one["stages"], one["shuffle_written"], one["shuffle_read"], one["spilled"]) == (1, 0, 0, 0)
    few, many = (measures.task_volumes(spark.range(n).repartition(4)).first() for n in (1000, 50_000))
    assert few["stages"] >= 2 and few["shuffle_written"] == few["shuffle_read"] > 0
    assert many["shuffle_written"] > 10 * few["shuffle_written"]


def test_empty_inputs(spark):
    p = points(spark, []).limit(0)
    assert exact_disk.exact_disk(p, 1.0).count() == 0
    assert rectangle.exact_rectangle(p, 1.0, 1.0).count() == 0
    assert ball.static_ball(p, 1.0).count() == 0
    assert union_arcs.coloured_arc_sweep(p, 1.0).count() == 0


@pytest.mark.parametrize("eps", [0.25, 0.4])
def test_sampled_ball_keeps_its_factor(spark, data, eps):
    p = V.part_pts(spark, data)
    plan = ball.plan(eps, samples=16)
    best = exact_disk.exact_disk(p, 40).first()["depth"]
    found = ball.static_ball(p, 40, eps, samples=16).first()
    assert plan.factor * best <= found["recorded"] <= found["depth"] <= best
    assert ball.static_ball(p, 40, eps, samples=16, prune=True).first()["recorded"] == found["recorded"]


def test_sampled_ball_does_not_depend_on_partitions(spark, data):
    p = V.part_pts(spark, data)
    rows = {tuple(ball.static_ball(p.repartition(n), 40, 0.4, samples=8, sampler="uniform", seed=4).first()) for n in (1, 8, 31)}
    assert len(rows) == 1


def test_random_samples_mostly_keep_the_factor(spark, data):
    p = V.part_pts(spark, data)
    best = exact_disk.exact_disk(p, 40).first()["depth"]
    depths = [ball.static_ball(p, 40, 0.4, samples=24, sampler="uniform", seed=s).first()["depth"] for s in range(4)]
    assert measures.success_rate(depths, best, G.cap_fraction(0.4, 2) * 0.9) >= 0.95


def test_grids_and_caps():
    assert len(G.shifted_grids(1.0, 0.25, 2, "paper")) == 36 and len(G.shifted_grids(1.0, 0.25, 2)) == 9
    assert [round(G.cap_fraction(e, 2), 3) for e in (0.1, 0.25, 0.4)] == [0.452, 0.383, 0.317]
    assert [round(G.cap_fraction(0.25, d), 2) for d in (3, 5)] == [0.32, 0.24]
    assert abs(G.cap_fraction(G.grid_eps(0.3, 2), 2) - 0.3) < 1e-6
    side, delta = 2 * 0.4 / math.sqrt(2), 0.16
    rng = random.Random(0)
    for _ in range(300):
        x, y = rng.uniform(-3, 3), rng.uniform(-3, 3)
        off = [math.hypot(*((c - s) % side - side / 2 for c, s in zip((x, y), shift))) for _, shift in G.shifted_grids(side, delta, 2)]
        assert min(off) <= delta * (1 + 1e-9)


def test_cap_fraction_by_chance(spark):
    for dim in (2, 3):
        r = measures.cap_fraction_mc(spark, 0.25, dim, 40_000).first()
        assert r["measured"] >= r["formula"] - 0.02


def test_negative_weights_and_nan_are_refused(spark):
    with pytest.raises(ValueError):
        G.check_points(points(spark, [(0, 0, -1, "a")]), ["x", "y"])
    with pytest.raises(ValueError):
        G.check_points(points(spark, [(math.nan, 0, 1, "a")]), ["x", "y"])
    with pytest.raises(ValueError):
        ball.plan(0.5)


def log_of(spark, steps):
    rows, at = [], {}
    for r, (op, i) in enumerate(steps, 1):
        at.setdefault(i, (float(i % 3), float(i // 3)))
        rows.append((r, op, i, *at[i], 1, 1 if op == "insert" else -1))
    return spark.createDataFrame(rows, "round long, op string, id long, x double, y double, w long, sign int")


def test_dynamic_replay_matches_recomputation(spark):
    rng = random.Random(3)
    steps, live = [], []
    for i in range(40):
        if live and rng.random() < 0.4:
            steps.append(("delete", live.pop(rng.randrange(len(live)))))
        steps.append(("insert", i))
        live.append(i)
    steps += [("delete", i) for i in live]
    log = log_of(spark, steps)
    p = ball.plan(0.4, samples=8)
    best = {r["round"]: r["depth"] for r in dynamic.round_best(log, 1.2, p).collect()}
    again = {r["round"]: r["depth"] for r in dynamic.recompute(log, list(range(1, len(steps) + 1)), 1.2, p).collect()}
    assert best == again and best[len(steps)] == 0
    by_epoch = {r["round"]: r["depth"] for r in dynamic.replay(log, 1.2, p).collect()}
    assert by_epoch == again
    epochs = sorted(tuple(r) for r in dynamic.assign_epochs(log).collect())
    size, sizes = 0, {}
    for r, (op, _) in enumerate(steps, 1):
        size += 1 if op == "insert" else -1
        sizes[r] = size
    for (_, start, base), after in zip(epochs, [*(e[1] for e in epochs[1:]), len(steps) + 1]):
        assert all(base / 2 <= sizes[r] <= 2 * base for r in range(start + 1, after))


def test_dyadic_blocks_cover_each_round_once(spark):
    rows = [(a, b) for a in range(1, 12) for b in range(a + 1, 14)]
    cut = dynamic.dyadic(spark.createDataFrame(rows, "a long, b long"), 5).collect()
    held = {}
    for r in cut:
        held.setdefault((r["a"], r["b"]), []).extend(range(r["block"] << r["level"], r["block"] + 1 << r["level"]))
    assert all(sorted(held[k]) == list(range(*k)) for k in rows)


def test_global_order_without_one_partition(spark):
    df = spark.createDataFrame([(int(v), 1) for v in np.random.default_rng(0).permutation(500)], "v long, w long")
    assert [r["rn"] for r in numbered(df, ["v"]).orderBy("v").collect()] == list(range(1, 501))
    assert prefix_sums(df, ["v"], {"s": "v"}).agg({"s": "max"}).first()[0] == sum(range(500))


def test_colour_sampling_branches(spark, data):
    p = V.event_pts(spark, data)
    best = colored_disk.output_sensitive(p, 120).first()["depth"]
    exact = colored_disk.sampled(p, 120, 0.5, branch="exact").first()
    assert exact["depth"] == best == exact["depth_kept"]
    drawn = colored_disk.sampled(p, 120, 0.5, 1.0, branch="sample").first()
    assert best * 0.5 <= drawn["depth"] <= best and drawn["depth_kept"] <= drawn["depth"]


def test_plans_have_no_cartesian_product(spark, data):
    p = V.part_pts(spark, data)
    for df in (exact_disk.exact_disk(p, 40), union_arcs.coloured_arc_sweep(p, 40), rectangle.exact_rectangle(p, 40, 40)):
        text = df._jdf.queryExecution().toString()
        assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text
    scan = ball.sample_depth(G.to_dual(p, 40, ["x", "y"]), ball.plan(0.4, samples=16))._jdf.queryExecution().toString()
    assert "p_name" not in scan.split("== Physical Plan ==")[1]


def test_sql_names(spark):
    from peakcover.functions.sql_names import register

    register(spark)
    assert spark.sql("SELECT peak_cell(2.5D, 0D, 1D) AS c, peak_near(0D, 0D, 3D, 4D, 5D) AS n, round(peak_cap(0.25D), 3) AS f").first()[:] == (2, True, 0.383)
    cells = {tuple(r) for r in spark.sql("SELECT * FROM peak_ball_cells(0.3D, 0.6D, 0D, 0D, 0.5D)").collect()}
    ball_row = spark.createDataFrame([(0, 0.3, 0.6, 1)], "id long, c0 double, c1 double, w long")
    assert cells == {(r["k0"], r["k1"]) for r in G.ball_cells(ball_row, [(0, (0.0, 0.0))], 0.5, 2).collect()}


def test_points_from_files(spark, data, tmp_path):
    p = V.part_pts(spark, data).select("id", "x", "y", "w", "color")
    V.write_answers(p, str(tmp_path / "p"), "color")
    p.write.option("header", True).csv(str(tmp_path / "c"))
    p.write.json(str(tmp_path / "j"))
    best = exact_disk.exact_disk(p, 40).first()["depth"]
    for form, where in (("parquet", "p"), ("csv", "c"), ("json", "j")):
        schema = "id long, x long, y long, w long, color string"
        assert exact_disk.exact_disk(V.read_points(spark, str(tmp_path / where), form, schema), 40).first()["depth"] == best


def test_round_queries_give_every_round(spark):
    from peakcover.plans import workloads
    from peakcover.sources import views

    d = "/root/testdata/sf0.001"
    total = 2 * spark.read.parquet(f"{d}/events.parquet").count()
    got = {r["round"]: r["depth"] for r in workloads.dynamic_round_all(spark, d).collect()}
    assert sorted(got) == list(range(1, total + 1))
    some = list(range(1, total + 1, 37))
    again = dynamic.recompute(views.update_log(spark, d), some, workloads.EVENT_RADIUS, workloads.event_plan)
    assert {r["round"]: r["depth"] for r in again.collect()} == {r: got[r] for r in some}
    assert {r["round"]: r["depth"] for r in workloads.asof_all(spark, d).collect()} == {r: got[r] for r in range(777, total, 777)}


def test_depth_at_meets_equal_points_once_and_broadcasts_nothing(spark):
    rows = [(x, 0, 2, c) for x in (0, 1, 5) for c in "aab"]
    p = points(spark, rows)
    for kind, near, far in (("weight", 12, 6), ("count", 6, 3), ("color", 2, 2)):
        found = G.depth_at(p.select(p.id.alias("q_id"), "x", "y"), p, 1.0, kind)
        got = {r["q_id"]: r["depth"] for r in found.collect()}
        assert got == {i: far if x == 5 else near for i, (x, *_) in enumerate(rows)}
        assert "Broadcast" not in found._jdf.queryExecution().executedPlan().toString()


def test_branch_and_bound_finds_what_brute_force_finds(monkeypatch):
    from peakcover.operators import branch, range_kernels

    rng = np.random.default_rng(3)
    for t in range(60):
        dim, n = int(rng.integers(2, 5)), int(rng.integers(1, 40))
        at = rng.integers(0, 8, (n, dim)) / 2 if t % 2 else rng.random((n, dim)) * 3
        own, w, sides = np.ones((n, dim), bool), rng.integers(0, 4, n), [1.0 + 0.5 * (i % 2) for i in range(dim)]
        monkeypatch.setattr(branch, "TRIED", (1, 50, 1000, 1 << 18)[t % 4])
        assert branch.best_box(at, own, w, sides) == range_kernels.best_box(at, own, w, sides)
        at, w, own = at[:8], w[:8], rng.random((min(n, 8), dim)) < 0.7
        every, held = [0], [0]  # over all places, and over those where each lower edge is a coordinate of a row inside
        for low in itertools.product(*(np.unique(at[own[:, i], i]) for i in range(dim))):
            inside = ((at >= low) & (at <= np.add(low, sides))).all(1)
            every.append(w[inside].sum())
            held += [every[-1]] if all((inside & own[:, i] & (at[:, i] == v)).any() for i, v in enumerate(low)) else []
        assert max(held) <= branch.best_box(at, own, w, sides) <= max(every)
    for t in range(60):
        n, radius = int(rng.integers(1, 16)), 1.0 if t % 4 < 2 else 0.75
        p = rng.integers(0, 4, (n, 3)).astype(float) if t % 2 else rng.random((n, 3)) * 2.5
        w = rng.integers(1, 4, n)
        monkeypatch.setattr(branch, "FEW", (0, 3, 12)[t % 3])
        places = np.concatenate([p, branch._crossings(p, radius)])
        assert branch.best_ball(p, w, radius, [1.5] * 3, 4.0) == ((((places[:, None] - p) ** 2).sum(2) <= radius * radius * branch.TOUCH) @ w).max()


def test_balls_in_space_beyond_the_old_bound(spark):
    rng = np.random.default_rng(8)
    p = rng.normal(size=(5200, 3)) * 0.3
    rows = spark.createDataFrame([(i, r) for i, r in enumerate(p.tolist())], "id long, pos array<double>")
    at_points = max(int((((p - c) ** 2).sum(1) <= 0.04).sum()) for c in p)
    assert exact_disk.exact_ball3(rows, 0.2).first()["depth"] >= at_points
    assert exact_disk.exact_ball3(rows.limit(0), 0.2).first()["depth"] == 0
    with pytest.raises(ValueError):
        exact_disk.exact_ball3(rows, 0.2, most=5000)


def test_coloured_branches_find_what_the_sweep_finds(spark):
    from peakcover.operators import branch

    rng = np.random.default_rng(5)
    for t in range(40):
        n = int(rng.integers(1, 60))
        x, y = (rng.integers(0, 9, n) / 2 if t % 2 else rng.random(n) * 4 for _ in range(2))
        hue = rng.integers(0, 12, n)
        got = branch.most_colours(x, y, hue, (2.0, 2.0), 4.0)
        assert got[0] == cell_kernels.sweep_kernel(x, y, hue)[0]
        assert len(set(hue[(x - got[1]) ** 2 + (y - got[2]) ** 2 <= 1 + 1e-8])) == got[0]
        assert branch.most_colours(x, y, hue, (2.0, 2.0), 4.0, got[0])[0] == got[0]
    rows = [(i, float(a), float(b), int(h)) for i, (a, b, h) in enumerate(zip(rng.random(200) * 9, rng.random(200) * 9, rng.integers(0, 30, 200)))]
    p = spark.createDataFrame(rows, "id long, x double, y double, color long")
    assert colored_disk.output_sensitive(p, 1.5, engine="branch").first()["depth"] == cell_kernels.sweep_kernel(*(np.array(v) for v in zip(*((a / 1.5, b / 1.5, h) for _, a, b, h in rows))))[0]
    assert colored_disk.output_sensitive(p.limit(0), 1.5, engine="branch").collect() == []

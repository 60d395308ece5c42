import random

import numpy as np
import pytest

from peakcover.operators import branch, exact_disk, tiled, union_arcs

from .test_placement import brute, points

#: The finding's query and the operator it goes by.
FORMS = {
    "F9 colored_circles": (union_arcs.coloured_by_circles, True),
    "F7 colored_arc_sweep": (union_arcs.coloured_arc_sweep, True),
    "F8 colored_arc_sweep_kinds": (lambda p, r: union_arcs.coloured_arc_sweep(p, r, "color"), True),
    "F10 colored_crossings": (union_arcs.coloured_by_crossings, True),
    "F24 exact_disk_candidates": (exact_disk.disk_by_candidates, False),
}


@pytest.mark.parametrize("name", FORMS)
def test_near_pairs_are_no_rows(spark, monkeypatch, name):
    """A dense tile, dealt into shares: right, and no window or join holds the pairs of near disks."""
    monkeypatch.setattr(tiled, "SHARE", 7)
    form, coloured = FORMS[name]
    rng = random.Random(5)
    rows = [(rng.uniform(0, 4), rng.uniform(0, 3), rng.randrange(1, 4), f"c{rng.randrange(9)}") for _ in range(45)] + [(1.0, 1.0, 2, "c0"), (1.0, 1.0, 1, "c8")]
    found = form(points(spark, rows), 1.0)
    assert found.first()["depth"] == brute(rows, 1.0, coloured)
    plan = found._jdf.queryExecution().toString()
    assert "Window" not in plan and "x2" not in plan


NODES = {"F1 colored_crossings": (union_arcs.coloured_by_crossings, union_arcs.crossed_arcs), "F3 colored_customers": (union_arcs.coloured_arc_sweep, union_arcs.swept_arcs)}


@pytest.mark.parametrize("name", NODES)
def test_dense_places_are_searched_in_nodes(spark, monkeypatch, name):
    """Same-coloured crowds: no task searches all near pairs, and small nodes, lattices and touching disks lose nothing."""
    form, leaf = NODES[name]
    rng, seen = random.Random(4), []
    for trial in range(24):
        snap = (lambda v: round(2 * v) / 2) if trial % 2 else (lambda v: v)
        rows = [(snap(rng.uniform(-2, 2)), snap(rng.uniform(-2, 2)), 1, f"c{rng.randrange(1 + trial % 9)}") for _ in range(rng.randrange(1, 40))]
        x, y, hue = (np.array(v) for v in zip(*sorted({(a, b, int(c[1:])) for a, b, _, c in rows})))
        for few in (1, 6, 64):
            monkeypatch.setattr(branch, "LEAF", few)
            depth, px, py = branch.most_colours(x, y, hue, (0.0, 0.0), 4.0, leaf=leaf)
            assert depth == brute(rows, 1.0, True)
            assert len(set(hue[(x - px) ** 2 + (y - py) ** 2 <= 1 + 1e-6])) >= depth
    monkeypatch.setattr(branch, "LEAF", 64)
    # 6,000 disks of three colours around two places: few of them are left in any node that is searched
    g = np.random.default_rng(2)
    x, y, hue = np.append(g.normal(0, 0.3, 5000), g.normal(1.2, 0.3, 1000)), g.normal(0, 0.3, 6000), np.append(np.arange(5000) % 2, np.full(1000, 2))

    def counted(*node):
        seen.append(len(node[0]))
        return leaf(*node)

    assert branch.most_colours(x, y, hue, (0.5, 0.5), 4.0, leaf=counted)[0] == 3 and max(seen, default=0) <= 64

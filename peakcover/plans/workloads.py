"""The workloads over the given tables: a query for each method, and brute-force SQL with the same rows."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import geometry as G
from ..operators import ball, convolution, exact_disk, interval, rectangle
from ..sources import views as V

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}
RADIUS = 40
S = V.SQL


def query(sql: str | None = None):
    """Register a query under its function's name, with its SQL."""

    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLE_SQL[f.__name__] = sql
        return f

    return add


def named(name: str, f, sql: str | None = None) -> None:
    QUERIES[name] = f
    if sql:
        ORACLE_SQL[name] = sql


# -- intervals -------------------------------------------------------------------------------------------------

LENGTHS_SQL = "(VALUES " + ", ".join(f"({i}, {v})" for i, v in enumerate(V.LENGTHS)) + ") AS t(q_id, length)"


def interval_sql(points: str, lengths: str = LENGTHS_SQL) -> str:
    """Every start at a position, or ending at one, summed directly."""
    return f"""WITH p AS (SELECT pos, sum(w) AS w FROM ({points}) GROUP BY pos), l AS (SELECT * FROM {lengths}),
    s AS (SELECT DISTINCT q_id, length, a FROM (SELECT q_id, length, pos AS a FROM p, l UNION ALL SELECT q_id, length, pos - length FROM p, l UNION ALL SELECT q_id, length, pos + 1 FROM p, l UNION ALL SELECT q_id, length, pos - length - 1 FROM p, l)),
    d AS (SELECT q_id, length, a, coalesce((SELECT sum(w) FROM p WHERE pos BETWEEN a AND a + length), 0) AS v FROM s)
    SELECT CAST(q_id AS INTEGER) AS q_id, CAST(length AS BIGINT) AS length, CAST(greatest(max(v), 0) AS BIGINT) AS weight FROM d GROUP BY q_id, length"""


@query(interval_sql(S["order_days"]))
def interval_batched(spark, d):
    return interval.batched_interval(V.order_days(spark, d), V.length_table(spark)).select("q_id", "length", "weight")


@query(interval_sql(S["order_days"]))
def interval_blocked(spark, d):
    return interval.blocked_interval(V.order_days(spark, d), V.length_table(spark))


@query(interval_sql(S["order_days"], "(VALUES (0, 30)) AS t(q_id, length)"))
def interval_best(spark, d):
    return interval.best_interval(V.order_days(spark, d), 30).select("q_id", "length", "weight")


@query(f"SELECT weight FROM ({interval_sql(S['order_days'], '(VALUES (0, 90)) AS t(q_id, length)')})")
def interval_range_frame(spark, d):
    return interval.range_frame_interval(V.order_days(spark, d), 90)


SIGNED_LENGTHS = (0, 100, 500, 2000)


@query(interval_sql(S["doc_signed"], "(VALUES " + ", ".join(f"({i}, {v})" for i, v in enumerate(SIGNED_LENGTHS)) + ") AS t(q_id, length)"))
def interval_signed(spark, d):
    return interval.batched_interval(V.doc_signed(spark, d), V.length_table(spark, SIGNED_LENGTHS)).select("q_id", "length", "weight")


def enclosing_sql(points: str, ks) -> str:
    asked = ", ".join(f"({k})" for k in ks)
    return f"WITH p AS (SELECT pos, row_number() OVER (ORDER BY pos) AS rn FROM ({points})), k AS (SELECT * FROM (VALUES {asked}) AS t(k)) SELECT CAST(k AS BIGINT) AS k, CAST(min(b.pos - a.pos) AS BIGINT) AS length FROM k, p AS a JOIN p AS b ON b.rn = a.rn + k - 1 GROUP BY k"


ENCLOSING_KS = (1, 2, 5, 10, 50, 100, 150)


@query(enclosing_sql(S["doc_len"], ENCLOSING_KS))
def enclosing_k(spark, d):
    return interval.smallest_enclosing(V.doc_len(spark, d), list(ENCLOSING_KS)).select("k", "length")


@query(enclosing_sql(S["event_ticks"], (2, 10, 100, 1000)))
def enclosing_events(spark, d):
    return interval.smallest_enclosing(V.event_ticks(spark, d), [2, 10, 100, 1000]).select("k", "length")


@query(f"WITH p AS (SELECT pos, row_number() OVER (ORDER BY pos) AS rn FROM ({S['doc_len']})) SELECT CAST(b.rn - a.rn + 1 AS BIGINT) AS k, CAST(min(b.pos - a.pos) AS BIGINT) AS length FROM p AS a JOIN p AS b ON b.rn >= a.rn GROUP BY 1")
def enclosing_all_k(spark, d):
    return interval.enclosing_all_k(V.doc_len(spark, d))


# -- convolutions and reductions -------------------------------------------------------------------------------


def sequences(spark, d, centred=False):
    return V.sequence_of(spark, d, "customer", centred), V.sequence_of(spark, d, "supplier", centred)


def conv_sql(best: str, where: str = "TRUE", suffix: str = "") -> str:
    return f"SELECT CAST(a.i + b.i AS INTEGER) AS k, CAST({best}(a.v + b.v) AS BIGINT) AS value FROM ({S['seq_a' + suffix]}) AS a, ({S['seq_b' + suffix]}) AS b WHERE a.i + b.i < 25 AND ({where.replace('k', '(a.i + b.i)')}) GROUP BY 1"


def some_indices(a):
    return convolution.all_indices(a).where("k % 4 = 1")


@query(conv_sql("min"))
def conv_min(spark, d):
    return convolution.minplus(*sequences(spark, d))


@query(conv_sql("min", "k % 4 = 1", "_c"))
def conv_min_indexed(spark, d):
    a, b = sequences(spark, d, True)
    return convolution.minplus_at(a, b, some_indices(a))


@query(conv_sql("max", "k % 4 = 1", "_c"))
def conv_max_indexed(spark, d):
    a, b = sequences(spark, d, True)
    return convolution.maxplus_at(a, b, some_indices(a))


@query(conv_sql("max", "k % 4 = 1"))
def conv_max_positive(spark, d):
    a, b = sequences(spark, d)
    return convolution.maxplus_at_positive(a, b, some_indices(a))


@query(conv_sql("min", suffix="_c"))
def conv_blocks(spark, d):
    a, b = sequences(spark, d, True)
    return convolution.full_by_indexed(a, b, 6)


@query(conv_sql("min", suffix="_c"))
def conv_monotone(spark, d):
    return convolution.by_monotone(*sequences(spark, d, True))


@query(conv_sql("min", suffix="_c"))
def chain_intervals_barrier(spark, d):
    return convolution.minplus_via_intervals(*sequences(spark, d, True), 10, "barrier")


@query(conv_sql("min", suffix="_c"))
def chain_intervals_lift(spark, d):
    return convolution.minplus_via_intervals(*sequences(spark, d, True), 10, "lift")


@query(conv_sql("min", suffix="_c"))
def chain_enclosing(spark, d):
    return convolution.minplus_via_enclosing(*sequences(spark, d, True))


@query(f"WITH a AS ({S['seq_a']}), b AS ({S['seq_b']}), c AS ({conv_sql('max')}) SELECT CAST(k AS INTEGER) AS k, CAST(greatest(value, coalesce((SELECT max(v) FROM a WHERE i > k), 0), coalesce((SELECT max(v) FROM b WHERE i > k), 0)) AS BIGINT) AS value FROM c")
def chain_intervals_literal(spark, d):
    """What the literal guards give: the convolution, or one later element alone if that is more."""
    a, b = sequences(spark, d)
    return convolution.positive_by_intervals(a, b, convolution.all_indices(a), "literal")


def long_conv_sql(n: int) -> str:
    seq = lambda status: f"SELECT CAST(r AS INTEGER) AS i, CAST(coalesce(s, 0) AS BIGINT) AS v FROM range({n}) AS t(r) LEFT JOIN (SELECT least({n - 1}, date_diff('day', DATE '{V.FIRST_ORDER_DAY}', CAST(o_orderdate AS DATE)) * {n} // 2405) AS i, sum(CAST(round(100 * o_totalprice) AS BIGINT)) AS s FROM orders WHERE o_orderstatus = '{status}' GROUP BY 1) ON i = r"
    return f"SELECT CAST(a.i + b.i AS INTEGER) AS k, CAST(min(a.v + b.v) AS BIGINT) AS value FROM ({seq('O')}) AS a, ({seq('F')}) AS b WHERE a.i + b.i < {n} GROUP BY 1"


@query(long_conv_sql(256))
def conv_min_long(spark, d):
    return convolution.minplus(V.long_sequence(spark, d, "O", 256), V.long_sequence(spark, d, "F", 256))


# -- exact disks and rectangles --------------------------------------------------------------------------------


def disk_sql(points: str, radius: float, what: str = "sum(p.w)") -> str:
    """All points and all crossings of two boundaries, each with what its closed disk covers."""
    return f"""WITH p AS MATERIALIZED ({points}), u AS (SELECT DISTINCT x, y FROM p),
    n AS (SELECT a.x, a.y, b.x AS x2, b.y AS y2, sqrt(CAST((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) AS DOUBLE)) AS dd FROM u AS a JOIN u AS b ON b.x BETWEEN a.x - {2 * radius} AND a.x + {2 * radius} AND b.y BETWEEN a.y - {2 * radius} AND a.y + {2 * radius} AND (a.x < b.x OR (a.x = b.x AND a.y < b.y))),
    h AS (SELECT *, sqrt(greatest(0.0, {radius * radius} - dd * dd / 4)) / dd AS k FROM n WHERE dd <= {2 * radius}),
    c AS (SELECT CAST(x AS DOUBLE) AS x, CAST(y AS DOUBLE) AS y FROM u UNION ALL SELECT (x + x2) / 2.0 - s * k * (y2 - y), (y + y2) / 2.0 + s * k * (x2 - x) FROM h, (VALUES (1.0), (-1.0)) AS t(s)),
    e AS (SELECT DISTINCT x, y FROM c),
    d AS (SELECT e.x, e.y, {what} AS v FROM e JOIN p ON p.x BETWEEN e.x - {radius + 1} AND e.x + {radius + 1} AND p.y BETWEEN e.y - {radius + 1} AND e.y + {radius + 1} AND (p.x - e.x) * (p.x - e.x) + (p.y - e.y) * (p.y - e.y) <= {radius * radius} * (1 + 2e-9) GROUP BY e.x, e.y)
    SELECT CAST(max(v) AS BIGINT) AS depth FROM d"""


@query(disk_sql(S["part_pts"], RADIUS))
def exact_disk_unit(spark, d):
    return exact_disk.exact_disk(V.part_pts(spark, d), RADIUS).select("depth")


@query(disk_sql(S["part_pts"], RADIUS))
def exact_disk_candidates(spark, d):
    return exact_disk.disk_by_candidates(V.part_pts(spark, d), RADIUS).select("depth")


@query(disk_sql(S["cust_pts"], 300))
def exact_disk_weighted(spark, d):
    return exact_disk.exact_disk(V.cust_pts(spark, d), 300).select("depth")


@query(disk_sql(S["part_pts"], RADIUS, "count(DISTINCT p.color)"))
def exact_disk_colored(spark, d):
    return exact_disk.disk_by_candidates(V.part_pts(spark, d), RADIUS, "color").select("depth")


@query(" UNION ALL ".join(f"SELECT CAST({q} AS INTEGER) AS q_id, depth FROM ({disk_sql(S['part_pts'], r)})" for q, r in ((1, 20), (2, 40))))
def batched_disk(spark, d):
    return exact_disk.batched_disk(V.part_pts(spark, d), {1: 20, 2: 40})


def rectangle_sql(points: str, a: float, b: float, what: str = "sum(p.w)", name: str = "weight") -> str:
    return f"WITH p AS MATERIALIZED ({points}), e AS (SELECT DISTINCT l.x, o.y FROM p AS l JOIN p AS o ON o.x BETWEEN l.x AND l.x + {a} AND o.y BETWEEN l.y - {b} AND l.y) SELECT CAST(max(v) AS BIGINT) AS {name} FROM (SELECT e.x, e.y, {what} AS v FROM e JOIN p ON p.x BETWEEN e.x AND e.x + {a} AND p.y BETWEEN e.y AND e.y + {b} GROUP BY e.x, e.y)"


@query(rectangle_sql(S["part_pts"], 40, 40))
def exact_rectangle(spark, d):
    return rectangle.exact_rectangle(V.part_pts(spark, d), 40, 40).select("weight")


@query(rectangle_sql(S["part_pts"], 40, 40))
def rectangle_candidates(spark, d):
    return rectangle.rectangle_by_candidates(V.part_pts(spark, d), 40, 40)


@query(rectangle_sql(S["part_pts"], 40, 40))
def rectangle_frames(spark, d):
    return rectangle.rectangle_by_frames(V.part_pts(spark, d), 40, 40).select("weight")


@query(rectangle_sql(S["part_pts"], 40, 40))
def rectangle_split_cells(spark, d):
    """Cells split from 20 points on, as very dense ones are."""
    return rectangle.exact_rectangle(V.part_pts(spark, d), 40, 40, most=20).select("weight")


@query(rectangle_sql(S["part_pts"], 40, 40, "count(DISTINCT p.color)", "colors"))
def rectangle_islands(spark, d):
    return rectangle.coloured_by_islands(V.part_pts(spark, d), 40, 40).select("colors")


@query(rectangle_sql(S["part_pts"], 40, 40, "count(DISTINCT p.color)", "colors"))
def rectangle_colored(spark, d):
    return rectangle.coloured_rectangle(V.part_pts(spark, d), 40, 40).select("colors")


@query(rectangle_sql(S["event_pts"], 120, 120, "count(DISTINCT p.color)", "colors"))
def rectangle_trajectories(spark, d):
    return rectangle.coloured_rectangle(V.event_pts(spark, d), 120, 120).select("colors")


@query(" UNION ALL ".join(f"SELECT CAST({q} AS INTEGER) AS q_id, weight FROM ({rectangle_sql(S['part_pts'], a, b)})" for q, a, b in V.RECTANGLES))
def batched_rectangle(spark, d):
    return rectangle.batched_rectangle(V.part_pts(spark, d), V.RECTANGLES)


BOX = 0.2
EMB3 = "SELECT vec_id AS id, CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y, CAST(embedding[3] AS DOUBLE) AS z FROM embeddings"


@query(f"WITH p AS MATERIALIZED ({EMB3}), e AS (SELECT a.x, b.y, c.z FROM p AS a JOIN p AS b ON b.x BETWEEN a.x AND a.x + {BOX}::DOUBLE AND b.y BETWEEN a.y - {BOX}::DOUBLE AND a.y JOIN p AS c ON c.x BETWEEN a.x AND a.x + {BOX}::DOUBLE AND c.y BETWEEN b.y AND b.y + {BOX}::DOUBLE AND c.z BETWEEN greatest(a.z, b.z) - {BOX}::DOUBLE AND least(a.z, b.z)) SELECT CAST(max(v) AS BIGINT) AS weight FROM (SELECT e.x, e.y, e.z, count(*) AS v FROM (SELECT DISTINCT * FROM e) AS e JOIN p ON p.x BETWEEN e.x AND e.x + {BOX}::DOUBLE AND p.y BETWEEN e.y AND e.y + {BOX}::DOUBLE AND p.z BETWEEN e.z AND e.z + {BOX}::DOUBLE GROUP BY 1, 2, 3)")
def exact_box3(spark, d):
    return rectangle.exact_box(V.emb_pts(spark, d, 3), (BOX, BOX, BOX))


BOX4 = 0.1
EMB4 = "SELECT CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y, CAST(embedding[3] AS DOUBLE) AS z, CAST(embedding[4] AS DOUBLE) AS u FROM embeddings"


def reach4(low: str, axis: str, at: str) -> str:
    return f"{at}.{axis} BETWEEN {low} AND {low} + {BOX4}::DOUBLE"


@query(f"""WITH p AS MATERIALIZED ({EMB4}),
    e2 AS (SELECT a.x AS x, b.y AS y, a.z AS az, b.z AS bz, a.u AS au, b.u AS bu FROM p AS a JOIN p AS b ON {reach4("a.x", "x", "b")} AND {reach4("b.y", "y", "a")}),
    e3 AS (SELECT e.x, e.y, c.z, e.au, e.bu, c.u AS cu FROM e2 AS e JOIN p AS c ON {reach4("e.x", "x", "c")} AND {reach4("e.y", "y", "c")} AND e.az BETWEEN c.z AND c.z + {BOX4}::DOUBLE AND e.bz BETWEEN c.z AND c.z + {BOX4}::DOUBLE),
    e4 AS (SELECT DISTINCT e.x, e.y, e.z, o.u FROM e3 AS e JOIN p AS o ON {reach4("e.x", "x", "o")} AND {reach4("e.y", "y", "o")} AND {reach4("e.z", "z", "o")} AND e.au BETWEEN o.u AND o.u + {BOX4}::DOUBLE AND e.bu BETWEEN o.u AND o.u + {BOX4}::DOUBLE AND e.cu BETWEEN o.u AND o.u + {BOX4}::DOUBLE)
    SELECT CAST(max(v) AS BIGINT) AS weight FROM (SELECT count(*) AS v FROM e4 AS e JOIN p ON {reach4("e.x", "x", "p")} AND {reach4("e.y", "y", "p")} AND {reach4("e.z", "z", "p")} AND {reach4("e.u", "u", "p")} GROUP BY e.x, e.y, e.z, e.u)""")
def exact_box4(spark, d):
    return rectangle.exact_box(V.emb_pts(spark, d, 4), (BOX4,) * 4)


@query()
def rectangle_volumes(spark, d):
    """Shuffle, spill and CPU of the sweep and of the frames; volumes are measured, so no SQL states them."""
    pts = V.part_pts(spark, d)
    rows = [measures.task_volumes(f(pts, 40, 40)).select(F.lit(f.__name__).alias("method"), "*") for f in (rectangle.exact_rectangle, rectangle.rectangle_by_frames)]
    return rows[0].union(rows[1])


@query()
def exact_ball3(spark, d):
    return exact_disk.exact_ball3(V.emb_pts(spark, d, 3), 0.1)


def draws_sql(dim: int, seed: str, salt: int = 0) -> str:
    """The portable draw of a sample, in SQL: columns h0.. named on the way."""
    return ", ".join(draw_steps(dim, seed)) + f", {draw_sql(salt)}"


def draw_steps(dim: int, seed: str) -> list[str]:
    m = G.MODULUS
    mod = lambda e: f"((({e}) % {m}) + {m}) % {m}"
    steps = [f"{mod(f'CAST({seed} AS BIGINT) * 48271 + g + 1')} AS h0"]
    steps += [f"{mod(f'h{i} * h{i} + 48271 * h{i} + k{i} + {1_000_003 * (i + 1)}')} AS h{i + 1}" for i in range(dim)]
    return [*steps, f"{mod(f'h{dim} * h{dim} + 69621 * h{dim} + j + 7')} AS hh"]


def draw_sql(salt: int = 0) -> str:
    return f"((((hh * hh + 48271 * hh + {11 + salt}) % {G.MODULUS}) * 69621) % {G.MODULUS}) / {float(G.MODULUS)!r}::DOUBLE"


def space_sql(balls: str, dim: int, eps: float, t: int, mode: str, own: bool, what: str = "sum(w)", seeds: str = "0", factor: str = "TRUE") -> str:
    """CTEs up to ``best``: samples of balls (w, color, c0..) in any dimension, drawn on spheres, by seed if there are several."""
    side = 2 * eps / dim**0.5
    axes, d = range(dim), f"{side!r}::DOUBLE"
    grids = ", ".join("(" + ", ".join([str(g), *(f"{x!r}::DOUBLE" for x in v)]) + ")" for g, v in G.shifted_grids(side, eps**2, dim, mode))
    names = ", ".join(["g", *(f"s{i}" for i in axes)])
    cell = ", ".join(["g", *(f"k{i}" for i in axes)])
    near = " + ".join(f"pow(q{i} - c{i}, 2)" for i in axes)
    steps = [f"b AS MATERIALIZED ({balls})", f"r AS (SELECT b.*, h.* FROM b, (VALUES {grids}) AS h({names}))"]
    if own:
        steps.append(f"m AS (SELECT DISTINCT {names}, " + ", ".join(f"CAST(floor((c{i} - s{i}) / {d}) AS BIGINT) AS k{i}" for i in axes) + " FROM r)")
    else:
        last = "r"
        for i in axes:
            steps.append(f"e{i} AS (SELECT *, unnest(range(CAST(floor((c{i} - s{i} - 1) / {d}) AS BIGINT), CAST(floor((c{i} - s{i} + 1) / {d}) AS BIGINT) + 1)) AS k{i} FROM {last})")
            last = f"e{i}"
        gap = " + ".join(f"pow(greatest(s{i} + k{i} * {d} - c{i}, 0.0, c{i} - s{i} - (k{i} + 1) * {d}), 2)" for i in axes)
        steps.append(f"m AS (SELECT DISTINCT {cell}, " + ", ".join(f"s{i}" for i in axes) + f" FROM {last} WHERE {gap} <= 1 + 1e-9)")
    if dim == 1:
        ways, drawn_at = ["CASE WHEN j = 0 THEN -1.0 ELSE 1.0 END"], "j"
    elif dim == 2:
        ways, drawn_at = ["cos(2 * pi() * u)", "sin(2 * pi() * u)"], draw_sql() + " AS u"
    else:
        normals = ", ".join(f"sqrt(-2 * ln({draw_sql(2 * i + 1)} + 1e-12)) * cos(2 * pi() * {draw_sql(2 * i + 2)}) AS u{i}" for i in axes)
        norm = "sqrt(" + " + ".join(f"u{i} * u{i}" for i in axes) + ")"
        ways, drawn_at = [f"u{i} / {norm}" for i in axes], normals
    count = 2 if dim == 1 else t
    steps.append(f"j AS (SELECT *, unnest(range({count})) AS j FROM m, (SELECT unnest([{seeds}]) AS seed))")
    last = "j"
    if dim > 1:  # a step at a time, as an alias used in its own list is written out anew
        *chain, final = draw_steps(dim, "seed")
        for k, step in enumerate([*chain, final]):
            steps.append(f"a{k} AS MATERIALIZED (SELECT *, {step} FROM {last})")
            last = f"a{k}"
    steps.append(f"a AS (SELECT *, {drawn_at} FROM {last})" if dim > 1 else "a AS (SELECT * FROM j)")
    steps.append(f"q AS MATERIALIZED (SELECT seed, {cell}, j, {', '.join(f's{i}' for i in axes)}, " + ", ".join(f"s{i} + (k{i} + 0.5) * {d} + {side * dim**0.5 / 2!r}::DOUBLE * {w} AS q{i}" for i, w in enumerate(ways)) + " FROM a)")
    # a ball counts where it meets the cell, though its samples lie a little outside; cells of points count all balls
    meets = "" if own else " AND " + " + ".join(f"pow(greatest(s{i} + k{i} * {d} - c{i}, 0.0, c{i} - s{i} - (k{i} + 1) * {d}), 2)" for i in axes) + " <= 1 + 1e-9"
    # the first coordinates meet by unit cells, so that no join is on inequalities alone
    reach = lambda c, z, back: f"unnest(range(CAST(floor({c}) AS BIGINT) - {back}, CAST(floor({c}) AS BIGINT) + {back + 1})) AS {z}"
    steps.append(f"y AS (SELECT *, {reach('c0', 'z0', 1)} FROM b)")
    steps.append(f"f AS (SELECT seed, {cell}, j, " + ", ".join(f"any_value(q{i}) AS q{i}" for i in axes) + f", CAST({what} AS BIGINT) AS recorded FROM q JOIN y ON z0 = CAST(floor(q0) AS BIGINT) WHERE {near} <= 1 + 1e-9{meets} GROUP BY seed, {cell}, j)")
    steps.append(f"best AS (SELECT * FROM f QUALIFY row_number() OVER (PARTITION BY seed ORDER BY recorded DESC, {cell}, j) = 1)")
    return ", ".join(steps)


def bounds_sql(dim: int, what: str) -> str:
    """The most around a ball's centre within 1 and within 2."""
    near = " + ".join(f"pow(x.c{i} - b.c{i}, 2)" for i in range(dim))
    one = lambda reach: f"(SELECT max(n) FROM (SELECT {what} AS n FROM (SELECT DISTINCT {', '.join(f'c{i}' for i in range(dim))} FROM b) AS x JOIN b ON {near} <= {reach * reach} * (1 + 1e-9) GROUP BY {', '.join(f'x.c{i}' for i in range(dim))}))"
    return f"CAST({one(1)} AS BIGINT) AS centred, CAST({one(2)} AS BIGINT) AS bound"


def space_query(balls: str, dim: int, eps: float, t: int, mode: str, own: bool, what: str = "sum(w)") -> str:
    near = " + ".join(f"pow(q{i} - c{i}, 2)" for i in range(dim))
    return f"WITH {space_sql(balls, dim, eps, t, mode, own, what)} SELECT recorded, CAST((SELECT {what} FROM b WHERE {near} <= 1 + 1e-9) AS BIGINT) AS depth, {bounds_sql(dim, what)} FROM best"


# -- deepest-sample balls --------------------------------------------------------------------------------------


def sampled_sql(points: str, radius: float, eps: float, t: int, what: str = "sum(w)", dedup: str = "") -> str:
    """Every ball x cell x even sample, rebuilt from the formulas."""
    side = 2 * eps / 2**0.5
    grids = ", ".join(f"({g}, {s[0]!r}::DOUBLE, {s[1]!r}::DOUBLE)" for g, s in G.shifted_grids(side, eps**2, 2))
    gap = lambda c, s, k: f"pow(greatest({s} + {k} * {side!r}::DOUBLE - {c}, 0.0, {c} - {s} - ({k} + 1) * {side!r}::DOUBLE), 2)"
    return f"""WITH b AS (SELECT *, CAST(x AS DOUBLE) / {radius} AS c0, CAST(y AS DOUBLE) / {radius} AS c1 FROM ({points})),
    r AS (SELECT * FROM b, (VALUES {grids}) AS t(g, s0, s1)),
    k AS (SELECT *, unnest(range(CAST(floor((c0 - s0 - 1) / {side!r}::DOUBLE) AS BIGINT), CAST(floor((c0 - s0 + 1) / {side!r}::DOUBLE) AS BIGINT) + 1)) AS k0 FROM r),
    l AS (SELECT *, unnest(range(CAST(floor((c1 - s1 - 1) / {side!r}::DOUBLE) AS BIGINT), CAST(floor((c1 - s1 + 1) / {side!r}::DOUBLE) AS BIGINT) + 1)) AS k1 FROM k),
    m AS (SELECT * FROM l WHERE {gap('c0', 's0', 'k0')} + {gap('c1', 's1', 'k1')} <= 1 + 1e-9),
    q AS (SELECT *, unnest(range({t})) AS j FROM m),
    h AS (SELECT * FROM q WHERE pow(s0 + (k0 + 0.5) * {side!r}::DOUBLE + {eps!r}::DOUBLE * cos(2 * pi() * j / {t}.0) - c0, 2) + pow(s1 + (k1 + 0.5) * {side!r}::DOUBLE + {eps!r}::DOUBLE * sin(2 * pi() * j / {t}.0) - c1, 2) <= 1 + 1e-9)
    SELECT CAST(g AS INTEGER) AS g, k0, k1, CAST(j AS BIGINT) AS j, CAST({what} AS BIGINT) AS depth FROM h GROUP BY g, k0, k1, j"""


def best_per_grid(depths):
    return depths.groupBy("g").agg(F.max("depth").cast("long").alias("recorded"), F.count("*").alias("samples_hit"))


def best_per_grid_sql(depths: str) -> str:
    return f"SELECT g, max(depth) AS recorded, count(*) AS samples_hit FROM ({depths}) GROUP BY g"


EPS, SAMPLES = 0.4, 16


def dual(spark, d, source=V.part_pts, radius=RADIUS):
    return G.to_dual(source(spark, d), radius, ["x", "y"])


PART_SAMPLES = sampled_sql(S["part_pts"], RADIUS, EPS, SAMPLES)


@query(f"SELECT max(depth) AS recorded FROM ({PART_SAMPLES})")
def ball_static_even(spark, d):
    return ball.static_ball(V.part_pts(spark, d), RADIUS, EPS, samples=SAMPLES).select(F.col("recorded").cast("long").alias("recorded"))


@query(best_per_grid_sql(PART_SAMPLES))
def ball_static_grids(spark, d):
    return best_per_grid(ball.sample_depth(dual(spark, d), ball.plan(EPS, samples=SAMPLES)))


@query(best_per_grid_sql(sampled_sql(S["cust_pts"], 300, EPS, SAMPLES)))
def ball_static_even_weighted(spark, d):
    return best_per_grid(ball.sample_depth(dual(spark, d, V.cust_pts, 300), ball.plan(EPS, samples=SAMPLES)))


@query(f"SELECT max(depth) AS recorded FROM ({PART_SAMPLES})")
def ball_pruned_same_answer(spark, d):
    return ball.static_ball(V.part_pts(spark, d), RADIUS, EPS, samples=SAMPLES, prune=True).select(F.col("recorded").cast("long").alias("recorded"))


@query(f"SELECT g, k0, k1, max(depth) AS recorded FROM ({PART_SAMPLES}) GROUP BY g, k0, k1 ORDER BY recorded DESC, g, k0, k1 LIMIT 10")
def ball_topk_cells(spark, d):
    p = ball.plan(EPS, samples=SAMPLES)
    return ball.deepest(ball.sample_depth(dual(spark, d), p), p, 10).select("g", "k0", "k1", F.col("recorded").cast("long").alias("recorded"))


PART_COLOURS = sampled_sql(S["part_pts"], RADIUS, EPS, SAMPLES, "count(DISTINCT color)")


@query(best_per_grid_sql(PART_COLOURS))
def ball_colored_even(spark, d):
    return best_per_grid(ball.colour_depth(dual(spark, d), ball.plan(EPS, samples=SAMPLES)))


@query(best_per_grid_sql(PART_COLOURS))
def ball_colored_bitmask(spark, d):
    return best_per_grid(ball.colour_depth_by_bits(dual(spark, d), ball.plan(EPS, samples=SAMPLES)))


@query(best_per_grid_sql(PART_COLOURS))
def ball_colored_ordered(spark, d):
    return best_per_grid(ball.colour_depth_by_order(dual(spark, d), ball.plan(EPS, samples=SAMPLES)))


@query(f"SELECT p.id AS q_id, count(*) AS depth FROM ({S['part_pts']}) AS p JOIN ({S['part_pts']}) AS o ON (p.x - o.x) * (p.x - o.x) + (p.y - o.y) * (p.y - o.y) <= {RADIUS * RADIUS} GROUP BY 1")
def depth_at_points(spark, d):
    points = V.part_pts(spark, d)
    return G.depth_at(points.select(F.col("id").alias("q_id"), "x", "y"), points, RADIUS).select("q_id", "depth")


# -- coloured disks --------------------------------------------------------------------------------------------

from ..operators import colored_disk, union_arcs  # noqa: E402

COLOURS_SQL = disk_sql(S["part_pts"], RADIUS, "count(DISTINCT p.color)")
KINDS_SQL = disk_sql(S["part_pts"], RADIUS, "count(DISTINCT p.kind)")


def depth_only(df):
    return df.select(F.col("depth").cast("long").alias("depth"))


@query(COLOURS_SQL)
def colored_circles(spark, d):
    return depth_only(union_arcs.coloured_by_circles(V.part_pts(spark, d), RADIUS))


@query(COLOURS_SQL)
def colored_arc_sweep(spark, d):
    return depth_only(union_arcs.coloured_arc_sweep(V.part_pts(spark, d), RADIUS))


@query(KINDS_SQL)
def colored_arc_sweep_kinds(spark, d):
    return depth_only(union_arcs.coloured_arc_sweep(V.part_pts(spark, d), RADIUS, "kind"))


@query(COLOURS_SQL)
def colored_crossings(spark, d):
    return depth_only(union_arcs.coloured_by_crossings(V.part_pts(spark, d), RADIUS))


for _engine in ("sweep", "slab", "trapezoid"):
    named(f"colored_{_engine}", lambda spark, d, e=_engine: depth_only(colored_disk.output_sensitive(V.part_pts(spark, d), RADIUS, engine=e)), COLOURS_SQL)


@query(COLOURS_SQL)
def colored_paper_grids(spark, d):
    return depth_only(colored_disk.output_sensitive(V.part_pts(spark, d), RADIUS, mode="paper"))


@query(disk_sql(S["event_pts"], 120, "count(DISTINCT p.color)").replace("SELECT DISTINCT x, y FROM c)", "SELECT x, y FROM c)"))
def colored_trajectories(spark, d):
    return depth_only(colored_disk.output_sensitive(V.event_pts(spark, d), 120, engine="branch"))


@query(f"SELECT 'exact' AS branch, depth FROM ({COLOURS_SQL})")
def colored_sampled_exact_branch(spark, d):
    return colored_disk.sampled(V.part_pts(spark, d), RADIUS, 0.5, branch="exact").select("branch", "depth")


def events_best(spark, d) -> int:
    return colored_disk.output_sensitive(V.event_pts(spark, d), 120, engine="branch").first()["depth"]


EVENT_COLOURS = disk_sql(S["event_pts"], 120, "count(DISTINCT p.color)").replace("SELECT DISTINCT x, y FROM c)", "SELECT x, y FROM c)")


def drawn(color: str, seed: int = 0) -> str:
    """The portable draw of a colour, in SQL: a number below 2^32."""
    return f"CAST('0x' || substr(md5(CAST({color} AS VARCHAR) || '|{seed}'), 1, 8) AS BIGINT)"


def kept_sql(points: str, lam: str, seed: int = 0) -> str:
    return f"SELECT * FROM ({points}) WHERE {drawn('color', seed)} < CAST(floor(least(1.0, {lam}) * 4294967296) AS BIGINT)"


def lam_sql(points: str, corners: str, eps: float, c1: float) -> str:
    return f"(SELECT {c1} * ln((SELECT count(*) FROM ({points}))) / {eps * eps} / max(best) FROM ({corners}))"


@query()
def colored_sampled_sample_branch(spark, d):
    """The sampled branch on trajectories: rate, kept disks, and whether (1 - eps) of the optimum is kept."""
    best = events_best(spark, d)
    return colored_disk.sampled(V.event_pts(spark, d), 120, 0.5, 1.0, branch="sample", engine="branch").select("branch", "lam", "kept_disks", "depth_kept", "depth", F.lit(best).cast("long").alias("optimum"), (F.col("depth") >= 0.5 * best).alias("within"))


@query(f"SELECT 'exact' AS branch, depth, depth AS optimum FROM ({COLOURS_SQL})")
def colored_sampled_auto(spark, d):
    """25 colours are fewer than the sampling level, so the branch chosen is the exact one."""
    points = V.part_pts(spark, d)
    best = union_arcs.coloured_arc_sweep(points, RADIUS).select(F.col("depth").cast("long").alias("optimum"))
    return colored_disk.sampled(points, RADIUS, 0.5).select("branch", "depth").crossJoin(F.broadcast(best))


@query(f"SELECT 'exact' AS branch, depth FROM ({KINDS_SQL})")
def colored_sampled_ball_estimate(spark, d):
    """The estimate from deepest samples in place of cell corners."""
    points = V.part_pts(spark, d).withColumn("color", F.col("kind"))
    return colored_disk.sampled(points, RADIUS, 0.5, estimate="ball").select("branch", "depth")


for _engine in ("slab", "trapezoid"):
    named(f"colored_strips_{_engine}", lambda spark, d, e=_engine: depth_only(colored_disk.strips_exact(V.part_pts(spark, d), RADIUS, engine=e)), COLOURS_SQL)


UNIT_GRIDS = ", ".join(f"({g}, {s[0]!r}::DOUBLE, {s[1]!r}::DOUBLE)" for g, s in G.shifted_grids(1.0, 0.25, 2))
CORNERS_SQL = f"""WITH b AS (SELECT DISTINCT CAST(x AS DOUBLE) / {RADIUS} AS c0, CAST(y AS DOUBLE) / {RADIUS} AS c1, color FROM ({S['part_pts']})),
    r AS (SELECT * FROM b, (VALUES {UNIT_GRIDS}) AS t(g, s0, s1)),
    k AS (SELECT *, unnest(range(CAST(floor(c0 - s0 - 1) AS BIGINT), CAST(floor(c0 - s0 + 1) AS BIGINT) + 2)) AS k0 FROM r),
    l AS (SELECT *, unnest(range(CAST(floor(c1 - s1 - 1) AS BIGINT), CAST(floor(c1 - s1 + 1) AS BIGINT) + 2)) AS k1 FROM k)
    SELECT CAST(g AS INTEGER) AS g, CAST(max(n) AS BIGINT) AS best FROM (SELECT g, k0, k1, count(DISTINCT color) AS n FROM l WHERE pow(s0 + k0 - c0, 2) + pow(s1 + k1 - c1, 2) <= 1 + 1e-9 GROUP BY g, k0, k1) GROUP BY g"""


@query(CORNERS_SQL)
def corner_estimate(spark, d):
    return colored_disk.corner_depth(V.part_pts(spark, d), RADIUS).groupBy("g").agg(F.max("depth").alias("best"))


FILTER_SQL = CORNERS_SQL.split("SELECT CAST(g AS INTEGER)")[0] + """, m AS (SELECT DISTINCT g, k0 - u AS k0, k1 - v AS k1, c0, c1, color FROM l, (VALUES (0, 0), (0, 1), (1, 0), (1, 1)) AS t(u, v) WHERE pow(s0 + k0 - c0, 2) + pow(s1 + k1 - c1, 2) <= 1 + 1e-9 AND k0 - u BETWEEN floor(c0 - s0 - 1) AND floor(c0 - s0 + 1) AND k1 - v BETWEEN floor(c1 - s1 - 1) AND floor(c1 - s1 + 1))
    SELECT CAST(g AS INTEGER) AS g, count(*) AS disks, CAST(max(n) AS BIGINT) AS most_colors FROM (SELECT g, k0, k1, count(DISTINCT color) OVER (PARTITION BY g, k0, k1) AS n FROM m) GROUP BY g"""


@query(FILTER_SQL)
def colored_corner_filter(spark, d):
    disks = colored_disk.corner_disks(V.part_pts(spark, d), RADIUS)
    per = disks.groupBy("g").agg(F.count("*").alias("disks"))
    return per.join(colored_disk.cell_colours(disks).groupBy("g").agg(F.max("colors").alias("most_colors")), "g")


ARCS_SQL = f"""WITH d AS MATERIALIZED (SELECT CAST(x AS DOUBLE) AS x, CAST(y AS DOUBLE) AS y, color, min(id) AS id FROM ({S['part_pts']}) GROUP BY 1, 2, 3),
    n AS (SELECT a.id, atan2(b.y - a.y, b.x - a.x) AS mid, acos(least(1.0, sqrt((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y)) / {2 * RADIUS})) AS half FROM d AS a JOIN d AS b ON a.color = b.color AND a.id <> b.id AND (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= {4 * RADIUS * RADIUS}),
    s AS (SELECT id, ((mid - half) + 4 * pi()) % (2 * pi()) AS lo, half FROM n),
    t AS (SELECT id, lo, least(lo + 2 * half, 2 * pi()) AS hi FROM s UNION ALL SELECT id, 0.0, lo + 2 * half - 2 * pi() FROM s WHERE lo + 2 * half > 2 * pi() UNION ALL SELECT id, 2 * pi(), 2 * pi() FROM d),
    w AS (SELECT id, lo, coalesce(max(hi) OVER (PARTITION BY id ORDER BY lo, hi ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0) AS reach FROM t)
    SELECT color, count(*) AS arcs FROM w JOIN d USING (id) WHERE lo - reach > 1e-9 GROUP BY color"""


@query(ARCS_SQL)
def union_arc_count(spark, d):
    return union_arcs.union_arcs(union_arcs.disks_of(V.part_pts(spark, d)), RADIUS).groupBy(F.col("hue").alias("color")).agg(F.count("*").alias("arcs"))


@query(ARCS_SQL.replace("SELECT color, count(*) AS arcs FROM w", f"SELECT color, CAST(sum(CASE WHEN reach < pi() THEN 1 ELSE 0 END + CASE WHEN lo > pi() THEN 1 ELSE 0 END) AS BIGINT) AS pieces FROM w"))
def monotone_arc_count(spark, d):
    """The pieces of the unions' boundaries that do not turn in x."""
    arcs = union_arcs.union_arcs(union_arcs.disks_of(V.part_pts(spark, d)), RADIUS)
    return union_arcs.monotone_arcs(arcs).groupBy(F.col("hue").alias("color")).agg(F.count("*").alias("pieces"))


def crossings_sql(points: str, color: str = "color") -> str:
    """(a, b, crossings, disks): places where exposed arcs of two colours cross, by the formulas."""
    arcs = ARCS_SQL.replace(S["part_pts"], points).replace("color", color).split(" SELECT " + color + ", count(*)")[0].rstrip()
    on = lambda t, lo, hi: " OR ".join(f"{t}{k} BETWEEN {lo} - 1e-7 AND {hi} + 1e-7" for k in ("", " + 2 * pi()", " - 2 * pi()"))
    return f"""{arcs}, e AS (SELECT id, reach AS lo, lo AS hi FROM w WHERE lo - reach > 1e-9),
    x AS (SELECT a.id AS i, b.id AS o, least(a.{color}, b.{color}) AS a, greatest(a.{color}, b.{color}) AS b, s, atan2(b.y - a.y, b.x - a.x) AS mid, sqrt((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y)) AS dd FROM d AS a JOIN d AS b ON a.{color} < b.{color}, (VALUES (-1), (1)) AS t(s) WHERE (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) BETWEEN 1e-9 AND {4 * RADIUS * RADIUS}),
    z AS (SELECT i, o, a, b, s, (mid + s * acos(least(1.0, dd / {2 * RADIUS})) + 4 * pi()) % (2 * pi()) AS ai, (mid + pi() - s * acos(least(1.0, dd / {2 * RADIUS})) + 4 * pi()) % (2 * pi()) AS ao FROM x WHERE s > 0 OR dd < {2 * RADIUS} * (1 - 1e-12)),
    m AS (SELECT {color}, count(*) AS n FROM d GROUP BY 1),
    k AS (SELECT a, b, count(*) AS crossings FROM (SELECT DISTINCT i, o, s, a, b FROM z JOIN e AS p ON p.id = i AND ({on('ai', 'p.lo', 'p.hi')}) JOIN e AS q ON q.id = o AND ({on('ao', 'q.lo', 'q.hi')})) GROUP BY a, b)
    SELECT a, b, crossings, p.n + q.n AS disks FROM k JOIN m AS p ON p.{color} = a JOIN m AS q ON q.{color} = b"""


# -- updates and streams ---------------------------------------------------------------------------------------

from ..functions import measures  # noqa: E402
from ..operators import dynamic, sampling  # noqa: E402
from ..streaming import ball_stream  # noqa: E402

EVENT_RADIUS, EVENT_EPS, EVENT_SAMPLES, EVERY = 120, 0.45, 8, 500
LOG_SQL = S["update_log"].replace("ts, value, 1 AS sign", f"(epoch_us(ts) - epoch_us(TIMESTAMP '{V.FIRST_EVENT_DAY}')) / 60000000.0 AS x, value AS y, 1 AS sign").replace("ts, value, -1", f"(epoch_us(ts) - epoch_us(TIMESTAMP '{V.FIRST_EVENT_DAY}')) / 60000000.0, value, -1")
event_plan = ball.plan(EVENT_EPS, samples=EVENT_SAMPLES)


EPOCHS_CTE = f"""s AS MATERIALIZED (SELECT round, CAST(sum(sign) OVER (ORDER BY round) AS BIGINT) AS live FROM ({LOG_SQL})),
    e AS (SELECT 0 AS epoch, CAST(round AS BIGINT) AS start, greatest(1, live) AS base FROM s WHERE round = (SELECT min(round) FROM s) UNION ALL
      SELECT epoch + 1, round, greatest(1, live) FROM (SELECT epoch, s.round, live, row_number() OVER (ORDER BY s.round) AS k FROM e JOIN s ON s.round > e.start AND (2 * live < base OR live > 2 * base)) WHERE k = 1)"""
BUDGET = 0.1


def epoch_rows_sql() -> str:
    """The log's rows by epoch, and the standing balls at each start."""
    return f"""WITH RECURSIVE {EPOCHS_CTE}, u AS (SELECT *, lead(start) OVER (ORDER BY epoch) AS until FROM e),
    l AS (SELECT id, any_value(x) AS x, any_value(y) AS y, min(round) FILTER (sign = 1) AS born, max(round) FILTER (sign = -1) AS died FROM ({LOG_SQL}) GROUP BY id),
    o AS (SELECT epoch, base, round, x, y, sign FROM ({LOG_SQL}) JOIN u ON round >= start AND (until IS NULL OR round < until) UNION ALL SELECT epoch, base, start, x, y, 1 FROM l JOIN u ON born < start AND (died IS NULL OR died >= start)),
    v AS (SELECT *, greatest(1, CAST(ceil({BUDGET / EVENT_EPS**2!r}::DOUBLE * ln(greatest(base, 2))) AS BIGINT)) AS t FROM o)"""


def epoch_changes_sql() -> str:
    """What each round changes at each sample of its epoch."""
    side = 2 * EVENT_EPS / 2**0.5
    grids = ", ".join(f"({g}, {x[0]!r}::DOUBLE, {x[1]!r}::DOUBLE)" for g, x in G.shifted_grids(side, EVENT_EPS**2, 2))
    gap = lambda c, h, k: f"pow(greatest({h} + {k} * {side!r}::DOUBLE - {c}, 0.0, {c} - {h} - ({k} + 1) * {side!r}::DOUBLE), 2)"
    cells = lambda c, h: f"unnest(range(CAST(floor(({c} - {h} - 1) / {side!r}::DOUBLE) AS BIGINT), CAST(floor(({c} - {h} + 1) / {side!r}::DOUBLE) AS BIGINT) + 1))"
    place = lambda i, f: f"pow(s{i} + (k{i} + 0.5) * {side!r}::DOUBLE + {EVENT_EPS!r}::DOUBLE * {f}(2 * pi() * u) - c{i}, 2)"
    return f"""{epoch_rows_sql()}, r AS (SELECT epoch, t, round, sign, CAST(x AS DOUBLE) / {EVENT_RADIUS} AS c0, CAST(y AS DOUBLE) / {EVENT_RADIUS} AS c1, h.* FROM v, (VALUES {grids}) AS h(g, s0, s1)),
    k AS (SELECT *, {cells('c0', 's0')} AS k0 FROM r), m AS (SELECT *, {cells('c1', 's1')} AS k1 FROM k),
    q AS (SELECT *, unnest(range(t)) AS j FROM m WHERE {gap('c0', 's0', 'k0')} + {gap('c1', 's1', 'k1')} <= 1 + 1e-9),
    a AS (SELECT *, {draws_sql(2, 'epoch')} AS u FROM q),
    c AS (SELECT epoch, g, k0, k1, j, round, sum(sign) AS dw FROM a WHERE {place(0, 'cos')} + {place(1, 'sin')} <= 1 + 1e-9 GROUP BY ALL)"""


@query(f"WITH RECURSIVE {EPOCHS_CTE} SELECT epoch, start, CAST(base AS BIGINT) AS base FROM e")
def dynamic_epochs(spark, d):
    return dynamic.assign_epochs(V.update_log(spark, d))


MID = f"SELECT CAST(x AS DOUBLE) AS x, CAST(y AS DOUBLE) AS y, sign AS w FROM ({LOG_SQL}) WHERE round <= (SELECT count(*) FROM events)"


@query(f"SELECT g, max(depth) AS recorded, count(*) AS samples_hit FROM ({sampled_sql(MID, EVENT_RADIUS, EVENT_EPS, EVENT_SAMPLES)}) WHERE depth <> 0 GROUP BY g")
def dynamic_final_depth(spark, d):
    """Sample depths after half of the rounds."""
    log = V.update_log(spark, d)
    half = V.table(spark, d, "events").count()
    return best_per_grid(dynamic.depth_after(log, half, EVENT_RADIUS, event_plan))


STANDING = f"SELECT r.round AS color, i.x, i.y FROM (SELECT round FROM ({LOG_SQL}) WHERE round % {EVERY} = 0) AS r JOIN (SELECT id, any_value(x) AS x, any_value(y) AS y, min(round) FILTER (sign = 1) AS born, max(round) FILTER (sign = -1) AS died FROM ({LOG_SQL}) GROUP BY id) AS i ON i.born <= r.round AND i.died > r.round"
ROUNDS_SQL = f"SELECT r.round, coalesce(depth, 0) AS depth FROM (SELECT CAST(round AS BIGINT) AS round FROM ({LOG_SQL}) WHERE round % {EVERY} = 0) AS r LEFT JOIN (SELECT color, max(depth) AS depth FROM ({sampled_sql(STANDING, EVENT_RADIUS, EVENT_EPS, EVENT_SAMPLES, 'count(*)').replace('GROUP BY g, k0, k1, j', 'GROUP BY g, k0, k1, j, color').replace('AS j, CAST', 'AS j, color, CAST')}) GROUP BY color) ON color = r.round"


@query()
def dynamic_round_all(spark, d):
    """The answer after every round."""
    return dynamic.round_best(V.update_log(spark, d), EVENT_RADIUS, event_plan).select("round", "depth")


@query(ROUNDS_SQL)
def dynamic_round_best(spark, d):
    """The rounds of ``dynamic_round_all`` that brute-force SQL can check: every 500th."""
    return dynamic_round_all(spark, d).where(f"round % {EVERY} = 0")


@query(ROUNDS_SQL)
def dynamic_recompute(spark, d):
    log = V.update_log(spark, d)
    rounds = range(EVERY, 2 * V.table(spark, d, "events").count() + 1, EVERY)
    return dynamic.recompute(log, list(rounds), EVENT_RADIUS, event_plan)


event_draws = ball.plan(EVENT_EPS, samples=EVENT_SAMPLES, sampler="uniform")


@query(f"{epoch_changes_sql()}, n AS (SELECT epoch, count(DISTINCT round) AS rounds FROM o GROUP BY epoch), w AS (SELECT epoch, sum(dw) OVER (PARTITION BY epoch, g, k0, k1, j ORDER BY round) AS depth FROM c) SELECT epoch, rounds, CAST(coalesce((SELECT max(depth) FROM w WHERE w.epoch = n.epoch), 0) AS BIGINT) AS depth FROM n")
def dynamic_replay_epochs(spark, d):
    """Every epoch on samples of its own, their number by its base."""
    return dynamic.replay(V.update_log(spark, d), EVENT_RADIUS, event_draws, BUDGET).groupBy("epoch").agg(F.count("*").alias("rounds"), F.max("depth").alias("depth"))


@query(f"WITH RECURSIVE {EPOCHS_CTE} SELECT epoch, CAST(greatest(1, ceil({BUDGET / EVENT_EPS**2!r}::DOUBLE * ln(greatest(base, 2)))) AS INTEGER) AS samples FROM e")
def epoch_budgets(spark, d):
    """How the samples of a cell follow the base of the epoch."""
    return dynamic.assign_epochs(V.update_log(spark, d)).select("epoch", dynamic.epoch_samples(EVENT_EPS, BUDGET).alias("samples"))


@query(f"SELECT g, max(depth) AS recorded, count(*) AS samples_hit FROM ({sampled_sql(MID, EVENT_RADIUS, EVENT_EPS, EVENT_SAMPLES)}) WHERE depth <> 0 GROUP BY g")
def stream_final_depth(spark, d):
    log = V.update_log(spark, d)
    half = V.table(spark, d, "events").count()
    return best_per_grid(ball_stream.replayed(log.where(F.col("round") <= half), EVENT_RADIUS, event_plan))


def timed_events(spark, d, color):
    return V.table(spark, d, "events").select(F.col("ts").cast("timestamp").alias("ts"), F.col(color).alias("color"))


@query("SELECT epoch_us(w) AS start_us, event_type AS color, count(*) AS n FROM (SELECT event_type, unnest(generate_series(time_bucket(INTERVAL 12 HOURS, ts) - INTERVAL 36 HOURS, time_bucket(INTERVAL 12 HOURS, ts), INTERVAL 12 HOURS)) AS w FROM events) GROUP BY 1, 2")
def hotspot_sliding(spark, d):
    return ball_stream.sliding_hotspots(timed_events(spark, d, "event_type")).select(F.unix_micros("start").alias("start_us"), "color", "n")


@query("WITH o AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOURS THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM o) SELECT user_id AS color, epoch_us(min(ts)) AS start_us, count(*) AS n FROM s GROUP BY user_id, k")
def event_sessions(spark, d):
    return ball_stream.sessions(timed_events(spark, d, "user_id")).select("color", F.unix_micros("start").alias("start_us"), "n")


@query("SELECT r_name, n_name, count(*) AS customers, CAST(sum(CAST(round(c_acctbal) AS BIGINT)) AS BIGINT) AS x FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name)")
def hotspot_rollup(spark, d):
    """Customers rolled up from nations to regions to all."""
    names = V.table(spark, d, "nation").join(F.broadcast(V.table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").alias("color"), "n_name", "r_name")
    return V.cust_pts(spark, d).join(F.broadcast(names), "color").rollup("r_name", "n_name").agg(F.count("*").alias("customers"), F.sum("x").alias("x"))


@query(f"SELECT q.r AS round, (SELECT b.depth FROM ({ROUNDS_SQL}) AS b WHERE b.round <= q.r ORDER BY b.round DESC LIMIT 1) AS depth FROM range(777, (SELECT 2 * count(*) FROM events), 777) AS q(r) WHERE q.r >= {EVERY}")
def asof_best(spark, d):
    answers = dynamic_round_best(spark, d)
    top = 2 * V.table(spark, d, "events").count()
    asked = spark.range(777, top, 777).select(F.col("id").alias("round")).where(f"round >= {EVERY}")
    return ball_stream.as_of(answers, asked).select("round", F.col("depth").cast("long").alias("depth"))


@query()
def asof_all(spark, d):
    """The newest of all answers at every 777th round; ``asof_best`` knows every 500th answer only."""
    asked = spark.range(777, 2 * V.table(spark, d, "events").count(), 777).select(F.col("id").alias("round"))
    return ball_stream.as_of(dynamic_round_all(spark, d), asked).select("round", F.col("depth").cast("long").alias("depth"))


# -- other dimensions, samplers and measures -------------------------------------------------------------------


def emb_sql(dim: int, radius: float) -> str:
    return "SELECT vec_id AS id, label AS color, label + 1 AS w, " + ", ".join(f"CAST(embedding[{i + 1}] AS DOUBLE) / {radius!r}::DOUBLE AS c{i}" for i in range(dim)) + " FROM embeddings"


#: dimension: radius, eps, samples, shifts, whether only cells that hold a point are sampled.  From three on the
#: shifts are fewer than the factor needs, so the answers stand beside a place's depth and a bound instead.  Eight are not listed: Spark's optimizer runs out of
#: memory on the plan.
SPACES = {1: (0.05, 0.4, 2, "thin", False), 3: (0.3, 0.45, 2, "two", False), 5: (0.4, 0.45, 2, "two", True)}


def space_ball(spark, d, dim: int, color: str | None = None):
    """(recorded, depth, centred, bound): the deepest sample, its true depth, the best place at a point, and no place's bound."""
    radius, eps, t, mode, own = SPACES[dim]
    points = V.emb_pts(spark, d, dim).withColumn("w", F.col("color") + 1)
    balls, p = G.to_dual(points, radius, None, "pos", dim), ball.plan(eps, dim, samples=t, mode=mode)
    if own:
        depths = ball.own_cell_depth(balls, p, color=color)
    else:
        depths = ball.colour_depth(balls, p, color) if color else ball.sample_depth(balls, p)
    best = ball.true_depth(ball.deepest(depths, p), balls, p, color=color).select(F.col("recorded").cast("long").alias("recorded"), F.col("depth").cast("long").alias("depth"))
    for name, reach in (("centred", 1.0), ("bound", 2.0)):
        best = best.crossJoin(F.broadcast(ball.around_points(balls, dim, reach, color).select(F.col("top").cast("long").alias(name))))
    return best


for _dim, (_r, _e, _t, _m, _o) in SPACES.items():
    named(f"ball_static_d{_dim}", lambda spark, d, k=_dim: space_ball(spark, d, k), space_query(emb_sql(_dim, _r), _dim, _e, _t, _m, _o))
    named(f"ball_colored_d{_dim}", lambda spark, d, k=_dim: space_ball(spark, d, k, "color"), space_query(emb_sql(_dim, _r), _dim, _e, _t, _m, _o, "count(DISTINCT color)"))


PART = S["part_pts"]
SUPPLIERS = "SELECT s_suppkey AS id, round(s_acctbal) AS x, 100.0 * s_nationkey AS y, 1 AS w, s_nationkey AS color FROM supplier"
SUPPLIER_RADIUS = 1500


def supplier_pts(spark, d):
    return V.table(spark, d, "supplier").select(F.col("s_suppkey").alias("id"), F.round("s_acctbal").alias("x"), (F.col("s_nationkey") * 100.0).alias("y"), F.lit(1).cast("long").alias("w"), F.col("s_nationkey").alias("color"))


SUPPLIER_DUAL = f"SELECT id, w, color, CAST(x AS DOUBLE) / {SUPPLIER_RADIUS} AS c0, CAST(y AS DOUBLE) / {SUPPLIER_RADIUS} AS c1 FROM ({SUPPLIERS})"
SEEDS = range(20)


@query(f"WITH {space_sql(SUPPLIER_DUAL, 2, EPS, SAMPLES, 'thin', False, seeds=', '.join(map(str, SEEDS)))}, o AS ({disk_sql(SUPPLIERS, SUPPLIER_RADIUS)}) SELECT CAST(seed AS INTEGER) AS seed, recorded, o.depth AS optimum, recorded >= {G.cap_fraction(EPS, 2)!r}::DOUBLE * o.depth AS within FROM best, o")
def success_by_seed(spark, d):
    """Random samples by twenty seeds: what each records, and whether it reaches the cap fraction of the optimum."""
    points = supplier_pts(spark, d)
    best = exact_disk.exact_disk(points, SUPPLIER_RADIUS).select(F.col("depth").cast("long").alias("optimum"))
    balls, p = G.to_dual(points, SUPPLIER_RADIUS, ["x", "y"]), ball.plan(EPS, samples=SAMPLES, sampler="uniform")
    seeded = balls.withColumn("seed", F.explode(F.array(*(F.lit(s) for s in SEEDS))))
    depths = ball.sample_hits(seeded, p, ["seed", "w"], seed=F.col("seed")).groupBy("seed", *p.cell, "j").agg(F.sum("w").alias("depth"))
    found = depths.groupBy("seed").agg(F.max("depth").cast("long").alias("recorded")).crossJoin(F.broadcast(best))
    return found.select("seed", "recorded", "optimum", (F.col("recorded") >= G.cap_fraction(EPS, 2) * F.col("optimum")).alias("within"))


@query(f"WITH {space_sql(f'SELECT id, w, color, CAST(x AS DOUBLE) / {RADIUS} AS c0, CAST(y AS DOUBLE) / {RADIUS} AS c1 FROM ({PART})', 2, EPS, SAMPLES, 'thin', False, seeds='3')} SELECT recorded, CAST((SELECT sum(w) FROM b WHERE pow(q0 - c0, 2) + pow(q1 - c1, 2) <= 1 + 1e-9) AS BIGINT) AS depth FROM best")
def ball_static_uniform(spark, d):
    """Random samples: what is recorded, and the true depth of the place."""
    return ball.static_ball(V.part_pts(spark, d), RADIUS, EPS, samples=SAMPLES, sampler="uniform", seed=3).select(F.col("recorded").cast("long").alias("recorded"), F.col("depth").cast("long").alias("depth"))


PAPER_BUDGET = f"CAST(ceil(ln((SELECT count(*) FROM part)) / {EPS * EPS!r}::DOUBLE) AS BIGINT)"


@query(f"SELECT samples, max(depth) AS recorded FROM (SELECT {PAPER_BUDGET} AS samples), ({sampled_sql(S['part_pts'], RADIUS, EPS, 16).replace('range(16)', f'range({PAPER_BUDGET})').replace('j / 16.0', f'j / CAST({PAPER_BUDGET} AS DOUBLE)')}) GROUP BY samples")
def ball_static_budget(spark, d):
    """The sample budget that grows with the logarithm of the points."""
    points = V.part_pts(spark, d)
    t = G.sample_budget(points.count(), EPS)
    return ball.static_ball(points, RADIUS, EPS, samples=t).select(F.lit(t).cast("long").alias("samples"), F.col("recorded").cast("long").alias("recorded"))


@query("SELECT supplier, dim, CAST(greatest(1, ceil(ln(CAST(n AS DOUBLE)) * (1 - f + 0.05) / 0.05)) AS INTEGER) AS samples FROM (SELECT l_suppkey AS supplier, count(*) AS n FROM lineitem GROUP BY 1), (SELECT 2 AS dim, acos((3 * 0.16 + 0.0256) / (2 + 0.32) / 0.4) / pi() AS f UNION ALL SELECT 3, 0.5 - (3 * 0.16 + 0.0256) / (2 + 0.32) / 0.4 / 2)")
def lean_budgets(spark, d):
    """For each supplier of n line items the samples that one good cell needs to fail with a chance of one in n only."""
    sizes = V.table(spark, d, "lineitem").groupBy(F.col("l_suppkey").alias("supplier")).agg(F.count("*").alias("n"))
    budgets = F.array(*(F.struct(F.lit(k).alias("dim"), G.lean_budget(F.col("n"), 0.4, k).alias("samples")) for k in (2, 3)))
    return sizes.select("supplier", F.explode(budgets).alias("b")).select("supplier", "b.*")


@query(f"""WITH p AS ({S['part_pts']}), g AS (SELECT max(depth) AS guess FROM ({PART_SAMPLES})), k AS (SELECT p.* FROM p, g WHERE {drawn('id')} < CAST(floor(least(1.0, ln((SELECT count(*) FROM p)) / 0.25 / guess) * 4294967296) AS BIGINT))
    SELECT (SELECT count(*) FROM k) AS kept, (SELECT guess FROM g) AS guess, (SELECT depth FROM ({disk_sql(S['part_pts'], RADIUS)})) AS optimum, (SELECT CAST(round(best.depth / least(1.0, ln((SELECT count(*) FROM p)) / 0.25 / g.guess)) AS BIGINT) FROM g, ({disk_sql('SELECT * FROM k', RADIUS).replace('WITH p AS MATERIALIZED (SELECT * FROM k)', 'WITH p AS MATERIALIZED (SELECT * FROM k)')}) AS best) AS estimate""")
def object_sample_ball(spark, d):
    """Objects kept at a rate from the deepest sample's depth; the exact optimum of what is kept, divided by the rate."""
    points = V.part_pts(spark, d)
    guess = ball.static_ball(points, RADIUS, EPS, samples=SAMPLES).first()["recorded"]
    best = exact_disk.exact_disk(points, RADIUS).select(F.col("depth").alias("optimum"))
    found = sampling.object_sample(points, RADIUS, 0.5, guess, 1.0)
    return found.select("kept", F.lit(guess).cast("long").alias("guess"), F.round("depth_kept").cast("long").alias("estimate")).crossJoin(F.broadcast(best))


MORTON = " + ".join(f"(((CAST(floor({c} / {RADIUS / 8!r}::DOUBLE) AS BIGINT) + 524288) >> {b}) & 1) * {1 << (2 * b + i)}" for i, c in enumerate(("x", "y")) for b in range(20))


@query(f"""WITH p AS ({S['part_pts']}), n AS (SELECT *, row_number() OVER (ORDER BY {MORTON}, id) AS rn FROM p), k AS (SELECT id, x, y, w * 3 AS w, color FROM n WHERE rn % 3 = 0)
    SELECT (SELECT count(*) FROM k) AS kept, (SELECT depth FROM ({disk_sql('SELECT * FROM k', RADIUS)})) AS depth_kept, (SELECT depth FROM ({disk_sql(S['part_pts'], RADIUS)})) AS optimum""")
def morton_sample_ball(spark, d):
    """Every third point along a space-filling curve: the exact optimum of what is kept, and of all."""
    points = V.part_pts(spark, d)
    best = exact_disk.exact_disk(points, RADIUS).select(F.col("depth").alias("optimum"))
    return sampling.morton_sample(points, RADIUS, 3).select("kept", "depth_kept").crossJoin(F.broadcast(best))


PART_BALLS = f"SELECT id, CAST(x AS DOUBLE) / {RADIUS} AS c0, CAST(y AS DOUBLE) / {RADIUS} AS c1 FROM ({S['part_pts']})"
_side = 2 * EPS / 2**0.5
THIN_GRIDS = ", ".join(f"({g}, {s[0]!r}::DOUBLE, {s[1]!r}::DOUBLE)" for g, s in G.shifted_grids(_side, EPS**2, 2))


@query(f"SELECT id, CAST(sum(CASE WHEN pow(c0 - s0 - (floor((c0 - s0) / {_side!r}::DOUBLE) + 0.5) * {_side!r}::DOUBLE, 2) + pow(c1 - s1 - (floor((c1 - s1) / {_side!r}::DOUBLE) + 0.5) * {_side!r}::DOUBLE, 2) <= {EPS**4!r}::DOUBLE * (1 + 1e-9) THEN 1 ELSE 0 END) AS BIGINT) AS n FROM ({PART_BALLS}), (VALUES {THIN_GRIDS}) AS t(g, s0, s1) GROUP BY id")
def grid_cells_near(spark, d):
    return measures.near_coverage(dual(spark, d), ball.plan(EPS, samples=SAMPLES))


CELLS_SQL = PART_SAMPLES[: PART_SAMPLES.index("    q AS (")].rstrip().rstrip(",")


@query(CELLS_SQL + f" SELECT CAST(9 AS BIGINT) AS grids, CAST(max(n) AS BIGINT) AS most_cells, CAST({(int(-(-2 // _side)) + 1) ** 2} AS BIGINT) AS bound, CAST(sum(n) AS BIGINT) AS cells FROM (SELECT id, g, count(*) AS n FROM m GROUP BY id, g)")
def touch_counts(spark, d):
    return measures.touch_counts(dual(spark, d), ball.plan(EPS, samples=SAMPLES))


@query(CELLS_SQL + f" SELECT CAST(coalesce(g, -1) AS INTEGER) AS g, count(*) AS cells, CAST(count(*) * {SAMPLES} AS BIGINT) AS samples FROM (SELECT DISTINCT g, k0, k1 FROM m) GROUP BY ROLLUP (g)")
def method_stats(spark, d):
    return measures.method_stats(dual(spark, d), ball.plan(EPS, samples=SAMPLES))


BALLS_SAMPLES = PART_SAMPLES[: PART_SAMPLES.index("    SELECT CAST(g AS INTEGER)")]


@query(f"{BALLS_SAMPLES} SELECT CAST(a.g AS INTEGER) AS g, CAST(a.n AS BIGINT) AS by_samples, CAST(b.n AS BIGINT) AS by_balls FROM (SELECT g, sum(d) AS n FROM (SELECT g, sum(w) AS d FROM h GROUP BY g, k0, k1, j) GROUP BY g) AS a JOIN (SELECT g, sum(w * n) AS n FROM (SELECT g, id, any_value(w) AS w, count(*) AS n FROM h GROUP BY g, id) GROUP BY g) AS b USING (g)")
def game_identity(spark, d):
    return measures.game_check(dual(spark, d), ball.plan(EPS, samples=SAMPLES))


@query("WITH e AS (SELECT DISTINCT 0.1::DOUBLE + 3 * l_discount AS eps FROM lineitem), q AS (SELECT eps, (3 * eps * eps + pow(eps, 4)) / (2 + 2 * eps * eps) / eps AS q FROM e) SELECT eps, dim, round(CASE dim WHEN 2 THEN acos(q) / pi() WHEN 3 THEN (1 - q) / 2 ELSE 0.5 - (q - q * q * q / 3) * 3 / 4 END, 6) AS factor FROM q, (SELECT unnest([2, 3, 5]) AS dim)")
def cap_fraction_table(spark, d):
    """Numeric integration against the closed forms of these dimensions, at an eps for each discount of the line items."""
    asked = V.table(spark, d, "lineitem").select((F.lit(0.1) + 3 * F.col("l_discount")).alias("eps")).distinct()
    integrate = F.udf(lambda e, k: None if e is None else round(G.cap_fraction(e, k), 6), "double")
    return asked.withColumn("dim", F.explode(F.array(F.lit(2), F.lit(3), F.lit(5)))).withColumn("factor", integrate("eps", "dim"))


@query()
def cap_fraction_measured(spark, d):
    """(dim, measured, formula): the cap's share by chance, a draw for each line item, and by formula."""
    items = V.table(spark, d, "lineitem").select("l_orderkey", "l_linenumber")
    rows = [measures.cap_fraction_drawn(items, 0.25, k).withColumn("dim", F.lit(k)) for k in (2, 3)]
    return rows[0].union(rows[1])


@query(crossings_sql(S["part_pts"]))
def pair_crossings(spark, d):
    """(a, b, crossings, disks): crossings of two colours' boundaries, and the disks of both."""
    points = V.part_pts(spark, d)
    disks = union_arcs.disks_of(points)
    return measures.pair_crossings(union_arcs.arc_crossings(points, RADIUS), disks)


@query(f"SELECT max(CAST(crossings AS DOUBLE) / disks) <= 6 AS linear, sum(crossings) <= 24 * (SELECT count(*) FROM (SELECT DISTINCT x, y, color FROM ({S['part_pts']}))) * (SELECT depth FROM ({COLOURS_SQL})) AS by_optimum, CAST(sum(crossings) AS BIGINT) AS crossings FROM ({crossings_sql(S['part_pts'])})")
def pair_crossings_bound(spark, d):
    """Two colours' boundaries cross at most 6 times the disks of both; in all at most 24 n times the optimum."""
    points = V.part_pts(spark, d)
    best = colored_disk.output_sensitive(points, RADIUS).first()["depth"]
    n = union_arcs.disks_of(points).count()
    return pair_crossings(spark, d).agg(F.bool_and(F.col("crossings") <= 6 * F.col("disks")).alias("linear"), (F.sum("crossings") <= 24 * n * best).alias("by_optimum"), F.sum("crossings").cast("long").alias("crossings"))


@query(f"SELECT g, most_colors <= 4 * (SELECT depth FROM ({COLOURS_SQL})) AS within FROM ({FILTER_SQL})")
def cell_color_bound(spark, d):
    """No filtered cell has more than four times the optimum's colours."""
    points = V.part_pts(spark, d)
    best = colored_disk.output_sensitive(points, RADIUS).select(F.col("depth").alias("best"))
    per = colored_disk.cell_colours(colored_disk.corner_disks(points, RADIUS)).groupBy("g").agg(F.max("colors").alias("n"))
    return per.crossJoin(F.broadcast(best)).select("g", (F.col("n") <= 4 * F.col("best")).alias("within"))


LAMBDAS = (0.25, 0.5, 0.75)


@query(" UNION ALL ".join(f"SELECT {lam}::DOUBLE AS lam, {lam}::DOUBLE * (SELECT count(*) FROM events) AS expected, (SELECT count(*) FROM ({kept_sql(S['event_pts'], lam)})) AS kept" for lam in LAMBDAS))
def sampled_size(spark, d):
    """(lam, expected, kept): disks of the kept colours against lam n."""
    points = V.event_pts(spark, d)
    n = points.count()
    rows = None
    for lam in LAMBDAS:
        one = colored_disk.keep_colours(points, lam).agg(F.lit(lam).alias("lam"), F.lit(lam * n).alias("expected"), F.count("*").alias("kept"))
        rows = one if rows is None else rows.union(one)
    return rows


@query(f"{epoch_changes_sql()}, n AS (SELECT epoch, count(*) AS rows, count(DISTINCT round) AS updates FROM o GROUP BY epoch), z AS (SELECT epoch, count(*) AS touched FROM c GROUP BY epoch) SELECT epoch, updates, rows - updates AS resampled, coalesce(touched, 0) AS touched FROM n LEFT JOIN z USING (epoch)")
def epoch_work(spark, d):
    return dynamic.epoch_stats(V.update_log(spark, d), EVENT_RADIUS, event_draws, BUDGET)


SWEEP = (0.1, 0.2, 0.3, 0.4)


def sweep_sql(eps: float) -> str:
    """The deepest even sample over the suppliers, its true depth and the optimum."""
    side = 2 * eps / 2**0.5
    shifts = G.shifted_grids(side, eps**2, 2)
    factor = ball.plan(eps, samples=SAMPLES).factor
    place = lambda i, f: f"h.s{i} + (b.k{i} + 0.5) * {side!r}::DOUBLE + {eps!r}::DOUBLE * {f}(2 * pi() * b.j / {SAMPLES}.0)"
    grids = ", ".join(f"({g}, {v[0]!r}::DOUBLE, {v[1]!r}::DOUBLE)" for g, v in shifts)
    return f"""SELECT {eps!r}::DOUBLE AS eps, {len(shifts)} AS grids, b.depth AS recorded, (SELECT count(*) FROM ({SUPPLIER_DUAL}) WHERE pow({place(0, 'cos')} - c0, 2) + pow({place(1, 'sin')} - c1, 2) <= 1 + 1e-9) AS depth, o.depth AS optimum, (SELECT count(*) FROM ({SUPPLIER_DUAL}) WHERE pow({place(0, 'cos')} - c0, 2) + pow({place(1, 'sin')} - c1, 2) <= 1 + 1e-9) >= {factor!r}::DOUBLE * o.depth AS within
    FROM (SELECT * FROM ({sampled_sql(SUPPLIERS, SUPPLIER_RADIUS, eps, SAMPLES)}) ORDER BY depth DESC, g, k0, k1, j LIMIT 1) AS b JOIN (VALUES {grids}) AS h(g, s0, s1) ON h.g = b.g, ({disk_sql(SUPPLIERS, SUPPLIER_RADIUS)}) AS o"""


@query(" UNION ALL ".join(f"SELECT * FROM ({sweep_sql(e)})" for e in SWEEP))
def eps_sweep(spark, d):
    """For each eps: recorded and true depth of the deepest even sample, the optimum, and whether the sure factor holds."""
    points, out = supplier_pts(spark, d), None
    best = exact_disk.exact_disk(points, SUPPLIER_RADIUS).select(F.col("depth").cast("long").alias("optimum"))
    for eps in SWEEP:
        p = ball.plan(eps, samples=SAMPLES)
        one = ball.static_ball(points, SUPPLIER_RADIUS, eps, samples=SAMPLES).crossJoin(F.broadcast(best)).select(F.lit(eps).alias("eps"), F.lit(len(p.grids)).alias("grids"), F.col("recorded").cast("long").alias("recorded"), F.col("depth").cast("long").alias("depth"), "optimum", (F.col("depth") >= p.factor * F.col("optimum")).alias("within"))
        out = one if out is None else out.union(one)
    return out


@query("SELECT n, CAST(6 AS BIGINT) AS m, CAST(ceil(n / 6.0) AS BIGINT) AS oracle_calls, 4 * n AS interval_points, 2 * n AS enclosing_points FROM (SELECT count(*) AS n FROM nation)")
def reduction_sizes(spark, d):
    a = V.sequence_of(spark, d, "customer")
    s = convolution.reduction_stats(a.count(), 6)
    return a.agg(F.count("*").alias("n"), *(F.lit(v).cast("long").alias(k) for k, v in (("m", 6), *s.items())))


@query(disk_sql(S["doc_pts"], 20, "count(DISTINCT p.color)"))
def colored_facilities(spark, d):
    """Variety of sources around a document size and line count."""
    return depth_only(union_arcs.coloured_arc_sweep(V.doc_pts(spark, d), 20))


@query(disk_sql(S["cust_pts"], 300, "count(DISTINCT p.color)"))
def colored_customers(spark, d):
    return depth_only(union_arcs.coloured_arc_sweep(V.cust_pts(spark, d), 300))


KEYED = f"SELECT id, x, y, w, CAST(id AS VARCHAR) AS color FROM ({S['part_pts']})"
VARIETIES = {"kind": f"SELECT id, x, y, w, kind AS color FROM ({S['part_pts']})", "color": f"SELECT id, x, y, w, color FROM ({S['part_pts']})", "key": KEYED}


@query(" UNION ALL ".join(f"SELECT '{n}' AS colours, (SELECT count(*) FROM (SELECT DISTINCT x, y, color FROM ({q}))) AS disks, (SELECT depth FROM ({disk_sql(q, RADIUS, 'count(DISTINCT p.color)')})) AS optimum, (SELECT CAST(sum(crossings) AS BIGINT) FROM ({crossings_sql(q)})) AS crossings" for n, q in VARIETIES.items()))
def output_sensitivity(spark, d):
    """(colours, disks, optimum, crossings): from few colours to one for each part, crossings grow with disks times optimum."""
    out = None
    for name in VARIETIES:
        points = V.part_pts(spark, d)
        points = points.withColumn("color", F.col("id").cast("string") if name == "key" else F.col(name))
        n = union_arcs.disks_of(points).agg(F.lit(name).alias("colours"), F.count("*").alias("disks"))
        best = union_arcs.coloured_arc_sweep(points, RADIUS).select(F.col("depth").cast("long").alias("optimum"))
        k = union_arcs.arc_crossings(points, RADIUS).agg(F.count("*").alias("crossings"))
        one = n.crossJoin(F.broadcast(best)).crossJoin(F.broadcast(k))
        out = one if out is None else out.union(one)
    return out

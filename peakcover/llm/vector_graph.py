"""Near-duplicate vectors by a robust-pruned flat graph over overlapping cluster shards.

Vectors of equal label are compared.  Equal vectors form one class first.  Each label's space is cut by
centroids fitted on a bounded sample (at most ``SAMPLE`` vectors a label, chosen by hash); every vector goes to
the shards of its ``overlap`` nearest centroids.  A shard of more than ``most`` vectors is dealt into blocks.

In each block a graph is built whose neighbour lists are robustly pruned; the lists of a vector from all its
blocks are united; then every vector searches each block of its shards: greedily from the block's medoid over
the united graph, and on reaching its range, through all neighbours inside a slightly wider range.  What is
found is verified by the cosine in double precision.  A pair that meets in several blocks counts in the first.

Pairs that share no shard are compared in cells, the parts of the space around few, coarser centroids.  A vector
can have a link in a cell only if the plane between that cell and its own is no farther than the angle of the
cosine; it is sent to those cells alone, and all products of two cells' vectors are taken, so none is lost.

Blocks return for each vector the number of its links, and only the links that join components: the
components a block's own links leave, as a star for each.  No pair list exists.  Centroids meet their label's
vectors in a join, a part of a large label at a time; small labels share a task, many at a time.

Defined cases: a null label, a null or zero vector, and null or non-finite components link with nothing; rows
with a null id take part as nothing and come back with a null component, kept; rows that share an id are one
vector if equal; vectors of another length than their label's first are compared among their own length.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common
from .components import connected

COSINE = 0.93
SAMPLE = 4096
MEAN_SHARD = 200
MOST_BLOCK = 1500
MEAN_CELL = 1500
PART = 4096
OVERLAP = 3
DEGREE, ALPHA, BEAM = 32, 1.2, 32
SLACK = 0.04


def robust_prune(vectors, candidates, degree: int = DEGREE, alpha: float = ALPHA):
    """Neighbour lists (-1 where short): a candidate goes if a kept neighbour is alpha times nearer to it than the node.

    candidates: node rows of candidate indices by ascending distance; all nodes are pruned side by side.
    """
    import numpy as np

    n, width = candidates.shape
    out = np.full((n, degree), -1, dtype=np.int32)
    alive = candidates >= 0
    rows = np.arange(n)
    gathered = vectors[np.maximum(candidates, 0)]
    far = 2 - 2 * np.einsum("nwd,nd->nw", gathered, vectors)
    for k in range(degree):
        first = alive.argmax(axis=1)
        some = alive[rows, first]
        if not some.any():
            break
        pick = np.where(some, candidates[rows, first], -1)
        out[:, k] = pick
        between = 2 - 2 * np.einsum("nwd,nd->nw", gathered, vectors[np.maximum(pick, 0)])
        alive &= ~((alpha * alpha * between <= far) & some[:, None])
        alive[rows, first] = False
    return out


def build_lists(vectors, degree: int = DEGREE):
    """Robust-pruned out-lists of one block with their reverse links added and pruned again."""
    import numpy as np

    n = len(vectors)
    if n < 2:
        return [np.zeros(0, dtype=np.int64) for _ in range(n)]
    near = vectors @ vectors.T
    np.fill_diagonal(near, -np.inf)
    width = min(n - 1, 3 * degree)
    # the nearest and, so that distant parts stay reachable, an even spread of the rest
    order = np.argsort(-near, axis=1, kind="stable")[:, : n - 1]
    spread = order[:, np.unique(np.linspace(0, n - 2, min(n - 1, degree)).astype(int))]
    candidates = np.concatenate([order[:, :width], spread], axis=1).astype(np.int32)
    lists = robust_prune(vectors, candidates, degree)
    back: list[list[int]] = [[] for _ in range(n)]
    for i, row in enumerate(lists.tolist()):
        for j in row:
            if j >= 0:
                back[j].append(i)
    return [np.unique(np.array([j for j in row if j >= 0] + back[i][: 2 * degree], dtype=np.int64)) for i, row in enumerate(lists.tolist())]


def range_search(queries, vectors, lists, medoid: int, cosine: float = COSINE, slack: float = SLACK, beam: int | None = BEAM):
    """For each query the vectors reached in range: a boolean table (queries x vectors) of places to verify."""
    import numpy as np

    q, n = len(queries), len(vectors)
    width = max([1, *map(len, lists)])
    table = np.full((n, width), -1, dtype=np.int64)
    for i, row in enumerate(lists):
        table[i, : len(row)] = row
    score = np.full((q, n), -np.inf, dtype=np.float32)
    opened = np.zeros((q, n), dtype=bool)
    score[:, medoid] = queries @ vectors[medoid]
    rows = np.arange(q)
    for _ in range(n if beam is None else min(n, beam)):
        # the nearest seen node that is not open yet; queries that have reached their range wait for the expansion
        todo = np.where(opened, -np.inf, score)
        best = todo.argmax(axis=1)
        value = todo[rows, best]
        active = np.flatnonzero((value > -np.inf) & (value < cosine - slack))
        if not len(active):
            break
        at = best[active]
        opened[active, at] = True
        near = table[at]
        got = np.einsum("awd,ad->aw", vectors[np.maximum(near, 0)], queries[active])
        a, w = np.nonzero(near >= 0)
        score[active[a], near[a, w]] = got[a, w]
    # range expansion, all nodes in range at once
    links = np.zeros((n, n), dtype=np.float32)
    for i, row in enumerate(lists):
        links[i, row] = 1
    inside = score >= cosine - slack
    fresh = inside & ~opened
    while fresh.any():
        opened |= fresh
        touched = (fresh.astype(np.float32) @ links > 0) & (score == -np.inf)
        a, b = np.nonzero(touched)
        for at in range(0, len(a), 1 << 16):
            x, y = a[at : at + (1 << 16)], b[at : at + (1 << 16)]
            score[x, y] = np.einsum("ad,ad->a", queries[x], vectors[y])
        inside = score >= cosine - slack
        fresh = inside & ~opened
    return inside


def prepared(vectors: DataFrame, id_col: str, vector: str, label: str) -> DataFrame:
    """Valid rows with an id: id, label, unit vector in double, as classes of equal vectors (rep, copies)."""
    good = f"`{vector}` IS NOT NULL AND `{label}` IS NOT NULL AND `{id_col}` IS NOT NULL AND size(`{vector}`) > 0 AND forall(`{vector}`, x -> x IS NOT NULL AND NOT isnan(x) AND abs(x) < double('Infinity')) AND exists(`{vector}`, x -> x <> 0)"
    rows = vectors.where(good).select(F.col(id_col).cast("long").alias("id"), F.col(label).cast("string").alias("label"), F.expr(f"transform(`{vector}`, x -> cast(x as double) + 0D)").alias("v"))
    rows = rows.withColumn("label", F.concat_ws(":", "label", F.size("v")))
    return rows.groupBy("label", "v").agg(F.min("id").alias("rep"), F.countDistinct("id").alias("copies"))


def fit_centroids(classes: DataFrame, sizes: DataFrame, sample: int = SAMPLE, means: tuple[int, int] = (MEAN_SHARD, MEAN_CELL), rounds: int = 6) -> DataFrame:
    """(label, fine, coarse) of the labels with more vectors than a shard, by spherical k-means on at most ``sample`` of each.

    The sample of a label comes first in the order of a hash, so it needs no second pass.
    """
    large = sizes.where(f"size > {means[0]}")
    chosen = classes.join(large, "label").where(f"pmod(xxhash64(rep, 17), 1000000) * cast(size as double) < {sample} * 1000000D").select("label", "size", "rep", "v")

    def fit(frame):
        import numpy as np
        import pandas as pd

        frame = frame.sort_values("rep").head(2 * sample)
        x = np.stack(frame["v"].to_numpy()).astype(np.float64)
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        out = []
        for mean in means:
            k = max(1, min(len(x), math.ceil(int(frame["size"].iloc[0]) / mean)))
            # below a thousand centroids for each sample: larger shards are dealt into blocks
            k = min(k, max(1, len(x) // 4))
            c = x[np.random.default_rng(11).choice(len(x), k, replace=False)]
            for _ in range(rounds):
                near = (x @ c.T).argmax(axis=1)
                for j in range(k):
                    part = x[near == j]
                    if len(part):
                        m = part.sum(axis=0)
                        c[j] = m / (np.linalg.norm(m) or 1)
            out.append(sorted(list(r) for r in c))
        return pd.DataFrame({"label": [frame["label"].iloc[0]], "fine": [out[0]], "coarse": [out[1]]})

    return common.staged(chosen.groupBy("label").applyInPandas(fit, "label string, fine array<array<double>>, coarse array<array<double>>"), "vector-centroids")


def cells_in_reach(x, centroids, cosine: float = COSINE):
    """(own cell of each unit vector, table of the cells that can hold a vector within ``cosine`` of it)."""
    import numpy as np

    scores = x @ centroids.T
    own = scores.argmax(axis=1)
    if cosine < 0:
        return own, np.ones(scores.shape, dtype=bool)
    # the bisecting planes pass through the origin, so the sine of the angle to one is the margin over the gap
    gaps = np.linalg.norm(centroids[:, None] - centroids[None], axis=2)
    return own, scores[np.arange(len(x)), own][:, None] - scores <= math.sqrt(max(0.0, 1 - cosine * cosine)) * gaps[own] + 1e-9


def assign(classes: DataFrame, sizes: DataFrame, centroids: DataFrame, overlap: int = OVERLAP, cosine: float = COSINE, mean_shard: int = MEAN_SHARD) -> DataFrame:
    """One row for each class: label, rep, copies, v (unit), shards (ascending), cell, reach (cells, none where all share a shard)."""
    shape = "label string, rep long, copies long, v array<double>, shards array<int>, cell int, reach array<int>"
    sized = classes.select("label", "rep", "copies", "v").join(sizes, "label")
    # a small label is one shard, and needs no centroids
    peak = sized.where(f"size <= {mean_shard}").withColumn("v", F.expr("transform(v, x -> x / array_max(transform(v, y -> abs(y))))"))
    small = peak.select("label", "rep", "copies", F.expr("transform(v, x -> x / sqrt(aggregate(v, 0D, (t, y) -> t + y * y)))").alias("v"), F.expr("array(0)").alias("shards"), F.lit(0).alias("cell"), F.expr("cast(array() as array<int>)").alias("reach"))
    parts = F.expr(f"cast(ceil(size / {PART}D) as int)")
    dealt = sized.where(f"size > {mean_shard}").withColumn("part", F.pmod(F.xxhash64("rep", F.lit(5)), parts).cast("int"))
    shared = centroids.join(sizes, "label").withColumn("part", F.explode(F.sequence(F.lit(0), parts - 1))).drop("size")

    def deal(key, frame, found):
        import numpy as np
        import pandas as pd

        if not len(frame) or not len(found):
            return pd.DataFrame({c.split()[0]: [] for c in shape.split(", ")})
        fine, coarse = (np.array([list(r) for r in found[c].iloc[0]]) for c in ("fine", "coarse"))
        x = np.stack(frame["v"].to_numpy()).astype(np.float64)
        x = x / np.abs(x).max(axis=1, keepdims=True)
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        shards = np.sort(np.argsort(-(x @ fine.T), axis=1, kind="stable")[:, :overlap], axis=1)
        cells, reach = np.zeros(len(x), dtype=int), [[]] * len(x)
        if len(fine) > overlap:
            cells, near = cells_in_reach(x, coarse, cosine)
            reach = [np.flatnonzero(row).tolist() for row in near]
        return frame[["label", "rep", "copies"]].assign(v=list(x), shards=shards.tolist(), cell=cells, reach=reach)

    large = dealt.groupBy("label", "part").cogroup(shared.groupBy("label", "part")).applyInPandas(deal, shape)
    return small.unionByName(large)


def apart(dealt: DataFrame, cosine: float, overlap: int, most: int) -> DataFrame:
    """Links between vectors that share no shard, in the form of the shards' own: a, b, others."""
    dealt = dealt.where("size(reach) > 0")
    cells = dealt.groupBy("label", "cell").agg(F.expr(f"cast(ceil(count(*) / {most}D) as int)").alias("blocks"))
    own = dealt.join(cells, ["label", "cell"]).withColumn("own", F.expr("cell * 1048576L + pmod(xxhash64(rep), blocks)"))
    asked = own.select("label", "own", "rep", "copies", "v", "shards", F.explode("reach").alias("cell")).join(cells, ["label", "cell"])
    # a link's two ends reach each other's cells, so they meet in the group of their two blocks, once
    asked = asked.withColumn("to", F.expr("explode(transform(sequence(0, blocks - 1), b -> cell * 1048576L + b))"))
    pairs = asked.select("label", F.expr("least(own, to) AS low"), F.expr("greatest(own, to) AS high"), "own", "rep", "copies", "v", "shards")

    def compare(key, frame):
        import numpy as np
        import pandas as pd

        low, high = int(key[1]), int(key[2])
        frame = frame.sort_values("rep")
        ids, copies = frame["rep"].to_numpy(), frame["copies"].to_numpy()
        left, right = np.flatnonzero(frame["own"] == low), np.flatnonzero(frame["own"] == high)
        sums, comp, joined = np.zeros(len(ids), dtype=np.int64), np.arange(len(ids)), []
        if len(left) and len(right):
            v = np.stack(frame["v"].to_numpy())
            shards = np.array([list(s) for s in frame["shards"]])
            y = v[right].astype(np.float32)
            for at in range(0, len(left), 256):
                rows = left[at : at + 256]
                near = v[rows].astype(np.float32) @ y.T >= cosine - 1e-3  # verified in double below
                a, b = np.nonzero(near)
                a, b = rows[a], right[b]
                if low == high:
                    a, b = a[a < b], b[a < b]
                exact = np.concatenate([np.einsum("ad,ad->a", v[a[i : i + 65536]], v[b[i : i + 65536]]) for i in range(0, len(a), 65536)] or [np.zeros(0)])
                a, b = a[exact >= cosine], b[exact >= cosine]
                shares = np.zeros(len(a), dtype=bool)
                for i in range(overlap):
                    for j in range(overlap):
                        shares |= shards[a, i] == shards[b, j]
                a, b = a[~shares], b[~shares]
                sums += np.bincount(a, weights=copies[b], minlength=len(ids)).astype(np.int64) + np.bincount(b, weights=copies[a], minlength=len(ids)).astype(np.int64)
                starters, starts = np.unique(a, return_index=True)
                for i, others in zip(starters, np.split(b, starts[1:])):
                    tops, first = np.unique(comp[others], return_index=True)
                    fresh = tops != comp[i]
                    if fresh.any():
                        joined += [(int(ids[i]), int(ids[j])) for j in others[first[fresh]]]
                        comp[np.isin(comp, tops)] = comp[i]
        some = np.flatnonzero(sums)
        out = [(int(ids[i]), None, int(sums[i])) for i in some] + [(i, j, 0) for i, j in joined]
        return pd.DataFrame(out, columns=["a", "b", "others"]).astype({"a": "int64", "b": "Int64", "others": "int64"})

    return pairs.groupBy("label", "low", "high").applyInPandas(compare, "a long, b long, others long")


def links(vectors: DataFrame, id_col: str = "vec_id", vector: str = "embedding", label: str = "label", cosine: float = COSINE, overlap: int = OVERLAP, most: int = MOST_BLOCK) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(classes: rep, copies; counts: rep, others; edges: a, b that span the links' components)."""
    classes = common.staged(prepared(vectors, id_col, vector, label), "vector-classes")
    labels = common.staged(classes.groupBy("label").agg(F.count("*").alias("size")), "vector-labels")
    packs = 1 + (labels.where(f"size <= {MEAN_SHARD}").agg(F.sum("size")).first()[0] or 0) // PART
    dealt = common.staged(assign(classes, labels, fit_centroids(classes, labels), overlap, float(cosine)), "vector-shards")
    members = dealt.drop("cell", "reach").withColumn("shard", F.explode("shards"))
    sizes = members.groupBy("label", "shard").agg(F.count("*").alias("size")).withColumn("blocks", F.expr(f"cast(ceil(size / {most}D) as int)"))
    placed = members.join(sizes.select("label", "shard", "blocks"), ["label", "shard"]).withColumn("block", F.expr("cast(pmod(xxhash64(rep), blocks) as int)"))
    # one room is a block, or many labels of one shard each
    placed = placed.join(labels, "label").withColumn("room", F.expr(f"if(size <= {MEAN_SHARD}, concat('s', pmod(xxhash64(label), {packs})), concat('l', shard, ':', block, ':', label))")).drop("size")
    placed = common.staged(placed, "vector-blocks")

    def build(room):
        import numpy as np
        import pandas as pd

        out = []
        for _, frame in room.groupby(["label", "shard", "block"], sort=False):
            frame = frame.sort_values("rep")
            x, ids = np.stack(frame["v"].to_numpy()), frame["rep"].to_numpy()
            out.append(pd.DataFrame({"rep": ids, "near": [ids[row] for row in build_lists(x)]}))
        return pd.concat(out)

    graphs = placed.groupBy("room").applyInPandas(build, "rep long, near array<long>")
    united = graphs.groupBy("rep").agg(F.array_distinct(F.flatten(F.collect_list("near"))).alias("near"))
    united = common.staged(united, "vector-graph")
    base = placed.join(united, "rep").select("room", "label", "shard", "block", "rep", "copies", "v", "shards", "near")
    base = common.staged(base, "vector-united")
    # vectors of other blocks of a shard ask there too, a slice of them at a time
    asking = placed.where("blocks > 1").withColumn("to", F.expr("explode(sequence(0, blocks - 1))")).where("to <> block")
    asking = asking.select("label", "shard", "block", F.col("to"), "rep", "copies", "v", "shards")
    threshold = float(cosine)

    def answer(x, ids, shards, y, other, weight, other_shards, inside, shard):
        """Links of the queries x among y that no earlier shared shard holds: (sums of copies, spanning pairs)."""
        import numpy as np

        a, b = np.nonzero(inside)
        keep = ids[a] != other[b]
        a, b = a[keep], b[keep]
        exact = np.concatenate([np.einsum("ad,ad->a", x[a[i : i + 65536]], y[b[i : i + 65536]]) for i in range(0, len(a), 65536)] or [np.zeros(0)])
        a, b = a[exact >= threshold], b[exact >= threshold]
        first = np.array([min(set(s).intersection(t)) == shard for s, t in zip(shards[a], other_shards[b])], dtype=bool) if len(a) else np.zeros(0, bool)
        a, b = a[first], b[first]
        sums = np.bincount(a, weights=weight[b], minlength=len(x)).astype(np.int64)
        top: dict[int, int] = {}

        def find(i):
            while top.setdefault(i, i) != i:
                top[i] = top[top[i]]
                i = top[i]
            return i

        pairs = []
        for i, j in zip(ids[a].tolist(), other[b].tolist()):
            p, r = find(i), find(j)
            if p != r:
                top[max(p, r)] = min(p, r)
                pairs.append((i, j))
        return sums, pairs

    def packed(ids, sums, pairs):
        import pandas as pd

        rows = [(i, None, s) for i, s in zip(ids.tolist(), sums.tolist()) if s] + [(i, j, 0) for i, j in pairs]
        return pd.DataFrame(rows, columns=["a", "b", "others"]).astype({"a": "int64", "b": "Int64", "others": "int64"})

    def prepare(frame):
        import numpy as np

        frame = frame.sort_values("rep")
        return (np.stack(frame["v"].to_numpy()), frame["rep"].to_numpy(), frame["copies"].to_numpy(), np.array([tuple(s) for s in frame["shards"]] + [None], dtype=object)[:-1])

    def graph(frame):
        import numpy as np

        frame = frame.sort_values("rep")
        x, ids = np.stack(frame["v"].to_numpy()), frame["rep"].to_numpy()
        lists = []
        for row in frame["near"]:
            at = np.minimum(np.searchsorted(ids, row), len(ids) - 1)
            lists.append(at[ids[at] == row])
        return x, lists, int((x @ x.sum(axis=0)).argmax())

    def search(room):
        import numpy as np
        import pandas as pd

        out = []
        for (_, shard, _), frame in room.groupby(["label", "shard", "block"], sort=False):
            x, ids, copies, shards = prepare(frame)
            y, lists, medoid = graph(frame)
            inside = np.concatenate([range_search(x[i : i + 512], y, lists, medoid, threshold) for i in range(0, len(x), 512)])
            out.append(packed(ids, *answer(x, ids, shards, y, ids, copies, shards, inside, int(shard))))
        return pd.concat(out)

    def search_across(key, left, right):
        import numpy as np
        import pandas as pd

        if not len(left) or not len(right):
            return pd.DataFrame({"a": pd.Series([], dtype="int64"), "b": pd.Series([], dtype="Int64"), "others": pd.Series([], dtype="int64")})
        y, lists, medoid = graph(right)
        _, ids, weight, held = prepare(right)
        x, asked, _, shards = prepare(left)
        inside = np.concatenate([range_search(x[i : i + 512], y, lists, medoid, threshold) for i in range(0, len(x), 512)])
        return packed(asked, *answer(x, asked, shards, y, ids, weight, held, inside, int(key[1])))

    shape = "a long, b long, others long"
    found = base.groupBy("room").applyInPandas(search, shape)
    # a group is one pair of blocks, so its size is bounded however large the shard
    targets = base.join(sizes.where("blocks > 1").select("label", "shard", "blocks"), ["label", "shard"]).withColumn("block_from", F.expr("explode(sequence(0, blocks - 1))")).where("block_from <> block")
    asking = asking.select("label", "shard", F.col("to").alias("block"), F.col("block").alias("block_from"), "rep", "copies", "v", "shards")
    keys = ["label", "shard", "block", "block_from"]
    across = asking.groupBy(*keys).cogroup(targets.select(*keys, "rep", "copies", "v", "shards", "near").groupBy(*keys)).applyInPandas(search_across, shape)
    found = common.staged(found.union(across).union(apart(dealt, threshold, overlap, most)), "vector-links")
    counts = found.where("b IS NULL").groupBy(F.col("a").alias("rep")).agg(F.sum("others").alias("others"))
    return classes, counts, found.where("b IS NOT NULL").select("a", "b")


def near_duplicates(vectors: DataFrame, id_col: str = "vec_id", vector: str = "embedding", label: str = "label", **options) -> DataFrame:
    """One row per vector: id, n_links, component_id, kept."""
    classes, counts, edges = links(vectors, id_col, vector, label, **options)
    comps = connected(edges).select(F.col("node").alias("rep"), "comp")
    whole = classes.join(counts, "rep", "left").join(comps, "rep", "left").where("copies > 1 OR others > 0 OR comp IS NOT NULL")
    whole = whole.select("label", "v", F.expr("coalesce(others, 0L) + copies - 1").alias("n"), F.expr("coalesce(comp, rep)").alias("comp"))
    rows = vectors.select(F.col(id_col).cast("long").alias("id"), F.concat_ws(":", F.col(label).cast("string"), F.size(vector)).alias("__label"), F.expr(f"transform(`{vector}`, x -> cast(x as double) + 0D)").alias("__v"), F.col(label).isNotNull().alias("__known"))
    met = rows.join(whole, (F.col("__label") == F.col("label")) & (F.col("__v") == F.col("v")) & F.col("__known") & F.col("id").isNotNull(), "left")
    out = met.select(F.col("id").alias(id_col), F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), F.expr("CASE WHEN id IS NOT NULL THEN coalesce(comp, id) END").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.expr(f"`{id_col}` = component_id"), F.lit(True)))


def recall(vectors: DataFrame, result: DataFrame, id_col: str = "vec_id", vector: str = "embedding", label: str = "label", cosine: float = COSINE, every: int = 50) -> DataFrame:
    """Links that brute force finds for the ids divisible by ``every``, those that ``result`` counts, and their share.

    The stated query set is sent to all rows in blocks; each task returns counts only.
    """
    spark = vectors.sparkSession
    classes = prepared(vectors, id_col, vector, label)
    asked = classes.where(f"rep % {every} = 0").select("label", "rep", "v")
    path = common.staged(asked, "recall-queries")
    def count(frames):
        import numpy as np
        import pandas as pd

        for f in frames:
            out = []
            for v, rep, copies, queries in zip(f["v"], f["rep"], f["copies"], f["queries"]):
                q = np.array([list(z["v"]) for z in queries])
                cos = q @ np.array(v) / (np.linalg.norm(q, axis=1) * np.linalg.norm(v))
                out += [(z["rep"], copies) for z, c in zip(queries, cos.tolist()) if c >= cosine and z["rep"] != rep]
            yield pd.DataFrame(out, columns=["rep", "n"])

    blocks = path.withColumn("part", F.expr("cast(pmod(xxhash64(rep), 16) as int)")).groupBy("label", "part").agg(F.collect_list(F.struct("rep", "v")).alias("queries"))
    truth = classes.join(blocks, "label").mapInPandas(count, "rep long, n long").groupBy("rep").agg(F.sum("n").alias("n"))
    own = classes.select("rep", (F.col("copies") - 1).alias("own"))
    both = path.select("rep").join(truth, "rep", "left").join(own, "rep").join(result.select(F.col(id_col).alias("rep"), "n_links"), "rep")
    return both.agg(F.sum(F.coalesce("n", F.lit(0)) + F.col("own")).alias("true_links"), F.sum("n_links").alias("found_links")).withColumn("recall", F.expr("if(true_links = 0, 1D, found_links / true_links)"))


def op7_vector_graph(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))

"""Connected components by alternating star contractions, all rows on the cluster."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common


def connected(edges: DataFrame) -> DataFrame:
    """(node, comp) for every node of the undirected edges (a, b); comp is the smallest node of its component.

    Each step writes its edges to the shared folder; the loop ends when a step changes none.  Self-links and
    repeated or reversed edges are allowed; no edges give no rows.
    """
    nodes = edges.select(F.least("a", "b").alias("v"), F.greatest("a", "b").alias("u"))
    now = common.staged(nodes.where("u > v").distinct(), "stars")
    mark = lambda e: tuple(e.agg(F.count("*"), F.sum(F.expr("cast(xxhash64(u, v) as decimal(38,0))"))).first())
    seen = mark(now)
    while seen[0]:
        both = now.select("u", "v").union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        # every larger neighbour goes to the node's minimum
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v").distinct()
        # then every smaller neighbour, and the node, to the smallest of them
        base = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(base, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v").union(base.select("u", F.col("m").alias("v"))).distinct()
        now = common.staged(small, "stars")
        last, seen = seen, mark(now)
        if last == seen:
            break
    comps = now.select(F.col("u").alias("node"), F.col("v").alias("comp"))
    return comps.union(comps.select("comp", "comp").distinct()).toDF("node", "comp")

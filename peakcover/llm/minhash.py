"""Near-duplicate documents by circulant MinHash, with exact Jaccard verification.

Two permutations make all coordinates of a signature: the first deals the shingle hashes over 32 bits, the
second, circularly shifted by one place for each coordinate, ranks them.  Coordinates are banded; documents
that share a band bucket are candidates, and a link stands only if the full shingle sets say so.

Copies (equal sets) form one class first, so a band bucket holds different sets only.  One pivot of each
bucket is verified against all other members, which joins most groups of near copies.  Buckets that still span
several components are settled as wholes, large ones by pairs of blocks: members of different components are
compared, unless their distances to the pivot (the Jaccard distance is a metric) or their sizes rule a link
out.  No link between different sets of a bucket is lost, and no pair leaves a task unless it is a link.

Defined cases: texts without words (null, empty) have no shingles and link with nothing; texts below
``width`` words are one shingle; very long texts are read whole, their signatures in slices; rows with a null id
are returned with a null component and kept; rows that share an id count as linked, and however often an id
repeats, each of its different texts is handled once; ties have no effect; an empty table gives no rows; input
columns other than id and text play no part, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common
from .components import connected

WIDTH = 5
PERCENT = 85
BANDS, ROWS = 24, 5
SMALL, BLOCK = 512, 400
WORD_SEED = 0x51ED


def shingle_set(text: str | None, width: int = WIDTH):
    """Sorted distinct 64-bit hashes of a text's word shingles."""
    from itertools import repeat

    import numpy as np
    from xxhash import xxh64_intdigest

    words = text.encode("utf-8", "surrogatepass").lower().split() if text else []
    if not words:
        return np.zeros(0, dtype=np.uint64)
    hashed = np.fromiter(map(xxh64_intdigest, words, repeat(WORD_SEED)), dtype=np.uint64, count=len(words))
    n = min(width, len(words))
    out = np.full(len(words) - n + 1, n, dtype=np.uint64)
    with np.errstate(over="ignore"):
        for j in range(n):
            out = (out ^ hashed[j : len(words) - n + 1 + j]) * np.uint64(0x9E3779B97F4A7C15)
            out ^= out >> np.uint64(32)
    return np.unique(out)


def signature(hashes, coordinates: int = BANDS * ROWS):
    """The circulant MinHash coordinates of a shingle set."""
    import numpy as np

    best = np.full(coordinates, 0xFFFFFFFF, dtype=np.uint32)
    dealt = ((hashes * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(32)).astype(np.uint32)
    shifts = np.arange(coordinates, dtype=np.uint32)[:, None]
    for at in range(0, len(dealt), 2048):
        z = dealt[None, at : at + 2048] + shifts
        spare = np.empty_like(z)
        for multiply, right in ((0x85EBCA6B, 13), (0xC2B2AE35, 16)):
            np.multiply(z, np.uint32(multiply), out=z)
            np.right_shift(z, np.uint32(right), out=spare)
            np.bitwise_xor(z, spare, out=z)
        np.minimum(best, z.min(axis=1), out=best)
    return best


def band_keys(best, bands: int = BANDS):
    import numpy as np

    table = best.reshape(bands, -1).astype(np.uint64)
    key = np.arange(1, bands + 1, dtype=np.uint64)
    with np.errstate(over="ignore"):
        for column in table.T:
            key = (key ^ column) * np.uint64(0x9E3779B97F4A7C15)
            key ^= key >> np.uint64(29)
    return key.view(np.int64)


def signatures(docs: DataFrame, id_col: str, text: str, width: int = WIDTH, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """doc_id, hash of the text, n_shingles, digest of the set, band keys (none without shingles)."""
    import hashlib

    added = [("n_shingles", T.LongType()), ("digest", T.BinaryType()), ("bands", T.ArrayType(T.LongType()))]

    def compute():
        def one(body):
            found = shingle_set(body, width)
            if not len(found):
                return 0, None, []
            return len(found), hashlib.blake2b(found.tobytes(), digest_size=16).digest(), band_keys(signature(found, bands * rows), bands).tolist()

        return lambda texts: zip(*map(one, texts))

    source = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(F.col(text)).alias("h"), F.col(text).alias("body"))
    return common.extend_rows(source, added, compute, ["body"]).drop("body")


def overlap(p, q) -> int:
    """The size of the intersection of two sorted sets."""
    import numpy as np

    if len(p) < len(q):
        p, q = q, p
    at = np.searchsorted(p, q)
    at[at == len(p)] = 0
    return int((p[at] == q).sum())


def scored(pairs: DataFrame, sets: DataFrame, percent: int = PERCENT) -> DataFrame:
    """The pairs (a, b) with their Jaccard distance d and whether they are linked, by their full sets."""
    wide = pairs.join(sets.select(F.col("rep").alias("b"), F.col("set").alias("set_b")), "b").join(sets.select(F.col("rep").alias("a"), F.col("set").alias("set_a")), "a")

    def check(batches):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            a, b, x, y = (batch.column(i) for i in range(4))
            away, linked = [], []
            for i in range(batch.num_rows):
                p, q = np.frombuffer(x[i].as_buffer(), dtype=np.uint64), np.frombuffer(y[i].as_buffer(), dtype=np.uint64)
                both = overlap(p, q)
                union = len(p) + len(q) - both
                away.append(1 - both / union)
                linked.append(100 * both >= percent * union)
            yield pa.RecordBatch.from_arrays([a, b, pa.array(away, pa.float64()), pa.array(linked, pa.bool_())], names=["a", "b", "d", "linked"])

    return wide.select("a", "b", "set_a", "set_b").mapInArrow(check, "a long, b long, d double, linked boolean")


def settle(frame, percent: int = PERCENT):
    """Links that join different components among one bucket's members, or between two blocks of them.

    Jaccard distance is a metric, so two members whose distances to the pivot differ by more than a link allows
    need no comparison; nor do members that a link has joined meanwhile, or whose sizes rule a link out.
    """
    import numpy as np
    import pandas as pd

    frame = frame.sort_values(["d", "rep"])
    reps, n, away, comp, block = (frame[c].to_numpy() for c in ("rep", "n", "d", "comp", "block"))
    two = frame["left"].iloc[0] != frame["right"].iloc[0]
    sets = [np.frombuffer(x, dtype=np.uint64) for x in frame["set"]]
    top: dict[int, int] = {}

    def find(i: int) -> int:
        while top.setdefault(i, i) != i:
            top[i] = top[top[i]]
            i = top[i]
        return i

    reach = 1 - percent / 100 + 1e-9
    ends = np.searchsorted(away, away + reach, side="right")
    out = []
    for i in range(len(reps)):
        j = np.arange(i + 1, ends[i])
        near = 100 * np.minimum(n[j], n[i]) >= percent * np.maximum(n[j], n[i])
        if two:
            near &= block[j] != block[i]
        for j in j[near & (comp[j] != comp[i])].tolist():
            p, q = find(int(comp[i])), find(int(comp[j]))
            if p == q:
                continue
            both = overlap(sets[i], sets[j])
            if 100 * both >= percent * (len(sets[i]) + len(sets[j]) - both):
                top[max(p, q)] = min(p, q)
                out.append((int(reps[i]), int(reps[j])))
    return pd.DataFrame(out, columns=["a", "b"]).astype("int64")


def class_sets(docs: DataFrame, needed: DataFrame, id_col: str, text: str, width: int) -> DataFrame:
    """(rep, set) of the needed classes (rep, doc_id, h), from the text that their first document has."""
    source = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(F.col(text)).alias("h"), F.col(text).alias("body"))
    met = source.join(needed.hint("merge"), ["doc_id", "h"]).select("rep", "body")  # grows with the corpus: never broadcast

    def run(batches):
        import pyarrow as pa

        last = None
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                reps, sets = [], []
                for rep, body in zip(part.column(0).to_pylist(), part.column(1)):
                    if rep != last:  # equal rows come one after the other, and one of them is enough
                        reps.append(rep)
                        sets.append(shingle_set(body.as_py(), width).tobytes())
                    last = rep
                yield pa.RecordBatch.from_arrays([pa.array(reps, pa.int64()), pa.array(sets, pa.binary())], names=["rep", "set"])

    return met.mapInArrow(run, "rep long, set binary")


def link_classes(classes: DataFrame, docs: DataFrame, id_col: str, text: str, width: int, percent: int, given: DataFrame | None = None) -> DataFrame:
    """Components (node, comp) of the classes (rep, doc_id, h, n, bands) that have a link, one of their own or a given one."""
    buckets = classes.select("rep", "n", F.explode("bands").alias("key"))
    pivots = buckets.groupBy("key").agg(F.min("rep").alias("pivot"), F.count("*").alias("m")).where("m > 1")
    members = common.staged(buckets.join(pivots, "key").select("key", "rep", "n", "pivot", "m"), "minhash-members")
    needed = classes.select("rep", "doc_id", "h").join(members.select("rep").distinct(), "rep", "left_semi")
    sets = common.staged(class_sets(docs, needed, id_col, text, width), "minhash-sets")
    pairs = members.where("rep <> pivot").select(F.col("pivot").alias("a"), F.col("rep").alias("b")).distinct()
    stars = common.staged(scored(pairs, sets, percent), "minhash-stars")
    links = stars.where("linked").select("a", "b")
    links = links if given is None else links.union(given)
    comps = common.staged(connected(links), "minhash-comps")
    held = members.join(stars.select(F.col("a").alias("pivot"), F.col("b").alias("rep"), "d"), ["pivot", "rep"], "left").join(comps.select(F.col("node").alias("rep"), "comp"), "rep", "left")
    held = common.staged(held.select("key", "rep", "n", "m", F.expr("if(rep = pivot, 0D, d)").alias("d"), F.coalesce("comp", "rep").alias("comp")), "minhash-held")
    split = held.groupBy("key").agg(F.min("comp").alias("low"), F.max("comp").alias("high")).where("low <> high").select("key")
    still = held.join(split, "key")
    # a member of a small bucket stays only if one of another component is near enough in distance to the pivot
    reach = f"{1 - percent / 100 + 1e-9}D"
    near = f"OVER (PARTITION BY key ORDER BY d RANGE BETWEEN {reach} PRECEDING AND {reach} FOLLOWING)"
    small = still.where(f"m <= {SMALL}").withColumn("low", F.expr(f"min(comp) {near}")).withColumn("high", F.expr(f"max(comp) {near}")).where("low <> high").drop("low", "high")
    still = common.staged(small.unionByName(still.where(f"m > {SMALL}")), "minhash-open")
    # of buckets with the same members one is enough
    alike = still.groupBy("key").agg(F.sum(F.expr("cast(xxhash64(rep) as decimal(38,0))")).alias("mark"), F.count("*").alias("left_m"))
    once = alike.groupBy("mark", "left_m").agg(F.min("key").alias("key"))
    parted = still.join(once, "key").withColumn("blocks", F.expr(f"cast(ceil(left_m / {BLOCK}D) as int)")).withColumn("block", F.expr("cast(pmod(xxhash64(rep, 3), blocks) as int)"))
    dealt = parted.withColumn("other", F.expr("explode(sequence(0, blocks - 1))")).select("key", "rep", "n", "d", "comp", "block", F.least("block", "other").alias("left"), F.greatest("block", "other").alias("right"))
    settled = dealt.join(sets, "rep").groupBy("key", "left", "right").applyInPandas(lambda frame: settle(frame, percent), "a long, b long")
    return common.staged(connected(links.union(settled)), "minhash-comps")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text: str = "text", width: int = WIDTH, percent: int = PERCENT, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id, kept."""
    coded = common.staged(signatures(docs, id_col, text, width, bands, rows), "minhash-signatures")
    worded = coded.where("n_shingles > 0 AND doc_id IS NOT NULL")
    classes = worded.groupBy("digest").agg(F.min(F.struct("doc_id", "h")).alias("first"), F.count("*").alias("copies"), F.any_value("n_shingles").alias("n"), F.any_value("bands").alias("bands"))
    classes = common.staged(classes.select(F.monotonically_increasing_id().alias("rep"), "digest", "first.doc_id", "first.h", "copies", "n", "bands"), "minhash-classes")
    # ids with several texts link these texts' classes
    several = worded.groupBy("doc_id").agg(F.min("digest").alias("low"), F.max("digest").alias("high")).where("low <> high").select("doc_id")
    of = worded.select("doc_id", "digest").distinct().join(several, "doc_id").join(classes.select("digest", "rep"), "digest").select("doc_id", "rep")
    given = of.join(of.groupBy("doc_id").agg(F.min("rep").alias("a")), "doc_id").where("a <> rep").select("a", F.col("rep").alias("b"))
    comps = link_classes(classes, docs, id_col, text, width, percent, None if several.isEmpty() else common.staged(given, "minhash-given"))
    # only classes of several documents or with links move a document's component
    held = classes.select("digest", "rep", "doc_id", "copies").join(comps.select(F.col("node").alias("rep"), "comp"), "rep", "left").where("copies > 1 OR comp IS NOT NULL")
    least = held.where("comp IS NOT NULL").groupBy("comp").agg(F.min("doc_id").alias("least"))
    moved = held.join(least, "comp", "left").select("digest", F.coalesce("least", "doc_id").alias("comp"))
    out = coded.select("doc_id", "n_shingles", "digest").join(moved, "digest", "left")
    component = F.expr("CASE WHEN doc_id IS NOT NULL THEN coalesce(comp, doc_id) END")
    return out.select("doc_id", "n_shingles", component.alias("component_id")).withColumn("kept", F.coalesce(F.expr("doc_id = component_id"), F.lit(True)))


def drop_near_duplicates(docs: DataFrame, **options) -> DataFrame:
    """The rows of ``docs`` that are kept, with their own columns; of rows with one id all stay or go."""
    id_col = options.get("id_col", "doc_id")
    gone = near_duplicates(docs, **options).where("NOT kept").select(F.col("doc_id").alias(id_col)).distinct()
    return docs.join(gone.hint("merge"), id_col, "left_anti").select(*docs.columns)  # grows with the corpus


def op3_minhash(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))

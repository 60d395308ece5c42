"""Benchmark decontamination: a hash set of the benchmark's word windows, scanned over every document.

Words are runs of digits, ASCII letters (lower-cased) and non-ASCII bytes.  An item gives all its windows of
``width`` words, or one window when it is shorter.  A window of word hashes that is found in the set is
verified word by word against the items it may come from.  The set, sorted hashes with places in the items'
words, is broadcast when it takes at most ``index_bytes``, which is known before anything is collected; beyond
that, window hashes of both sides meet in a shuffle join and are verified as well, with the same result.

Defined cases: very long texts are read whole; null or wordless texts have no words and no hits; wordless items have no windows; an item
without an id counts as the item ``null``; repeated items count once; repeated documents are judged row by
row; an empty benchmark contaminates nothing.
"""

from __future__ import annotations

import hashlib
import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common

WORD = rb"[^\x00-\x2f\x3a-\x60\x7b-\x7f]+"
WIDTH = 13
INDEX_BYTES = 64 << 20
#: What the index takes at most for a word: its bytes apart, its hash, a window's hash and place, an offset.
WORD_COST = 96
MULTIPLIER = 0x9E3779B97F4A7C15
ADDED = [("n_words", T.LongType()), ("n_hit", T.LongType()), ("item_ids", T.ArrayType(T.StringType())), ("spans", T.ArrayType(T.ArrayType(T.LongType())))]


def words_of(text: str | None) -> list[bytes]:
    return re.findall(WORD, text.encode("utf-8", "surrogatepass").lower()) if text else []


def windows_of(words: list[bytes], width: int) -> list[tuple[bytes, ...]]:
    if not words:
        return []
    n = min(width, len(words))
    return [tuple(words[i : i + n]) for i in range(len(words) - n + 1)]


def word_hashes(words: list[bytes]):
    import numpy as np
    from xxhash import xxh64_intdigest

    return np.fromiter(map(xxh64_intdigest, words), dtype=np.uint64, count=len(words))


def build_index(items: list[tuple[object, str | None]], width: int = WIDTH) -> dict:
    """names of the items, their words, the sorted word hashes, and by window length the sorted window hashes with their places."""
    import numpy as np

    names, texts, known, found = [], [], [], {}
    for item, text in items:
        words = words_of(text)
        if not words:
            continue
        hashes, size = word_hashes(words), min(width, len(words))
        starts = np.arange(len(words) - size + 1)
        at = found.setdefault(size, ([], [], []))
        at[0].append(window_hashes(hashes[starts[:, None] + np.arange(size)]))
        at[1].append(np.full(len(starts), len(names), dtype=np.int32))
        at[2].append(starts.astype(np.int32))
        known.append(np.unique(hashes))
        names.append("null" if item is None else str(item))
        # one string of words and where each begins
        texts.append((b" ".join(words), np.cumsum([0, *(len(w) + 1 for w in words)], dtype=np.int32)))
    windows = {}
    for size, parts in found.items():
        hashes, owner, start = (np.concatenate(p) for p in parts)
        order = np.argsort(hashes, kind="stable")
        windows[size] = (hashes[order], owner[order], start[order])
    return {"names": names, "texts": texts, "words": np.unique(np.concatenate(known)) if known else np.zeros(0, np.uint64), "windows": windows}


def window_hashes(table):
    """One hash for each row of word hashes."""
    import numpy as np

    with np.errstate(over="ignore"):
        h = np.zeros(len(table), dtype=np.uint64)
        for column in table.T:
            h = (h ^ column) * np.uint64(MULTIPLIER)
            h ^= h >> np.uint64(29)
    return h


def scan(words: list[bytes], index: dict) -> tuple[int, int, list[str], list[list[int]]]:
    """(words, words hit, sorted items, hit spans as [first word, end]) of one document."""
    import numpy as np

    n = len(words)
    ids, known = word_hashes(words), index["words"]
    hit, items = np.zeros(n + 1, dtype=np.int32), set()
    here = known[np.minimum(np.searchsorted(known, ids), len(known) - 1)] == ids if len(known) else np.zeros(n, dtype=bool)
    unknown = np.concatenate([[0], np.cumsum(~here)])
    for size, (hashes, owner, start) in index["windows"].items():
        if n < size:
            continue
        starts = np.flatnonzero(unknown[size:] == unknown[:-size])
        if not len(starts):
            continue
        tables = window_hashes(ids[starts[:, None] + np.arange(size)])
        low, high = np.searchsorted(hashes, tables), np.searchsorted(hashes, tables, side="right")
        for k in np.flatnonzero(low < high).tolist():
            i = int(starts[k])
            own, same = b" ".join(words[i : i + size]), False
            for j in range(int(low[k]), int(high[k])):
                text, offsets = index["texts"][owner[j]]
                if text[offsets[start[j]] : offsets[start[j] + size] - 1] == own:
                    items.add(index["names"][owner[j]])
                    same = True
            if same:
                hit[i] += 1
                hit[i + size] -= 1
    inside = np.cumsum(hit[:-1]) > 0
    edges = np.flatnonzero(np.diff(np.concatenate([[0], inside.view(np.int8), [0]])))
    return n, int(inside.sum()), sorted(items), edges.reshape(-1, 2).tolist()


def scan_documents(docs: DataFrame, benchmark: DataFrame, text: str = "text", item: str = "item_id", item_text: str = "text", width: int = WIDTH, index_bytes: int = INDEX_BYTES) -> DataFrame:
    """Every row of ``docs`` with n_words, n_hit, item_ids (sorted) and spans (word offsets)."""
    spark = docs.sparkSession
    items = benchmark.select(F.col(item).cast("string").alias("item"), F.col(item_text).cast("string").alias("body"))
    # an upper bound of the index, from the numbers of bytes and words
    words = F.size(F.regexp_extract_all("body", F.lit(r"[0-9A-Za-z\x{80}-\x{10ffff}]+"), F.lit(0)))
    size = items.distinct().agg(F.sum(F.coalesce(F.octet_length("body") + words * WORD_COST, F.lit(0)) + 256)).first()[0] or 0
    if size > index_bytes:
        return scan_by_join(docs, items, text, width)
    index = spark.sparkContext.broadcast(build_index([tuple(r) for r in items.distinct().collect()], width))

    def compute():
        found = index.value
        return lambda texts: zip(*(scan(words_of(t), found) for t in texts))

    return common.extend_rows(docs, ADDED, compute, [text])


def scan_by_join(docs: DataFrame, items: DataFrame, text: str, width: int = WIDTH) -> DataFrame:
    """The same result where the benchmark is too large to broadcast: windows of both sides meet by hash.

    Texts stay where they are; only hashed windows move, those of documents with the place they start at.  Hits
    come back to their document with the item's words, and count if these stand there.
    """
    keyed = common.staged(docs.withColumn("__row", F.monotonically_increasing_id()), "decontaminate-docs")
    shapes = "size int, h1 long, h2 long"

    def digests(words: list[bytes], sizes):
        for size in sizes:
            for i in range(len(words) - size + 1):
                d = hashlib.blake2b(b" ".join(words[i : i + size]), digest_size=16).digest()
                yield size, i, int.from_bytes(d[:8], "little", signed=True), int.from_bytes(d[8:], "little", signed=True)

    def item_windows(frames):
        import pandas as pd

        for f in frames:
            rows = []
            for it, body in zip(f["item"], f["body"]):
                w = words_of(body)
                rows += [(None if pd.isna(it) else it, s, a, b, b" ".join(w[i : i + s])) for s, i, a, b in digests(w, [min(width, len(w))] if w else [])]
            yield pd.DataFrame(rows, columns=["item", "size", "h1", "h2", "words"])

    windows = items.mapInPandas(item_windows, f"item string, {shapes}, words binary").select(F.coalesce("item", F.lit("null")).alias("item"), "size", "h1", "h2", "words").distinct()
    windows = common.staged(windows, "decontaminate-windows")
    sizes = sorted(r[0] for r in windows.select("size").distinct().collect())

    def doc_windows(frames):
        import pandas as pd

        for f in frames:
            for row, body in zip(f["__row"], f["body"]):
                got = list(digests(words_of(body), sizes))
                for at in range(0, len(got), 50_000):
                    yield pd.DataFrame([(row, *x) for x in got[at : at + 50_000]], columns=["__row", "size", "at", "h1", "h2"])

    hits = keyed.select("__row", F.col(text).alias("body")).mapInPandas(doc_windows, "__row long, size int, at long, h1 long, h2 long").join(windows, ["size", "h1", "h2"])
    per = hits.groupBy("__row").agg(F.collect_set(F.struct("at", "size", "item", "words")).alias("__hits"))
    joined = keyed.join(per, "__row", "left").drop("__row")

    def compute():
        def work(texts, hits):
            import numpy as np

            out = []
            for t, spans in zip(texts, hits):
                words, names = words_of(t), set()
                n = len(words)
                mark = np.zeros(n + 1, dtype=np.int32)
                for s in spans or []:
                    if b" ".join(words[s["at"] : s["at"] + s["size"]]) == bytes(s["words"]):
                        names.add(s["item"])
                        mark[s["at"]] += 1
                        mark[s["at"] + s["size"]] -= 1
                inside = np.cumsum(mark[:-1]) > 0
                edges = np.flatnonzero(np.diff(np.concatenate([[0], inside.view(np.int8), [0]])))
                out.append((n, int(inside.sum()), sorted(names), edges.reshape(-1, 2).tolist()))
            return zip(*out)

        return work

    return common.extend_rows(joined, ADDED, compute, [text, "__hits"]).drop("__hits")


CONTAMINATED = "n_hit > 0 AND 20 * n_hit >= n_words"


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The rows of ``docs`` that the contamination rule leaves, with their own columns."""
    return scan_documents(docs, benchmark, **options).where(f"NOT ({CONTAMINATED})").select(*docs.columns)


def cut_spans(docs: DataFrame, benchmark: DataFrame, text: str = "text", **options) -> DataFrame:
    """The same rows, with every hit word run cut out of the text (bytes from its first to its last word)."""

    def compute():
        def work(texts, spans):
            out = []
            for t, runs in zip(texts, spans):
                if not t or not runs:
                    out.append(t)
                    continue
                raw = t.encode("utf-8", "surrogatepass")
                found = [m.span() for m in re.finditer(WORD, raw.lower())]
                keep, at = [], 0
                for a, b in runs:
                    keep.append(raw[at : found[a][0]])
                    at = found[b - 1][1]
                out.append(b"".join([*keep, raw[at:]]).decode("utf-8", "replace"))
            return (out,)

        return work

    judged = scan_documents(docs, benchmark, text=text, **options)
    return common.extend_rows(judged, [(text, T.StringType())], compute, [text, "spans"]).select(*docs.columns)


def op8_decontaminate(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = scan_documents(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return out.select("doc_id", "n_words", "n_hit", F.size("item_ids").cast("long").alias("n_items"), F.sha2(F.array_join("item_ids", ","), 256).alias("items_sha256"), F.expr(CONTAMINATED).alias("contaminated"))

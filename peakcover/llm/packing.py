"""Lexical retrieval packing: windows filled with the best BM25 neighbours of a seed document.

Documents are encoded, an end id is appended, and whole windows are cut off first.  What is left of each
document goes to a shard (a block of consecutive rows of one partition, bounded in tokens) with its own BM25
inverted index over token ids.  The longest unused rest seeds a window; its ``query_terms`` highest weighted terms
(all with None) query the index, and the unused neighbours fill the window in order of score, as many as it takes
(ranked ``NEIGHBOURS`` at first, all of them if these do not fill it).  The neighbour that would overflow is cut,
and its rest stays in the shard.  So every window is full but the last of a shard, which is cut at powers of
two: such sequences need no padding.  No row is shuffled, and sequence ids are unique by partition.

Defined cases: a very long text is encoded and cut whole, in a shard of its own size; a null text is empty and gives the end id alone; a null id is returned as null; repeated rows
are packed one by one; an empty table gives no pieces; ties of score go to the earlier row.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common

WINDOW = 2048
SHARD_TOKENS = 1_500_000
QUERY_TERMS = 12
NEIGHBOURS = 24
K1, B = 1.2, 0.75


class Shard:
    """A BM25 index over the token ids of its items; ``best`` ranks unused items for a seed."""

    def __init__(self, items: list):
        import numpy as np

        n = self.n = len(items)
        sizes = np.array([len(x) for x in items], dtype=np.int64)
        owner = np.repeat(np.arange(n, dtype=np.int64), sizes)
        tokens = np.concatenate([*items, np.zeros(0, np.uint32)]).astype(np.int64)
        keys, tf = np.unique(tokens * n + owner, return_counts=True) if n else (np.zeros(0, np.int64), np.zeros(0, np.int64))
        term, self.item = keys // max(n, 1), (keys % max(n, 1)).astype(np.int32)
        terms, self.begin, df = np.unique(term, return_index=True, return_counts=True)
        self.end = self.begin + df
        idf = np.log1p((n - df + 0.5) / (df + 0.5))
        norm = K1 * (1 - B + B * sizes / max(1.0, sizes.mean() if n else 1.0))
        row = np.repeat(np.arange(len(terms)), df)
        self.weight = (idf[row] * tf * (K1 + 1) / (tf + norm[self.item])).astype(np.float32)
        self.row = row.astype(np.int32)
        order = np.lexsort((self.row, -self.weight, self.item))
        self.by_item = order
        self.first = np.searchsorted(self.item[order], np.arange(n + 1))
        self.unused = np.ones(n, dtype=bool)

    def best(self, seed: int, count: int | None = NEIGHBOURS, query_terms: int | None = QUERY_TERMS) -> list[int]:
        """Unused items by descending score for the seed's highest weighted terms (ties: the earlier item)."""
        import numpy as np

        last = self.first[seed + 1] if query_terms is None else min(self.first[seed] + query_terms, self.first[seed + 1])
        at = self.by_item[self.first[seed] : last]
        scores = np.zeros(self.n, dtype=np.float32)
        for r in self.row[at].tolist():
            span = slice(self.begin[r], self.end[r])
            scores[self.item[span]] += self.weight[span]
        scores[~self.unused] = 0
        found = np.flatnonzero(scores)
        if count is not None and len(found) > count:
            found = found[np.argpartition(-scores[found], count)[:count]]
        return found[np.lexsort((found, -scores[found]))].tolist()


def fill(sizes: list[int], shard: Shard, window: int = WINDOW, query_terms: int | None = QUERY_TERMS) -> Iterator[list[tuple[int, int, int]]]:
    """Windows as lists of (item, offset in the item, length); all but the last are full."""
    import numpy as np

    at, left = [0] * len(sizes), list(sizes)
    order = np.argsort(-np.array(sizes, dtype=np.int64), kind="stable").tolist()
    place = 0
    pending = None  # the item that was cut by the last window goes first
    while True:
        if pending is None:
            while place < len(order) and not shard.unused[order[place]]:
                place += 1
            if place == len(order):
                return
            pending = order[place]
        seed, pending = pending, None
        shard.unused[seed] = False
        row, room = [(seed, at[seed], left[seed])], window - left[seed]
        spare = None
        for count in (NEIGHBOURS, None):
            near = shard.best(seed, count, query_terms) if room else []
            for x in near:
                if left[x] <= room:
                    row.append((x, at[x], left[x]))
                    room -= left[x]
                    shard.unused[x] = False
                elif spare is None:
                    spare = x
                if not room:
                    break
            # one that overflows will be cut and fills the window; else all neighbours follow
            if not room or spare is not None or len(near) < NEIGHBOURS:
                break
        while room:
            if spare is None or not shard.unused[spare]:
                while place < len(order) and not shard.unused[order[place]]:
                    place += 1
                if place == len(order):
                    break
                spare = order[place]
            take = min(room, left[spare])
            row.append((spare, at[spare], take))
            at[spare] += take
            left[spare] -= take
            room -= take
            if not left[spare]:
                shard.unused[spare] = False
        if spare is not None and shard.unused[spare] and at[spare]:
            pending = spare
        yield row


def at_powers(row: list[tuple[int, int, int]], window: int) -> Iterator[list[tuple[int, int, int]]]:
    """A window as it is if full; else cut into sequences whose lengths are its powers of two."""
    total = sum(x[2] for x in row)
    if total == window:
        yield row
        return
    bit = 1 << total.bit_length() - 1
    out, room, todo = [], bit, list(reversed(row))
    while todo:
        item, start, size = todo.pop()
        take = min(size, room)
        out.append((item, start, take))
        if take < size:
            todo.append((item, start + take, size - take))
        room -= take
        if not room:
            yield out
            total -= bit
            bit = room = 1 << max(0, total.bit_length() - 1)
            out = []


def pack(docs: DataFrame, id_col: str = "doc_id", text: str = "text", window: int = WINDOW, end_id: int = 1, shard_tokens: int = SHARD_TOKENS, tokenizer: tuple[str, str | None] | None = None, with_ids: bool = False, query_terms: int | None = QUERY_TERMS) -> DataFrame:
    """One row per piece: id, start, length, ids_crc32, doc_tokens, sequence_id, offset[, ids as little-endian uint32]."""
    json_path, ranks = tokenizer or common.bpe_paths()
    fields = [T.StructField(id_col, docs.schema[id_col].dataType)] + [T.StructField(n, T.LongType()) for n in ("start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")]
    schema = T.StructType(fields + [T.StructField("ids", T.BinaryType())] * with_ids)

    def run(batches):
        import numpy as np
        import pyarrow as pa
        from pyspark import TaskContext
        from pyspark.sql.pandas.types import to_arrow_schema

        encode = common.token_encoder(json_path, ranks)
        out_schema = to_arrow_schema(schema)
        serial = TaskContext.get().partitionId() << 40

        def packed(block):
            nonlocal serial
            rests = [(i, len(ids) - len(ids) % window) for i, (_, ids) in enumerate(block) if len(ids) % window]
            items = [block[i][1][s:] for i, s in rests]
            whole = ([(i, s, window)] for i, (_, ids) in enumerate(block) for s in range(0, len(ids) - window + 1, window))
            mixed = ([(rests[x][0], rests[x][1] + s, n) for x, s, n in row] for row in fill([len(x) for x in items], Shard(items), window, query_terms))
            rows = []
            for row in (*whole, *mixed):
                for sequence in at_powers(row, window):
                    offset = 0
                    for i, s, n in sequence:
                        raw = block[i][1][s : s + n].astype("<u4").tobytes()
                        rows.append((block[i][0], s, n, zlib.crc32(raw), len(block[i][1]), serial, offset, raw)[: len(out_schema)])
                        offset += n
                    serial += 1
            return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), out_schema)], schema=out_schema)

        block, size = [], 0
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                for key, body in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    ids = encode(body) if body else []
                    ids.append(end_id)
                    block.append((key, np.array(ids, dtype=np.uint32)))
                    size += len(ids)
                    if size >= shard_tokens:
                        yield packed(block)
                        block, size = [], 0
        if block:
            yield packed(block)
        del block
        common.give_back()

    return docs.select(id_col, text).mapInArrow(run, schema)


def padding_share(pieces: DataFrame, window: int = WINDOW) -> DataFrame:
    """tokens, sequences, padding (slots up to the window, none at a power of two) of packed pieces."""
    lengths = pieces.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    pad = F.when(F.expr("bit_count(n) = 1"), F.lit(0)).otherwise(F.lit(window) - F.col("n"))
    return lengths.agg(F.sum("n").alias("tokens"), F.count("*").alias("sequences"), F.sum(pad).alias("padding"))


def op1_packing(spark, sf_dir: str) -> DataFrame:
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"))

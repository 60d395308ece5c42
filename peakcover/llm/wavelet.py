"""Token output as one wavelet matrix per shard: succinct bit planes that give access, counts and positions.

A shard file holds the ids of consecutive documents (ascending id).  Plane by plane, from the highest bit,
the ids' bits are stored in the order that the planes above leave, zeros before ones.  With the count of ones
before each 512-bit block, ``access``, ``rank`` (occurrences before a place), ``count`` (in a range) and
``select`` (the place of the k-th occurrence) need one step per plane, and no other copy of the ids exists.
All sections are compressed on their own inside the one file.

Defined cases: a null text is empty and gives the end id alone; null ids come first; rows with equal ids are
ordered by their content; an empty table writes nothing and reads as no rows.
"""

from __future__ import annotations

import json
import struct
import zlib

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window

from . import common

MAGIC = b"PKWVMX01"
BLOCK = 512
SHARD_TOKENS = 2_000_000
ROWS_PER_RANGE = 4096
MOST_RANGES = 4096


class WaveletMatrix:
    def __init__(self, n: int, planes: list, zeros: list[int]):
        """planes: uint8 arrays of packed bits (little bit order), highest bit first."""
        import numpy as np

        self.n, self.planes, self.zeros = n, planes, zeros
        self.before = []
        for p in planes:
            per = np.add.reduceat(np.bitwise_count(p).astype(np.int64), np.arange(0, len(p), BLOCK // 8)) if len(p) else np.zeros(0, np.int64)
            self.before.append(np.concatenate([[0], np.cumsum(per)]))

    @classmethod
    def build(cls, values, levels: int) -> WaveletMatrix:
        import numpy as np

        planes, zeros, now = [], [], values
        for bit in range(levels - 1, -1, -1):
            ones = (now >> now.dtype.type(bit) & now.dtype.type(1)).view(now.dtype).astype(bool)
            planes.append(np.packbits(ones, bitorder="little"))
            low = now[~ones]
            zeros.append(len(low))
            now = np.concatenate([low, now[ones]])
        return cls(len(values), planes, zeros)

    def bit(self, level: int, i: int) -> int:
        return int(self.planes[level][i >> 3]) >> (i & 7) & 1

    def ones_before(self, level: int, i: int) -> int:
        import numpy as np

        block = i // BLOCK
        total, at = int(self.before[level][block]), block * BLOCK // 8
        total += int(np.bitwise_count(self.planes[level][at : i >> 3]).sum())
        if i & 7:
            total += (int(self.planes[level][i >> 3]) & (1 << (i & 7)) - 1).bit_count()
        return total

    def down(self, level: int, i: int, bit: int) -> int:
        ones = self.ones_before(level, i)
        return self.zeros[level] + ones if bit else i - ones

    def access(self, i: int) -> int:
        value = 0
        for level in range(len(self.planes)):
            b = self.bit(level, i)
            value = value << 1 | b
            i = self.down(level, i, b)
        return value

    def interval(self, value: int, lo: int, hi: int) -> tuple[int, int]:
        for level in range(len(self.planes)):
            b = value >> len(self.planes) - 1 - level & 1
            lo, hi = self.down(level, lo, b), self.down(level, hi, b)
        return lo, hi

    def rank(self, value: int, i: int) -> int:
        """Occurrences of ``value`` before place ``i``."""
        return self.count(value, 0, i)

    def count(self, value: int, lo: int, hi: int) -> int:
        if value >> len(self.planes):
            return 0
        lo, hi = self.interval(value, lo, hi)
        return hi - lo

    def place(self, level: int, bit: int, k: int) -> int:
        """The place of the k-th (from 0) bit of that kind in a plane."""
        import numpy as np

        before = self.before[level]
        ranks = before if bit else np.arange(len(before)) * BLOCK - before
        block = int(np.searchsorted(ranks, k, side="right")) - 1
        bits = np.unpackbits(self.planes[level][block * BLOCK // 8 : (block + 1) * BLOCK // 8], bitorder="little")
        return block * BLOCK + int(np.flatnonzero(bits == bit)[k - int(ranks[block])])

    def select(self, value: int, k: int) -> int:
        """The place of the k-th (from 0) occurrence of ``value``; -1 if there are not so many."""
        if k < 0 or k >= self.count(value, 0, self.n):
            return -1
        i = self.interval(value, 0, self.n)[0] + k
        for level in range(len(self.planes) - 1, -1, -1):
            b = value >> len(self.planes) - 1 - level & 1
            i = self.place(level, b, i - self.zeros[level] if b else i)
        return i

    def values(self):
        """All ids in order, undoing the planes from the lowest."""
        import numpy as np

        now = np.zeros(self.n, dtype=np.uint32)
        for level in range(len(self.planes) - 1, -1, -1):
            ones = np.unpackbits(self.planes[level], count=self.n, bitorder="little").astype(bool)
            up = np.empty_like(now)
            up[~ones] = now[: self.zeros[level]]
            up[ones] = now[self.zeros[level] :] | np.uint32(1 << len(self.planes) - 1 - level)
            now = up
        return now


def dump_shard(keys: list, sizes: list[int], matrix: WaveletMatrix) -> bytes:
    import numpy as np
    import zstandard

    pack = zstandard.ZstdCompressor(level=1).compress
    sections = [pack(json.dumps(keys).encode()), pack(np.array(sizes, dtype="<u8").tobytes())] + [pack(p.tobytes()) for p in matrix.planes]
    head = json.dumps({"n": matrix.n, "zeros": matrix.zeros, "sections": [len(s) for s in sections]}).encode()
    return MAGIC + struct.pack("<I", len(head)) + head + b"".join(sections)


def load_shard(raw: bytes) -> tuple[list, list[int], WaveletMatrix]:
    import numpy as np
    import zstandard

    if raw[:8] != MAGIC:
        raise ValueError("not a wavelet shard")
    unpack = zstandard.ZstdDecompressor().decompress
    size = struct.unpack_from("<I", raw, 8)[0]
    head, at, parts = json.loads(raw[12 : 12 + size]), 12 + size, []
    for n in head["sections"]:
        parts.append(unpack(raw[at : at + n]))
        at += n
    matrix = WaveletMatrix(head["n"], [np.frombuffer(p, dtype=np.uint8) for p in parts[2:]], head["zeros"])
    return json.loads(parts[0]), np.frombuffer(parts[1], dtype="<u8").astype(int).tolist(), matrix


def write_shards(docs: DataFrame, path: str, id_col: str = "doc_id", text: str = "text", end_id: int = 0, vocabulary: int = 50_257, shard_tokens: int = SHARD_TOKENS, tokenizer: tuple[str, str | None] | None = None) -> DataFrame:
    """Encode, order by id and write shard files below ``path``; returns their manifest (path, at, part, docs, tokens)."""
    json_path, ranks = tokenizer or common.bpe_paths()
    levels = max(1, (max(vocabulary, end_id + 1) - 1).bit_length())
    small = levels <= 16
    source = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text).alias("body"))
    ranges = max(1, min(MOST_RANGES, -(-source.select("id").count() // ROWS_PER_RANGE)))
    bounds = source.approxQuantile("id", [i / ranges for i in range(1, ranges)], 1 / (4 * ranges)) if ranges > 1 else []
    # ids go out as 16-bit numbers where they fit: about half the bytes of the text
    coded = T.StructType.fromDDL("id long, at int, ids binary")

    def encode(batches):
        import numpy as np
        import pyarrow as pa

        code, edges = common.token_encoder(json_path, ranks), np.array(sorted(bounds), dtype=np.float64)
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                keys = batch.column(0).slice(at, 256).to_pylist()
                ids = [np.array([*(code(t) if t else ()), end_id], dtype="<u2" if small else "<u4").tobytes() for t in batch.column(1).slice(at, 256).to_pylist()]
                where = [0 if k is None else int(np.searchsorted(edges, float(k), side="right")) for k in keys]
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(where, pa.int32()), pa.array(ids, pa.binary())], names=["id", "at", "ids"])

    written = T.StructType.fromDDL("path string, at int, part int, docs long, tokens long")

    def write(batches):
        import numpy as np
        import pyarrow as pa
        from pyspark import TaskContext

        attempt = TaskContext.get().taskAttemptId()
        fs, root = common.open_store(path)
        fs.create_dir(root, recursive=True)

        def flush(at, part, keys, arrays):
            name = f"{at:05d}-{part:05d}.wavelet"
            joined = np.concatenate(arrays)
            with fs.open_output_stream(f"{root}/.{name}.{attempt}") as f:
                f.write(dump_shard(keys, [len(a) for a in arrays], WaveletMatrix.build(joined, levels)))
            fs.move(f"{root}/.{name}.{attempt}", f"{root}/{name}")
            row = (f"{path}/{name}", at, part, len(keys), len(joined))
            return pa.RecordBatch.from_arrays([pa.array([v], type=t) for v, t in zip(row, (pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.int64()))], names=written.names)

        now, part, keys, arrays, size = None, 0, [], [], 0
        for batch in batches:
            for key, at, raw in zip(*(c.to_pylist() for c in batch.columns)):
                if keys and (at != now or size >= shard_tokens):
                    yield flush(now, part, keys, arrays)
                    part, keys, arrays, size = part + 1 if at == now else 0, [], [], 0
                now = at
                keys.append(key)
                arrays.append(np.frombuffer(raw, dtype="<u2" if small else "<u4"))
                size += len(arrays[-1])
        if keys:
            yield flush(now, part, keys, arrays)

    dealt = source.mapInArrow(encode, coded).repartitionById(ranges, F.col("at")).sortWithinPartitions("at", F.asc_nulls_first("id"), "ids")
    return common.staged(dealt.mapInArrow(write, written), "wavelet-manifest")


def read_shards(manifest: DataFrame, id_col: str = "doc_id", with_ids: bool = False) -> DataFrame:
    """One row per document: id, start (ids of all documents before it), n_tokens, ids_crc32[, ids]."""
    spark = manifest.sparkSession
    per_range = manifest.groupBy("at").agg(F.sum("tokens").alias("total"))  # MOST_RANGES rows at most
    base = per_range.select("at", (F.sum("total").over(Window.orderBy("at")) - F.col("total")).alias("base"))
    inside = F.sum("tokens").over(Window.partitionBy("at").orderBy("part")) - F.col("tokens")
    files = manifest.withColumn("inside", inside).join(F.broadcast(base), "at").select("path", (F.col("base") + F.col("inside")).alias("start"))
    fields = [T.StructField(n, T.LongType()) for n in (id_col, "start", "n_tokens", "ids_crc32")]
    schema = T.StructType(fields + [T.StructField("ids", T.BinaryType())] * with_ids)

    def read(batches):
        import numpy as np
        import pyarrow as pa
        from pyspark.sql.pandas.types import to_arrow_schema

        kinds = to_arrow_schema(schema)
        for batch in batches:
            for path, start in zip(*(c.to_pylist() for c in batch.columns)):
                fs, place = common.open_store(path)
                with fs.open_input_stream(place, compression=None) as f:
                    keys, sizes, matrix = load_shard(f.read())
                ids, rows, at = matrix.values().astype("<u4"), [], 0
                for key, n in zip(keys, sizes):
                    raw = ids[at : at + n].tobytes()
                    rows.append((key, start + at, n, zlib.crc32(raw), raw)[: len(kinds)])
                    at += n
                yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), kinds)], schema=kinds)

    parts = max(spark.sparkContext.defaultParallelism, min(10_000, manifest.count() // 4))
    return files.repartition(parts).mapInArrow(read, schema)


def op4_wavelet(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return read_shards(write_shards(docs, common.fresh_path(spark, "wavelet")))

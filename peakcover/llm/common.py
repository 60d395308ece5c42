"""What the operators of this subpackage share: written tables, worker caches, words and token ids."""

from __future__ import annotations

import sys
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

#: Text in these characters is cut alike by both byte-level tokenizer libraries.
PLAIN_TEXT = "[^\\t\\n\\r\\x20-\\x7e\\xa1-\\u024f]|<\\|"


def shared_root(spark: SparkSession) -> str:
    """The folder that the driver and all executors see; one of our own only where the session names none (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        root = held.get() if held.isDefined() else None
    if not root:
        if not spark.sparkContext.master.split("[")[0] == "local":
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors see")
        root = "file://" + tempfile.mkdtemp(prefix="peakcover-")
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"


def staged(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage ends there, and a lost executor loses nothing."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def worker_cache(key: object, make: Callable[[], object]) -> object:
    """An object kept by the Python worker process from task to task."""
    kept = sys.__dict__.setdefault("_peakcover_worker_cache", {})
    if key not in kept:
        if len(kept) > 16:
            kept.clear()
        kept[key] = make()
    return kept[key]


def give_back() -> None:
    """Return freed memory of a worker to the system, as workers stay for later tasks."""
    import ctypes
    import gc

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except OSError:
        pass


def open_store(uri: str):
    """(pyarrow file system, path) for a URI of the shared folder, on the driver or an executor."""
    from pyarrow import fs

    if "://" not in uri and not uri.startswith("file:"):
        return fs.LocalFileSystem(), uri
    if uri.startswith("file:"):
        return fs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    return fs.FileSystem.from_uri(uri)


def extend_rows(df: DataFrame, added: list[tuple[str, T.DataType]], compute: Callable, inputs: list[str]) -> DataFrame:
    """All columns of ``df`` and the added ones, which ``compute(*lists of the input columns)`` makes batch by batch.

    An added column takes the place of an input column of the same name.
    """
    from pyspark.sql.pandas.types import to_arrow_type

    names = {n for n, _ in added}
    kept = [f for f in df.schema.fields if f.name not in names]
    schema = T.StructType(kept + [T.StructField(n, t, True) for n, t in added])
    where = [df.columns.index(c) for c in inputs]
    keep = [i for i, f in enumerate(df.schema.fields) if f.name not in names]
    arrow = [to_arrow_type(t) for _, t in added]
    labels = [f.name for f in schema.fields]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = compute()
        try:
            for batch in batches:
                for at in range(0, batch.num_rows, 512):
                    part = batch.slice(at, 512)
                    got = work(*(part.column(i).to_pylist() for i in where))
                    cols = [part.column(i) for i in keep] + [pa.array(v, type=t) for v, t in zip(got, arrow)]
                    yield pa.RecordBatch.from_arrays(cols, names=labels)
        finally:
            del work
            give_back()

    return df.mapInArrow(run, schema)


def bpe_paths() -> tuple[str, str]:
    """Default places of the public byte-level vocabulary: the tokenizer file, and the same ranks."""
    import public_tokenizers as P

    return P.path("byte_bpe_50k.json"), P.path("byte_bpe_50k.tiktoken")


def token_encoder(json_path: str, ranks_path: str | None = None) -> Callable[[str], list[int]]:
    """A function from a whole text to its ids, as ``tokenizers`` gives them without special tokens.

    The rank form of the same vocabulary encodes texts of plain characters several times faster and gives
    the same ids; all other texts, and any text where a special token could be spelled, go to the tokenizer file.
    """

    def make():
        import os
        import re

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        if ranks_path is None:
            whole = Tokenizer.from_file(json_path)
            return lambda text: whole.encode(text, add_special_tokens=False).ids
        import base64

        import public_tokenizers as P
        import tiktoken

        with open(ranks_path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        fast = tiktoken.Encoding("ranks", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
        del ranks
        odd, slow = re.compile(PLAIN_TEXT), []

        def encode(text: str) -> list[int]:
            if odd.search(text):
                if not slow:  # many tasks never need it
                    slow.append(Tokenizer.from_file(json_path))
                return slow[0].encode(text, add_special_tokens=False).ids
            return fast.encode_ordinary(text)

        return encode

    return worker_cache(("bpe", json_path, ranks_path), make)

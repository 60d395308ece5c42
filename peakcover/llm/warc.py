"""WARC archives: a writer with payload revisits, and a sequential reader.

Every record is one gzip member.  The reader inflates members incrementally (nothing is held but the record
at hand), frames each record by its content length and verifies block and payload digests.  A revisit holds
only the HTTP headers of its page, whose content length is that of the full payload.

Defined cases: a null html is an empty payload; a null url gives no target header; a null page id reads back
as null and never becomes the record that others refer to while another id is there; of rows with one id and
one payload each smallest one is a response; characters that would break a header line are percent-encoded;
an empty table writes no archive and reads as no rows.
"""

from __future__ import annotations

import base64
import hashlib
import zlib
from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common

VERSION = b"WARC/1.1"
DATE = "2020-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
ARCHIVE_BYTES = 256 << 20
MIN_PAYLOAD = 0
CHUNK = 1 << 20
READ = T.StructType([T.StructField("page_id", T.LongType()), T.StructField("url", T.StringType()), T.StructField("record_type", T.StringType()), T.StructField("payload_bytes", T.LongType()), T.StructField("payload_digest", T.StringType()), T.StructField("refers_to", T.LongType()), T.StructField("payload", T.BinaryType())])


def base32_sha1(raw: bytes) -> str:
    return base64.b32encode(hashlib.sha1(raw).digest()).decode()


def one_line(value: str) -> str:
    return "".join(c if c >= " " and c != "\x7f" else "".join(f"%{b:02X}" for b in c.encode("utf-8", "surrogatepass")) for c in value)


def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None, is_revisit: bool) -> bytes:
    """One record as a gzip member."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if is_revisit else http + payload
    name = lambda x: "<urn:page:" + ("" if x is None else str(x)) + ">"
    head = [("WARC-Type", "revisit" if is_revisit else "response"), ("WARC-Record-ID", name(page_id)), ("WARC-Date", DATE)]
    head += [("WARC-Target-URI", one_line(url))] if url is not None else []
    head += [("WARC-Profile", PROFILE), ("WARC-Refers-To", name(refers_to))] if is_revisit else []
    head += [("Content-Type", "application/http; msgtype=response"), ("WARC-Payload-Digest", f"sha1:{base32_sha1(payload)}"), ("WARC-Block-Digest", f"sha1:{base32_sha1(block)}"), ("Content-Length", str(len(block)))]
    raw = VERSION + b"\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head).encode("utf-8", "surrogatepass") + b"\r\n" + block + b"\r\n\r\n"
    packer = zlib.compressobj(6, zlib.DEFLATED, 31)
    return packer.compress(raw) + packer.flush()


def members(stream) -> Iterator[bytes]:
    """The inflated members of a gzip file, one after the other."""
    held = b""
    while True:
        held = held or stream.read(CHUNK)
        if not held:
            return
        inflater, parts = zlib.decompressobj(31), []
        while not inflater.eof:
            parts.append(inflater.decompress(held or stream.read(CHUNK)))
            held = inflater.unused_data if inflater.eof else b""
            if not inflater.eof and not parts[-1]:
                more = stream.read(CHUNK)
                if not more:
                    raise ValueError("the archive ends inside a member")
                held = more
        yield b"".join(parts)


def headers(raw: bytes) -> dict[str, str]:
    return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in raw.decode("utf-8", "surrogatepass").split("\r\n")[1:])}


def page_of(name: str | None) -> int | None:
    inner = (name or "").removeprefix("<urn:page:").removesuffix(">")
    return int(inner) if inner else None


def parse(raw: bytes) -> tuple:
    """A record's row; raises if its framing or a digest is wrong."""
    head, gap, rest = raw.partition(b"\r\n\r\n")
    fields = headers(head)
    size = int(fields["content-length"])
    block = rest[:size]
    if not gap or not head.startswith(b"WARC/") or len(block) != size or rest[size:] != b"\r\n\r\n":
        raise ValueError("a record is not framed by its content length")
    if fields["warc-block-digest"] != f"sha1:{base32_sha1(block)}":
        raise ValueError("a block digest differs")
    http, _, payload = block.partition(b"\r\n\r\n")
    kind, digest = fields["warc-type"], fields["warc-payload-digest"].removeprefix("sha1:")
    if kind == "response" and digest != base32_sha1(payload):
        raise ValueError("a payload digest differs")
    length = len(payload) if kind == "response" else int(headers(http)["content-length"])
    return page_of(fields["warc-record-id"]), fields.get("warc-target-uri"), kind, length, digest, page_of(fields.get("warc-refers-to")), payload if kind == "response" else None


def mark_revisits(pages: DataFrame, min_payload: int = MIN_PAYLOAD) -> DataFrame:
    """page_id, url, html, refers_to: the smallest id with the same payload, where it is another's.

    Only groups of two or more take part in the join; its page side can be split where one payload is common.
    """
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))
    keyed = rows.withColumn("digest", F.unhex(F.sha1("html")))
    firsts = keyed.where(F.octet_length("html") >= min_payload).groupBy("digest").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).where("n > 1").select("digest", "first")
    return keyed.join(firsts, "digest", "left").select("page_id", "url", "html", F.expr("CASE WHEN first IS NOT NULL AND (page_id IS NULL OR page_id <> first) THEN first END").alias("refers_to"))


def write_archives(pages: DataFrame, path: str, min_payload: int = MIN_PAYLOAD, archive_bytes: int = ARCHIVE_BYTES) -> DataFrame:
    """Write archives below ``path`` in the shared folder; returns their manifest (path, records, bytes)."""
    manifest = T.StructType.fromDDL("path string, records long, bytes long")

    def write(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        task = TaskContext.get()
        fs, root = common.open_store(path)
        fs.create_dir(root, recursive=True)
        out, part, count, size, place = None, 0, 0, 0, ""

        def close():
            out.close()
            name = f"part-{task.partitionId():06d}-{part:04d}.warc.gz"
            fs.move(place, f"{root}/{name}")
            return pa.RecordBatch.from_arrays([pa.array([f"{path}/{name}"]), pa.array([count], pa.int64()), pa.array([size], pa.int64())], names=manifest.names)

        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                for page, url, html, first in zip(*(c.to_pylist() for c in batch.slice(at, 256).columns)):
                    if out is None:
                        place = f"{root}/.part-{task.partitionId()}-{part}-{task.taskAttemptId()}"
                        out = fs.open_output_stream(place, compression=None)
                    raw = record(page, url, html.encode("utf-8", "surrogatepass"), first, first is not None)
                    out.write(raw)
                    count, size = count + 1, size + len(raw)
                    if size >= archive_bytes:
                        yield close()
                        out, part, count, size = None, part + 1, 0, 0
        if out is not None:
            yield close()

    return common.staged(mark_revisits(pages, min_payload).mapInArrow(write, manifest), "warc-manifest")


def read_archives(paths: DataFrame, with_payload: bool = True) -> DataFrame:
    """One row per record of the archives named in the column ``path``, one archive after the other in each task."""
    schema = READ if with_payload else T.StructType(READ.fields[:-1])

    def read(batches):
        import pyarrow as pa
        from pyspark.sql.pandas.types import to_arrow_schema

        kinds = to_arrow_schema(schema)
        batch_of = lambda rows: pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), kinds)], schema=kinds)
        for batch in batches:
            for path in batch.column(0).to_pylist():
                fs, place = common.open_store(path)
                rows, size = [], 0
                with fs.open_input_stream(place, compression=None) as stream:
                    for raw in members(stream):
                        rows.append(parse(raw)[: len(kinds)])
                        size += len(raw) if with_payload else 100
                        if size > 8 << 20:
                            yield batch_of(rows)
                            rows, size = [], 0
                if rows:
                    yield batch_of(rows)

    files = paths.select("path")
    return files.repartition(max(1, min(10_000, files.count()))).mapInArrow(read, schema)


def op2_warc(spark, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    archives = write_archives(pages, common.fresh_path(spark, "warc"))
    return read_archives(archives, with_payload=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")

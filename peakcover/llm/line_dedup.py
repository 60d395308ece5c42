"""Line dedup by the shortest windows of lines, in DataFrame operations only.

A unit is the shortest window of two or more lines and ``unit_bytes`` bytes that starts at a line, or that ends at
one; it depends on its own lines alone.  Whatever repeats over two or more lines and ``unit_bytes`` is a union of
units, each of which repeats as well, so it is found wherever it stands.  So is every line of ``solo_bytes``.
Such units that occur twice or more anywhere are compared byte by byte (their lines' texts under each line
hash, and their line hashes under each unit hash); the first occurrence by (id, line) stays, the lines of the others go.

Only hashes move until a unit is known to repeat; the texts move once, to meet their documents' candidates.

Defined cases: null texts stay null and have no lines; units neither start nor end with a blank line (spaces
only); an occurrence that overlaps the first one stays; rows
with a null id are returned unchanged and remove nothing; rows that share an id are one document, and lines go
only where the row's own lines match; a text all of whose lines go is empty; an empty table gives no rows;
should two different texts ever share a hash, no occurrence of that hash is removed; columns of any name pass
through; passages below ``unit_bytes`` in all, and lines alone below ``solo_bytes``, stay (both are parameters).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

SOLO_BYTES = 120
UNIT_BYTES = 40
NEAR_LINES = 64


def let(name: str, value: str, body: str) -> str:
    """``body`` with ``name`` bound to ``value``, which is computed once for the row."""
    return f"element_at(transform(array({value}), {name} -> {body}), 1)"


def sequence_hash(hashes: str) -> str:
    """SQL for the hash of a unit from its lines' hashes."""
    return f"xxhash64({hashes})"


def units_of(text: str = "body", solo_bytes: int = SOLO_BYTES, unit_bytes: int = UNIT_BYTES) -> str:
    """SQL for a text's units: array of (h, i: first line from 0, n: lines)."""
    lines = f"transform(split({text}, '\\n', -1), l -> named_struct('h', xxhash64(l), 'solo', octet_length(l) >= {solo_bytes}, 'b', octet_length(trim(l))))"
    full = f"s.t >= {unit_bytes} AND s.n >= 2"
    run = f"aggregate({{part}}, named_struct('t', 0, 'n', 0), (s, z) -> if({full}, s, named_struct('t', s.t + z.b, 'n', s.n + 1)))"

    def shortest(near: str, whole: str) -> str:
        """The lines that a window takes; the whole text is read only if the nearest lines are too short."""
        far = let("s", run.format(part=whole), f"if({full}, s.n, NULL)")
        return let("s", run.format(part=near), f"if({full}, s.n, {far})")

    forth = f"if(i + 1 < size(c.hs) AND c.hs[i].b + get(c.hs, i + 1).b >= {unit_bytes}, 2, {shortest(f'slice(c.hs, i + 1, {NEAR_LINES})', 'slice(c.hs, i + 1, size(c.hs))')})"
    back = shortest(f"reverse(slice(c.hs, greatest(i + 2 - {NEAR_LINES}, 1), least(i + 1, {NEAR_LINES})))", "reverse(slice(c.hs, 1, i + 1))")
    starting = f"transform(filter(c.at, i -> c.hs[i].b > 0), i -> named_struct('i', i, 'n', {forth}))"
    # two lines that suffice are the window that starts at the first of them
    ending = f"transform(filter(c.at, i -> i > 0 AND c.hs[i].b > 0 AND get(c.hs, i - 1).b + c.hs[i].b < {unit_bytes}), i -> {let('n', back, chr(39).join(['named_struct(', 'i', ', i + 1 - n, ', 'n', ', n)']))})"
    solo = f"transform(filter(c.at, i -> c.hs[i].solo AND c.hs[i].b >= {unit_bytes}), i -> named_struct('i', i, 'n', 1))"
    unit = "named_struct('h', " + sequence_hash("transform(slice(c.hs, w.i + 1, w.n), z -> z.h)") + ", 'i', w.i, 'n', w.n)"
    found = f"transform(filter(concat({starting}, {ending}, {solo}), w -> w.n IS NOT NULL), w -> {unit})"
    return let("q", lines, let("c", "named_struct('hs', q, 'at', sequence(0, size(q) - 1))", found))


def kept_text(text: str, gone: str) -> str:
    """SQL for the text without the lines of ``gone``, an array of (i, n)."""
    left = "array_except(sequence(0, size(v.lines) - 1), v.gone)"
    places = f"flatten(transform({gone}, g -> sequence(g.i, g.i + g.n - 1)))"
    return let("v", f"named_struct('lines', split({text}, '\\n', -1), 'gone', {places})", f"array_join(transform({left}, i -> v.lines[i]), '\\n')")


def mark_repeats(docs: DataFrame, id_col: str = "doc_id", text: str = "text", **sizes: int) -> DataFrame:
    """All rows of ``docs`` with ``__gone``: the (i, n) of their repeated units that are not the first occurrence."""
    units = docs.where(F.col(id_col).isNotNull() & F.col(text).isNotNull()).select(F.col(id_col).alias("__id"), F.expr(f"explode({units_of(f'`{text}`', **sizes)})").alias("u")).select("__id", "u.h", "u.i", "u.n")
    repeated = units.groupBy("h").agg(F.min(F.struct("__id", "i")).alias("first"), F.count("*").alias("c")).where("c > 1").select("h", "first")
    hits = units.join(repeated, "h").groupBy("__id").agg(F.collect_list(F.struct("h", "i", "n", F.expr("__id = first.__id AND i < first.i + n").alias("stays"))).alias("__hits"))
    own = sequence_hash("transform(slice(v.l, x.i + 1, x.n), z -> xxhash64(z))") + " = x.h"
    checked = let("v", f"named_struct('l', split(`{text}`, '\\n', -1))", f"filter(__hits, x -> x.i + x.n <= size(v.l) AND {own})")
    met = docs.join(hits.withColumnRenamed("__id", id_col), id_col, "left").select(*docs.columns, F.expr(f"CASE WHEN size(__hits) > 0 THEN {checked} END").alias("__hits"))
    met = common.staged(met, "line-dedup")
    hit = met.where("size(__hits) > 0")
    split_lines = f"named_struct('l', split(`{text}`, '\\n', -1))"
    # a unit is its sequence of line hashes, and a line hash is one text: both are checked, so a line moves once
    covered = let("v", split_lines, "transform(array_distinct(flatten(transform(__hits, x -> sequence(x.i, x.i + x.n - 1)))), i -> v.l[i])")
    lines = hit.select(F.explode(F.expr(covered)).alias("bytes")).groupBy(F.xxhash64("bytes").alias("line"), "bytes").agg(F.count("*").alias("c"))
    odd_lines = common.staged(lines.groupBy("line").agg(F.count("*").alias("texts")).where("texts > 1").select("line"), "line-dedup-lines")
    sequences = let("v", split_lines, "transform(__hits, x -> named_struct('h', x.h, 'seq', transform(slice(v.l, x.i + 1, x.n), z -> xxhash64(z))))")
    seqs = hit.select(F.explode(F.expr(sequences)).alias("b")).select("b.h", "b.seq").groupBy("h", "seq").agg(F.count("*").alias("c"))
    odd_units = common.staged(seqs.groupBy("h").agg(F.count("*").alias("texts")).where("texts > 1").select("h"), "line-dedup-units")
    if not (odd_lines.isEmpty() and odd_units.isEmpty()):
        through = seqs.select("h", F.explode("seq").alias("line")).join(odd_lines, "line").select("h")
        rows = hit.select(F.col(id_col).alias("__id"), F.explode("__hits").alias("x")).select("__id", F.col("x.h").alias("h"))
        unsafe = rows.join(odd_units.union(through).distinct(), "h").groupBy("__id").agg(F.collect_set("h").alias("__unsafe")).withColumnRenamed("__id", id_col)
        met = met.join(unsafe, id_col, "left").withColumn("__hits", F.expr("filter(__hits, x -> __unsafe IS NULL OR NOT array_contains(__unsafe, x.h))")).drop("__unsafe")
    return met.select(*docs.columns, F.expr("transform(filter(__hits, x -> NOT x.stays), x -> named_struct('i', x.i, 'n', x.n))").alias("__gone"))


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text: str = "text", counts: tuple[str, str] = ("n_lines", "n_removed"), **sizes: int) -> DataFrame:
    """All rows of ``docs``, the text without repeated lines, and two counts (n_lines, n_removed) in place of columns of their names."""
    held = [c for c in docs.columns if c != text and c not in counts]
    # columns of any name pass through as one
    rest = F.struct(*(F.col(f"`{c}`") for c in held)).alias("__rest")
    marked = mark_repeats(docs.select(F.col(f"`{id_col}`").alias("__doc"), F.col(f"`{text}`").alias("__text"), rest), "__doc", "__text", **sizes)
    places = "size(array_distinct(flatten(transform(__gone, g -> sequence(g.i, g.i + g.n - 1)))))"
    removed = F.expr(f"CASE WHEN size(__gone) > 0 THEN {places} ELSE 0 END").cast("long")
    total = F.expr("CASE WHEN __text IS NULL THEN 0 ELSE octet_length(__text) - octet_length(replace(__text, '\\n', '')) + 1 END").cast("long")
    fresh = F.expr(f"CASE WHEN size(__gone) > 0 THEN {kept_text('__text', '__gone')} ELSE __text END")
    return marked.select(*(F.col("__rest").getField(c).alias(c) for c in held), fresh.alias(text), total.alias(counts[0]), removed.alias(counts[1]))


def op10_line_dedup(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return dedup_lines(docs).select("doc_id", "n_lines", "n_removed", "text")

"""Point, interval and sequence views over the given tables, with the same views as SQL text.

Every view prunes to the columns it needs, so only those reach the Parquet scan.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EVENT_LIFE_DAYS = 2
FIRST_EVENT_DAY, FIRST_ORDER_DAY = "2024-01-01", "1995-01-01"
LENGTHS = (0, 7, 30, 90, 365)
RECTANGLES = ((1, 40, 40), (2, 80, 20), (3, 100, 100))

#: The views as DuckDB text, for oracles.
SQL = {
    "part_pts": "SELECT p_partkey AS id, CAST(10 * p_size AS BIGINT) AS x, CAST(round(10 * (p_retailprice - 900)) AS BIGINT) AS y, CAST(1 AS BIGINT) AS w, p_brand AS color, p_type AS kind FROM part",
    "cust_pts": "SELECT c_custkey AS id, CAST(round(c_acctbal) AS BIGINT) AS x, CAST(100 * coalesce(n, 0) AS BIGINT) AS y, CAST(coalesce(cents, 0) AS BIGINT) AS w, c_nationkey AS color FROM customer LEFT JOIN (SELECT o_custkey, count(*) AS n, sum(CAST(round(100 * o_totalprice) AS BIGINT)) AS cents FROM orders GROUP BY o_custkey) ON o_custkey = c_custkey",
    "event_pts": f"SELECT event_id AS id, (epoch_us(ts) - epoch_us(TIMESTAMP '{FIRST_EVENT_DAY}')) / 60000000.0 AS x, value AS y, CAST(1 AS BIGINT) AS w, user_id AS color FROM events",
    "order_days": f"SELECT CAST(date_diff('day', DATE '{FIRST_ORDER_DAY}', CAST(o_orderdate AS DATE)) AS BIGINT) AS pos, CAST(round(100 * o_totalprice) AS BIGINT) AS w FROM orders",
    "event_ticks": "SELECT epoch_us(ts) AS pos FROM events",
    "doc_pts": "SELECT doc_id AS id, n_chars / 10.0::DOUBLE AS x, 10.0::DOUBLE * (length(text) - length(replace(text, chr(10), ''))) AS y, CAST(1 AS BIGINT) AS w, source AS color FROM documents",
    "doc_len": "SELECT CAST(n_chars AS BIGINT) AS pos FROM documents",
    "doc_signed": "SELECT CAST(n_chars AS BIGINT) AS pos, CAST(quality - 2 * toxic AS BIGINT) AS w FROM documents JOIN labels USING (doc_id)",
    "seq_a": "SELECT CAST(n_nationkey AS INTEGER) AS i, CAST(coalesce(sum(CAST(round(100 * c_acctbal) AS BIGINT)), 0) AS BIGINT) AS v FROM nation LEFT JOIN customer ON c_nationkey = n_nationkey GROUP BY 1",
    "seq_b": "SELECT CAST(n_nationkey AS INTEGER) AS i, CAST(coalesce(sum(CAST(round(100 * s_acctbal) AS BIGINT)), 0) AS BIGINT) AS v FROM nation LEFT JOIN supplier ON s_nationkey = n_nationkey GROUP BY 1",
    "update_log": f"SELECT row_number() OVER (ORDER BY t_us, op, id) AS round, * FROM (SELECT epoch_us(ts) AS t_us, 'insert' AS op, event_id AS id, ts, value, 1 AS sign FROM events UNION ALL SELECT epoch_us(ts) + {EVENT_LIFE_DAYS} * 86400000000, 'delete', event_id, ts, value, -1 FROM events)",
}
for _name in ("a", "b"):
    SQL[f"seq_{_name}_c"] = f"SELECT i, v - (SELECT CAST(round(avg(v)) AS BIGINT) FROM ({SQL[f'seq_{_name}']})) AS v FROM ({SQL[f'seq_{_name}']})"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cents(column: str):
    return F.round(100 * F.col(column)).cast("long")


def part_pts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), (F.col("p_size") * 10).cast("long").alias("x"), F.round(10 * (F.col("p_retailprice") - 900)).cast("long").alias("y"), F.lit(1).cast("long").alias("w"), F.col("p_brand").alias("color"), F.col("p_type").alias("kind"))


def cust_pts(spark: SparkSession, sf_dir: str) -> DataFrame:
    spent = table(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("*").alias("n"), F.sum(cents("o_totalprice")).alias("cents"))
    rows = table(spark, sf_dir, "customer").select("c_custkey", "c_acctbal", "c_nationkey").join(spent, "c_custkey", "left")
    return rows.select(F.col("c_custkey").alias("id"), F.round("c_acctbal").cast("long").alias("x"), (100 * F.coalesce("n", F.lit(0))).cast("long").alias("y"), F.coalesce("cents", F.lit(0)).cast("long").alias("w"), F.col("c_nationkey").alias("color"))


def line_pts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select((F.col("l_orderkey") * 10 + F.col("l_linenumber")).alias("id"), (F.col("l_quantity") * 20).alias("x"), (F.col("l_extendedprice") / 100).alias("y"), F.col("l_quantity").cast("long").alias("w"), F.col("l_suppkey").alias("color"))


def minutes(ts: str = "ts"):
    return (F.unix_micros(F.col(ts).cast("timestamp")) - F.expr(f"unix_micros(timestamp'{FIRST_EVENT_DAY} 00:00:00+00:00')")) / F.lit(60000000.0)


def event_pts(spark: SparkSession, sf_dir: str, color: str = "user_id") -> DataFrame:
    return table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), minutes().alias("x"), F.col("value").alias("y"), F.lit(1).cast("long").alias("w"), F.col(color).alias("color"))


def event_json_pts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events weighted by the number in their JSON properties (0 without)."""
    weight = F.coalesce(F.get_json_object("props", "$.k").cast("long"), F.lit(0))
    return table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), minutes().alias("x"), F.col("value").alias("y"), weight.alias("w"), F.col("event_type").alias("color"))


def emb_pts(spark: SparkSession, sf_dir: str, dim: int) -> DataFrame:
    pos = F.transform(F.slice("embedding", 1, dim), lambda v: v.cast("double"))
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), pos.alias("pos"), F.lit(1).cast("long").alias("w"), F.col("label").alias("color"))


def doc_pts(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = F.length("text") - F.length(F.replace("text", F.lit("\n"), F.lit("")))
    return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), (F.col("n_chars") / 10).alias("x"), (10.0 * lines).alias("y"), F.lit(1).cast("long").alias("w"), F.col("source").alias("color"))


def page_hosts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages by size of html, with the url's host as colour."""
    return table(spark, sf_dir, "pages").select(F.col("page_id").alias("id"), F.length("html").cast("long").alias("pos"), F.regexp_extract("url", "://([^/?#]*)", 1).alias("color"))


def order_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select(F.datediff(F.col("o_orderdate").cast("date"), F.lit(FIRST_ORDER_DAY).cast("date")).cast("long").alias("pos"), cents("o_totalprice").alias("w"))


def event_ticks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select(F.unix_micros(F.col("ts").cast("timestamp")).alias("pos"), F.lit(1).cast("long").alias("w"))


def doc_len(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select(F.col("n_chars").cast("long").alias("pos"), F.lit(1).cast("long").alias("w"))


def doc_signed(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = table(spark, sf_dir, "labels").select("doc_id", (F.col("quality") - 2 * F.col("toxic")).cast("long").alias("w"))
    return table(spark, sf_dir, "documents").select("doc_id", F.col("n_chars").cast("long").alias("pos")).join(labels, "doc_id").select("pos", "w")


def sequence_of(spark: SparkSession, sf_dir: str, which: str, centred: bool = False) -> DataFrame:
    """(i, v): cents of balance by nation, zero filled; ``which`` is customer or supplier; centred: less the rounded mean."""
    p = which[0]
    rows = table(spark, sf_dir, which).groupBy(F.col(f"{p}_nationkey").alias("n_nationkey")).agg(F.sum(cents(f"{p}_acctbal")).alias("s"))
    out = table(spark, sf_dir, "nation").select("n_nationkey").join(rows, "n_nationkey", "left").select(F.col("n_nationkey").cast("int").alias("i"), F.coalesce("s", F.lit(0)).cast("long").alias("v"))
    if not centred:
        return out
    mean = out.agg(F.round(F.avg("v")).cast("long").alias("m"))
    return out.crossJoin(F.broadcast(mean)).select("i", (F.col("v") - F.col("m")).alias("v"))


def long_sequence(spark: SparkSession, sf_dir: str, status: str, buckets: int) -> DataFrame:
    """(i, v): cents of orders of a status by equal day buckets, zero filled."""
    days = table(spark, sf_dir, "orders").where(F.col("o_orderstatus") == status).select(F.datediff(F.col("o_orderdate").cast("date"), F.lit(FIRST_ORDER_DAY).cast("date")).alias("day"), cents("o_totalprice").alias("c"))
    sums = days.groupBy(F.expr(f"cast(least({buckets - 1}, day * {buckets} div 2405) as int)").alias("i")).agg(F.sum("c").alias("s"))
    return spark.range(buckets).select(F.col("id").cast("int").alias("i")).join(sums, "i", "left").select("i", F.coalesce("s", F.lit(0)).cast("long").alias("v"))


def update_log(spark: SparkSession, sf_dir: str, days: int = EVENT_LIFE_DAYS) -> DataFrame:
    """(round, at, op, id, x, y, w, sign): every event is inserted at its time and deleted ``days`` later."""
    from ..operators.ordering import numbered

    life = days * 86_400_000_000
    rows = event_pts(spark, sf_dir).select("id", "x", "y", "w").join(table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), F.unix_micros(F.col("ts").cast("timestamp")).alias("at")), "id")
    both = rows.select("id", "x", "y", "w", F.explode(F.array(F.struct(F.col("at"), F.lit("insert").alias("op"), F.lit(1).alias("sign")), F.struct((F.col("at") + life).alias("at"), F.lit("delete").alias("op"), F.lit(-1).alias("sign")))).alias("u")).select("u.at", "u.op", "id", "x", "y", "w", "u.sign")
    return numbered(both, ["at", "op", "id"], "round")


def length_table(spark: SparkSession, lengths=LENGTHS) -> DataFrame:
    return spark.createDataFrame([(i, int(v)) for i, v in enumerate(lengths)], "q_id int, length long")


def read_points(spark: SparkSession, path: str, form: str, schema: str = "id long, x double, y double, w long, color string") -> DataFrame:
    """Points from Parquet, CSV (with a header) or JSON under an explicit schema; rows with a NaN coordinate fail later checks."""
    reader = spark.read.schema(schema)
    return reader.option("header", True).csv(path) if form == "csv" else reader.format(form).load(path)


def write_answers(df: DataFrame, path: str, by: str | None = None) -> None:
    """Answers or sample depths as Parquet, partitioned by grid where that is asked for."""
    writer = df.write.mode("overwrite")
    (writer.partitionBy(by) if by else writer).parquet(path)

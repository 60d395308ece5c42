"""The deepest sample over a stream of updates.

Sample depths are signed sums, so late or reordered updates inside the watermark end in the right state.  Every
micro-batch emits the samples it changed; a table of changes, newest batch last, holds the current depths.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import geometry as G
from ..operators.ball import BallPlan, sample_hits
from ..plans.staging import shared_root

UPDATE_SCHEMA = "round long, at timestamp, op string, id long, x double, y double, w long"


def read_updates(spark: SparkSession, path: str, form: str = "parquet", files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(UPDATE_SCHEMA).option("maxFilesPerTrigger", files_per_batch).format(form).load(path)


def unrepeated(updates: DataFrame, delay: str = "3 days") -> DataFrame:
    """Each (id, op) once within the watermark, so a replayed file changes nothing."""
    return updates.withWatermark("at", delay).dropDuplicatesWithinWatermark(["id", "op"])


def sample_sums(updates: DataFrame, radius: float, p: BallPlan) -> DataFrame:
    """Streaming aggregate (g, k.., j, depth); state is one number for each sample that an update has touched."""
    rows = updates.select("x", "y", (F.col("w") * F.expr("if(op = 'insert', 1, -1)")).alias("dw"))
    return sample_hits(G.to_dual(rows, radius, ["x", "y"]), p, ["dw"]).groupBy(*p.cell, "j").agg(F.sum("dw").alias("depth"))


def run(updates: DataFrame, radius: float, p: BallPlan, path: str, available_now: bool = True):
    """Start the stream; every batch's changes go to ``path``/changes.  Returns the query."""
    writer = sample_sums(updates, radius, p).writeStream.outputMode("update").option("checkpointLocation", f"{path}/checkpoint")
    # a batch that is run again replaces its own folder, so the table is the same after a restart
    sink = lambda batch, i: batch.write.mode("overwrite").parquet(f"{path}/changes/batch={i}")
    writer = writer.foreachBatch(sink)
    return (writer.trigger(availableNow=True) if available_now else writer.trigger(processingTime="10 seconds")).start()


def current(spark: SparkSession, path: str, p: BallPlan) -> DataFrame:
    """(g, k.., j, depth): the newest depth of every sample, those that fell back to 0 left out."""
    rows = spark.read.parquet(f"{path}/changes")
    return rows.groupBy(*p.cell, "j").agg(F.max_by("depth", "batch").alias("depth")).where("depth <> 0")


def current_best(spark: SparkSession, path: str, p: BallPlan) -> DataFrame:
    return current(spark, path, p).agg(F.max("depth").alias("depth"))


def replayed(log: DataFrame, radius: float, p: BallPlan, files: int = 4) -> DataFrame:
    """A log written as files and read as a stream to its end: the final sample depths."""
    spark = log.sparkSession
    import uuid

    path = f"{shared_root(spark)}/ball-stream-{uuid.uuid4().hex}"
    rows = log.select("round", F.timestamp_micros("at").alias("at"), "op", "id", F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y"), F.col("w").cast("long").alias("w"))
    rows.repartitionByRange(files, "round").write.parquet(f"{path}/updates")
    run(unrepeated(read_updates(spark, f"{path}/updates"), "365 days"), radius, p, path).awaitTermination()
    return current(spark, path, p)


def sliding_hotspots(events: DataFrame, width: str = "2 days", step: str = "12 hours", delay: str = "1 day") -> DataFrame:
    """(start, color, n): events of each colour in sliding windows; works on streams and tables."""
    return events.withWatermark("ts", delay).groupBy(F.window("ts", width, step).alias("win"), "color").agg(F.count("*").alias("n")).select(F.col("win.start").alias("start"), "color", "n")


def sessions(events: DataFrame, gap: str = "6 hours", delay: str = "1 day") -> DataFrame:
    """(color, start, n): each colour's sessions."""
    return events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("win"), "color").agg(F.count("*").alias("n")).select("color", F.col("win.start").alias("start"), "n")


def as_of(answers: DataFrame, asked: DataFrame, at: str = "round") -> DataFrame:
    """For every asked time the newest answer not after it, by one sorted pass over range blocks' union."""
    both = answers.select(F.col(at), F.struct(*[c for c in answers.columns if c != at]).alias("a"), F.lit(None).cast("long").alias("q")).unionByName(asked.select(F.col(at), F.lit(None).cast("long").alias("q")).withColumn("q", F.col(at)), allowMissingColumns=True)
    # answers of one block of times go on to the next by a carried last answer: blocks are few, rows are not
    blocked = both.withColumn("block", F.expr(f"{at} div 1024"))
    inside = Window.partitionBy("block").orderBy(F.col(at), F.col("q").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    last = blocked.where("a IS NOT NULL").groupBy("block").agg(F.max_by("a", at).alias("end"))
    carried = last.unionByName(blocked.select("block").distinct(), allowMissingColumns=True).groupBy("block").agg(F.any_value("end", True).alias("end"))
    carry = carried.select("block", F.last("end", True).over(Window.partitionBy(F.lit(0)).orderBy("block").rowsBetween(Window.unboundedPreceding, -1)).alias("before"))
    found = blocked.withColumn("now", F.last("a", True).over(inside)).where("q IS NOT NULL").join(carry, "block")
    return found.select(F.col(at), F.coalesce("now", "before").alias("a")).select(at, "a.*")

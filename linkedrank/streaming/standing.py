"""Standing queries over a feed of change files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkedrank.operators import maintain
from linkedrank.sources import shared_folder


def _saved(spark: SparkSession, folder: str) -> dict[str, int]:
    """Last batch id of each saved query."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs, out = path.getFileSystem(spark._jsc.hadoopConfiguration()), {}
    if fs.exists(path):
        for q in fs.listStatus(path):
            ids = [int(b.getPath().getName()) for b in fs.listStatus(q.getPath()) if fs.exists(spark._jvm.org.apache.hadoop.fs.Path(b.getPath(), "_SUCCESS"))]
            if ids:
                out[q.getPath().getName()] = max(ids)
    return out


def run_standing(spark: SparkSession, states: dict[str, maintain.State], folder: str, schema: str, relation: str, checkpoint: str | None = None) -> dict[str, maintain.State]:
    """Apply all change files of one relation (seq, op, key, text, links) to several queries.

    Each micro-batch is netted once, for all queries. A query's state is saved under its batch id once the batch is
    done, next to the stream's own checkpoint; after a restart each query goes on from its last saved state
    and skips batches that it has seen, so a replayed batch is applied once. Reports of the answers' differences are
    written under the same id. Late changes take part by their seq.
    """
    where = checkpoint or f"{shared_folder(spark)}/stream-{relation}-{'-'.join(sorted(states))}"
    saved = _saved(spark, f"{where}/states")
    for name, batch_id in saved.items():
        if name in states:
            s = states[name]
            states[name] = maintain.load(spark, f"{where}/states/{name}/{batch_id}", s.schema, s.query, s.config)

    def handle(batch: DataFrame, batch_id: int) -> None:
        todo = [n for n in states if saved.get(n, -1) < batch_id]
        if not todo or batch.isEmpty():
            return
        net = maintain.netted({relation: batch})
        for name in todo:
            states[name], report = maintain.apply(states[name], {relation: batch}, net)
            report.write.mode("overwrite").parquet(f"{where}/reports/{name}/{batch_id}")
            states[name].save(f"{where}/states/{name}/{batch_id}")
            saved[name] = batch_id

    q = (spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(folder)
         .writeStream.foreachBatch(handle).option("checkpointLocation", f"{where}/stream").trigger(availableNow=True).start())
    q.awaitTermination()
    return states


def report_sink(spark: SparkSession, where: str, name: str) -> DataFrame:
    """All reports that ``run_standing`` wrote for a query, with their batch ids."""
    return spark.read.parquet(f"{where}/reports/{name}/*").withColumn("batch", F.element_at(F.split(F.col("_metadata.file_path"), "/"), -2).cast("long"))


def first_changes(changes: DataFrame, late: str = "2 days") -> DataFrame:
    """A stream of changes without repeated ones: a (key, seq) counts once within the watermark."""
    return changes.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).dropDuplicatesWithinWatermark(["key", "seq"])


def change_counts(events: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "2 days") -> DataFrame:
    """Changes per window and type; ``ts`` is cast, since watermarks refuse zone-less timestamps."""
    e = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    return e.groupBy(F.window("ts", width, slide or width).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")

"""Boxes over streams: keys on ingest, standing boxes, windows of hits, running counters."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from zbox.operators.joins import level_of_table, opened_at
from zbox.sources.scratch import scratch
from zbox.sources.ztable import add_key
from zbox.spec import ZSpec


def tag_boxes(rows: DataFrame, pieces: DataFrame, spec: ZSpec, residual=None) -> DataFrame:
    """Rows of a stream (or batch) with the box_id of every standing box they are in. The pieces are a
    static table, opened into prefixes and broadcast: standing boxes are few and bounded by the caller."""
    keyed = add_key(rows, spec)
    at = level_of_table(pieces)
    level = at[0] if at else 0
    own = keyed.withColumn("prefix", F.shiftrightunsigned("z", level))
    hit = own.join(F.broadcast(opened_at(pieces, level)), "prefix").filter((F.col("z") >= F.col("z_lo")) & (F.col("z") <= F.col("z_hi")))
    hit = hit.drop("prefix", "piece", "z_lo", "z_hi")
    return hit if residual is None else hit.filter(residual)


def windowed_hits(tagged: DataFrame, ts: str, size: str, slide: str | None = None, delay: str | None = None) -> DataFrame:
    """Hits per box and window; ``delay`` sets the watermark of a stream."""
    t = tagged.withWatermark(ts, delay) if delay else tagged
    w = F.window(ts, size, slide) if slide else F.window(ts, size)
    return t.groupBy(w.alias("w"), "box_id").agg(F.count("*").alias("hits")).select(F.col("w.start").alias("start"), "box_id", "hits")


def session_hits(tagged: DataFrame, ts: str, gap: str, key: str, delay: str | None = None) -> DataFrame:
    t = tagged.withWatermark(ts, delay) if delay else tagged
    return t.groupBy(F.session_window(ts, gap).alias("w"), key).agg(F.count("*").alias("hits")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), key, "hits")


def run_once(df: DataFrame, mode: str = "append", key: tuple[str, ...] = ()) -> DataFrame:
    """Drives a bounded stream to its end into files below the shared folder, and reads them. In complete and
    update mode every micro-batch is written in a folder of its own: of complete results the last one counts,
    of updates the last row of each ``key``. A batch that is run again overwrites its own folder."""
    spark, path = df.sparkSession, scratch(df.sparkSession, "stream")
    spark.createDataFrame([], df.schema).write.parquet(f"{path}/rows/batch=-1")  # a stream without rows has a result too

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/rows/batch={number}")

    q = df.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    schema = StructType([*df.schema.fields, StructField("batch", LongType())])
    rows = spark.read.schema(schema).option("basePath", f"{path}/rows").parquet(f"{path}/rows")
    if mode == "complete":
        last = rows.agg(F.max("batch")).first()[0]
        return rows.filter(F.col("batch") == (last if last is not None else -1)).drop("batch")
    if mode == "update":
        others = [c for c in df.columns if c not in key]
        last = rows.groupBy(*key).agg(F.max_by(F.struct(*others), "batch").alias("last"))
        return last.select(*key, *(F.col(f"last.{c}").alias(c) for c in others))
    return rows.drop("batch")


def append_to_z_table(df: DataFrame, spec: ZSpec, path: str, checkpoint: str, files: int = 4):
    """A sink: every micro-batch is clustered by itself and appended."""
    from zbox.sources.ztable import append_z

    return df.writeStream.foreachBatch(lambda batch, _: append_z(batch, spec, path, files)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def running_counts(tagged: DataFrame):
    """Running number of hits per (box, user), kept in state: a row per key and micro-batch."""
    import pandas as pd
    from pyspark.sql.streaming import StatefulProcessor

    class Count(StatefulProcessor):
        def init(self, handle):
            self.n = handle.getValueState("n", "n long")

        def handleInputRows(self, key, rows, timerValues):
            n = (self.n.get()[0] if self.n.exists() else 0) + sum(len(r) for r in rows)
            self.n.update((n,))
            yield pd.DataFrame({"box_id": [key[0]], "user_id": [key[1]], "hits": [n]})

        def close(self):
            pass

    return tagged.groupBy("box_id", "user_id").transformWithStateInPandas(Count(), "box_id long, user_id long, hits long", "Update", "none")

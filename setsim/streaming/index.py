"""Incremental similarity join for micro-batches, and an online inverted index with expiry."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from setsim.functions.spec import SimSpec
from setsim.operators.verify import finish


def _written(spark, path: str) -> bool:
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark._jsc.hadoopConfiguration()).exists(target)


def incremental_join(batch: DataFrame, batch_id: int, index_path: str, spec: SimSpec) -> DataFrame:
    """New similar pairs of a batch of long sets ``(sid, tok)``: new with stored and new with new; then stores the batch.

    The index is Parquet partitioned by batch id. A batch that is replayed reads only older batches and overwrites its
    own partition, so results and index are the same after a failure.
    """
    spark = batch.sparkSession
    sizes = batch.groupBy("sid").agg(F.count("*").cast("int").alias("n"))
    new = batch.join(sizes, "sid").select("sid", "n", "tok")
    own = f"{index_path}/batch={batch_id}"
    new.write.mode("overwrite").parquet(own)
    new = spark.read.schema("sid long, n int, tok string").parquet(own)
    every = spark.read.schema("sid long, n int, tok string, batch long").parquet(index_path).filter(F.col("batch") <= batch_id)
    r = new.select(F.col("sid").alias("sid_r"), F.col("n").alias("n_r"), "tok")
    s = every.select(F.col("sid").alias("sid_s"), F.col("n").alias("n_s"), "tok", "batch")
    fresh = (F.col("batch") < batch_id) | (F.col("sid_s") < F.col("sid_r"))
    counted = r.join(s, "tok").filter(fresh).groupBy("sid_r", "sid_s").agg(F.min("n_r").alias("n_r"), F.min("n_s").alias("n_s"), F.count("*").cast("int").alias("overlap"))
    return finish(counted, spec, True)


def index_stream(long_sets: DataFrame, index_path: str, result_path: str, checkpoint: str, spec: SimSpec):
    """Run ``incremental_join`` over all available input of a streaming frame of long sets."""

    def each(batch: DataFrame, batch_id: int) -> None:
        incremental_join(batch, batch_id, index_path, spec).write.mode("overwrite").parquet(f"{result_path}/batch={batch_id}")

    return long_sets.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


class TokenIndex(StatefulProcessor):
    """Per token the sets that showed it lately; every arriving set meets those of each of its tokens."""

    def __init__(self, ttl_ms: int):
        self.ttl_ms = ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.postings = handle.getListState("postings", "sid long, n int", ttlDurationMs=self.ttl_ms)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        known = list(self.postings.get())
        for batch in rows:
            for sid, n in zip(batch["sid"].tolist(), batch["n"].tolist(), strict=True):
                met = [(sid, n, other, size) for other, size in known if other != sid]
                if met:
                    yield pd.DataFrame(met, columns=["sid_r", "n_r", "sid_s", "n_s"])
                self.postings.appendValue((sid, n))
                known.append((sid, n))

    def close(self) -> None:
        pass


def online_index(prefix_rows: DataFrame, ttl_ms: int = 86_400_000) -> DataFrame:
    """Meetings ``sid_r, n_r, sid_s, n_s`` of streamed rows ``(tok, sid, n)`` (one per prefix token), state by token with expiry."""
    return prefix_rows.groupBy("tok").transformWithStateInPandas(statefulProcessor=TokenIndex(ttl_ms), outputStructType="sid_r long, n_r int, sid_s long, n_s int", outputMode="Append", timeMode="ProcessingTime")

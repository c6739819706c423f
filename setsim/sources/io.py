"""Readers and writers: any Spark format to long sets, encoded collections as size-bucketed Parquet, bucketed postings."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from setsim.sources.workloads import from_arrays, long_sets


def read_sets(spark: SparkSession, source: str, sid: str, tokens: Column | str, *, format: str = "parquet", schema=None, exploded: bool = False, **options) -> DataFrame:
    """Long sets from Parquet, ORC, CSV, JSON, text or (``format="table"``) a table or view.

    ``tokens`` is an array column, or a scalar column with ``exploded=True`` (one token per row).
    """
    if format == "table":
        df = spark.table(source)
    else:
        reader = spark.read.format(format).options(**options)
        df = (reader.schema(schema) if schema else reader).load(source)
    return long_sets(df, sid, tokens) if exploded else from_arrays(df, sid, F.col(tokens) if isinstance(tokens, str) else tokens)


def size_bucket(n: str = "n") -> Column:
    """Bucket of a size: the position of its highest bit."""
    return F.floor(F.log2(F.col(n) + F.lit(0.5))).cast("int")


def save_collection(sets: DataFrame, path: str, mode: str = "errorifexists") -> None:
    """Encoded sets as Parquet, partitioned by size bucket so that a length filter prunes files."""
    sets.withColumn("bucket", size_bucket()).repartition("bucket", F.pmod(F.col("sid"), F.lit(16))).sortWithinPartitions("n").write.mode(mode).partitionBy("bucket").parquet(path)


def load_collection(spark: SparkSession, path: str, least: int | None = None, largest: int | None = None) -> DataFrame:
    """Encoded sets, limited to sizes that can match (prunes partitions, then row groups)."""
    df = spark.read.parquet(path)
    if least is not None:
        df = df.filter((F.col("bucket") >= max(0, least).bit_length() - 1) & (F.col("n") >= least))
    if largest is not None:
        df = df.filter((F.col("bucket") <= max(1, largest).bit_length() - 1) & (F.col("n") <= largest))
    return df.drop("bucket")


def save_postings(postings: DataFrame, name: str, buckets: int = 64) -> None:
    """Postings as a table bucketed and sorted by token: joins on the token need no exchange."""
    postings.write.bucketBy(buckets, "rank").sortBy("rank").mode("overwrite").saveAsTable(name)


class SyntheticSets(DataSource):
    """``spark.read.format("synthetic_sets")``: random sets with options n, mean, universe, skew, partitions, seed."""

    @classmethod
    def name(cls) -> str:
        return "synthetic_sets"

    def schema(self) -> str:
        return "sid bigint, tok string"

    def reader(self, schema) -> DataSourceReader:
        return _SyntheticReader(self.options)


class _SyntheticReader(DataSourceReader):
    def __init__(self, options):
        self.n, self.mean, self.universe = int(options.get("n", 1000)), float(options.get("mean", 10)), int(options.get("universe", 220))
        self.skew, self.parts, self.seed = float(options.get("skew", 0)), int(options.get("partitions", 4)), int(options.get("seed", 1))

    def partitions(self):
        return [InputPartition(k) for k in range(self.parts)]

    def read(self, partition):
        k = partition.value
        rng = np.random.default_rng([self.seed, k])
        for sid in range(k, self.n, self.parts):
            size = max(1, rng.poisson(self.mean))
            x = rng.random(size)
            toks = np.unique((self.universe**x - 1 if self.skew else x * self.universe).astype(np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(toks), sid)), pa.array([str(t) for t in toks.tolist()])], names=["sid", "tok"])

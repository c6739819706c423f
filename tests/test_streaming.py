"""Streams drained to the end equal their batch forms."""

import time

from pyspark.sql import functions as F

from setsim.functions.spec import SimSpec
from setsim.operators import joins
from setsim.operators.order import prepare
from setsim.sources.workloads import order_parts
from setsim.streaming.index import incremental_join, index_stream, online_index
from setsim.streaming.sets import session_sets, similarity_probe, stream_sets


def test_sets_per_window(spark, tmp_path):
    rows = [(1, "2024-01-01 00:10:00", "a"), (1, "2024-01-01 00:20:00", "b"), (1, "2024-01-01 00:25:00", "b"), (2, "2024-01-01 05:00:00", "a"), (1, "2024-01-02 00:00:00", "c")]
    spark.createDataFrame(rows, "user_id long, ts string, event_type string").withColumn("ts", F.to_timestamp("ts")).write.parquet(str(tmp_path / "events"))
    batch = spark.read.parquet(str(tmp_path / "events"))
    events = spark.readStream.schema(batch.schema).parquet(str(tmp_path / "events"))
    q = stream_sets(events, watermark="1 hour").writeStream.outputMode("complete").format("memory").queryName("w").trigger(availableNow=True).start()
    q.awaitTermination()
    got = {(r.key, str(r.window_start)[:10], tuple(r.tokens)) for r in spark.table("w").collect()}
    assert got == {(1, "2024-01-01", ("a", "b")), (2, "2024-01-01", ("a",)), (1, "2024-01-02", ("c",))}
    assert session_sets(batch, watermark="").count() == 3


def test_incremental_join(spark, sf, tmp_path):
    long = order_parts(spark, sf)
    spec = SimSpec.of("jaccard", "0.5")
    want = {tuple(r) for r in joins.similarity_join(long, threshold="0.5").collect()}
    got = set()
    for k in range(3):
        part = long.filter(F.pmod(F.xxhash64("sid"), F.lit(3)) == k)
        for _ in range(2):  # a replay changes nothing
            found = {tuple(r) for r in incremental_join(part, k, str(tmp_path / "index"), spec).collect()}
        got |= found
    assert got == want
    long.filter("sid % 2 = 0").coalesce(1).write.parquet(str(tmp_path / "in"))
    long.filter("sid % 2 = 1").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("sid long, tok string").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    index_stream(stream, str(tmp_path / "i2"), str(tmp_path / "out"), str(tmp_path / "ck"), spec).awaitTermination()
    assert {tuple(r)[:6] for r in spark.read.parquet(str(tmp_path / "out")).drop("batch").collect()} == want


def test_probe(spark, sf):
    stored = prepare(order_parts(spark, sf))
    spec = SimSpec.of("jaccard", "0.6")
    own = stored.sets.limit(40).select("sid", F.explode("toks").alias("rank")).join(stored.vocab, "rank").groupBy("sid").agg(F.collect_list("tok").alias("tokens"))
    extra = spark.createDataFrame([(-1, ["never seen"])], "sid long, tokens array<string>")
    got = {(r.sid, r.sid_s) for r in similarity_probe(own.unionByName(extra), stored, spec).collect()}
    ids = {r.sid for r in own.select("sid").collect()}
    pairs = {(r.id_l, r.id_r) for r in joins.join_collections(stored, None, spec).collect()}
    assert got == {(a, b) for x, y in pairs for a, b in ((x, y), (y, x)) if a in ids} | {(i, i) for i in ids}


def test_online_index(spark, tmp_path):
    rows = [("a", 1, 2), ("a", 2, 2), ("b", 1, 2), ("c", 3, 1), ("a", 4, 1)]
    spark.createDataFrame(rows, "tok string, sid long, n int").coalesce(1).write.parquet(str(tmp_path / "rows"))
    stream = spark.readStream.schema("tok string, sid long, n int").parquet(str(tmp_path / "rows"))
    conf = "spark.sql.streaming.stateStore.providerClass"
    spark.conf.set(conf, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        q = online_index(stream).writeStream.format("memory").queryName("met").option("checkpointLocation", str(tmp_path / "ck")).start()
        deadline = time.time() + 60
        while time.time() < deadline and not spark.table("met").count():
            time.sleep(1)
        q.stop()
    finally:
        spark.conf.unset(conf)
    got = {frozenset((r.sid_r, r.sid_s)) for r in spark.table("met").collect()}
    assert got == {frozenset(x) for x in ((1, 2), (1, 4), (2, 4))}

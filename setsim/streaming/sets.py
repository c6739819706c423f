"""Sets from event streams and probes of streamed sets against stored ones."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setsim.functions.bitmap import BitmapSpec, attach
from setsim.functions.spec import SimSpec
from setsim.operators.candidates import prefix_postings
from setsim.operators.order import Collection


def stream_sets(events: DataFrame, *, key: str = "user_id", token: str | Column = "event_type", ts: str = "ts", window: str = "1 day", slide: str | None = None, watermark: str = "1 hour") -> DataFrame:
    """Distinct tokens per key and event-time window; late events beyond the watermark are dropped."""
    tok = F.col(token) if isinstance(token, str) else token
    span = F.window(ts, window, slide) if slide else F.window(ts, window)
    live = events.withWatermark(ts, watermark) if watermark else events
    grouped = live.groupBy(span.alias("w"), F.col(key).alias("key")).agg(F.array_sort(F.collect_set(tok.cast("string"))).alias("tokens"))
    return grouped.select("key", F.col("w.start").alias("window_start"), F.col("w.end").alias("window_end"), "tokens", F.size("tokens").alias("n"))


def session_sets(events: DataFrame, *, key: str = "user_id", token: str = "event_type", ts: str = "ts", gap: str = "30 minutes", watermark: str = "1 hour") -> DataFrame:
    """Distinct tokens per key and session."""
    live = events.withWatermark(ts, watermark) if watermark else events
    grouped = live.groupBy(F.session_window(ts, gap).alias("w"), F.col(key).alias("key")).agg(F.array_sort(F.collect_set(F.col(token).cast("string"))).alias("tokens"))
    return grouped.select("key", F.col("w.start").alias("window_start"), F.col("w.end").alias("window_end"), "tokens", F.size("tokens").alias("n"))


def once_per_key(events: DataFrame, keys: list[str], ts: str = "ts", watermark: str = "1 hour") -> DataFrame:
    """Repeated events within the watermark are dropped."""
    return events.withWatermark(ts, watermark).dropDuplicatesWithinWatermark(keys)


def similarity_probe(batch: DataFrame, stored: Collection, spec: SimSpec, *, sid: str = "sid", tokens: str = "tokens") -> DataFrame:
    """Similar stored sets of every set of a micro-batch (use in ``foreachBatch``): ``sid, sid_s, overlap, sim``.

    Only the index side is cut to prefixes: all known tokens of a streamed set probe it, so tokens that the stored
    vocabulary lacks need no place in its order.
    """
    each = batch.select(F.col(sid).alias("sid"), F.array_distinct(tokens).alias("ts")).filter(F.size("ts") > 0)
    ranked = each.select("sid", F.size("ts").alias("n_r"), F.explode("ts").alias("tok")).join(stored.vocab.select("tok", "rank"), "tok")
    index = prefix_postings(stored.sets, spec).select("rank", F.col("sid").alias("sid_s"), F.col("n").alias("n_s"))
    pairs = ranked.join(index, "rank").select("sid", "n_r", "sid_s", "n_s").distinct()
    tokens_s = stored.sets.select(F.col("sid").alias("sid_s"), F.explode("toks").alias("rank"))
    counted = pairs.join(ranked.select("sid", "rank"), "sid").join(tokens_s, ["sid_s", "rank"]).groupBy("sid", "sid_s", "n_r", "n_s").agg(F.count("*").cast("int").alias("overlap"))
    return counted.filter(spec.accepts_col("overlap", "n_r", "n_s")).select("sid", "sid_s", "overlap", spec.sim_col("overlap", "n_r", "n_s").alias("sim"))


def sketch_of(sets: DataFrame, bitmap: BitmapSpec) -> DataFrame:
    """Slim form of encoded sets for a broadcast or a stream-static join: id, size, bitmap words."""
    return attach(sets, bitmap).select("sid", "n", *bitmap.columns)

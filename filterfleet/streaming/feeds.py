"""Streams of memberships: filters kept up to date by micro-batches, windows of filters, one filter a site as state."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession, functions as F

from filterfleet.functions.hashing import positions
from filterfleet.functions.params import FilterSpec
from filterfleet.operators.filters import bit_of, build_filters, union_filters, word_of


def events_stream(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """The events table as a stream; times become zoned ones, which watermarks ask for."""
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def window_filters(events: DataFrame, spec: FilterSpec, length: str = "1 day", slide: str | None = None, late: str | None = None, site: str = "user_id") -> DataFrame:
    """(window start, word_ix, word): one filter of elements for each window; works on batches and streams alike."""
    if late:
        events = events.withWatermark("ts", late)
    frame = F.window("ts", length, slide) if slide else F.window("ts", length)
    bits = events.select(frame.alias("w"), F.explode(positions(F.col(site), spec)).alias("pos"))
    return bits.groupBy(F.col("w.start").alias("start"), word_of("pos").alias("word_ix")).agg(F.bit_or(bit_of("pos")).alias("word"))


class FilterFeed:
    """foreachBatch sink: each batch writes the filters of its own rows; a reader ORs what lies there.

    Every `merge_every` batches what came since the last whole table is OR-ed into a new one, so a batch costs what it
    brings, and a reader opens one whole table and fewer than merge_every small ones. A batch that is delivered again
    writes the same files again, and OR-ing twice changes nothing.
    """

    def __init__(self, path: str, spec: FilterSpec, site: str = "user_id", element: str = "event_id", merge_every: int = 16):
        self.path, self.spec, self.site, self.element, self.merge_every = path, spec, site, element, merge_every

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        fresh = build_filters(batch.select(F.col(self.site).alias("site_id"), F.col(self.element).alias("element")), self.spec)
        fresh.write.mode("overwrite").parquet(f"{self.path}/b{batch_id}")
        if (batch_id + 1) % self.merge_every == 0:
            self._merged(batch.sparkSession, batch_id - self.merge_every, batch_id).write.mode("overwrite").parquet(f"{self.path}/whole{batch_id}")

    def _merged(self, spark: SparkSession, whole: int, last: int) -> DataFrame:
        """The whole table as of a batch (none below 0) and the batches after it."""
        parts = [f"{self.path}/whole{whole}"] if whole >= 0 else []
        return union_filters(spark.read.parquet(*parts, *(f"{self.path}/b{k}" for k in range(max(whole, -1) + 1, last + 1))), "filter_id")

    def at(self, spark: SparkSession, batch_id: int) -> DataFrame:
        """All filters as of a batch."""
        return self._merged(spark, (batch_id + 1) // self.merge_every * self.merge_every - 1, batch_id)


def run_feed(stream: DataFrame, feed: FilterFeed, checkpoint: str) -> int:
    """Runs a feed over what the stream has now; returns the last batch's number."""
    query = stream.writeStream.foreachBatch(feed).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return max((p["batchId"] for p in query.recentProgress), default=-1)


def sessions(events: DataFrame, gap: str = "2 hours") -> DataFrame:
    return events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n_events")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n_events")


def site_filters(stream: DataFrame, spec: FilterSpec) -> DataFrame:
    """(site_id, n_elements, ones): one growing filter a site, kept as state between batches."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    m = spec.m
    spotted = stream.select(F.col("site_id"), positions(F.col("element"), spec).alias("spots"))

    def grow(key, frames: Iterator[pd.DataFrame], state: GroupState):
        n, bits = state.get if state.exists else (0, bytes(m // 8))
        held = bytearray(bits)
        for frame in frames:
            for spots in frame["spots"]:
                n += 1
                for p in spots:
                    held[p // 8] |= 1 << p % 8
        state.update((n, bytes(held)))
        yield pd.DataFrame({"site_id": [key[0]], "n_elements": [n], "ones": [int.from_bytes(held, "little").bit_count()]})

    return spotted.groupBy("site_id").applyInPandasWithState(grow, "site_id long, n_elements long, ones long", "n long, bits binary", "update", GroupStateTimeout.NoTimeout)


def moving_window(day_words: DataFrame, days: int = 7) -> DataFrame:
    """(day, word_ix, word): for each day the union of its filter and those of the days before it, `days` in all."""
    spread = day_words.select(F.explode(F.sequence(F.col("day"), F.col("day") + days - 1)).alias("of"), "word_ix", "word")
    last = day_words.agg(F.max("day").alias("last"))
    return spread.join(F.broadcast(last), F.col("of") <= F.col("last")).groupBy(F.col("of").alias("day"), "word_ix").agg(F.bit_or("word").alias("word"))  # one row

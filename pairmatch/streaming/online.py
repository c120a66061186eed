"""Matching on streams: windows, late rows, arrival order, running state.

Event times without a zone are cast first, since watermarks need a zoned type.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F


def read_events(spark: SparkSession, path: str, schema, per_trigger: int = 1) -> DataFrame:
    df = spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)
    return df.withColumn("ts", F.col("ts").cast("timestamp"))


def windowed(events: DataFrame, size: str = "1 hour", slide: str | None = None, late: str | None = "2 hours") -> DataFrame:
    """Counts and sums a window and type; tumbling, or sliding by slide."""
    e = events.withWatermark("ts", late) if late and events.isStreaming else events
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return e.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("value")).select(F.col("w.start").alias("start"), "event_type", "n", "value")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str | None = "2 hours") -> DataFrame:
    e = events.withWatermark("ts", late) if late and events.isStreaming else events
    s = F.session_window("ts", gap)
    return e.groupBy(s.alias("s"), "user_id").agg(F.count("*").alias("n")).select(F.col("s.start").alias("start"), F.col("s.end").alias("end"), "user_id", "n")


def unique_arrivals(events: DataFrame, late: str = "2 hours") -> DataFrame:
    """First arrival of each event id, state kept for the watermark's length."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def match_arrivals(events: DataFrame, records: DataFrame, key: str) -> DataFrame:
    """Arriving events with the static record of their key."""
    return events.join(records, key)


def running_matches(events: DataFrame) -> DataFrame:
    """Per user, the events so far and the largest value, updated with every batch."""
    from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

    class Running(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.seen = handle.getValueState("seen", "n long, top double")

        def handleInputRows(self, key, rows, timerValues):  # noqa: N802, N803
            import pandas as pd

            n, top = self.seen.get() if self.seen.exists() else (0, float("-inf"))
            for pdf in rows:
                n, top = n + len(pdf), max(top, float(pdf["value"].max()))
            self.seen.update((n, top))
            yield pd.DataFrame({"user_id": [key[0]], "n": [n], "top": [top]})

        def close(self) -> None:
            pass

    return events.groupBy("user_id").transformWithStateInPandas(Running(), "user_id long, n long, top double", "Update", "None")


def select_per_batch(model, u_r: float, sink):
    """foreachBatch function: the least uncertain share of each batch of pairs with evidence goes to sink(df, batch_id)."""
    from pairmatch.operators.self_training import select_uncertainty, uncertainty
    from pairmatch.plans.session import cut

    def run(batch: DataFrame, batch_id: int) -> None:
        scored = cut(uncertainty(model.passes(model.score(batch))).withColumnRenamed("pred", "pseudo"))
        sink(select_uncertainty(scored, u_r)[0], batch_id)

    return run

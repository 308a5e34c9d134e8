"""Event-time forms: prequential scores, late rows, replays, delayed labels."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.model import Model, score_expr


def timed(stream: DataFrame, ts: str) -> DataFrame:
    """Event time as a timestamp with zone: files often hold it without."""
    return stream.withColumn(ts, F.col(ts).cast("timestamp"))


def prequential(stream: DataFrame, model: Model, cols: list[str], ts: str = "ts", window: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Accuracy per event-time window of a fixed model over (ts, cols, y); rows later than the watermark are dropped."""
    s = F.array(*score_expr(model, cols))
    hit = (F.array_position(s, F.array_max(s)) - 1 == F.col("y")).cast("double")
    return timed(stream, ts).withWatermark(ts, late).groupBy(F.window(ts, window)).agg(F.avg(hit).alias("accuracy"), F.count("*").alias("n"))


def once(stream: DataFrame, key: str, ts: str = "ts", late: str = "10 minutes") -> DataFrame:
    """Rows without replays within the watermark."""
    return timed(stream, ts).withWatermark(ts, late).dropDuplicatesWithinWatermark([key])


def with_labels(events: DataFrame, labels: DataFrame, key: str, within: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Stream-stream join of rows with labels that arrive up to `within` later; labels: (key, label_ts, y)."""
    e = timed(events, "ts").withWatermark("ts", late).alias("e")
    lab = timed(labels, "label_ts").withWatermark("label_ts", late).alias("l")
    return e.join(lab, (F.col(f"e.{key}") == F.col(f"l.{key}")) & (F.col("l.label_ts") >= F.col("e.ts")) & (F.col("l.label_ts") <= F.col("e.ts") + F.expr(f"INTERVAL {within}")))

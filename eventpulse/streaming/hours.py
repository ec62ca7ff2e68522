"""Counts and sums by hour with own state and event-time timers."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from eventpulse.plans.scratch import ship
from eventpulse.streaming.clusters import ROCKSDB

HOUR_US = 3_600_000_000
HOURLY = "event_type string, closed_us long, n long, total double"


class HourProcessor(StatefulProcessor):
    """State of a type: count and sum of each open hour. A timer at the hour's end sends them on and forgets them."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.open = handle.getMapState("open", "closed_us long", "n long, total double")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        for pdf in rows:
            for closed, part in pdf.groupby("closed_us")["value"]:
                closed = int(closed)
                n, total = self.open.getValue((closed,)) if self.open.containsKey((closed,)) else (0, 0.0)
                self.open.updateValue((closed,), (n + len(part), total + float(part.sum())))
                self.handle.registerTimer(closed // 1000)
        yield from ()

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        closed = expiredTimerInfo.getExpiryTimeInMs() * 1000
        if self.open.containsKey((closed,)):
            n, total = self.open.getValue((closed,))
            self.open.removeKey((closed,))
            yield pd.DataFrame({"event_type": [key[0]], "closed_us": [closed], "n": [n], "total": [total]})

    def close(self) -> None:
        pass


def hourly(events: DataFrame) -> DataFrame:
    """HOURLY rows of a stream of (ts, event_type, value); its last, later row only moves the watermark."""
    spark = events.sparkSession
    ship(spark)
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", ROCKSDB)
    closed = (F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / HOUR_US) + 1) * HOUR_US
    rows = events.withWatermark("ts", "0 seconds").select("ts", F.coalesce("event_type", F.lit("")).alias("event_type"), closed.cast("long").alias("closed_us"), "value")
    return rows.groupBy("event_type").transformWithStateInPandas(HourProcessor(), HOURLY, "append", "eventtime")

"""Static structures beside streams: probing, windows of hits, and filters by window.

A static structure takes no insertions, so a stream probes it without state; what changes over
time is rebuilt, by micro-batch or by closed window."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from ..functions import hashing
from ..operators import build as band
from ..operators import solve
from ..operators.lookup import probe
from ..params import BandParams


def events_stream(spark: SparkSession, path: str, schema, max_files: int = 4) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(path)


def probe_stream(s: band.BandStructure, stream: DataFrame, cols: list[str]) -> DataFrame:
    """Rows of the stream whose key the filter may hold; stateless."""
    return probe(s, stream, cols, strategy="broadcast", out="_m").where("_m").drop("_m")


def window_hits(stream: DataFrame, time: str, size: str, delay: str, slide: str | None = None) -> DataFrame:
    """Hits by tumbling or sliding window; rows later than `delay` are dropped."""
    at = F.window(time, size, slide) if slide else F.window(time, size)
    return stream.withWatermark(time, delay).groupBy(at.alias("w")).agg(F.count(F.lit(1)).alias("hits"))


def session_hits(stream: DataFrame, time: str, key: str, gap: str, delay: str) -> DataFrame:
    return stream.withWatermark(time, delay).groupBy(F.session_window(time, gap).alias("w"), key).agg(F.count(F.lit(1)).alias("hits"))


def first_seen(stream: DataFrame, time: str, cols: list[str], delay: str) -> DataFrame:
    """Each key once per watermark span."""
    return stream.withWatermark(time, delay).dropDuplicatesWithinWatermark(cols)


def rebuild_each_batch(path: str, cols: list[str], params: BandParams) -> Callable[[DataFrame, int], None]:
    """foreachBatch writer of one filter version per micro-batch. A repeated batch finds its
    version there and leaves it."""
    from ..sources import store

    def write(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        version = f"batch-{batch_id}"
        try:
            store.manifest(spark, path, version)
            return
        except Exception as e:  # not there yet
            if "PATH_NOT_FOUND" not in str(e):
                raise
        store.write(band.build(batch, cols, params=params), path, version)

    return write


class WindowFilter(StatefulProcessor):
    """Collects the digests of one window's keys, and when the watermark passes its end emits
    the window's zero-right-hand-side filter. Key: window end in milliseconds."""

    def __init__(self, r: int = 8) -> None:
        self.params = BandParams(kind="zero", r=r, free="random", is_filter=True, n_shards=1).resolved()

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.digests = handle.getMapState("digests", "lo long", "hi long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        for part in rows:
            for hi, lo in zip(part["hi"].tolist(), part["lo"].tolist(), strict=True):
                self.digests.updateValue((int(lo),), (int(hi),))
        if key[0] not in list(self.handle.listTimers()):
            self.handle.registerTimer(int(key[0]))
        yield from ()

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        pairs = list(self.digests.iterator())
        lo = np.array([k[0] for k, _ in pairs], np.int64).view(np.uint64)
        hi = np.array([v[0] for _, v in pairs], np.int64).view(np.uint64)
        table = solve.solve_shards({0: solve.Keys(hi, lo, np.zeros(len(hi), np.uint64))}, self.params)[0]
        self.digests.clear()
        yield pd.DataFrame(
            {"window_end": [key[0]], "n": [len(pairs)], "n_starts": [table.n_starts], "z": [table.z.tobytes()]}
        )

    def close(self) -> None:
        pass


WINDOW_FILTER = "window_end long, n long, n_starts long, z binary"


def window_filters(stream: DataFrame, time: str, cols: list[str], size: str, delay: str, r: int = 8) -> DataFrame:
    """A stream of filters, one for each closed window of the key columns."""
    keyed = hashing.with_digest(stream.withWatermark(time, delay), cols)
    ended = keyed.withColumn("window_end", F.unix_millis(F.window(time, size)["end"]))
    return (
        ended.select("window_end", "hi", "lo", time)
        .groupBy("window_end")
        .transformWithStateInPandas(WindowFilter(r), WINDOW_FILTER, outputMode="append", timeMode="EventTime")
    )

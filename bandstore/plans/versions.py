"""Which version of a structure holds at a time: an as-of join by union and window."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W


def as_of(rows: DataFrame, versions: DataFrame, time: str, version: str, by: list[str] | None = None, slack: str = "1 day") -> DataFrame:
    """Add the latest version whose time is not after the row's, null before the first.

    Both sides meet in one shuffle by `by` and the time's span of `slack`; each version is also
    handed on to the first later span that has rows or versions, so no window crosses a span.
    versions: the `by` columns, `time` and `version`; a version for each time."""
    keys = by or []
    span = F.window(time, slack)["start"]
    left = rows.withColumn("_span", span)
    right = versions.select(*keys, F.col(time), F.col(version), span.alias("_span"))
    # The last version of each span serves later spans until one has its own. Spans with a
    # version are few: a row for each span and key.
    last = right.groupBy(*keys, "_span").agg(F.max_by(version, time).alias("_carried"))
    spans = left.select(*keys, "_span").unionByName(right.select(*keys, "_span")).distinct().join(last, [*keys, "_span"], "left")
    w = W.partitionBy(*(keys or [F.lit(0)])).orderBy("_span").rowsBetween(W.unboundedPreceding, -1)
    carried = spans.withColumn("_before", F.last("_carried", ignorenulls=True).over(w)).drop("_carried")
    tagged = left.withColumns({"_side": F.lit(1), "_v": F.lit(None).cast(versions.schema[version].dataType), "_row": F.struct(*rows.columns)})
    marks = right.select(*keys, time, "_span", F.lit(0).alias("_side"), F.col(version).alias("_v"), F.lit(None).cast(tagged.schema["_row"].dataType).alias("_row"))
    both = tagged.select(*keys, time, "_span", "_side", "_v", "_row").unionByName(marks)
    within = W.partitionBy(*keys, "_span").orderBy(time, "_side").rowsBetween(W.unboundedPreceding, 0)
    found = both.withColumn("_v", F.last("_v", ignorenulls=True).over(within)).where("_side = 1")
    joined = found.join(carried, [*keys, "_span"], "left")
    return joined.select("_row.*", F.coalesce("_v", "_before").alias(version))

"""Heavy hitters of a sliding window: the alternative to decay that forgets all at once."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def exact(stream: DataFrame, width: int, phi: float, now: int) -> DataFrame:
    """(item, f, share) over now - width < at <= now."""
    f = stream.where((F.col("tick") > now - width) & (F.col("tick") <= now) & F.col("item").isNotNull()).groupBy("item").agg(F.count("*").cast("double").alias("f"))
    total = f.agg(F.sum("f").alias("c"))
    return f.crossJoin(F.broadcast(total)).where(F.col("f") > F.lit(phi) * F.col("c")).select("item", "f", (F.col("f") / F.col("c")).alias("share"))


def rolling(stream: DataFrame, width: int) -> DataFrame:
    """(item, at, ord, n): occurrences of the item in the width ending at each of them."""
    frame = W.partitionBy("item").orderBy("tick").rangeBetween(-(width - 1), 0)
    return stream.select("item", "tick", "ord", F.count("*").over(frame).alias("n"))

"""Walks: limits, closure under composition, neighbourhoods."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import written


def from_distance(pairs: DataFrame, speed: float = 1.0, limit: int | None = None) -> DataFrame:
    """Directed walks both ways from undirected pairs (a, b, and secs or metres), up to limit seconds."""
    if "metres" in pairs.columns:
        pairs = pairs.withColumn("secs", F.ceil(F.col("metres") / speed).cast("int"))
    p = pairs.select("a", "b", "secs").where("a <> b")
    p = p.where(F.col("secs") <= limit) if limit is not None else p
    return p.union(p.select("b", "a", "secs")).groupBy("a", "b").agg(F.min("secs").alias("secs"))


def close(walks: DataFrame, max_doublings: int = 12) -> DataFrame:
    """Least seconds between all stops that walks join, by doubling: a pass composes every walk with
    every other and doubles the number of legs, so components of diameter d take log2(d) passes.
    Closed walks may exceed the limit that single ones kept to."""
    w = written(walks.select("a", "b", "secs"))
    mark = w.agg(F.count("*"), F.sum("secs")).first()
    for _ in range(max_doublings):
        second = w.select(F.col("a").alias("b"), F.col("b").alias("c"), F.col("secs").alias("more"))
        two = w.join(second, "b").where("a <> c").select("a", F.col("c").alias("b"), (F.col("secs") + F.col("more")).alias("secs"))
        w = written(w.union(two).groupBy("a", "b").agg(F.min("secs").cast("int").alias("secs")))
        now = w.agg(F.count("*"), F.sum("secs")).first()
        if now == mark:
            return w
        mark = now
    raise ValueError(f"walks still grow after {max_doublings} doublings; they join too many stops to be closed")


def neighbourhood(stops: DataFrame, walks: DataFrame) -> DataFrame:
    """(a, b, secs) with every stop at no distance from itself."""
    own = stops.select(F.col("stop_id").alias("a"), F.col("stop_id").alias("b"), F.lit(0).alias("secs"))
    return own.unionByName(walks)

"""Labels, Pareto sets and legs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def pareto(labels: DataFrame, by: tuple[str, ...] = ("req_id",)) -> DataFrame:
    """Of labels (.., n, arr) those that arrive before every one with fewer transfers."""
    w = Window.partitionBy(*by).orderBy("n", "arr").rowsBetween(Window.unboundedPreceding, -1)
    return labels.withColumn("before_", F.min("arr").over(w)).where("before_ is null or arr < before_").drop("before_")


def pareto_nd(rows: DataFrame, by: list[str], cost: list[str]) -> DataFrame:
    """Rows that no other row of the group dominates in all of cost; equal rows stay. A group's
    skyline is found by comparing its rows with one another, so groups should be small."""
    a, b = rows.distinct().alias("a"), rows.select(*by, *cost).distinct().alias("b")
    same = [F.col(f"a.{c}").eqNullSafe(F.col(f"b.{c}")) for c in by]
    no_worse = [F.col(f"b.{c}") <= F.col(f"a.{c}") for c in cost]
    less = F.lit(False)
    for c in cost:
        less = less | (F.col(f"b.{c}") < F.col(f"a.{c}"))
    cond = less
    for c in [*same, *no_worse]:
        cond = cond & c
    return a.join(b, cond, "left_anti")


def at_most(labels: DataFrame, k: int, by: tuple[str, ...] = ("req_id",)) -> DataFrame:
    """For every n up to k the earliest arrival with at most n transfers (rows only where reached)."""
    grid = labels.select(*by).distinct().withColumn("n", F.explode(F.sequence(F.lit(0), F.lit(k))))
    w = Window.partitionBy(*by).orderBy("n").rowsBetween(Window.unboundedPreceding, 0)
    full = grid.join(labels.groupBy(*by, "n").agg(F.min("arr").alias("arr")), [*by, "n"], "left")
    return full.withColumn("arr", F.min("arr").over(w)).where("arr is not null")


def earliest_arrival(labels: DataFrame, by: tuple[str, ...] = ("req_id",)) -> DataFrame:
    return labels.groupBy(*by).agg(F.min("arr").alias("arr"))


def replay(net, labelled: DataFrame, reqs: DataFrame) -> DataFrame:
    """Rows (req_id, n) whose legs don't replay on the timetable: board after arriving and walking,
    rides one more than transfers, last arrival plus walk gives the label. Empty if all is well."""
    legs = labelled.select("req_id", "n", "arr", F.posexplode("legs").alias("nth", "leg")).select("req_id", "n", "arr", "nth", "leg.*")
    ev = net.events.select("trip_id", "idx", "stop_id", F.col("arr").alias("t"))
    on = ev.select("trip_id", F.col("idx").alias("from_idx"), F.col("stop_id").alias("on_stop"), F.col("t").alias("on_t"))
    off = ev.select("trip_id", F.col("idx").alias("to_idx"), F.col("stop_id").alias("off_stop"), F.col("t").alias("off_t"))
    full = legs.join(on, ["trip_id", "from_idx"], "left").join(off, ["trip_id", "to_idx"], "left").join(reqs, "req_id")
    w = Window.partitionBy("req_id", "n").orderBy("nth")
    full = full.withColumns({"prev_stop": F.coalesce(F.lag("off_stop").over(w), F.col("source")), "prev_t": F.coalesce(F.lag("off_t").over(w), F.col("dep")), "last": F.lead("nth").over(w).isNull()})
    near = net.neighbourhood()
    full = full.join(near.select(F.col("a").alias("prev_stop"), F.col("b").alias("on_stop"), F.col("secs").alias("w1")), ["prev_stop", "on_stop"], "left")
    full = full.join(near.select(F.col("a").alias("off_stop"), F.col("b").alias("target"), F.col("secs").alias("w2")), ["off_stop", "target"], "left")
    bad = F.coalesce(F.col("prev_t") + F.col("w1") > F.col("on_t"), F.lit(True)) | F.coalesce(F.col("from_idx") >= F.col("to_idx"), F.lit(True))
    bad = bad | (F.col("last") & F.coalesce(F.col("off_t") + F.col("w2") != F.col("arr"), F.lit(True))) | (F.col("last") & (F.col("nth") > F.col("n")))
    return full.where(bad).select("req_id", "n").distinct()


def hhmm(seconds):
    """Seconds after midnight as HH:MM."""
    return F.format_string("%02d:%02d", F.floor(seconds / 3600).cast("int"), F.floor(seconds % 3600 / 60).cast("int"))

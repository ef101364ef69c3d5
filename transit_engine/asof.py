"""The earliest trip of a route that can be boarded at a stop from a time on."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .schema import Network
from .storage import sorted_if_large


def earliest(probes: DataFrame, net: Network) -> DataFrame:
    """probes (route_id, idx, tau, ...) with column rank added; probes that catch no trip are dropped.

    Departure at tau still boards. At a constant headway the rank is arithmetic on two small tables;
    otherwise departures and probes of a (route, idx) meet in one descending window, whose frame only
    grows, so no join on an inequality is needed."""
    if net.headway is not None:
        at = net.offsets.select("route_id", "idx", F.col("offset").alias("o_")).join(sorted_if_large(net.headway), "route_id")
        at = at.select("route_id", "idx", (F.col("first") + F.col("o_")).alias("f_"), F.col("step").alias("s_"), F.col("trips").alias("t_"))
        late = F.greatest(F.lit(0), F.ceil((F.col("tau") - F.col("f_")) / F.col("s_"))).cast("int")
        return probes.join(at, ["route_id", "idx"]).withColumn("rank", late).where("rank < t_").drop("f_", "s_", "t_")
    return earliest_by_window(probes, net)


def earliest_by_window(probes: DataFrame, net: Network) -> DataFrame:
    """As earliest, for any first-in-first-out timetable."""
    names = [c for c in probes.columns if c not in ("route_id", "idx", "tau")]
    rest = F.struct(*names) if names else F.struct(F.lit(0).alias("none_"))
    p = probes.select("route_id", "idx", "tau", F.lit(0).alias("side"), F.lit(None).cast("int").alias("r"), rest.alias("rest"))
    d = net.events.select("route_id", "idx", F.col("dep").alias("tau"), F.lit(1).alias("side"), F.col("rank").alias("r"), F.lit(None).cast(p.schema["rest"].dataType).alias("rest"))
    w = Window.partitionBy("route_id", "idx").orderBy(F.desc("tau"), F.desc("side"), F.desc("r")).rowsBetween(Window.unboundedPreceding, 0)
    got = p.unionByName(d).withColumn("rank", F.last("r", ignorenulls=True).over(w)).where("side = 0 and rank is not null")
    return got.select("route_id", "idx", "tau", *[F.col(f"rest.{c}").alias(c) for c in names], "rank")


def times_at(df: DataFrame, net: Network, idx: str, out: str, rank: str = "rank") -> DataFrame:
    """df (route_id, rank, idx column) with the arrival of that trip at that index as column out."""
    if net.headway is not None:
        off = net.offsets.select("route_id", F.col("idx").alias(idx), F.col("offset").alias("o_"))
        hw = net.headway.select("route_id", F.col("first").alias("f_"), F.col("step").alias("s_"))
        return df.join(sorted_if_large(off), ["route_id", idx]).join(sorted_if_large(hw), "route_id").withColumn(out, (F.col("f_") + F.col("s_") * F.col(rank) + F.col("o_")).cast("int")).drop("o_", "f_", "s_")
    e = net.events.select("route_id", F.col("rank").alias(rank), F.col("idx").alias(idx), F.col("arr").alias(out))
    return df.join(e, ["route_id", rank, idx])

"""Nested cells: parents split in children, and the stop pairs that their fill-in needs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import cells, partition
from .hypergraph import Hypergraph
from .schema import Network

#: Cut stops whose pairs may be listed.
MOST_CUTS = 100_000


def split(h: Hypergraph, parents: int, children: int, imbalance: float = 0.2, seed: int = 0) -> DataFrame:
    """(node_id, parent, cell): parents cells by the multilevel partitioner, then every parent's own part
    of the hypergraph again, all parents in parallel. cell numbers children through all parents."""
    top = partition.multilevel(h, parents, imbalance, seed).withColumnRenamed("cell", "parent")
    return top.join(partition.each_parent(h, top, children, imbalance, seed), "node_id").select("node_id", "parent", ((F.col("parent") - 1) * children + F.col("cell")).cast("int").alias("cell"))


def levels(net: Network, nested_cells: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Stop cells of the parents and of the children."""
    top = cells.stop_cells(net, nested_cells.select("node_id", F.col("parent").alias("cell")))
    low = cells.stop_cells(net, nested_cells.select("node_id", "cell"))
    return top, low


def pairs(net: Network, nested_cells: DataFrame, mode: str = "strict") -> DataFrame:
    """Ordered (src_stop, dst_stop) to search. paper: all pairs of top cut stops, and in every parent its
    top cut stops with the cut stops that only its children have, both ways; siblings: also between
    child cut stops of different children of a parent; strict: also inside one child, a safe superset."""
    from .hypergraph import incidence

    top, low = levels(net, nested_cells)
    t = top.where("cell = 0").select("stop_id")
    at = incidence(net).join(nested_cells, "node_id").select("stop_id", "parent", "cell").distinct()
    g = t.join(at.select("stop_id", "parent").distinct(), "stop_id")
    only = low.where("cell = 0").select("stop_id").join(t, "stop_id", "left_anti")
    hset = only.join(at, "stop_id").select("stop_id", "parent", "cell").distinct()
    h = hset.select("stop_id", "parent").distinct()
    a = lambda d: d.select(F.col("stop_id").alias("src_stop"), *[c for c in d.columns if c != "stop_id"])
    b = lambda d: d.select(F.col("stop_id").alias("dst_stop"), *[c for c in d.columns if c != "stop_id"])
    out = flat_pairs(t)
    out = out.union(a(g).join(b(h), "parent").select("src_stop", "dst_stop")).union(a(h).join(b(g), "parent").select("src_stop", "dst_stop"))
    if mode == "siblings":
        other = b(hset).withColumnRenamed("cell", "cell2")
        out = out.union(a(hset).join(other, "parent").where("cell <> cell2").select("src_stop", "dst_stop"))
    elif mode == "strict":
        out = out.union(a(h).join(b(h), "parent").select("src_stop", "dst_stop"))
    return out.where("src_stop <> dst_stop").distinct()


def flat_pairs(cuts: DataFrame) -> DataFrame:
    """All ordered pairs of cut stops: a list of cut stops squared, which is what a flat partition costs.
    One side is a list of at most MOST_CUTS stops, checked, that goes to every task of the other."""
    n = cuts.count()
    if n > MOST_CUTS:
        raise ValueError(f"{n} cut stops: as many pairs squared are no fill-in to compute; use fewer cells")
    dst = cuts.select(F.col("stop_id").alias("dst_stop"))
    return cuts.select(F.col("stop_id").alias("src_stop")).join(F.broadcast(dst), F.col("src_stop") != F.col("dst_stop"))


def tagged(found: DataFrame, net: Network, nested_cells: DataFrame) -> DataFrame:
    """The fill-in with the level its pair belongs to (1: both stops are top cut stops, 2: else)."""
    top, _ = levels(net, nested_cells)
    t = top.where("cell = 0").select("stop_id", F.lit(1).alias("top_"))
    x = found.join(t.select(F.col("stop_id").alias("src_stop"), F.col("top_").alias("s_")), "src_stop", "left").join(t.select(F.col("stop_id").alias("dst_stop"), F.col("top_").alias("d_")), "dst_stop", "left")
    return x.withColumn("level", F.when(F.col("s_").isNotNull() & F.col("d_").isNotNull(), 1).otherwise(2)).drop("s_", "d_")

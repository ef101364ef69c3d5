"""Hypergraph partitioners: multilevel (three ways to coarsen), exact, and by a given column."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .hypergraph import Hypergraph
from .storage import written

#: Nodes of the coarsest level that the driver may hold; a level is contracted in Spark until it fits.
DRIVER_NODES = 20_000
#: What the driver takes where contraction ends early, nodes and pins; beyond it an error is raised.
MOST_NODES, MOST_PINS = 200_000, 5_000_000
#: Edges with more pins don't rate node pairs (they still count in every cut).
RATED_PINS = 60


def _ratings(pins: DataFrame, edges: DataFrame, nodes: DataFrame, heaviest: float) -> DataFrame:
    """(a, b, rating): how strongly two nodes belong together: the sum of weight / (pins - 1) over the
    edges that both are pins of, if their joint weight fits a cell well."""
    size = pins.groupBy("edge_id").agg(F.count("*").alias("k")).where((F.col("k") > 1) & (F.col("k") <= RATED_PINS))
    p = pins.join(size, "edge_id").join(edges.select("edge_id", F.col("weight").alias("w")), "edge_id")
    a = p.select("edge_id", F.col("node_id").alias("a"), (F.col("w") / (F.col("k") - 1)).alias("r"))
    b = p.select("edge_id", F.col("node_id").alias("b"))
    r = a.join(b, "edge_id").where("a <> b").groupBy("a", "b").agg(F.sum("r").alias("rating"))
    w = nodes.select("node_id", "weight")
    r = r.join(w.select(F.col("node_id").alias("a"), F.col("weight").alias("wa")), "a").join(w.select(F.col("node_id").alias("b"), F.col("weight").alias("wb")), "b")
    return r.where(F.col("wa") + F.col("wb") <= heaviest).select("a", "b", "rating")


def contract(h: Hypergraph, heaviest: float, coarsen: str = "mutual") -> DataFrame:
    """(node_id, into): one round of coarsening. mutual: pairs that choose each other; first_choice: every
    node joins its choice if that one stays; community: as mutual inside label-propagated communities."""
    r = _ratings(h.pins, h.edges, h.nodes, heaviest)
    if coarsen == "community":
        label = h.nodes.select("node_id", F.col("node_id").alias("label"))
        for _ in range(3):
            votes = r.join(label.withColumnRenamed("node_id", "b"), "b").groupBy("a", "label").agg(F.sum("rating").alias("v"))
            best = votes.groupBy(F.col("a").alias("node_id")).agg(F.max_by("label", F.struct("v", -F.col("label"))).alias("new"))
            label = written(label.join(best, "node_id", "left").select("node_id", F.coalesce("new", "label").alias("label")))
        la, lb = (label.select(F.col("node_id").alias(c), F.col("label").alias("l" + c)) for c in "ab")
        r = r.join(la, "a").join(lb, "b").where("la = lb").select("a", "b", "rating")
    choice = written(r.groupBy("a").agg(F.max_by("b", F.struct(F.round("rating", 9), -F.col("b"))).alias("b")))
    back = choice.select(F.col("a").alias("b"), F.col("b").alias("back"))
    pairs = choice.join(back, "b", "left")
    if coarsen == "first_choice":
        # of a chain of choices, those that point at a smaller id join it if it doesn't join another itself
        joins = pairs.where("b < a").select("a", "b")
        root = joins.join(joins.select(F.col("a").alias("b"), F.lit(1).alias("moves")), "b", "left").where("moves is null")
        pair = root.select(F.col("a").alias("node_id"), F.col("b").alias("into"))
    else:
        pair = pairs.where("back = a and b < a").select(F.col("a").alias("node_id"), F.col("b").alias("into"))
    return h.nodes.select("node_id").join(pair, "node_id", "left").select("node_id", F.coalesce("into", "node_id").alias("into"))


def _project(h: Hypergraph, into: DataFrame) -> Hypergraph:
    """The next coarser level: weights added, pins renamed, edges of one pin dropped, equal ones merged."""
    nodes = h.nodes.join(into, "node_id").groupBy(F.col("into").alias("node_id")).agg(F.sum("weight").alias("weight"))
    pins = h.pins.join(into, "node_id").groupBy("edge_id").agg(F.sort_array(F.collect_set("into")).alias("pins")).where(F.size("pins") > 1)
    merged = written(pins.join(h.edges.select("edge_id", "weight"), "edge_id").groupBy("pins").agg(F.min("edge_id").alias("edge_id"), F.sum("weight").alias("weight")))
    return Hypergraph(written(nodes), merged.select("edge_id", F.explode("pins").alias("node_id")), merged.select("edge_id", "weight"))


def grouped(h: Hypergraph, into: DataFrame) -> Hypergraph:
    """h with its nodes merged as into (node_id, into) says: a level that some column gives."""
    return _project(h, into)


# --- the coarsest level, on arrays --------------------------------------------------------------

class Small:
    """A hypergraph that fits one task: pins by edge and by node."""

    def __init__(self, weight: np.ndarray, pins: list[np.ndarray], cost: np.ndarray):
        self.weight, self.pins, self.cost = weight, pins, cost
        self.of_node: list[list[int]] = [[] for _ in weight]
        for e, p in enumerate(pins):
            for v in p.tolist():
                self.of_node[v].append(e)

    def cut(self, cell: np.ndarray) -> float:
        return float(sum(c for p, c in zip(self.pins, self.cost, strict=True) if (cell[p] != cell[p[0]]).any()))

    def grow(self, p: int, most: float, rng) -> np.ndarray:
        """Cells grown one after another from a random node, always by the node with the strongest ties."""
        cell, n = np.full(len(self.weight), -1), len(self.weight)
        total = self.weight.sum()
        order = rng.permutation(n).tolist()
        for c in range(p - 1):
            load, tie = 0.0, {}
            while load < total / p:
                v = max(tie, key=lambda x: (tie[x], -x)) if tie else next((x for x in order if cell[x] < 0), None)
                if v is None:
                    break
                tie.pop(v, None)
                if cell[v] >= 0 or load + self.weight[v] > most and load:
                    if not tie:
                        break
                    continue
                cell[v] = c
                load += self.weight[v]
                for e in self.of_node[v]:
                    for u in self.pins[e].tolist():
                        if cell[u] < 0:
                            tie[u] = tie.get(u, 0.0) + self.cost[e] / max(1, len(self.pins[e]) - 1)
        cell[cell < 0] = p - 1
        return cell

    def refine(self, cell: np.ndarray, p: int, most: float, passes: int = 10) -> np.ndarray:
        """Moves single nodes while that cuts less (or balances an overweight cell)."""
        count = np.zeros((len(self.pins), p), np.int64)
        for e, pin in enumerate(self.pins):
            np.add.at(count[e], cell[pin], 1)
        load = np.bincount(cell, self.weight, p)
        size = np.array([len(x) for x in self.pins])
        for _ in range(passes):
            moved = 0
            for v in range(len(cell)):
                es, own = self.of_node[v], cell[v]
                if not es:
                    continue
                es = np.array(es)
                leave = -(self.cost[es] * (count[es, own] == size[es])).sum()
                gain = leave + (self.cost[es, None] * (count[es] == (size[es] - 1)[:, None])).sum(0)
                gain[own] = -np.inf
                gain[load + self.weight[v] > most] = -np.inf
                c = int(np.argmax(gain))
                if gain[c] > 1e-12 or (load[own] > most and gain[c] > -np.inf):
                    count[es, own] -= 1
                    count[es, c] += 1
                    load[own] -= self.weight[v]
                    load[c] += self.weight[v]
                    cell[v] = c
                    moved += 1
            if not moved:
                break
        return cell

    def solve(self, p: int, imbalance: float, seed: int, tries: int = 6) -> np.ndarray:
        most = (1 + imbalance) * self.weight.sum() / p
        best, least = None, np.inf
        for t in range(tries):
            cell = self.refine(self.grow(p, most, np.random.default_rng(seed * 1000 + t)), p, most)
            c = self.cut(cell) + 1e6 * max(0.0, np.bincount(cell, self.weight, p).max() - most)
            if c < least:
                best, least = cell, c
        return best


def _small(nodes: pd.DataFrame, pins: pd.DataFrame, edges: pd.DataFrame) -> tuple[np.ndarray, Small]:
    ids = np.sort(nodes["node_id"].to_numpy())
    weight = nodes.set_index("node_id")["weight"].reindex(ids).to_numpy(float)
    pins = pins.sort_values(["edge_id", "node_id"])
    at, e = np.searchsorted(ids, pins["node_id"].to_numpy()), pins["edge_id"].to_numpy()
    cut = np.append(np.flatnonzero(np.append(True, e[1:] != e[:-1])), len(e)) if len(e) else np.zeros(1, int)
    cost = edges.set_index("edge_id")["weight"]
    lists = [at[s:z] for s, z in zip(cut[:-1], cut[1:], strict=True)]
    return ids, Small(weight, lists, np.array([cost[e[s]] for s in cut[:-1]], float))


def multilevel(h: Hypergraph, p: int, imbalance: float = 0.2, seed: int = 0, coarsen: str = "mutual", driver_nodes: int = DRIVER_NODES) -> DataFrame:
    """(node_id, cell 1..p): coarsen in Spark until the level fits the driver, partition it there by
    greedy growth and moves, hand cells down and move single nodes on the finest level. A cell weighs at most (1 + imbalance) of the mean."""
    spark = h.nodes.sparkSession
    total = h.nodes.agg(F.sum("weight")).first()[0] or 0.0
    level, down = Hypergraph(written(h.nodes), written(h.pins), written(h.edges)), h.nodes.select("node_id", F.col("node_id").alias("into"))
    size = first = level.nodes.count()
    while size > max(driver_nodes, 40 * p):
        into = written(contract(level, (1 + imbalance) * total / p / 3, coarsen))
        down = written(down.join(into.select(F.col("node_id").alias("into"), F.col("into").alias("up")), "into").select("node_id", F.col("up").alias("into")))
        level = _project(level, into)
        now = level.nodes.count()
        if now > 0.95 * size:
            break
        size = now
    if size > MOST_NODES or level.pins.count() > MOST_PINS:
        raise ValueError(f"contraction ended at {size} nodes, too many for the driver")
    ids, small = _small(level.nodes.toPandas(), level.pins.toPandas(), level.edges.select("edge_id", "weight").toPandas())
    cell = small.solve(p, imbalance, seed)
    cells = spark.createDataFrame(pd.DataFrame({"into": ids, "cell": (cell + 1).astype(np.int32)}), "into bigint, cell int")
    top = written(down.join(cells, "into").select("node_id", "cell"))
    return top if size == first else refined(h, top, p, (1 + imbalance) * total / p)


def refined(h: Hypergraph, cells: DataFrame, p: int, most: float, passes: int = 4) -> DataFrame:
    """cells after single moves on the finest level, all in Spark. A pass scores every node at the border
    against all cells by the edges that a move would join or cut, and takes moves of positive gain that
    start in one cell, lead into one other and touch no edge together: of the nodes of an edge only the
    one of greatest gain may move. What a cell may still take is shared in order of gain."""
    pins, edges = h.pins, h.edges.select("edge_id", F.col("weight").alias("w"))
    for number in range(passes):
        own = pins.join(cells, "node_id")
        count = own.groupBy("edge_id", "cell").agg(F.count("*").alias("k"))
        size = count.groupBy("edge_id").agg(F.sum("k").alias("size"), F.count("*").alias("parts")).where("parts > 1")
        # moving a lone pin to the only other cell of its edge joins the edge
        cut = own.join(size, "edge_id").join(edges, "edge_id")
        here = cut.join(count.withColumnRenamed("k", "mine"), ["edge_id", "cell"])
        other = count.select("edge_id", F.col("cell").alias("to"), F.col("k").alias("theirs"))
        joins = here.join(other, "edge_id").where("`to` <> cell")
        joins = joins.groupBy("node_id", "cell", "to").agg(F.sum(F.when(F.col("theirs") == F.col("size") - 1, F.col("w")).otherwise(0.0)).alias("up"))
        whole = own.join(count.groupBy("edge_id").agg(F.count("*").alias("parts")).where("parts = 1"), "edge_id").join(edges, "edge_id")
        loss = whole.groupBy("node_id").agg(F.sum("w").alias("down"))
        gain = joins.join(loss, "node_id", "left").join(h.nodes.select("node_id", "weight"), "node_id")
        gain = gain.withColumn("gain", F.round(F.col("up") - F.coalesce("down", F.lit(0.0)), 9)).where("gain > 0")
        best = gain.groupBy("node_id").agg(F.max_by(F.struct("cell", "to", "weight", "gain"), F.struct("gain", -F.col("to"))).alias("m")).select("node_id", "m.*")
        best = written(best)
        lead = pins.join(best, "node_id").groupBy("edge_id").agg(F.max_by("node_id", F.struct("gain", -F.col("node_id"))).alias("lead"))
        blocked = pins.join(best.select("node_id"), "node_id").join(lead, "edge_id").where("node_id <> lead").select("node_id").distinct()
        free = best.join(blocked, "node_id", "left_anti")
        load = cells.join(h.nodes.select("node_id", "weight"), "node_id").groupBy("cell").agg(F.sum("weight").alias("load"))
        room = Window.partitionBy("to").orderBy(F.desc("gain"), "node_id").rowsBetween(Window.unboundedPreceding, 0)
        free = free.join(load.withColumnRenamed("cell", "to"), "to").withColumn("full", F.col("load") + F.sum("weight").over(room)).where(F.col("full") <= most)
        moves = written(free.select("node_id", F.col("to").alias("new")))
        if not moves.limit(1).count():
            break
        cells = written(cells.join(moves, "node_id", "left").select("node_id", F.coalesce("new", "cell").alias("cell")))
    return cells




def each_parent(h: Hypergraph, top: DataFrame, children: int, imbalance: float = 0.2, seed: int = 0) -> DataFrame:
    """(node_id, cell 1..children) inside every parent of top (node_id, parent): one group per parent."""
    n = top.join(h.nodes.select("node_id", "weight"), "node_id")
    p = h.pins.join(top, "node_id").select("parent", "edge_id", "node_id").join(h.edges.select("edge_id", "weight"), "edge_id")
    whole = n.select("parent", F.lit(-1).cast("long").alias("edge_id"), "node_id", "weight").unionByName(p.select("parent", "edge_id", "node_id", "weight"))

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        nodes, pins = pdf[pdf.edge_id < 0], pdf[pdf.edge_id >= 0]
        pins = pins[pins.groupby("edge_id").node_id.transform("size") > 1]
        ids, small = _small(nodes, pins, pins[["edge_id", "weight"]].drop_duplicates("edge_id"))
        return pd.DataFrame({"node_id": ids, "cell": (small.solve(children, imbalance, seed) + 1).astype(np.int32)})

    return written(whole.groupBy("parent").applyInPandas(one, "node_id long, cell int"))


def exact(spark: SparkSession, h: Hypergraph, p: int, lo: float, hi: float, most_nodes: int = 24) -> DataFrame:
    """(node_id, cell) of greatest uncut weight with node weights of lo..hi in every cell, by branch and
    bound: nodes in order of the edge weight at them, empty cells used in order, bound by the edges not
    yet cut and the weight that is left. For small hypergraphs only; an edge counts if all its own pins
    share a cell. If no partition keeps the bounds, an error says so."""
    ids, s = _small(h.nodes.toPandas(), h.pins.toPandas(), h.edges.select("edge_id", "weight").toPandas())
    n = len(ids)
    if n > most_nodes:
        raise ValueError(f"{n} nodes; the exact partitioner takes {most_nodes} at most")
    order = sorted(range(n), key=lambda v: (-sum(s.cost[e] for e in s.of_node[v]), v))
    ahead = np.append(np.cumsum([s.weight[v] for v in order][::-1])[::-1], 0.0)
    best: list = [-1.0, None]
    cell, load, size = [-1] * n, [0.0] * p, [0] * p

    def go(k: int, left: float, first: list):
        if left <= best[0] or sum(max(0.0, lo - x) for x in load) > ahead[k] + 1e-9:
            return
        if k == n:
            best[:] = left, cell.copy()
            return
        v = order[k]
        for c in range(min(p, sum(x > 0 for x in size) + 1)):
            if load[c] + s.weight[v] > hi + 1e-9:
                continue
            nxt, lost = first.copy(), 0.0
            for e in s.of_node[v]:
                if nxt[e] == -1:
                    nxt[e] = c
                elif nxt[e] not in (-2, c):
                    nxt[e], lost = -2, lost + s.cost[e]
            cell[v], load[c], size[c] = c, load[c] + s.weight[v], size[c] + 1
            go(k + 1, left - lost, nxt)
            cell[v], load[c], size[c] = -1, load[c] - s.weight[v], size[c] - 1

    go(0, float(s.cost.sum()) + 1e-9, [-1] * len(s.pins))
    if best[1] is None:
        raise ValueError(f"no partition into {p} cells keeps node weights between {lo} and {hi}")
    return spark.createDataFrame([(int(i), c + 1) for i, c in zip(ids, best[1], strict=True)], "node_id bigint, cell int")


def by_column(net_nodes: DataFrame, column: str) -> DataFrame:
    """Cells that some column already gives, numbered from 1 in its order."""
    return net_nodes.select("node_id", F.dense_rank().over(Window.orderBy(column)).alias("cell"))

"""Approximate nearest neighbours: one navigable small-world graph per shard, shard results merged."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise, table
from .vectors import classes, matrix, valid


class Graph:
    """Layers of flat neighbour arrays (-1: none). Layer 0 holds every point with 2 * degree places;
    a point stands in layer k with probability degree**-k, by a seeded draw.

    Points are lifted by one coordinate to equal lengths, so that the largest inner product with a
    query is the least distance. Neighbours are chosen among the nearest points of the layer so that
    no chosen one is nearer to another than to the point; free places take the next nearest, and half
    of all places are kept for the way back."""

    def __init__(self, x: np.ndarray, degree: int = 16, near: int = 64, seed: int = 11):
        norm = (x * x).sum(1)
        self.x = x.astype(np.float32)
        lifted = np.concatenate([x, np.sqrt(np.maximum(norm.max(initial=0.0) - norm, 0))[:, None]], 1).astype(np.float32)
        level = np.floor(-np.log(1 - np.random.default_rng(seed).random(len(x))) / np.log(degree)).astype(int)
        self.layers, k = [], 0
        while k == 0 or (level >= k).sum() > degree:
            at = np.flatnonzero(level >= k)
            self.layers.append((at, self._connect(lifted[at], 2 * degree if k == 0 else degree, near)))
            k += 1

    @staticmethod
    def _connect(y: np.ndarray, places: int, near: int) -> np.ndarray:
        n, own = len(y), max(1, places // 2)
        near = min(near, n - 1)
        out = np.full((n, places), -1, np.int32)
        if near < 1:
            return out
        chosen = np.full((n, own), -1, np.int32)
        for lo in range(0, n, 256):
            s = y[lo : lo + 256] @ y.T
            s[np.arange(len(s)), np.arange(lo, lo + len(s))] = -np.inf
            c = np.argpartition(-s, near - 1, axis=1)[:, :near]
            v = np.take_along_axis(s, c, 1)
            o = np.argsort(-v, axis=1, kind="stable")
            c, v = np.take_along_axis(c, o, 1), np.take_along_axis(v, o, 1)
            among = np.einsum("qkd,qjd->qkj", y[c], y[c], optimize=True)
            taken = np.zeros(c.shape, bool)
            for k in range(near):
                clash = (taken[:, :k] & (among[:, k, :k] > v[:, k : k + 1])).any(1)
                taken[:, k] = ~clash & (taken[:, :k].sum(1) < own)
            rank = np.where(taken, 0, 1) * near + np.arange(near)  # chosen first, then the next nearest
            first = np.argsort(rank, axis=1)[:, :own]
            chosen[lo : lo + 256, : first.shape[1]] = np.take_along_axis(c, first, 1)
        out[:, :own] = chosen
        src, dst = np.repeat(np.arange(n), own), chosen.ravel()
        live = dst >= 0
        src, dst = src[live], dst[live]
        order = np.lexsort((-(y[src] * y[dst]).sum(1), dst))
        src, dst = src[order], dst[order]
        place = np.arange(len(dst)) - np.searchsorted(dst, dst)
        fits = place < places - own
        out[dst[fits], own + place[fits]] = src[fits]
        return out

    def search(self, q: np.ndarray, beam: int = 128, wide: int = 4) -> tuple[np.ndarray, np.ndarray]:
        """(ids, scores) of up to beam near points for every query at once, best first, -1 beyond."""
        q = q.astype(np.float32)
        entry = np.full((len(q), 1), self.layers[-1][0][0])  # a point has one number in all layers
        for at, flat in self.layers[:0:-1]:
            entry = at[self._beam(q, self.x[at], flat, np.searchsorted(at, entry), 8, 1)[0][:, :1]]
        return self._beam(q, self.x, self.layers[0][1], entry, beam, wide)

    @staticmethod
    def _beam(q, x, flat, entry, beam, wide):
        m, n = len(q), len(x)
        beam = min(beam, n)
        seen = np.zeros((m, n), bool)
        row = np.arange(m)[:, None]
        ids = np.full((m, beam), -1, np.int32)
        score = np.full((m, beam), -np.inf, np.float32)
        open_ = np.zeros((m, beam), bool)
        ids[:, :1], score[:, :1], open_[:, :1] = entry, (q * x[entry[:, 0]]).sum(1)[:, None], True
        seen[row, entry] = True
        live = np.arange(m)
        while len(live):
            s = np.where(open_[live], score[live], -np.inf)
            pick = np.argpartition(-s, min(wide, beam) - 1, axis=1)[:, :wide] if beam > wide else np.tile(np.arange(beam), (len(live), 1))
            good = np.take_along_axis(s, pick, 1) > -np.inf
            r = live[:, None]
            open_[r, pick] = False
            nb = np.where(good[:, :, None], flat[ids[r, pick]], -1).reshape(len(live), -1)
            nb.sort(axis=1)
            new = nb >= 0
            new[:, 1:] &= nb[:, 1:] != nb[:, :-1]
            new &= ~seen[r, nb]
            i, j = np.nonzero(new)
            seen[live[i], nb[i, j]] = True
            v = np.full(nb.shape, -np.inf, np.float32)
            v[i, j] = np.einsum("nd,nd->n", q[live[i]], x[nb[i, j]])
            all_v = np.concatenate([score[live], v], 1)
            top = np.argpartition(-all_v, beam - 1, axis=1)[:, :beam]
            ids[live] = np.take_along_axis(np.concatenate([ids[live], nb], 1), top, 1)
            score[live] = np.take_along_axis(all_v, top, 1)
            fresh = np.concatenate([open_[live], np.isfinite(v)], 1)
            open_[live] = np.take_along_axis(fresh, top, 1)
            ids[score == -np.inf] = -1
            live = live[open_[live].any(1)]
        o = np.argsort(-score, axis=1, kind="stable")
        return np.take_along_axis(ids, o, 1), np.take_along_axis(score, o, 1)


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 20, shard_rows: int = 8192, beam: int = 128, block: int = 512) -> DataFrame:
    """The k nearest rows of vectors for every row of queries (both: vec_id, embedding) by inner
    product: query_id, rank, vec_id, score; a row never answers the query of its own id.

    Equal vectors are one point that stands for its members (the k + 1 least ids are enough for any
    answer). Points are dealt to shards of about shard_rows by hash; each shard's task builds its graph
    and writes it as one row of flat arrays. Query blocks go to every shard, are searched there abreast,
    and scores of the points found are computed anew in double precision on the original vectors, so
    score is exact; the k best of all shards are merged, ties to the smaller vec_id.
    Defined cases: vectors that are null, zero, hold null or non-finite components or have an uncommon
    length neither ask nor answer; with fewer candidates than k all found are returned; an id
    that repeats stands for the least of its vectors, component by component; an empty table gives no rows; other columns are ignored.
    """
    # the key follows the vector, so an id that repeats is one vector whatever the order of arrival
    rows = materialise(valid(vectors.select("vec_id", "embedding")).groupBy("vec_id").agg(F.min(F.struct("v", "key")).alias("m")).select("vec_id", "m.v", "m.key"))
    points = classes(rows, k + 1)
    shards = max(1, -(-points.count() // shard_rows))
    asks = rows.join(queries.select(F.col("vec_id").alias("q_")).distinct(), F.col("vec_id") == F.col("q_"), "left_semi")

    def build(t: pa.Table) -> pa.Table:
        t = t.sort_by("rep")
        x = matrix(t["v"])
        g = Graph(x)
        return pa.table({
            "shard": t["shard"].slice(0, 1).combine_chunks(), "rep": pa.array([np.asarray(t["rep"]).astype(np.int64).tobytes()], pa.binary()),
            "x": pa.array([x.tobytes()], pa.binary()), "dim": pa.array([x.shape[1]], pa.int32()),
            "nodes": pa.array([[a.astype(np.int32).tobytes() for a, _ in g.layers]], pa.list_(pa.binary())),
            "flat": pa.array([[f.tobytes() for _, f in g.layers]], pa.list_(pa.binary())),
        })

    shape = "shard int, rep binary, x binary, dim int, nodes array<binary>, flat array<binary>"
    graphs = materialise(points.select(F.pmod(F.xxhash64("rep"), F.lit(shards)).cast("int").alias("shard"), "rep", "v").groupBy("shard").applyInArrow(build, shape))

    def pack(t: pa.Table) -> pa.Table:
        return pa.table({"qid": pa.array([np.asarray(t["vec_id"]).astype(np.int64).tobytes()], pa.binary()), "q": pa.array([matrix(t["v"]).tobytes()], pa.binary())})

    n_asks = asks.count()
    blocks = asks.select("vec_id", "v", F.pmod(F.xxhash64("vec_id", F.lit(1)), F.lit(max(1, -(-n_asks // block)))).alias("b")).groupBy("b").applyInArrow(pack, "qid binary, q binary")
    work = graphs.join(blocks.withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(shards - 1)))), "shard")

    def search(batches):
        built = (None, None)
        for b in batches:
            for r in b.to_pylist():
                if built[0] != r["shard"]:
                    g = Graph.__new__(Graph)
                    full = np.frombuffer(r["x"], np.float64).reshape(-1, r["dim"])
                    g.x = full.astype(np.float32)
                    nodes = [np.frombuffer(a, np.int32) for a in r["nodes"]]
                    g.layers = [(a, np.frombuffer(f, np.int32).reshape(len(a), -1)) for a, f in zip(nodes, r["flat"], strict=True)]
                    built = (r["shard"], (g, full, np.frombuffer(r["rep"], np.int64)))
                g, full, rep = built[1]
                q, qid = np.frombuffer(r["q"], np.float64).reshape(-1, r["dim"]), np.frombuffer(r["qid"], np.int64)
                ids, _ = g.search(q, max(beam, 2 * k))
                keep = min(ids.shape[1], 2 * k)
                i, j = np.nonzero(ids[:, :keep] >= 0)
                at = ids[i, j]
                yield pa.record_batch([pa.array(qid[i]), pa.array(rep[at]), pa.array(np.einsum("nd,nd->n", q[i], full[at]))], names=["query_id", "rep", "score"])

    found = work.mapInArrow(search, "query_id long, rep long, score double")
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "rep")
    # one more than k: the query's own class may hold no one else
    found = found.withColumn("r", F.row_number().over(best)).where(F.col("r") <= k + 1).drop("r")
    full = found.join(points.select("rep", F.explode("least").alias("vec_id")).hint("merge"), "rep").where("vec_id <> query_id")
    final = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return full.withColumn("rank", F.row_number().over(final)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def op3_hnsw(spark, sf_dir: str) -> DataFrame:
    v = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return nearest(v, v.where(F.col("vec_id") % 20 == 0))

"""Embedding near-dedup: iterative quantisation, multi-index Hamming tables, exact rerank."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, materialise, table
from .vectors import classes, matrix, sample_matrix, valid


def learn_rotation(x: np.ndarray, bits: int = 64, rounds: int = 40, seed: int = 3) -> tuple[np.ndarray, np.ndarray]:
    """(mean, projection) of unit vectors x to bits whose signs are the code: principal axes turned by
    the rotation that alternating least squares (signs, then orthogonal fit) finds for balanced bits."""
    mean = x.mean(0)
    c = x - mean
    bits = min(bits, x.shape[1])
    _, _, axes = np.linalg.svd(c[:20000], full_matrices=False)
    if len(axes) < bits:  # fewer samples than bits: complete the basis
        q, _ = np.linalg.qr(np.concatenate([axes.T, np.eye(x.shape[1])], 1))
        axes = q.T[:bits]
    w = axes[:bits].T
    y = c @ w
    r, _ = np.linalg.qr(np.random.default_rng(seed).standard_normal((bits, bits)))
    for _ in range(rounds):
        u, _, vt = np.linalg.svd(np.where(y @ r >= 0, 1.0, -1.0).T @ y)
        r = (u @ vt).T
    return mean, w @ r


def codes(x: np.ndarray, mean: np.ndarray, w: np.ndarray) -> np.ndarray:
    bits = (x - mean) @ w >= 0
    full = np.zeros((len(x), 64), np.uint8)
    full[:, : bits.shape[1]] = bits
    return np.packbits(full, axis=1, bitorder="little").view(np.uint64).ravel()


def plan_tables(n: int, bits: int, cosine: float, miss: float = 0.02, seed: int = 5) -> np.ndarray:
    """Masks of the index tables: each is a substring of the code of about log2(n) bits (10 at least),
    and there are enough that a pair at the threshold, whose bits differ with probability angle / pi,
    agrees in none with probability miss at most."""
    width = min(bits, max(10, math.ceil(math.log2(max(2, n)))))
    agree = (1 - math.acos(cosine) / math.pi) ** width
    count = max(4, math.ceil(math.log(miss) / math.log(1 - agree)))
    r, masks, deck = np.random.default_rng(seed), [], []
    for _ in range(count):
        if len(deck) < width:  # substrings of one shuffled code are disjoint, then it is shuffled anew
            deck = r.permutation(bits).tolist()
        masks.append(sum(1 << deck.pop() for _ in range(width)))
    return np.array(masks, np.uint64)


def _runs(*keys: np.ndarray) -> np.ndarray:
    """Start of every run of equal keys, and the end."""
    new = np.ones(len(keys[0]), bool)
    new[1:] = np.logical_or.reduce([k[1:] != k[:-1] for k in keys])
    return np.append(np.flatnonzero(new), len(new))


def near_duplicate_links(vectors: DataFrame, cosine: float = 0.95, radius: int = 16, sample: int = 20000, block: int = 1024) -> DataFrame:
    """One row per vector: vec_id, n_links, component_id, kept.

    Equal vectors are one class. Classes get binary codes from a rotation learned on a bounded sample;
    codes meet in several substring tables, and only members with a partner within radius bits in a
    table go on, with their vectors, to be compared there exactly (double precision). A pair is counted
    in the first table whose substring both share, so none is counted twice and no pair is ever a row:
    a table's bucket gives each member its count and a star forest of its links. A bucket of more than
    block members is dealt as all pairs of its blocks, so a large group is spread over many tasks.
    Defined cases: null, zero and non-finite vectors, and those of an uncommon length, have no links
    and are their own component; repeated rows of an id are members of their class each, with the same
    result; an empty table gives no rows; other columns are ignored.
    """
    rows = materialise(valid(vectors))
    each = classes(rows, 1)
    n = each.count()
    unit = lambda x: x / np.linalg.norm(x, axis=1, keepdims=True)
    x = sample_matrix(each, "v", sample)
    ids = vectors.select(F.col("vec_id"))
    if not n:
        return ids.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").cast("long").alias("component_id"), F.lit(True).alias("kept"))
    mean, w = learn_rotation(unit(x))
    masks = plan_tables(n, w.shape[1], cosine)
    sent = vectors.sparkSession.sparkContext.broadcast((mean, w, masks))

    def coded(batches):
        mean, w, masks = sent.value
        for b in batches:
            c = codes(unit(matrix(b.column(1))), mean, w)
            at = np.repeat(np.arange(len(c)), len(masks))
            t = np.tile(np.arange(len(masks), dtype=np.int32), len(c))
            yield pa.record_batch([b.column(0).take(pa.array(at)), pa.array(c[at].view(np.int64)), pa.array(t), pa.array((c[at] & masks[t]).view(np.int64))], names=["rep", "code", "t", "sub"])

    entries = each.select("rep", "v").mapInArrow(coded, "rep long, code long, t int, sub long")
    # buckets of one code don't go on
    sizes = entries.groupBy("t", "sub").agg(F.count("*").alias("n_in")).where("n_in > 1")
    entries, sizes = materialise(entries), materialise(sizes)
    parts = F.ceil(F.col("n_in") / block).cast("int")
    mine = F.pmod(F.xxhash64("rep"), F.col("parts")).cast("int")
    dealt = (
        entries.join(sizes.withColumn("parts", parts).hint("merge"), ["t", "sub"])
        .withColumn("mine", mine)
        .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
        .withColumns({"lo": F.least("mine", "other"), "hi": F.greatest("mine", "other")})
        .select("t", "sub", "lo", "hi", "mine", "rep", "code")
    )

    def pairs_of(mine, lo, hi):
        """Rows of a task that it compares: two blocks with each other, or one with itself."""
        return (np.flatnonzero(mine == lo), np.flatnonzero(mine == hi)) if lo != hi else (np.arange(len(mine)),) * 2

    def suspects(batches):
        for b in _whole(batches, 4):
            t, sub, lo, hi, mine, rep, code = (np.asarray(c) for c in b.columns)
            code = code.view(np.uint64)
            keep = np.zeros(len(rep), bool)
            cut = _runs(t, sub, lo, hi)
            for s, e in zip(cut[:-1], cut[1:], strict=True):
                if e - s < 2:
                    continue
                i, j = pairs_of(mine[s:e], lo[s], hi[s])
                for p in range(0, len(i), 512):
                    near = np.bitwise_count(code[s:e][i[p : p + 512], None] ^ code[s:e][None, j]) <= radius
                    near &= rep[s:e][i[p : p + 512], None] != rep[s:e][None, j]
                    keep[s + i[p : p + 512][near.any(1)]] = True
                    keep[s + j[near.any(0)]] = True
            yield b.filter(pa.array(keep))

    key = ["t", "sub", "lo", "hi"]
    schema = "t int, sub long, lo int, hi int, mine int, rep long, code long"
    active = materialise(dealt.repartition(*key).sortWithinPartitions(*key).mapInArrow(suspects, schema))
    full = active.join(each.select("rep", "v", "weight").hint("merge"), "rep").select(*key, "mine", "rep", "code", "weight", "v")

    def compare(batches):
        masks = sent.value[2]
        for b in _whole(batches, 4):
            t, sub, lo, hi, mine, rep, code, weight = (np.asarray(c) for c in b.columns[:8])
            code, u = code.view(np.uint64), unit(matrix(b.column(8)))
            links, least = np.zeros(len(rep), np.int64), rep.copy()
            cut = _runs(t, sub, lo, hi)
            for s, e in zip(cut[:-1], cut[1:], strict=True):
                i, j = pairs_of(mine[s:e], lo[s], hi[s])
                i, j = i + s, j + s
                while True:  # least member reachable inside this task, in rounds
                    was = least[s:e].copy()
                    first = (was == rep[s:e]).all()
                    for p in range(0, len(i), 512):
                        a = i[p : p + 512]
                        hit = (u[a] @ u[j].T >= cosine) & (rep[a][:, None] != rep[j][None, :])
                        if not hit.any():
                            continue
                        low = np.where(hit, least[j][None, :], np.iinfo(np.int64).max).min(1)
                        least[a] = np.minimum(least[a], low)
                        low = np.where(hit, least[a][:, None], np.iinfo(np.int64).max).min(0)
                        least[j] = np.minimum(least[j], low)
                        if links is not None and first:
                            y, z = np.nonzero(hit)
                            earlier = np.zeros(len(y), bool)
                            diff = code[a[y]] ^ code[j[z]]
                            for k in range(int(t[s])):
                                earlier |= (diff & masks[k]) == 0
                            y, z = a[y[~earlier]], j[z[~earlier]]
                            np.add.at(links, y, weight[z])
                            if lo[s] != hi[s]:
                                np.add.at(links, z, weight[y])
                    if (least[s:e] == was).all():
                        break
                    first = False
            some = pa.array(np.flatnonzero((links > 0) | (least != rep)))
            yield pa.record_batch([b.column(5).take(some), pa.array(links).take(some), pa.array(least).take(some)], names=["rep", "links", "least"])

    found = materialise(full.repartition(*key).sortWithinPartitions(*key).mapInArrow(compare, "rep long, links long, least long"))
    groups = components(found.select(F.col("rep").alias("a"), F.col("least").alias("b")))
    total = found.groupBy("rep").agg(F.sum("links").alias("links"))
    per_class = each.join(total, "rep", "left").join(groups.withColumnRenamed("node", "rep"), "rep", "left").select(
        "key", (F.coalesce("links", F.lit(0).cast("long")) + F.col("weight") - 1).alias("links"), F.coalesce("component", "rep").alias("component")
    )
    of_row = rows.select("vec_id", "key").join(materialise(per_class).hint("merge"), "key").select(F.col("vec_id").alias("id_"), "links", "component").distinct()
    out = ids.join(materialise(of_row), F.col("vec_id") == F.col("id_"), "left")
    own = F.coalesce("component", F.col("vec_id").cast("long"))
    return out.select("vec_id", F.coalesce("links", F.lit(0).cast("long")).alias("n_links"), own.alias("component_id"), (F.col("vec_id").eqNullSafe(own)).alias("kept"))


def _whole(batches, keys: int):
    """Joins and cuts Arrow batches so that no run of equal first keys columns is parted."""
    rest = None
    for b in batches:
        if not b.num_rows:
            continue
        if rest is not None:
            b = pa.concat_batches([rest, b])
        cols = [np.asarray(b.column(k)) for k in range(keys)]
        last = _runs(*cols)[-2]
        if last:
            yield b.slice(0, last)
        rest = b.slice(last)
    if rest is not None:
        yield rest


def op1_itq_neardup(spark, sf_dir: str) -> DataFrame:
    return near_duplicate_links(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"))

"""Repeated windows of a sequence, decided exactly without shuffling every window.

Each window is named after one part of its content, so equal windows have equal names wherever they
stand; consecutive windows of one name form a *context*, one row. Names that occur once in the corpus
settle all their windows as unique; contexts that agree as a whole settle theirs as repeated; only
what is left, a small share, is compared window by window.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import discard, doc_key, materialise

CONTEXT = T.StructType([T.StructField(n, T.LongType()) for n in ("k_id", "k_text", "x", "c")] + [T.StructField("at", T.IntegerType()), T.StructField("n", T.IntegerType()), T.StructField("multi", T.BooleanType())])
KEY = ["k_id", "k_text"]
_BASE = 0x9E3779B97F4A7C15 | 5
_INVERSE = pow(_BASE, -1, 1 << 64)


def mix(x: np.ndarray) -> np.ndarray:
    """Scrambles 64-bit words, one to one."""
    x = x ^ (x >> np.uint64(30))
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


class Powers:
    """Powers of the base and of its inverse modulo 2**64, grown on demand."""

    def __init__(self):
        self.up = self.down = np.ones(1, np.uint64)

    def to(self, n: int):
        if len(self.up) < n:
            size = 1 << int(np.ceil(np.log2(n)))
            for name, b in (("up", _BASE), ("down", _INVERSE)):
                f = np.full(size, b, np.uint64)
                f[0] = 1
                setattr(self, name, np.multiply.accumulate(f))
        return self.up, self.down


class Rolling:
    """Hashes of any stretch of a sequence of 64-bit symbols: differences of a running polynomial."""

    def __init__(self, symbols: np.ndarray, powers: Powers):
        up, self.down = powers.to(len(symbols) + 1)
        self.sums = np.zeros(len(symbols) + 1, np.uint64)
        np.cumsum(symbols * up[: len(symbols)], out=self.sums[1:])

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((self.sums[end] - self.sums[start]) * self.down[start] + (end - start).astype(np.uint64))


def context_rows(key: np.ndarray, begin: np.ndarray, first: np.ndarray, flagged: np.ndarray, width: int, whole: memoryview, size: int):
    """Contexts from the name of the window at every position.

    key: name by position; begin: position of each document, and the end; first: for each document the
    number of its windows; flagged: names that may stand twice in one context; whole: the content, size
    bytes a position, whose hash names what a context holds.
    Returns (document, position in it, windows, x, c, multi)."""
    per = np.diff(begin)
    doc = np.repeat(np.arange(len(per)), per)
    off = np.arange(len(key)) - begin[:-1][doc]
    w = np.flatnonzero(off < first[doc])
    if not len(w):
        e = np.zeros(0, np.int64)
        return e, e, e, e.astype(np.uint64), e.astype(np.uint64), e.astype(bool)
    k, d = key[w], doc[w]
    new = np.ones(len(w), bool)
    new[1:] = (k[1:] != k[:-1]) | (d[1:] != d[:-1])
    s = np.flatnonzero(new)
    n = np.diff(np.append(s, len(w)))
    at = w[s]
    digest = xxhash.xxh3_64_intdigest
    c = np.fromiter((digest(whole[a:b]) for a, b in zip((at * size).tolist(), ((at + n + width - 1) * size).tolist(), strict=True)), np.uint64, len(at))
    return d[s], off[at], n, mix(k[s]), c, np.isin(k[s], flagged) if len(flagged) else np.zeros(len(s), bool)


def to_batch(keys, d, at, n, x, c, multi) -> pa.RecordBatch:
    take = pa.array(d)
    return pa.RecordBatch.from_arrays(
        [keys[0].take(take), keys[1].take(take), pa.array(x.view(np.int64)), pa.array(c.view(np.int64)), pa.array(at.astype(np.int32)), pa.array(n.astype(np.int32)), pa.array(multi)],
        names=CONTEXT.names,
    )


def keyed(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", *doc_key(docs), "text")


def repeated_names(contexts: DataFrame, bits: int = 27) -> DataFrame:
    """The contexts whose name stands in more than one of them (or may stand twice in one), and few
    others: names are counted exactly, then set in a bitmap of 2**bits bits, the only thing that is
    broadcast. A full bitmap lets more rows pass, never fewer; what follows decides exactly."""
    named = contexts.groupBy("x").agg(F.count("*").alias("k"), F.max("multi").alias("m")).where("k > 1 or m").select("x")
    slices = 128
    per = (1 << bits) // slices

    def fill(t: pa.Table) -> pa.Table:
        slot = _slots(np.asarray(t["x"]), bits)
        cells = np.zeros(per, np.uint8)
        cells[slot % per] = 1
        return pa.table({"slice": pa.array([int(slot[0] // per)], pa.int32()), "cells": pa.array([np.packbits(cells).tobytes()], pa.binary())})

    # the slice is the top of the slot, so that a slice's rows come to one group
    top = F.shiftrightunsigned(F.col("x"), 64 - 7).cast("int")
    rows = named.select("x").withColumn("g", top).groupBy("g").applyInArrow(fill, "slice int, cells binary").collect()
    bitmap = np.zeros((slices, per // 8), np.uint8)
    for r in rows:
        bitmap[r["slice"]] |= np.frombuffer(r["cells"], np.uint8)
    sent = contexts.sparkSession.sparkContext.broadcast(bitmap)

    def keep(batches):
        flat = sent.value.ravel()
        at = CONTEXT.names.index("x")
        for b in batches:
            slot = _slots(np.asarray(b.column(at)), bits)
            yield b.filter(pa.array((flat[slot >> 3] >> (7 - (slot & 7)).astype(np.uint8)) & 1 == 1))

    return contexts.mapInArrow(keep, CONTEXT)


def _slots(x: np.ndarray, bits: int) -> np.ndarray:
    return (x.view(np.uint64) >> np.uint64(64 - bits)).astype(np.int64)


def classed(contexts: DataFrame, made: list[DataFrame]) -> DataFrame:
    """One row per (x, c): members, the first member (k_id, k_text, at), n, and for its name: classes
    and multi. Aggregations combine on the map side, so a context of a third of all documents is one
    row per task. The result, a written table, is added to made, for its later deletion."""
    each = contexts.groupBy("x", "c").agg(F.count("*").alias("members"), F.min(F.struct(*KEY, "at")).alias("first"), F.first("n").alias("n"), F.max("multi").alias("multi"))
    each = materialise(each)
    names = materialise(each.groupBy("x").agg(F.count("*").alias("classes"), F.max("multi").alias("x_multi")))
    kinds = materialise(each.drop("multi").join(names.hint("merge"), "x"))
    discard(each, names)
    made.append(kinds)
    return kinds


def per_document(spans: DataFrame) -> DataFrame:
    """Spans (k_id, k_text, at, n) gathered as one sorted array per document."""
    return spans.groupBy(*KEY).agg(F.sort_array(F.collect_list(F.struct(F.col("at").cast("int").alias("at"), F.col("n").cast("int").alias("n")))).alias("spans"))


def covered(size: int, spans, width: int) -> np.ndarray:
    """Which of size symbols lie in a window of spans (first window, number of windows)."""
    edge = np.zeros(size + 1, np.int64)
    if spans is not None and len(spans):
        a = np.array([(s["at"], s["n"]) for s in spans], np.int64)
        np.add.at(edge, a[:, 0], 1)
        np.add.at(edge, np.minimum(size, a[:, 0] + a[:, 1] + width - 1), -1)
    return np.cumsum(edge[:-1]) > 0


def window_repeats(windows: DataFrame, keep_first: bool, made: list[DataFrame]) -> DataFrame:
    """windows: (x, h, k_id, k_text, at), one row per window that is compared singly. Returns spans of
    those whose (x, h) stands elsewhere too; with keep_first the first of each stays out. The written
    tables that the result reads are added to made, for their later deletion."""
    w = materialise(windows)
    met = materialise(w.groupBy("x", "h").agg(F.count("*").alias("members"), F.min(F.struct(*KEY, "at")).alias("first")).where("members > 1"))
    made += [w, met]
    hit = w.join(met.hint("merge"), ["x", "h"])
    if keep_first:
        hit = hit.where(F.struct(*KEY, "at") != F.col("first"))
    return hit.select(*KEY, "at", F.lit(1).alias("n"))

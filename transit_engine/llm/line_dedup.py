"""Line dedup with sharded cuckoo filters in front of exact reference-count tables."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import doc_key, materialise, shield, table

_SLOTS = 4
_EDGE = " \t\n\x0b\x0c\r"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


# --- the filter ---------------------------------------------------------------------------------

def _mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit words (xor-shifts and odd multiplications)."""
    x = x.astype(np.uint64, copy=True)
    for shift, odd in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x ^= x >> np.uint64(shift)
        x *= np.uint64(odd)
    return x ^ (x >> np.uint64(31))


class CuckooFilter:
    """Buckets of four 16-bit fingerprints; a key lies in one of two buckets that its fingerprint
    links, so it can be moved, and deleted, without the key itself. Size is a power of two."""

    def __init__(self, capacity: int, cells: np.ndarray | None = None):
        buckets = 1 << max(1, int(np.ceil(np.log2(max(1, capacity) / (_SLOTS * 0.8)))))
        self.cells = np.zeros((buckets, _SLOTS), np.uint16) if cells is None else cells
        self.mask = np.uint64(len(self.cells) - 1)

    def _places(self, keys: np.ndarray):
        m = _mix(keys)
        tag = (m >> np.uint64(48)).astype(np.uint16)
        tag[tag == 0] = 1
        one = m & self.mask
        return tag, one, self._other(one, tag)

    def _other(self, bucket, tag):
        return (bucket ^ _mix(np.asarray(tag).astype(np.uint64))) & self.mask

    def contains(self, keys: np.ndarray) -> np.ndarray:
        tag, one, two = self._places(np.asarray(keys).view(np.uint64))
        t = tag[:, None]
        return ((self.cells[one] == t) | (self.cells[two] == t)).any(1)

    def insert(self, keys: np.ndarray) -> "CuckooFilter":
        """Adds each key once; returns the filter that holds them (a larger one if they didn't fit)."""
        keys = np.asarray(keys).view(np.uint64)
        for tag, one, two in zip(*(x.tolist() for x in self._places(keys)), strict=True):
            if not self._put(tag, one, two):
                raise OverflowError("cuckoo filter is full: build it with a larger capacity")
        return self

    def _put(self, tag: int, one: int, two: int) -> bool:
        for b in (one, two):
            free = np.flatnonzero(self.cells[b] == 0)
            if len(free):
                self.cells[b, free[0]] = tag
                return True
        b = one
        for step in range(500):
            slot = (tag + step) % _SLOTS
            tag, self.cells[b, slot] = int(self.cells[b, slot]), tag
            b = int(self._other(np.array([b], np.uint64), np.array([tag], np.uint16))[0])
            free = np.flatnonzero(self.cells[b] == 0)
            if len(free):
                self.cells[b, free[0]] = tag
                return True
        return False

    def delete(self, keys: np.ndarray) -> None:
        """Takes each key out once. Only keys that were inserted may be deleted."""
        keys = np.asarray(keys).view(np.uint64)
        for tag, one, two in zip(*(x.tolist() for x in self._places(keys)), strict=True):
            for b in (one, two):
                at = np.flatnonzero(self.cells[b] == tag)
                if len(at):
                    self.cells[b, at[0]] = 0
                    break

    @classmethod
    def build(cls, keys: np.ndarray) -> "CuckooFilter":
        capacity = max(8, len(keys))
        while True:
            try:
                return cls(capacity).insert(keys)
            except OverflowError:
                capacity *= 2


# --- reference counts ---------------------------------------------------------------------------

def line_key(line: Column) -> Column:
    """White space stripped at both ends, A-Z lower-cased."""
    return F.translate(F.btrim(line, F.lit(_EDGE)), _UPPER, _LOWER)


def _lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def _hashes(text: Column) -> Column:
    """For every line its key as 128 bits: array of (h1, h2), null for a key of no characters."""
    return F.transform(
        _lines(text),
        lambda x: F.transform(F.array(line_key(x)), lambda k: F.when(k != "", F.struct(F.xxhash64(k).alias("h1"), F.xxhash64(F.lit("line"), k).alias("h2"))))[0],
    )


def reference_counts(docs: DataFrame) -> DataFrame:
    """Exact table (h1, h2, n): documents (rows) that hold a line with this key. Counted per document
    once and combined before the shuffle, so a key of a third of all lines is one row per task."""
    keys = docs.select(F.explode(F.array_distinct(_hashes(F.col("text")))).alias("k")).where("k is not null")
    return keys.groupBy(F.col("k.h1").alias("h1"), F.col("k.h2").alias("h2")).agg(F.count("*").alias("n"))


def insert_documents(counts: DataFrame, docs: DataFrame) -> DataFrame:
    """Counts after docs came in."""
    return _merged(counts, reference_counts(docs))


def delete_documents(counts: DataFrame, docs: DataFrame) -> DataFrame:
    """Counts after docs, which had come in before, went out: the exact inverse of insert_documents."""
    return _merged(counts, reference_counts(docs).withColumn("n", -F.col("n")))


def _merged(counts: DataFrame, change: DataFrame) -> DataFrame:
    return counts.unionByName(change).groupBy("h1", "h2").agg(F.sum("n").alias("n")).where("n > 0")


def filters(counts: DataFrame, min_docs: int, shards: int) -> DataFrame:
    """One cuckoo filter per shard over the keys that min_docs documents hold: (shard, cells binary)."""
    hot = counts.where(F.col("n") >= min_docs).select(F.pmod("h1", F.lit(shards)).cast("int").alias("shard"), "h2")

    def build(keys: pa.Table) -> pa.Table:
        made = CuckooFilter.build(keys["h2"].to_numpy())
        return pa.table({"shard": keys["shard"].slice(0, 1).combine_chunks(), "cells": pa.array([made.cells.tobytes()], pa.binary())})

    return hot.groupBy("shard").applyInArrow(build, "shard int, cells binary")


def maintained(built: DataFrame, before: DataFrame, after: DataFrame, min_docs: int, shards: int) -> DataFrame:
    """The filters after a change of the counts, without a rebuild: keys that have come to min_docs
    documents are inserted, those that have fallen below are deleted. Only a shard that has no room
    left is built anew, from the exact table."""
    hot = lambda counts, name: counts.where(F.col("n") >= min_docs).select("h1", "h2", F.lit(True).alias(name))
    change = hot(before, "was").join(hot(after, "is"), ["h1", "h2"], "full_outer").where("was is null or is is null")
    change = change.select(F.pmod("h1", F.lit(shards)).cast("int").alias("shard"), "h2", F.col("is").isNotNull().alias("comes"))

    def run(key: tuple, old: pa.Table, keys: pa.Table) -> pa.Table:
        cells = np.frombuffer(old["cells"][0].as_py(), np.uint16).reshape(-1, _SLOTS).copy() if old.num_rows else None
        own, h, comes = CuckooFilter(8, cells), keys["h2"].to_numpy(), np.asarray(keys["comes"], bool)
        own.delete(h[~comes])
        try:
            made = own.insert(h[comes]).cells.tobytes()
        except OverflowError:
            made = None
        return pa.table({"shard": pa.array([key[0].as_py()], pa.int32()), "cells": pa.array([made], pa.binary())})

    new = materialise(built.groupBy("shard").cogroup(change.groupBy("shard")).applyInArrow(run, "shard int, cells binary"))
    full = new.where("cells is null").select("shard")
    fresh = filters(after.withColumn("shard", F.pmod("h1", F.lit(shards)).cast("int")).join(full, "shard", "left_semi"), min_docs, shards)
    return new.where("cells is not null").unionByName(fresh)


_SUSPECT = "k_id long, k_text long, h1 long, h2 long"


def _distinct_keys(docs: DataFrame) -> DataFrame:
    """(k_id, k_text, k): every document with its distinct line keys as an array."""
    return docs.select(*doc_key(docs), F.array_distinct(_hashes(F.col("text"))).alias("k"))


def _sent(docs: DataFrame, built: DataFrame, shards: int) -> DataFrame:
    """(k_id, k_text, h1, h2) of lines that the filters don't clear, once per document; the filters
    are broadcast, so only such lines are shuffled."""
    cells = {r["shard"]: r["cells"] for r in built.collect()}
    sent = docs.sparkSession.sparkContext.broadcast(cells)
    keyed = _distinct_keys(docs).select("k_id", "k_text", F.col("k.h1").alias("h1"), F.col("k.h2").alias("h2"))

    def probe(batches):
        own = {s: CuckooFilter(0, np.frombuffer(c, np.uint16).reshape(-1, _SLOTS)) for s, c in sent.value.items()}
        for b in batches:
            lists = b.column(2)
            h1, h2 = b.column(2).flatten(), b.column(3).flatten()
            row = np.repeat(np.arange(b.num_rows), np.asarray(lists.value_lengths().fill_null(0)))
            there = np.asarray(h1.is_valid())
            h1, h2 = h1.fill_null(0).to_numpy(), h2.fill_null(0).to_numpy()
            shard = h1 % shards
            hit = np.zeros(len(h1), bool)
            for s, f in own.items():
                at = np.flatnonzero((shard == s) & there)
                hit[at] = f.contains(h2[at])
            at = np.flatnonzero(hit)
            if len(at):
                take = pa.array(row[at])
                yield pa.record_batch([b.column(0).take(take), b.column(1).take(take), pa.array(h1[at]), pa.array(h2[at])], names=["k_id", "k_text", "h1", "h2"])

    return keyed.mapInArrow(probe, _SUSPECT)


def _dealt(docs: DataFrame, built: DataFrame, shards: int, salts: int = 16) -> DataFrame:
    """As _sent where the filters are too many to broadcast: lines travel to the shard of their key,
    in salted parts, so that one line of a third of all documents is spread; each part meets its
    filter at its head and streams past it."""
    k = F.explode("k").alias("k")
    lines = _distinct_keys(docs).select("k_id", "k_text", k).where("k is not null").select("k_id", "k_text", F.col("k.h1").alias("h1"), F.col("k.h2").alias("h2"))
    lines = lines.select(
        F.pmod("h1", F.lit(shards)).cast("int").alias("shard"), F.pmod(F.xxhash64("k_id", "k_text"), F.lit(salts)).cast("int").alias("salt"),
        F.lit(None).cast("binary").alias("cells"), "k_id", "k_text", "h1", "h2",
    )
    heads = built.select("shard", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"), "cells", *[F.lit(None).cast("long").alias(c) for c in ("k_id", "k_text", "h1", "h2")])

    def probe(batches):
        at_shard, own = None, None
        for b in batches:
            shard, head = np.asarray(b.column(0)), np.asarray(b.column(2).is_valid())
            cut = np.flatnonzero(np.append(True, (shard[1:] != shard[:-1]) | head[1:] | head[:-1]))
            for s, e in zip(cut, np.append(cut[1:], len(shard)), strict=True):
                if head[s]:
                    at_shard, own = shard[s], CuckooFilter(0, np.frombuffer(b.column(2)[int(s)].as_py(), np.uint16).reshape(-1, _SLOTS))
                elif own is not None and at_shard == shard[s]:
                    part = b.slice(int(s), int(e - s))
                    ok = own.contains(np.asarray(part.column(6)))
                    yield pa.RecordBatch.from_arrays([c.filter(pa.array(ok)) for c in part.columns[3:]], names=["k_id", "k_text", "h1", "h2"])

    parts = heads.unionByName(lines).repartition("shard", "salt").sortWithinPartitions("shard", "salt", F.col("cells").isNull())
    return parts.mapInArrow(probe, _SUSPECT)


def drop_common_lines(docs: DataFrame, min_docs: int = 10, counts: DataFrame | None = None, built: DataFrame | None = None, filter_bytes: int = 64 << 20, shards: int = 64) -> DataFrame:
    """docs with columns n_lines, n_dropped, kept_text (null where text was null).

    A line whose key (see line_key) at least min_docs documents hold goes from every document; keys
    of no characters never do. counts: the exact table; by default that of docs itself. built: the
    filters that maintained() keeps beside it; by default they are built from the counts.
    Lines first meet the cuckoo filters, whose false positives the exact table then clears. Filters of
    filter_bytes or less are broadcast; larger ones stay dealt, and lines are shuffled to them.
    Defined cases: null or empty text is one empty line; rows that repeat an id count as documents of
    their own and are cleaned alike; a null id works as an id; an empty table gives no rows; other
    columns pass through.
    """
    counts = materialise(counts if counts is not None else reference_counts(docs)).where(F.col("n") >= min_docs)
    built = materialise(built if built is not None else filters(counts, min_docs, shards))
    small = (built.agg(F.sum(F.length("cells"))).first()[0] or 0) <= filter_bytes
    suspects = _sent(docs, built, shards) if small else _dealt(docs, built, shards)
    found = suspects.join(counts.select("h1", "h2"), ["h1", "h2"], "left_semi")
    per_doc = found.groupBy("k_id", "k_text").agg(F.collect_set(F.struct("h1", "h2")).alias("gone_"))
    k_id, k_text = doc_key(docs)
    d = docs.withColumns({"k_id": k_id, "k_text": k_text}).join(per_doc, ["k_id", "k_text"], "left").drop("k_id", "k_text")
    both = F.arrays_zip(_lines(F.col("text")).alias("line"), _hashes(F.col("text")).alias("k"))
    stays = F.when(F.col("gone_").isNull(), _lines(F.col("text"))).otherwise(
        F.transform(F.filter(both, lambda x: x["k"].isNull() | ~F.array_contains(F.col("gone_"), x["k"])), lambda x: x["line"])
    )
    d = d.withColumn("stays_", stays).withColumn("n_lines", F.size(_lines(F.col("text"))).cast("long"))
    d = d.withColumns({"n_dropped": F.col("n_lines") - F.size("stays_"), "kept_text": F.when(F.col("text").isNotNull(), F.array_join("stays_", "\n"))})
    return d.drop("stays_", "gone_")


def op4_line_dedup(spark, sf_dir: str) -> DataFrame:
    d = drop_common_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return d.select("doc_id", "n_lines", "n_dropped", F.sha2(F.coalesce("kept_text", F.lit("")).cast("binary"), 256).alias("kept_sha256"))


def stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without their common lines; n_chars follows where it is a column."""
    d, back = shield(docs, {"n_lines", "n_dropped", "kept_text", "stays_", "gone_", "k_id", "k_text"})
    d = drop_common_lines(d).withColumn("text", F.col("kept_text"))
    if "n_chars" in docs.columns:
        d = d.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return back(d)


ORACLE = r"""
WITH l AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos FROM documents),
k AS (SELECT *, translate(regexp_replace(line, '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g'),
                          'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
c AS (SELECT key FROM k WHERE key <> '' GROUP BY key HAVING count(DISTINCT doc_id) >= 10),
j AS (SELECT k.*, c.key IS NOT NULL AS gone FROM k LEFT JOIN c ON k.key = c.key)
SELECT doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (gone)::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '')) AS kept_sha256
FROM j GROUP BY doc_id
"""

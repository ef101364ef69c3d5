"""Substring dedup by recompression: locally consistent names for token runs and pairs."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import discard, materialise, table
from .repeats import CONTEXT, KEY, Powers, Rolling, classed, context_rows, covered, keyed, mix, per_document, repeated_names, to_batch, window_repeats

_FAR = 1 << 40
_U = np.uint64


class Symbols:
    """A level of the parse of a batch of texts: names, spans [s, e) in words, and supports [a, b),
    the words that fix the symbol: any other place with these words has the same symbol there.
    A support that would need to see past a text's end is put far outside, so it fits no window."""

    def __init__(self, name, s, e, a, b, doc):
        self.name, self.s, self.e, self.a, self.b, self.doc = name, s, e, a, b, doc

    @classmethod
    def of_words(cls, h: np.ndarray, doc: np.ndarray) -> "Symbols":
        i = np.arange(len(h))
        return cls(h, i, i + 1, i, i + 1, doc)

    def _beside(self, low: bool):
        """Support of the next symbol on one side, far where the text ends."""
        x = self.a if low else self.b
        out = np.full(len(x), -_FAR if low else _FAR, np.int64)
        same = self.doc[1:] == self.doc[:-1]
        if low:
            out[1:][same] = x[:-1][same]
        else:
            out[:-1][same] = x[1:][same]
        return out

    def runs(self) -> "Symbols":
        """Every maximal run of one name becomes one symbol, named by the name and the run's length."""
        n = len(self.name)
        new = np.ones(n, bool)
        new[1:] = (self.name[1:] != self.name[:-1]) | (self.doc[1:] != self.doc[:-1])
        f = np.flatnonzero(new)
        z = np.append(f[1:], n) - 1
        size = (z - f + 1).astype(_U)
        name = np.where(size > 1, mix(self.name[f] * _U(3) + size), self.name[f])
        a, b = self._beside(True)[f], self._beside(False)[z]
        return Symbols(name, self.s[f], self.e[z], a, b, self.doc[f])

    def pairs(self, level: int) -> "Symbols":
        """Names are split in two classes by a hash; a left one followed by a right one becomes one
        symbol, named by both. What stays single also depends on the neighbour that it didn't join."""
        n = len(self.name)
        right = (mix(self.name + _U(level * 0x632BE59BD9B4E019 & (2**64 - 1))) & _U(1)).astype(bool)
        joins = np.zeros(n, bool)
        joins[:-1] = ~right[:-1] & right[1:] & (self.doc[1:] == self.doc[:-1])
        second = np.zeros(n, bool)
        second[1:] = joins[:-1]
        a = np.where(right, np.minimum(self.a, self._beside(True)), self.a)
        b = np.where(right, self.b, np.maximum(self.b, self._beside(False)))
        i = np.flatnonzero(~second)
        j = i + joins[i]
        two = j > i
        name = np.where(two, mix(self.name[i] * _U(0xD6E8FEB86659FD93) + mix(self.name[j] + _U(level))), self.name[i])
        return Symbols(name, self.s[i], self.e[j], np.where(two, self.a[i], a[i]), np.where(two, self.b[j], b[i]), self.doc[i])


def parse(h: np.ndarray, doc: np.ndarray, rounds: int) -> list[Symbols]:
    """Levels from words up: runs once, then rounds of pairs."""
    levels = [Symbols.of_words(h, doc)]
    levels.append(levels[0].runs())
    for r in range(rounds):
        levels.append(levels[-1].pairs(r + 1))
    return levels


def window_names(levels: list[Symbols], count: int, width: int) -> tuple[np.ndarray, np.ndarray]:
    """For the window at every position the name of one symbol that its words fix, from the highest
    level that has any: the one of most words, then of least name. Also the names that stand twice
    within reach of one another in a text."""
    best = np.full(count, ~_U(0), _U)
    flagged = []
    for depth, lv in reversed(list(enumerate(levels))):
        todo = best == ~_U(0)
        if not todo.any():
            break
        span = np.minimum(lv.e - lv.s, 15).astype(_U)
        key = ((_U(15) - span) << _U(60)) | (mix(lv.name + _U(depth)) >> _U(4))
        room = width - (lv.b - lv.a)
        fit = np.flatnonzero(room >= 0)
        low, top, k = lv.b[fit] - width, lv.a[fit], key[fit]
        if depth < len(levels) - 1:  # only symbols near windows that are still without a name
            ahead = np.concatenate([[0], np.cumsum(todo)])
            some = ahead[np.clip(top + 1, 0, count)] > ahead[np.clip(low, 0, count)]
            low, top, k, fit = low[some], top[some], k[some], fit[some]
        level_best = np.full(count, ~_U(0), _U)
        for o in range(width):
            p = low + o
            on = (p <= top) & (p >= 0)
            if not on.any():
                break
            np.minimum.at(level_best, p[on], k[on])
        best = np.where(todo, level_best, best)
        order = np.lexsort((lv.s[fit], k))
        ks, ss, ds = k[order], lv.s[fit][order], lv.doc[fit][order]
        near = (ks[1:] == ks[:-1]) & (ds[1:] == ds[:-1]) & (ss[1:] - ss[:-1] <= 3 * width)
        flagged.append(np.unique(ks[1:][near]))
    return best, np.unique(np.concatenate(flagged)) if flagged else np.zeros(0, _U)


def _hashes(texts: list[bytes | None]):
    digest = xxhash.xxh64_intdigest
    split = [t.split() if t else [] for t in texts]
    begin = np.concatenate([[0], np.cumsum([len(w) for w in split])])
    h = np.fromiter((digest(w) for ws in split for w in ws), _U, count=int(begin[-1]))
    return split, begin, h


def _slices(batches, column: int, size: int = 4_000_000):
    """Record batches cut so that a column of binary values holds about size bytes."""
    for whole in batches:
        got = np.cumsum(np.asarray(pa.compute.fill_null(pa.compute.binary_length(whole.column(column)), 0)))
        lo = 0
        while lo < whole.num_rows:
            hi = max(lo + 1, int(np.searchsorted(got, (got[lo - 1] if lo else 0) + size, side="right")))
            yield whole.slice(lo, hi - lo)
            lo = hi


def packed(docs: DataFrame) -> DataFrame:
    """(doc_id, k_id, k_text, z): whole texts, compressed before they are shuffled (null stays null)."""
    d = keyed(docs).select("doc_id", *KEY, F.col("text").cast("binary").alias("z"))

    def run(batches):
        press = zstandard.ZstdCompressor(level=1)
        for b in batches:
            z = [None if t is None else press.compress(t) for t in b.column(3).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[:3], pa.array(z, pa.binary())], names=b.schema.names)

    return d.mapInArrow(run, d.schema)


def _unpacked(column) -> list[bytes | None]:
    loose = zstandard.ZstdDecompressor()
    return [None if z is None else loose.decompress(z) for z in column.to_pylist()]


def word_contexts(docs: DataFrame, width: int, rounds: int) -> DataFrame:
    def run(batches):
        for b in _slices(batches, 2):
            _, begin, h = _hashes(b.column(2).to_pylist())
            if not len(h):
                continue
            doc = np.repeat(np.arange(b.num_rows), np.diff(begin))
            best, flagged = window_names(parse(h, doc, rounds), len(h), width)
            rows = context_rows(best, begin, np.maximum(np.diff(begin) - width + 1, 0), flagged, width, memoryview(h).cast("B"), 8)
            yield to_batch((b.column(0), b.column(1)), *rows)

    return keyed(docs).select(*KEY, F.col("text").cast("binary").alias("text")).mapInArrow(run, CONTEXT)


def single_windows(docs: DataFrame, reps: DataFrame, width: int) -> DataFrame:
    """(x, h, k_id, k_text, at) of every window of the contexts reps (x, k_id, k_text, at, n). A window
    that repeats within its document is given twice at most: first and last place."""
    per = reps.groupBy(*KEY).agg(F.collect_list(F.struct("x", "at", "n")).alias("spans"))
    joined = packed(docs).join(per.hint("merge"), KEY).dropDuplicates(KEY)

    def run(batches):
        powers = Powers()
        for b in _slices(batches, 2, 1_500_000):
            _, begin, h = _hashes(_unpacked(b.column(2)))
            roll = Rolling(h, powers)
            spans = b.column(3)
            own = np.repeat(np.arange(b.num_rows), np.asarray(spans.value_lengths()))
            flat = spans.flatten()
            x, at, n = (np.asarray(flat.field(k)) for k in range(3))
            n = n.astype(np.int64)
            row = np.repeat(np.arange(len(own)), n)
            pos = at[row] + np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n)
            start = begin[own[row]] + pos
            take = pa.array(own[row])
            yield pa.RecordBatch.from_arrays([pa.array(x[row]), pa.array(roll.of(start, start + width).view(np.int64)), b.column(0).take(take), b.column(1).take(take), pa.array(pos.astype(np.int32))], names=["x", "h", *KEY, "at"])

    return joined.select(*KEY, "z", "spans").mapInArrow(run, "x long, h long, k_id long, k_text long, at int")


def drop_repeats(docs: DataFrame, width: int = 20, rounds: int = 3) -> DataFrame:
    """doc_id, n_words, n_removed, kept (the words that stay, joined by one space, as bytes).

    A word goes if a window of width consecutive words covers it whose word sequence also starts
    earlier: in a document of smaller id, or before in the same one. Words are compared by 64-bit
    hashes inside groups of equal 64-bit names, i.e. by 128 bits.
    Defined cases: null and blank texts have no words; a null id is the least; rows that share id and
    text are one document and get one result each; an empty table gives no rows; other columns are
    ignored. Long texts are handled as a whole.
    """
    contexts = materialise(word_contexts(docs, width, rounds))
    some = materialise(repeated_names(contexts))
    discard(contexts)
    made = [some]
    kinds = classed(some, made)
    twice = kinds.where("members > 1").select("x", "c", "first")
    later = some.join(twice.hint("merge"), ["x", "c"]).where(F.struct(*KEY, "at") != F.col("first")).select(*KEY, "at", "n")
    mixed = materialise(kinds.where("classes > 1 or x_multi").select("x", "first.k_id", "first.k_text", "first.at", "n"))
    singles = window_repeats(single_windows(docs, mixed, width), True, made)
    spans = materialise(per_document(later.union(singles)))
    discard(mixed, *made)
    joined = packed(docs).join(spans.hint("merge"), KEY, "left").select("doc_id", "z", "spans")

    def run(batches):
        for b in _slices(batches, 1, 1_500_000):
            n, gone, kept = [], [], []
            for t, s in zip(_unpacked(b.column(1)), b.column(2).to_pylist(), strict=True):
                w = t.split() if t else []
                off = covered(len(w), s, width) if s else None
                n.append(len(w))
                gone.append(int(off.sum()) if off is not None else 0)
                kept.append(b" ".join(w if off is None else [x for x, o in zip(w, off.tolist(), strict=True) if not o]))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(kept, pa.binary())], names=["doc_id", "n_words", "n_removed", "kept"])

    fields = [T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField("kept", T.BinaryType())]
    return joined.mapInArrow(run, T.StructType([docs.schema["doc_id"], *fields]))


def op7_recompression(spark, sf_dir: str) -> DataFrame:
    d = drop_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return d.select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))

"""Suffix-array dedup: two-stage suffix sorting of the passages that may repeat."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import discard, materialise, table
from .repeats import CONTEXT, KEY, Powers, Rolling, classed, context_rows, covered, keyed, mix, per_document, repeated_names, to_batch

_U = np.uint64
_GRAM = 32


# --- sorting ------------------------------------------------------------------------------------

_POWERS = Powers()
_PACK = 7  # symbols of nine bits in a word


def _packed(t: np.ndarray, left: np.ndarray) -> np.ndarray:
    """For every place the next symbols as one number; what follows the end of a text counts as 0."""
    wide = np.append(t, np.zeros(_PACK, t.dtype)).astype(_U)
    word = np.zeros(len(t), _U)
    for k in range(_PACK):
        word = (word << _U(9)) | wide[k : k + len(t)]
    short = np.minimum(left, _PACK)
    return word & ~((_U(1) << (_U(9) * (_PACK - short).astype(_U))) - _U(1))


def _rolling(t: np.ndarray) -> Rolling:
    return Rolling(mix(np.arange(1, 258, dtype=_U))[t], _POWERS)


def ordered(pos: np.ndarray, t: np.ndarray, stop: np.ndarray, depth: int, roll: Rolling | None = None) -> np.ndarray:
    """The suffixes that start at pos in the order of their first depth symbols: sorted by a word of
    symbols, then tied ones by the next word, and so on. Of suffixes whose first depth symbols (or all, if
    fewer) have one hash a single one is sorted and the others stand with it; common prefixes are counted on the
    symbols themselves, so the hash decides no more than who stands beside whom."""
    left = stop - np.arange(len(t))
    word = _packed(t, left)
    h = (roll or _rolling(t)).of(pos, np.minimum(pos + depth, stop[pos]))
    alike = np.argsort(h, kind="stable")
    other = np.append(True, h[alike][1:] != h[alike][:-1])
    some = pos[alike[other]]
    cur = some[np.argsort(word[some])]
    group, act, at = np.zeros(len(cur), np.int64), np.arange(len(cur)), 0
    while len(act):
        p = cur[act]
        key = np.where(at < left[p], word[np.minimum(p + at, len(t) - 1)], _U(0))
        if at:
            o = np.lexsort((key, group[act]))
            cur[act], key = p[o], key[o]
        g = group[act]
        new = np.append(True, (g[1:] != g[:-1]) | (key[1:] != key[:-1]))
        start = np.flatnonzero(new)
        size = np.diff(np.append(start, len(act)))
        group[act] = act[np.repeat(start, size)]
        at += _PACK
        # suffixes that have come to their ends together, or to depth, are equal
        act = act[np.repeat(size > 1, size) & (key & _U(511) != 0)] if at < depth else act[:0]
    place = np.empty(len(t), np.int32)
    place[cur] = np.arange(len(cur), dtype=np.int32)
    return pos[alike][np.argsort(place[some][np.cumsum(other) - 1], kind="stable")]


def _joined(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(code points of texts, a separator below every byte behind each; ends, separators included)."""
    ends = np.cumsum([len(t) + 1 for t in texts])
    t = np.frombuffer(b"\0".join(texts) + b"\0", np.uint8).astype(np.int16) + 1
    t[ends - 1] = 0
    return t, ends


def two_stage_suffixes(texts: list[bytes], depth: int) -> tuple[np.ndarray, np.ndarray]:
    """(suffix array, code points) of texts joined by separators below every byte, order decided by
    the first depth bytes at least (suffixes that agree in these stand together in some order)."""
    t, ends = _joined(texts)
    return _two_stage(t, ends, np.diff(np.append(0, ends)), depth), t


def _two_stage(t: np.ndarray, ends: np.ndarray, first: np.ndarray, depth: int, roll: Rolling | None = None) -> np.ndarray:
    """The suffixes that start in the first symbols of each text (first: how many), and few others, in order.

    First stage: only suffixes that are smaller than their successor are compared. Second stage: one
    scan over the buckets of leading characters puts every other suffix in place, behind the one that
    it precedes in the text. That needs its successors up to the next that is compared, but no further."""
    if not first.any():
        return np.zeros(0, np.int64)
    stop = np.repeat(ends - 1, np.diff(np.concatenate([[0], ends])))
    # a run of one character is smaller than its successor if what ends the run is larger
    turn = np.flatnonzero(np.append(t[1:] != t[:-1], True))
    after = np.append(t, 0)[turn + 1] > t[turn]
    after[-1] = True
    smaller = np.repeat(after, np.diff(np.concatenate([[-1], turn])))
    compared = np.flatnonzero(smaller)
    begin, some = np.concatenate([[0], ends[:-1]]), first > 0
    last = compared[np.searchsorted(compared, (begin + first - 1)[some])]  # every separator is compared
    edge = np.zeros(len(t) + 1, np.int8)
    edge[begin[some]] = 1
    edge[last + 1] -= 1
    taken = np.cumsum(edge[:-1], dtype=np.int8) > 0
    sorted_ = ordered(compared[taken[compared]], t, stop, depth, roll)

    behind = taken & ~smaller
    per = np.bincount(t[taken], minlength=258)
    begin = np.concatenate([[0], np.cumsum(per)])
    sa = np.full(int(begin[-1]), -1, np.int64)
    first = t[sorted_]
    held = np.bincount(first, minlength=258)
    at = np.arange(len(sorted_)) - np.concatenate([[0], np.cumsum(held)])[first]
    sa[begin[first] + per[first] - held[first] + at] = sorted_
    fill = begin[:-1].copy()
    for c in np.flatnonzero(per).tolist():
        got = begin[c]
        while got < fill[c]:  # suffixes before others of this very bucket's first part
            seg = sa[got : fill[c]]
            got = fill[c]
            prev = seg[seg > 0] - 1
            prev = prev[(t[prev] == c) & behind[prev]]
            sa[got : got + len(prev)] = prev
            fill[c] = got + len(prev)
        prev = sa[begin[c] : begin[c + 1]]
        prev = prev[prev > 0] - 1
        prev = prev[(t[prev] > c) & behind[prev]]
        to = t[prev]
        order = np.argsort(to, kind="stable")
        prev, to = prev[order], to[order]
        many = np.bincount(to, minlength=258)
        sa[fill[to] + np.arange(len(to)) - np.concatenate([[0], np.cumsum(many)])[to]] = prev
        fill += many
    return sa


def adjacent_prefixes(sa: np.ndarray, t: np.ndarray, most: int, pair: np.ndarray | None = None) -> np.ndarray:
    """Common prefix of each listed suffix (those at pair) with the next one, counted to most at most;
    separators end it. Eight characters are compared at a time while pairs still agree."""
    raw = np.append(np.maximum(t - 1, 0).astype(np.uint8), np.zeros(most + 16, np.uint8))
    word = np.lib.stride_tricks.as_strided(raw, (len(raw) - 7, 8), (1, 1)).copy().view(np.uint64).ravel()
    sep = np.append(np.flatnonzero(t == 0), len(t))
    pair = np.arange(max(0, len(sa) - 1)) if pair is None else pair
    one, two = sa[pair], sa[pair + 1]
    out = np.zeros(len(pair), np.int64)
    room = lambda at: sep[np.searchsorted(sep, at)] - at
    limit = np.minimum(np.minimum(room(one), room(two)), most)
    live = np.arange(len(out))
    while len(live):
        diff = word[one[live] + out[live]] ^ word[two[live] + out[live]]
        same = np.where(diff == 0, 8, (np.bitwise_count((diff & (~diff + _U(1))) - _U(1)) >> 3).astype(np.int64))
        out[live] += same
        live = live[(same == 8) & (out[live] < limit[live])]
    return np.minimum(out, limit)


def alike_windows(sa: np.ndarray, t: np.ndarray, width: int, pair: np.ndarray) -> np.ndarray:
    """Whether the suffixes at pair and the next ones agree in their first width symbols, none of which is
    a separator. Pairs at one distance that follow each other share nearly all of what they compare, so such a run is
    compared as a whole; adjacent prefixes decide where one doesn't agree throughout."""
    low, high = np.minimum(sa[pair], sa[pair + 1]), np.maximum(sa[pair], sa[pair + 1])
    key = (high - low) * len(t) + low
    order = np.argsort(key)
    start = np.flatnonzero(np.append(True, np.diff(key[order]) != 1)) if len(pair) else pair
    size = np.diff(np.append(start, len(pair)))
    raw = np.maximum(t - 1, 0).astype(np.uint8).tobytes()
    at = zip(low[order[start]].tolist(), high[order[start]].tolist(), (size + width - 1).tolist(), strict=True)
    good = np.repeat(np.fromiter((raw[a : a + n] == raw[b : b + n] for a, b, n in at), bool, len(start)), size)
    out = np.empty(len(pair), bool)
    out[order] = good
    rest = np.flatnonzero(~out)
    out[rest] = adjacent_prefixes(sa, t, width, pair[rest]) >= width
    return out


def repeated_in(texts: list[bytes], width: int, twin=None) -> list[np.ndarray]:
    """For every text the starts of its windows of width bytes that start elsewhere in texts too. A
    text marked in twin stands for several equal ones: beside each of its suffixes stands that of a
    copy, and their common prefix is the whole suffix."""
    t, ends = _joined(texts)
    roll = _rolling(t)
    sa = _two_stage(t, ends, np.maximum(np.diff(np.append(0, ends)) - width, 0), width, roll)
    own = np.searchsorted(ends, sa, side="right")
    fits = sa + width < ends[own]
    sa, own = sa[fits], own[fits]
    # neighbours whose first width bytes differ in their hash can't agree in them; the rest is compared
    h = roll.of(sa, sa + width)
    pair = np.flatnonzero(h[1:] == h[:-1])
    same = np.zeros(max(0, len(sa) - 1), bool)
    same[pair] = alike_windows(sa, t, width, pair)
    hit = np.zeros(len(sa), bool) if twin is None else np.asarray(twin, bool)[own]
    hit[:-1] |= same
    hit[1:] |= same
    at = np.sort(sa[hit])
    cut = np.searchsorted(at, np.concatenate([[0], ends]))
    begin = np.concatenate([[0], ends[:-1]])
    return [at[cut[i] : cut[i + 1]] - begin[i] for i in range(len(texts))]


# --- contexts -----------------------------------------------------------------------------------

def _symbols(texts: list[bytes | None]):
    begin = np.concatenate([[0], np.cumsum([len(t) if t else 0 for t in texts])])
    flat = np.frombuffer(b"".join(t for t in texts if t), np.uint8)
    return begin, mix(np.arange(1, 257, dtype=_U))[flat]


def sliding_least(h: np.ndarray, w: int) -> np.ndarray:
    """Least of every w consecutive values: prefix and suffix minima of blocks of w meet."""
    n = len(h)
    out = n - w + 1
    if out < 1:
        return h[:0]
    pad = np.full((-n) % w, ~_U(0), _U)
    b = np.concatenate([h, pad]).reshape(-1, w)
    left = np.minimum.accumulate(b, axis=1).ravel()
    right = np.minimum.accumulate(b[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(right[:out], left[w - 1 : w - 1 + out])


def _slices(batches, column: int, size: int = 250_000):
    for whole in batches:
        got = np.cumsum(np.asarray(pa.compute.fill_null(pa.compute.binary_length(whole.column(column)), 0)))
        lo = 0
        while lo < whole.num_rows:
            hi = max(lo + 1, int(np.searchsorted(got, (got[lo - 1] if lo else 0) + size, side="right")))
            yield whole.slice(lo, hi - lo)
            lo = hi


def byte_contexts(docs: DataFrame, width: int) -> DataFrame:
    """A window is named by the least hash of its stretches of some bytes."""
    gram = min(_GRAM, width)

    def run(batches):
        powers = Powers()
        for b in _slices(batches, 2):
            begin, h = _symbols(b.column(2).to_pylist())
            if len(h) < width:
                continue
            roll = Rolling(h, powers)
            g = mix((roll.sums[gram:] - roll.sums[:-gram]) * roll.down[: len(h) - gram + 1] + _U(gram))  # roll.of at every place
            names = sliding_least(g, width - gram + 1)
            first = np.maximum(np.diff(begin) - width + 1, 0)
            names = np.append(names, np.zeros(len(h) - len(names), _U))
            whole = memoryview(b"".join(t for t in b.column(2).to_pylist() if t))
            yield to_batch((b.column(0), b.column(1)), *context_rows(names, begin, first, _often(g, names, begin, width), width, whole, 1))

    return keyed(docs).select(*KEY, F.col("text").cast("binary").alias("text")).mapInArrow(run, CONTEXT)


def _often(g: np.ndarray, names: np.ndarray, begin: np.ndarray, width: int) -> np.ndarray:
    """Window names that some text holds twice within reach, so that one context may hold both."""
    some = np.unique(names[np.append(True, names[1:] != names[:-1])])
    low = np.zeros(1 << 16, bool)
    low[some.astype(np.uint16)] = True
    at = np.flatnonzero(low[g.astype(np.uint16)])  # few others beside them
    at = at[np.isin(g[at], some)]
    order = np.lexsort((at, g[at]))
    v, p = g[at][order], at[order]
    near = (v[1:] == v[:-1]) & (p[1:] - p[:-1] <= 3 * width)
    return np.unique(v[1:][near])


REPS = "x long, c long, off int, n int"


def _passages(docs: DataFrame, reps: DataFrame) -> DataFrame:
    """Each document that holds reps (x, c, twin, k_id, k_text, at, n), once, with their list."""
    per = reps.groupBy(*KEY).agg(F.collect_list(F.struct("x", "c", "twin", "at", "n")).alias("spans"))
    d = keyed(docs).select(*KEY, F.col("text").cast("binary").alias("text"))
    return d.join(per.hint("merge"), KEY).dropDuplicates(KEY).select("text", "spans")


def sorted_spans(docs: DataFrame, reps: DataFrame, width: int, shard_bytes: int = 200_000) -> DataFrame:
    """(x, c, off, n): spans of repeated windows in the passages reps, from where they begin, by suffix
    arrays. Passages of one name go to one shard, as only they can share a window; a shard of about
    shard_bytes is sorted at once. A passage with copies (twin) enters once, for all of them."""

    def cut(batches):
        for b in batches:
            texts, spans = b.column(0).to_pylist(), b.column(1).to_pylist()
            rows = [(s["x"], s["c"], s["twin"], t[s["at"] : s["at"] + s["n"] + width - 1]) for t, ss in zip(texts, spans, strict=True) for s in ss]
            cols = list(zip(*rows, strict=True)) or [[]] * 4
            yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(cols, (pa.int64(), pa.int64(), pa.bool_(), pa.binary()), strict=True)], names=["x", "c", "twin", "part"])

    parts = _passages(docs, reps).mapInArrow(cut, "x long, c long, twin boolean, part binary")

    def flush(rows):
        if not rows:
            return
        out = []
        for (x, c, _, _), w in zip(rows, repeated_in([r[3] for r in rows], width, [r[2] for r in rows]), strict=True):
            if len(w):
                first = np.flatnonzero(np.append(True, w[1:] != w[:-1] + 1))
                out += [(x, c, int(w[s]), int(e - s)) for s, e in zip(first, np.append(first[1:], len(w)), strict=True)]
        cols = list(zip(*out, strict=True)) if out else [[]] * 4
        kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int32())
        yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(cols, kinds, strict=True)], names=["x", "c", "off", "n"])

    def sort(batches):
        rows, held = [], 0
        for b in batches:
            for r in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if held > shard_bytes and r[0] != rows[-1][0]:
                    yield from flush(rows)
                    rows, held = [], 0
                rows.append(r)
                held += len(r[3])
        yield from flush(rows)

    return parts.repartition("x").sortWithinPartitions("x").mapInArrow(sort, REPS)


def counted_windows(docs: DataFrame, reps: DataFrame, width: int, made: list[DataFrame]) -> DataFrame:
    """(x, c, off, n) as sorted_spans, for names with too many different passages for one shard: the
    windows of each passage are counted by an aggregation, which spreads over all tasks. Written
    tables that the result reads are added to made."""

    def run(batches):
        powers = Powers()
        for b in _slices(batches, 0):
            begin, h = _symbols(b.column(0).to_pylist())
            roll = Rolling(h, powers)
            spans = b.column(1)
            own = np.repeat(np.arange(b.num_rows), np.asarray(spans.value_lengths()))
            x, c, _, at, n = (np.asarray(f) for f in spans.flatten().flatten())
            n = n.astype(np.int64)
            for lo in range(0, len(own), 2000):
                m = n[lo : lo + 2000]
                row = lo + np.repeat(np.arange(len(m)), m)
                off = np.arange(len(row)) - np.repeat(np.cumsum(m) - m, m)
                start = begin[own[row]] + at[row] + off
                cols = [pa.array(x[row]), pa.array(c[row]), pa.array(off.astype(np.int32)), pa.array(roll.of(start, start + width).view(np.int64))]
                yield pa.RecordBatch.from_arrays(cols, names=["x", "c", "off", "h"])

    w = materialise(_passages(docs, reps).mapInArrow(run, "x long, c long, off int, h long"))
    met = materialise(w.groupBy("x", "h").agg(F.count("*").alias("k")).where("k > 1").select("x", "h"))
    made += [w, met]
    copies = reps.where("twin").select("x", "c", F.lit(0).alias("off"), "n")
    return w.join(met.hint("merge"), ["x", "h"]).select("x", "c", "off", F.lit(1).alias("n")).union(copies)


def drop_repeats(docs: DataFrame, width: int = 400, shard_passages: int = 4000) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept (the bytes that stay).

    A byte goes if a string of width bytes covers it that also starts anywhere else, in another
    document or the same; matches never cross documents, and overlapping ones count.
    Windows whose name stands once in the corpus are settled as unique; everything else goes through
    suffix arrays, one shard per group of names: each different passage once,
    for all its copies, and what adjacent common prefixes find in a passage holds in all of them. A name with
    more than shard_passages different passages, which would be too much for one task, is decided by
    counting its windows' hashes instead, with the same result.
    Defined cases: null text is empty; a null id is the least; rows that share id and text hold each
    other's strings and get one result each; an empty table gives no rows; other columns are ignored.
    """
    contexts = materialise(byte_contexts(docs, width))
    some = materialise(repeated_names(contexts))
    discard(contexts)
    made = [some]
    kinds = classed(some, made)
    reps = kinds.where("members > 1 or classes > 1 or x_multi").select("x", "c", (F.col("members") > 1).alias("twin"), "first.k_id", "first.k_text", "first.at", "n", "classes")
    reps = materialise(reps)
    made.append(reps)
    found = sorted_spans(docs, reps.where(F.col("classes") <= shard_passages).drop("classes"), width)
    many = reps.where(F.col("classes") > shard_passages).drop("classes")
    if many.limit(1).count():
        found = found.union(counted_windows(docs, many, width, made))
    found = materialise(found)
    made.append(found)
    spans = some.select("x", "c", *KEY, "at").join(found.hint("merge"), ["x", "c"]).select(*KEY, (F.col("at") + F.col("off")).alias("at"), "n")
    spans = materialise(per_document(spans))
    discard(*made)
    d = keyed(docs).select("doc_id", *KEY, F.col("text").cast("binary").alias("text"))
    joined = d.join(spans.hint("merge"), KEY, "left").select("doc_id", "text", "spans")

    def run(batches):
        for b in _slices(batches, 1):
            size, gone, runs, kept = [], [], [], []
            for t, s in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                t = t or b""
                size.append(len(t))
                if not s:
                    gone.append(0), runs.append(0), kept.append(t)
                    continue
                off = covered(len(t), s, width)
                gone.append(int(off.sum()))
                runs.append(int(off[0]) + int((off[1:] & ~off[:-1]).sum()))
                kept.append(np.frombuffer(t, np.uint8)[~off].tobytes())
            cols = [b.column(0), pa.array(size, pa.int64()), pa.array(gone, pa.int64()), pa.array(runs, pa.int64()), pa.array(kept, pa.binary())]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept"])

    longs = [T.StructField(n, T.LongType()) for n in ("n_bytes", "n_removed", "n_spans")]
    return joined.mapInArrow(run, T.StructType([docs.schema["doc_id"], *longs, T.StructField("kept", T.BinaryType())]))


def op2_suffix_array(spark, sf_dir: str) -> DataFrame:
    d = drop_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return d.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))

"""SentencePiece encoding and decoding: n-best segmentation over the piece lattice."""

from __future__ import annotations

import heapq
import re
import uuid
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import table

#: Where the vocabulary lies unless a caller names another file.
MODEL = "/opt/tokenizers/piece_bpe_32k.model"
_SPACE = "▁"
_OWN = "\ud800"  # stands for a U+2581 of the text itself: no Spark string holds a lone surrogate
_UNIT = re.compile(f"{_SPACE}+[^{_SPACE}\n]*|[^{_SPACE}\n]+|\n")
_ODD = np.uint64(0x9E3779B97F4A7C15)
_FALLBACK, _NONE, _BEGUN = -1, -2, -3  # a character that is no piece; nothing; what pieces only begin with


def load_vocabulary(path: str = MODEL) -> tuple[list[str], list[float], int]:
    """(pieces, scores, id of byte 0) of a SentencePiece model file with byte fallback.

    A unigram model's scores are used as they are. A merge model has ranks for scores; its pieces
    then get Zipf log probabilities, -ln(rank + 10), which order segmentations by both length and rank."""
    from sentencepiece import sentencepiece_model_pb2 as pb

    m = pb.ModelProto()
    with open(path, "rb") as f:
        m.ParseFromString(f.read())
    normal = [p.type == 1 for p in m.pieces]
    pieces = [p.piece if ok else "" for p, ok in zip(m.pieces, normal, strict=True)]
    if m.trainer_spec.model_type == 1:
        scores = [p.score for p in m.pieces]
    else:
        rank, scores = 0, []
        for ok in normal:
            scores.append(-float(np.log(rank + 10)))
            rank += ok
    byte0 = next((i for i, p in enumerate(m.pieces) if p.type == 6), len(pieces))
    return pieces, scores, byte0


class Lattice:
    """The vocabulary with a hash table from pieces to ids, and searches over units of text.

    A unit is a run of spaces with the letters after it, or a line feed; no piece crosses its ends,
    so a text's best segmentation joins those of its units."""

    def __init__(self, pieces: list[str], scores: list[float], byte0: int):
        self.pieces, self.scores, self.byte0 = pieces, np.array([*scores, min(scores) - 10.0]), byte0
        self.id_of = {p: i for i, p in enumerate(pieces) if p}
        self.raw = [bytes([i - byte0]) if byte0 <= i < byte0 + 256 else p.replace(_SPACE, " ").encode() for i, p in enumerate(pieces)]
        self.longest = max(map(len, self.id_of))
        begins = dict.fromkeys((p[:n] for p in self.id_of for n in range(1, len(p))), _BEGUN)
        keys = {}
        for p, i in (begins | self.id_of).items():
            keys[int(self._grow(np.zeros(1, np.uint64), p)[0])] = i
        assert len(keys) == len(begins | self.id_of), "two pieces or beginnings share a hash"
        bits = 19
        while True:
            self.shift, self.keys, self.ids = np.uint64(64 - bits), np.zeros((1 << bits) + 8, np.uint64), np.zeros((1 << bits) + 8, np.int32)
            if all(self._store(k, i) for k, i in keys.items()):
                break
            bits += 1

    @staticmethod
    def _grow(h, text):
        for c in text:
            h = (h + np.uint64(ord(c) + 1)) * _ODD
        return h

    def _store(self, k: int, i: int) -> bool:
        with np.errstate(over="ignore"):
            at = int((np.uint64(k) * _ODD) >> self.shift)
        for p in range(at, at + 3):
            if not self.keys[p]:
                self.keys[p], self.ids[p] = k, i
                return True
        return False

    def edges(self, cp: np.ndarray, end: np.ndarray):
        """All pieces of the units that the code points cp spell; end: for every position the end of
        its unit. (start, length, id) with id -1 where a single character is no piece. A start is left as
        soon as no piece begins with what was read from it."""
        start, length, piece = [], [], []
        at, h = np.arange(len(cp)), np.zeros(len(cp), np.uint64)
        for n in range(1, self.longest + 1):
            stay = at + n <= end[at]
            at, h = at[stay], h[stay]
            if not len(at):
                break
            h = (h + (cp[at + n - 1].astype(np.uint64) + np.uint64(1))) * _ODD
            slot = ((h * _ODD) >> self.shift).astype(np.int64)
            got = np.where(self.keys[slot] == h, self.ids[slot], np.int32(_NONE))
            for p in (1, 2):
                some = np.flatnonzero(got == _NONE)
                some = some[self.keys[slot[some] + p] == h[some]]
                got[some] = self.ids[slot[some] + p]
            known = got != _NONE
            if n == 1:
                got[got < _FALLBACK] = _FALLBACK
            hit = got >= _FALLBACK
            start.append(at[hit])
            length.append(np.full(int(hit.sum()), n))
            piece.append(got[hit])
            at, h = at[known], h[known]
        return np.concatenate(start), np.concatenate(length), np.concatenate(piece)

    def segment(self, units: list[str]):
        """Best segmentations of many units at once: (ids flat, count per unit, score per unit, loss
        of the second best per unit, inf if there is none).

        Forward scores by relative position, all units abreast; the loss of a lattice edge is what the
        best path through it lacks, and the least loss off the best path is that of the second best."""
        size = np.array([len(u) for u in units], np.int64)
        cp = np.frombuffer("".join(units).encode("utf-32-le", "surrogatepass"), np.uint32)
        first = np.concatenate([[0], np.cumsum(size)])
        unit = np.repeat(np.arange(len(units)), size)
        start, length, piece = self.edges(cp, first[1:][unit])
        u = unit[start]
        cost = self.scores[piece]
        if (piece == _FALLBACK).any():
            odd = np.flatnonzero(piece == _FALLBACK)
            c = cp[start[odd]]
            cost[odd] *= np.where(c < 0x80, 1, np.where(c < 0x800, 2, np.where((c < 0x10000), 3, 4)))
        src = start + u  # a unit of n characters has n + 1 nodes
        dst = src + length
        rel = start - first[u]
        f, b = np.full(len(cp) + len(units), -np.inf), np.full(len(cp) + len(units), -np.inf)
        head, tail = first[:-1] + np.arange(len(units)), first[1:] + np.arange(len(units))
        f[head] = 0.0
        b[tail] = 0.0
        back = np.zeros(len(f), np.int64)
        for into, frm, stage, score in ((dst, src, rel + length, f), (src, dst, -rel, b)):
            key = ((stage - stage.min()) << 37) | (into << 5) | (31 - length)
            order = np.argsort(key)  # no two edges share a key
            st, node = stage[order], into[order]
            new = np.flatnonzero(np.concatenate([[True], node[1:] != node[:-1]]))
            cuts = np.flatnonzero(np.concatenate([[True], st[new][1:] != st[new][:-1], [True]]))
            width = np.diff(np.concatenate([new, [len(order)]]))
            for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
                a, z = new[lo], (new[hi] if hi < len(new) else len(order))
                o = order[a:z]
                v = score[frm[o]] + cost[o]
                top = np.maximum.reduceat(v, new[lo:hi] - a)
                score[node[new[lo:hi]]] = top
                if score is f:
                    win = np.flatnonzero(v == np.repeat(top, width[lo:hi]))
                    n = node[a:z][win][::-1]  # ties: the longest piece, written last
                    back[n] = o[win][::-1]
        on = np.zeros(len(start), bool)
        at, live = tail.copy(), np.arange(len(units))
        while len(live):
            e = back[at]
            on[e] = True
            at = src[e]
            go = at != head[live]
            at, live = at[go], live[go]
        best = f[tail]
        loss = np.maximum(best[u] - (f[src] + cost + b[dst]), 0.0)
        loss[on] = np.inf
        second = np.full(len(units), np.inf)
        np.minimum.at(second, u, loss)
        path = np.flatnonzero(on)
        path = path[np.argsort(start[path], kind="stable")]
        ids, owner = piece[path].astype(np.int64), u[path]
        if (ids == _FALLBACK).any():
            ids, owner = self._bytes(ids, owner, cp[start[path]])
        return ids.astype(np.int32), np.bincount(owner, minlength=len(units)), best, second

    def _bytes(self, ids, owner, cp):
        out, own = [], []
        for i, o, c in zip(ids.tolist(), owner.tolist(), cp.tolist(), strict=True):
            new = [i] if i != _FALLBACK else [self.byte0 + x for x in (_SPACE if c == 0xD800 else chr(c)).encode()]
            out += new
            own += [o] * len(new)
        return np.array(out, np.int64), np.array(own, np.int64)

    def n_best(self, unit: str, n: int) -> list[tuple[float, list[int]]]:
        """The n best segmentations of a unit, best first: forward Viterbi scores, then A* from the
        unit's end to its start. What is left of a partial path is known exactly (the forward score of
        the node it has come to), so complete paths leave the queue in order of their scores."""
        size = len(unit)
        into = [[] for _ in range(size + 1)]
        for i in range(size):
            for j in range(i + 1, min(size, i + self.longest) + 1):
                if (p := self.id_of.get(unit[i:j])) is not None:
                    into[j].append((i, p, float(self.scores[p])))
                elif j == i + 1:
                    raw = _SPACE if unit[i] == _OWN else unit[i]
                    into[j].append((i, _FALLBACK, float(self.scores[_FALLBACK]) * len(raw.encode())))
        ahead = [0.0] + [-np.inf] * size
        for j in range(1, size + 1):
            ahead[j] = max(ahead[i] + s for i, _, s in into[j])
        # only a node's n best ways to the end can matter, which bounds the search where many scores tie
        out, queue, serial, seen = [], [(-ahead[size], 0, size, 0.0, None)], 0, [0] * (size + 1)
        while queue and len(out) < n:
            total, _, at, done, path = heapq.heappop(queue)
            seen[at] += 1
            if seen[at] > n:
                continue
            if at == 0:
                ids = []
                while path:
                    (i, p), path = path
                    ids += [p] if p != _FALLBACK else [self.byte0 + x for x in (_SPACE if unit[i] == _OWN else unit[i]).encode()]
                out.append((-total, ids))
                continue
            for i, p, s in into[at]:
                serial += 1
                heapq.heappush(queue, (-(ahead[i] + s + done), serial, i, done + s, ((i, p), path)))
        return out

    def spell(self, ids: list[int]) -> str:
        return b"".join(map(self.raw.__getitem__, ids)).decode("utf-8", "replace")

    def decode(self, ids) -> str:
        """The text that ids spell; the space put before the first word goes."""
        text = self.spell(list(ids))
        return text[1:] if text[:1] == " " else text


def units_of(text: str) -> list[str]:
    return _UNIT.findall(_SPACE + text.replace(_SPACE, _OWN).replace(" ", _SPACE)) if text else []


class Segmented:
    """Segmentations of the units seen so far; where there are most of them, those met only once go, then
    the rarer ones, until half are left. Frequent units are searched once, and memory stays bounded."""

    def __init__(self, lattice: Lattice, n: int, most: int = 500_000):
        self.lattice, self.n, self.most = lattice, n, most
        self.code: dict[str, int] = {}
        self.ids, self.count, self.start, self.met = np.zeros(0, np.int32), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.best, self.second, self.exact = np.zeros(0), np.zeros(0), np.zeros(0, bool)
        self.losses: dict[str, list[tuple[float, np.ndarray | None]]] = {}

    def thin(self):
        """Leaves the most frequent half of most units at most; how often they were met counts half from then on."""
        stay = np.flatnonzero(self.met > 1)
        if len(stay) > self.most // 2:
            stay = np.sort(stay[np.argpartition(-self.met[stay], self.most // 2)[: self.most // 2]])
        reps = self.count[stay]
        to = np.cumsum(reps) - reps
        self.ids = self.ids[np.repeat(self.start[stay] - to, reps) + np.arange(int(reps.sum()))]
        self.start, self.met = to, self.met[stay] // 2
        for name in ("count", "best", "second", "exact"):
            setattr(self, name, getattr(self, name)[stay])
        units = list(self.code)
        self.code = {units[k]: i for i, k in enumerate(stay.tolist())}
        self.losses = {u: x for u, x in self.losses.items() if u in self.code}

    def codes(self, split: list[list[str]]) -> np.ndarray:
        if len(self.code) > self.most:
            self.thin()
        code, old = self.code, len(self.code)
        units = list(chain.from_iterable(split))
        flat = np.fromiter(map(code.get, units, repeat(-1)), np.int64, len(units))
        if len(gap := np.flatnonzero(flat < 0)):
            unknown = [units[i] for i in gap.tolist()]
            new = list(dict.fromkeys(unknown))
            code.update(zip(new, range(old, old + len(new)), strict=True))
            self._add(new)
            flat[gap] = np.fromiter(map(code.__getitem__, unknown), np.int64, len(unknown))
        self.met += np.bincount(flat, minlength=len(self.met))
        return flat

    def _add(self, new: list[str]):
        ids, count, best, second = self.lattice.segment(new)
        self.start = np.concatenate([self.start, len(self.ids) + np.cumsum(count) - count])
        if self.lattice.spell(ids.tolist()) == self._plain(new):
            exact = np.ones(len(new), bool)
        else:
            at = np.concatenate([[0], np.cumsum(count)])
            exact = np.array([self.lattice.spell(ids[at[i] : at[i + 1]].tolist()) == self._plain([u]) for i, u in enumerate(new)])
        for name, more in (("ids", ids), ("count", count), ("best", best), ("second", second), ("exact", exact)):
            setattr(self, name, np.concatenate([getattr(self, name), more]))
        self.met = np.concatenate([self.met, np.zeros(len(new), np.int64)])

    @staticmethod
    def _plain(units: list[str]) -> str:
        return "".join(units).replace(_SPACE, " ").replace(_OWN, _SPACE)

    def alternatives(self, unit: str) -> list[tuple[float, np.ndarray | None]]:
        """(loss against the unit's best, ids) of its n best segmentations; the first is the one that ids
        has (None), also where others score the same."""
        if unit not in self.losses:
            c = self.code[unit]
            own = self.ids[self.start[c] : self.start[c] + self.count[c]].tolist()
            found = self.lattice.n_best(unit, self.n)
            rest = [(found[0][0] - s, np.array(ids, np.int32)) for s, ids in found if ids != own]
            self.losses[unit] = [(0.0, None), *rest[: self.n - 1]]
        return self.losses[unit]


def encode_batch(lattice: Lattice, texts: list[str | None], n: int = 3, seen: Segmented | None = None):
    """For every text (ids as int32 array, scores of its n best segmentations, best first; the ids of
    each; whether decoding the ids gives the text).

    Only the n - 1 units whose second segmentation loses least can differ among the n best, so the
    A* search runs on those alone. Decoding joins what units decode to, so each new unit is checked."""
    seen = seen or Segmented(lattice, n)
    split = [units_of(t or "") for t in texts]
    flat = seen.codes(split)
    out, at = [], 0
    for us in split:
        c = flat[at : at + len(us)]
        at += len(us)
        if not len(c):
            none = np.zeros(0, np.int32)
            out.append((none, [0.0], [none], True))
            continue
        reps = seen.count[c]
        base = np.repeat(seen.start[c] - (np.cumsum(reps) - reps), reps)
        got = seen.ids[base + np.arange(len(base))]
        # each alternative: its loss, and (unit, ids) of what it replaces
        total, ways = float(seen.best[c].sum()), [(0.0, ())]
        if n > 1:
            k, second = min(n - 1, len(c)), seen.second[c]
            few = np.argpartition(second, k - 1)[:k]
            for i in (i for i in few.tolist() if np.isfinite(second[i])):
                more = seen.alternatives(us[i])
                ways = sorted(((a + b, r if x is None else (*r, (i, x))) for a, r in ways for b, x in more), key=lambda w: w[0])[:n]
        ends = np.cumsum(reps)
        every = []
        for _, swaps in ways:
            parts, lo = [], 0
            for i, x in sorted(swaps, key=lambda w: w[0]):
                parts += [got[lo : ends[i] - reps[i]], x]
                lo = ends[i]
            every.append(np.concatenate([*parts, got[lo:]]) if swaps else got)
        out.append((got, [total - a for a, _ in ways], every, bool(seen.exact[c].all())))
    return out


#: What a worker process holds for the tasks that follow: the name of a job, and its vocabulary and units.
_held: list = [None, None]


def _units_held(job: str, vocabulary, n: int) -> Segmented:
    """The job's segmentations, made once per worker process and used by all its tasks."""
    if _held[0] != job:
        _held[:] = job, Segmented(Lattice(*vocabulary), n)
    return _held[1]


def encode(docs: DataFrame, n: int = 3, model: str = MODEL, chars: int = 1_000_000) -> DataFrame:
    """docs with ids (array of int), n_best (scores, best first), n_best_ids (the ids of each, so its first
    entry is ids) and round_trip (decoding gives the text).

    Whole texts; space and line feed end units. A character that is no piece is spelled in bytes, so
    decoding gives every text back exactly, also one that holds U+2581. Defined cases: null text gives
    null ids; empty text no ids and score 0; repeated rows agree; other columns pass through. Batches
    are cut at chars characters, which bounds memory (a single longer text is one batch).
    The vocabulary file is read on the driver and broadcast: its size is the file's, not the data's.
    """
    own = ("ids", "n_best", "n_best_ids", "round_trip")
    docs = docs.select(*[c for c in docs.columns if c not in own])
    at = docs.columns.index("text")
    sent = docs.sparkSession.sparkContext.broadcast(load_vocabulary(model))
    job = uuid.uuid4().hex

    def run(batches):
        seen = _units_held(job, sent.value, n)
        for whole in batches:
            lo = 0
            sizes = np.asarray(pa.compute.fill_null(pa.compute.utf8_length(whole.column(at)), 0))
            while lo < whole.num_rows:
                hi = lo + max(1, int(np.searchsorted(np.cumsum(sizes[lo : lo + 4096]), chars, side="right")))
                b = whole.slice(lo, hi - lo)
                lo = hi
                texts = b.column(at).to_pylist()
                made = encode_batch(seen.lattice, texts, n, seen)
                offsets = np.concatenate([[0], np.cumsum([len(x) for x, *_ in made])]).astype(np.int32)
                mask = pa.array([t is None for t in texts])
                ids = pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate([x for x, *_ in made])), mask=mask)
                back = [None if t is None else ok for t, (*_, ok) in zip(texts, made, strict=True)]
                flat = [x for _, _, xs, _ in made for x in xs]
                inner = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum([len(x) for x in flat])]).astype(np.int32)), pa.array(np.concatenate(flat)))
                outer = np.concatenate([[0], np.cumsum([len(xs) for _, _, xs, _ in made])]).astype(np.int32)
                every = pa.ListArray.from_arrays(pa.array(outer), inner, mask=mask)
                cols = [*b.columns, ids, pa.array([s for _, s, *_ in made], pa.list_(pa.float64())), every, pa.array(back, pa.bool_())]
                yield pa.RecordBatch.from_arrays(cols, names=[*b.schema.names, *own])

    more = [T.StructField("ids", T.ArrayType(T.IntegerType())), T.StructField("n_best", T.ArrayType(T.DoubleType())), T.StructField("n_best_ids", T.ArrayType(T.ArrayType(T.IntegerType()))), T.StructField("round_trip", T.BooleanType())]
    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, *more]))


def op5_piece_lattice(spark, sf_dir: str) -> DataFrame:
    d = encode(table(spark, sf_dir, "documents").select("doc_id", "text"))
    digest = F.sha2(F.array_join("ids", " ").cast("binary"), 256)
    every = F.sha2(F.array_join(F.transform("n_best_ids", lambda x: F.array_join(x, " ")), "\n").cast("binary"), 256)
    return d.select("doc_id", F.coalesce(F.size("ids"), F.lit(0)).cast("long").alias("n_pieces"), "n_best", digest.alias("ids_sha256"), every.alias("n_best_sha256"), "round_trip")


def stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document with its ids, and its best segmentations with their scores."""
    return encode(docs).drop("text")

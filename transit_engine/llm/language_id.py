"""Language identification: a bidirectional gated recurrent network over bytes, in numpy."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import held_out, least_hashed, shield, table

_PAD = 256


class ByteGru:
    """Two GRUs of width h read a piece of bytes in either direction; a softmax over both states
    labels every position. Parameters are float32; inputs enter as one learned row per byte value."""

    def __init__(self, classes: int, h: int = 8, seed: int = 0):
        r = np.random.default_rng(seed)
        self.h, self.k = h, classes
        f = lambda *s, scale: (r.standard_normal(s) * scale).astype(np.float32)
        self.p = {}
        for d in "fb":  # one contiguous array per gate (z update, r reset, c candidate) and direction
            for gate in "zrc":
                self.p[f"e{gate}{d}"] = f(257, h, scale=0.5)  # byte -> gate, bias included
                self.p[f"u{gate}{d}"] = f(h, h, scale=h**-0.5)
            self.p["o" + d] = f(h, classes, scale=h**-0.5)
        self.p["b"] = np.zeros(classes, np.float32)

    @staticmethod
    def _sig(x):
        np.multiply(x, 0.5, out=x)
        np.tanh(x, out=x)
        x += 1.0
        x *= 0.5
        return x

    def _gate(self, gate: str, d: str, x: np.ndarray, s: np.ndarray):
        g = self.p[f"e{gate}{d}"].take(x, 0)
        g += s @ self.p[f"u{gate}{d}"]
        return g

    def _step(self, d: str, x: np.ndarray, s: np.ndarray):
        z = self._sig(self._gate("z", d, x, s))
        r = self._sig(self._gate("r", d, x, s))
        c = self._gate("c", d, x, r * s)
        np.tanh(c, out=c)
        return z, r, c, s + z * (c - s)

    def probabilities(self, x: np.ndarray) -> np.ndarray:
        """x: (time, pieces) byte values, 256 beyond a piece's end. Per piece the sum over its
        positions of the label probabilities, (pieces, classes)."""
        t, n = x.shape
        logits = np.empty((t, n, self.k), np.float32)
        s = np.zeros((n, self.h), np.float32)
        for i in range(t):
            s = self._step("f", x[i], s)[3]
            np.matmul(s, self.p["of"], out=logits[i])
        s = np.zeros((n, self.h), np.float32)
        total = np.zeros((n, self.k), np.float64)
        for i in range(t - 1, -1, -1):
            s = self._step("b", x[i], s)[3]
            there = (x[i] != _PAD).astype(np.float32)[:, None]
            s *= there  # the backward reader starts at a piece's own end
            a = logits[i]
            a += s @ self.p["ob"]
            a += self.p["b"]
            np.clip(a, -30, 30, out=a)
            np.exp(a, out=a)
            there /= a.sum(1, keepdims=True)
            a *= there
            total += a
        return total

    def gradients(self, x: np.ndarray, y: np.ndarray):
        """Cross-entropy of every position with its piece's label: loss and gradients, by
        backpropagation through time in both directions."""
        t, n = x.shape
        h = self.h
        mask = (x != _PAD).astype(np.float32)
        states, trace = {}, {}
        for d in "fb":
            s, states[d], trace[d] = np.zeros((n, h), np.float32), [None] * t, [None] * t
            for i in range(t) if d == "f" else range(t - 1, -1, -1):
                z, r, c, new = self._step(d, x[i], s)
                if d == "b":
                    new = new * mask[i][:, None]
                trace[d][i] = (s, z, r, c)
                s = states[d][i] = new
        hf, hb = np.stack(states["f"]), np.stack(states["b"])
        a = hf @ self.p["of"] + hb @ self.p["ob"] + self.p["b"]
        a -= a.max(2, keepdims=True)
        q = np.exp(a)
        q /= q.sum(2, keepdims=True)
        loss = float(-(np.log(q[:, np.arange(n), y] + 1e-9) * mask).sum() / mask.sum())
        q[:, np.arange(n), y] -= 1
        q *= (mask / mask.sum())[:, :, None]
        g = {k: np.zeros_like(v) for k, v in self.p.items()}
        g["b"] = q.sum((0, 1))
        for d, hs in (("f", hf), ("b", hb)):
            g["o" + d] = np.einsum("tnh,tnk->hk", hs, q, optimize=True)
            back = q @ self.p["o" + d].T
            carry = np.zeros((n, h), np.float32)
            for i in range(t - 1, -1, -1) if d == "f" else range(t):
                s, z, r, c = trace[d][i]
                ds = back[i] + carry
                if d == "b":
                    ds = ds * mask[i][:, None]
                dc = ds * z * (1 - c * c)
                dz = ds * (c - s) * z * (1 - z)
                via = dc @ self.p["uc" + d].T
                dr = via * s * r * (1 - r)
                carry = ds * (1 - z) + via * r + dz @ self.p["uz" + d].T + dr @ self.p["ur" + d].T
                for gate, seen, slope in (("z", s, dz), ("r", s, dr), ("c", r * s, dc)):
                    g[f"u{gate}{d}"] += seen.T @ slope
                    np.add.at(g[f"e{gate}{d}"], x[i], slope)
        return loss, g

    def fit(self, x: np.ndarray, y: np.ndarray, steps: int, batch: int = 192, rate: float = 0.03, seed: int = 0) -> "ByteGru":
        """Adam on batches drawn with a fixed seed."""
        r = np.random.default_rng(seed)
        m, v = ({k: np.zeros_like(p) for k, p in self.p.items()} for _ in range(2))
        for step in range(1, steps + 1):
            at = r.integers(0, x.shape[1], batch)
            _, g = self.gradients(x[:, at], y[at])
            lr = rate * min(1.0, 2 * (1 - step / (steps + 1)))
            for k in self.p:
                m[k] += 0.1 * (g[k] - m[k])
                v[k] += 0.01 * (g[k] ** 2 - v[k])
                self.p[k] -= (lr * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-8)).astype(np.float32)
        return self


def pieces_of(texts: list[bytes], length: int) -> tuple[np.ndarray, np.ndarray]:
    """Cuts texts into pieces of length bytes: (length, pieces) array padded with 256, and the text of each piece."""
    sizes = np.array([len(t) for t in texts], np.int64)
    n = -(-sizes // length)
    owner = np.repeat(np.arange(len(texts)), n)
    grid = np.full(int(n.sum()) * length, _PAD, np.int16)
    start = np.concatenate([[0], np.cumsum(n)])[:-1] * length
    flat = np.frombuffer(b"".join(texts), np.uint8)
    shift = start - np.concatenate([[0], np.cumsum(sizes)])[:-1]
    grid[np.arange(len(flat)) + np.repeat(shift, sizes)] = flat
    return np.ascontiguousarray(grid.reshape(-1, length).T), owner


def train(docs: DataFrame, sample: int = 3000, piece: int = 48, steps: int = 120, h: int = 8, seed: int = 7):
    """(languages, network) from a bounded sample: the sample labelled documents of least hash that
    are not held out, one piece of 4 * piece characters of each. Only text and lang are seen."""
    use = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out(F.col("doc_id")))
    at = F.pmod(F.xxhash64("text", F.lit("at")), F.greatest(F.lit(1), F.length("text") - 4 * piece)) + 1
    n = docs.where(F.col("lang").isNotNull() & ~held_out(F.col("doc_id"))).count()
    few = least_hashed(use, F.xxhash64("text", "doc_id"), sample, n)
    some = few.select("lang", F.col("text").substr(at.cast("int"), F.lit(4 * piece)).alias("part"), "h_")
    rows = sorted(some.collect(), key=lambda r: (r["h_"], r["lang"], r["part"]))
    langs = sorted({r["lang"] for r in rows})
    if not langs:
        return [], None
    x, owner = pieces_of([r["part"].encode() for r in rows], piece)
    full = (x != _PAD).all(0)
    if full.any():
        x, owner = x[:, full], owner[full]
    y = np.array([langs.index(r["lang"]) for r in rows])[owner]
    return langs, ByteGru(len(langs), h, seed).fit(x, y, steps)


def identify(docs: DataFrame, model=None, length: int = 256, wide: int = 4096) -> DataFrame:
    """docs with lang_pred and score.

    Every byte of a text is labelled, in pieces of length bytes that start with empty states; the
    probabilities of all positions are averaged over the document and the best language wins (ties:
    the first in code point order). score is its averaged probability. Defined cases: null text and
    text without a letter give `und` with score 0, as does everything if nothing was labelled;
    repeated rows agree; other columns pass through. Work goes piece by piece in groups of wide
    pieces, so memory doesn't follow a text's length.
    """
    langs, net = model or train(docs)
    sent = docs.sparkSession.sparkContext.broadcast((langs, net))
    extra = [c for c in docs.columns if c not in ("lang_pred", "score")]
    docs = docs.select(*extra)

    def run(batches):
        langs, net = sent.value
        for whole in batches:
            for lo in range(0, whole.num_rows, 512):
                b = whole.slice(lo, 512)
                texts = b.column(at_text).cast(pa.binary()).to_pylist()
                wants = [bool(langs) and t is not None and any(c.isalpha() for c in t.decode()) for t in texts]
                own = np.flatnonzero(wants)
                pred, score = ["und"] * len(texts), np.zeros(len(texts))
                if len(own):
                    x, owner = pieces_of([texts[i] for i in own], length)
                    total = np.zeros((len(own), len(langs)))
                    for p in range(0, x.shape[1], wide):
                        np.add.at(total, owner[p : p + wide], net.probabilities(x[:, p : p + wide]))
                    total /= total.sum(1, keepdims=True)
                    for i, c, s in zip(own, total.argmax(1), total.max(1), strict=True):
                        pred[i], score[i] = langs[c], min(1.0, s)
                cols = [*b.columns, pa.array(pred, pa.string()), pa.array(score)]
                yield pa.RecordBatch.from_arrays(cols, names=[*b.schema.names, "lang_pred", "score"])

    at_text = docs.columns.index("text")
    schema = T.StructType([*docs.schema.fields, T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])
    return docs.mapInArrow(run, schema)


def op6_language_id(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    d = identify(docs.select("doc_id", "text"), train(docs))
    return d.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")


def stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a language stay; those without any (`und`) go."""
    d, back = shield(docs, {"lang_pred", "score"})
    return back(identify(d, train(docs)).where("lang_pred <> 'und'"))

"""Toxicity: a logistic model of words that is held to equal scores when identity terms are swapped or put in."""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import held_out, least_hashed, table

#: Terms for groups of people; those of one row may stand for each other in a sentence (fixed values).
IDENTITY_TERMS = (
    ("women", "men", "girls", "boys", "transgender", "nonbinary"),
    ("woman", "man", "girl", "boy", "female", "male"),
    ("muslim", "christian", "jewish", "hindu", "buddhist", "atheist"),
    ("muslims", "christians", "jews", "hindus", "buddhists", "atheists"),
    ("black", "white", "asian", "latino", "african", "european"),
    ("gay", "lesbian", "bisexual", "straight", "queer", "heterosexual"),
    ("immigrant", "refugee", "foreigner", "citizen", "native", "migrant"),
    ("disabled", "blind", "deaf", "elderly", "young", "old"),
    ("frauen", "männer", "mädchen", "jungen"),
    ("muslime", "christen", "juden", "atheisten"),
    ("ausländer", "flüchtling", "migranten", "einheimische"),
    ("femmes", "hommes", "filles", "garçons"),
    ("musulmans", "chrétiens", "juifs", "athées"),
    ("immigrés", "réfugiés", "étrangers", "citoyens"),
    ("mujeres", "hombres", "niñas", "niños"),
    ("musulmanes", "cristianos", "judíos", "ateos"),
    ("inmigrantes", "refugiados", "extranjeros", "ciudadanos"),
)
_SWAP = {t: row[(i + 1) % len(row)] for row in IDENTITY_TERMS for i, t in enumerate(row)}
_TERMS = sorted(_SWAP)
_EDGE = " .,;:!?\"'()[]{}<>*_-=/|"
_BITS = 18


def words_of(text: str | None) -> set[str]:
    """Lower-cased words of the whole text without marks at their ends, each once."""
    return {w.strip(_EDGE) for w in set((text or "").lower().split())} - {""}


def feature_ids(words: set[str], prefixes: tuple[int, ...] = (4, 5)) -> list[int]:
    """Hashed features: every word, and the first letters of longer words."""
    ids = {zlib.crc32(w.encode()) & ((1 << _BITS) - 1) for w in words}
    for n in prefixes:
        ids |= {zlib.crc32(b"^" + p.encode()) & ((1 << _BITS) - 1) for p in {w[:n] for w in words if len(w) > n}}
    return sorted(ids)


def swapped(words: set[str]) -> set[str]:
    """The words of the counterfactual text: every identity term replaced by another of its row."""
    return {_SWAP.get(w, w) for w in words}


def counterfactual_pair(words: set[str]) -> tuple[set[str], set[str]]:
    """The two texts whose scores shall agree. A text with identity terms and its swapped one; any
    other gets a mention put in: itself and the same text that also names a group, chosen by its words."""
    other = swapped(words)
    if other == words:
        other = words | {_TERMS[zlib.crc32(" ".join(sorted(words)).encode()) % len(_TERMS)]}
    return words, other


class _Rows:
    """Rows of feature ids, flat."""

    def __init__(self, rows: list[np.ndarray]):
        self.n = len(rows)
        self.at = np.repeat(np.arange(self.n), [len(r) for r in rows])
        self.ids = np.concatenate(rows) if rows else np.zeros(0, np.int64)

    def score(self, w: np.ndarray) -> np.ndarray:
        return np.bincount(self.at, w[self.ids], self.n)

    def back(self, slope: np.ndarray) -> np.ndarray:
        return np.bincount(self.ids, slope[self.at], 1 << _BITS)


def label_pull(rows: list[np.ndarray], label: np.ndarray, min_rows: int) -> np.ndarray:
    """How far each feature tells the labels apart: the size of the logarithm of its smoothed rates
    among rows of label 1 and of label 0. Features in fewer than min_rows rows have 0."""
    one, rest = (np.bincount(np.concatenate([np.zeros(0, np.int64), *(r for r, y in zip(rows, label, strict=True) if (y > 0) == k)]), minlength=1 << _BITS) for k in (True, False))
    n = (label > 0).sum()
    ratio = np.log((one + 1) / (n + 2)) - np.log((rest + 1) / (len(label) - n + 2))
    return np.abs(ratio) * (one + rest >= min_rows)


def fit(rows: list[np.ndarray], label: np.ndarray, twins: list[tuple[int, np.ndarray]], pull: float = 1.0, ridge: float = 1e-3, min_rows: int = 5, steps: int = 150, weight: float = 5.0):
    """(weights, bias) that minimise mean log loss (label 1 counts weight times) + ridge * |v|^2 + pull *
    mean squared difference of the scores of each row in twins and its counterfactual. A feature's
    weight is v times its label_pull, so that the ridge bears least on what tells the labels apart;
    one that only counterfactuals hold starts from a pull of 1 and can but come out near 0."""
    label = np.asarray(label, float)
    scale = label_pull(rows, label, min_rows)
    if twins:
        inserted = np.unique(np.concatenate([r for _, r in twins]))
        scale[inserted] = np.where(scale[inserted] == 0, 1.0, scale[inserted])
    live = scale > 0
    x = _Rows([r[live[r]] for r in rows])
    # a row and its counterfactual differ in few features; the others cancel
    mine = _Rows([d[live[d]] for i, r in twins for d in (np.setdiff1d(rows[i], r),)])
    its = _Rows([d[live[d]] for i, r in twins for d in (np.setdiff1d(r, rows[i]),)])
    v, m, q = (np.zeros(1 << _BITS) for _ in range(3))
    rate = min(max(label.mean() if len(label) else 0.5, 1e-3), 1 - 1e-3)
    b = np.log(rate / (1 - rate))
    for step in range(1, steps + 1):
        w = v * scale
        score = x.score(w)
        p = 1 / (1 + np.exp(-np.clip(score + b, -30, 30)))
        slope = (p - label) * np.where(label > 0, weight, 1.0) / max(1, len(label))
        g = x.back(slope)
        if len(twins):
            gap = 2 * pull / len(twins) * (mine.score(w) - its.score(w))
            g += mine.back(gap) - its.back(gap)
        g = g * scale + 2 * ridge * v
        m += 0.1 * (g - m)
        q += 0.02 * (g * g - q)
        v -= 0.05 * (m / (1 - 0.9**step)) / (np.sqrt(q / (1 - 0.98**step)) + 1e-6) * live
        b -= 0.5 * slope.sum()
    return (v * scale).astype(np.float32), float(b)


def train(docs: DataFrame, labels: DataFrame, sample: int = 8000, pull: float = 1.0):
    """Weights and bias from at most sample labelled documents (least hash first) that are not held
    out. Only hashed features travel to the driver, never texts, and at most sample rows of them,
    however many rows repeat an id. An id with several labels counts as label 1 if one of them is."""
    known = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    known = known.groupBy(F.col("doc_id").alias("id_")).agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
    known = least_hashed(known, F.xxhash64("id_"), sample, known.count())
    rows = docs.join(known, F.col("doc_id") == F.col("id_")).select("toxic", "text", F.xxhash64("id_", "text").alias("o"))

    def run(batches):
        for b in batches:
            own, other = [], []
            for t in b.column(1).to_pylist():
                x, y = counterfactual_pair(words_of(t))
                own.append(feature_ids(x))
                other.append(feature_ids(y))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(own, pa.list_(pa.int32())), pa.array(other, pa.list_(pa.int32())), b.column(2)], names=["toxic", "ids", "other", "o"])

    made = rows.mapInArrow(run, "toxic int, ids array<int>, other array<int>, o long")
    got = made.orderBy("o", "toxic", "ids").limit(sample).toArrow()  # in an order of its own: sums don't depend on arrival
    ids = [np.array(x, np.int64) for x in got["ids"].to_pylist()]
    twins = [(i, np.array(x, np.int64)) for i, x in enumerate(got["other"].to_pylist())]
    return fit(ids, np.array(got["toxic"].to_pylist(), float), twins, pull)


def score_toxicity(docs: DataFrame, model) -> DataFrame:
    """docs with column score: the model's probability from all words of the whole text.

    Defined cases: null and empty texts have no words and get the model's bias; with no labels at
    all the bias is 0 (score 0.5); repeated rows agree; other columns pass through."""
    sent = docs.sparkSession.sparkContext.broadcast(model)
    docs = docs.select(*[c for c in docs.columns if c != "score"])
    at = docs.columns.index("text")

    def run(batches):
        w, bias = sent.value
        for b in batches:
            s = [float(w[feature_ids(x)].sum()) + bias if (x := words_of(t)) else bias for t in b.column(at).to_pylist()]
            p = 1 / (1 + np.exp(-np.clip(np.array(s, float), -30, 30)))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(p)], names=[*b.schema.names, "score"])

    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, T.StructField("score", T.DoubleType())]))


def op9_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    d = score_toxicity(docs, train(docs, table(spark, sf_dir, "labels")))
    return d.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))

"""Mixing sources to target weights along a time-varying curriculum (native DataFrame functions only)."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, doc_key, materialise, shield, table

#: Weights by the rank of a source, repeating (fixed values of the contract).
WEIGHTS = (5, 2, 1)
#: How a source's weight tilts over training time t in 0..1, by the same rank: w(t) = w * (1 + slope * (2t - 1)).
SLOPES = (-0.5, 0.0, 0.5)


def source_targets(sizes: DataFrame, share: float = 1.5, cap: float = 2.0, weights=WEIGHTS, slopes=SLOPES) -> DataFrame:
    """Words each source shall give: (skey, source_size, target, slope).

    Budget share * all words is dealt by weight; a source gets cap * its size at most and what it
    can't take is dealt again. In closed form: order sources by cap / weight; the first k of them
    are capped, the rest share what is left at one level, for the one k where that is consistent.
    The table has one row per source, whatever the number of documents.
    """
    n = len(weights)
    s = sizes.groupBy("skey").agg(F.sum("size").alias("source_size"))
    order = Window.orderBy(F.col("skey").startswith("n"), "skey")
    rank = (F.row_number().over(order) - 1) % n
    pick = lambda values: F.element_at(F.array(*[F.lit(float(v)) for v in values]), (F.col("r") + 1).cast("int"))
    s = s.withColumn("r", rank).withColumns({"weight": pick(weights), "slope": pick(slopes), "most": F.lit(cap) * F.col("source_size")})
    up = Window.orderBy(F.col("most") / F.col("weight"), "skey")
    every = Window.partitionBy(F.lit(0))
    s = s.withColumns({
        "total": F.sum("source_size").over(every) * F.lit(share),
        "all_weight": F.sum("weight").over(every),
        "capped_before": F.coalesce(F.sum("most").over(up.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)),
        "weight_before": F.coalesce(F.sum("weight").over(up.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)),
    })
    level = (F.col("total") - F.col("capped_before")) / (F.col("all_weight") - F.col("weight_before"))
    s = s.withColumn("level", level).withColumn("fits", F.col("level") <= F.col("most") / F.col("weight"))
    s = s.withColumn("water", F.max(F.when(F.col("fits"), F.col("level"))).over(every))
    # beyond the water level every source is capped only if the budget exceeds all caps
    target = F.least(F.col("most"), F.coalesce(F.col("water") * F.col("weight"), F.col("most")))
    return s.select("skey", "source_size", target.alias("target"), "slope")


def curriculum(docs: DataFrame, share: float = 1.5, cap: float = 2.0, weights=WEIGHTS, slopes=SLOPES, bin_rows: int = 50_000, with_start: bool = False) -> DataFrame:
    """One row per row of docs: doc_id, source, size, source_size, target, taken, position.

    Within a source, documents stand in the order of an md5 of id and text. The source gives whole
    passes over all its words and one more over as many words from the front as its target still
    needs, so its taken words are its target rounded down. The running sum over that order is taken in
    two steps, so that a source or an id with a third of all rows is spread: words per (source, leading
    md5 digits) are summed first and accumulated over the digits; only rows of one digit bin, about
    bin_rows of all sources, meet in one window. The number of digits changes no result.
    position is the training time in 0..1 of the document's first pass: where the source's integrated
    weight schedule, scaled to the words that it gives, has asked for the words up to the middle of
    what is taken (closed form); passes() gives the times of all passes.
    Defined cases: null text has size 0; null source is a source of its own, last; a null id is
    ordered as an empty one; size 0 takes 0; rows that repeat an id are separate documents, in an order
    of their texts; an empty table gives no rows. Other columns are ignored.
    """
    sizes = materialise(
        docs.select(
            "doc_id", "source",
            F.when(F.col("source").isNull(), F.lit("n")).otherwise(F.concat(F.lit("m"), "source")).alias("skey"),
            F.coalesce(F.regexp_count("text", F.lit(WORD)).cast("long"), F.lit(0).cast("long")).alias("size"),
            F.md5(F.concat_ws(" ", F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.md5(F.coalesce("text", F.lit("")).cast("binary"))).cast("binary")).alias("h"),
            doc_key(docs)[1],
        )
    )
    digits = max(2, math.ceil(math.log(max(1, sizes.count()) / bin_rows, 16)))
    sizes = sizes.withColumn("bin", F.substring("h", 1, digits))
    targets = materialise(source_targets(sizes, share, cap, weights, slopes))
    bins = sizes.groupBy("skey", "bin").agg(F.sum("size").alias("bin_size"))
    before = Window.partitionBy("skey").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
    bins = bins.withColumn("bin_start", F.coalesce(F.sum("bin_size").over(before), F.lit(0).cast("long")))
    # one row per source and bin: the plan of every bin, joined to its documents
    bins = materialise(bins.join(targets, "skey").drop("bin_size"))
    inside = Window.partitionBy("skey", "bin").orderBy("h").rowsBetween(Window.unboundedPreceding, -1)
    d = sizes.join(bins, ["skey", "bin"]).withColumn("start", F.col("bin_start") + F.coalesce(F.sum("size").over(inside), F.lit(0).cast("long")))
    goal = F.floor(F.col("target")).cast("long")
    full = F.when(F.col("source_size") > 0, F.floor(goal / F.col("source_size"))).otherwise(0).cast("long")
    rest = goal - full * F.col("source_size")
    extra = F.greatest(F.lit(0).cast("long"), F.least(F.col("size"), rest - F.col("start")))
    d = d.withColumn("taken", full * F.col("size") + extra).withColumn("position", _when(F.lit(0)))
    return d.select("doc_id", "source", "size", "source_size", "target", "taken", "position", *(["start", "slope", "k_text"] if with_start else []))


def _when(before) -> Column:
    """Training time of the pass that before whole passes precede: (before * source_size + start + half
    of what the pass takes) of the target's words have been given, and the demand is inverted there."""
    now = F.greatest(F.lit(0).cast("long"), F.least(F.col("size"), F.col("taken") - before * F.col("size")))
    goal = F.greatest(F.floor("target"), F.lit(1))
    u = F.least(F.lit(1.0), (before * F.col("source_size") + F.col("start") + now / 2) / goal)
    s = F.col("slope")
    return F.when(s == 0, u).otherwise(((s - 1) + F.sqrt((1 - s) * (1 - s) + 4 * s * u)) / (2 * s))


def passes(docs: DataFrame, **more) -> DataFrame:
    """One row per pass that takes words of a document: doc_id, k_text and source (which tell rows of one id
    apart), pass (from 1), size, taken (of this pass), position. The mix in training order is this sorted by position."""
    d = curriculum(docs, with_start=True, **more).where("taken > 0")
    d = d.withColumn("pass", F.explode(F.sequence(F.lit(1), F.ceil(F.col("taken") / F.col("size")).cast("int"))))
    before = F.col("pass") - 1
    now = F.least(F.col("size"), F.col("taken") - before * F.col("size"))
    return d.select("doc_id", "k_text", "source", "pass", "size", now.alias("taken"), _when(before).alias("position"))


def op10_curriculum_mix(spark, sf_dir: str) -> DataFrame:
    d = curriculum(table(spark, sf_dir, "documents"))
    d = d.repartitionByRange("position", "doc_id").sortWithinPartitions("position", "doc_id")
    return d.select("doc_id", "size", "source_size", "target", "taken", F.round("position", 9).alias("position"))


def stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix in training order: a document that is taken twice comes twice, each pass at its own time; one
    that is not taken goes."""
    d, back = shield(docs, {"k_text_", "mixed_id", "mixed_source", "pass", "position"})
    plan = passes(docs).select(F.col("doc_id").alias("mixed_id"), F.col("k_text").alias("k_text_"), F.col("source").alias("mixed_source"), "pass", "position")
    plan = plan.dropDuplicates(["mixed_id", "k_text_", "mixed_source", "pass"])
    same = F.col("doc_id").eqNullSafe(F.col("mixed_id")) & F.col("source").eqNullSafe(F.col("mixed_source"))
    d = d.join(plan, same & (doc_key(d)[1] == F.col("k_text_")))
    return back(d.repartitionByRange("position", "doc_id", "pass").sortWithinPartitions("position", "doc_id", "pass"))


ORACLE = r"""
WITH d AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
         md5(coalesce(doc_id::VARCHAR, '') || ' ' || md5(coalesce(text, ''))) AS h FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
k AS (SELECT *, (row_number() OVER (ORDER BY source IS NULL, source) - 1) % 3 AS k FROM s),
r AS (SELECT *, CASE k WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS w, CASE k WHEN 0 THEN -0.5::DOUBLE WHEN 1 THEN 0 ELSE 0.5 END AS tilt, 2.0::DOUBLE * source_size AS most FROM k),
p AS (SELECT *, 1.5::DOUBLE * sum(source_size) OVER () AS total, sum(w) OVER () AS ws,
             coalesce(sum(most) OVER o, 0) AS cb, coalesce(sum(w) OVER o, 0) AS wb
      FROM r WINDOW o AS (ORDER BY most / w, source IS NULL, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
q AS (SELECT *, max(CASE WHEN (total - cb) / (ws - wb) <= most / w THEN (total - cb) / (ws - wb) END) OVER () AS water FROM p),
t AS (SELECT source, source_size, tilt, least(most, coalesce(water * w, most))::DOUBLE AS target FROM q),
c AS (SELECT d.*, t.source_size, t.target, t.tilt, coalesce(sum(size) OVER (PARTITION BY d.source ORDER BY h
        ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start, floor(t.target)::BIGINT AS goal
      FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
g AS (SELECT *, CASE WHEN source_size > 0 THEN goal // source_size ELSE 0 END AS passes FROM c),
x AS (SELECT *, (passes * size + greatest(0, least(size, goal - passes * source_size - start)))::BIGINT AS taken FROM g),
u AS (SELECT *, least(1.0::DOUBLE, (start + greatest(0, least(size, taken)) / 2) / greatest(goal, 1)) AS u FROM x)
SELECT doc_id, size, source_size, target, taken,
       round(CASE WHEN tilt = 0 THEN u ELSE (tilt - 1 + sqrt((1 - tilt) * (1 - tilt) + 4 * tilt * u)) / (2 * tilt) END, 9) AS position FROM u
"""

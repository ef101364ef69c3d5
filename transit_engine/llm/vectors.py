"""What the two vector operators share: valid vectors, and classes of equal ones."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import least_hashed, materialise


def valid(vectors: DataFrame) -> DataFrame:
    """(vec_id, v, key): rows whose vector is not null, not zero and has only finite components; key
    names equal vectors (128 bits as a struct). A vector of another length than the most common one
    (ties: the longest) takes no part, as no product with the others is defined."""
    v = F.col("embedding")
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    ok = v.isNotNull() & finite & F.exists(v, lambda x: x != 0)
    rows = vectors.where(ok).select("vec_id", F.transform(v, lambda x: x.cast("double") + 0.0).alias("v"))
    size = rows.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), F.desc("n")).first()
    rows = rows.where(F.size("v") == (size["n"] if size else 0))
    return rows.withColumn("key", F.struct(F.xxhash64("v").alias("a"), F.xxhash64(F.lit("v"), "v").alias("b")))


def classes(rows: DataFrame, members: int) -> DataFrame:
    """One row per distinct vector: (key, rep, weight, v, least): the least vec_id, the number of rows
    and the members least ids. Rows of a class are combined in salted parts first."""
    part = rows.groupBy("key", F.pmod(F.xxhash64("vec_id"), F.lit(64)).alias("salt")).agg(
        F.count("*").alias("w"), F.slice(F.sort_array(F.collect_list("vec_id")), 1, members).alias("ids"), F.first("v").alias("v")
    )
    made = part.groupBy("key").agg(F.sum("w").alias("weight"), F.slice(F.sort_array(F.flatten(F.collect_list("ids"))), 1, members).alias("least"), F.first("v").alias("v"))
    return materialise(made.withColumn("rep", F.col("least")[0]))


def matrix(column) -> np.ndarray:
    """A list column of equal lengths as a matrix of doubles."""
    a = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    n = len(a)
    return np.asarray(a.flatten()).reshape(n, -1).astype(np.float64) if n else np.zeros((0, 1))


def sample_matrix(df: DataFrame, column: str, rows: int) -> np.ndarray:
    """The rows vectors of least hash, on the driver: a bounded sample to fit on."""
    got = least_hashed(df.select(column), F.xxhash64(column), rows, df.count()).select(column, "h_").toArrow().sort_by("h_")
    return matrix(got[column])

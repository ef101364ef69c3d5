"""What several operators share: scratch tables, document keys, components of link graphs."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The white space of every contract: space and U+0009 to U+000D.
SPACE = r"[\x20\x09-\x0D]"
WORD = r"[^\x20\x09-\x0D]+"


def scratch_root(spark: SparkSession) -> str:
    """The shared folder for written intermediates: spark.checkpoint.dir, as the session has it.

    Only where a session names none (tests on one machine) a folder below the warehouse is set.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        have = spark.sparkContext.getCheckpointDir()
        if not have:
            spark.sparkContext.setCheckpointDir(spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_checkpoints")
            have = spark.sparkContext.getCheckpointDir()
        root = have
    return root.rstrip("/")


def materialise(df: DataFrame) -> DataFrame:
    """Writes df as Parquet into the shared scratch folder and reads it back: lineage ends there,
    lost executors cost only the files' next read, and consumers see real sizes."""
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/tables/{uuid.uuid4().hex}"
    df.write.parquet(path)
    made = spark.read.schema(df.schema).parquet(path)
    made.scratch_path = path
    return made


def discard(*made: DataFrame) -> None:
    """Deletes tables of materialise() that nothing will read again."""
    for one in made:
        spark = one.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(one.scratch_path)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shield(docs: DataFrame, own: set[str]):
    """docs with columns that bear names of own (in any case) renamed, and a function that selects the
    columns of docs, names and order restored, from what was derived from it."""
    names = {c: f"_shielded_{i}_{c}" if c.lower() in own else c for i, c in enumerate(docs.columns)}
    moved = docs.select(*[F.col(f"`{c}`").alias(n) for c, n in names.items()])
    return moved, lambda d: d.select(*[F.col(f"`{n}`").alias(c) for c, n in names.items()])


def held_out(doc_id: Column) -> Column:
    """crc32 of the id's decimal text, modulo 5, is 0; a null id is never held out."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def doc_key(df: DataFrame) -> list[Column]:
    """Two non-null longs that identify a document: its id (null: the least long) and a hash of its text.

    Rows equal in both are repeats of one document and always get the same result."""
    return [
        F.coalesce(F.col("doc_id").cast("long"), F.lit(-(2**63)).cast("long")).alias("k_id"),
        F.xxhash64(F.coalesce(F.col("text"), F.lit(""))).alias("k_text"),
    ]


def least_hashed(df: DataFrame, h: Column, rows: int, n: int) -> DataFrame:
    """The rows rows of df of least hash h (long, in column h_), where df has n rows or fewer. Only hashes
    below a bound that leaves about three times as many are sorted, as else every partition would send
    as many rows to the one place where they meet. With hashes that repeat very often it may be fewer."""
    bound = min(2**63 - 1, (3 * rows + 1000) * 2**64 // max(1, n) - 2**63)
    return df.withColumn("h_", h).where(F.col("h_") <= bound).orderBy("h_").limit(rows)


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Connected components of (a long, b long): one row (node, component = least node) for every
    node of an edge; no row for others.

    Alternates two star contractions until nothing changes. Each step needs the least neighbour of
    every node (an aggregation that combines on the map side) joined back to the edges; the minima
    are written first, so both join inputs are plain exchanges that adaptive execution may split
    where one node holds many edges. Edges stay at most as many as given, in two columns; a round's
    tables are deleted when the next has read them. The number of rounds grows with the logarithm of
    the longest chain; if max_rounds don't do, an error is raised.
    """
    e = materialise(
        edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct()
    )

    def signature(df: DataFrame) -> tuple:
        return tuple(df.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())

    before = signature(e)
    for _ in range(max_rounds):
        # large star: every node hands its larger neighbours to the least node it sees
        both = e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        seen = materialise(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")))
        grown = materialise(
            both.join(seen.hint("merge"), "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        )
        discard(e, seen)
        # small star: every node hands its smaller neighbours to the least of them
        least = materialise(grown.groupBy("u").agg(F.min("v").alias("m")))
        joined = grown.join(least.hint("merge"), "u")
        e = materialise(
            joined.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
            .union(least.select("u", F.col("m").alias("v")))
            .where("u <> v").distinct()
        )
        discard(grown, least)
        after = signature(e)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError(f"components are not settled after {max_rounds} rounds")
    nodes = e.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return nodes.union(e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())

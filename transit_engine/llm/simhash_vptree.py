"""SimHash near-dedup: fingerprints linked exactly through a vantage-point tree in Hamming space."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import components, discard, doc_key, least_hashed, materialise, shield, table

_ALL = np.uint64(0x0101010101010101)


def text_fingerprint(words: list[bytes], size: int = 3) -> int:
    """Bit b is 1 if it is set in over half of the shingles' XXH64 (seed 42); no words: 0."""
    if not words:
        return 0
    if len(words) < size:
        shingles = [b" ".join(words)]
    else:
        shingles = map(b" ".join, zip(*(words[i:] for i in range(size)), strict=False))
    digest = xxhash.xxh64_intdigest
    return majority(np.fromiter((digest(s, 42) for s in shingles), np.uint64))


def majority(h: np.ndarray) -> int:
    """Bit b is 1 if it is set in over half of the hashes; of none: 0."""
    counts = np.zeros(64, np.int64)
    for at in range(0, len(h), 1 << 15):
        counts += np.unpackbits(h[at : at + (1 << 15)].view(np.uint8), bitorder="little").reshape(-1, 64).sum(0, dtype=np.int64)
    return int(np.packbits(2 * counts > len(h), bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, size: int = 3) -> DataFrame:
    """(doc_id, fp long): the fingerprint of every row's whole text, A-Z lower-cased,
    split at white space. Null text has no words."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        for b in batches:
            out = [text_fingerprint(t.lower().split() if t else [], size) for t in b.column(1).cast(pa.binary()).to_pylist()]
            yield pa.record_batch([b.column(0), pa.array(np.array(out, np.uint64).view(np.int64))], names=["doc_id", "fp"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, fp long")


# --- the tree -----------------------------------------------------------------------------------

def build_tree(sample: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """Vantage points and radii of 2**depth - 1 inner nodes in heap order (node 1 is the root;
    children 2k: distance <= radius, 2k + 1: beyond). Fitted on a sample; any point can be placed."""
    vantage, radius = np.zeros(1 << depth, np.uint64), np.zeros(1 << depth, np.int64)
    groups = {1: sample}
    for node in range(1, 1 << depth):
        g = groups.pop(node, sample[:0])
        if not len(g):
            continue
        tries = g[:: max(1, len(g) // 8)][:8]
        d = np.bitwise_count(tries[:, None] ^ g[None, :]).astype(np.int64)
        best = int(np.argmax(d.var(1)))
        vantage[node], radius[node] = tries[best], int(np.median(d[best]))
        near = d[best] <= radius[node]
        groups[2 * node], groups[2 * node + 1] = g[near], g[~near]
    return vantage, radius


def place(fp: np.ndarray, vantage: np.ndarray, radius: np.ndarray, reach: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, leaf) of every point: its own leaf, and leaves on the near side of a boundary that it
    lies beyond by reach or less. By the triangle inequality two points within reach of each other
    meet in a leaf: where a boundary parts them, the far one also follows the near one."""
    row, node = np.arange(len(fp)), np.ones(len(fp), np.int64)
    for _ in range(int(np.log2(len(vantage)))):
        d = np.bitwise_count(fp[row] ^ vantage[node]).astype(np.int64)
        near = d <= radius[node]
        also = ~near & (d <= radius[node] + reach)
        row, node = np.concatenate([row, row[also]]), np.concatenate([2 * node + ~near, 2 * node[also]])
    return row, node


def link_leaf(fp: np.ndarray, node_id: np.ndarray, reach: int, also: np.ndarray | None = None, also_reach: int = 64) -> tuple[np.ndarray, np.ndarray]:
    """A star forest (member, least member) of the groups that links within reach make of one leaf.
    With also (second fingerprints) a link needs those within also_reach, too.

    Points are sorted by distance to one of them; only those whose distances differ by reach or less
    can be linked (triangle bound), a contiguous run. Links are unioned block by block, never listed."""
    d = np.bitwise_count(fp ^ fp[0]).astype(np.int64)
    order = np.lexsort((node_id, d))
    fp, node_id, d = fp[order], node_id[order], d[order]
    also = also[order] if also is not None else None
    root = np.arange(len(fp))

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    ends = np.searchsorted(d, d + reach, side="right")
    block = 256
    for at in range(0, len(fp), block):
        to, end = min(at + block, len(fp)), ends[min(at + block, len(fp)) - 1]
        i, j = np.nonzero(np.bitwise_count(fp[at:to, None] ^ fp[None, at:end]) <= reach)
        later = j > i
        i, j = i[later] + at, j[later] + at
        if also is not None:
            both = np.bitwise_count(also[i] ^ also[j]) <= also_reach
            i, j = i[both], j[both]
        if len(i):
            while True:  # full compression, so that one look gives the group
                up = root[root]
                if (up == root).all():
                    break
                root = up
            a, b = root[i], root[j]
            apart = a != b
            for x, y in np.unique(np.stack([a[apart], b[apart]], 1), axis=0).tolist():
                x, y = find(x), find(y)
                if x != y:
                    root[max(x, y)] = min(x, y)
    top = np.array([find(x) for x in range(len(fp))], np.int64)
    least = np.full(len(fp), np.iinfo(np.int64).max)
    np.minimum.at(least, top, node_id)
    own = least[top]
    linked = own != node_id
    return node_id[linked], own[linked]


def links(points: DataFrame, reach: int = 3, leaf_rows: int = 2048, sample_rows: int = 1 << 16, max_depth: int = 16, also_reach: int | None = None) -> DataFrame:
    """points: (fp long, node long), distinct in both. Returns (a, b): links of nodes that join the same
    groups as all pairs of points within reach of each other would.

    With a column kind (small ints) points of different kinds never meet: each kind has a tree of its
    own. With also_reach the nodes, read as fingerprints, must lie within that of each other, too.

    Each tree is fitted on its kind's part of the sample_rows points of least hash; the nodes (at most
    2**max_depth a kind) are all that is broadcast. Every point is placed; every leaf is one group of
    the shuffle."""
    points = points.select("fp", "node", (F.col("kind") if "kind" in points.columns else F.lit(0)).cast("long").alias("kind"))
    kinds = {r["kind"]: r["n"] for r in points.groupBy("kind").agg(F.count("*").alias("n")).collect()}
    n = sum(kinds.values())
    rows = least_hashed(points.select("fp", "kind"), F.xxhash64("fp") if len(kinds) < 2 else F.xxhash64("fp", "kind"), sample_rows, n).collect()
    sample = {k: [] for k in kinds}
    for r in sorted(rows, key=lambda r: r["h_"]):
        sample[r["kind"]].append(r["fp"])
    depth = {k: min(max_depth, max(0, int(np.ceil(np.log2(max(1, m) / leaf_rows))))) for k, m in kinds.items()}
    trees = points.sparkSession.sparkContext.broadcast({k: build_tree(np.array(x, np.int64).view(np.uint64), depth[k]) for k, x in sample.items()})

    def spread(batches):
        for b in batches:
            fp, kind = b.column(0).to_numpy(zero_copy_only=False).view(np.uint64), b.column(2).to_numpy(zero_copy_only=False)
            for k in np.unique(kind).tolist():
                of_kind = np.flatnonzero(kind == k)
                row, leaf = place(fp[of_kind], *trees.value[k], reach)
                at = pa.array(of_kind[row])
                yield pa.record_batch([pa.array((k << (max_depth + 1)) + leaf), b.column(0).take(at), b.column(1).take(at)], names=["leaf", "fp", "node"])

    def link(t: pa.Table) -> pa.Table:
        node = t["node"].to_numpy()
        second = () if also_reach is None else (node.view(np.uint64), also_reach)
        a, b = link_leaf(t["fp"].to_numpy().view(np.uint64), node, reach, *second)
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    placed = points.mapInArrow(spread, "leaf long, fp long, node long")
    return placed.groupBy("leaf").applyInArrow(link, "a long, b long")


def linked_groups(points: DataFrame, reach: int = 3, **tree) -> DataFrame:
    """(node, component) for every node that some other point of links() lies within reach of, through
    chains of such links."""
    return components(links(points, reach, **tree))


def near_duplicates(docs: DataFrame, size: int = 3, reach: int = 3) -> DataFrame:
    """(doc_id, fp, component_id) of every row: component_id is the least id that links of
    fingerprints with reach or fewer differing bits lead to, its own included.

    Links are between fingerprints, never between ids: equal fingerprints are one point of the tree,
    so a group of exact copies costs one row, however large, and rows that share an id stay apart if
    their texts do. Defined cases: null or blank text has fingerprint 0, linked like any other; a null
    id is no least id (a group with no other has component null); repeated rows link with each other;
    an empty table gives no rows; columns besides doc_id and text are ignored.
    """
    prints = materialise(fingerprints(docs, size))
    points = materialise(prints.groupBy("fp").agg(F.min("doc_id").alias("least")))
    groups = linked_groups(points.select("fp", F.col("fp").alias("node")), reach)
    grouped = materialise(points.join(groups, points.fp == groups.node, "left").select("fp", "least", F.coalesce("component", "fp").alias("group")))
    least = grouped.groupBy("group").agg(F.min("least").alias("component_id"))
    of_fp = materialise(grouped.join(least.hint("merge"), "group").select("fp", "component_id"))
    discard(points, grouped)
    return prints.join(of_fp.hint("merge"), "fp").select("doc_id", "fp", "component_id")


def op8_simhash_vptree(spark, sf_dir: str) -> DataFrame:
    d = near_duplicates(table(spark, sf_dir, "documents"))
    return d.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def word_prints(docs: DataFrame, words: int, kinds: int) -> DataFrame:
    """docs (long columns, then text) with the text replaced by node, the fingerprint of its shingles of
    words words, and prints, as many fingerprints of its distinct single words as kinds says, each of
    the words' hashes mixed in another way."""
    keys = docs.columns[:-1]
    names = ", ".join(f"{c} {docs.schema[c].dataType.simpleString()}" for c in keys)
    digest = xxhash.xxh64_intdigest
    odd = [np.uint64((0x9E3779B97F4A7C15 * (2 * k + 1)) % 2**64) for k in range(kinds)]

    def run(batches):
        for b in batches:
            node, prints = [], []
            for t in b.column(len(keys)).cast(pa.binary()).to_pylist():
                w = t.lower().split() if t else []
                node.append(text_fingerprint(w, words))
                h = np.fromiter((digest(x, 42) for x in set(w)), np.uint64)
                for k in odd:
                    mixed = h * k
                    mixed = (mixed ^ (mixed >> np.uint64(32))) * k
                    prints.append(majority(mixed ^ (mixed >> np.uint64(29))))
            ends = pa.array(np.arange(0, len(prints) + 1, kinds, dtype=np.int32))
            flat = pa.array(np.array(prints, np.uint64).view(np.int64))
            made = [pa.array(np.array(node, np.uint64).view(np.int64)), pa.ListArray.from_arrays(ends, flat)]
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], *made], names=[*keys, "node", "prints"])

    return docs.mapInArrow(run, f"{names}, node long, prints array<long>")


def copy_groups(prints: DataFrame, reach: int, also_reach: int) -> DataFrame:
    """prints of word_prints(). (node, group) of every distinct node: groups are joined by links of any kind of
    print, within reach, whose nodes lie within also_reach.

    Nodes of one and the same print are linked with the least of them, where it lies within also_reach,
    before the tree sees any: a crowd of near copies comes as one point, the others stay points."""
    points = materialise(prints.select("node", F.posexplode("prints").alias("kind", "fp")).distinct())
    least = materialise(points.groupBy("kind", "fp").agg(F.min("node").alias("least")))
    led = materialise(points.join(least.hint("merge"), ["kind", "fp"]).withColumn("near", F.bit_count(F.col("node").bitwiseXOR(F.col("least"))) <= also_reach))
    heads = materialise(led.where("not near or node = least").select("fp", "node", "kind"))
    stars = led.where("near and node <> least").select(F.col("node").alias("a"), F.col("least").alias("b")).distinct()
    joined = components(stars.union(links(heads, reach, also_reach=also_reach)))
    nodes = points.select("node").distinct()
    groups = materialise(nodes.join(joined.hint("merge"), "node", "left").select("node", F.coalesce("component", "node").alias("group")))
    discard(points, least, led, heads)
    return groups


def shingle_sets(docs: DataFrame, size: int) -> DataFrame:
    """docs (long columns, then text) with the text replaced by sh: the hashes of its distinct
    shingles, as in text_fingerprint."""
    keys = docs.columns[:-1]
    kinds = ", ".join(f"{c} {docs.schema[c].dataType.simpleString()}" for c in keys)
    digest = xxhash.xxh64_intdigest

    def run(batches):
        for b in batches:
            out = []
            for t in b.column(len(keys)).cast(pa.binary()).to_pylist():
                w = t.lower().split() if t else []
                every = [b" ".join(w)] if len(w) < size else map(b" ".join, zip(*(w[i:] for i in range(size)), strict=False))
                out.append(np.unique(np.fromiter((digest(x, 42) for x in every), np.uint64)).view(np.int64))
            flat = np.concatenate([np.zeros(0, np.int64), *out])
            ends = np.concatenate([[0], np.cumsum([len(x) for x in out])]).astype(np.int32)
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))], names=[*keys, "sh"])

    return docs.mapInArrow(run, f"{kinds}, sh array<long>")


_KEPT = "group long, k_id long, k_text long, sh array<long>"


def _greedy(similarity: float):
    """Of a few documents of one group, in order, those that no earlier one that stays is similar to."""

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by([("k_id", "ascending"), ("k_text", "ascending")])
        sets, kept = [np.asarray(x.values) for x in t["sh"]], []
        for i, x in enumerate(sets):
            common = (len(np.intersect1d(x, sets[j], assume_unique=True)) for j in kept)
            if all(n < similarity * (len(x) + len(sets[j]) - n) for j, n in zip(kept, common, strict=True)):
                kept.append(i)
        return t.take(pa.array(kept, pa.int64()))

    return run


def kept_documents(docs: DataFrame, reach: int = 3, words: int = 5, similarity: float = 0.8, heads: int = 256, head_shingles: int = 1 << 22, kinds: int = 6, also_reach: int = 16) -> DataFrame:
    """(k_id, k_text) of the documents that stay: see doc_key.

    Groups of linked fingerprints are only where copies are looked for. Replacing one word changes five
    shingles but one single word, so prints of single words stay within reach where those of shingles
    do not; several kinds of them find what one misses, and the shingles' own print (also_reach: a
    similarity of 0.8 makes 9.5 of 64 bits differ on average, unrelated texts 32) keeps unrelated
    texts of like words apart. Of equal texts the least id
    stays. In a group of several texts the first heads documents (fewer, but one at least, where their
    shingles are over head_shingles together) are compared with one another; one
    whose share of common shingles of words words (Jaccard) with an earlier one that stays is similarity
    or more goes. Then every other document of the group goes that is similar to one of those that
    stay, and the rest starts over, until nothing is left. Documents go in order, so what stays does not
    depend on the size of a batch. So no document goes without one that stays
    and is that similar to it, however long the chains of links are. A round joins a group with heads
    rows at most, and adaptive execution may split its larger side; only groups of several texts get
    that far."""
    k_id, k_text = doc_key(docs)
    keyed = docs.select("doc_id", "text", k_id, k_text)
    prints = materialise(word_prints(keyed.select("k_id", "k_text", "text"), words, kinds))
    of_fp = copy_groups(prints, reach, also_reach)
    texts = materialise(prints.select("k_id", "k_text", "node").join(of_fp.hint("merge"), "node").groupBy("group", "k_text").agg(F.min("k_id").alias("k_id")))
    several = texts.groupBy("group").agg(F.count("*").alias("n")).where("n > 1").select("group")
    stays = texts.join(several.hint("merge"), "group", "left_anti").select("k_id", "k_text")
    crowd = texts.join(several.hint("merge"), "group").select(F.col("k_id").alias("i_"), F.col("k_text").alias("t_"), "group")
    same = (F.col("k_id") == F.col("i_")) & (F.col("k_text") == F.col("t_"))
    members = keyed.join(crowd.hint("merge"), same).select("group", "k_id", "k_text", "text").dropDuplicates(["k_id", "k_text"])
    live = materialise(shingle_sets(members, words))
    order = Window.partitionBy("group").orderBy("k_id", "k_text")
    while live.limit(1).count():
        few = live.withColumn("r", F.row_number().over(order)).where(F.col("r") <= heads)
        few = few.withColumn("upto", F.sum(F.size("sh").cast("long")).over(order)).where((F.col("upto") <= head_shingles) | (F.col("r") == 1)).drop("r", "upto")
        first = materialise(few.groupBy("group").applyInArrow(_greedy(similarity), _KEPT))
        stays = stays.union(first.select("k_id", "k_text"))
        both = F.size(F.array_intersect("sh", "f_sh"))
        close = live.join(first.select("group", F.col("sh").alias("f_sh")).hint("merge"), "group").where(both * (1 + similarity) >= similarity * (F.size("sh") + F.size("f_sh")) - 1e-9)
        rest = materialise(live.join(close.select("k_id", "k_text").distinct().hint("merge"), ["k_id", "k_text"], "left_anti").select(*live.columns))
        discard(live)
        live = rest
    discard(prints, of_fp)
    return stays


def stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of near-duplicates (five-word shingles, similarity of 0.8 or more, found through linked
    fingerprints) the document with the least id stays; rows that repeat a document count once."""
    stays = materialise(kept_documents(docs)).select(F.col("k_id").alias("k_id_"), F.col("k_text").alias("k_text_"))
    # repeats of one document: the last step leaves one, on the partitioning that the join has
    d, back = shield(docs, {"k_id_", "k_text_"})
    k_id, k_text = doc_key(d)
    d = d.withColumns({"k_id_": k_id, "k_text_": k_text})
    return back(d.join(stays, ["k_id_", "k_text_"], "left_semi").dropDuplicates(["k_id_", "k_text_"]))

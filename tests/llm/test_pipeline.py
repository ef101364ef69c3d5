import random
from collections import Counter

import corpus_pipeline
from test_operators import DOCS, awkward
from transit_engine.llm import language_id, line_dedup, simhash_vptree


def test_stages(spark, sf):
    rows = [r for r in awkward()]
    docs = spark.createDataFrame(rows, DOCS)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = corpus_pipeline.materialise(stage(spark, docs, sf))
        assert out.columns == docs.columns, name
        docs = out
    last = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
    assert last.count() == docs.count() and last.where("round_trip = false").count() == 0


def test_stages_on_nothing(spark, sf):
    docs = spark.createDataFrame([], DOCS)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs, sf).count() == 0


def test_run(spark, sf):
    out = corpus_pipeline.run(spark, sf)
    assert out.count() > 0 and {"doc_id", "ids"} <= set(out.columns)


def test_clean_documents_stay(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = language_id.stage(spark, docs, sf)
    assert kept.count() == docs.where("text rlike '\\\\p{L}'").count()
    assert line_dedup.stage(spark, docs, sf).count() == docs.count()


def test_shared_ids_drop_no_other_text(spark, sf):
    words = lambda k: " ".join(f"w{k}x{i}" for i in range(60))
    rows = [(None, words(1)), (None, words(2)), (None, words(1)), (3, words(2)), (4, words(3)), (4, words(4)), (5, words(5)), (6, words(5))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    kept = simhash_vptree.stage(spark, docs, sf).collect()
    assert sorted(r.text for r in kept) == sorted(words(k) for k in range(1, 6))
    assert {r.doc_id for r in kept if r.text == words(5)} == {5}


def _jaccard(a: str, b: str, n: int = 5) -> float:
    x, y = ({tuple(w[i : i + n]) for i in range(len(w) - n + 1)} or {tuple(w)} for w in (a.lower().split(), b.lower().split()))
    return len(x & y) / len(x | y)


def test_only_similar_documents_go(spark, sf):
    """Links reach far here, so groups hold texts that are no copies: none goes without a similar one that stays."""
    r = random.Random(3)
    base = [f"w{r.randrange(4000)}" for _ in range(120)]
    rows = []
    for i in range(60):
        w = list(base)
        for _ in range(i // 4):
            w[r.randrange(len(w))] = f"x{r.randrange(9999)}"
        rows.append((i, " ".join(w)))
    docs = spark.createDataFrame([*rows, (60, rows[0][1]), (61, None), (62, "")], "doc_id long, text string").repartition(3)
    text, ids = dict(rows), {}
    for k in simhash_vptree.kept_documents(docs, reach=20, heads=4).collect():
        ids[k.k_id] = 1
    assert {61}.isdisjoint({60}) and 60 not in ids and 1 < len(ids) < 60
    for i, t in rows:
        near = [j for j in ids if j in text and j <= i and _jaccard(t, text[j]) >= 0.8]
        assert near
    kept = sorted(j for j in ids if j in text)
    assert all(_jaccard(text[a], text[b]) < 0.8 for k, a in enumerate(kept) for b in kept[k + 1 :])


def test_near_copies_go(spark):
    """Copies with words replaced, similarity 0.8 to 0.95, of texts over a small vocabulary; nearly all go, nothing else."""
    r = random.Random(11)
    vocabulary = [f"v{i}" for i in range(800)]
    texts = {i: [r.choice(vocabulary) for _ in range(r.randrange(80, 400))] for i in range(600)}
    copies = {}
    for i in range(300):
        w = list(texts[i])
        while _jaccard(" ".join(texts[i]), " ".join(w)) > 0.95 - i / 2400:
            w[r.randrange(len(w))] = r.choice(vocabulary)
        if _jaccard(" ".join(texts[i]), " ".join(w)) >= 0.8:
            copies[1000 + i] = w
    rows = [(i, " ".join(w)) for i, w in (texts | copies).items()]
    kept = {k.k_id for k in simhash_vptree.kept_documents(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert set(texts) <= kept and len(copies) > 250
    assert len(set(copies) - kept) >= 0.9 * len(copies)


def test_stages_against_brute_force(spark):
    """Line dedup and near-dedup of the given documents, by plain Python."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    texts = {r.doc_id: r.text for r in docs.collect()}
    key = lambda s: s.strip(" \t\n\x0b\x0c\r").translate({c: c + 32 for c in range(65, 91)})
    n = Counter(k for t in texts.values() for k in {key(x) for x in (t or "").split("\n")} - {""})
    want = {i: None if t is None else "\n".join(x for x in t.split("\n") if not key(x) or n[key(x)] < 10) for i, t in texts.items()}
    lines = corpus_pipeline.materialise(line_dedup.stage(spark, docs, ""))
    assert {r.doc_id: r.text for r in lines.collect()} == want
    kept = {r.doc_id for r in simhash_vptree.stage(spark, lines, "").collect()}
    first = {}
    for i in sorted(want):
        first.setdefault(want[i] or "", i)
    assert kept <= set(first.values())
    for i in set(want) - kept:
        assert any(j < i and (want[j] or "") == (want[i] or "") or _jaccard(want[i] or "", want[j] or "") >= 0.8 for j in kept if j < i)


def test_batches_change_nothing(spark):
    """What near-dedup keeps does not depend on how many documents of a group are compared at once."""
    words = [f"w{i}" for i in range(60)]
    rows = [(i, " ".join(words[: 40 + i % 20] + [f"x{i // 7}"] * (i % 5))) for i in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    kept = [sorted(k.k_id for k in simhash_vptree.kept_documents(docs, reach=20, **batch).collect()) for batch in ({}, {"heads": 3}, {"head_shingles": 1})]
    assert kept[0] == kept[1] == kept[2] and 1 < len(kept[0]) < 40

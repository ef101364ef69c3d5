"""Every operator against brute force, on small tables that hold the awkward cases."""

import hashlib
import os
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest

from transit_engine.llm import curriculum_mix, hnsw, itq_neardup, language_id, line_dedup, piece_lattice, recompression, simhash_vptree, suffix_array, toxicity

DOCS = "doc_id long, text string, lang string, source string, n_chars int, k_id int, gone_ int, score double, spans int"
VECS = "vec_id long, embedding array<float>, label int"


def awkward():
    r = random.Random(5)
    words = ["la", "the", "of", "naïve", "straße", "x", "idiot", "▁odd", "日本", "Zeile"]
    say = lambda n: " ".join(r.choice(words) + str(r.randint(0, 30)) for _ in range(n))
    passage = say(90)
    texts = [say(r.randint(1, 150)) for _ in range(25)]
    texts += [say(20) + "\n" + passage + "\n" + say(30) for _ in range(12)]
    texts += [passage, passage, "a" * 3000, "la " * 700, "", None, " \n\t ", "\n\n", "Common line\n" + say(5), "x"]
    texts += [f"{say(3)}\n  COMMON LINE \t\nShared\n{say(4)}" for _ in range(12)]
    rows = [(i, t, "en", f"s{i % 4}", None, 1, None, 0.5, 3) for i, t in enumerate(texts)]
    rows[3] = (3, rows[3][1], None, None, None, 1, None, None, 3)
    return rows


@pytest.fixture(scope="module")
def rows():
    return awkward()


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, DOCS).repartition(5)


def table(df, key="doc_id"):
    return {r[key]: r for r in df.collect()}


def digest(b: bytes) -> str:
    return hashlib.sha256(b).hexdigest()


def test_lines(docs, rows):
    got = table(line_dedup.drop_common_lines(docs.drop("k_id", "gone_")))
    key = lambda s: re.sub(r"^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$", "", s).translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
    lines = {r[0]: (r[1] or "").split("\n") for r in rows}
    n = Counter(k for ls in lines.values() for k in {key(x) for x in ls})
    assert n["common line"] >= 10
    for i, ls in lines.items():
        keep = [x for x in ls if not key(x) or n[key(x)] < 10]
        assert (got[i].n_lines, got[i].n_dropped) == (len(ls), len(ls) - len(keep))
        assert (got[i].kept_text or "") == "\n".join(keep) and (got[i].kept_text is None) == (rows[i][1] is None)


def test_lines_without_filters_agree(docs):
    d = docs.select("doc_id", "text")
    a, b = line_dedup.drop_common_lines(d), line_dedup.drop_common_lines(d, filter_bytes=0)
    assert a.exceptAll(b).count() == b.exceptAll(a).count() == 0


def test_reference_counts_are_reversible(docs):
    d = docs.select("doc_id", "text")
    first, second = d.where("doc_id < 30"), d.where("doc_id >= 30")
    one = line_dedup.reference_counts(first)
    both = line_dedup.insert_documents(one, second)
    assert both.exceptAll(line_dedup.reference_counts(d)).count() == 0
    back = line_dedup.delete_documents(both, second)
    assert back.exceptAll(one).count() == one.exceptAll(back).count() == 0


def test_cuckoo_filter():
    keys = np.random.default_rng(1).integers(-(2**62), 2**62, 3000)
    f = line_dedup.CuckooFilter.build(keys)
    assert f.contains(keys).all()
    other = np.random.default_rng(2).integers(-(2**62), 2**62, 20000)
    assert f.contains(other).mean() < 0.01
    f.delete(keys[:1000])
    assert f.contains(keys[1000:]).all() and f.contains(keys[:1000]).mean() < 0.05


def test_suffixes_against_sorting():
    r = random.Random(2)
    for trial in range(40):
        ts = [bytes(r.choice(b"ab c\n\xff") for _ in range(r.randint(0, 40))) for _ in range(r.randint(1, 6))]
        ts = [b"a" * r.randint(0, 60), *ts] if trial % 3 == 0 else ts
        joined, ends = b"\0".join(ts) + b"\0", np.cumsum([len(x) + 1 for x in ts])
        suffix = lambda p, e=ends, j=joined: j[p : int(e[np.searchsorted(e, p, side="right")]) - 1]
        sa, t = suffix_array.two_stage_suffixes(ts, 10**6)
        assert sorted(sa.tolist()) == list(range(len(joined)))
        assert [suffix(p) for p in sa] == sorted(suffix(p) for p in range(len(joined)))
        lcp = suffix_array.adjacent_prefixes(sa, t, 9)
        for a, b, n in zip(sa[:-1], sa[1:], lcp, strict=True):
            assert n == min(9, len(os.path.commonprefix([suffix(a), suffix(b)])))


def test_only_windows_are_sorted(monkeypatch):
    """repeated_in against brute force; suffixes without a whole window are left out, but for a few."""
    r, sizes, sort = random.Random(5), [], suffix_array.ordered
    monkeypatch.setattr(suffix_array, "ordered", lambda pos, *a: sizes.append(len(pos)) or sort(pos, *a))
    for trial in range(60):
        width = r.choice([1, 3, 8, 30])
        part = [bytes(r.choice(b"ab\0\xff"[: r.randint(1, 4)]) for _ in range(r.randint(0, 40))) for _ in range(4)]
        ts = [b"".join(r.choice(part) for _ in range(r.randint(0, 4))) for _ in range(r.randint(1, 6))]
        n = Counter(t[i : i + width] for t in ts for i in range(len(t) - width + 1))
        got = suffix_array.repeated_in(ts, width)
        assert [g.tolist() for g in got] == [[i for i in range(len(t) - width + 1) if n[t[i : i + width]] > 1] for t in ts], (trial, ts)
    sizes.clear()
    assert not any(map(len, suffix_array.repeated_in([bytes(r.choices(b"abcd", k=600)) for _ in range(20)], 400)))
    assert 20 < sizes[0] <= 20 * 202
    t, ends = suffix_array._joined([bytes(r.choices(b"ab", k=50)) for _ in range(3)])
    sa = np.array([p for e in ends for p in range(e - 51, e - 5)])
    r.shuffle(sa)
    pair = np.arange(len(sa) - 1)
    assert suffix_array.alike_windows(sa, t, 4, pair).tolist() == (suffix_array.adjacent_prefixes(sa, t, 4) >= 4).tolist()


@pytest.mark.parametrize("width, passages", [(40, 4000), (40, 1), (400, 4000), (5, 4000)])
def test_repeated_bytes(docs, rows, width, passages):
    got = table(suffix_array.drop_repeats(docs, width, passages))
    texts = {r[0]: (r[1] or "").encode() for r in rows}
    n = Counter(t[i : i + width] for t in texts.values() for i in range(len(t) - width + 1))
    for i, t in texts.items():
        off = np.zeros(len(t), bool)
        for p in range(len(t) - width + 1):
            if n[t[p : p + width]] > 1:
                off[p : p + width] = True
        g = got[i]
        assert (g.n_bytes, g.n_removed) == (len(t), off.sum())
        assert g.n_spans == (np.diff(np.concatenate([[0], off.astype(int)])) == 1).sum()
        assert bytes(g.kept) == np.frombuffer(t, np.uint8)[~off].tobytes()


@pytest.mark.parametrize("width, rounds", [(20, 3), (4, 3), (20, 0), (1, 2)])
def test_repeated_words(docs, rows, width, rounds):
    got = table(recompression.drop_repeats(docs, width, rounds))
    seen = set()
    for i, t, *_ in rows:
        w = (t or "").encode().split()
        off = np.zeros(len(w), bool)
        for p in range(len(w) - width + 1):
            k = tuple(w[p : p + width])
            off[p : p + width] |= k in seen
            seen.add(k)
        g = got[i]
        assert (g.n_words, g.n_removed) == (len(w), off.sum())
        assert bytes(g.kept) == b" ".join(x for x, o in zip(w, off, strict=True) if not o)


def test_parse_is_locally_consistent():
    r = np.random.default_rng(0)
    core = r.integers(1, 9, 60).astype(np.uint64)
    a = np.concatenate([r.integers(1, 9, 17).astype(np.uint64), core, r.integers(1, 9, 5).astype(np.uint64)])
    b = np.concatenate([r.integers(1, 9, 4).astype(np.uint64), core, r.integers(1, 9, 30).astype(np.uint64)])
    top = [recompression.parse(x, np.zeros(len(x), int), 3)[-1] for x in (a, b)]
    inside = lambda s, at: {(int(n), int(p - at)) for n, p, lo, hi in zip(s.name, s.s, s.a, s.b, strict=True) if lo >= at and hi <= at + 60}
    x, y = inside(top[0], 17), inside(top[1], 4)
    assert x == y and len(x) >= 5


def test_fingerprints_and_groups(docs, rows):
    import xxhash

    got = table(simhash_vptree.near_duplicates(docs))

    def print_of(t):
        w = (t or "").encode().lower().split()
        sh = [b" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else ([b" ".join(w)] if w else [])
        h = [xxhash.xxh64_intdigest(s, 42) for s in sh]
        return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))

    fp = {r[0]: print_of(r[1]) for r in rows}
    group = {i: i for i in fp}
    changed = True
    while changed:
        changed = False
        for i in fp:
            low = min(group[j] for j in fp if bin(fp[i] ^ fp[j]).count("1") <= 3)
            if low < group[i]:
                group[i], changed = low, True
    for i in fp:
        assert got[i].fp % 2**64 == fp[i] and got[i].component_id == group[i]


def test_tree_meets_all_pairs():
    r = np.random.default_rng(3)
    base = r.integers(0, 2**63, 200).astype(np.uint64)
    fp = np.unique(np.concatenate([base ^ (np.uint64(1) << r.integers(0, 64, 200).astype(np.uint64)) ^ (np.uint64(1) << r.integers(0, 64, 200).astype(np.uint64)) for _ in range(10)]))
    row, leaf = simhash_vptree.place(fp, *simhash_vptree.build_tree(fp, 5), 3)
    leaves = [set(leaf[row == i].tolist()) for i in range(len(fp))]
    i, j = np.nonzero(np.triu(np.bitwise_count(fp[:, None] ^ fp[None]) <= 3, 1))
    assert len(i) > 300 and all(leaves[a] & leaves[b] for a, b in zip(i, j, strict=True))


def test_mix(docs, rows):
    got = curriculum_mix.curriculum(docs).collect()
    assert len(got) == len(rows)
    per = {}
    for r in got:
        assert 0 <= r.taken <= 2 * r.size and 0 <= r.position <= 1
        t = per.setdefault(r.source, [0, 0, r.target, r.source_size])
        t[0], t[1] = t[0] + r.taken, t[1] + r.size
    total = sum(x[1] for x in per.values())
    assert abs(sum(x[2] for x in per.values()) - 1.5 * total) < 1e-6 * total
    for taken, size, target, source_size in per.values():
        assert size == source_size and taken == int(target) and target <= 2 * size + 1e-9
    again = curriculum_mix.curriculum(docs.repartition(3)).collect()
    assert sorted(map(str, got)) == sorted(map(str, again))


def test_units_against_all_segmentations():
    lat = piece_lattice.Lattice(*piece_lattice.load_vocabulary())

    def every(s):
        if not s:
            yield 0.0, []
        for j in range(1, min(len(s), lat.longest) + 1):
            p = lat.id_of.get(s[:j])
            if p is not None:
                yield from ((float(lat.scores[p]) + a, [p, *b]) for a, b in every(s[j:]))
            elif j == 1:
                raw = ("▁" if s[0] == "\ud800" else s[0]).encode()
                yield from ((float(lat.scores[-1]) * len(raw) + a, [lat.byte0 + x for x in raw] + b) for a, b in every(s[1:]))

    units = ["▁hello", "▁", "▁▁▁a", "\n", "straße", "▁日本語", "▁x\ud800y", "▁idiotic", "▁😀"]
    ids, count, best, second = lat.segment(units)
    at = np.concatenate([[0], np.cumsum(count)])
    for k, u in enumerate(units):
        full = sorted(every(u), key=lambda x: -x[0])
        assert abs(best[k] - full[0][0]) < 1e-9
        assert np.allclose([s for s, _ in lat.n_best(u, 5)], [s for s, _ in full[:5]])
        assert (len(full) == 1 and np.isinf(second[k])) or abs(second[k] - (full[0][0] - full[1][0])) < 1e-9
        assert ids[at[k] : at[k + 1]].tolist() in [i for s, i in full if abs(s - full[0][0]) < 1e-9]


def test_pieces_round_trip(docs, rows):
    lat = piece_lattice.Lattice(*piece_lattice.load_vocabulary())
    got = table(piece_lattice.encode(docs, n=4))
    for i, t, *_ in rows:
        if t is None:
            assert got[i].ids is None and got[i].round_trip is None
        else:
            assert lat.decode(got[i].ids) == t and got[i].round_trip
            assert got[i].n_best == sorted(got[i].n_best, reverse=True)


def test_gradients():
    net = language_id.ByteGru(3, h=4, seed=1)
    for k in net.p:
        net.p[k] = net.p[k].astype(np.float64)
    r = np.random.default_rng(0)
    x, y = r.integers(0, 256, (6, 5)), r.integers(0, 3, 5)
    x[4:, 2] = 256
    loss, g = net.gradients(x, y)
    for k in ("uzf", "ucb", "of", "ezb", "b", "erf"):
        i = np.unravel_index(np.argmax(np.abs(g[k])), g[k].shape)
        was = net.p[k][i]
        net.p[k][i] = was + 1e-5
        up = net.gradients(x, y)[0]
        net.p[k][i] = was - 1e-5
        down = net.gradients(x, y)[0]
        net.p[k][i] = was
        assert abs((up - down) / 2e-5 - g[k][i]) < 1e-3 * max(1, abs(g[k][i])), k


def test_language_accuracy(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text", "lang")
    d = language_id.identify(docs, language_id.train(docs, steps=80)).collect()
    held = [r for r in d if zlib.crc32(str(r.doc_id).encode()) % 5 == 0 and r.lang]
    assert np.mean([r.lang == r.lang_pred for r in held]) > 0.95


def test_language_edges(docs, spark):
    got = table(language_id.identify(docs))
    assert got[39].lang_pred == "und" or got[39].text
    for r in got.values():
        letters = r.text is not None and any(c.isalpha() for c in r.text)
        assert (r.lang_pred == "und") == (not letters) and 0 <= r.score <= 1
    none = language_id.identify(docs.where("lang = 'zz'"))
    assert none.count() == 0


def test_toxicity(spark):
    d, l = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    s = toxicity.score_toxicity(d.select("doc_id", "text"), toxicity.train(d, l, sample=2500)).join(l, "doc_id").select("doc_id", "score", "toxic").collect()
    held = [r for r in s if zlib.crc32(str(r.doc_id).encode()) % 5 == 0]
    pos, neg = [r.score for r in held if r.toxic == 1], [r.score for r in held if r.toxic == 0]
    assert np.mean([a > b for a in pos for b in neg]) > 0.9 and np.mean([x >= 0.5 for x in neg]) < 0.02


def test_counterfactuals_pull_scores_together():
    r = np.random.default_rng(0)
    words = lambda i: {f"w{k}" for k in r.integers(0, 30, 6)} | ({"women"} if i % 2 else {"men"})
    docs = [words(i) for i in range(200)]
    y = np.array([i % 2 for i in range(200)])  # labels that follow the identity term
    rows = [np.array(toxicity.feature_ids(w)) for w in docs]
    twins = [(i, np.array(toxicity.feature_ids(toxicity.swapped(w)))) for i, w in enumerate(docs)]
    gap = {}
    for pull in (0.0, 5.0):
        w, _ = toxicity.fit(rows, y, twins, pull=pull)
        gap[pull] = np.mean([(w[rows[i]].sum() - w[t].sum()) ** 2 for i, t in twins])
    assert gap[5.0] < 0.1 * gap[0.0]


@pytest.fixture(scope="module")
def vectors(spark):
    r = np.random.default_rng(4)
    base = r.standard_normal((300, 16))
    near = base[:40].repeat(4, 0) + 0.05 * r.standard_normal((160, 16))
    x = np.concatenate([base, near, base[5:8], base[5:8]]).astype(np.float32)
    rows = [(i, [float(f) for f in v], 0) for i, v in enumerate(x)]
    n = len(rows)
    rows += [(n, None, 0), (n + 1, [0.0] * 16, 0), (n + 2, [float("nan")] + [1.0] * 15, 0), (n + 3, [None] + [1.0] * 15, 0), (n + 4, [1.0] * 3, 0), (n + 5, [], 0), (n + 20 - n % 20, [float("inf")] * 16, 0)]
    return spark.createDataFrame(rows, VECS).repartition(4), x


def test_vector_links(vectors):
    df, x = vectors
    got = table(itq_neardup.near_duplicate_links(df, block=16), "vec_id")
    u = x.astype(float) / np.linalg.norm(x.astype(float), axis=1, keepdims=True)
    hit = u @ u.T >= 0.95
    np.fill_diagonal(hit, False)
    links = np.array([got[i].n_links for i in range(len(x))])
    assert (links <= hit.sum(1)).all() and links.sum() >= 0.9 * hit.sum()
    for i in range(len(x), len(x) + 6):
        assert (got[i].n_links, got[i].component_id, got[i].kept) == (0, i, True)
    label = np.arange(len(x))
    while True:
        new = np.array([min(label[i], label[hit[i]].min(initial=len(x))) for i in range(len(x))])
        if (new == label).all():
            break
        label = new
    assert np.mean([got[i].component_id == label[i] for i in range(len(x))]) > 0.95


def test_nearest(vectors):
    df, x = vectors
    got = hnsw.nearest(df, df.where("vec_id % 20 = 0"), shard_rows=150).collect()
    x = x.astype(float)
    by = {}
    for r in got:
        by.setdefault(r.query_id, []).append(r)
    hits = 0
    ask = range(0, len(x), 20)
    assert set(by) == set(ask)
    for q in ask:
        s = x @ x[q]
        s[q] = -np.inf
        want = sorted(range(len(x)), key=lambda i: (-s[i], i))[:20]
        mine = sorted(by[q], key=lambda r: r["rank"])
        assert [r["rank"] for r in mine] == list(range(1, 21))
        assert all(abs(r.score - s[r.vec_id]) < 1e-12 for r in mine)
        assert mine == sorted(mine, key=lambda r: (-r.score, r.vec_id))
        hits += len(set(want) & {r.vec_id for r in mine})
    assert hits / (20 * len(ask)) >= 0.9


@pytest.mark.parametrize("f", [suffix_array.drop_repeats, recompression.drop_repeats, simhash_vptree.near_duplicates, curriculum_mix.curriculum, piece_lattice.encode, language_id.identify, lambda d: line_dedup.drop_common_lines(d.drop("k_id", "gone_"))])
def test_empty_and_repeated(docs, f):
    assert f(docs.where("false")).count() == 0
    some = docs.where("doc_id < 6")
    twice = f(some.union(some)).collect()
    assert len(twice) == 12


def test_empty_vectors(vectors):
    df, _ = vectors
    none = df.where("false")
    assert itq_neardup.near_duplicate_links(none).count() == 0 and hnsw.nearest(none, none).count() == 0


def test_null_ids(spark):
    d = spark.createDataFrame([(None, "a b c d"), (None, None), (1, "a b c d"), (2, "x y z w")], "doc_id long, text string")
    for f in (suffix_array.drop_repeats, recompression.drop_repeats, simhash_vptree.near_duplicates, line_dedup.drop_common_lines):
        assert f(d).count() == 4


def test_passes_follow_demand(spark, sf):
    text = " ".join("w" for _ in range(20))
    rows = [(600 * k + i, text, f"s{k}") for k in range(3) for i in range(600)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(3)
    got = curriculum_mix.passes(docs).collect()
    assert sum(r.taken for r in got) == sum(r.taken for r in curriculum_mix.curriculum(docs).collect())
    for k, slope in enumerate(curriculum_mix.SLOPES):
        mine = [r for r in got if r.source == f"s{k}"]
        total = sum(r.taken for r in mine)
        for t in (0.1, 0.25, 0.5, 0.75, 0.9, 1.0):
            asked = (1 - slope) * t + slope * t * t
            assert abs(sum(r.taken for r in mine if r.position <= t) / total - asked) < 0.01
        again = [r.position for r in mine if r["pass"] == 2]
        assert not again or min(again) >= max(r.position for r in mine if r["pass"] == 1)
    null = spark.createDataFrame([(None, "a b c", "x"), (None, "d e f g h i", "x"), (7, "j k", "y")], docs.schema)
    out = curriculum_mix.stage(spark, null, sf).collect()
    assert len(out) == curriculum_mix.passes(null).count() and len({r.text for r in out}) == 3


def test_n_best_ids_have_their_scores(docs, rows):
    lat = piece_lattice.Lattice(*piece_lattice.load_vocabulary())
    got, several = table(piece_lattice.encode(docs, n=4)), 0
    for i, t, *_ in rows:
        if t is None:
            assert got[i].n_best_ids is None
            continue
        ways = got[i].n_best_ids
        assert ways[0] == got[i].ids and len(ways) == len(got[i].n_best) == len({tuple(w) for w in ways})
        for score, ids in zip(got[i].n_best, ways, strict=True):
            assert lat.decode(ids) == t
            if t.isascii():
                assert abs(sum(float(lat.scores[p]) for p in ids) - score) < 1e-6 or any(lat.byte0 <= p < lat.byte0 + 256 for p in ids)
        several += len(ways) > 1
    assert several > 20
    for unit in ("▁hello", "▁idiotic"):
        seen = piece_lattice.Segmented(lat, 3)
        (_, scores, ways, _), = piece_lattice.encode_batch(lat, [unit[1:]], 3, seen)
        full = lat.n_best(unit, 3)
        assert np.allclose(scores, [s for s, _ in full]) and sorted(w.tolist() for w in ways) == sorted(w for _, w in full)


@pytest.mark.parametrize("filter_bytes", [64 << 20, 0])
def test_lines_that_end_in_other_separators(spark, filter_bytes):
    texts = ["foo \u0085"] * 9 + ["foo\u0085", "\x0b Bar\x0c\r", "\tbAR "] + ["bar"] * 8
    d = spark.createDataFrame([(None if i % 2 else i, t) for i, t in enumerate(texts)], "doc_id long, text string").repartition(3)
    got = line_dedup.drop_common_lines(d, filter_bytes=filter_bytes).collect()
    assert sorted(r.text for r in got if not r.n_dropped) == sorted(texts[:10]) and all(r.kept_text == "" for r in got if r.n_dropped)


def test_filters_follow_the_counts(docs):
    d = docs.select("doc_id", "text")
    first, second = d.where("doc_id < 44"), d.where("doc_id >= 44")
    one = line_dedup.materialise(line_dedup.reference_counts(first))
    built = line_dedup.materialise(line_dedup.filters(one, 2, 4))
    both = line_dedup.materialise(line_dedup.insert_documents(one, second))
    grown = line_dedup.materialise(line_dedup.maintained(built, one, both, 2, 4))
    back = line_dedup.materialise(line_dedup.maintained(grown, both, one, 2, 4))
    for counts, cells in ((one, built), (both, grown), (one, back)):
        own = {r.shard: line_dedup.CuckooFilter(0, np.frombuffer(r.cells, np.uint16).reshape(-1, 4)) for r in cells.collect()}
        for r in counts.where("n >= 2").collect():
            assert own[r.h1 % 4].contains(np.array([r.h2]))[0]
    kept = sum(int((f.cells != 0).sum()) for f in own.values())
    assert kept == one.where("n >= 2").count() < both.where("n >= 2").count()
    a, b = line_dedup.drop_common_lines(d, 2, both, grown, shards=4), line_dedup.drop_common_lines(d, 2)
    assert a.exceptAll(b).count() == b.exceptAll(a).count() == 0


def test_shared_ids_link_no_texts(spark):
    words = lambda k: " ".join(f"w{k}x{i}" for i in range(30))
    d = spark.createDataFrame([(None, words(1)), (None, words(2)), (5, words(1)), (9, words(2)), (9, words(3)), (None, words(4))], "doc_id long, text string")
    got = {(r.doc_id, r.fp): r.component_id for r in simhash_vptree.near_duplicates(d).collect()}
    by = Counter(got.values())
    assert len(got) == 6 and by == Counter({5: 2, 9: 3, None: 1})


def test_repeated_vector_ids_agree(spark):
    rows = [(i, [float(i % 7), 1.0]) for i in range(30)] + [(20, [9.0, 1.0]), (20, [-9.0, 1.0])]
    runs = [hnsw.nearest(d, d.where("vec_id % 20 = 0"), k=4).collect() for d in (spark.createDataFrame(x, "vec_id long, embedding array<double>").repartition(n) for x, n in ((rows, 1), (rows[::-1], 3)))]
    assert sorted(runs[0]) == sorted(runs[1]) and len(runs[0]) == 8
    assert all(abs(r.score - (-9.0 * (r.vec_id % 7) + 1)) < 1e-9 for r in runs[0] if r.query_id == 20)


def test_labels_and_rows_that_repeat(spark):
    d = spark.createDataFrame([(1, f"word{i % 50}") for i in range(300)] + [(2, "other")], "doc_id long, text string")
    l = spark.createDataFrame([(1, 1), (1, 0), (2, 0), (None, 1)], "doc_id long, toxic int")
    seen = []
    keep, toxicity.fit = toxicity.fit, lambda ids, y, twins, pull: seen.append((len(ids), len(twins), y.sum())) or keep(ids, y, twins, pull)
    try:
        out = toxicity.score_toxicity(d, toxicity.train(d, l, sample=40)).collect()
    finally:
        toxicity.fit = keep
    assert seen[0][:2] == (40, 40) and seen[0][2] >= 39 and len(out) == 301


def test_mentions_of_groups_stay_harmless():
    r = np.random.default_rng(1)
    y = np.array([i % 4 == 0 for i in range(400)], int)
    docs = [{f"n{k}" for k in r.integers(0, 60, 8)} | ({"moron"} if k and r.random() < 0.8 else set()) | ({"women"} if r.random() < (0.7 if k else 0.02) else set()) for k in y]
    rows = [np.array(toxicity.feature_ids(w)) for w in docs]
    twins = [(i, np.array(toxicity.feature_ids(toxicity.counterfactual_pair(w)[1]))) for i, w in enumerate(docs)]
    neutral = [{f"n{k}" for k in r.integers(0, 60, 8)} for _ in range(200)]
    false = {}
    for pull in (0.0, 20.0):
        w, b = toxicity.fit(rows, y, twins, pull=pull)
        score = lambda x: w[toxicity.feature_ids(x)].sum() + b  # noqa: B023, E731
        false[pull] = np.mean([score(x | {"women"}) >= 0 for x in neutral])
        assert np.mean([score(x) >= 0 for x in neutral]) < 0.1 and np.mean([score(x | {"moron"}) >= 0 for x in neutral]) > 0.9
    assert false[20.0] < 0.5 * false[0.0] and false[0.0] > 0.2


def test_sorted_arrays_decide_all_repeats(docs, rows, monkeypatch):
    spans = []
    keep = suffix_array.sorted_spans
    monkeypatch.setattr(suffix_array, "sorted_spans", lambda *a: spans.append(suffix_array.materialise(keep(*a))) or spans[-1])
    monkeypatch.setattr(suffix_array, "counted_windows", None)
    got = table(suffix_array.drop_repeats(docs, 40))
    assert sum(g.n_removed > 0 for g in got.values()) > 12 and spans[0].count() > 0


def test_mix_positions_reach_the_end(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    last = curriculum_mix.passes(docs).groupBy("source").agg({"position": "max"}).collect()
    assert len(last) > 3 and all(r[1] > 0.95 for r in last)


def test_units_outlive_tasks_and_thinning(rows):
    """A worker's tasks share one vocabulary and its units; where there are too many, those met often stay."""
    vocabulary = piece_lattice.load_vocabulary()
    held = piece_lattice._units_held("a job", vocabulary, 3)
    assert piece_lattice._units_held("a job", vocabulary, 3) is held and piece_lattice._units_held("another", vocabulary, 3) is not held
    texts = [t for _, t, *_ in rows]
    want = piece_lattice.encode_batch(held.lattice, texts, 3)
    few, got, sizes = piece_lattice.Segmented(held.lattice, 3, most=40), [], []
    for lo in range(0, len(texts), 5):
        old = set(few.code)
        got += piece_lattice.encode_batch(held.lattice, texts[lo : lo + 5], 3, few)
        sizes.append(len(old & set(few.code)))
    assert 0 < max(sizes[2:]) and len(few.code) < len({u for t in texts for u in piece_lattice.units_of(t or "")})
    for (ids, scores, every, ok), (ids2, scores2, every2, ok2) in zip(got, want, strict=True):
        assert ids.tolist() == ids2.tolist() and scores == scores2 and ok == ok2 and [x.tolist() for x in every] == [x.tolist() for x in every2]

"""Joins and repeated strings against brute force, and the pipeline against a plain version."""

import hashlib
import random
from itertools import combinations

import numpy as np
import pytest

import corpus_pipeline
from bflyspark.llm import jaccard_join, quality_rules, secret_scan, suffix_dedup
from bflyspark.llm.decontaminate import Block, Limits, find
from bflyspark.llm.queries import llm_queries


def mutants(seed=3):
    rnd = random.Random(seed)
    words = [f"w{i}" for i in range(3000)]
    texts = []
    for size in (30, 90, 160):
        base = [rnd.choice(words) for _ in range(size)]
        now = base
        for _ in range(40):
            now = list(rnd.choice([base, now, now]))
            for _ in range(rnd.randint(0, 3)):
                now[rnd.randrange(size)] = rnd.choice(words)
            texts.append(" ".join(now))
    return texts + ["", None, "a", "a b", "A B", "  ", "x y z w", "x y z w"] + [" ".join(rnd.choice(words) for _ in range(rnd.randint(1, 40))) for _ in range(60)]


def classes(texts, words, num):
    sets = []
    for t in texts:
        w = (t or "").lower().split()
        sets.append({tuple(w[k : k + words]) for k in range(max(1, len(w) - words + 1))} if w else set())
    root = list(range(len(sets)))

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, a in enumerate(sets):
        for j in range(i):
            common = len(a & sets[j])
            if a and sets[j] and 100 * common >= num * (len(a) + len(sets[j]) - common):
                x, y = sorted((top(i), top(j)))
                root[y] = x
    return {i: (len(s), top(i)) for i, s in enumerate(sets)}


@pytest.mark.parametrize("load,levels", [(16 << 20, 6), (6000, 3), (6000, 0)])
def test_jaccard_join_is_exact(spark, monkeypatch, load, levels):
    monkeypatch.setattr(jaccard_join, "REGION_BYTES", load)
    monkeypatch.setattr(jaccard_join, "LEVELS", levels)
    texts = mutants()
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for words, num in ((4, 85), (5, 80)):
        got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_join.join_documents(df, words, num).collect()}
        assert got == classes(texts, words, num)


def test_cores_of_two_pivots_link(spark, monkeypatch):
    """Chains in which a text links with its neighbours alone: cores of pivots three steps apart meet in one link."""
    monkeypatch.setattr(jaccard_join, "REGION_BYTES", 4000)
    texts = [" ".join(f"c{chain}x{3 * i + k}" for k in range(43)) for chain in range(3) for i in range(60)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r.component_id for r in jaccard_join.join_documents(docs).collect()}
    assert got == {i: i // 60 * 60 for i in range(180)}


def test_regions_are_cut_by_pivots(monkeypatch):
    """Voronoi regions with windows and cores find what all pairs find, at any size of a region."""
    import numpy as np

    cuts = []
    near = jaccard_join.near
    monkeypatch.setattr(jaccard_join, "near", lambda d, num: cuts.append(d.shape) or near(d, num))
    rnd = random.Random(4)
    for clusters, copies, edits in ((1, 2, 1), (6, 4, 2), (30, 12, 3), (4, 120, 4), (150, 1, 0), (40, 6, 8)):
        sets = []
        for c in range(clusters):
            base = rnd.sample(range(c * 150, c * 150 + 400), 120)
            now = set(base)
            for _ in range(copies):
                now = set(rnd.choice([base, list(now)]))
                for x in rnd.sample(sorted(now), edits):
                    now.remove(x)
                    now.add(rnd.randrange(10**6, 10**7))
                sets.append(now)
        arrays = [np.array(sorted(s), np.uint64) for s in sets]
        nodes = [i * 7919 + 11 for i in range(len(sets))]
        for num in (80, 85):
            got, want = list(range(len(sets))), list(range(len(sets)))

            def top(root, i):
                while root[i] != i:
                    i = root[i]
                return i

            for a, b in jaccard_join.region_links(nodes, arrays, num):
                i, j = nodes.index(a), nodes.index(b)
                common = len(sets[i] & sets[j])
                assert 100 * common >= num * (len(sets[i]) + len(sets[j]) - common)
                got[top(got, i)] = top(got, j)
            for i, a in enumerate(sets):
                for j in range(i):
                    common = len(a & sets[j])
                    if 100 * common >= num * (len(a) + len(sets[j]) - common):
                        want[top(want, i)] = top(want, j)
            parts = lambda root: {frozenset(i for i in range(len(root)) if top(root, i) == r) for r in {top(root, k) for k in range(len(root))}}
            assert parts(got) == parts(want)
    assert len(cuts) > 5


def test_join_without_broadcasts(spark):
    """Adaptive plans that deal rows anew must keep regions whole."""
    key = "spark.sql.autoBroadcastJoinThreshold"
    old = spark.conf.get(key)
    spark.conf.set(key, "100")
    try:
        texts = mutants(8)
        df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
        got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_join.join_documents(df).collect()}
        assert got == classes(texts, 4, 85)
    finally:
        spark.conf.set(key, old)


def test_rings_lose_no_link():
    rings = jaccard_join.Rings(85)
    for size in range(1, 400):
        ring = rings.ring(size)
        for other in range(size, size * 100 // 85 + 1):
            assert rings.ring(other) in (ring, ring + 1)
            gap = (size + other) * 15 // 185
            assert rings.differing(ring + 1) >= gap and rings.blocks(ring + 1) > rings.differing(ring + 1)


def test_join_of_odd_inputs(odd, none):
    rows = jaccard_join.join_documents(odd).collect()
    assert len(rows) == odd.count()
    assert {r.component_id for r in rows if r.doc_id in (2, 3, 4)} == {2}
    assert jaccard_join.join_documents(none).count() == 0
    left = jaccard_join.one_of_each(odd)
    ids = [r.doc_id for r in left.collect()]
    assert left.columns == odd.columns and ids.count(2) == 1 and 3 not in ids and 4 not in ids and 0 in ids
    assert jaccard_join.one_of_each(none).count() == 0


def without_repeats(texts, length=200):
    seen = {}
    data = [(t or "").encode() for t in texts]
    for b in data:
        for p in range(len(b) - length + 1):
            seen[b[p : p + length]] = seen.get(b[p : p + length], 0) + 1
    out = []
    for b in data:
        gone = bytearray(len(b))
        for p in range(len(b) - length + 1):
            if seen[b[p : p + length]] > 1:
                gone[p : p + length] = b"\1" * length
        kept = bytes(c for c, g in zip(b, gone, strict=True) if not g)
        spans = sum(g and not (i and gone[i - 1]) for i, g in enumerate(gone))
        out.append((len(b), sum(gone), spans, hashlib.sha256(kept).hexdigest()))
    return out


def passages(seed=1):
    rnd = random.Random(seed)
    words = ["alpha", "beta", "gamma", "delé", "eps", "zeta"]
    say = lambda n: " ".join(rnd.choice(words) + str(rnd.randint(0, 99)) for _ in range(n))
    shared = [say(n) for n in (25, 40, 60, 200)]
    texts = []
    for _ in range(60):
        parts = [say(rnd.randint(0, 60))]
        for _ in range(rnd.randint(0, 3)):
            s = rnd.choice(shared)
            a = rnd.randint(0, len(s) // 3)
            parts += [s[a : len(s) - rnd.randint(0, len(s) // 3)], say(rnd.randint(0, 30))]
        texts.append(" ".join(parts))
    return texts + [texts[0], "x" * 900, "", None, "y" * 199, "z" * 200, "ab" * 150]


@pytest.mark.parametrize("batch", [100_000, 300])
def test_repeated_strings(spark, monkeypatch, batch):
    monkeypatch.setattr(suffix_dedup, "BATCH_STARTS", batch)
    texts = passages()
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(5)
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.remove_repeats(df).collect()}
    assert [got[i] for i in range(len(texts))] == without_repeats(texts)


def test_repeated_strings_in_small_chunks(spark, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "CHUNK", 1200)
    texts = passages(4)
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.remove_repeats(df).collect()}
    assert [got[i] for i in range(len(texts))] == without_repeats(texts)


def test_periodic_texts_and_many_untouched(spark):
    """A text that repeats itself at every byte, one with far periods, copies of short texts that nothing is asked of."""
    rnd = random.Random(9)
    unit = "".join(rnd.choice("abcdefgh ") for _ in range(230))
    texts = ["ab" * 9000, (unit + "x") * 30, unit + "tail", "short"] + ["same short text"] * 300 + ["".join(rnd.choice("abcdefgh ") for _ in range(400))]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.remove_repeats(df).collect()}
    assert [got[i] for i in range(len(texts))] == without_repeats(texts)


def test_index_family_levels():
    rnd = random.Random(2)
    contents = [bytes(rnd.choice(b"ab") for _ in range(rnd.randint(200, 260))) for _ in range(200)]
    contents += [contents[3], contents[50][5:] + b"q" * 5]
    family = suffix_dedup.IndexFamily()
    found = set()
    for k, c in enumerate(contents):
        for owner, start in family.add([c], __import__("numpy").array([k])):
            found |= set(zip(owner.tolist(), start.tolist(), strict=True))
    seen = {}
    for k, c in enumerate(contents):
        for p in range(len(c) - 199):
            seen.setdefault(c[p : p + 200], []).append((k, p))
    assert found == {x for places in seen.values() if len(places) > 1 for x in places}
    assert len(family.levels) <= 16 and all(len(a) > len(b) for a, b in zip(family.levels, family.levels[1:], strict=False))


def test_removal_of_odd_inputs(odd, none):
    rows = suffix_dedup.remove_repeats(odd).collect()
    assert len(rows) == odd.count()
    assert all(r.n_removed == r.n_bytes for r in rows if r.doc_id in (2, 3))
    assert suffix_dedup.remove_repeats(none).count() == 0
    kept = {r.doc_id: r for r in suffix_dedup.remove_repeats(odd, with_text=True).collect()}
    assert bytes(kept[6].kept) == b"one"


def test_pipeline_stages(spark, small, tiny):
    """The stages against plain versions of the same rules, on the rows that the stage before kept."""
    docs = {r.doc_id: r for r in tiny.collect()}
    refs = quality_rules.references(tiny)
    good = {i: r.text for i, r in docs.items() if quality_rules.measure(r.text, r.lang, refs, quality_rules.DivergenceLimits())[-1]}
    ids = sorted(good)
    first = classes([good[i] for i in ids], 5, 80)
    unique = {i: good[i] for k, i in enumerate(ids) if first[k][1] == k}
    block = Block([(r.item_id, r.text) for r in spark.read.parquet(f"{small}/benchmark.parquet").collect()])
    clean = {i: t for i, t in unique.items() if not find([t], block, Limits())[0]}
    want = {i: hashlib.sha256(secret_scan.redacted_text(t).encode()).hexdigest() for i, t in clean.items()}
    got = {r.doc_id: r.decoded_sha256 for r in corpus_pipeline.run(spark, small).collect()}
    assert got == want
    assert [name for name, _ in corpus_pipeline.STAGES][0] == "quality rules" and len(corpus_pipeline.STAGES) == 5


def test_stages_keep_columns(spark, small, odd, none):
    for frame in (odd, none):
        docs = frame
        for _, stage in corpus_pipeline.STAGES[:-1]:
            docs = stage(spark, docs, small)
            assert docs.columns == frame.columns
        assert corpus_pipeline.STAGES[-1][1](spark, docs, small).count() == docs.count()


def test_every_operator_is_registered():
    names = list(llm_queries())
    assert [n.split("_")[0] for n in names if n.startswith("op")].__len__() == 10 and "pipeline" in names


def test_gathered_cells_keep_every_pair():
    rng = np.random.default_rng(5)
    for most in (2, 4, 30):
        cells = [rng.choice(40, rng.integers(2, most + 1), replace=False).astype(np.int64) for _ in range(200)]
        cells += [np.delete(np.arange(100, 160, dtype=np.int64), rng.choice(60, 5, replace=False)) for _ in range(30)]
        sizes = np.array([len(c) for c in cells], np.int64)
        names, nodes = jaccard_join.gathered(np.concatenate(cells), sizes)
        groups: dict[int, set[int]] = {}
        for name, node in zip(names.tolist(), nodes.tolist(), strict=True):
            groups.setdefault(name, set()).add(node)  # equal cells share a name and are told as one later
        pairs = lambda sets: {p for s in sets for p in combinations(sorted(s), 2)}
        assert pairs(c.tolist() for c in cells) <= pairs(groups.values())
        assert len(nodes) < sizes.sum() and max(map(len, groups.values())) <= 2 * sizes.max()

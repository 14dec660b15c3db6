import random
import re

import numpy as np
import pyarrow as pa

from ctxmatch.llm import near_dup
from ctxmatch.llm.components import components

WS = re.compile(r"[\x20\x09-\x0D]+")


def brute_sets(texts, words):
    out = {}
    for i, x in texts.items():
        x = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in x or "")
        w = [y for y in WS.split(x) if y]
        out[i] = {tuple(w[k : k + words]) for k in range(len(w) - words + 1)} if len(w) >= words else {tuple(w)} if w else set()
    return out


def brute_components(sets, percent=80):
    name = {i: i for i in sets}

    def find(x):
        while name[x] != x:
            x = name[x]
        return x

    ids = sorted(sets)
    for k, a in enumerate(ids):
        for b in ids[:k]:
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                name[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


def near_copies(seed, groups=12, size=9):
    rng, rows = random.Random(seed), {}
    for g in range(groups):
        base = [rng.choice("alpha beta gamma delta epsilon zeta eta theta iota kappa".split()) + str(rng.randint(0, 300)) for _ in range(rng.randint(30, 200))]
        for _ in range(rng.randint(1, size)):
            own = list(base)
            for _ in range(rng.randint(0, max(1, len(base) // 40))):
                own[rng.randrange(len(own))] = f"new{rng.randint(0, 10**6)}"
            rows[len(rows)] = " ".join(own)
    return rows


def test_components_equal_brute_force(spark, docs, none):
    texts = near_copies(1) | {1000 + r.doc_id: r.text for r in docs.collect()}
    df = spark.createDataFrame([(i, t, t) for i, t in texts.items()], "doc_id long, text string, component_id string").repartition(3)
    for words in (4, 5):
        sets = brute_sets(texts, words)
        want = brute_components(sets)
        got = near_dup.near_components(df, words=words).collect()
        assert len(got) == len(texts)
        for r in got:
            assert (r.n_shingles, r.component_id, r.kept) == (len(sets[r.doc_id]), want[r.doc_id], want[r.doc_id] == r.doc_id)
    kept = near_dup.drop_near_copies(docs)
    assert kept.columns == docs.columns
    assert near_dup.near_components(none).count() == 0


def test_null_ids_and_repeated_rows(spark):
    df = spark.createDataFrame([(None, "a b c d e f"), (3, "a b c d e f"), (3, "a b c d e f"), (2, "A B c d e f"), (9, None)], "doc_id long, text string")
    got = sorted((str(r.doc_id), str(r.component_id), r.kept) for r in near_dup.near_components(df).collect())
    assert got == [("2", "2", True), ("3", "2", False), ("3", "2", False), ("9", "9", True), ("None", "None", True)]


def test_shuffled_large_texts_across_chunks(monkeypatch):
    monkeypatch.setattr(near_dup, "CHUNK", 50)
    texts = {i: t for i, t in enumerate([*near_copies(2, 3, 3).values(), "", "A", "é É  x\ty\nz", None, "a b c d"])}
    sets = brute_sets(texts, 4)
    got = list(near_dup.shingle_sets(pa.array([t or "" for t in texts.values()]), 4))
    assert [len(x) for x in got] == [len(sets[i]) for i in texts]
    for a in texts:
        for b in texts:
            assert len(np.intersect1d(got[a], got[b])) == len(sets[a] & sets[b])


def test_odd_sketch_estimates_similarity():
    rng, signer = np.random.default_rng(3), near_dup.Signer(30, 5)
    for similarity in (0.7, 0.8, 0.9, 0.97):
        errors = []
        for _ in range(40):
            n = 600
            same = int(2 * n * similarity / (1 + similarity))
            pool = rng.integers(0, 1 << 63, 2 * n - same, dtype=np.uint64)
            a, b = pool[:n], np.concatenate([pool[:same], pool[n:]])
            x, y = signer.sign(a)[1], signer.sign(b)[1]
            errors.append(near_dup.estimate(sum(int(v).bit_count() for v in (x ^ y).view(np.uint64)), 150) - similarity)
        assert abs(np.mean(errors)) < 0.02 and np.std(errors) < 0.06
    assert near_dup.estimate(near_dup.most_differing_bits(0.66, 150), 150) >= 0.65


def test_components_of_a_long_path(spark):
    pairs = [(i, i + 1) for i in range(60)] + [(100, 101), (200, 100), (5, 5)]
    got = {r.id: r.component for r in components(spark.createDataFrame(pairs, "a long, b long").repartition(3)).collect()}
    assert got == {i: 0 for i in range(61)} | {100: 100, 101: 100, 200: 100}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0

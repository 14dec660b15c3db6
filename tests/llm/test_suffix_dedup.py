import hashlib
import random

import numpy as np
import pytest

from ctxmatch.llm import suffix_dedup as S


def brute(texts, least):
    """id -> (n_bytes, n_removed, n_spans, sha) by looking at every window."""
    first, out = {}, {}
    for i in sorted(texts):
        b = (texts[i] or "").encode()
        gone = np.zeros(len(b), bool)
        for k in range(len(b) - least + 1):
            if first.setdefault(b[k : k + least], (i, k)) != (i, k):
                gone[k : k + least] = True
        spans = int(np.count_nonzero(np.diff(np.concatenate([[0], gone.astype(int)])) == 1))
        out[i] = (len(b), int(gone.sum()), spans, hashlib.sha256(bytes(np.frombuffer(b, np.uint8)[~gone])).hexdigest())
    return out


def passages(seed, n=60, alphabet="abcdefgh é\n"):
    rng = random.Random(seed)
    text = lambda lo, hi: "".join(rng.choice(alphabet) for _ in range(rng.randint(lo, hi)))
    shared, rows = [text(20, 260) for _ in range(12)], {}
    for i in range(n):
        rows[i * 3] = "".join(rng.choice([text(0, 200), rng.choice(shared), rng.choice(shared)[rng.randint(0, 30) :]]) for _ in range(rng.randint(0, 8)))
    rows[1] = rows[3]
    rows[2] = "ab" * 300
    rows[4] = "z" * 450
    rows[5] = "z" * 99
    rows[7] = None
    return rows


@pytest.mark.parametrize("seed,least,k,chunk", [(1, 100, 32, 1 << 20), (2, 40, 8, 700), (3, 100, 32, 100), (4, 25, 20, 1 << 20), (5, 400, 16, 1 << 20)])
def test_removal_equals_brute_force(spark, monkeypatch, seed, least, k, chunk):
    monkeypatch.setattr(S, "CHUNK", chunk)
    texts = passages(seed)
    df = spark.createDataFrame([(i, t, t) for i, t in texts.items()], "doc_id long, text string, covered string").repartition(4)
    got = {r.doc_id: tuple(r)[1:] for r in S.remove_repeats(df, least=least, k=k, bucket_bytes=3000).collect()}
    assert got == brute(texts, least)


def test_awkward_documents(spark, docs, none):
    texts = {r.doc_id: r.text for r in docs.collect()}
    got = {r.doc_id: tuple(r)[1:] for r in S.remove_repeats(docs).collect()}
    assert got == brute(texts, 100)
    assert S.remove_repeats(none).count() == 0
    df = spark.createDataFrame([(1, "q" * 50 + "x" * 120), (1, "q" * 50 + "x" * 120), (None, "x" * 120), (2, "x" * 120)], "doc_id long, text string")
    got = sorted((str(r.doc_id), r.n_removed, r.n_spans, r.rest) for r in S.remove_repeats(df, with_rest=True).collect())
    one = brute({1: "q" * 50 + "x" * 120}, 100)[1]
    assert got[:2] == [("1", one[1], one[2], b"q" * 50 + b"x" * (120 - one[1]))] * 2 and got[2][:3] == ("2", 120, 1) and got[3][:3] == ("None", 0, 0)


def test_maximal_repeats_equal_brute_force():
    rng = random.Random(9)
    for trial in range(60):
        texts = ["".join(rng.choice("ab") for _ in range(rng.randint(0, 40))).encode() for _ in range(rng.randint(1, 5))]
        least = rng.choice([1, 2, 3, 5])
        at = {}
        for t, x in enumerate(texts):
            for i in range(len(x)):
                for j in range(i + least, len(x) + 1):
                    at.setdefault(x[i:j], []).append((t, i))
        want = {}
        for s, places in at.items():
            left = {texts[t][i - 1] if i else (t, i, "start") for t, i in places}
            right = {texts[t][i + len(s)] if i + len(s) < len(texts[t]) else (t, "end") for t, i in places}
            if len(places) > 1 and len(left) > 1 and len(right) > 1:
                want[s] = sorted(places)
        assert {s: sorted(p) for s, p in S.maximal_repeats(texts, least)} == want


def test_anchors_do_not_depend_on_what_stands_beside_a_text():
    rng = random.Random(12)
    text = "".join(rng.choice("ab") for _ in range(3000)).encode()
    other = "".join(rng.choice("abc") for _ in range(1 << 17)).encode()
    alone = S.units_of(np.frombuffer(text, np.uint8), np.array([0, 3000]), 100, 8)
    beside = S.units_of(np.frombuffer(other + text, np.uint8), np.array([0, 1 << 17, (1 << 17) + 3000]), 100, 8)
    own = beside[0] == 1
    for a, b in zip(alone[1:], beside[1:], strict=True):
        assert (a == b[own]).all()


def test_later_occurrences_are_those_of_maximal_repeats():
    rng = random.Random(13)
    for _ in range(60):
        texts = ["".join(rng.choice("ab") for _ in range(rng.randint(0, 60))).encode() for _ in range(rng.randint(1, 5))]
        least = rng.choice([2, 3, 5, 8])
        place = np.arange(len(texts)) * 1000
        want, got = set(), set()
        for s, found in S.maximal_repeats(texts, least):
            first = min(found)
            want |= {(t, i + j) for t, i in found if (t, i) != first for j in range(len(s))}
        for t, i, n in zip(*S.later_occurrences(texts, place, least), strict=True):
            got |= {(t, i + j) for j in range(n)}
        assert got == want


def test_lengths_that_do_not_fit_are_refused(docs):
    with pytest.raises(ValueError):
        S.repeated_spans(docs, least=1 << 16)
    with pytest.raises(ValueError):
        S.repeated_spans(docs, least=20, k=32)

import hashlib
import random
import zlib

import numpy as np
import pytest
from test_near_dup import brute_components, brute_sets
from test_simple_ops import WS, by_id, tiktoken_encoding

from ctxmatch.llm import mixing, toxicity


def corpus(seed=4, n=500):
    """Invented prose; toxic texts hold an insult of the public list or a word of an invented stem."""
    rng = random.Random(seed)
    words = [a + b for a in "ba ce di fo gu ha je ki lo mu".split() for b in "ran tel sim pon dur".split()]
    rows, labels = [], []
    for i in range(n):
        text = rng.choices(words, k=rng.randint(15, 60))
        toxic = i % 6 == 0
        if toxic:
            for _ in range(rng.randint(1, 3)):
                text.insert(rng.randrange(len(text)), rng.choice(["moron", "scum", "stupid"]) if i % 12 else "grobzak" + rng.choice(words))
        rows.append((i, " ".join(text), "en", f"s{i % 4}" if i % 3 else "s0", 0))
        labels.append((i, 1, int(toxic)))
    return rows, labels


def test_label_model_recovers_accuracies_of_correlated_voters():
    rng = np.random.default_rng(0)
    y = rng.random(20_000) < 0.2
    vote = lambda hit, false: np.where(rng.random(len(y)) < np.where(y, hit, false), 1, 0)
    good, weak = vote(0.8, 0.02), vote(0.6, 0.1)
    copy = np.where(rng.random(len(y)) < 0.95, weak, vote(0.6, 0.1))
    other = vote(0.7, 0.05)
    clean = -(1 - np.maximum(good, other))
    votes = np.stack([good, weak, copy, other, clean], 1)
    patterns, counts = np.unique(votes, axis=0, return_counts=True)
    model = toxicity.LabelModel(prior=0.2).fit(patterns, counts)
    assert model.parent[2] == 1 or model.parent[1] == 2, "the copy is tied to what it copies"
    post = model.posterior(votes)
    assert ((post > 0.5) == y).mean() > 0.93


def test_expectation_maximisation_equals_loops():
    rng = np.random.default_rng(3)
    votes, counts = np.unique(rng.integers(-1, 2, (400, 4)) * (rng.random((400, 4)) < 0.7), axis=0, return_counts=True)
    votes = votes.astype(int)
    known_votes, known = votes[:6], np.array([1, 0, 1, 0, 1, 0])
    first, second = (toxicity.LabelModel(rounds=n).fit(votes, counts, known_votes, known) for n in (14, 15))
    assert first.parent == second.parent, "the tree is settled"
    rows = [(v, c, p) for v, c, p in zip(votes.tolist(), counts.tolist(), first.posterior(votes).tolist(), strict=True)] + [(v, counts.sum() / 6, y) for v, y in zip(known_votes.tolist(), known.tolist(), strict=True)]
    for j, parent in enumerate(first.parent):
        for y in (0, 1):
            for above in (-1, 0, 1):
                seen = [sum(c * (p if y else 1 - p) for v, c, p in rows if v[j] == state and (v[parent] if parent >= 0 else -1) == above) + 1 / 3 for state in (-1, 0, 1)]
                assert np.allclose(second.table[j][y][above + 1], np.log(np.array(seen) / sum(seen)))
    prior = sum(c * p for _, c, p in rows) / sum(c for _, c, _ in rows)
    assert abs(second.prior - np.clip(prior, 1e-3, 0.6)) < 1e-12
    for v, p in zip(votes.tolist(), second.posterior(votes), strict=True):
        odds = prior / (1 - prior)
        for j, parent in enumerate(second.parent):
            above = v[parent] + 1 if parent >= 0 else 0
            odds *= np.exp(second.table[j][1][above][v[j] + 1] - second.table[j][0][above][v[j] + 1])
        assert abs(p - odds / (1 + odds)) < 1e-9


def test_patterns_vote_without_a_lexicon():
    lexicons, at = toxicity.Lexicons([], np.zeros(0, int)), {name: k for k, name in enumerate(toxicity.VOTERS)}
    for name, text in {"told off": "oh SHUT UP now", "called names": "You total moron, go", "masked": "what the f**k is it", "wished away": "people like you should die"}.items():
        assert lexicons.look(text)[0][at[name]] == 1, name
    quiet = lexicons.look("the meeting *** starts at 9, you should come")[0]
    assert not any(quiet[at[name]] for name in toxicity.PATTERNS) and quiet[-1] == -1


def test_toxicity_held_out_accuracy(spark, docs, none):
    rows, labels = corpus()
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    lab = spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    got = by_id(toxicity.score_documents(df, toxicity.fit(df, lab)))
    for i, r in got.items():
        assert r.held_out == (zlib.crc32(str(i).encode()) % 5 == 0) and 0 <= r.score <= 1 and r.predicted == (r.score >= 0.5)
    held = [i for i in got if got[i].held_out]
    assert np.mean([got[i].predicted == labels[i][2] for i in held]) > 0.95
    # labels of the held-out fold are never looked at
    other = spark.createDataFrame([(i, q, 1 - t if zlib.crc32(str(i).encode()) % 5 == 0 else t) for i, q, t in labels], "doc_id long, quality int, toxic int")
    assert by_id(toxicity.score_documents(df, toxicity.fit(df, other))) == got
    # without gold anchors the label model still learns the voters
    free = by_id(toxicity.score_documents(df, toxicity.fit(df, lab, anchor=0)))
    assert np.mean([free[i].predicted == labels[i][2] for i in held]) > 0.9
    # labels given twice, a labelled document given twice, a null id, labels of no document
    again = df.union(df.filter("doc_id < 40")).union(df.filter("doc_id = 6").selectExpr("cast(null as long)", *df.columns[1:]))
    more = lab.union(lab).union(lab.filter("doc_id < 9").selectExpr("doc_id + 100000", "quality", "toxic"))
    assert toxicity.labelled_sample(again, more, 8000, 5)[0] == toxicity.labelled_sample(df, lab, 8000, 5)[0]
    scored = toxicity.score_documents(again, toxicity.fit(again, more)).collect()
    assert len(scored) == 541 and [(r.held_out, r.predicted) for r in scored if r.doc_id is None] == [(False, 1)]
    assert {r.score for r in scored if r.doc_id == 6} == {r.score for r in scored if r.doc_id is None}
    # defined cases
    awkward = by_id(toxicity.score_documents(docs, toxicity.fit(docs, lab.filter("false"))))
    assert len(awkward) == docs.count() and all(r.predicted == 0 for r in awkward.values())
    assert toxicity.score_documents(none, toxicity.fit(none, lab)).count() == 0
    assert toxicity.drop_toxic(docs, lab).columns == docs.columns


def test_pipeline_equals_brute_force(spark, tmp_path):
    pipeline = pytest.importorskip("corpus_pipeline")
    _, _, reference, _ = tiktoken_encoding()
    rows, labels = corpus(n=300)
    rows += [(1000 + k, rows[k * 7 + 1][1].replace(" ", "  "), "en", "s1", 0) for k in range(12)]
    rows += [(2000 + k, rows[k * 5 + 2][1] + " tail", "en", "s2", 0) for k in range(20)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").repartition(4).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    model = toxicity.fit(docs, spark.read.parquet(f"{tmp_path}/labels.parquet"))
    left = {r[0]: r[1] for r in rows if model.score(r[1]) < 0.5}
    assert len(rows) - 20 > len(left) > len(rows) * 0.7
    first = {}
    for i in sorted(left):
        first.setdefault(WS.sub(" ", left[i]), i)
    left = {i: left[i] for i in first.values()}
    name = brute_components(brute_sets(left, 5))
    left = {i: t for i, t in left.items() if name[i] == i}
    got = by_id(pipeline.run(spark, str(tmp_path)))
    assert set(got) == set(left)
    for i, r in got.items():
        ids = reference.encode_ordinary(left[i])
        assert r.ids == ids and r.n_tokens == len(ids) and r.decoded_sha256 == hashlib.sha256(left[i].encode()).hexdigest()
    columns = docs.columns
    for _, stage in pipeline.STAGES[:-1]:
        docs = stage(spark, docs, str(tmp_path))
        assert docs.columns == columns


def test_pipeline_on_awkward_tables(spark, tmp_path, docs):
    """An empty table, null ids, a row given twice, texts that are null or empty and columns named like the stages' own, through all stages."""
    pipeline = pytest.importorskip("corpus_pipeline")
    pytest.importorskip("public_tokenizers")
    _, labels = corpus(n=40)
    own = docs.withColumns({"block": mixing.F.lit(1), "kept": mixing.F.lit("x"), "position": mixing.F.lit(9), "digest": mixing.F.lit(2)})
    rows = own.union(own.filter("doc_id = 6")).union(own.filter("doc_id = 15").withColumn("doc_id", mixing.F.lit(None).cast("long")))
    for name, table, count in (("some", rows, None), ("none", own.filter("false"), 0)):
        table.write.parquet(f"{tmp_path}/{name}/documents.parquet")
        spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/{name}/labels.parquet")
        got = pipeline.run(spark, f"{tmp_path}/{name}").collect()
        assert sorted(r.position for r in got) == list(range(len(got))) and (count is None or len(got) == count)
    got = pipeline.run(spark, f"{tmp_path}/some").collect()
    left = sorted(str(r.doc_id) for r in got)
    assert {"1", "3", "6", "7"} <= set(left) and not {"2", "4", "8", "14"} & set(left)  # copies go, one empty text stays


def test_pipeline_rows_tell_the_mix(spark, tmp_path, monkeypatch):
    pipeline = pytest.importorskip("corpus_pipeline")
    pytest.importorskip("public_tokenizers")
    rng = random.Random(6)
    rows = [(i, "word " * rng.choice([1, 3, 400]), f"s{min(2, i % 7)}") for i in range(700)]
    spark.createDataFrame(rows, "doc_id long, text string, source string").write.parquet(f"{tmp_path}/documents.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    mixed = [r.doc_id for r in mixing.mix(docs, mixing.tempered(0.5)).orderBy("slot", "offset").collect()]
    mix, tokens = pipeline.STAGES[-2:]
    spark.conf.set("spark.sql.files.maxRecordsPerFile", 90)  # several files of unequal sizes
    try:
        monkeypatch.setattr(pipeline, "STAGES", [mix, tokens])
        got = {r.position: r.doc_id for r in pipeline.run(spark, str(tmp_path)).collect()}
        monkeypatch.setattr(pipeline, "STAGES", [("mixing", lambda spark, docs, sf_dir: docs), tokens])
        plain = {r.position: r.doc_id for r in pipeline.run(spark, str(tmp_path)).collect()}
    finally:
        spark.conf.unset("spark.sql.files.maxRecordsPerFile")
    assert got == dict(enumerate(mixed)) and sorted(plain) == sorted(got) and plain != got

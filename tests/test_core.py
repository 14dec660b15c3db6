"""Worked examples, golden counts and invariants of the schema-matching methods."""

import math
from dataclasses import replace

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from ctxmatch.functions import encode, labels
from ctxmatch.models import mlp, predict, train
from ctxmatch.operators import block, match, metrics
from ctxmatch.plans import augment, graph, paths, pipeline, serialize
from ctxmatch.sources import catalog, io
from ctxmatch.sources.scenarios import MINI, SCENARIO, SPECS, TPCH, Schema, truth


def stats(spark, schemas, mode, d):
    rows = augment.statistics(catalog.load(spark, schemas), (mode,), d).collect()
    return {(r.schema_id, r.depth): (r.views, r.columns) for r in rows}


def test_published_view_counts_of_the_public_schema(spark):
    got = stats(spark, [TPCH], "directed", 5)
    assert [got["tpch", d] for d in range(1, 6)] == [(8, 61), (16, 180), (23, 337), (26, 417), (27, 457)]


def test_golden_counts_of_the_scenarios(spark):
    names = [SPECS[s] for s in (*SCENARIO, "corpus")]
    directed, inverse = stats(spark, names, "directed", 4), stats(spark, names, "inverse", 4)
    assert directed == inverse
    assert [directed["star", d] for d in (1, 2, 3, 4)] == [(7, 37), (14, 117), (19, 190), (21, 226)]
    assert [directed["rental", d] for d in (2, 3, 4)] == [(32, 181), (52, 407), (62, 561)]
    assert directed["corpus", 4] == (8, 34)
    undirected = stats(spark, [SPECS["star"], SPECS["dealer"]], "undirected", 7)
    assert undirected["star", 5] == (49, 725) and undirected["dealer", 7] == (64, 1005)


def test_truth_counts():
    found = {}
    for a, _, b, _, kind in truth():
        found.setdefault((a, b), []).append(kind)
    assert {k: (v.count("direct"), v.count("contextual")) for k, v in found.items()} == {
        ("star", "desk"): (20, 6), ("star", "dealer"): (18, 7), ("star", "rental"): (23, 10), ("desk", "dealer"): (16, 8), ("desk", "rental"): (14, 13), ("dealer", "rental"): (16, 10),
    }


def test_direction_stops_paths_and_neighbours_of_a_view(spark):
    c = catalog.load(spark, [MINI["mini_ship"]])
    directed = {r.view_id for r in paths.views(graph.edges(c), c.tables, 4).collect()}
    assert "client>shipment>line" in directed and "client>shipment>shop" not in directed
    assert "client>shipment>shop" in {r.view_id for r in paths.views(graph.edges(c, "undirected"), c.tables, 4).collect()}
    views = paths.views(graph.edges(c), c.tables, 2)
    near = {r.view_id: (r.weak, r.strong) for r in augment.context(views, c).collect()}
    assert near["client>shipment"] == (["line"], ["shop"])
    rac = augment.expand(views, c).withColumn("y", labels.soft(F.col("path"), F.col("position")))
    y = rac.filter("view_id = 'client>shipment' and column_name = 'country'").first().y
    assert y == {"client": pytest.approx(0.60653, abs=1e-5), "shipment": 1.0}


def test_ties_cycles_islands_and_self_references(spark):
    c = catalog.load(spark, [MINI["mini_tie"]])
    assert {r.view_id for r in paths.views(graph.edges(c), c.tables, 3).collect() if r.n_tables == 3} == {"a>b>d"}
    assert {r.view_id for r in paths.views(graph.edges(c), c.tables, 3, ties="all").collect() if r.n_tables == 3} == {"a>b>d", "a>c>d"}
    assert graph.edges(catalog.load(spark, [MINI["mini_multi"]])).count() == 1
    assert graph.edges(catalog.load(spark, [MINI["mini_self"]])).count() == 0
    c = catalog.load(spark, [MINI["mini_cycle"]])
    assert {r.view_id for r in paths.views(graph.edges(c), c.tables, 5).collect()} == {"shop", "staff", "shop>staff", "staff>shop"}
    rows = augment.build(catalog.load(spark, [MINI["mini_island"]]), d_max=3)
    assert all(r.text.endswith("[SEP] weak tables None [SEP] strong tables None") for r in rows.collect())


def test_sentences(spark):
    c = catalog.load(spark, [SPECS["star"]])
    rows = {r.column_name: r.text for r in augment.build(c, d_max=1, kind="META").collect()}
    assert rows["c_nationkey"] == "[CLS] column c_nationkey [SEP] table customer [SEP] type int [SEP] constraint foreign key references table nation column n_nationkey"
    assert rows["c_acctbal"].endswith("constraint None") and rows["c_custkey"].endswith("constraint primary key")
    both = augment.build(catalog.load(spark, [SPECS["corpus"]]), d_max=1, kind="NOTAB").filter("column_id = 'corpus.labels.doc_id'").first().text
    assert "primary key and foreign key" in both and "table labels" not in both
    bare = augment.build(c, d_max=1, kind="META", options=serialize.Options(anchors=False, marks=False, tokens=3)).filter("column_name = 'p_size'").first().text
    assert bare == "p_size part int"
    doc = serialize.table(c).filter("table_id = 'nation'").first().text
    assert doc == "[CLS] table nation [SEP] keys n_nationkey int [SEP] foreign keys n_regionkey int references region r_regionkey [SEP] columns n_name string"


def brute_views(tables, links, d_max):
    best = {}
    for s in tables:
        front = [[s]]
        best[s, s] = [s]
        for _ in range(d_max - 1):
            found = {}
            for p in front:
                for a, b in links:
                    if a == p[-1] and (s, b) not in best:
                        found[b] = min(found.get(b, p + [b]), p + [b])
            for b, p in found.items():
                best[s, b] = p
            front = list(found.values())
    return sorted(best.values())


@settings(max_examples=5, deadline=None)
@given(st.sets(st.tuples(st.sampled_from("abcde"), st.sampled_from("abcde")), min_size=1, max_size=9), st.integers(1, 4))
def test_views_equal_breadth_first_search(spark, links, d_max):
    s = Schema("g", {x: x for x in "abcde"}, [(x, f"{x}1", 1, "int", True, None, "") for x in "abcde"], [(a, f"{a}1", b, f"{b}1") for a, b in links])
    c = catalog.load(spark, [s])
    want = brute_views("abcde", {(a, b) for a, b in links if a != b}, d_max)
    for how in ("group", "join"):
        assert sorted(list(r.path) for r in paths.views(graph.edges(c), c.tables, d_max, how=how).collect()) == want
    every = [sorted(list(r.path) for r in paths.views(graph.edges(c), c.tables, d_max, how=how, ties="all").collect()) for how in ("group", "join")]
    assert every[0] == every[1]
    counted = {r.depth: r.pairs for r in paths.estimate(graph.edges(c), c.tables, d_max).collect()}
    assert counted == {d: sum(len(p) == d for p in want) for d in {len(p) for p in want}}
    assert sum(r.pairs for r in paths.estimate(graph.edges(c), c.tables, d_max, budget=4).collect()) == counted[1] == 5


def test_encoders(spark):
    df = spark.createDataFrame([(1, "customer name customer"), (2, ""), (3, "customer name")], "id long, text string")
    x = {r.id: np.array(r.x) for r in encode.WordHash(64).transform(df, "text", "x").collect()}
    assert abs(np.linalg.norm(x[1]) - 1) < 1e-6 and not x[2].any()
    cells = {(r.id, r.bucket): r.value for r in encode.word_buckets(df, ["id"], "text").collect()}
    for (i, b), v in cells.items():
        assert abs(x[i][b] - v) < 1e-6
    for e in (encode.HashedNgram(128), encode.HashedTfIdf(64), encode.Word2VecPooled(8)):
        rows = e.transform(df, "text", "x").collect()
        assert {len(r.x) for r in rows} == {e.dim}


CONFIG = mlp.TrainConfig(hidden=(7, 5), epochs=4, folds=2, dropout=0.0)


def sample(n=12, d=6, outputs=5, seed=1):
    rng = np.random.default_rng(seed)
    mask = np.zeros((n, outputs))
    mask[: n // 2, :3] = 1
    mask[n // 2 :, 3:] = 1
    return rng.standard_normal((n, d)), rng.choice([0, 0.60653, 1], (n, outputs)) * mask, mask


@pytest.mark.parametrize("loss", ["focal", "bce"])
def test_gradients_equal_finite_differences_and_respect_the_mask(loss):
    x, y, mask = sample()
    config = replace(CONFIG, loss=loss)
    net = mlp.Mlp((6, 7, 5, 5), 3)
    dw, db = net.gradients(x, y, mask, config)
    for params, grads in ((net.w, dw), (net.b, db)):
        for p, g in zip(params, grads, strict=True):
            at = tuple(np.random.default_rng(0).integers(0, s) for s in p.shape)
            old = p[at]
            p[at] = old + 1e-6
            up = net.loss(x, y, mask, config)
            p[at] = old - 1e-6
            down = net.loss(x, y, mask, config)
            p[at] = old
            assert abs((up - down) / 2e-6 - g[at]) < 1e-6
    half = net.gradients(x[:6], y[:6], mask[:6], config)
    assert not half[0][-1][:, 3:].any() and not half[1][-1][3:].any()


def test_focal_reduces_to_half_of_bce():
    p, y = np.array([0.01, 0.5, 0.99]), np.array([0, 0.60653, 1])
    assert np.allclose(mlp.focal(p, y, 0.5, 0), mlp.bce(p, y) / 2)
    assert math.isclose(mlp.focal(np.array([0.5]), np.array([1.0]), 0.9, 2)[0], 0.9 * 0.25 * math.log(2))


def test_weights_round_trip_and_sliced_head():
    net = mlp.Mlp((6, 7, 5, 5), 2)
    x = sample()[0]
    back = mlp.Mlp.from_bytes((6, 7, 5, 5), net.to_bytes())
    assert np.allclose(net.forward(x)[0], back.forward(x)[0], atol=1e-6)
    assert np.allclose(net.forward(x, slice(2, 4))[0], net.forward(x)[0][:, 2:4])


def test_training_is_deterministic_and_scores_cover_the_target(spark, tmp_path):
    c = catalog.load(spark, [SPECS["desk"], SPECS["dealer"]])
    rac = augment.build(c, d_max=2, kind="META", encoder=encode.HashedNgram(32))
    models = train.train(rac, c.tables, "PAIR", config=CONFIG)
    a, b = models.collect(), train.train(rac.repartition(5), c.tables, "PAIR", config=CONFIG).collect()
    assert {(r.model_id, r.fold): r.weights for r in a} == {(r.model_id, r.fold): r.weights for r in b} and len(a) == 2
    train.save(models, str(tmp_path / "m"))
    saved = train.load(spark, str(tmp_path / "m"))
    cols = augment.build(c, d_max=1, kind="META", encoder=encode.HashedNgram(32))
    pairs = spark.createDataFrame([("desk", "dealer"), ("dealer", "desk")], "source_schema string, target_schema string")
    top = predict.top_tables(predict.scores(cols, saved, "PAIR", pairs)).collect()
    assert len(top) == 29 * 8 + 35 * 7 and {r.rank for r in top if r.target_schema == "desk"} == set(range(1, 8))
    outputs = sorted(f"{r.schema_id}.{r.table_id}" for r in c.tables.collect())
    net = mlp.Mlp((32, 7, 5, len(outputs)), 1)
    dw, _ = train.gradient_step(rac.repartition(3), net, outputs, CONFIG)
    x, y, mask = train.matrices(rac.select("schema_id", "x", "y").toPandas(), outputs)
    assert np.allclose(dw[0], net.gradients(x, y, mask, CONFIG)[0][0], atol=1e-9)
    # models too large to be sent to every task meet blocks of columns
    every = lambda df: sorted((r.run, r.column_id, r.target_schema, r.table_id, round(r.p, 9)) for r in df.collect())
    assert every(predict.scores(cols, saved, "PAIR", pairs, broadcast_bytes=0)) == every(predict.scores(cols, saved, "PAIR", pairs))


def test_distributed_training_equals_local_steps(spark):
    c = catalog.load(spark, [SPECS["desk"]])
    rac = augment.build(c, d_max=2, kind="META", encoder=encode.HashedNgram(16))
    outputs, config = sorted(f"desk.{r.table_id}" for r in c.tables.collect()), replace(CONFIG, batch=40)
    net = train.train_distributed(rac.repartition(3), outputs, config, epochs=2, seed=5)
    n = rac.count()
    batches = -(-n // 40)
    rows = rac.select("schema_id", "x", "y", *[train.batch_of(e, batches).alias(f"b{e}") for e in (0, 1)]).toPandas()
    local, adam = mlp.Mlp((16, 7, 5, len(outputs)), 5), mlp.Adam(config)
    before = local.loss(*train.matrices(rows, outputs), config)
    for e in (0, 1):
        for b in range(batches):
            dw, db = local.gradients(*train.matrices(rows[rows[f"b{e}"] == b], outputs), config)
            adam.step(local.w + local.b, dw + db)
    assert all(np.allclose(x, y, atol=1e-7) for x, y in zip(net.w + net.b, local.w + local.b, strict=True))
    assert net.loss(*train.matrices(rows, outputs), config) < before


def test_model_counts():
    assert [train.count(k, 4) for k in train.KINDS] == [4, 6, 1] and [len(train.specs(k, list(SCENARIO))) for k in train.KINDS] == [4, 6, 1]


def test_knn_equals_brute_force_and_unit_vectors_agree_on_cosine(spark, monkeypatch):
    rng = np.random.default_rng(4)
    v = rng.standard_normal((60, 8))
    v /= np.linalg.norm(v, axis=1, keepdims=True)
    rows = [(i, v[i].tolist()) for i in range(60)]
    src, tgt = spark.createDataFrame(rows[:20], "query long, x array<double>"), spark.createDataFrame(rows[20:], "neighbour long, x array<double>").repartition(3)
    got = {(r.query, r.rank): r.neighbour for r in block.knn(src, tgt, 5).collect()}
    for q in range(20):
        order = sorted(range(20, 60), key=lambda t: (round(float(np.linalg.norm(v[q] - v[t])), 6), t))[:5]
        assert [got[q, k] for k in range(1, 6)] == order
    assert got == {(r.query, r.rank): r.neighbour for r in block.knn(src, tgt, 5, metric="cosine").collect()}
    every = spark.createDataFrame([(q, 0) for q in range(20)], "query long, table_id int")
    monkeypatch.setattr(block, "TILE", (7, 9))
    tiles = block.knn(src, tgt, 5, broadcast_bytes=0)
    assert got == {(r.query, r.rank): r.neighbour for r in tiles.collect()}
    within = block.knn_within(src, tgt.withColumn("table_id", F.lit(0)), every, 5)
    assert got == {(r.query, r.rank): r.neighbour for r in within.collect()}


@pytest.mark.parametrize("metric", ["l2", "cosine"])
@pytest.mark.parametrize("limit", [block.BROADCAST_BYTES, 0])
def test_knn_breaks_ties_by_neighbour(spark, metric, limit):
    order = np.random.default_rng(2).permutation(400).tolist()
    tgt = spark.createDataFrame([(i, [1.0, 2.0]) for i in order], "neighbour long, x array<double>").repartition(5)
    src = spark.createDataFrame([(1, [2.0, 1.0]), (2, [1.0, 2.0]), (3, [0.0, 0.0])], "query long, x array<double>")
    got = {}
    for r in block.knn(src, tgt, 3, metric=metric, broadcast_bytes=limit).collect():
        got.setdefault(r.query, []).append((r.rank, r.neighbour, r.dist))
    assert {q: [n for _, n, _ in sorted(v)] for q, v in got.items()} == {1: [0, 1, 2], 2: [0, 1, 2], 3: [0, 1, 2]}
    assert got[2][0][2] == (0 if metric == "l2" else 1)
    assert block.knn(src, tgt.filter("false"), 3, metric=metric, broadcast_bytes=limit).count() == 0 == block.knn(src.filter("false"), tgt, 3, broadcast_bytes=limit).count()


def test_knn_across_keeps_unlike_and_orthogonal_neighbours(spark):
    rows = [("s", "s.a", [1.0, 0.0]), ("s", "s.b", [0.0, 1.0]), ("t", "t.a", [0.0, 1.0]), ("t", "t.b", [-1.0, 0.0]), ("u", "u.a", [0.0, 0.0])]
    df = spark.createDataFrame(rows, "schema_id string, id string, x array<double>").repartition(3)
    found = block.knn(df.withColumnRenamed("id", "query"), df.withColumnRenamed("id", "neighbour"), None, metric="cosine", across="schema_id")
    got = {(r.query, r.schema_id, r.rank): (r.neighbour, r.dist) for r in found.collect()}
    assert got["s.a", "t", 1] == ("t.a", 0.0) and got["s.a", "t", 2] == ("t.b", -1.0) and got["s.a", "u", 1] == ("u.a", 0.0)
    assert len(got) == 2 * 3 + 2 * 3 + 4


def test_hashed_blocking_finds_nine_in_ten(spark):
    from ctxmatch.queries.methods import K_GRID, lsh_recall

    recall = {r.k: r.recall for r in lsh_recall(spark, "/root/testdata/sf0.01").collect()}
    assert sorted(recall) == K_GRID and min(recall.values()) >= 0.9


def test_recall_units_and_average_precision(spark):
    truth_rows = spark.createDataFrame([(1, "a", "t1"), (1, "a", "t2"), (1, "b", "t3")], "g int, q string, item string")
    ranked = spark.createDataFrame([(1, "a", "t1", 1), (1, "a", "t9", 2), (1, "a", "t2", 3), (1, "b", "t9", 1), (1, "b", "t3", 2)], "g int, q string, item string, rank int")
    how = {"query": "q", "item": "item", "by": ["g"]}
    get = lambda df, c: {r.k: r[c] for r in df.collect()}
    assert get(metrics.recall_at(ranked, truth_rows, [1, 2, 3], cutoff="k", **how), "recall") == {1: 0.333333, 2: 0.666667, 3: 1.0}
    assert get(metrics.recall_at(ranked, truth_rows, [1, 2, 3], cutoff="k", unit="any", **how), "recall") == {1: 0.5, 2: 1.0, 3: 1.0}
    assert get(metrics.recall_at(ranked, truth_rows, [1, 2, 3], cutoff="k", unit="all", **how), "recall") == {1: 0.0, 2: 0.5, 3: 1.0}
    assert get(metrics.map_at(ranked, truth_rows, [1, 3], **how), "map") == {1: 0.5, 3: pytest.approx(((1 + 2 / 3) / 2 + 1 / 2) / 2, abs=1e-6)}
    p = {r.k: r for r in metrics.precision_f1_mrr(ranked, truth_rows, [3], **how).collect()}[3]
    assert (p.precision, p.mrr) == (0.5, 0.75)


def test_full_search_equals_all_tables_and_learning_beats_chance(spark, tmp_path_factory):
    from ctxmatch.queries.methods import valued

    cat = valued(spark, "/root/testdata/sf0.001")
    tables = pipeline.predict_tables(cat, pipeline.learn(cat, "HOLO", 2), "HOLO")
    every = tables.select("column_id", "target_schema", "table_id")
    key = lambda df: sorted((r.column_id, r.target_column, r.cosine) for r in df.collect())
    assert key(pipeline.column_cosines(cat, every)) == key(pipeline.full_search(cat, None))
    from ctxmatch.queries.methods import directed_truth

    wanted = metrics.table_truth(directed_truth(spark))
    hit = wanted.join(tables.filter("rank <= 3"), ["source_schema", "column_id", "target_schema", "table_id"], "left_semi").count() / wanted.count()
    chance = np.mean([3 / {"star": 7, "desk": 7, "dealer": 8, "rental": 15}[r.target_schema] for r in wanted.collect()])
    assert hit > chance + 0.15


def test_break_even_and_group_means(spark):
    rows = spark.createDataFrame([("s", 1, 0.2), ("s", 2, 0.5), ("s", 3, 0.6), ("s", 4, 0.55)], "s string, t int, value double")
    assert metrics.break_even_t(rows, ["s"]).first().t == 3
    res = spark.createDataFrame([("x-a", "a", "M", 1, 0.4), ("x-a", "a", "M", 2, 1.0), ("x-b", "b", "M", 1, 0.8)], "scenario string, target string, model string, t int, value double")
    got = {(r.group, r.t): r.value for r in metrics.group_means(res, "b").collect()}
    assert got == {("target is not large", 1): 0.4, ("target is not large", 2): 1.0, ("target is large", 1): 0.8, ("all", 1): 0.6, ("all", 2): 1.0}
    carried = {(r.group, r.t): r.value for r in metrics.group_means(res, "b", "carry_forward").collect()}
    assert carried["all", 2] == 0.9
    assert [pipeline.default_t(k) for k in (1, 3, 10, 20)] == [2, 3, 4, 5]


def test_late_rows_are_dropped_and_counted(spark):
    from ctxmatch.queries.streams import closed_days

    seen = []
    days = {str(r.day): r.n for r in closed_days(spark, "/root/testdata/sf0.001", seen).collect()}
    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet").groupBy(F.to_date("ts").alias("d")).count().collect()
    assert days == {str(r.d): r["count"] for r in events if str(r.d) in days} and len(days) >= 25
    assert sum(p["late"] for p in seen) >= 5 and sum(p["rows"] for p in seen) > sum(r["count"] for r in events)


def test_registered_matcher_equals_the_pipeline(spark):
    from ctxmatch.functions.registered import register, register_matcher
    from ctxmatch.queries.methods import valued

    cat, encoder = valued(spark, "/root/testdata/sf0.001"), encode.HashedNgram(256)
    models = pipeline.learn(cat, "HOLO", 1, config=replace(pipeline.QUICK, epochs=2))
    register(spark)
    register_matcher(spark, cat, models, "HOLO", encoder=encoder)
    tables = pipeline.predict_tables(cat, models, "HOLO")
    near = tables.filter("rank <= 3").select("column_id", "target_schema", "table_id")
    want = block.ranked(pipeline.column_cosines(cat, near), ["column_id", "target_schema"], [F.col("cosine").desc(), F.col("target_column")], 5).filter("source_schema = 'star' AND target_schema = 'desk'")
    key = lambda df: sorted((r.column_id, r.target_column, round(r.cosine, 5), r["rank"]) for r in df.collect())
    assert key(spark.sql("SELECT * FROM match_schemas('star', 'desk', 3, 5)")) == key(want)
    text = augment.build(cat, d_max=1, kind="REF").filter("column_id = 'star.customer.c_name'").first().text
    got = {r.table_id: (r["rank"], r.p) for r in spark.sql("SELECT * FROM candidate_tables(:text, 'rental')", args={"text": text}).collect()}
    assert got == {r.table_id: (r["rank"], r.p) for r in tables.filter("column_id = 'star.customer.c_name' AND target_schema = 'rental'").collect()}


def test_explanations_link_suggestion_and_match(spark):
    cat = catalog.load(spark, [SPECS["rental"]])
    links = paths.views(graph.edges(cat, "undirected"), cat.tables, 8)
    matches = spark.createDataFrame([("star.region.r_name>rental", "rental.continents.continent_name", 0.9)], "query string, target string, cosine double")
    tables = spark.createDataFrame([("star.region.r_name>rental", 1, "members", 0.8), ("star.region.r_name>rental", 2, "continents", 0.3)], "query string, rank int, table_id string, p double")
    row = match.explain(matches, tables, links).first()
    assert row.within and row.link == "members>outlets>countries>continents" and [s.p for s in row.suggested] == [0.8, 0.3]


def test_results_survive_a_sink(spark, tmp_path):
    rows = spark.createDataFrame([("a", "a.t.x", "b", "b.u.y", 0.5, 1)], "source_schema string, column_id string, target_schema string, target_column string, cosine double, rank int")
    io.save_matches(rows, str(tmp_path / "m"))
    assert sorted(spark.read.parquet(str(tmp_path / "m")).select(*rows.columns).collect()) == rows.collect()


def test_external_encoder_is_loaded_once_per_worker(spark):
    df = spark.createDataFrame([(1, "ab"), (2, None)], "id long, text string")
    x = {r.id: list(r.x) for r in encode.ExternalModel(lambda: lambda texts: [[len(t), 1.0] for t in texts], 2).transform(df, "text", "x").collect()}
    assert x == {1: [2.0, 1.0], 2: [0.0, 1.0]}


def test_jdbc_catalog_reads_the_information_schema():
    asked = {}

    class Reader:
        def format(self, name):
            asked["format"] = name
            return self

        def options(self, **options):
            asked.update(options)
            return self

        def load(self):
            return "rows"

    class Session:
        read = Reader()

    assert catalog.from_jdbc(Session(), "jdbc:postgresql://host/db", "retail", user="me") == "rows"
    assert asked["format"] == "jdbc" and asked["url"] == "jdbc:postgresql://host/db" and asked["user"] == "me" and "table_schema = 'retail'" in asked["query"]


def _vectors(n, dim, seed):
    return np.random.default_rng(seed).standard_normal((n, dim)).round(3)


def test_hashed_blocking_ranks_the_rows_of_its_buckets_without_joining_pairs(spark, monkeypatch):
    v, planes, tables, probes = _vectors(90, 6, 3), 3, 2, 2
    src = spark.createDataFrame([(i, v[i].tolist()) for i in range(40)], "query long, x array<double>")
    tgt = spark.createDataFrame([(i, v[i].tolist()) for i in range(40, 90)], "neighbour long, x array<double>").repartition(3)
    normals = np.random.default_rng(5).standard_normal((tables, planes, 6))
    wanted = {}
    for q in range(40):
        among = set()
        for t in range(tables):
            side = normals[t] @ v[q]
            by = np.argsort(abs(side), kind="stable")
            looks = [set(), {by[0]}, {by[1]}, {by[0], by[1]}]
            patterns = {tuple((s > 0) ^ (p in flips) for p, s in enumerate(side)) for flips in looks}
            among |= {i for i in range(40, 90) if tuple(normals[t] @ v[i] > 0) in patterns}
        order = sorted(among, key=lambda i: (round(float(np.linalg.norm(v[q] - v[i])), 6), i))[:4]
        wanted |= {(q, rank): i for rank, i in enumerate(order, 1)}
    how = {"planes": planes, "tables": tables, "probes": probes}
    found = block.lsh(src, tgt, 4, **how)
    assert {(r.query, r.rank): r.neighbour for r in found.collect()} == wanted
    assert "Join" not in found._jdf.queryExecution().executedPlan().toString()
    monkeypatch.setattr(block, "TILE", (7, 9))
    assert {(r.query, r.rank): r.neighbour for r in block.lsh(src, tgt, 4, broadcast_bytes=0, **how).collect()} == wanted


def test_search_within_tables_meets_in_tiles(spark, monkeypatch):
    v = _vectors(60, 5, 6)
    src = spark.createDataFrame([(i, v[i].tolist()) for i in range(20)], "query long, x array<double>")
    held = [(i, i % 4) for i in range(20, 60)] + [(21, 0), (22, 3)]  # two neighbours are in two tables
    tgt = spark.createDataFrame([(i, t, v[i].tolist()) for i, t in held], "neighbour long, table_id int, x array<double>").repartition(3)
    asked = [(q, t) for q in range(20) for t in range(4) if (q + t) % 3] + [(1, 0), (1, 0), (2, 9)]  # repeated, and a table that is not there
    found = block.knn_within(src, tgt, spark.createDataFrame(asked, "query long, table_id int"), 6)
    wanted = {}
    for q in range(20):
        among = {i for i, t in held if (q, t) in asked}
        order = sorted(among, key=lambda i: (round(float(np.linalg.norm(v[q] - v[i])), 6), i))[:6]
        wanted |= {(q, rank): i for rank, i in enumerate(order, 1)}
    assert {(r.query, r.rank): r.neighbour for r in found.collect()} == wanted
    assert "FlatMapCoGroupsInArrow" in found._jdf.queryExecution().executedPlan().toString()
    monkeypatch.setattr(block, "TILE", (3, 4))
    again = block.knn_within(src, tgt, spark.createDataFrame(asked, "query long, table_id int"), 6)
    assert {(r.query, r.rank): r.neighbour for r in again.collect()} == wanted


def test_constrained_recall_lists_no_true_pairs(spark):
    from ctxmatch.queries import QUERIES

    rows = spark.createDataFrame([(1, True, 1), (1, False, 2), (1, True, 3), (2, False, 1)], "g int, hit boolean, rank int")
    got = metrics.recall_of_hits(rows, spark.createDataFrame([(4,)], "total long"), [1, 3], by=["g"], cutoff="k")
    assert {(r.g, r.k): r.recall for r in got.collect()} == {(1, 1): 0.25, (1, 3): 0.5, (2, 1): 0.0, (2, 3): 0.0}
    plan = QUERIES["vector_constrained"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapCoGroupsInArrow" in plan and "zip_with" not in plan


@pytest.mark.parametrize("limit", [block.GROUP_BYTES, 0])
def test_cosine_ranks_of_a_group(spark, limit, monkeypatch):
    monkeypatch.setattr(block, "TILE", (16, 16))
    v = _vectors(50, 4, 8)
    v[3], v[41], v[44:48] = 0, 0, v[40]  # zeros, and ties
    src = spark.createDataFrame([(i, i % 2, v[i].tolist()) for i in range(20)] + [(99, 7, [1.0] * 4)], "query long, label int, x array<double>")
    tgt = spark.createDataFrame([(i, i % 2, v[i].tolist()) for i in range(20, 50)], "neighbour long, label int, x array<double>").repartition(3)
    found = block.cosine_ranks(src, tgt, "label", group_bytes=limit)
    cos = lambda q, t: round(float(v[q] @ v[t] / (np.linalg.norm(v[q]) * np.linalg.norm(v[t]))), 6) + 0.0 if v[q].any() and v[t].any() else 0.0
    wanted = {(q, rank): (t, cos(q, t)) for q in range(20) for rank, t in enumerate(sorted((t for t in range(20, 50) if t % 2 == q % 2), key=lambda t: (-cos(q, t), t)), 1)}
    assert {(r.query, r.rank): (r.neighbour, r.dist) for r in found.collect()} == wanted
    assert found.schema["rank"].dataType.simpleString() == "int"
    assert ("Window" in found._jdf.queryExecution().executedPlan().toString()) == (limit == 0)

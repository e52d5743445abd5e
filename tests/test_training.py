"""Block training, evaluation and baselines on small graphs."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from gembed.baselines import coarsen, graph_conv, walks
from gembed.operators import evaluate, experiments, kernels, partition, train_block
from gembed.operators.spec import EntityType, GraphSpec, RelationSpec, preset
from gembed.plans import checks
from gembed.sources import graphs

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def community(spark):
    """Two groups of nodes, edges inside groups only."""
    rng = np.random.default_rng(0)
    rows = {(f"n{g}_{a}", f"n{g}_{b}") for g in range(4) for a, b in rng.integers(0, 15, (120, 2)) if a != b}
    return spark.createDataFrame([("r", s, d, 1) for s, d in sorted(rows)], "rel string, src string, dst string, weight long").cache()


def spec_of(**changes):
    return preset("identity", [EntityType("n")], [("r", "n", "n")], **({"dim": 8, "lr": 0.1, "chunk": 20, "uniform": 20, "batch": 100} | changes))


def vectors(model):
    return {r["key"]: np.array(r["vec"]) for r in model.vectors().collect()}


def test_parts_cover_all_edges(spark, community):
    p = train_block.prepare(community, spec_of(), 4)
    assert p.edges.count() == community.count()
    assert sum(p.sizes.values()) == p.entities.count() == 60
    assert p.entities.groupBy("part").agg(F.min("offset").alias("a"), (F.max("offset") + 1 - F.count("*")).alias("b")).where("a != 0 or b != 0").isEmpty()


@pytest.mark.parametrize("parts,machines", [(1, 1), (4, 1), (4, 2)])
def test_training_finds_the_groups(spark, community, parts, machines):
    model = train_block.fit(train_block.prepare(community, spec_of(), parts), epochs=6, machines=machines)
    assert model.log[-1]["loss"] < model.log[0]["loss"]
    v = vectors(model)
    same = np.mean([v[a] @ v[b] for a in v for b in v if a != b and a[:3] == b[:3]])
    other = np.mean([v[a] @ v[b] for a in v for b in v if a[:3] != b[:3]])
    assert same > other


def test_a_repeated_run_gives_the_same_bytes(spark, community):
    a, b = (vectors(train_block.fit(train_block.prepare(community, spec_of(), 2), epochs=1)) for _ in range(2))
    assert all((a[k] == b[k]).all() for k in a)


def test_resume_equals_an_uninterrupted_run(spark, community, tmp_path):
    prep = train_block.prepare(community, spec_of(), 2)
    whole = vectors(train_block.fit(prep, epochs=2))
    folder = f"file://{tmp_path}/model"
    train_block.fit(prep, epochs=1, checkpoint=folder)
    again = train_block.resume(prep, folder, 1)
    assert again.epoch == 1
    resumed = vectors(train_block.fit(prep, epochs=2, model=again))
    assert all((whole[k] == resumed[k]).all() for k in whole)


def test_one_part_equals_the_plain_kernel(spark, community):
    spec = spec_of()
    prep = train_block.prepare(community, spec, 1)
    got = vectors(train_block.fit(prep, epochs=1))
    rows = prep.edges.orderBy("h").collect()
    m = kernels.start_matrix(spec, 0, 0, prep.sizes[0, 0])
    rng = np.random.Generator(np.random.Philox(key=[spec.seed * 1_000_003, 0]))
    kernels.train_edges(spec, spec.relations[0], kernels.Params.start(spec.relations[0], 8, spec.seed), m, m, np.array([r["src_off"] for r in rows]), np.array([r["dst_off"] for r in rows]), np.ones(len(rows), np.float32), rng, kernels.Counters())
    at = {r["key"]: r["offset"] for r in prep.entities.collect()}
    assert max(np.abs(got[k] - m.x[at[k]]).max() for k in got) < 1e-5


def test_whole_types_are_shared_and_merged(spark):
    e = graphs.user_event(spark, SF)
    spec = GraphSpec((EntityType("user"), EntityType("event", False)), (RelationSpec("did", "user", "event", rhs_op="translation"),), dim=8)
    model = train_block.fit(train_block.prepare(e, spec, 2), epochs=2, machines=1)
    v = model.vectors()
    assert v.groupBy("etype").count().count() == 2 and v.count() == 20
    assert np.abs(model.params[0].theta["both", "rhs"]).sum() > 0


def test_sub_epochs_and_merge_modes(spark, community):
    model = train_block.fit(train_block.prepare(community, spec_of(), 2), epochs=1, sub_epochs=2, merge="mean")
    assert model.log[0]["edges"] == community.count()


def test_reciprocal_preset_trains(spark, community):
    spec = preset("complex_n3_reciprocal", [EntityType("n")], [("r", "n", "n")], dim=8)
    model = train_block.fit(train_block.prepare(community, spec, 1), epochs=1)
    assert {k[0] for k in model.params[0].theta} == {"src", "dst"}
    m = evaluate.evaluate(model, community, community, k=20)
    assert 0 < m["mrr"] <= 1


def test_filtered_ranks_are_not_worse(spark, community):
    model = train_block.fit(train_block.prepare(community, spec_of(), 1), epochs=3)
    raw = evaluate.rank_edges(model, community, community, k=30).withColumnRenamed("better", "raw")
    flt = evaluate.rank_edges(model, community, community, k=30, filtered=True, known=community)
    assert raw.join(flt, ["rel", "src", "dst", "side"]).where("better > raw").isEmpty()
    m = evaluate.metrics(flt).first()
    assert m["hits1"] <= m["hits10"] and 0 < m["mrr"] <= 1


def test_learned_vectors_beat_the_controls(spark):
    e = partition.split_edges(graphs.word_next(spark, SF), {"train": 0.75, "test": 0.25})
    e.persist()
    train, test = e.where("split = 'train'").drop("split"), e.where("split = 'test'").drop("split")
    model = train_block.fit(train_block.prepare(train, experiments.one_type_spec(train), 1), epochs=4)
    learned = evaluate.evaluate(model, test, train, k=500)["mrr"]
    random = evaluate.metrics(evaluate.random_ranks(test, train, 500)).first()["mrr"]
    assert abs(random - evaluate.random_mrr(500)) < 0.004 and learned > 2 * random
    by = {m: evaluate.metrics(evaluate.degree_ranks(test, train, 500, m)).first()["mrr"] for m in ("data", "uniform")}
    assert by["uniform"] > 3 * by["data"]  # degree looks good against uniform candidates only


def test_walks_follow_edges(spark, community):
    w = walks.random_walks(community, walks=1, length=4)
    near = walks.neighbours(community).select(F.col("key").alias("a"), F.col("next").alias("b"))
    steps = w.alias("x").join(w.alias("y"), F.expr("x.walk = y.walk and y.pos = x.pos + 1")).select(F.col("x.key").alias("a"), F.col("y.key").alias("b"))
    assert steps.join(near, ["a", "b"], "left_anti").isEmpty() and steps.count() == 60 * 3


def test_word2vec_base_and_levels(spark, community):
    assert walks.deepwalk(community, walks=2, length=5, dim=4, epochs=1, base="word2vec").count() == 60
    v = coarsen.mile(community, levels=2, dim=8, base="block", epochs=1)
    assert v.count() >= 55
    assert graph_conv.rgcn(community, v, 1, 8).count() == v.count()


def test_matching_pairs_are_mutual(spark, community):
    to = coarsen.matching(coarsen.undirected(community))
    assert to.groupBy("super").count().where("count > 2").isEmpty() and to.count() == 60


def test_empty_graph(spark):
    e = spark.createDataFrame([], "rel string, src string, dst string, weight long")
    model = train_block.fit(train_block.prepare(e, spec_of(), 2), epochs=1)
    assert model.vectors().count() == 0


def test_plans(spark):
    o = spark.read.parquet(f"{SF}/orders.parquet").where("o_orderkey < 10").select("o_orderkey")
    checks.assert_pushed(o, "o_orderkey")
    assert checks.read_columns(o) == ["o_orderkey:bigint>"] or "o_custkey" not in str(checks.read_columns(o))
    checks.assert_no_python(graphs.word_next(spark, SF))
    checks.assert_no_cartesian(graphs.kb(spark, SF))


def test_speed_hardly_depends_on_batched_negatives(spark):
    rows = {(r["mode"], r["negatives"]): r for r in experiments.negatives_speed(spark, (10, 50, 100), dim=32, edges=2000, nodes=2000).collect()}
    assert rows["batched", 100]["rows_per_edge"] == rows["batched", 10]["rows_per_edge"] == 4
    assert rows["unbatched", 100]["rows_per_edge"] > 150
    assert rows["batched", 100]["edges_per_second"] > 2 * rows["unbatched", 100]["edges_per_second"]


def test_multi_level_keeps_every_node(spark):
    pairs = [(f"p{i}", f"q{i}") for i in range(20)]
    paths = [(f"r{i}x{k}", f"r{i}x{k + 1}") for i in range(6) for k in range(4)]
    edges = spark.createDataFrame([("near", a, b, 1.0) for a, b in [*pairs, *paths, ("alone", "alone")]], "rel string, src string, dst string, weight double")
    nodes = {x for e in [*pairs, *paths] for x in e} | {"alone"}
    v = {r["key"]: r["vec"] for r in coarsen.mile(edges, levels=2, dim=8, base="block", epochs=1).collect()}
    assert set(v) == nodes and all(len(x) == 8 for x in v.values())
    assert v["p0"] == v["q0"] != v["p1"]


def test_edges_with_unseen_endpoints_are_ranked(spark, community):
    model = train_block.fit(train_block.prepare(community, spec_of(), 1), epochs=1)
    rel = community.first()["rel"]
    some = community.select("src", "dst").first()
    test = spark.createDataFrame([(rel, some["src"], "new"), (rel, "new", some["dst"]), (rel, "new", "newer"), (rel, some["src"], some["dst"])], "rel string, src string, dst string")
    ranks = evaluate.rank_edges(model, test, community, k=30, mode="uniform")
    for side in ("src", "dst"):
        candidates = {r["key"] for r in evaluate.candidate_keys(community, side, 30, "uniform").collect()}
        got = {(r["src"], r["dst"]): r for r in ranks.where(F.col("side") == side).collect()}
        assert len(got) == 4
        for (s, d), r in got.items():
            if "new" in (s, d):
                assert (r["better"], r["ties"]) == (0, len(candidates - {s if side == "src" else d}))
    plain = experiments.vector_ranks(model.vectors().select("key", "vec"), test, community, 30).collect()
    assert len(plain) == 4 and all(r["better"] == 0 and r["ties"] > 0 for r in plain if "new" in (r["src"], r["dst"]))


def test_ranks_by_blocks_equal_those_of_a_pool(spark, community, monkeypatch):
    model = train_block.fit(train_block.prepare(community, spec_of(sim="cos"), 1), epochs=1)
    test = community.unionByName(community.limit(3))
    for kind in ({"mode": "all"}, {"mode": "data", "filtered": True, "k": 40}):
        monkeypatch.undo()
        pool = sorted(map(tuple, evaluate.rank_edges(model, test, community, **kind).collect()))
        monkeypatch.setattr(evaluate, "POOL_BYTES", 0)
        monkeypatch.setattr(evaluate, "BLOCK_BYTES", 4 * 8 * 16)
        monkeypatch.setattr(evaluate, "BLOCK_EDGES", 50)
        assert sorted(map(tuple, evaluate.rank_edges(model, test, community, **kind).collect())) == pool


def test_one_machine_loads_as_few_parts_as_the_order_allows(spark, community):
    from gembed.operators.schedule import inside_out, simulate_swaps

    for p in (1, 2, 4):
        log = train_block.fit(train_block.prepare(community, spec_of(), p), epochs=1).log[0]
        assert (log["rounds"], log["swaps"]) == (1, simulate_swaps(inside_out(p))["loads"]) and log["edges"] == community.count()


def test_a_job_reads_the_folders_of_its_units_only(spark, community):
    prep = train_block.prepare(community, spec_of(), 4)
    rows = train_block.job_rows(prep, [[(0, 1)], [(2, 3), (2, 2)]])
    plan = rows._jdf.queryExecution().executedPlan().toString()
    assert "unit#" in plan.split("PartitionFilters:")[1].split("]")[0]
    want = prep.edges.where("unit in (1, 11, 10)").count()
    assert rows.where("p_src >= 0").count() == want


def test_merges_of_changes():
    dx, da = np.ones(6, np.float32), np.full(6, 4.0, np.float32)
    parts = [(dx, da), (3 * dx, 0 * da)]
    assert (train_block.merged(parts, "sum")[0] == 4).all() and (train_block.merged(parts, "mean")[0] == 2).all()
    x, acc = train_block.merged(parts, "adagrad")
    assert (x == 1).all() and (acc == 4).all()  # a chain without gradients changes nothing
    rows = [(np.ones(6, np.float32), np.array([9.0, 0.0, 1.0], np.float32)), (np.ones(6, np.float32), np.array([7.0, 4.0, 0.0], np.float32))]
    x, acc = train_block.merged(rows, "adagrad")
    assert np.allclose(x, [0.75 + 7**0.5 / 4, 0.75 + 7**0.5 / 4, 1, 1, 1, 1]) and acc.tolist() == [16, 4, 1]
    with pytest.raises(ValueError):
        train_block.merged(parts, "other")


def test_shared_parameters_are_taken_over_as_often_as_asked(spark, community):
    spec = preset("transe", [EntityType("n")], [("r", "n", "n")], dim=8)
    log = train_block.fit(train_block.prepare(community, spec, 4), epochs=1, sync_every=3, merge="adagrad").log[0]
    assert log["rounds"] == 4 and log["edges"] == community.count()


def test_bags_equal_a_plain_matrix_of_means():
    rng = np.random.default_rng(3)
    features = kernels.Matrix(rng.normal(size=(7, 4)).astype(np.float32), np.zeros(7, np.float32))
    bags = kernels.Bags(features, np.array([0, 2, 2, 5]), np.array([1, 6, 0, 1, 3]))
    want = np.stack([features.x[[1, 6]].mean(0), np.zeros(4), features.x[[0, 1, 3]].mean(0)])
    assert np.allclose(bags.x[np.arange(3)], want) and np.allclose(bags.x[np.array([[2, 0], [1, 1]])], want[[[2, 0], [1, 1]]])
    before = features.x.copy()
    kernels._apply(bags, np.array([0, 2, 2]), np.ones((3, 4), np.float32), 1.0, "sgd")
    assert np.allclose(before - features.x, np.array([2 / 3, 0.5 + 2 / 3, 0, 2 / 3, 0, 0, 0.5])[:, None].repeat(4, 1), atol=1e-6)


def test_featurised_types_train_their_features(spark):
    rng = np.random.default_rng(1)
    rows = sorted({(f"u{u}", f"i{u % 3}_{k}") for u, k in rng.integers(0, 60, (900, 2))})
    edges = spark.createDataFrame([("r", u, i, 1) for u, i in rows], "rel string, src string, dst string, weight long")
    bags = spark.createDataFrame([(i, f) for i in {i for _, i in rows} for f in (f"group{i[1]}", f"size{i[3:]}")], "key string, feature string")
    spec = preset("identity", [EntityType("user"), EntityType("item", featurised=True)], [("r", "user", "item")], dim=8, lr=0.1, chunk=20, uniform=20, batch=100)
    model = train_block.fit(train_block.prepare(edges, spec, 2, bags={"item": bags}), epochs=6)
    feature = {r["feature"]: np.array(r["vec"]) for r in model.feature_vectors("item").collect()}
    vec = {r["key"]: np.array(r["vec"]) for r in model.vectors().collect()}
    assert all(np.allclose(vec[i], (feature[f"group{i[1]}"] + feature[f"size{i[3:]}"]) / 2, atol=1e-6) for _, i in rows)
    own = np.mean([vec[u] @ feature[f"group{int(u[1:]) % 3}"] for u, _ in rows])
    other = np.mean([vec[u] @ feature[f"group{(int(u[1:]) + 1) % 3}"] for u, _ in rows])
    assert own > other


def test_refinement_learns_its_matrix(spark, community):
    nodes = [r["key"] for r in community.select(F.col("src").alias("key")).union(community.select("dst")).distinct().orderBy("key").collect()]
    rng = np.random.default_rng(2)
    v = spark.createDataFrame([(k, rng.normal(size=3).tolist()) for k in nodes], "key string, vec array<double>")
    held = coarsen.around(community, v).collect()
    x, y = (np.array([r[c] for r in held]) for c in ("around", "vec"))
    w = coarsen.learn_matrix(community, v, 3)
    gram = x.T @ x
    assert np.allclose(w, np.linalg.solve(gram + 1e-3 * np.trace(gram) / 3 * np.eye(3), x.T @ y))
    got = {r["key"]: np.array(r["vec"]) for r in coarsen.refine(community, v, matrix=w).collect()}
    assert all(np.allclose(got[r["key"]], 0.5 * np.array(r["vec"]) + 0.5 * np.array(r["around"]) @ w) for r in held)
    alone = spark.createDataFrame([("far", [1.0, 2.0, 3.0])], "key string, vec array<double>")
    assert {r["key"]: r["vec"] for r in coarsen.refine(community, v.union(alone), matrix=w).collect()}["far"] == [1.0, 2.0, 3.0]


def test_the_parameter_server_goes_on_batch_by_batch(spark):
    from gembed.functions import vectors as V
    from gembed.operators import train_sql

    e = graphs.user_event(spark, SF)
    start = e.select(F.col("src").alias("key")).union(e.select("dst")).distinct().select("key", V.initial(4, 0.5, 1, "init", F.col("key")).alias("vec"), F.lit(0.0).alias("acc"))
    one = {r["key"]: r["vec"] for r in train_sql.fit(e, start, batches=1, draws=5, chunk=10).collect()}
    assert one == {r["key"]: r["vec"] for r in train_sql.step(e, start, draws=5, chunk=10).collect()}
    assert len(train_sql.fit(e, start, batches=2, draws=5, chunk=10).collect()) == len(one)


def test_bags_are_read_in_columns_and_their_vectors_made_in_tasks(spark, monkeypatch):
    """Features of shared nodes come to the driver as numbers, and no node's vector goes through it."""
    edges = spark.createDataFrame([("r", f"u{i % 7}", f"i{i}", 1) for i in range(50)], "rel string, src string, dst string, weight long")
    bags = spark.createDataFrame([(f"i{i}", f) for i in range(50) if i != 3 for f in (f"a{i % 4}", f"b{i % 3}", f"b{i % 3}")], "key string, feature string")
    spec = preset("identity", [EntityType("user"), EntityType("item", featurised=True)], [("r", "user", "item")], dim=8)
    prep = train_block.prepare(edges, spec, 2, bags={"item": bags})
    names, ptr, ids = prep.bags[1]
    at = {r["key"]: r["offset"] for r in prep.entities.where("etype = 1").collect()}
    got = {k: [names[j] for j in ids[ptr[i] : ptr[i + 1]]] for k, i in at.items()}
    assert got == {f"i{i}": [] if i == 3 else [f"a{i % 4}", f"b{i % 3}"] for i in range(50)}
    model = train_block.fit(prep, epochs=1)
    sent = []
    made = type(spark).createDataFrame
    monkeypatch.setattr(type(spark), "createDataFrame", lambda self, rows, *a, **k: (sent.append(len(rows)), made(self, rows, *a, **k))[1])
    monkeypatch.setattr(train_block, "READ_VALUES", 8 * 9)
    vec = {r["key"]: np.array(r["vec"]) for r in model.vectors().where("etype = 1").collect()}
    assert sum(sent) < 20 and len(vec) == 50 and not vec["i3"].any()
    x = model.shared[1].x
    assert all(np.allclose(vec[k], x[[names.index(f) for f in fs]].mean(0), atol=1e-6) for k, fs in got.items() if fs)


def test_independent_trainings_run_side_by_side(spark, community):
    """All three are under way at once, and each returns what it returns alone."""
    import threading

    from gembed.operators import experiments

    met = threading.Barrier(3)

    def run(seed):
        met.wait(60)
        return [tuple(r) for r in train_block.fit(train_block.prepare(community, spec_of(seed=seed), 1), epochs=1).vectors().orderBy("etype", "key").collect()]

    together = experiments.side_by_side(spark, (1, 2, 3), run)
    alone = train_block.fit(train_block.prepare(community, spec_of(seed=2), 1), epochs=1).vectors().orderBy("etype", "key").collect()
    assert together[1] == [tuple(r) for r in alone] and together[0] != together[1]
    with pytest.raises(ZeroDivisionError):
        experiments.side_by_side(spark, (1, 0), lambda x: 1 / x)


def _pairs(test, train, keys, score, side):
    """Ranks of a control by pairs in plain Python."""
    out = {}
    for e in test:
        own = e[side]
        some = [c for c in keys if c != own]
        if some:
            pos = score(e, own)
            out[e["src"], e["dst"]] = (sum(score(e, c) > pos for c in some), sum(score(e, c) == pos for c in some))
    return out


@pytest.mark.parametrize("side", ["src", "dst"])
def test_controls_count_without_a_row_for_each_pair(spark, side):
    """Candidates that repeat, equal an edge's endpoint, or tie; endpoints that training has not seen."""
    from collections import Counter

    from gembed.functions.hashing import py_h32

    rng = np.random.default_rng(5)
    train = spark.createDataFrame([("r", f"a{x}", f"b{y}", 1) for x, y in {(int(x), int(y)) for x, y in rng.integers(0, 7, (60, 2)) ** 2 // 6}], "rel string, src string, dst string, weight long").cache()
    test = spark.createDataFrame([("r", f"a{x}", f"b{y}", 1) for x in range(0, 9, 2) for y in range(9)] + [("other", "a1", "b1", 1)], "rel string, src string, dst string, weight long").cache()
    keys = [r["key"] for r in evaluate.candidate_keys(train, side, 20).collect()]
    deg = Counter(r[side] for r in train.collect())
    tested = [r for r in test.collect() if r["rel"] == "r"]
    for ranks, score in ((evaluate.degree_ranks, lambda e, c: deg[c]), (evaluate.random_ranks, lambda e, c: py_h32(1, "rnd", e["src"], e["dst"] if c == e[side] else c))):
        found = ranks(test, train, 20, "data", side)
        assert "Aggregate" not in found._jdf.queryExecution().executedPlan().toString()
        assert {(r["src"], r["dst"]): (r["better"], r["ties"]) for r in found.collect()} == _pairs(tested, train, keys, score, side)


def test_vector_ranks_count_without_a_row_for_each_pair(spark, community):
    """Nodes without a vector tie, also as candidates; repeated candidates count as often as they occur."""
    keys = sorted({r[s] for r in community.collect() for s in ("src", "dst")})
    rng = np.random.default_rng(3)
    x = {k: rng.integers(-2, 3, 3).astype(float) for k in keys[::2] + keys[1::4]}
    vec = spark.createDataFrame([(k, v.tolist()) for k, v in x.items()], "key string, vec array<float>")
    drawn = [r["key"] for r in evaluate.candidate_keys(community, "dst", 30).collect()]
    found = experiments.vector_ranks(vec, community, community, 30)
    assert "Aggregate" not in found._jdf.queryExecution().executedPlan().toString()
    want = {}
    for e in community.collect():
        s, d = x.get(e["src"]), x.get(e["dst"])
        some = [c for c in drawn if c != e["dst"]]
        less = lambda c, f: s is not None and d is not None and c in x and f(s @ x[c], s @ d)  # noqa: B023, E731
        tied = sum(s is None or d is None or c not in x or s @ x[c] == s @ d for c in some)
        want[e["src"], e["dst"]] = (sum(less(c, lambda a, b: a > b) for c in some), tied)
    assert {(r["src"], r["dst"]): (r["better"], r["ties"]) for r in found.collect()} == want


def test_large_tables_are_shuffled_with_the_same_results(spark, community, monkeypatch):
    from gembed import session
    from gembed.sources import graphs

    spec = experiments.one_type_spec(community, dim=8)

    def results():
        model = train_block.fit(train_block.prepare(community, spec, 2), epochs=1)
        ranks = sorted(tuple(r) for r in evaluate.rank_edges(model, community, community, 20).collect())
        words = sorted(tuple(r) for r in graphs.word_next(spark, "/root/testdata/sf0.001").collect())
        return ranks, words, sorted(tuple(r) for r in evaluate.degree_ranks(community, community, 20).collect())

    small = results()
    monkeypatch.setattr(session, "SMALL_BYTES", 0)
    assert results() == small


def test_an_epoch_comes_in_the_order_of_units_buckets_and_hashes(spark, community):
    prep = train_block.prepare(community, experiments.one_type_spec(community, dim=8), 2)
    rows = train_block.job_rows(prep, [[(0, 1), (0, 0)], [(1, 1)]], epoch=1).collect()
    mixed = {(r["p_src"], r["p_dst"], r["src_off"], r["dst_off"]): r["h"] for r in prep.edges.selectExpr("p_src", "p_dst", "src_off", "dst_off", "xxhash64(h, 1) h").collect()}
    at = [(r["chain"], r["seq"], r["p_src"], r["p_dst"], mixed.get((r["p_src"], r["p_dst"], r["src_off"], r["dst_off"]), -1)) for r in rows]
    assert at == sorted(at) and len(rows) == community.count() + 3


def test_fits_of_labels_run_side_by_side(spark, monkeypatch):
    """Fits of all folds and labels overlap, and their scores are those of one fit after another."""
    import threading
    import time

    from gembed.operators import downstream

    rows = [(f"d{i}", [float(i % 2), float(i % 3 == 0), float(i % 5)]) for i in range(60)]
    vec = spark.createDataFrame(rows, "key string, vec array<float>")
    labels = spark.createDataFrame([(k, "odd" if x[0] else "even") for k, x in rows], "key string, label string")
    at, most, lock, fit = [0], [0], threading.Lock(), downstream.LogisticRegression.fit

    def counted(self, *args):
        with lock:
            at[0] += 1
            most[0] = max(most[0], at[0])
        time.sleep(0.3)
        try:
            return fit(self, *args)
        finally:
            with lock:
                at[0] -= 1

    monkeypatch.setattr(downstream.LogisticRegression, "fit", counted)
    found = downstream.classify(vec, labels, 10, 1).collect()
    assert most[0] > 1 and [(r["fold"], r["micro_f1"], r["macro_f1"]) for r in found] == [(0, 1.0, 1.0)]


@pytest.mark.parametrize("blocks", (False, True))
def test_raw_and_filtered_ranks_come_from_the_same_scores(spark, community, monkeypatch, blocks):
    model = train_block.fit(train_block.prepare(community, spec_of(), 1), epochs=1)
    if blocks:
        monkeypatch.setattr(evaluate, "POOL_BYTES", 0)
        monkeypatch.setattr(evaluate, "BLOCK_BYTES", 4 * 8 * 16)
    test = community.unionByName(community.limit(3).withColumn("dst", F.lit("unseen")))
    one = [evaluate.evaluate(model, test, community, k=40, filtered=filtered) for filtered in (False, True)]
    assert one[0]["mr"] > one[1]["mr"]
    for a, b in zip(evaluate.evaluate_both(model, test, community, k=40), one, strict=True):
        assert a == pytest.approx(b)


def test_link_prediction_scores_each_edge_and_side_once_for_a_method(spark, community, monkeypatch):
    scored, known = [], []
    ranks, kept = evaluate.rank_edges, evaluate.known_candidates
    monkeypatch.setattr(evaluate, "rank_edges", lambda *a, **k: scored.append(1) or ranks(*a, **k))
    monkeypatch.setattr(evaluate, "known_candidates", lambda *a, **k: known.append(1) or kept(*a, **k))
    found = experiments.link_prediction(spark, community, ("transe", "identity"), epochs=1, dim=8, k=30).collect()
    assert [(r["method"], r["ranks"]) for r in found] == [(m, r) for m in ("transe", "identity") for r in ("raw", "filtered")]
    assert all(0 < r["mrr"] <= 1 for r in found) and len(scored) == 2 and len(known) == 2


def test_filtered_ranks_of_placed_edges_need_no_join(spark, community):
    prepared = train_block.prepare(community, spec_of(), 1)
    model = train_block.fit(prepared, epochs=1)
    test = community.unionByName(community.limit(3).withColumn("dst", F.lit("unseen")))
    drawn = {side: evaluate.stored(evaluate.candidate_keys(community, side, 40), "candidates") for side in ("src", "dst")}
    drops = {side: evaluate.known_candidates(test, community, drawn[side], side) for side in drawn}
    where = evaluate.placed_with(evaluate.placed(prepared, test), drops)
    ranks = evaluate.rank_edges(model, test, community, filtered=True, known=community, drawn=drawn, where=where)
    assert "Join" not in checks.plan_text(ranks)
    want = evaluate.rank_edges(model, test, community, filtered=True, known=community, drawn=drawn)
    assert sorted(map(tuple, ranks.collect())) == sorted(map(tuple, want.collect()))


def test_fits_read_a_stored_table_in_as_few_tasks_as_its_bytes_ask_for(spark, monkeypatch):
    from gembed.operators import downstream

    rows = [(f"d{i}", [float(i % 2), float(i % 3 == 0), float(i % 5)]) for i in range(60)]
    vec = spark.createDataFrame(rows, "key string, vec array<float>").repartition(4)
    labels = spark.createDataFrame([(k, "odd" if x[0] else "even") for k, x in rows], "key string, label string")
    parts, plans, fit = [], [], downstream.LogisticRegression.fit

    def seen(self, data):
        parts.append(data.rdd.getNumPartitions())
        plans.append(checks.plan_text(data))
        return fit(self, data)

    monkeypatch.setattr(downstream.LogisticRegression, "fit", seen)
    assert [tuple(r) for r in downstream.classify(vec, labels, 10, 1).collect()] == [(0, 1.0, 1.0)]
    assert parts == [1, 1] and not any("Join" in x or "InMemoryTableScan" in x for x in plans)

"""The experiments: each returns a small DataFrame of measures."""

from __future__ import annotations

import itertools
from dataclasses import replace
from threading import Lock

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines import coarsen, walks
from ..functions.hashing import h32
from ..session import is_small, key_bytes, side_by_side, stored
from ..sources import graphs
from ..sources.tables import table
from . import downstream, evaluate, kernels
from .costs import Timer
from .partition import min_count_filter, split_edges
from .schedule import occupancy, rounds
from .spec import EntityType, GraphSpec, RelationSpec, preset
from .train_block import fit, prepare


def _halves(edges: DataFrame, test: float = 0.25) -> tuple[DataFrame, DataFrame, DataFrame]:
    e = stored(split_edges(edges, {"train": 1 - test, "test": test}), "split-edges")
    return e, e.where("split = 'train'").drop("split"), e.where("split = 'test'").drop("split")


def one_type_spec(edges: DataFrame, name: str = "identity", **changes) -> GraphSpec:
    rels = [r["rel"] for r in edges.select("rel").distinct().orderBy("rel").collect()]
    return preset(name, [EntityType("node")], [(r, "node", "node") for r in rels], **changes)


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """Word-follows-word, two parts, one epoch; ranking measures against both candidate kinds and the controls."""
    _, train, test = _halves(graphs.word_next(spark, sf))
    model = fit(prepare(train, one_type_spec(train), 2), epochs=1)
    rows = [("learned", m, *[float(v) for v in evaluate.evaluate(model, test, train, mode=m).values()]) for m in ("data", "uniform")]
    rows.append(("random", "expected", 0.0, evaluate.random_mrr(500), 251.0, 1 / 501, 10 / 501))
    return spark.createDataFrame(rows, "scorer string, candidates string, n double, mrr double, mr double, hits1 double, hits10 double")


def link_prediction(spark: SparkSession, edges: DataFrame, methods=("identity", "transe", "distmult", "complex", "rescal", "hole"), epochs: int = 5, dim: int = 32, parts: int = 1, k: int = 500) -> DataFrame:
    """Each method's measures, ranks raw and filtered by all known edges; parts, buckets, candidates and those that are known are made once for all, and scores once for both.

    Methods run side by side, so their seconds are those of a chain with the others' beside it."""
    every, train, test = _halves(edges)
    prepared = prepare(train, one_type_spec(train, dim=dim), parts)
    drawn = {side: stored(evaluate.candidate_keys(train, side, k), "candidates") for side in ("src", "dst")}
    drops = {side: stored(evaluate.known_candidates(test, every, drawn[side], side), "known-candidates") for side in drawn}
    where = evaluate.placed_with(evaluate.placed(prepared, test), drops)
    turn = Lock()  # one method's ranks at a time, with all tasks

    def run(name):
        with Timer() as t:
            model = fit(replace(prepared, spec=one_type_spec(train, name, dim=dim)), epochs=epochs)
        with turn:
            found = evaluate.evaluate_both(model, test, train, k=k, known=every, drawn=drawn, where=where, drops=drops)
        return [(name, kind, float(t.seconds), float(model.log[-1]["rss_mb"]), *[float(m[x]) for x in ("mrr", "mr", "hits10")]) for kind, m in zip(("raw", "filtered"), found, strict=True)]

    out = [row for rows in side_by_side(spark, methods, run) for row in rows]
    return spark.createDataFrame(out, "method string, ranks string, seconds double, rss_mb double, mrr double, mr double, hits10 double")


def baselines(spark: SparkSession, edges: DataFrame, epochs: int = 2, dim: int = 32, k: int = 500) -> DataFrame:
    """Own vectors, random walks and multi-level embedding of the same graph: candidates, edges and measure are the same.

    Methods run side by side, so their seconds are those of a method with the others beside it."""
    _, train, test = _halves(edges)
    turn = Lock()

    def run(name):
        with Timer() as t:
            if name == "own":
                vec = fit(prepare(train, one_type_spec(train, dim=dim), 1), epochs=epochs).vectors().select("key", "vec")
            elif name == "deepwalk":
                vec = walks.deepwalk(train, walks=2, length=6, dim=dim, epochs=epochs)
            else:
                vec = coarsen.mile(train, int(name[-1]), dim, "block", epochs)
            vec = stored(vec, "baseline-vectors")
        with turn:
            m = evaluate.metrics(vector_ranks(vec, test, train, k)).first()
        return name, float(t.seconds), m["n"], *[float(m[x]) for x in ("mrr", "mr", "hits10")]

    out = side_by_side(spark, ("own", "deepwalk", "multi_level_1", "multi_level_3"), run)
    return spark.createDataFrame(out, "method string, seconds double, n long, mrr double, mr double, hits10 double")


def featurised(spark: SparkSession, sf: str, epochs: int = 2, dim: int = 16) -> DataFrame:
    """Orders and the parts in them, parts as bags of brand, type and size: measures beside those of plain part vectors."""
    from .features import part_bags

    edges = graphs.kb(spark, sf).where("rel = 'order_has_part'").select("rel", "src", "dst", "weight")
    bags = part_bags(table(spark, sf, "part")).select(F.concat(F.lit("part:"), F.col("key").cast("string")).alias("key"), "feature")
    _, train, test = _halves(edges)
    out = []
    for name, kind in (("bags", EntityType("part", featurised=True)), ("plain", EntityType("part"))):
        spec = preset("starspace", [EntityType("order"), kind], [("order_has_part", "order", "part")], dim=dim, negatives="batched")
        with Timer() as t:
            model = fit(prepare(train, spec, 2, bags={"part": bags} if kind.featurised else None), epochs=epochs)
        m = evaluate.evaluate(model, test, train, k=200, sides=("dst",))
        vectors = len(model.prepared.bags[1][0]) if kind.featurised else sum(n for (e, _), n in model.prepared.sizes.items() if e == 1)
        out.append((name, vectors, float(t.seconds), *[float(m[x]) for x in ("mrr", "mr", "hits10")]))
    return spark.createDataFrame(out, "parts string, trained_vectors long, seconds double, mrr double, mr double, hits10 double")


def learning_curve(spark: SparkSession, edges: DataFrame, epochs: int = 5, parts: int = 2, machines: int = 1) -> DataFrame:
    _, train, test = _halves(edges)
    model = fit(prepare(train, one_type_spec(train), parts), epochs=epochs, machines=machines, after_epoch=lambda m: {"mrr": evaluate.evaluate(m, test, train)["mrr"]})
    at, out = 0.0, []
    for e in model.log:
        at += e["seconds"]
        out.append((e["epoch"], at, float(e["mrr"]), float(e["loss"])))
    return spark.createDataFrame(out, "epoch int, seconds double, mrr double, loss double")


def partition_sweep(spark: SparkSession, edges: DataFrame, parts=(1, 4, 8, 16), epochs: int = 5, dim: int = 32, k: int = 500) -> DataFrame:
    _, train, test = _halves(edges)
    out = []
    for p in parts:
        prepared = prepare(train, one_type_spec(train, dim=dim), p)
        with Timer() as t:
            model = fit(prepared, epochs=epochs)
        m = evaluate.evaluate(model, test, train, k=k)
        last = model.log[-1]
        out.append((p, float(t.seconds), sum(e["train_seconds"] for e in model.log), float(last["swaps"]), float(max(prepared.sizes.values()) * (4 * dim + 4) * 2), float(last["rss_mb"]), float(m["mrr"]), float(m["hits10"])))
    return spark.createDataFrame(out, "parts int, seconds double, kernel_seconds double, swaps double, part_pair_bytes double, rss_mb double, mrr double, hits10 double")


def parallel_sweep(spark: SparkSession, edges: DataFrame, machines=(1, 2, 4), epochs: int = 5, dim: int = 32) -> DataFrame:
    _, train, test = _halves(edges)
    out = []
    for m in machines:
        p = max(1, 2 * m) if m > 1 else 2
        with Timer() as t:
            model = fit(prepare(train, one_type_spec(train, dim=dim), p), epochs=epochs, machines=m)
        q = evaluate.evaluate(model, test, train)
        # seconds that the slowest unit of each round took: what a cluster with m free workers would wait for
        out.append((m, p, float(t.seconds), sum(e["train_seconds"] for e in model.log), occupancy(rounds(p, m, "tournament", False), m), float(q["mrr"]), float(q["hits10"])))
    return spark.createDataFrame(out, "machines int, parts int, seconds double, unit_seconds double, occupancy double, mrr double, hits10 double")


def bucket_order(spark: SparkSession, edges: DataFrame, kinds=("inside_out", "row_major", "random", "outside_in"), parts: int = 4, epochs: int = 3) -> DataFrame:
    from .schedule import aligned_by_part, order

    _, train, test = _halves(edges)

    def run(kind):
        model = fit(prepare(train, one_type_spec(train), parts), epochs=epochs, bucket_order=kind)
        return kind, model.log[-1]["swaps"], aligned_by_part(order(kind, parts)) is None, float(evaluate.evaluate(model, test, train)["mrr"])

    out = side_by_side(spark, kinds, run)
    return spark.createDataFrame(out, "kind string, loads int, aligned boolean, mrr double")


def negatives_speed(spark: SparkSession, negatives=(10, 20, 50, 100, 200, 500), dim: int = 100, edges: int = 4000, nodes: int = 20_000, batch: int = 500, given: DataFrame | None = None) -> DataFrame:
    """Edges per second of the kernel, by negatives per edge, batched and unbatched, in batches of equal size.

    Of a ``given`` graph the ``edges`` edges with the smallest hash are trained, over and over if it has fewer; without one edges are random.
    """
    rng = np.random.default_rng(1)
    if given is not None:
        drawn = given.select("src", "dst", h32(1, "bench", F.col("rel"), F.col("src"), F.col("dst")).alias("h")).orderBy("h", "src", "dst").limit(edges).toArrow()
        ends = [np.array([f"{side}:{k}" for k in drawn.column(side).to_pylist()]) for side in ("src", "dst")]
        names, places = np.unique(np.concatenate(ends), return_inverse=True)
        nodes, held = len(names), places.reshape(2, -1)
    out = []
    for mode, n in itertools.product(("batched", "unbatched"), negatives):
        rel = RelationSpec("r", "n", "n")
        half = max(1, n // 2)
        spec = GraphSpec((EntityType("n"),), (rel,), dim=dim, negatives=mode, chunk=half, uniform=half, batch=batch)
        m, params = kernels.start_matrix(spec, 0, 0, nodes), kernels.Params.start(rel, dim)
        some = edges if mode == "batched" else max(2 * batch, edges * 10 // n)
        s, d = (rng.integers(0, nodes, some), rng.integers(0, nodes, some)) if given is None else (np.resize(x, some) for x in held)
        count = kernels.Counters()
        with Timer() as t:
            kernels.train_edges(spec, rel, params, m, m, s, d, np.ones(some, np.float32), rng, count)
        out.append((mode, n, some / t.seconds, count.rows_gathered / some, count.scores / some))
    return spark.createDataFrame(out, "mode string, negatives int, edges_per_second double, rows_per_edge double, scores_per_edge double")


def negative_ablation(spark: SparkSession, edges: DataFrame, epochs: int = 3) -> DataFrame:
    """Measures by share of prevalence draws (chunk and uniform counts), under both candidate kinds."""
    _, train, test = _halves(edges)

    def run(setting):
        alpha, chunk, uniform = setting
        model = fit(prepare(train, one_type_spec(train, chunk=chunk, uniform=uniform), 1), epochs=epochs)
        return alpha, *[float(evaluate.evaluate(model, test, train, mode=m)["mrr"]) for m in ("data", "uniform")]

    out = side_by_side(spark, ((0.1, 10, 90), (0.5, 50, 50), (1.0, 100, 0)), run)
    return spark.createDataFrame(out, "alpha double, mrr_data double, mrr_uniform double")


def candidate_sampling(spark: SparkSession, edges: DataFrame, epochs: int = 3, k: int = 500) -> DataFrame:
    """Learned vectors and the controls under both candidate kinds; the controls' ranks are counted while the chain trains."""
    _, train, test = _halves(edges)
    kinds = ("data", "uniform")
    drawn = {mode: {side: stored(evaluate.candidate_keys(train, side, k, mode), "candidates") for side in ("src", "dst")} for mode in kinds}

    def learned():
        model = fit(prepare(train, one_type_spec(train), 1), epochs=epochs)
        return [float(evaluate.evaluate(model, test, train, k=k, mode=mode, drawn=drawn[mode])["mrr"]) for mode in kinds]

    def control(ranks):
        both = lambda mode: (ranks(test, train, k, mode, side, drawn=drawn[mode][side]) for side in ("src", "dst"))
        return [float(evaluate.metrics(next(x).unionByName(next(x))).first()["mrr"]) for x in map(both, kinds)]

    runs = (learned, lambda: control(evaluate.degree_ranks), lambda: control(evaluate.random_ranks))
    found = zip(*side_by_side(spark, runs, lambda f: f()), strict=True)
    return spark.createDataFrame([(scorer, mode, mrr) for mode, now in zip(kinds, found, strict=True) for scorer, mrr in zip(("learned", "degree", "random"), now, strict=True)], "scorer string, candidates string, mrr double")


def replicates(spark: SparkSession, edges: DataFrame, name: str = "complex", seeds=(1, 2, 3), parts: int = 4, machines: int = 2, epochs: int = 3) -> DataFrame:
    _, train, test = _halves(edges)

    def run(seed):
        model = fit(prepare(train, one_type_spec(train, name, seed=seed), parts), epochs=epochs, machines=machines)
        return name, seed, parts, float(evaluate.evaluate(model, test, train)["mrr"])

    out = side_by_side(spark, seeds, run)
    return spark.createDataFrame(out, "method string, seed int, parts int, mrr double")


def grid_search(spark: SparkSession, edges: DataFrame, grid: dict[str, tuple], metric: str = "mrr", epochs: int = 2) -> DataFrame:
    """All settings, chosen on a validation split; best first."""
    e = stored(split_edges(edges, {"train": 0.9, "valid": 0.05, "test": 0.05}), "grid-edges")
    train, valid = e.where("split = 'train'").drop("split"), e.where("split = 'valid'").drop("split")

    def run(values):
        setting = dict(zip(grid, values, strict=True))
        model = fit(prepare(train, one_type_spec(train, **setting), 1), epochs=epochs)
        return str(setting), float(evaluate.evaluate(model, valid, train)[metric])

    out = side_by_side(spark, itertools.product(*grid.values()), run)
    return spark.createDataFrame(sorted(out, key=lambda x: -x[1]), f"setting string, {metric} double")


def large_graph_preparation(spark: SparkSession, edges: DataFrame) -> DataFrame:
    """Nodes and relations seen five times, split 90/5/5: sizes of each split."""
    e = split_edges(min_count_filter(edges, 5), {"train": 0.9, "valid": 0.05, "test": 0.05})
    return e.groupBy("split").agg(F.count(F.lit(1)).alias("edges"), F.count_distinct("rel").alias("relations"))


def vector_ranks(vectors: DataFrame, test: DataFrame, train: DataFrame, k: int = 200) -> DataFrame:
    """Ranks under plain vectors (key, vec) by dot product, candidates by prevalence; where a vector is missing, candidates tie.

    ``vectors`` are stored. Candidates go to the tasks, where edges of one source share a row of scores in double precision.
    """
    cand = evaluate.candidate_keys(train, "dst", k).groupBy("rel", "key").agg(F.count(F.lit(1)).alias("times"))
    dim = len((vectors.select("vec").first() or {"vec": [0.0]})["vec"])
    vec = vectors.select("key", F.col("vec").cast("array<double>").alias("vec"))
    if is_small(*key_bytes(vectors, "key"), 8 * dim):
        vec = F.broadcast(vec)
    none = F.array_repeat(F.lit(0.0), dim)
    held = F.broadcast(cand).join(vec, "key", "left").select("rel", "key", "times", F.col("vec").isNotNull().alias("has"), F.coalesce("vec", none).alias("vec")).toArrow()
    rels, flat = np.array(held.column("rel").to_pylist(), object), held.column("vec").combine_chunks().flatten().to_numpy().reshape(-1, dim)
    keys, times, has = np.array(held.column("key").to_pylist(), object), held.column("times").to_numpy(), np.array(held.column("has").to_pylist(), bool)
    pools = {r: ({x: i for i, x in enumerate(keys[at])}, times[at], has[at], flat[at]) for r in set(rels.tolist()) for at in [np.flatnonzero(rels == r)]}
    rows = test.select("rel", "src", "dst").join(vec.select(F.col("key").alias("src"), F.col("vec").alias("sv")), "src", "left").join(vec.select(F.col("key").alias("dst"), F.col("vec").alias("dv")), "dst", "left")
    rows = rows.select("rel", "src", "dst", (F.col("sv").isNotNull() & F.col("dv").isNotNull()).alias("seen"), F.coalesce("sv", none).alias("sv"), F.coalesce("dv", none).alias("dv"))
    arrow = pa.schema([("rel", pa.string()), ("src", pa.string()), ("dst", pa.string()), ("better", pa.int64()), ("ties", pa.int64())])

    def run(batches):
        for b in batches:
            rel, dst = np.array(b.column("rel").to_pylist(), object), b.column("dst").to_pylist()
            seen = np.array(b.column("seen").to_pylist(), bool)
            sv, dv = (b.column(c).flatten().to_numpy(zero_copy_only=False).reshape(-1, dim) for c in ("sv", "dv"))
            better, ties, some = (np.zeros(b.num_rows, np.int64) for _ in range(3))
            for r in set(rel.tolist()) & set(pools):
                place, n, known, x = pools[r]
                step = max(1, evaluate.SCORE_BYTES // (8 * len(n)))
                every = np.flatnonzero(rel == r)
                for at in (every[lo : lo + step] for lo in range(0, len(every), step)):
                    s, pos = sv[at] @ x.T, (sv[at] * dv[at]).sum(1)
                    off = 1e-12 * np.maximum(1, np.abs(pos))  # sums in another order differ in their last digits
                    can = known & seen[at, None]
                    counts = np.broadcast_to(n, s.shape).copy()
                    own = np.array([place.get(dst[i], -1) for i in at])
                    counts[np.flatnonzero(own >= 0), own[own >= 0]] = 0
                    up = can & (s > (pos + off)[:, None])
                    level = ~can | (~up & (s >= (pos - off)[:, None]))
                    better[at], ties[at], some[at] = (counts * up).sum(1), (counts * level).sum(1), counts.sum(1)
            yield pa.RecordBatch.from_arrays([b.column("rel"), b.column("src"), b.column("dst"), pa.array(better), pa.array(ties)], schema=arrow).filter(pa.array(some > 0))

    return rows.mapInArrow(run, "rel string, src string, dst string, better long, ties long")


def baseline_metrics(spark: SparkSession, edges: DataFrame, kind: str, levels: int = 1, dim: int = 16) -> DataFrame:
    _, train, test = _halves(edges)
    with Timer() as t:
        vec = walks.deepwalk(train, walks=2, length=6, dim=dim, epochs=2) if kind == "deepwalk" else coarsen.mile(train, levels, dim, "deepwalk", 2, walks=2, length=6)
        vec = stored(vec, "baseline-vectors")
    m = evaluate.metrics(vector_ranks(vec, test, train))
    return m.select(F.lit(kind).alias("method"), F.lit(float(t.seconds)).alias("seconds"), "n", "mrr", "mr", "hits10")


def classify_documents(spark: SparkSession, sf: str, dim: int = 16, epochs: int = 2, folds: int = 10, run: int = 10) -> DataFrame:
    """Document vectors from the document-word graph as features; labels are language, quality and toxicity."""
    edges = graphs.doc_word(spark, sf, min_docs=5)
    spec = GraphSpec((EntityType("document"), EntityType("word")), (RelationSpec("contains", "document", "word"),), dim=dim)
    vec = stored(fit(prepare(edges, spec, 1), epochs=epochs).vectors().where("etype = 0").select("key", "vec"), "document-vectors")
    docs, labels = table(spark, sf, "documents"), table(spark, sf, "labels")
    many = labels.select(F.col("doc_id").cast("string").alias("key"), F.explode(F.filter(F.array(F.when(F.col("quality") == 1, F.lit("quality")), F.when(F.col("toxic") == 1, F.lit("toxic"))), lambda x: x.isNotNull())).alias("label"))
    langs = docs.join(labels.select("doc_id"), "doc_id", "left_semi").select(F.col("doc_id").cast("string").alias("key"), F.concat(F.lit("lang="), "lang").alias("label"))
    return downstream.classify(vec, many.unionByName(langs), folds, run)


def stream_ingest(spark: SparkSession, sf: str, folder: str) -> DataFrame:
    """Events appended to the bucket store by micro-batches; edges by batch."""
    from ..streaming import ingest

    events = table(spark, sf, "events").select("event_id", "ts", "user_id", "event_type")
    parts = f"{folder}/in"
    events.repartition(3, (h32(1, "day", F.to_date("ts")) % 3)).write.mode("overwrite").parquet(parts)
    ingest.append_buckets(ingest.event_stream(spark, parts, events.schema), f"{folder}/out")
    return spark.read.parquet(f"{folder}/out").groupBy("batch").agg(F.sum("weight").alias("events"), F.count(F.lit(1)).alias("edges"))

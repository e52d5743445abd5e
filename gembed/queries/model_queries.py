"""Samplers, scores, losses, steps, ranking, baselines and training experiments."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from ..baselines import coarsen, walks
from ..functions import vectors as V
from ..functions.hashing import h32, sql_h32
from ..operators import costs, downstream, evaluate, experiments, features, kernels, losses, partition, relops, schedule, train_block, train_sql  # noqa: F401
from ..operators.spec import PRESETS, EntityType, preset
from ..session import stored
from ..sources import graphs
from ..sources.tables import table
from .base import DOC_WORD, USER_EVENT, query, sql_dot, sql_vec, word_next_ctes
from .graph_queries import KNN, TWO, _split_sql

D, SPREAD = 4, 0.5


# -- samplers


def _cand_sql(side: str, k: int, mode: str, source: str = "edges") -> str:
    if mode == "data":
        return f"SELECT rel, key FROM (SELECT rel, {side} AS key, row_number() OVER (PARTITION BY rel ORDER BY {sql_h32(chr(39) + '1' + chr(39), chr(39) + 'cand' + chr(39), chr(39) + side + chr(39), 'rel', 'src', 'dst')}, {side}) AS n FROM {source}) WHERE n <= {k}"
    inner = f"(SELECT DISTINCT rel, {side} AS key FROM {source})"
    return f"SELECT rel, key FROM (SELECT rel, key, row_number() OVER (PARTITION BY rel ORDER BY {sql_h32(chr(39) + '1' + chr(39), chr(39) + 'cand' + chr(39), chr(39) + side + chr(39), 'rel', 'key')}, key) AS n FROM {inner}) WHERE n <= {k}"


@query("neg_prevalence", f"WITH {word_next_ctes()} SELECT * FROM ({_cand_sql('dst', 500, 'data')})")
def neg_prevalence(spark, sf):
    return evaluate.candidate_keys(graphs.word_next(spark, sf), "dst", 500, "data")


@query("neg_uniform", f"WITH {word_next_ctes()} SELECT * FROM ({_cand_sql('dst', 500, 'uniform')})")
def neg_uniform(spark, sf):
    return evaluate.candidate_keys(graphs.word_next(spark, sf), "dst", 500, "uniform")


@query("neg_mixed", f"WITH {word_next_ctes()} SELECT * FROM ({_cand_sql('src', 250, 'data')}) UNION ALL SELECT * FROM ({_cand_sql('src', 250, 'uniform')})")
def neg_mixed(spark, sf):
    return evaluate.candidate_keys(graphs.word_next(spark, sf), "src", 500, "mixed")


@query("eval_candidates", f"WITH {DOC_WORD} SELECT rel, count(*)::BIGINT AS n, count(DISTINCT key)::BIGINT AS different FROM ({_cand_sql('dst', 2000, 'data')}) GROUP BY rel")
def eval_candidates(spark, sf):
    return evaluate.candidate_keys(graphs.doc_word(spark, sf), "dst", 2000).groupBy("rel").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("key").alias("different"))


@query(
    "neg_unbatched",
    f"""WITH {USER_EVENT}, nodes AS (SELECT key, row_number() OVER (ORDER BY key) - 1 AS place, count(*) OVER () AS size FROM (SELECT DISTINCT dst AS key FROM edges))
    SELECT src, dst, k.k::INTEGER AS slot, key AS cand FROM edges, range(8) k(k) JOIN nodes ON place = {sql_h32("'1'", "'fresh'", 'src', 'dst', 'k.k')} % size""",
)
def neg_unbatched(spark, sf):
    """Fresh uniform candidates for each edge: an explode and an equi-join on the drawn place."""
    e = graphs.user_event(spark, sf)
    nodes = train_sql.placed_nodes(e, "dst")
    size = nodes.groupBy("rel").agg(F.count(F.lit(1)).alias("size"))
    drawn = e.withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(7)))).join(F.broadcast(size), "rel").withColumn("place", (h32(1, "fresh", F.col("src"), F.col("dst"), F.col("slot")) % F.col("size")).cast("int"))
    return drawn.join(nodes, ["rel", "place"]).select("src", "dst", "slot", F.col("key").alias("cand"))


def _chunks_sql(chunk: int) -> str:
    h = sql_h32("'1'", "'chunk'", "src", "dst")
    return f"chunked AS (SELECT *, ((row_number() OVER (PARTITION BY rel ORDER BY {h}, src, dst) - 1) // {chunk})::INTEGER AS chunk_id FROM edges)"


def _negatives_sql(chunk: int, draws: int, side: str) -> str:
    h = sql_h32("'1'", "'uni'", f"'{side}'", "rel", "chunk_id", "slot")
    return f"""{_chunks_sql(chunk)},
    nodes AS (SELECT rel, key, row_number() OVER (PARTITION BY rel ORDER BY key) - 1 AS place, count(*) OVER (PARTITION BY rel) AS size FROM (SELECT DISTINCT rel, {side} AS key FROM edges)),
    slots AS (SELECT rel, chunk_id, s.slot FROM (SELECT DISTINCT rel, chunk_id FROM chunked), range({draws}) s(slot)),
    uni AS (SELECT s.rel, s.chunk_id, n.key AS cand FROM (SELECT *, {h} AS h FROM slots) s JOIN nodes n ON n.rel = s.rel AND n.place = s.h % n.size),
    pool AS (SELECT rel, chunk_id, cand, count(*)::BIGINT AS times FROM (SELECT rel, chunk_id, {side} AS cand FROM chunked UNION ALL SELECT rel, chunk_id, cand FROM uni) GROUP BY ALL),
    neg AS (SELECT c.rel, c.chunk_id, src, dst, weight, cand, times FROM chunked c JOIN pool p ON p.rel = c.rel AND p.chunk_id = c.chunk_id WHERE cand <> {side})"""


@query("neg_batched_counts", f"WITH {USER_EVENT}, {_negatives_sql(50, 50, 'dst')} SELECT chunk_id, count(*)::BIGINT AS n, sum(times)::BIGINT AS with_repeats FROM neg GROUP BY 1")
def neg_batched_counts(spark, sf):
    return train_sql.negatives(graphs.user_event(spark, sf), 50, 50).groupBy("chunk_id").agg(F.count(F.lit(1)).alias("n"), F.sum("times").alias("with_repeats"))


# -- scores of the customers' nations


def _nation_edges(spark, sf):
    return table(spark, sf, "customer").select(F.col("c_custkey").cast("string").alias("src"), F.col("c_nationkey").cast("string").alias("dst"))


def _score(spark, sf, op: str, sim: str):
    e = _nation_edges(spark, sf)
    size = D * D if op == "linear" else D
    theta = None if op == "identity" else V.initial(size, SPREAD, 1, "theta", F.lit(op))
    s, d = V.initial(D, SPREAD, 1, "c", F.col("src")), V.initial(D, SPREAD, 1, "n", F.col("dst"))
    v = e.select("src", "dst", s.alias("s"), d.alias("d"), *([] if theta is None else [theta.alias("theta")]))
    return v.select("src", "dst", F.round(V.similarity(sim, F.col("s"), V.apply_op(op, F.col("d"), F.col("theta") if theta is not None else None, D)), 9).alias("score"))


def _score_sql(op: str, sim: str) -> str:
    size = D * D if op == "linear" else D
    h = D // 2
    g = {
        "identity": "d",
        "translation": "list_transform(list_zip(d, t), lambda z: z[1] + z[2])",
        "diagonal": "list_transform(list_zip(d, t), lambda z: z[1] * z[2])",
        "linear": f"list_transform(range({D}), lambda i: {sql_dot(f't[i * {D} + 1:i * {D} + {D}]', 'd')})",
        "complex_diagonal": f"list_concat(list_transform(range({h}), lambda i: d[i + 1] * t[i + 1] - d[i + {h} + 1] * t[i + {h} + 1]), list_transform(range({h}), lambda i: d[i + 1] * t[i + {h} + 1] + d[i + {h} + 1] * t[i + 1]))",
    }[op]
    score = sql_dot("s", "y")
    if sim == "cos":
        score = f"({score}) / (sqrt({sql_dot('s', 's')}) * sqrt({sql_dot('y', 'y')}))"
    return f"""WITH v AS (SELECT c_custkey::VARCHAR AS src, c_nationkey::VARCHAR AS dst, {sql_vec(D, SPREAD, 1, "'c'", 'c_custkey')} AS s, {sql_vec(D, SPREAD, 1, "'n'", 'c_nationkey')} AS d, {sql_vec(size, SPREAD, 1, "'theta'", f"'{op}'")} AS t FROM customer),
    y AS (SELECT src, dst, s, {g} AS y FROM v) SELECT src, dst, round({score}, 9) AS score FROM y"""


for _name, _op, _sim in (
    ("score_identity_dot", "identity", "dot"), ("score_identity_cos", "identity", "cos"), ("score_translation_cos", "translation", "cos"),
    ("score_diagonal_dot", "diagonal", "dot"), ("score_linear_dot", "linear", "dot"), ("score_complex", "complex_diagonal", "complex_dot"),
):
    query(_name, _score_sql(_op, _sim))(lambda spark, sf, o=_op, s=_sim: _score(spark, sf, o, s))


@query(
    "score_hole",
    f"""WITH v AS (SELECT c_custkey::VARCHAR AS src, c_nationkey::VARCHAR AS dst, {sql_vec(8, SPREAD, 1, "'c'", 'c_custkey')} AS s, {sql_vec(8, SPREAD, 1, "'n'", 'c_nationkey')} AS d, {sql_vec(8, SPREAD, 1, "'theta'", "'hole'")} AS t FROM customer)
    SELECT src, dst, round(list_sum(list_transform(range(8), lambda k: s[k + 1] * list_sum(list_transform(range(8), lambda i: t[i + 1] * d[(i + k) % 8 + 1])))), 6) AS score FROM v""",
)
def score_hole(spark, sf):
    """Circular correlation by FFT in Arrow (checked against its definition in tests)."""
    from pyspark.sql.functions import pandas_udf

    def score(s: pd.Series, d: pd.Series, t: pd.Series) -> pd.Series:
        a, b, c = (np.stack(x.to_numpy()) for x in (s, d, t))
        return pd.Series((a * relops._correlate(c, b)).sum(1).round(6))

    score = pandas_udf(score, "double")
    e = _nation_edges(spark, sf)
    return e.select("src", "dst", score(V.initial(8, SPREAD, 1, "c", F.col("src")), V.initial(8, SPREAD, 1, "n", F.col("dst")), V.initial(8, SPREAD, 1, "theta", F.lit("hole"))).alias("score"))


@query(
    "score_featurized",
    f"""WITH bags AS (SELECT p_partkey AS key, unnest(['brand:' || p_brand, 'type:' || p_type, 'size:' || p_size]) AS feature FROM part),
    v AS (SELECT key, {sql_vec(D, SPREAD, 1, "'f'", 'feature')} AS vec FROM bags), e AS (SELECT key, unnest(range({D})) AS k, unnest(vec) AS x FROM v), m AS (SELECT key, k, avg(x) AS x FROM e GROUP BY 1, 2)
    SELECT key, round(sum(x * x), 9) AS score FROM m GROUP BY 1""",
)
def score_featurized(spark, sf):
    bags = features.part_bags(table(spark, sf, "part"))
    known = bags.select("feature").distinct().select("feature", V.initial(D, SPREAD, 1, "f", F.col("feature")).alias("vec"))
    return features.featurize(bags, known).select("key", F.round(V.dot(F.col("vec"), F.col("vec")), 9).alias("score"))


# -- losses and one step, on the user-event graph


def _start(e):
    return e.select(F.col("src").alias("key")).union(e.select("dst")).distinct().select("key", V.initial(D, SPREAD, 1, "init", F.col("key")).alias("vec"), F.lit(0.0).alias("acc"))


def _terms_sql(loss: str) -> str:
    key = "rel, src, dst"
    base = f"""WITH {USER_EVENT}, {_negatives_sql(50, 20, 'dst')},
    vec AS (SELECT key, {sql_vec(D, SPREAD, 1, "'init'", 'key')} AS v FROM (SELECT DISTINCT src AS key FROM edges UNION SELECT DISTINCT dst FROM edges)),
    sc AS (SELECT n.*, {sql_dot('a.v', 'b.v')} AS pos, {sql_dot('a.v', 'c.v')} AS neg FROM neg n JOIN vec a ON a.key = n.src JOIN vec b ON b.key = n.dst JOIN vec c ON c.key = n.cand)"""
    if loss == "ranking":
        term = "sum(weight * times * greatest(0, 0.1 - pos + neg))"
        return f"{base} SELECT {key}, round({term}, 6) AS loss FROM sc GROUP BY ALL"
    if loss == "logistic":
        soft = lambda x: f"(greatest({x}, 0) + ln(1 + exp(-abs({x}))))"
        return f"{base} SELECT {key}, round(any_value(weight) * {soft('-any_value(pos)')} + any_value(weight) * sum(times * {soft('neg')}) / sum(times), 6) AS loss FROM sc GROUP BY ALL"
    return f"{base} SELECT {key}, round(any_value(weight) * ln((exp(any_value(pos)) + sum(times * exp(neg))) / exp(any_value(pos))), 6) AS loss FROM sc GROUP BY ALL"


def _loss(spark, sf, loss):
    e = graphs.user_event(spark, sf)
    terms = train_sql.loss_terms(train_sql.scores(train_sql.negatives(e, 20, 50), _start(e)), loss)
    return terms.groupBy("rel", "src", "dst").agg(F.round(F.sum("loss"), 6).alias("loss"))


for _l in ("ranking", "logistic", "softmax"):
    query(f"loss_{_l}", _terms_sql(_l))(lambda spark, sf, x=_l: _loss(spark, sf, x))


def _step_sql(optimizer: str) -> str:
    """One ranking step, destinations corrupted, as SQL."""
    rate = "0.1" if optimizer == "sgd" else "0.1 / (sqrt(acc) + 1e-10)"
    return f"""WITH {USER_EVENT}, {_negatives_sql(50, 20, 'dst')},
    vec AS (SELECT key, {sql_vec(D, SPREAD, 1, "'init'", 'key')} AS v FROM (SELECT DISTINCT src AS key FROM edges UNION SELECT DISTINCT dst FROM edges)),
    sc AS (SELECT n.*, a.v AS sv, b.v AS dv, c.v AS cv, {sql_dot('a.v', 'b.v')} AS pos, {sql_dot('a.v', 'c.v')} AS neg FROM neg n JOIN vec a ON a.key = n.src JOIN vec b ON b.key = n.dst JOIN vec c ON c.key = n.cand),
    t AS (SELECT *, CASE WHEN 0.1 - pos + neg > 0 THEN (weight * times)::DOUBLE ELSE 0 END AS g FROM sc),
    each AS (SELECT src AS key, list_transform(list_zip(cv, dv), lambda z: g * (z[1] - z[2])) AS gv FROM t UNION ALL SELECT dst, list_transform(sv, lambda x: -g * x) FROM t UNION ALL SELECT cand, list_transform(sv, lambda x: g * x) FROM t),
    flat AS (SELECT key, unnest(range({D})) AS k, unnest(gv) AS x FROM each), summed AS (SELECT key, k, sum(x) AS x FROM flat GROUP BY 1, 2),
    acc AS (SELECT key, sum(x * x) AS acc FROM summed GROUP BY 1),
    old AS (SELECT key, unnest(range({D})) AS k, unnest(v) AS v FROM vec)
    SELECT o.key, o.k::INTEGER AS k, round(o.v - coalesce(s.x * {rate}, 0), 6) AS x FROM old o LEFT JOIN summed s ON s.key = o.key AND s.k = o.k LEFT JOIN acc a ON a.key = o.key"""


def _step(spark, sf, optimizer):
    e = graphs.user_event(spark, sf)
    terms = train_sql.loss_terms(train_sql.scores(train_sql.negatives(e, 20, 50), _start(e)), "ranking")
    new = train_sql.update(_start(e), train_sql.gradients(terms), 0.1, optimizer)
    return new.select("key", F.posexplode("vec").alias("k", "x")).select("key", "k", F.round("x", 6).alias("x"))


for _o in ("sgd", "adagrad_row"):
    query(f"step_{_o}", _step_sql(_o))(lambda spark, sf, x=_o: _step(spark, sf, x))


@query(
    "step_relation",
    f"""WITH v AS (SELECT {sql_vec(D, SPREAD, 1, "'c'", 'c_custkey')} AS s, {sql_vec(D, SPREAD, 1, "'n'", 'c_nationkey')} AS d FROM customer),
    e AS (SELECT i.i, j.j, s[i.i + 1] AS a, d[j.j + 1] AS b FROM v, range({D}) i(i), range({D}) j(j))
    SELECT 'linear' AS op, (i * {D} + j)::INTEGER AS k, round(sum(a * b), 4) AS grad FROM e GROUP BY ALL
    UNION ALL SELECT 'diagonal', i::INTEGER, round(sum(a * b), 4) FROM e WHERE i = j GROUP BY ALL UNION ALL SELECT 'translation', i::INTEGER, round(sum(a), 4) FROM e WHERE i = j GROUP BY ALL""",
)
def step_relation(spark, sf):
    """Gradients of a relation's parameters under a dot product, by the kernel's own backward pass, summed over batches."""
    import pyarrow as pa

    e = _nation_edges(spark, sf).select(V.initial(D, SPREAD, 1, "c", F.col("src")).alias("s"), V.initial(D, SPREAD, 1, "n", F.col("dst")).alias("d"))

    def run(batches):
        for b in batches:
            s, d = (b.column(c).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, D) for c in ("s", "d"))
            for op in ("linear", "diagonal", "translation"):
                grad = relops.backward(op, d, relops.parameters(op, D).astype(np.float64), s)[1].ravel()
                yield pa.RecordBatch.from_pydict({"op": [op] * len(grad), "k": pa.array(np.arange(len(grad)), pa.int32()), "grad": grad})

    return e.mapInArrow(run, "op string, k int, grad double").groupBy("op", "k").agg(F.round(F.sum("grad"), 4).alias("grad"))


# -- ranking


RANKS = f"""{KNN}, test AS (SELECT q, id, s FROM best WHERE place <= 5),
    better AS (SELECT t.q, t.id, count(*) FILTER (WHERE p.s > t.s) AS better, count(*) FILTER (WHERE p.s > t.s AND NOT EXISTS (SELECT 1 FROM test k WHERE k.q = p.q AND k.id = p.id)) AS better_filtered FROM test t JOIN pairs p ON p.q = t.q GROUP BY 1, 2)"""


def _knn_ranks(spark, sf):
    """Ranks of each vector's five nearest under the given vectors, among all others; raw and filtered."""
    from ..operators.nearest import nearest_exact, ranks_exact

    vec = table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
    return ranks_exact(stored(nearest_exact(vec, vec, 5, drop_self=True), "nearest"), vec, 5)


@query("rank_raw", f"WITH {RANKS} SELECT q, id AS true, better::BIGINT AS better, (1 + better)::BIGINT AS rank FROM better")
def rank_raw(spark, sf):
    return _knn_ranks(spark, sf).select("q", "true", "better", (F.col("better") + 1).alias("rank"))


@query("rank_filtered", f"WITH {RANKS} SELECT q, id AS true, (1 + better_filtered)::BIGINT AS rank FROM better")
def rank_filtered(spark, sf):
    return _knn_ranks(spark, sf).select("q", "true", (F.col("better_filtered") + 1).alias("rank"))


@query("knn_exact_mrr", f"WITH {RANKS} SELECT round(avg(1.0 / (1 + better)), 9) AS mrr_raw, round(avg(1.0 / (1 + better_filtered)), 9) AS mrr_filtered FROM better")
def knn_exact_mrr(spark, sf):
    return _knn_ranks(spark, sf).agg(F.round(F.avg(1 / (1 + F.col("better"))), 9).alias("mrr_raw"), F.round(F.avg(1 / (1 + F.col("better_filtered"))), 9).alias("mrr_filtered"))


@query("mrr_mr_hits", f"WITH {RANKS} SELECT count(*)::BIGINT AS n, round(avg(1.0 / (1 + better)), 9) AS mrr, round(avg(1.0 + better), 9) AS mr, round(avg((better < 1)::INTEGER), 9) AS hits1, round(avg((better < 10)::INTEGER), 9) AS hits10 FROM better")
def mrr_mr_hits(spark, sf):
    m = evaluate.metrics(_knn_ranks(spark, sf).withColumn("ties", F.lit(0)))
    return m.select("n", *[F.round(c, 9).alias(c) for c in ("mrr", "mr", "hits1", "hits10")])


@query("metrics_rollup", f"WITH {RANKS}, r AS (SELECT (q % 3)::INTEGER AS grp, (id % 2)::INTEGER AS side, better FROM better) SELECT grp, side, count(*)::BIGINT AS n, round(avg(1.0 / (1 + better)), 9) AS mrr FROM r GROUP BY ROLLUP (grp, side)")
def metrics_rollup(spark, sf):
    r = _knn_ranks(spark, sf).select((F.col("q") % 3).cast("int").alias("grp"), (F.col("true") % 2).cast("int").alias("side"), "better").withColumn("ties", F.lit(0))
    return evaluate.metrics(r, ("grp", "side")).select("grp", "side", "n", F.round("mrr", 9).alias("mrr"))


# -- the evaluator itself on given vectors: every vector's five nearest are the edges, all nodes the candidates


def _given(spark, sf, **changes):
    e = graphs.knn(spark, sf)
    vec = table(spark, sf, "embeddings").select(F.lit(0).alias("etype"), F.col("vec_id").cast("string").alias("key"), F.col("embedding").alias("vec"))
    dim = len(table(spark, sf, "embeddings").select("embedding").first()[0])
    spec = preset("identity", [EntityType("node")], [("near", "node", "node")], dim=dim, **changes)
    return e, train_block.from_vectors(e, spec, vec, 3)


def _given_sql(side: str, filtered: bool) -> str:
    kept = "src" if side == "dst" else "dst"
    gone = "AND NOT EXISTS (SELECT 1 FROM e f WHERE f.src = t.src AND f.dst = c.key)" if side == "dst" else "AND NOT EXISTS (SELECT 1 FROM e f WHERE f.dst = t.dst AND f.src = c.key)"
    return f"""SELECT '{side}' AS side, t.src, t.dst, count(*) FILTER (WHERE p.s > t.s AND abs(p.s - t.s) > 1e-6 * greatest(1, abs(t.s)))::BIGINT AS better, count(*) FILTER (WHERE abs(p.s - t.s) <= 1e-6 * greatest(1, abs(t.s)))::BIGINT AS ties
    FROM t CROSS JOIN (SELECT DISTINCT {side} AS key FROM e) c JOIN every p ON p.a = t.{kept} AND p.b = c.key WHERE c.key <> t.{side} {gone if filtered else ''} GROUP BY ALL"""


def _given_ctes() -> str:
    return f"""WITH {KNN}, e AS (SELECT q::VARCHAR AS src, id::VARCHAR AS dst FROM best WHERE place <= 5),
    every AS (SELECT a.vec_id::VARCHAR AS a, b.vec_id::VARCHAR AS b, list_inner_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) AS s FROM embeddings a, embeddings b),
    t AS (SELECT e.src, e.dst, p.s FROM e JOIN every p ON p.a = e.src AND p.b = e.dst)"""


def _given_ranks(spark, sf, **kind):
    e, model = _given(spark, sf)
    return evaluate.rank_edges(model, e, e, mode="all", exact=True, **kind).select("side", "src", "dst", "better", "ties")


query("rank_edges_raw", f"{_given_ctes()} {_given_sql('dst', False)} UNION ALL {_given_sql('src', False)}")(lambda spark, sf: _given_ranks(spark, sf))
query("rank_edges_filtered", f"{_given_ctes()} {_given_sql('dst', True)} UNION ALL {_given_sql('src', True)}")(lambda spark, sf: _given_ranks(spark, sf, filtered=True))
query("rank_all_blocks", f"{_given_ctes()} {_given_sql('dst', False)} UNION ALL {_given_sql('src', False)}")(lambda spark, sf: _given_ranks(spark, sf, pool_bytes=0))


@query(
    "score_given_edges",
    f"""WITH {KNN}, v AS (SELECT vec_id AS id, embedding::DOUBLE[] AS x FROM embeddings), y AS (SELECT id, list_transform(x, lambda z, i: z + i::DOUBLE / 128) AS y FROM v)
    SELECT q::VARCHAR AS src, b.id::VARCHAR AS dst, round({sql_dot('v.x', 'y.y')} / sqrt({sql_dot('v.x', 'v.x')}) / sqrt({sql_dot('y.y', 'y.y')}), 9) AS score FROM best b JOIN v ON v.id = q JOIN y ON y.id = b.id WHERE place <= 5""",
)
def score_given_edges(spark, sf):
    """Edges scored by a model with given vectors, a given translation and the cosine."""
    e = graphs.knn(spark, sf)
    vec = table(spark, sf, "embeddings").select(F.lit(0).alias("etype"), F.col("vec_id").cast("string").alias("key"), F.col("embedding").alias("vec"))
    dim = len(table(spark, sf, "embeddings").select("embedding").first()[0])
    model = train_block.from_vectors(e, preset("transe", [EntityType("node")], [("near", "node", "node")], dim=dim), vec, 2)
    model.params[0].theta["both", "rhs"] = (np.arange(1, dim + 1) / 128).astype(np.float32)
    return evaluate.score_edges(model, e).select("src", "dst", F.round("score", 9).alias("score"))


def _split_word(spark, sf):
    e = partition.split_edges(graphs.word_next(spark, sf), dict(TWO))
    return e.where("split = 'train'"), e.where("split = 'test'")


def _control_sql(mode: str, kind: str) -> str:
    pos, neg = (sql_h32("'1'", "'rnd'", "src", "dst"), sql_h32("'1'", "'rnd'", "src", "key")) if kind == "random" else ("coalesce(o.deg, 0)", "coalesce(k.deg, 0)")
    cand = _cand_sql("dst", 200, mode, "train")
    join = "" if kind == "random" else "LEFT JOIN deg o ON o.key = t.dst LEFT JOIN deg k ON k.key = c.key"
    own = "t.src, t.dst, c.key, c.times"
    p = pos.replace("src", "t.src").replace("dst", "t.dst") if kind == "random" else pos
    n = neg.replace("src", "t.src").replace("(key)", "(c.key)") if kind == "random" else neg
    return f"""WITH {word_next_ctes()}, e AS (SELECT *, {_split_sql(*TWO)} AS split FROM edges), train AS (SELECT * FROM e WHERE split = 'train'), test AS (SELECT * FROM e WHERE split = 'test'),
    deg AS (SELECT dst AS key, count(*) AS deg FROM train GROUP BY 1), cand AS (SELECT key, count(*)::BIGINT AS times FROM ({cand}) GROUP BY 1),
    x AS (SELECT {own}, {p} AS pos, {n} AS neg FROM test t CROSS JOIN cand c {join} WHERE c.key <> t.dst),
    r AS (SELECT src, dst, sum(CASE WHEN neg > pos THEN times ELSE 0 END) AS better, sum(CASE WHEN neg = pos THEN times ELSE 0 END) AS ties FROM x GROUP BY 1, 2)
    SELECT count(*)::BIGINT AS n, round(avg(1.0 / (1 + better + ties / 2.0)), 6) AS mrr FROM r"""


def _control(spark, sf, mode, fn):
    train, test = _split_word(spark, sf)
    m = evaluate.metrics(fn(test, train, 200, mode))
    return m.select("n", F.round("mrr", 6).alias("mrr"))


for _mode in ("data", "uniform"):
    query(f"random_control_{_mode}", _control_sql(_mode, "random"))(lambda spark, sf, m=_mode: _control(spark, sf, m, evaluate.random_ranks))
    query(f"degree_scorer_{_mode}", _control_sql(_mode, "degree"))(lambda spark, sf, m=_mode: _control(spark, sf, m, evaluate.degree_ranks))


@query(
    "micro_macro_f1",
    """WITH r AS (SELECT 'quality' AS label, quality AS truth, (doc_id % 3 > 0)::INTEGER AS pred FROM labels UNION ALL SELECT 'toxic', toxic, (doc_id % 4 = 0)::INTEGER FROM labels),
    c AS (SELECT label, sum(pred * truth) AS tp, sum(pred * (1 - truth)) AS fp, sum((1 - pred) * truth) AS fn FROM r GROUP BY 1)
    SELECT round(2.0 * sum(tp) / (2.0 * sum(tp) + sum(fp) + sum(fn)), 9)::DOUBLE AS micro_f1, round(avg(2.0 * tp / (2.0 * tp + fp + fn)), 9)::DOUBLE AS macro_f1 FROM c""",
)
def micro_macro_f1(spark, sf):
    t = table(spark, sf, "labels")
    r = t.select(F.lit("quality").alias("label"), F.col("quality").alias("truth"), (F.col("doc_id") % 3 > 0).cast("int").alias("pred")).union(t.select(F.lit("toxic"), "toxic", (F.col("doc_id") % 4 == 0).cast("int")))
    return downstream.f1_scores(r).select(F.round("micro_f1", 9).alias("micro_f1"), F.round("macro_f1", 9).alias("macro_f1"))


# -- baselines


NEAR = """near AS (SELECT key, next, row_number() OVER (PARTITION BY key ORDER BY next) - 1 AS n, count(*) OVER (PARTITION BY key) AS degree FROM (SELECT src AS key, dst AS next FROM edges UNION SELECT dst, src FROM edges))"""


@query(
    "walk_steps",
    f"""WITH RECURSIVE {word_next_ctes()}, {NEAR}, walk AS (SELECT DISTINCT key || '#0' AS walk, 0 AS pos, key FROM near
      UNION ALL SELECT w.walk, w.pos + 1, n.next FROM walk w JOIN near n ON n.key = w.key AND n.n = {sql_h32("'1'", "'walk'", 'w.walk', 'w.pos + 1')} % n.degree WHERE w.pos < 3)
    SELECT walk, pos::INTEGER AS pos, key FROM walk""",
)
def walk_steps(spark, sf):
    return walks.random_walks(graphs.word_next(spark, sf), walks=1, length=4)


@query(
    "skipgram_pairs",
    "WITH w AS (SELECT user_id::VARCHAR AS walk, row_number() OVER (PARTITION BY user_id ORDER BY event_id)::INTEGER AS pos, event_type AS key FROM events) SELECT 'near' AS rel, a.key AS src, b.key AS dst, count(*)::BIGINT AS weight FROM w a JOIN w b ON a.walk = b.walk AND b.pos > a.pos AND b.pos <= a.pos + 3 WHERE a.key <> b.key GROUP BY ALL",
)
def skipgram_pairs(spark, sf):
    from pyspark.sql import Window

    pos = F.row_number().over(Window.partitionBy("user_id").orderBy("event_id"))
    w = table(spark, sf, "events").select(F.col("user_id").cast("string").alias("walk"), pos.alias("pos"), F.col("event_type").alias("key"))
    return walks.skipgram_pairs(w, 3)


_PAIRS = "und AS (SELECT least(src, dst) AS a, greatest(src, dst) AS b, sum(weight)::DOUBLE AS weight FROM edges WHERE src <> dst GROUP BY 1, 2), sym AS (SELECT a AS key, b AS other, weight FROM und UNION ALL SELECT b, a, weight FROM und)"
_MATCH = f"""best AS (SELECT key, other FROM (SELECT key, other, row_number() OVER (PARTITION BY key ORDER BY weight DESC, {sql_h32("'0'", "'match'", 'least(key, other)', 'greatest(key, other)')} DESC, other DESC) AS n FROM sym) WHERE n = 1)"""


_BEST = f"""best AS MATERIALIZED (SELECT key, arg_max(other, (weight, h, other)) AS other FROM (SELECT *, {sql_h32("'0'", "'match'", 'least(key, other)', 'greatest(key, other)')} AS h FROM sym) GROUP BY key)"""


@query("coarsen_level", f"WITH {word_next_ctes().replace('edges AS (', 'edges AS MATERIALIZED (')}, {_PAIRS.replace('und AS (', 'und AS MATERIALIZED (')}, {_BEST} SELECT x.key, CASE WHEN y.key IS NULL THEN x.key ELSE least(x.key, x.other) END AS super FROM best x LEFT JOIN best y ON y.key = x.other AND y.other = x.key")
def coarsen_level(spark, sf):
    return coarsen.matching(coarsen.undirected(graphs.word_next(spark, sf)), 0)


@query(
    "refine_average",
    f"""WITH {USER_EVENT}, {_PAIRS}, vec AS (SELECT key, {sql_vec(D, SPREAD, 1, "'init'", 'key')} AS v FROM (SELECT DISTINCT key FROM sym)), f AS (SELECT key, unnest(range({D})) AS k, unnest(v) AS x FROM vec),
    m AS (SELECT s.key, f.k, sum(f.x * s.weight) / sum(s.weight) AS x FROM sym s JOIN f ON f.key = s.other GROUP BY 1, 2)
    SELECT f.key, f.k::INTEGER AS k, round(0.5 * f.x + 0.5 * m.x, 9) AS x FROM f JOIN m ON m.key = f.key AND m.k = f.k""",
)
def refine_average(spark, sf):
    e = graphs.user_event(spark, sf)
    return coarsen.refine(e, _start(e).select("key", "vec")).select("key", F.posexplode("vec").alias("k", "x")).select("key", "k", F.round("x", 9).alias("x"))


# -- experiments: trained models, so rows only


@query("train_block_metrics")
def train_block_metrics(spark, sf):
    return experiments.flagship(spark, sf)


@query("train_partition_sweep")
def train_partition_sweep(spark, sf):
    return experiments.partition_sweep(spark, graphs.word_next(spark, sf), epochs=1)


@query("train_parallel_sweep")
def train_parallel_sweep(spark, sf):
    return experiments.parallel_sweep(spark, graphs.word_next(spark, sf), machines=(1, 2, 4, 8), epochs=1)


@query("bench_negatives")
def bench_negatives(spark, sf):
    """The trainer's kernel on orders placed by customers."""
    return experiments.negatives_speed(spark, (10, 50, 100, 200), given=graphs.placed(spark, sf))


@query("classify_docs")
def classify_docs(spark, sf):
    return experiments.classify_documents(spark, sf)


@query(
    "presets",
    """SELECT name, op, sim, loss, reciprocal, parameters::BIGINT AS parameters FROM (VALUES ('rescal', 'linear', 'dot', 'softmax', false, 256), ('transe', 'translation', 'cos', 'ranking', false, 16), ('distmult', 'diagonal', 'dot', 'softmax', false, 16),
    ('complex', 'complex_diagonal', 'complex_dot', 'softmax', false, 16), ('hole', 'circular_correlation', 'dot', 'logistic', false, 16), ('starspace', 'identity', 'cos', 'ranking', false, 0), ('complex_n3_reciprocal', 'complex_diagonal', 'complex_dot', 'softmax', true, 64), ('identity', 'identity', 'dot', 'softmax', false, 0)) t(name, op, sim, loss, reciprocal, parameters)""",
)
def presets(spark, sf):
    """What each preset makes of a relation at d = 16, and the parameters that a trained relation then holds."""
    rows = []
    for name in PRESETS:
        spec = preset(name, [EntityType("n")], [("r", "n", "n")], dim=16)
        rel = spec.relations[0]
        held = kernels.Params.start(rel, spec.dim)
        rows.append((name, rel.rhs_op, spec.sim, spec.loss, rel.reciprocal, sum(t.size for t in held.theta.values())))
    return spark.createDataFrame(rows, "name string, op string, sim string, loss string, reciprocal boolean, parameters long")


@query("speedup", "SELECT machines, seconds, speedup, efficiency FROM (VALUES (1::INTEGER, 30.0::DOUBLE, 1.0::DOUBLE, 1.0::DOUBLE), (2, 23.0, 30.0::DOUBLE / 23.0, 30.0::DOUBLE / 23.0 / 2), (4, 13.0, 30.0::DOUBLE / 13.0, 30.0::DOUBLE / 13.0 / 4), (8, 7.7, 30.0::DOUBLE / 7.7::DOUBLE, 30.0::DOUBLE / 7.7::DOUBLE / 8)) t(machines, seconds, speedup, efficiency)")
def speedup(spark, sf):
    return spark.createDataFrame([tuple(r.values()) for r in costs.speedup({1: 30.0, 2: 23.0, 4: 13.0, 8: 7.7})], "machines int, seconds double, speedup double, efficiency double")

"""The trainer's own reading and loads against SQL, and the experiments on graphs that have a signal."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.hashing import sql_h32
from ..operators import evaluate, experiments, partition, schedule, train_block
from ..operators.nearest import nearest_by_relation
from ..operators.spec import EntityType, preset
from ..session import stored
from ..sources import graphs
from ..sources.tables import table
from ..streaming import ingest
from .base import kb_ctes, query, sql_dot, word_next_ctes
from .graph_queries import KNN

_kept: dict = {}


def _graph(spark, sf, name: str):
    """A graph stored once per application: several experiments read it."""
    key = (spark.sparkContext.applicationId, sf, name)
    if key not in _kept:
        for old in [k for k in _kept if k[0] != key[0]]:
            del _kept[old]
        _kept[key] = stored(getattr(graphs, name)(spark, sf), f"graph-{name}")
    return _kept[key]


def _part(key: str, p: int) -> str:
    return f"({sql_h32("'1'", "'part'", '0', key)} % {p})::INTEGER"


# -- what the trainer reads and loads


@query("trained_loads", " UNION ALL ".join(f"(WITH {word_next_ctes()} SELECT {p}::INTEGER AS parts, 1::INTEGER AS jobs, {1 + p * (p - 1) // 2}::BIGINT AS loads, {1 + p * (p - 1) // 2}::BIGINT AS stores, count(*)::BIGINT AS edges FROM edges)" for p in (2, 4, 8)))
def trained_loads(spark, sf):
    """Parts that one machine really loaded and stored in an epoch, and edges that it trained, from the trainer's log."""
    e = _graph(spark, sf, "word_next")

    def run(p):
        log = train_block.fit(train_block.prepare(e, experiments.one_type_spec(e, dim=8), p), epochs=1).log[0]
        return p, log["rounds"], int(log["loads"]), int(log["stores"]), int(log["edges"])

    out = experiments.side_by_side(spark, (2, 4, 8), run)
    return spark.createDataFrame(out, "parts int, jobs int, loads long, stores long, edges long")


@query("trained_pieces", f"WITH {word_next_ctes()} SELECT {_part('src', 2)} AS p_src, {_part('dst', 2)} AS p_dst, ({sql_h32("'1'", "'mix'", 'rel', 'src', 'dst')} % 3)::INTEGER AS piece, count(*)::BIGINT AS n FROM edges GROUP BY ALL")
def trained_pieces(spark, sf):
    """The edges that a job of each sub-epoch reads, by bucket."""
    e = _graph(spark, sf, "word_next")
    prep = train_block.prepare(e, experiments.one_type_spec(e, dim=8), 2, portable=True)
    plan = [schedule.units_in_order(schedule.inside_out(2))]
    out = None
    for piece in range(3):
        rows = train_block.job_rows(prep, plan, (piece, 3)).where("p_src >= 0").select("p_src", "p_dst", F.lit(piece).alias("piece"))
        out = rows if out is None else out.union(rows)
    return out.groupBy("p_src", "p_dst", "piece").agg(F.count(F.lit(1)).alias("n"))


@query(
    "schedule_covers",
    " UNION ALL ".join(
        f"SELECT '{policy}' AS policy, {p}::INTEGER AS parts, {m}::INTEGER AS machines, {e}::INTEGER AS epoch, {p * (p + 1) // 2}::BIGINT AS units, {p * (p + 1) // 2}::BIGINT AS different, 0::BIGINT AS clashes, 0::BIGINT AS crowded, 0::BIGINT AS unaligned"
        for policy in ("affinity", "tournament") for p, m in ((4, 2), (8, 4), (16, 8), (8, 2)) for e in (0, 1)
    ),
)
def schedule_covers(spark, sf):
    """Chains of all rounds: every unit once, no part in two chains of a round, no round above its machines, and in
    a first epoch no later chain on two parts that nobody has trained."""
    rows = []
    for policy in ("affinity", "tournament"):
        for p, m in ((4, 2), (8, 4), (16, 8), (8, 2)):
            for e in (0, 1):
                known: set[int] = set() if e == 0 else set(range(p))
                for r, now in enumerate(schedule.chains(p, m, policy, e == 0)):
                    for c, chain in enumerate(now):
                        new = bool(known) and not known & {x for u in chain for x in u}
                        rows += [(policy, p, m, e, r, c, a, b, new) for a, b in chain]
                    known |= {x for chain in now for u in chain for x in u}
    df = spark.createDataFrame(rows, "policy string, parts int, machines int, epoch int, round int, chain int, a int, b int, unaligned boolean")
    by = ["policy", "parts", "machines", "epoch"]
    held = df.select(*by, "round", "chain", F.explode(F.array("a", "b")).alias("part")).groupBy(*by, "round", "part").agg(F.count_distinct("chain").alias("n"))
    clashes = held.groupBy(*by).agg(F.count_if(F.col("n") > 1).alias("clashes"))
    crowded = df.groupBy(*by, "round").agg(F.count_distinct("chain").alias("n")).groupBy(*by).agg(F.count_if(F.col("n") > F.col("machines")).alias("crowded"))
    units = df.groupBy(*by).agg(F.count(F.lit(1)).alias("units"), F.count_distinct("a", "b").alias("different"), F.count_if("unaligned").alias("unaligned"))
    return units.join(clashes, by).join(crowded, by)


# -- draws inside types and parts


def _unrestricted_sql() -> str:
    h = sql_h32("'1'", "'cand'", "'src'", "rel", "key")
    n = lambda nodes: f"(SELECT key FROM (SELECT key, row_number() OVER (ORDER BY {h}, key) AS n FROM ({nodes})) WHERE n <= 500)"
    left, every = "SELECT DISTINCT rel, src AS key FROM e", "SELECT DISTINCT rel, src AS key FROM e UNION SELECT DISTINCT rel, dst FROM e"
    share = lambda nodes: f"(SELECT avg((key IN (SELECT src FROM e))::INTEGER) FROM {n(nodes)})"
    return f"WITH {kb_ctes()}, e AS (SELECT * FROM edges WHERE rel = 'part_brand') SELECT round({share(left)}, 9)::DOUBLE AS restricted_right_type, round({share(every)}, 9)::DOUBLE AS unrestricted_right_type"


@query("neg_type_restricted", _unrestricted_sql())
def neg_type_restricted(spark, sf):
    """Share of drawn source candidates of the right type, when draws keep to the relation's type and when they don't."""
    e = _graph(spark, sf, "kb").where("rel = 'part_brand'")
    own = e.select("src").distinct().withColumnRenamed("src", "key")
    right = lambda drawn: drawn.join(own.withColumn("ok", F.lit(1.0)), "key", "left").agg(F.round(F.avg(F.coalesce("ok", F.lit(0.0))), 9).alias("x")).first()["x"]
    shares = (right(evaluate.candidate_keys(e, "src", 500, "uniform", restrict_type=t)) for t in (True, False))
    return spark.createDataFrame([tuple(shares)], "restricted_right_type double, unrestricted_right_type double")


@query(
    "neg_part_restricted",
    f"""WITH {word_next_ctes()}, nodes AS (SELECT key, {_part('key', 4)} AS part FROM (SELECT src AS key FROM edges UNION SELECT dst FROM edges)),
    placed AS (SELECT *, row_number() OVER (PARTITION BY part ORDER BY {sql_h32("'1'", "'offset'", '0', 'key')}, key) - 1 AS place, count(*) OVER (PARTITION BY part) AS size FROM nodes)
    SELECT part, s.slot::INTEGER AS slot, key FROM placed, range(50) s(slot) WHERE place = {sql_h32("'1'", "'inside'", '0', 'part', 's.slot')} % size""",
)
def neg_part_restricted(spark, sf):
    """Candidates drawn for a bucket come from the part at hand."""
    e = _graph(spark, sf, "word_next")
    return partition.draw_inside(partition.partition_entities(e, experiments.one_type_spec(e, dim=8), 4, portable=True), 50).select("part", "slot", "key")


# -- nearest nodes under a relation, stream and static side, observed counts


@query(
    "nearest_under_relation",
    f"""WITH v AS (SELECT vec_id AS id, embedding::DOUBLE[] AS x FROM embeddings), y AS (SELECT id, list_transform(x, lambda z, i: z * (i % 3)::DOUBLE) AS y FROM v),
    n AS (SELECT id FROM (SELECT q AS id FROM (WITH {KNN} SELECT q FROM best WHERE place <= 5) UNION SELECT id FROM (WITH {KNN} SELECT id FROM best WHERE place <= 5))),
    s AS (SELECT v.id AS a, y.id AS b, {sql_dot('v.x', 'y.y')} AS score FROM v, y WHERE v.id IN (SELECT id FROM n) AND y.id IN (SELECT id FROM n))
    SELECT src, dst, place, round(score, 6) AS score FROM (SELECT a::VARCHAR AS src, b::VARCHAR AS dst, score, row_number() OVER (PARTITION BY a ORDER BY score DESC)::INTEGER AS place FROM s) WHERE place <= 3""",
)
def nearest_under_relation(spark, sf):
    """The best three destinations of every node, among all nodes, under a relation's diagonal operator."""
    import numpy as np

    e = graphs.knn(spark, sf)
    vec = table(spark, sf, "embeddings").select(F.lit(0).alias("etype"), F.col("vec_id").cast("string").alias("key"), F.col("embedding").alias("vec"))
    dim = len(table(spark, sf, "embeddings").select("embedding").first()[0])
    model = train_block.from_vectors(e, preset("distmult", [EntityType("node")], [("near", "node", "node")], dim=dim), vec, 2)
    model.params[0].theta["both", "rhs"] = (np.arange(1, dim + 1) % 3).astype(np.float32)
    keys = e.select(F.col("src").alias("key")).union(e.select("dst")).distinct()
    return nearest_by_relation(model, keys, "near", 3).select("src", "dst", "place", F.round("score", 6).alias("score"))


@query("stream_static_degrees", "SELECT e.event_id, e.event_type, d.n::BIGINT AS degree FROM events e JOIN (SELECT user_id, count(*) AS n FROM events WHERE event_type = 'view' GROUP BY 1) d ON d.user_id = e.user_id WHERE e.event_type <> 'view'")
def stream_static_degrees(spark, sf):
    """A stream of events joined with a static table of degrees."""
    from ..session import scratch

    root = scratch(spark, "stream-static")
    ev = table(spark, sf, "events").select("event_id", "ts", "user_id", "event_type")
    ev.repartition(3, "event_id").write.parquet(f"{root}/in")
    degree = ev.where("event_type = 'view'").groupBy("user_id").agg(F.count(F.lit(1)).alias("degree"))
    joined = ingest.with_static(ingest.event_stream(spark, f"{root}/in", ev.schema).where("event_type != 'view'"), degree, "user_id")
    joined.select("event_id", "event_type", "degree").writeStream.format("parquet").option("path", f"{root}/out").option("checkpointLocation", f"{root}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("event_id long, event_type string, degree long").parquet(f"{root}/out")


@query("observed_counts", "SELECT count(*)::BIGINT AS edges, count(*) FILTER (WHERE l_quantity > 25)::BIGINT AS large, max(l_quantity)::DOUBLE AS most FROM lineitem")
def observed_counts(spark, sf):
    """Counts observed while a job writes its edges, without a pass of their own."""
    from pyspark.sql import Observation

    from ..sources.tables import noop

    seen = Observation("edges")
    rows = table(spark, sf, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    noop(rows.observe(seen, F.count(F.lit(1)).alias("edges"), F.count_if(F.col("l_quantity") > 25).alias("large"), F.max(F.col("l_quantity").cast("double")).alias("most")))
    got = seen.get
    return spark.createDataFrame([(got["edges"], got["large"], got["most"])], "edges long, large long, most double")


# -- experiments: trained models, so rows only


@query("link_prediction_kb")
def link_prediction_kb(spark, sf):
    """Five operators on the knowledge base, ranks raw and filtered."""
    return experiments.link_prediction(spark, _graph(spark, sf, "kb"), ("transe", "distmult", "complex", "rescal", "hole"), epochs=2)


@query("baselines_word_next")
def baselines_word_next(spark, sf):
    return experiments.baselines(spark, _graph(spark, sf, "word_next"))


@query("learning_curve_words")
def learning_curve_words(spark, sf):
    return experiments.learning_curve(spark, _graph(spark, sf, "word_next"), epochs=3)


@query("candidate_contrast")
def candidate_contrast(spark, sf):
    return experiments.candidate_sampling(spark, _graph(spark, sf, "word_next"), epochs=2)


@query("alpha_ablation")
def alpha_ablation(spark, sf):
    return experiments.negative_ablation(spark, _graph(spark, sf, "word_next"), epochs=1)


@query("bucket_order_sweep")
def bucket_order_sweep(spark, sf):
    return experiments.bucket_order(spark, _graph(spark, sf, "word_next"), epochs=1)


@query("grid_words")
def grid_words(spark, sf):
    return experiments.grid_search(spark, _graph(spark, sf, "word_next"), {"lr": (0.03, 0.1), "uniform": (50, 100)}, epochs=1)


@query("replicates_complex")
def replicates_complex(spark, sf):
    return experiments.replicates(spark, _graph(spark, sf, "word_next"), epochs=1)


@query("large_graph_preparation", f"WITH {kb_ctes()}, nodes AS (SELECT key FROM (SELECT src AS key FROM edges UNION ALL SELECT dst FROM edges) GROUP BY 1 HAVING count(*) >= 5), rels AS (SELECT rel FROM edges GROUP BY 1 HAVING count(*) >= 5), kept AS (SELECT * FROM edges WHERE src IN (SELECT key FROM nodes) AND dst IN (SELECT key FROM nodes) AND rel IN (SELECT rel FROM rels)), s AS (SELECT rel, {sql_h32("'1'", "'split'", 'rel', 'src', 'dst')} / 4294967296.0::DOUBLE AS h FROM kept) SELECT CASE WHEN h < 0.9 THEN 'train' WHEN h < 0.9 + 0.05 THEN 'valid' ELSE 'test' END AS split, count(*)::BIGINT AS edges, count(DISTINCT rel)::BIGINT AS relations FROM s GROUP BY 1")
def large_graph_preparation(spark, sf):
    return experiments.large_graph_preparation(spark, _graph(spark, sf, "kb"))


@query("featurised_parts")
def featurised_parts(spark, sf):
    return experiments.featurised(spark, sf)


@query("parameter_server_epoch")
def parameter_server_epoch(spark, sf):
    """An epoch of batches through a store of vectors: loss of all edges before and after."""
    from ..functions import vectors as V
    from ..operators import train_sql

    e = graphs.user_event(spark, sf)
    start = e.select(F.col("src").alias("key")).union(e.select("dst")).distinct().select("key", V.initial(8, 0.5, 1, "init", F.col("key")).alias("vec"), F.lit(0.0).alias("acc"))
    loss = lambda v: train_sql.loss_terms(train_sql.scores(train_sql.negatives(e, 20, 50), v), "softmax").agg(F.sum("loss")).first()[0]
    after = train_sql.fit(e, start, epochs=1, batches=3, draws=20, chunk=50)
    return spark.createDataFrame([("start", loss(start)), ("after", loss(after))], "at string, loss double")

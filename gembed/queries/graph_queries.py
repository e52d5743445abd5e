"""Graph builders, preparation, parts, buckets and schedules."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.hashing import h32, sql_h32
from ..operators import costs, partition, schedule
from ..operators.spec import EntityType, GraphSpec, RelationSpec
from ..sources import graphs
from .base import DOC_WORD, PLACED, PURCHASES, SQL, TOKENS, USER_EVENT, kb_ctes, query, word_next_ctes

COLUMNS = "SELECT rel, src, dst, weight FROM edges"


@query("g_word_next", f"WITH {word_next_ctes()} {COLUMNS}")
def g_word_next(spark, sf):
    return graphs.word_next(spark, sf)


@query("g_doc_word", f"WITH {DOC_WORD} {COLUMNS}")
def g_doc_word(spark, sf):
    return graphs.doc_word(spark, sf)


@query("g_kb_edges", f"WITH {kb_ctes()} {COLUMNS}")
def g_kb_edges(spark, sf):
    return graphs.kb(spark, sf)


@query("g_purchases", f"WITH {PURCHASES} {COLUMNS}")
def g_purchases(spark, sf):
    return graphs.purchases(spark, sf)


@query("g_user_event", f"WITH {USER_EVENT} {COLUMNS}")
def g_user_event(spark, sf):
    return graphs.user_event(spark, sf)


KNN = """pairs AS (SELECT a.vec_id AS q, b.vec_id AS id, list_inner_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) AS s FROM embeddings a, embeddings b WHERE a.vec_id <> b.vec_id),
    best AS (SELECT q, id, s, row_number() OVER (PARTITION BY q ORDER BY s DESC, id) AS place FROM pairs)"""


@query("g_knn", f"WITH {KNN} SELECT 'near' AS rel, q::VARCHAR AS src, id::VARCHAR AS dst, 1::BIGINT AS weight FROM best WHERE place <= 5")
def g_knn(spark, sf):
    return graphs.knn(spark, sf)


@query(
    "g_page_links",
    """SELECT 'links' AS rel, page_id::VARCHAR AS src, dst, count(*)::BIGINT AS weight FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="/([^"]*)"', 1)) AS dst FROM pages) GROUP BY ALL
    UNION ALL SELECT 'hosted_by', page_id::VARCHAR, regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1), 1 FROM pages""",
)
def g_page_links(spark, sf):
    return graphs.page_links(spark, sf)


@query("g_conv_word", f"SELECT role AS rel, conv_id::VARCHAR AS src, dst, count(*)::BIGINT AS weight FROM (SELECT role, conv_id, unnest({TOKENS}) AS dst FROM conversations) GROUP BY ALL")
def g_conv_word(spark, sf):
    return graphs.conv_word(spark, sf)


@query(
    "degrees",
    f"""WITH {word_next_ctes()}, s AS (SELECT src AS key, sum(weight) AS n FROM edges GROUP BY 1), d AS (SELECT dst AS key, sum(weight) AS n FROM edges GROUP BY 1)
    SELECT coalesce(s.key, d.key) AS key, coalesce(s.n, 0)::BIGINT AS degree_src, coalesce(d.n, 0)::BIGINT AS degree_dst FROM s FULL JOIN d ON s.key = d.key""",
)
def degrees(spark, sf):
    return partition.degrees(graphs.word_next(spark, sf))


@query(
    "min_count_filter",
    f"""WITH {DOC_WORD}, ends AS (SELECT key FROM (SELECT src AS key FROM edges UNION ALL SELECT dst FROM edges) GROUP BY key HAVING count(*) >= 5)
    SELECT rel, src, dst, weight FROM edges WHERE src IN (SELECT key FROM ends) AND dst IN (SELECT key FROM ends) AND (SELECT count(*) FROM edges) >= 5""",
)
def min_count_filter(spark, sf):
    return partition.min_count_filter(graphs.doc_word(spark, sf), 5)


def _split_sql(*cuts: tuple[str, float]) -> str:
    h = sql_h32("'1'", "'split'", "rel", "src", "dst")
    at, out = 0.0, "CASE"
    for name, share in cuts[:-1]:
        at += share
        out += f" WHEN {h} / 4294967296.0::DOUBLE < {at!r}::DOUBLE THEN '{name}'"
    return out + f" ELSE '{cuts[-1][0]}' END"


THREE = (("train", 0.9), ("valid", 0.05), ("test", 0.05))
TWO = (("train", 0.75), ("test", 0.25))


@query("split_counts", f"WITH {word_next_ctes()} SELECT {_split_sql(*THREE)} AS split, count(*)::BIGINT AS n FROM edges GROUP BY ALL")
def split_counts(spark, sf):
    return partition.split_edges(graphs.word_next(spark, sf), dict(THREE)).groupBy("split").agg(F.count(F.lit(1)).alias("n"))


@query("split_two_way", f"WITH {USER_EVENT} SELECT rel, src, dst, weight, {_split_sql(*TWO)} AS split FROM edges")
def split_two_way(spark, sf):
    return partition.split_edges(graphs.user_event(spark, sf), dict(TWO))


KB_TYPES = ("customer", "supplier", "nation", "region", "part", "brand", "type", "size", "segment", "order", "priority", "user", "hour")
KB_RELATIONS = [
    ("customer_in_nation", "customer", "nation"), ("supplier_in_nation", "supplier", "nation"), ("nation_in_region", "nation", "region"), ("part_brand", "part", "brand"), ("part_type", "part", "type"),
    ("part_size", "part", "size"), ("customer_segment", "customer", "segment"), ("order_by_customer", "order", "customer"), ("order_priority", "order", "priority"), ("order_has_part", "order", "part"),
    ("part_from_supplier", "part", "supplier"), *[(f"user_{t}", "user", "hour") for t in graphs.EVENT_TYPES],
]


def kb_spec(**changes) -> GraphSpec:
    """The knowledge base's spec: small value types stay whole, the rest is partitioned."""
    whole = {"nation", "region", "brand", "type", "size", "segment", "priority", "hour"}
    return GraphSpec(tuple(EntityType(t, t not in whole) for t in KB_TYPES), tuple(RelationSpec(r, s, d, rhs_op="translation") for r, s, d in KB_RELATIONS), **({"dim": 16, "sim": "cos", "loss": "ranking"} | changes))


@query("type_violations", "SELECT 'nation_in_region' AS rel, 'region:' || n_regionkey AS src, 'nation:' || n_nationkey AS dst FROM nation UNION ALL SELECT 'unknown', 'nation:0', 'region:0'")
def type_violations(spark, sf):
    edges = graphs.kb(spark, sf).select("rel", "src", "dst")
    wrong = edges.where("rel = 'nation_in_region'").select("rel", F.col("dst").alias("src"), F.col("src").alias("dst"))
    more = spark.createDataFrame([("unknown", "nation:0", "region:0")], "rel string, src string, dst string")
    nodes = edges.select(F.col("src").alias("key")).union(edges.select("dst")).distinct().withColumn("type", F.substring_index("key", ":", 1))
    return partition.validate_edges(edges.unionByName(wrong).unionByName(more), nodes, kb_spec())


def _word_spec() -> GraphSpec:
    return GraphSpec((EntityType("word"),), (RelationSpec("follows", "word", "word"),))


def _doc_word_spec() -> GraphSpec:
    return GraphSpec((EntityType("document"), EntityType("word")), (RelationSpec("contains", "document", "word"),))


def _user_spec() -> GraphSpec:
    return GraphSpec((EntityType("user"), EntityType("event", False)), (RelationSpec("did", "user", "event"),))


def _part_sql(etype: str, key: str, p: int) -> str:
    return f"({sql_h32("'1'", "'part'", etype, key)} % {p})::INTEGER"


@query("partition_sizes", f"WITH {DOC_WORD}, nodes AS (SELECT DISTINCT 0 AS etype, src AS key FROM edges UNION SELECT DISTINCT 1, dst FROM edges) SELECT etype::INTEGER AS etype, {_part_sql('etype', 'key', 4)} AS part, count(*)::BIGINT AS n, max(0)::INTEGER AS first, (count(*) - 1)::INTEGER AS last FROM nodes GROUP BY 1, 2")
def partition_sizes(spark, sf):
    e = partition.partition_entities(graphs.doc_word(spark, sf), _doc_word_spec(), 4, portable=True)
    return e.groupBy("etype", "part").agg(F.count(F.lit(1)).alias("n"), F.min("offset").alias("first"), F.max("offset").alias("last"))


def _buckets(edges, spec, p):
    return partition.bucket_edges(edges, partition.partition_entities(edges, spec, p, portable=True), spec)


@query("bucket_counts", f"WITH {word_next_ctes()} SELECT {_part_sql('0', 'src', 4)} AS p_src, {_part_sql('0', 'dst', 4)} AS p_dst, count(*)::BIGINT AS n FROM edges GROUP BY 1, 2")
def bucket_counts(spark, sf):
    return _buckets(graphs.word_next(spark, sf), _word_spec(), 4).groupBy("p_src", "p_dst").agg(F.count(F.lit(1)).alias("n"))


@query("bucket_counts_one_sided", f"WITH {USER_EVENT} SELECT {_part_sql('0', 'src', 4)} AS p_src, {_part_sql('0', 'src', 4)} AS p_dst, count(*)::BIGINT AS n FROM edges GROUP BY 1, 2")
def bucket_counts_one_sided(spark, sf):
    return _buckets(graphs.user_event(spark, sf), _user_spec(), 4).groupBy("p_src", "p_dst").agg(F.count(F.lit(1)).alias("n"))


@query(
    "inverse_relations",
    f"""WITH {kb_ctes()}, a AS MATERIALIZED (SELECT DISTINCT rel, src, dst FROM edges UNION ALL SELECT DISTINCT rel || '_inverse', dst, src FROM edges),
    n AS (SELECT rel, count(*) AS n FROM a GROUP BY 1)
    SELECT x.rel, y.rel AS of, count(*) / any_value(n.n)::DOUBLE AS share FROM a x JOIN a y ON x.src = y.dst AND x.dst = y.src AND x.rel > y.rel JOIN n ON n.rel = x.rel GROUP BY x.rel, y.rel HAVING count(*) / any_value(n.n)::DOUBLE >= 0.95""",
)
def inverse_relations(spark, sf):
    return graphs.inverse_relations(graphs.kb(spark, sf, add_inverse=True))


def _orders_sql(kind: str, p: int) -> str:
    """Step, source and target part of an order, as SQL."""
    if kind in ("inside_out", "outside_in"):
        rows = f"""SELECT k, j, 0 AS turn, k AS a, j AS b FROM range({p}) r(k), range({p}) s(j) WHERE j < k UNION ALL SELECT k, j, 1, j, k FROM range({p}) r(k), range({p}) s(j) WHERE j < k UNION ALL SELECT k, -1, 2, k, k FROM range({p}) r(k)"""
        by = "k, j DESC, turn" if kind == "inside_out" else "k DESC, j, turn DESC"
    else:
        rows = f"SELECT k, j, 0 AS turn, k AS a, j AS b FROM range({p}) r(k), range({p}) s(j)"
        by = "a, b" if kind == "row_major" else "b, a"
    return f"SELECT (row_number() OVER (ORDER BY {by}) - 1)::INTEGER AS step, a::INTEGER AS p_src, b::INTEGER AS p_dst FROM ({rows})"


def _placed_buckets(spark, sf, parts, portable: bool = True):
    """parts, p_src, p_dst, edges: orders placed by customers, both types cut in so many parts, by bucket."""
    at = lambda etype, key, p: partition.part_of(F.lit(etype), F.col(key), p, 1, portable)
    cuts = F.array(*[F.struct(F.lit(p).alias("parts"), at(0, "src", p).alias("p_src"), at(1, "dst", p).alias("p_dst")) for p in parts])
    return graphs.placed(spark, sf).select(F.inline(cuts)).groupBy("parts", "p_src", "p_dst").agg(F.count(F.lit(1)).alias("edges"))


def _placed_buckets_sql(p: int) -> str:
    return f"(SELECT {_part_sql('0', 'src', p)} AS p_src, {_part_sql('1', 'dst', p)} AS p_dst, count(*)::BIGINT AS edges FROM edges GROUP BY 1, 2)"


def _order_df(spark, sf, kind, p):
    """The buckets of the orders' graph in the order in which they are trained, with their edges."""
    steps = spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(schedule.order(kind, p))], "step int, p_src int, p_dst int")
    held = _placed_buckets(spark, sf, (p,)).drop("parts")
    return steps.join(held, ["p_src", "p_dst"], "left").select("step", "p_src", "p_dst", F.coalesce("edges", F.lit(0)).cast("long").alias("edges"))


for _kind in ("inside_out", "row_major", "column_major", "outside_in"):
    query(f"order_{_kind}", f"WITH {PLACED} SELECT o.*, coalesce(b.edges, 0)::BIGINT AS edges FROM ({_orders_sql(_kind, 6)}) o LEFT JOIN {_placed_buckets_sql(6)} b ON b.p_src = o.p_src AND b.p_dst = o.p_dst")(lambda spark, sf, k=_kind: _order_df(spark, sf, k, 6))


@query(
    "alignment_check",
    " UNION ALL ".join(
        f"""(WITH {PLACED}, s AS (SELECT (row_number() OVER (ORDER BY o.step) - 1) AS step, p_src, p_dst FROM ({_orders_sql(k, p)}) o SEMI JOIN {_placed_buckets_sql(p)} b USING (p_src, p_dst)), parts AS (SELECT step, p_src AS part FROM s UNION SELECT step, p_dst FROM s), first AS (SELECT part, min(step) AS at FROM parts GROUP BY 1)
        SELECT '{k}' AS kind, {p}::INTEGER AS parts, (SELECT count(*) FROM s)::INTEGER AS buckets, coalesce(min(s.step), -1)::INTEGER AS first_violation FROM s JOIN first f ON f.part = s.p_src JOIN first g ON g.part = s.p_dst WHERE s.step > 0 AND f.at = s.step AND g.at = s.step)"""
        for k in ("inside_out", "outside_in", "row_major", "column_major")
        for p in (4, 6)
    ),
)
def alignment_check(spark, sf):
    """Of the buckets that hold orders, in each order: the first one that shares no part with those before."""
    held = {(r["parts"], r["p_src"], r["p_dst"]) for r in _placed_buckets(spark, sf, (4, 6)).collect()}
    rows = []
    for k in ("inside_out", "outside_in", "row_major", "column_major"):
        for p in (4, 6):
            seq = [b for b in schedule.order(k, p) if (p, *b) in held]
            bad = schedule.aligned_by_part(seq)
            rows.append((k, p, len(seq), -1 if bad is None else bad))
    return spark.createDataFrame(rows, "kind string, parts int, buckets int, first_violation int")


@query("swap_counts", " UNION ALL ".join(f"SELECT {p}::INTEGER AS parts, {1 + p * (p - 1) // 2}::INTEGER AS inside_out, {p * p - 2}::INTEGER AS row_major" for p in (2, 4, 8, 16)))
def swap_counts(spark, sf):
    loads = lambda k, p: schedule.simulate_swaps(schedule.order(k, p))["loads"]
    return spark.createDataFrame([(p, loads("inside_out", p), loads("row_major", p)) for p in (2, 4, 8, 16)], "parts int, inside_out int, row_major int")


@query("rounds_disjoint", " UNION ALL ".join(f"SELECT {p}::INTEGER AS parts, {p - 1 if p % 2 == 0 else p}::INTEGER AS rounds, {p * (p - 1) // 2}::INTEGER AS pairs, {p * (p - 1) // 2}::INTEGER AS different, true AS disjoint" for p in (4, 5, 8, 16)))
def rounds_disjoint(spark, sf):
    rows = []
    for p in (4, 5, 8, 16):
        plan = schedule.tournament(p)
        flat = [u for r in plan for u in r]
        rows.append((p, len(plan), len(flat), len(set(flat)), all(len({x for u in r for x in u}) == 2 * len(r) for r in plan)))
    return spark.createDataFrame(rows, "parts int, rounds int, pairs int, different int, disjoint boolean")


@query("occupancy")
def occupancy(spark, sf):
    """Share of busy workers: greedy first epochs and tournament rounds, for P = 2M and P = 4M; by units that hold
    orders, and by their edges, when a round lasts as long as its largest unit."""
    sizes = [(m, times * m) for m in (1, 2, 4, 8) for times in (2, 4)]
    held: dict = {}
    for r in _placed_buckets(spark, sf, sorted({p for _, p in sizes}), portable=False).collect():
        unit = (r["parts"], min(r["p_src"], r["p_dst"]), max(r["p_src"], r["p_dst"]))
        held[unit] = held.get(unit, 0) + r["edges"]
    rows = []
    for m, p in sizes:
        out = []
        for plan in (schedule.rounds(p, m, "affinity", True), schedule.rounds(p, m, "tournament", False)):
            kept = [[u for u in now if (p, *sorted(u)) in held] for now in plan]
            work = [[held[p, *sorted(u)] for u in now] for now in kept if now]
            out += [schedule.occupancy([now for now in kept if now], m), sum(map(sum, work)) / (m * sum(map(max, work))) if work else 0.0]
        rows.append((m, p, out[0], out[2], out[1], out[3]))
    return spark.createDataFrame(rows, "machines int, parts int, first_epoch double, later_epochs double, first_epoch_by_edges double, later_epochs_by_edges double")


@query("schedule_rows")
def schedule_rows(spark, sf):
    return spark.createDataFrame(schedule.schedule_rows(8, 4, 2, "tournament"), "epoch int, sub_epoch int, round int, slot int, unit int, p_a int, p_b int")


_NODES = f"WITH {PLACED}, n AS (SELECT count(*) AS edges, count(DISTINCT src) AS orders, count(DISTINCT dst) AS customers FROM edges)"


def _placed_sizes(spark, sf):
    """Edges, orders and customers of the orders' graph."""
    return graphs.placed(spark, sf).agg(F.count(F.lit(1)).alias("edges"), F.count_distinct("src").alias("orders"), F.count_distinct("dst").alias("customers")).first()


@query("partition_io", f"{_NODES} " + " UNION ALL ".join(f"SELECT {p}::INTEGER AS parts, {1 + p * (p - 1) // 2}::BIGINT AS loads, {1 + p * (p - 1) // 2}::BIGINT AS stores, ({2 * (1 + p * (p - 1) // 2)} * (ceil(orders / {p}.0) + ceil(customers / {p}.0)) * 404)::BIGINT AS bytes FROM n" for p in (2, 4, 8, 16)))
def partition_io(spark, sf):
    """What an epoch over the orders' graph moves: 100 dimensions and one accumulator a node, parts of equal size."""
    n = _placed_sizes(spark, sf)
    rows = [(p, *[int(costs.partition_io(p, (-(-n["orders"] // p) - (-n["customers"] // p)) * 404)[k]) for k in ("loads", "stores", "bytes")]) for p in (2, 4, 8, 16)]
    return spark.createDataFrame(rows, "parts int, loads long, stores long, bytes long")


@query("negative_cost", f"{_NODES} " + " UNION ALL ".join(f"SELECT '{m}' AS mode, {c}::INTEGER AS chunk, ({f'2 * edges + 2 * ceil(edges / {c}.0) * {c}' if m == 'batched' else f'2 * edges * {2 * c}'})::BIGINT AS rows, (edges + 2 * edges * {2 * c if m == 'batched' else 2 * c - 1})::BIGINT AS scores, (2 * edges * {2 * c - 1})::BIGINT AS negatives FROM n" for m in ("batched", "unbatched") for c in (5, 10, 25, 50, 100, 250)))
def negative_cost(spark, sf):
    """Rows, scores and negatives of an epoch over the orders' graph, its edges as one batch."""
    n, rows = _placed_sizes(spark, sf)["edges"], []
    for m in ("batched", "unbatched"):
        for c in (5, 10, 25, 50, 100, 250):
            x = costs.negative_cost(n, c, c, 100, m)
            rows.append((m, c, x["rows"], x["scores"], x["negatives"]))
    return spark.createDataFrame(rows, "mode string, chunk int, rows long, scores long, negatives long")


@query("ps_traffic", f"WITH {word_next_ctes()} SELECT count(*)::BIGINT AS edges, (ceil(count(*) / 1000.0) * 400000 * 8)::BIGINT AS parameter_server_bytes, (2 * 7 * ceil((SELECT count(*) FROM (SELECT src FROM edges UNION SELECT dst FROM edges)) / 4.0) * 404)::BIGINT AS block_bytes FROM edges")
def ps_traffic(spark, sf):
    e = graphs.word_next(spark, sf)
    n = e.count()
    nodes = e.select("src").union(e.select("dst")).distinct().count()
    return spark.createDataFrame([(n, costs.ps_bytes(n, 1000, 50, 50, 100), costs.partition_io(4, -(-nodes // 4) * 404)["bytes"])], "edges long, parameter_server_bytes long, block_bytes long")


@query("model_size", f"{_NODES} SELECT nodes, dim, (nodes * dim * 4)::BIGINT AS bytes, (nodes * dim * 4 + nodes * 4)::BIGINT AS with_state FROM (SELECT orders AS nodes, 100::INTEGER AS dim FROM n UNION ALL SELECT customers, 100 FROM n UNION ALL SELECT orders + customers, 400 FROM n)")
def model_size(spark, sf):
    """Bytes of the vectors of orders, of customers, and of both at four times the dimensions."""
    n = _placed_sizes(spark, sf)
    rows = [(k, d, costs.model_bytes(k, d), costs.model_bytes(k, d, True)) for k, d in ((n["orders"], 100), (n["customers"], 100), (n["orders"] + n["customers"], 400))]
    return spark.createDataFrame(rows, "nodes long, dim int, bytes long, with_state long")


@query("relation_params", "SELECT op, (CASE op WHEN 'identity' THEN 0 WHEN 'linear' THEN 16 * 256 ELSE 16 * 16 END)::BIGINT AS parameters FROM (VALUES ('identity'), ('translation'), ('diagonal'), ('linear'), ('complex_diagonal'), ('circular_correlation')) t(op)")
def relation_params(spark, sf):
    rows = []
    for op in ("identity", "translation", "diagonal", "linear", "complex_diagonal", "circular_correlation"):
        spec = GraphSpec(tuple(EntityType(t) for t in KB_TYPES), tuple(RelationSpec(r, s, d, rhs_op=op) for r, s, d in KB_RELATIONS), dim=16)
        rows.append((op, spec.n_shared()))
    return spark.createDataFrame(rows, "op string, parameters long")


@query("partition_plan", f"{_NODES}, m AS (SELECT (orders + customers)::BIGINT AS nodes, memory, (orders + customers)::DOUBLE * 404::DOUBLE AS state FROM n, (VALUES (100000000000::BIGINT), (80000000), (8000000), (100000)) v(memory)) SELECT nodes, memory, (CASE WHEN state <= 0.6::DOUBLE * memory::DOUBLE THEN 1 ELSE ceil(2::DOUBLE * state / (0.6::DOUBLE * memory::DOUBLE)) END)::INTEGER AS parts FROM m")
def partition_plan(spark, sf):
    """Parts of the orders' graph at 100 dimensions, by a task's memory."""
    n = _placed_sizes(spark, sf)
    nodes = n["orders"] + n["customers"]
    return spark.createDataFrame([(nodes, m, partition.plan_partitions(nodes, 100, m).parts) for m in (100_000_000_000, 80_000_000, 8_000_000, 100_000)], "nodes long, memory long, parts int")


assert SQL

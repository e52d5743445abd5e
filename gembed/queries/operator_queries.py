"""Relational, window, streaming and SQL-surface operators around the methods, each on the given tables."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.hashing import h32, sql_h32
from ..operators import train_sql
from ..session import scratch
from ..sources import graphs
from ..sources.tables import read_triples, table, write_triples
from ..streaming import ingest
from .base import DOC_WORD, TOKENS, USER_EVENT, kb_ctes, query, word_next_ctes
from .graph_queries import KNN, _part_sql


@query("triples_round_trip", f"WITH {kb_ctes()} SELECT rel, src AS head, dst AS tail FROM edges WHERE rel IN ('nation_in_region', 'customer_in_nation')")
def triples_round_trip(spark, sf):
    path = scratch(spark, "triples")
    write_triples(graphs.kb(spark, sf).where(F.col("rel").isin("nation_in_region", "customer_in_nation")).select(F.col("src").alias("head"), "rel", F.col("dst").alias("tail")), path)
    return read_triples(spark, path).select("rel", "head", "tail")


@query("triples_data_source", "SELECT 'nation:' || n_nationkey AS head, 'nation_in_region' AS rel, 'region:' || n_regionkey AS tail FROM nation")
def triples_data_source(spark, sf):
    from ..sources.triples import TripleTextSource

    path = scratch(spark, "triples")
    write_triples(graphs.kb(spark, sf).where("rel = 'nation_in_region'").select(F.col("src").alias("head"), "rel", F.col("dst").alias("tail")), path)
    spark.dataSource.register(TripleTextSource)
    return spark.read.format("triples").option("path", path).load()


@query("json_props", """SELECT event_id, (props->>'$.k')::BIGINT AS k FROM events""")
def json_props(spark, sf):
    return table(spark, sf, "events").select("event_id", F.from_json("props", "k long").getField("k").alias("k"))


@query("variant_props", """SELECT (props->>'$.k')::BIGINT AS k, count(*)::BIGINT AS n FROM events GROUP BY 1""")
def variant_props(spark, sf):
    return table(spark, sf, "events").select(F.variant_get(F.parse_json("props"), "$.k", "long").alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@query("url_host", "SELECT regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) AS host, count(*)::BIGINT AS n FROM pages GROUP BY 1")
def url_host(spark, sf):
    return table(spark, sf, "pages").groupBy(F.parse_url("url", F.lit("HOST")).alias("host")).agg(F.count(F.lit(1)).alias("n"))


@query("joins_broadcast", "SELECT n_name, count(*)::BIGINT AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def joins_broadcast(spark, sf):
    nation = table(spark, sf, "nation")  # 25 rows at every scale
    return table(spark, sf, "customer").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("customers"))


@query("joins_merge", "SELECT o_orderpriority AS priority, count(*)::BIGINT AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def joins_merge(spark, sf):
    o, li = table(spark, sf, "orders"), table(spark, sf, "lineitem")
    return o.hint("merge").join(li, o["o_orderkey"] == li["l_orderkey"]).groupBy(F.col("o_orderpriority").alias("priority")).agg(F.count(F.lit(1)).alias("lines"))


@query("joins_hash", "SELECT c_mktsegment AS segment, count(*)::BIGINT AS orders FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def joins_hash(spark, sf):
    o, c = table(spark, sf, "orders"), table(spark, sf, "customer")
    return o.join(c.hint("shuffle_hash"), o["o_custkey"] == c["c_custkey"]).groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count(F.lit(1)).alias("orders"))


@query("left_outer_labels", "SELECT d.doc_id, l.quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def left_outer_labels(spark, sf):
    return table(spark, sf, "documents").select("doc_id").join(table(spark, sf, "labels").select("doc_id", "quality"), "doc_id", "left")


@query("exists_not_exists", "SELECT count(*)::BIGINT AS never FROM customer c WHERE NOT EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey)")
def exists_not_exists(spark, sf):
    table(spark, sf, "customer").createOrReplaceTempView("_gembed_customer")
    table(spark, sf, "orders").createOrReplaceTempView("_gembed_orders")
    return spark.sql("SELECT count(*) AS never FROM _gembed_customer c WHERE NOT EXISTS (SELECT 1 FROM _gembed_orders o WHERE o.o_custkey = c.c_custkey)")


@query("anti_known", f"WITH {USER_EVENT}, c AS (SELECT DISTINCT e.src, d.dst AS cand FROM edges e, (SELECT DISTINCT dst FROM edges UNION SELECT 'none') d) SELECT src, cand FROM c WHERE NOT EXISTS (SELECT 1 FROM edges e WHERE e.src = c.src AND e.dst = c.cand)")
def anti_known(spark, sf):
    """Candidates that form no known edge: the filtered setting's anti-join."""
    e = graphs.user_event(spark, sf)
    cand = e.select("dst").distinct().select(F.col("dst").alias("cand")).union(spark.createDataFrame([("none",)], "cand string"))
    pairs = e.select("src").distinct().join(F.broadcast(cand))  # six event types, whatever the scale
    return pairs.join(e.select("src", F.col("dst").alias("cand")), ["src", "cand"], "left_anti")


@query("theta_units", "WITH u AS (SELECT a, b FROM range(6) r(a), range(6) s(b) WHERE a <= b) SELECT x.a::INTEGER AS a, x.b::INTEGER AS b, y.a::INTEGER AS c, y.b::INTEGER AS d FROM u x JOIN u y ON x.a <> y.a AND x.a <> y.b AND x.b <> y.a AND x.b <> y.b")
def theta_units(spark, sf):
    """Pairs of units that may be trained at the same time."""
    u = spark.range(6).select(F.col("id").cast("int").alias("a")).join(spark.range(6).select(F.col("id").cast("int").alias("b")), F.col("a") <= F.col("b"))
    v = u.select(F.col("a").alias("c"), F.col("b").alias("d"))
    return u.join(v, (F.col("a") != F.col("c")) & (F.col("a") != F.col("d")) & (F.col("b") != F.col("c")) & (F.col("b") != F.col("d")))


@query(
    "range_sampler_join",
    f"""WITH {USER_EVENT}, d AS (SELECT src, sum(weight) AS deg FROM edges GROUP BY 1), c AS (SELECT src, sum(deg) OVER (ORDER BY src) AS hi, sum(deg) OVER (ORDER BY src) - deg AS lo, sum(deg) OVER () AS total FROM d),
    u AS (SELECT i::INTEGER AS draw, {sql_h32("'1'", "'draw'", 'i')} % (SELECT max(total) FROM c)::BIGINT AS x FROM range(200) r(i)) SELECT draw, src FROM u JOIN c ON x >= lo AND x < hi""",
)
def range_sampler_join(spark, sf):
    """Degree-proportional draws: a point falls in a cumulative interval; cut in bins, it is an equi-join."""
    e = graphs.user_event(spark, sf)
    d = e.groupBy("src").agg(F.sum("weight").alias("deg"))
    # cumulative sums in two steps: inside hash-independent key ranges, then over the few ranges' totals
    d = d.withColumn("part", F.substring("src", 1, 2))
    inside = F.sum("deg").over(Window.partitionBy("part").orderBy("src"))
    totals = d.groupBy("part").agg(F.sum("deg").alias("n"))
    before = totals.withColumn("base", F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1))).select("part", F.coalesce("base", F.lit(0)).alias("base"))
    c = d.join(F.broadcast(before), "part").select("src", (F.col("base") + inside - F.col("deg")).alias("lo"), (F.col("base") + inside).alias("hi"))
    total = totals.agg(F.sum("n").alias("total"))
    width = 256
    bins = c.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor((F.col("hi") - 1) / width))))
    draws = spark.range(200).select(F.col("id").cast("int").alias("draw")).join(F.broadcast(total)).select("draw", (h32(1, "draw", F.col("draw")) % F.col("total")).alias("x")).withColumn("bin", F.floor(F.col("x") / width))
    return draws.join(bins, "bin").where("x >= lo and x < hi").select("draw", "src")


@query("asof_degree", "WITH d AS (SELECT user_id, ts, event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS degree FROM events), q AS (SELECT user_id, max(ts) - INTERVAL 5 DAY AS at FROM events GROUP BY 1) SELECT q.user_id, coalesce((SELECT max(degree) FROM d WHERE d.user_id = q.user_id AND d.ts <= q.at), 0)::BIGINT AS degree FROM q")
def asof_degree(spark, sf):
    """As-of join by union and a running last value: a user's degree five days before its last event."""
    ev = table(spark, sf, "events").select("user_id", "ts", "event_id")
    deg = ev.withColumn("degree", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("ts", "event_id")))
    ask = ev.groupBy("user_id").agg((F.max("ts") - F.expr("interval 5 day")).alias("ts"))
    rows = deg.select("user_id", "ts", F.lit(0).alias("turn"), "event_id", "degree").unionByName(ask.select("user_id", "ts", F.lit(1).alias("turn"), F.lit(None).cast("long").alias("event_id"), F.lit(None).cast("long").alias("degree")))
    last = F.last("degree", ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts", "turn", "event_id").rowsBetween(Window.unboundedPreceding, 0))
    return rows.withColumn("d", last).where("turn = 1").select("user_id", F.coalesce("d", F.lit(0)).alias("degree"))


@query("interval_join", "SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def interval_join(spark, sf):
    ev = table(spark, sf, "events").select("event_id", "user_id", "ts")
    a, b = ev.select(F.col("event_id").alias("first"), "user_id", F.col("ts").alias("t1")), ev.select(F.col("event_id").alias("second"), "user_id", F.col("ts").alias("t2"))
    return a.join(b, "user_id").where(F.expr("t2 > t1 and t2 <= t1 + interval 10 minutes")).select("first", "second")


@query("lateral_neighbours", f"WITH {USER_EVENT} SELECT src, dst, weight FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY weight DESC, dst) AS n FROM edges) WHERE n <= 2")
def lateral_neighbours(spark, sf):
    graphs.user_event(spark, sf).createOrReplaceTempView("_gembed_edges")
    return spark.sql("SELECT n.src, x.dst, x.weight FROM (SELECT DISTINCT src FROM _gembed_edges) n, LATERAL (SELECT dst, weight FROM _gembed_edges e WHERE e.src = n.src ORDER BY weight DESC, dst LIMIT 2) x")


@query("set_ops_split", f"WITH {USER_EVENT}, e AS (SELECT src, dst, {sql_h32(chr(39) + 's' + chr(39), 'src', 'dst')} % 4 = 0 AS test FROM edges), tr AS (SELECT src, dst FROM e WHERE NOT test), te AS (SELECT src, dst FROM e WHERE test) SELECT (SELECT count(*) FROM (SELECT * FROM tr INTERSECT SELECT * FROM te))::BIGINT AS both, (SELECT count(*) FROM (SELECT src, dst FROM e EXCEPT SELECT * FROM tr))::BIGINT AS held_out, (SELECT count(*) FROM (SELECT * FROM tr UNION SELECT * FROM te))::BIGINT AS known")
def set_ops_split(spark, sf):
    e = graphs.user_event(spark, sf).select("src", "dst").withColumn("test", h32("s", F.col("src"), F.col("dst")) % 4 == 0)
    tr, te, every = e.where("not test").drop("test"), e.where("test").drop("test"), e.drop("test")
    one = lambda df, n: df.agg(F.count(F.lit(1)).alias(n))
    return one(tr.intersect(te), "both").join(one(every.subtract(tr), "held_out")).join(one(tr.union(te).distinct(), "known"))  # three single rows


@query("multiset_ops", "SELECT l_partkey, l_suppkey FROM lineitem EXCEPT ALL SELECT DISTINCT l_partkey, l_suppkey FROM lineitem")
def multiset_ops(spark, sf):
    pairs = table(spark, sf, "lineitem").select("l_partkey", "l_suppkey")
    return pairs.exceptAll(pairs.distinct())


@query("grouping_sets_buckets", f"WITH {word_next_ctes()}, b AS (SELECT {_part_sql('0', 'src', 4)} AS p_src, {_part_sql('0', 'dst', 4)} AS p_dst FROM edges) SELECT p_src, p_dst, grouping(p_src, p_dst)::BIGINT AS level, count(*)::BIGINT AS n FROM b GROUP BY GROUPING SETS ((p_src), (p_dst), ())")
def grouping_sets_buckets(spark, sf):
    from ..operators.partition import part_of

    e = graphs.word_next(spark, sf).select(part_of(F.lit(0), F.col("src"), 4, 1, True).alias("p_src"), part_of(F.lit(0), F.col("dst"), 4, 1, True).alias("p_dst"))
    e.createOrReplaceTempView("_gembed_buckets")
    return spark.sql("SELECT p_src, p_dst, grouping_id(p_src, p_dst) AS level, count(*) AS n FROM _gembed_buckets GROUP BY p_src, p_dst GROUPING SETS ((p_src), (p_dst), ())")


@query("cube_metrics", "SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n, round(sum(l_quantity), 3) AS quantity FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def cube_metrics(spark, sf):
    return table(spark, sf, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 3).alias("quantity"))


@query("pivot_bucket_matrix", f"WITH {word_next_ctes()}, b AS (SELECT {_part_sql('0', 'src', 3)} AS p_src, {_part_sql('0', 'dst', 3)} AS p FROM edges) SELECT p_src, count(*) FILTER (p = 0)::BIGINT AS to_0, count(*) FILTER (p = 1)::BIGINT AS to_1, count(*) FILTER (p = 2)::BIGINT AS to_2 FROM b GROUP BY 1")
def pivot_bucket_matrix(spark, sf):
    from ..operators.partition import part_of

    e = graphs.word_next(spark, sf).select(part_of(F.lit(0), F.col("src"), 3, 1, True).alias("p_src"), part_of(F.lit(0), F.col("dst"), 3, 1, True).alias("p"))
    wide = e.groupBy("p_src").pivot("p", [0, 1, 2]).agg(F.count(F.lit(1)))
    return wide.select("p_src", *[F.coalesce(str(i), F.lit(0)).alias(f"to_{i}") for i in range(3)])


@query("unpivot_metrics", "SELECT l_returnflag AS flag, 'quantity' AS metric, round(sum(l_quantity), 3) AS value FROM lineitem GROUP BY 1 UNION ALL SELECT l_returnflag, 'discount', round(sum(l_discount), 3) FROM lineitem GROUP BY 1")
def unpivot_metrics(spark, sf):
    wide = table(spark, sf, "lineitem").groupBy(F.col("l_returnflag").alias("flag")).agg(F.round(F.sum("l_quantity"), 3).alias("quantity"), F.round(F.sum("l_discount"), 3).alias("discount"))
    return wide.unpivot("flag", ["quantity", "discount"], "metric", "value")


@query("degree_quantiles", f"WITH {word_next_ctes()}, d AS (SELECT src, count(*) AS deg FROM edges GROUP BY 1) SELECT quantile_cont(deg, 0.5)::DOUBLE AS p50, quantile_cont(deg, 0.9)::DOUBLE AS p90, quantile_cont(deg, 0.99)::DOUBLE AS p99, max(deg)::BIGINT AS top FROM d")
def degree_quantiles(spark, sf):
    d = graphs.word_next(spark, sf).groupBy("src").agg(F.count(F.lit(1)).alias("deg"))
    return d.agg(F.percentile("deg", F.lit(0.5)).alias("p50"), F.percentile("deg", F.lit(0.9)).alias("p90"), F.percentile("deg", F.lit(0.99)).alias("p99"), F.max("deg").alias("top"))


@query("approx_distinct")
def approx_distinct(spark, sf):
    d = graphs.doc_word(spark, sf)
    return d.agg(F.approx_count_distinct("dst").alias("words"), F.hll_sketch_estimate(F.hll_sketch_agg("dst")).alias("sketched"), F.count_distinct("dst").alias("exact"))


@query("distinct_neighbours", f"WITH {DOC_WORD} SELECT src, count(DISTINCT dst)::BIGINT AS words, sum(weight)::BIGINT AS tokens FROM edges GROUP BY 1")
def distinct_neighbours(spark, sf):
    return graphs.doc_word(spark, sf).groupBy("src").agg(F.count_distinct("dst").alias("words"), F.sum("weight").alias("tokens"))


@query("window_topk", f"WITH {KNN} SELECT q AS query, id, place::INTEGER AS place FROM best WHERE place <= 3")
def window_topk(spark, sf):
    from ..operators.nearest import nearest_exact

    v = table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
    return nearest_exact(v, v, 3, drop_self=True).select("query", "id", "place")


@query("window_bigrams", f"WITH t AS (SELECT {TOKENS} AS w FROM documents) SELECT src, dst, count(*)::BIGINT AS n FROM (SELECT unnest(w[1:len(w)-1]) AS src, unnest(w[2:len(w)]) AS dst FROM t WHERE len(w) > 1) GROUP BY ALL")
def window_bigrams(spark, sf):
    return graphs.bigrams_by_window(table(spark, sf, "documents")).groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))


@query("window_ranks", "SELECT c_custkey, rank() OVER w AS r, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd, ntile(10) OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal, c_custkey) AS decile FROM customer WINDOW w AS (PARTITION BY c_mktsegment ORDER BY round(c_acctbal / 100))")
def window_ranks(spark, sf):
    w = Window.partitionBy("c_mktsegment").orderBy(F.round(F.col("c_acctbal") / 100))
    return table(spark, sf, "customer").select("c_custkey", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("dr"), F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"), F.ntile(10).over(Window.partitionBy("c_mktsegment").orderBy("c_acctbal", "c_custkey")).cast("long").alias("decile"))


@query("range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW)::BIGINT AS last_hour, first_value(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS first_event FROM events")
def range_frame(spark, sf):
    """Frames over seconds that are rounded, halves to the even one, as the SQL's cast does."""
    by, second = Window.partitionBy("user_id"), F.rint(F.expr("unix_micros(cast(ts AS timestamp))") / 1e6).cast("long")
    return table(spark, sf, "events").select("event_id", F.count(F.lit(1)).over(by.orderBy(second).rangeBetween(-3600, 0)).alias("last_hour"), F.first("event_id").over(by.orderBy("ts", "event_id")).alias("first_event"))


@query("running_degree", "SELECT event_id, sum(1) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)::BIGINT AS degree, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events")
def running_degree(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf, "events").select("event_id", F.sum(F.lit(1)).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("degree"), F.lag("event_type").over(w).alias("before"))


@query("tumbling_events", "SELECT date_trunc('day', ts)::TIMESTAMP AS window_start, user_id, count(*)::BIGINT AS n FROM events GROUP BY 1, 2")
def tumbling_events(spark, sf):
    return ingest.tumbling(table(spark, sf, "events"))


@query("sliding_events", "SELECT (date_trunc('day', ts) + INTERVAL (6 * (hour(ts) // 6)) HOUR - INTERVAL (6 * k) HOUR)::TIMESTAMP AS window_start, event_type, count(*)::BIGINT AS n FROM events, range(4) r(k) GROUP BY 1, 2")
def sliding_events(spark, sf):
    return ingest.sliding(table(spark, sf, "events"))


@query(
    "session_events",
    """WITH g AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 12 HOUR THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
    s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS no FROM g)
    SELECT min(ts)::TIMESTAMP AS session_start, (max(ts) + INTERVAL 12 HOUR)::TIMESTAMP AS session_end, user_id, count(*)::BIGINT AS n FROM s GROUP BY user_id, no""",
)
def session_events(spark, sf):
    return ingest.sessions(table(spark, sf, "events"))


@query("view_then_purchase", "SELECT v.user_id, v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts > v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR")
def view_then_purchase(spark, sf):
    return ingest.view_then_purchase(table(spark, sf, "events"))


@query("stream_replay", "SELECT rel, src, dst, sum(weight)::BIGINT AS weight FROM (SELECT 'did' AS rel, user_id::VARCHAR AS src, event_type AS dst, 1 AS weight FROM events) GROUP BY ALL")
def stream_replay(spark, sf):
    """Events streamed into the bucket store by micro-batches, read back and summed."""
    root = scratch(spark, "stream")
    ev = table(spark, sf, "events").select("event_id", "ts", "user_id", "event_type")
    ev.repartition(3, "event_id").write.parquet(f"{root}/in")
    ingest.append_buckets(ingest.event_stream(spark, f"{root}/in", ev.schema), f"{root}/out")
    return spark.read.parquet(f"{root}/out").groupBy("rel", "src", "dst").agg(F.sum("weight").alias("weight"))


@query("array_math", "WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings) SELECT vec_id, round(list_sum(list_transform(e, lambda x: x * x)), 6) AS norm2, round(list_max(e), 6) AS top, round(list_sum(e[1:32]), 6) AS first_half FROM v")
def array_math(spark, sf):
    e = F.col("embedding").cast("array<double>")
    zero = F.lit(0.0)
    return table(spark, sf, "embeddings").select("vec_id", F.round(F.aggregate(F.zip_with(e, e, lambda x, y: x * y), zero, lambda a, x: a + x), 6).alias("norm2"), F.round(F.array_max(e), 6).alias("top"), F.round(F.aggregate(F.slice(e, 1, 32), zero, lambda a, x: a + x), 6).alias("first_half"))


@query("math_functions", "SELECT l_orderkey, l_linenumber, l_partkey, round(1 / (1 + exp(-l_discount)), 9) AS sigmoid, round(ln(1 + exp(l_tax)), 9) AS softplus, greatest(l_discount, l_tax) AS larger, date_diff('day', o_orderdate, l_shipdate)::INTEGER AS days FROM lineitem JOIN orders ON o_orderkey = l_orderkey")
def math_functions(spark, sf):
    li, o = table(spark, sf, "lineitem"), table(spark, sf, "orders")
    j = li.join(o, li["l_orderkey"] == o["o_orderkey"])
    return j.select("l_orderkey", "l_linenumber", "l_partkey", F.round(1 / (1 + F.exp(-F.col("l_discount"))), 9).alias("sigmoid"), F.round(F.log1p(F.exp("l_tax")), 9).alias("softplus"), F.greatest("l_discount", "l_tax").alias("larger"), F.datediff("l_shipdate", "o_orderdate").alias("days"))


@query("map_options", "SELECT 'n' || n_nationkey AS name, n_regionkey AS region, 2::INTEGER AS size FROM nation")
def map_options(spark, sf):
    m = F.map_from_arrays(F.array(F.lit("name"), F.lit("region")), F.array(F.concat(F.lit("n"), "n_nationkey"), F.col("n_regionkey").cast("string")))
    return table(spark, sf, "nation").select(m.alias("m")).select(F.element_at("m", "name").alias("name"), F.element_at("m", "region").cast("int").alias("region"), F.size("m").alias("size"))


@query("hash_portable", f"SELECT c_custkey, {sql_h32(chr(39) + '42' + chr(39), 'c_custkey')} AS h FROM customer")
def hash_portable(spark, sf):
    return table(spark, sf, "customer").select("c_custkey", h32(42, F.col("c_custkey")).alias("h"))


@query("scalar_subquery", f"WITH {word_next_ctes()}, d AS (SELECT src, sum(weight) AS deg FROM edges GROUP BY 1) SELECT src, deg::BIGINT AS deg FROM d WHERE deg > 20 * (SELECT avg(deg) FROM d)")
def scalar_subquery(spark, sf):
    graphs.word_next(spark, sf).createOrReplaceTempView("_gembed_word_next")
    return spark.sql("WITH d AS (SELECT src, sum(weight) AS deg FROM _gembed_word_next GROUP BY src) SELECT src, deg FROM d WHERE deg > 20 * (SELECT avg(deg) FROM d)")


@query("recursive_levels", "WITH RECURSIVE l AS (SELECT n_nationkey::BIGINT AS node, n_nationkey::BIGINT AS super, 0 AS level FROM nation UNION ALL SELECT node, super // 2, level + 1 FROM l WHERE level < 5) SELECT node, super, level::INTEGER AS level FROM l")
def recursive_levels(spark, sf):
    table(spark, sf, "nation").createOrReplaceTempView("_gembed_nation")
    return spark.sql("WITH RECURSIVE l AS (SELECT CAST(n_nationkey AS BIGINT) AS node, CAST(n_nationkey AS BIGINT) AS super, 0 AS level FROM _gembed_nation UNION ALL SELECT node, super DIV 2, level + 1 FROM l WHERE level < 5) SELECT node, super, level FROM l")


@query("sql_functions", "SELECT a.vec_id, round(list_inner_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 5) AS dot, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 5) AS cos FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def sql_functions(spark, sf):
    from ..functions.udfs import register_all

    register_all(spark)
    table(spark, sf, "embeddings").createOrReplaceTempView("_gembed_vectors")
    return spark.sql("SELECT a.vec_id, round(gembed_dot(a.embedding, b.embedding), 5) AS dot, round(gembed_cos(a.embedding, b.embedding), 5) AS cos FROM _gembed_vectors a JOIN _gembed_vectors b ON b.vec_id = a.vec_id + 1")


@query("sql_aggregates", "WITH e AS (SELECT label, unnest(range(64)) AS k, unnest(embedding::DOUBLE[]) AS x FROM embeddings) SELECT label, k::INTEGER AS k, round(avg(x), 6) AS mean, round(sum(x), 4) AS total FROM e GROUP BY 1, 2")
def sql_aggregates(spark, sf):
    """Vector mean by the aggregate function, and its column twin."""
    from ..operators.features import vec_sum

    v = table(spark, sf, "embeddings").select("label", F.col("embedding").cast("array<double>").alias("vec"))
    mean, total = (vec_sum(v, "label", "vec", how).select("label", F.posexplode("vec").alias("k", how)) for how in ("mean", "sum"))
    return mean.join(total, ["label", "k"]).select("label", "k", F.round("mean", 6).alias("mean"), F.round("sum", 4).alias("total"))


@query("udtf_order", "SELECT (row_number() OVER (ORDER BY a, b) - 1)::INTEGER AS step, a::INTEGER AS p_src, b::INTEGER AS p_dst FROM range(5) r(a), range(5) s(b)")
def udtf_order(spark, sf):
    from ..functions.udfs import register_all

    register_all(spark)
    return spark.sql("SELECT step, p_src, p_dst FROM bucket_order(5, 'row_major')")


@query("udtf_negatives", "SELECT count(*)::BIGINT AS one_side, 2 * count(*)::BIGINT AS both_sides FROM range(50) r(i), range(100) s(j) WHERE i <> j")
def udtf_negatives(spark, sf):
    from ..functions.udfs import register_all

    register_all(spark)
    return spark.sql("SELECT count(*) AS one_side, 2 * count(*) AS both_sides FROM batched_negatives(50, 50)")


@query("sampled_edges", f"WITH {word_next_ctes()} SELECT src, dst FROM edges WHERE {sql_h32(chr(39) + 'sample' + chr(39), 'src', 'dst')} < 429496729")
def sampled_edges(spark, sf):
    """A tenth of the edges by a hash threshold: the sampling operator, the same rows in every run."""
    return graphs.word_next(spark, sf).where(h32("sample", F.col("src"), F.col("dst")) < 429496729).select("src", "dst")


@query("chunk_numbers", f"WITH {USER_EVENT} SELECT src, dst, ((row_number() OVER (PARTITION BY rel ORDER BY {sql_h32(chr(39) + '1' + chr(39), chr(39) + 'chunk' + chr(39), 'src', 'dst')}, src, dst) - 1) // 50)::INTEGER AS chunk_id FROM edges")
def chunk_numbers(spark, sf):
    return train_sql.chunked(graphs.user_event(spark, sf), 50).select("src", "dst", "chunk_id")


@query("top_edges", f"WITH {word_next_ctes()} SELECT src, dst, weight FROM edges ORDER BY weight DESC, src, dst LIMIT 20 OFFSET 5")
def top_edges(spark, sf):
    return graphs.word_next(spark, sf).orderBy(F.desc("weight"), "src", "dst").offset(5).limit(20).select("src", "dst", "weight")


@query("count_if_hits", "SELECT l_returnflag AS flag, count(*) FILTER (l_quantity <= 10)::BIGINT AS small, max_by(l_orderkey, (l_extendedprice, l_orderkey)) AS dearest FROM lineitem GROUP BY 1")
def count_if_hits(spark, sf):
    return table(spark, sf, "lineitem").groupBy(F.col("l_returnflag").alias("flag")).agg(F.count_if(F.col("l_quantity") <= 10).alias("small"), F.max_by("l_orderkey", F.struct("l_extendedprice", "l_orderkey")).alias("dearest"))

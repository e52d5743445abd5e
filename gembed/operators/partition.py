"""Ids, parts and buckets: done once before training, in a few joins, so that no epoch needs a key again."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import fast, h32
from ..session import stored
from .spec import GraphSpec


def part_of(etype, key, p: int, seed: int = 1, portable: bool = False) -> Column:
    return ((h32 if portable else fast)(F.lit(seed), F.lit("part"), etype, key) % p).cast("int")


def min_count_filter(edges: DataFrame, least: int = 5, until_stable: bool = False, rounds: int = 20) -> DataFrame:
    """Keeps nodes and relations that occur at least so often; once, or until nothing more goes."""
    before = None
    for _ in range(rounds if until_stable else 1):
        ends = edges.select(F.col("src").alias("key")).union(edges.select("dst"))
        nodes = ends.groupBy("key").count().where(F.col("count") >= least).select("key")
        rels = edges.groupBy("rel").count().where(F.col("count") >= least).select("rel")
        kept = edges.join(nodes.withColumnRenamed("key", "src"), "src", "left_semi").join(nodes.withColumnRenamed("key", "dst"), "dst", "left_semi").join(F.broadcast(rels), "rel", "left_semi").select(*edges.columns)
        if not until_stable:
            return kept
        edges = stored(kept, "min-count")
        now = edges.count()
        if now == before:
            break
        before = now
    return edges


def split_edges(edges: DataFrame, shares: dict[str, float], seed: int = 1, portable: bool = True) -> DataFrame:
    """Adds ``split`` by a hash of the edge's key: the same edge always falls in the same split."""
    h = (h32(seed, "split", F.col("rel"), F.col("src"), F.col("dst")) if portable else fast(F.lit(seed), F.lit("split"), F.col("rel"), F.col("src"), F.col("dst")).bitwiseAND(F.lit(0xFFFFFFFF))) / float(1 << 32)
    at, out, names = 0.0, None, list(shares)
    total = sum(shares.values())
    for name in names[:-1]:
        at += shares[name] / total
        out = F.when(h < at, name) if out is None else out.when(h < at, name)
    return edges.withColumn("split", F.lit(names[-1]) if out is None else out.otherwise(names[-1]))


def degrees(edges: DataFrame) -> DataFrame:
    """key, degree as source and as destination (weights summed); full outer, so one-sided nodes stay."""
    src = edges.groupBy(F.col("src").alias("key")).agg(F.sum("weight").alias("degree_src"))
    dst = edges.groupBy(F.col("dst").alias("key")).agg(F.sum("weight").alias("degree_dst"))
    return src.join(dst, "key", "full").select("key", F.coalesce("degree_src", F.lit(0)).cast("long").alias("degree_src"), F.coalesce("degree_dst", F.lit(0)).cast("long").alias("degree_dst"))


def typed(edges: DataFrame, spec: GraphSpec) -> DataFrame:
    """Adds relation and type numbers from the spec (a broadcast of the relations); unknown relations are dropped by ``validate``."""
    rows = [(r.name, i, spec.type_no(r.src_type), spec.type_no(r.dst_type)) for i, r in enumerate(spec.relations)]
    rel = edges.sparkSession.createDataFrame(rows, "rel string, rel_no int, src_type int, dst_type int")
    return edges.join(F.broadcast(rel), "rel")


def validate_edges(edges: DataFrame, node_types: DataFrame, spec: GraphSpec) -> DataFrame:
    """Edges without a defined score: unknown relation, or an endpoint of another type. node_types: key, type."""
    rows = [(r.name, r.src_type, r.dst_type) for r in spec.relations]
    rel = edges.sparkSession.createDataFrame(rows, "rel string, src_type string, dst_type string")
    ok = edges.join(F.broadcast(rel), "rel").join(node_types.select(F.col("key").alias("src"), F.col("type").alias("src_type")), ["src", "src_type"], "left_semi").join(node_types.select(F.col("key").alias("dst"), F.col("type").alias("dst_type")), ["dst", "dst_type"], "left_semi")
    return edges.join(ok.select("rel", "src", "dst"), ["rel", "src", "dst"], "left_anti")


def partition_entities(edges: DataFrame, spec: GraphSpec, p: int, portable: bool = False) -> DataFrame:
    """etype, key, part, offset of every node; ``offset`` numbers the nodes of a part from 0.

    Numbering is a window inside each part (a part must fit in a task anyway); there is no global order.
    """
    e = typed(edges, spec)
    nodes = e.select(F.col("src_type").alias("etype"), F.col("src").alias("key")).union(e.select("dst_type", "dst")).distinct()
    cut = F.lit(False)
    for i, t in enumerate(spec.types):
        cut = cut | ((F.col("etype") == i) & F.lit(t.partitioned))
    nodes = nodes.withColumn("part", F.when(cut, part_of(F.col("etype"), F.col("key"), p, spec.seed, portable)).otherwise(F.lit(0)))
    mixed = (h32 if portable else fast)(F.lit(spec.seed), F.lit("offset"), F.col("etype"), F.col("key"))
    place = F.row_number().over(Window.partitionBy("etype", "part").orderBy(mixed, "key"))
    return nodes.withColumn("offset", (place - 1).cast("int"))


def draw_inside(entities: DataFrame, draws: int, seed: int = 1) -> DataFrame:
    """(etype, part, slot, key): uniform draws of nodes for each type and part, from that part alone."""
    size = entities.groupBy("etype", "part").agg(F.count(F.lit(1)).alias("size"))
    slots = size.withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(draws - 1))))
    at = slots.withColumn("offset", (h32(seed, "inside", F.col("etype"), F.col("part"), F.col("slot")) % F.col("size")).cast("int"))
    return at.join(entities, ["etype", "part", "offset"]).select("etype", "part", "slot", "key")


def bucket_edges(edges: DataFrame, entities: DataFrame, spec: GraphSpec, portable: bool = False, small: bool = False) -> DataFrame:
    """rel_no, p_src, p_dst, src_off, dst_off, weight and a hash that mixes edges inside a unit.

    An endpoint of a whole type takes the other endpoint's part, so P parts give P squared buckets if
    both types are partitioned, P if one is, and one if none is. ``small``: the entities may go to every task.
    """
    if small:
        entities = F.broadcast(entities)
    whole = [i for i, t in enumerate(spec.types) if not t.partitioned]
    e = typed(edges, spec)
    src = entities.select(F.col("etype").alias("src_type"), F.col("key").alias("src"), F.col("part").alias("_ps"), F.col("offset").alias("src_off"))
    dst = entities.select(F.col("etype").alias("dst_type"), F.col("key").alias("dst"), F.col("part").alias("_pd"), F.col("offset").alias("dst_off"))
    j = e.join(src, ["src_type", "src"]).join(dst, ["dst_type", "dst"])
    ps = F.when(F.col("src_type").isin(whole), F.lit(None).cast("int")).otherwise(F.col("_ps")) if whole else F.col("_ps")
    pd = F.when(F.col("dst_type").isin(whole), F.lit(None).cast("int")).otherwise(F.col("_pd")) if whole else F.col("_pd")
    return j.select(
        F.col("rel_no").alias("rel"),
        F.coalesce(ps, pd, F.lit(0)).alias("p_src"),
        F.coalesce(pd, ps, F.lit(0)).alias("p_dst"),
        "src_off",
        "dst_off",
        F.col("weight").cast("float").alias("weight"),
        (h32 if portable else fast)(F.lit(spec.seed), F.lit("mix"), F.col("rel"), F.col("src"), F.col("dst")).alias("h"),
    )


@dataclass(frozen=True)
class PartPlan:
    parts: int
    task_bytes: int
    epoch_bytes: int


def plan_partitions(nodes: int, dim: int, memory_per_task: int, machines: int = 1) -> PartPlan:
    """The fewest parts of which two fit in 60 % of a task's memory and that keep all machines busy."""
    state = nodes * (4 * dim + 4)
    fit = math.ceil(2 * state / (0.6 * memory_per_task))
    p = max(1 if machines == 1 else 2 * machines, 1 if state <= 0.6 * memory_per_task else fit)
    return PartPlan(p, 2 * math.ceil(state / p), p * state)

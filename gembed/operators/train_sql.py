"""The training step as joins and aggregates: the readable form of the kernel, checked by SQL, and the
parameter-server baseline (every batch fetches its rows by a join and pushes summed gradients back).

Batches, chunks and draws come from hashes of keys. Vectors are (key, vec, acc) rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..functions.hashing import h32


def chunked(edges: DataFrame, chunk: int, seed: int = 1) -> DataFrame:
    """Adds ``chunk_id``: edges in hash order, cut evenly inside each relation (and bucket, where it has one)."""
    by = [c for c in ("bucket", "rel") if c in edges.columns]
    place = F.row_number().over(Window.partitionBy(*by).orderBy(h32(seed, "chunk", F.col("src"), F.col("dst")), "src", "dst"))
    return edges.withColumn("chunk_id", ((place - 1) / chunk).cast("int"))


def uniform_nodes(nodes: DataFrame, chunks: DataFrame, draws: int, side: str, seed: int = 1) -> DataFrame:
    """(rel, chunk_id, key): uniform draws for each chunk. nodes: rel, key with dense ``place`` and its ``size``."""
    slots = chunks.select("rel", "chunk_id").distinct().withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(draws - 1))))
    size = nodes.groupBy("rel").agg(F.count(F.lit(1)).alias("size"))
    at = slots.join(F.broadcast(size), "rel").withColumn("place", (h32(seed, "uni", side, F.col("rel"), F.col("chunk_id"), F.col("slot")) % F.col("size")).cast("int"))
    return at.join(nodes, ["rel", "place"]).select("rel", "chunk_id", "key", "slot")


def placed_nodes(edges: DataFrame, side: str) -> DataFrame:
    """(rel, key, place): the nodes of a relation's side, numbered by key."""
    nodes = edges.select("rel", F.col(side).alias("key")).distinct()
    return nodes.withColumn("place", F.row_number().over(Window.partitionBy("rel").orderBy("key")) - 1)


def negatives(edges: DataFrame, draws: int, chunk: int, side: str = "dst", seed: int = 1) -> DataFrame:
    """(rel, src, dst, weight, chunk_id, cand, times): the chunk's own endpoints and the uniform draws, the edge's own excepted."""
    e = chunked(edges, chunk, seed)
    own = e.select("rel", "chunk_id", F.col(side).alias("cand"))
    uni = uniform_nodes(placed_nodes(edges, side), e, draws, side, seed).select("rel", "chunk_id", F.col("key").alias("cand"))
    pool = own.unionByName(uni).groupBy("rel", "chunk_id", "cand").agg(F.count(F.lit(1)).alias("times"))
    return e.join(pool, ["rel", "chunk_id"]).where(F.col("cand") != F.col(side))


def scores(rows: DataFrame, vectors: DataFrame, side: str = "dst") -> DataFrame:
    """Adds ``pos`` and ``neg``, dot products of the edge and of the edge with the candidate."""
    v = lambda name, out: vectors.select(F.col("key").alias(name), F.col("vec").alias(out))
    kept = "src" if side == "dst" else "dst"
    j = rows.join(v("src", "sv"), "src").join(v("dst", "dv"), "dst").join(v("cand", "cv"), "cand")
    return j.withColumn("pos", V.dot(F.col("sv"), F.col("dv"))).withColumn("neg", V.dot(F.col("sv" if kept == "src" else "dv"), F.col("cv")))


def loss_terms(scored: DataFrame, loss: str, margin: float = 0.1) -> DataFrame:
    """Adds per negative its gradient by score ``gn`` (with multiplicity) and per row of it ``gp``, and ``loss``.

    gp is the share of this negative in the positive's gradient, so that sums per edge are right.
    """
    key = ["rel", "src", "dst"]
    w, t = F.col("weight").cast("double"), F.col("times").cast("double")
    per_edge = Window.partitionBy(*key)
    if loss == "ranking":
        on = (F.lit(margin) - F.col("pos") + F.col("neg") > 0).cast("double")
        out = scored.withColumn("gn", w * t * on).withColumn("loss", w * t * F.greatest(F.lit(0.0), F.lit(margin) - F.col("pos") + F.col("neg")))
        return out.withColumn("gp", -F.col("gn"))
    if loss == "softmax":
        top = F.greatest(F.max("neg").over(per_edge), F.col("pos"))
        e = scored.withColumn("_top", top).withColumn("_en", t * F.exp(F.col("neg") - F.col("_top"))).withColumn("_ep", F.exp(F.col("pos") - F.col("_top")))
        e = e.withColumn("_z", F.col("_ep") + F.sum("_en").over(per_edge)).withColumn("_rows", F.count(F.lit(1)).over(per_edge))
        e = e.withColumn("gn", w * F.col("_en") / F.col("_z")).withColumn("gp", -F.col("gn"))
        return e.withColumn("loss", w * (F.log("_z") - (F.col("pos") - F.col("_top"))) / F.col("_rows")).drop("_top", "_en", "_ep", "_z", "_rows")
    if loss == "logistic":
        soft = lambda x: F.greatest(x, F.lit(0.0)) + F.log1p(F.exp(-F.abs(x)))
        sig = lambda x: 1 / (1 + F.exp(-x))
        e = scored.withColumn("_j", F.sum(t).over(per_edge)).withColumn("_rows", F.count(F.lit(1)).over(per_edge))
        e = e.withColumn("gn", w * t * sig(F.col("neg")) / F.col("_j")).withColumn("gp", -w * sig(-F.col("pos")) / F.col("_rows"))
        return e.withColumn("loss", w * soft(-F.col("pos")) / F.col("_rows") + w * t * soft(F.col("neg")) / F.col("_j")).drop("_j", "_rows")
    raise ValueError(loss)


def gradients(terms: DataFrame, side: str = "dst") -> DataFrame:
    """(key, k, g): summed gradient of each coordinate of each touched node."""
    kept, kv, true, tv = ("src", "sv", "dst", "dv") if side == "dst" else ("dst", "dv", "src", "sv")
    weighted = terms.select(
        F.col(kept).alias("a"), F.col(true).alias("b"), F.col("cand").alias("c"),
        F.zip_with(F.transform(tv, lambda x: x * F.col("gp")), F.transform("cv", lambda x: x * F.col("gn")), lambda x, y: x + y).alias("ga"),
        F.transform(kv, lambda x: x * F.col("gp")).alias("gb"), F.transform(kv, lambda x: x * F.col("gn")).alias("gc"),
    )
    each = weighted.select(F.explode(F.array(*[F.struct(F.col(n).alias("key"), F.col(g).alias("g")) for n, g in (("a", "ga"), ("b", "gb"), ("c", "gc"))])).alias("x"))
    return each.select("x.key", F.posexplode("x.g").alias("k", "g")).groupBy("key", "k").agg(F.sum("g").alias("g"))


def update(vectors: DataFrame, grads: DataFrame, lr: float, optimizer: str = "adagrad_row") -> DataFrame:
    """New (key, vec, acc) of all nodes; untouched rows pass unchanged."""
    g = grads.groupBy("key").agg(F.transform(F.array_sort(F.collect_list(F.struct("k", "g"))), lambda x: x["g"]).alias("g"))
    j = vectors.join(g, "key", "left")
    acc = F.col("acc") + F.coalesce(V.dot(F.col("g"), F.col("g")), F.lit(0.0))
    rate = F.lit(lr) if optimizer == "sgd" else F.lit(lr) / (F.sqrt(acc) + F.lit(1e-10))
    vec = F.when(F.col("g").isNull(), F.col("vec")).otherwise(F.zip_with("vec", "g", lambda x, y: x - y * rate))
    return j.select("key", vec.alias("vec"), (F.col("acc") if optimizer == "sgd" else acc).alias("acc"))


def step(edges: DataFrame, vectors: DataFrame, chunk: int = 50, draws: int = 50, loss: str = "softmax", lr: float = 0.1, optimizer: str = "adagrad_row", margin: float = 0.1, seed: int = 1) -> DataFrame:
    """One full-batch step over both sides."""
    g = None
    for side in ("dst", "src"):
        part = gradients(loss_terms(scores(negatives(edges, draws, chunk, side, seed), vectors, side), loss, margin), side)
        g = part if g is None else g.unionByName(part)
    return update(vectors, g.groupBy("key", "k").agg(F.sum("g").alias("g")), lr, optimizer)


def fit(edges: DataFrame, vectors: DataFrame, epochs: int = 1, batches: int = 4, seed: int = 1, **kind) -> DataFrame:
    """The parameter-server baseline: every batch pulls its rows by joins and pushes summed gradients back.

    Batches are dealt by a hash of the edge; the store of vectors is written anew after each, so a batch
    sees all that came before, and a lost executor costs its tasks.
    """
    from ..session import stored

    place = h32(seed, "batch", F.col("rel"), F.col("src"), F.col("dst")) % batches
    for epoch in range(epochs):
        for b in range(batches):
            vectors = stored(step(edges.where(place == b), vectors, seed=seed + epoch, **kind), "server-vectors")
    return vectors

"""Exact nearest vectors by blocks: a block of queries is scored against a block of vectors in one product.

Both sides are cut in blocks; each pair of blocks is one row of work and returns its own best k, which
a ranking per query merges. Nothing is broadcast that grows with the data, and a task holds two blocks and
a bounded piece of their scores. A product only tells which scores may matter; those are added up again in the order of the
dimensions, so equal vectors have equal scores wherever they lie.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


#: Bytes of vectors in one block, and of scores that a task holds at a time.
BLOCK_BYTES, SCORE_BYTES = 4 << 20, 16 << 20


def _blocked(df: DataFrame, name: str, blocks: int, *more: str) -> DataFrame:
    """id, vec and lists of doubles (``more``) gathered in ``blocks`` rows of packed values."""
    ordered = df.select(F.col("id").cast("long").alias("id"), "vec", *more, F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int").alias(name)).repartition(blocks, name).sortWithinPartitions(name, "id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        for b in batches:
            no, ids = b.column(name).to_numpy(), b.column("id").to_numpy()
            x = b.column("vec").flatten().to_numpy(zero_copy_only=False).astype(np.float32).reshape(len(ids), -1)
            y = [b.column(c).flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1) for c in more]
            for k in np.unique(no):
                held.setdefault(int(k), []).append([z[no == k] for z in (ids, x, *y)])
        for k, parts in held.items():
            ids, x, *y = (np.concatenate(z) for z in zip(*parts, strict=True))
            packed = [ids.astype("<i8"), x.astype("<f4"), *(z.astype("<f8") for z in y)]
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([x.shape[1]], pa.int32()), *(pa.array([z.tobytes()]) for z in packed)], names=[name, "dim", "ids", "x", *more])

    return ordered.mapInArrow(run, ", ".join([f"{name} int, dim int, ids binary, x binary", *(f"{c} binary" for c in more)]))


def blocks_for(df: DataFrame, least: int) -> int:
    """Blocks of which each is at most ``BLOCK_BYTES``: from the number of rows and the size of a vector."""
    n, size = df.agg(F.count(F.lit(1)), F.max(F.size("vec"))).first()
    return max(least, -(-n * (size or 0) * 4 // BLOCK_BYTES))


def _pairs(queries: DataFrame, vectors: DataFrame, query_blocks: int | None, vector_blocks: int | None, *more: str) -> DataFrame:
    """A row for each block of queries and block of vectors, dealt by the pair."""
    query_blocks, vector_blocks = query_blocks or blocks_for(queries, 2), vector_blocks or blocks_for(vectors, 4)
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    q = _blocked(queries, "qb", query_blocks, *more).select("qb", "dim", F.col("ids").alias("qids"), F.col("x").alias("qx"), *more).withColumn("vb", every(vector_blocks))
    v = _blocked(vectors, "vb", vector_blocks).select("vb", "ids", "x").withColumn("qb", every(query_blocks))
    n = query_blocks * vector_blocks
    return q.repartition(n, "qb", "vb").join(v.repartition(n, "qb", "vb"), ["qb", "vb"])


class _Pair:
    """Two unpacked blocks, their scores in pieces of ``SCORE_BYTES``, and how far a product may be off."""

    def __init__(self, row: dict):
        self.qi, self.vi = np.frombuffer(row["qids"], "<i8"), np.frombuffer(row["ids"], "<i8")
        self.qx, self.vx = (np.frombuffer(row[c], "<f4").reshape(-1, row["dim"]).astype(np.float64) for c in ("qx", "x"))

    def classes(self) -> tuple[np.ndarray, np.ndarray]:
        """Rows of vectors so that equal ones are neighbours, lower ids first; where a run of equal ones begins."""
        order = np.lexsort((self.vi, *self.vx.T))
        y = self.vx[order]
        return order, np.concatenate([[True], (y[1:] != y[:-1]).any(1)]) if len(y) else np.zeros(0, bool)

    def keep(self, rows: np.ndarray) -> None:
        self.vi, self.vx = self.vi[rows], self.vx[rows]

    def pieces(self) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """First query, scores (minus infinity where there is none) and, for each query, twice the most that two ways to add them up differ by."""
        step = max(1, SCORE_BYTES // (8 * max(1, len(self.vi))))
        most = np.sqrt((self.vx**2).sum(1)).max(initial=0)
        for lo in range(0, len(self.qi), step):
            x = self.qx[lo : lo + step]
            s = x @ self.vx.T
            s[~np.isfinite(s)] = -np.inf
            yield lo, s, 4 * x.shape[1] * np.finfo(np.float64).eps * np.sqrt((x**2).sum(1)) * most

    def exact(self, q: np.ndarray, v: np.ndarray) -> np.ndarray:
        """Scores of given rows, added up in the order of the dimensions."""
        out = np.zeros(len(q))
        for k in range(self.qx.shape[1]):
            out += self.qx[q, k] * self.vx[v, k]
        return out


def nearest_exact(queries: DataFrame, vectors: DataFrame, k: int, drop_self: bool = False, query_blocks: int | None = None, vector_blocks: int | None = None) -> DataFrame:
    """query, id, score, place of the k best vectors by dot product, ties by id. Inputs: id, vec."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                pair = _Pair(b.slice(i, 1).to_pylist()[0])
                order, first = pair.classes()
                start = np.maximum.accumulate(np.where(first, np.arange(len(first)), 0))
                # of equal vectors, only so many of the lowest ids can be among the best
                pair.keep(np.sort(order[np.arange(len(first)) - start < k + drop_self]))
                for lo, s, off in pair.pieces():
                    if drop_self:
                        at = np.searchsorted(pair.vi, pair.qi[lo : lo + len(s)])
                        own = np.flatnonzero((at < len(pair.vi)) & (pair.vi[np.minimum(at, len(pair.vi) - 1)] == pair.qi[lo : lo + len(s)])) if len(pair.vi) else []
                        s[own, at[own]] = -np.inf
                    last = np.partition(s, s.shape[1] - k, axis=1)[:, s.shape[1] - k] if s.shape[1] > k else np.full(len(s), -np.inf)
                    q, v = np.nonzero((s >= (last - off)[:, None]) & (s > -np.inf))
                    score = pair.exact(q + lo, v)
                    best = np.lexsort((v, -score, q))  # ids ascend inside a block
                    q, v, score = q[best], v[best], score[best]
                    place = np.arange(len(q)) - np.searchsorted(q, q)
                    q, v, score = (x[place < k] for x in (q, v, score))
                    yield pa.RecordBatch.from_arrays([pa.array(pair.qi[q + lo]), pa.array(pair.vi[v]), pa.array(score)], names=["query", "id", "score"])

    found = _pairs(queries, vectors, query_blocks, vector_blocks).mapInArrow(run, "query long, id long, score double")
    place = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("score"), "id"))
    return found.withColumn("place", place).where(F.col("place") <= k)


def better_exact(queries: DataFrame, vectors: DataFrame, query_blocks: int | None = None, vector_blocks: int | None = None) -> DataFrame:
    """query, no, better: how many vectors other than the query's own score above each of its ``given`` scores.

    Inputs: id, vec, given (as many scores for each query; infinite ones are passed over) and id, vec.
    Equal vectors are scored once and counted as often as they occur.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                row = b.slice(i, 1).to_pylist()[0]
                pair = _Pair(row)
                given = np.frombuffer(row["given"], "<f8").reshape(len(pair.qi), -1)
                order, first = pair.classes()
                times = np.diff(np.append(np.flatnonzero(first), len(first)))
                class_of = np.empty(len(order), np.int64)
                class_of[order] = np.cumsum(first) - 1
                ids = pair.vi
                pair.keep(order[first])
                at = np.minimum(np.searchsorted(ids, pair.qi), max(0, len(ids) - 1))
                own = np.where(ids[at] == pair.qi, class_of[at], -1) if len(ids) else np.full(len(pair.qi), -1)
                for lo, s, off in pair.pieces():
                    t = given[lo : lo + len(s)]
                    q, v = np.nonzero(s > (t.min(1, initial=np.inf) - off)[:, None])
                    score, n = pair.exact(q + lo, v), times[v] - (own[q + lo] == v)
                    better = np.stack([np.bincount(q, n * (score > t[q, j]), len(s)) for j in range(t.shape[1])], 1).astype(np.int64)
                    width = t.shape[1]
                    yield pa.RecordBatch.from_arrays([pa.array(np.repeat(pair.qi[lo : lo + len(s)], width)), pa.array(np.tile(np.arange(width, dtype=np.int32), len(s))), pa.array(better.ravel())], names=["query", "no", "better"])

    counted = _pairs(queries, vectors, query_blocks, vector_blocks, "given").mapInArrow(run, "query long, no int, better long")
    return counted.groupBy("query", "no").agg(F.sum("better").alias("better"))


def ranks_exact(edges: DataFrame, vectors: DataFrame, most: int) -> DataFrame:
    """q, true, better, better_filtered of given edges (query, id, score; at most ``most`` a query) among all vectors but
    the query's own. ``better_filtered`` leaves out the query's other given edges; scores are those of ``nearest_exact``.
    """
    own = edges.groupBy("query").agg(F.array_sort(F.collect_list(F.struct("score", "id"))).alias("e"))
    scores = F.transform("e", lambda x: x["score"])
    full = F.concat(scores, F.array_repeat(F.lit(float("inf")), F.lit(most) - F.size("e")))
    queries = own.join(vectors.select(F.col("id").alias("query"), "vec"), "query").select(F.col("query").alias("id"), "vec", full.alias("given"))
    each = own.select("query", F.posexplode("e").alias("no", "x"), "e")
    among = F.size(F.filter("e", lambda y: y["score"] > F.col("x.score")))
    return each.join(better_exact(queries, vectors), ["query", "no"]).select(F.col("query").alias("q"), F.col("x.id").alias("true"), "better", (F.col("better") - among).alias("better_filtered"))


def nearest_by_relation(model, keys: DataFrame, rel: str, k: int) -> DataFrame:
    """src, dst, score, place: the k best destinations of given sources (key) under a relation's operators."""
    from . import relops

    spec = model.spec
    r = spec.relations[spec.relation_no(rel)]
    th = model.params[spec.relation_no(rel)].theta
    which = "dst" if r.reciprocal else "both"
    vec = model.vectors().join(model.prepared.entities.select("etype", "key", (F.col("part").cast("long") * (1 << 32) + F.col("offset")).alias("id")), ["etype", "key"])

    def moved(rows: DataFrame, op: str, theta) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                x = b.column("vec").flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, spec.dim)
                y = relops.forward(op, x, theta).astype(np.float32)
                y = relops.normalise(y)[0] if spec.sim == "cos" else y
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, y.size + 1, spec.dim, dtype=np.int32)), pa.array(y.ravel()))
                yield pa.RecordBatch.from_arrays([b.column("id"), lists], names=["id", "vec"])

        return rows.select("id", "vec").mapInArrow(run, "id long, vec array<float>")

    of = lambda side: vec.where(F.col("etype") == spec.type_no(side))
    asked = of(r.src_type).join(keys.select("key").distinct(), "key")
    found = nearest_exact(moved(asked, r.lhs_op, th.get((which, "lhs"))), moved(of(r.dst_type), "identity" if r.reciprocal else r.rhs_op, th.get((which, "rhs"))), k)
    named = found.join(of(r.src_type).select(F.col("id").alias("query"), F.col("key").alias("src")), "query").join(of(r.dst_type).select("id", F.col("key").alias("dst")), "id")
    return named.select("src", "dst", "score", "place")

"""A relational graph convolution encoder: each layer mixes a node's vector with the degree-normalised
sum of its neighbours' vectors per relation, each through the relation's matrix.

The layers' matrices are fixed orthogonal ones (drawn from the seed), so this is an untrained encoder
over trained base vectors; the decoder is any similarity of the engine. It stands for the encoder's
cost and data flow: one join, one product per relation in Arrow, one sum per node.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.features import vec_sum


def relation_matrix(rel: str, layer: int, d: int, seed: int) -> np.ndarray:
    from ..functions.hashing import py_h32

    rng = np.random.default_rng(py_h32(seed, "rgcn", rel, layer))
    q, _ = np.linalg.qr(rng.normal(size=(d, d)))
    return q.astype(np.float32)


def rgcn_layer(edges: DataFrame, vectors: DataFrame, layer: int = 0, d: int = 32, seed: int = 1) -> DataFrame:
    """(key, vec) after one layer; nodes without incoming edges keep their vector."""
    deg = edges.groupBy("rel", "dst").agg(F.count(F.lit(1)).alias("deg"))
    msg = edges.join(vectors.select(F.col("key").alias("src"), "vec"), "src").join(deg, ["rel", "dst"]).select("rel", F.col("dst").alias("key"), "deg", "vec")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, np.ndarray] = {}
        for b in batches:
            rel, deg = np.array(b.column("rel").to_pylist(), object), b.column("deg").to_numpy()
            x = np.array(b.column("vec").to_pylist(), np.float32).reshape(b.num_rows, d)
            for r in set(rel.tolist()):
                if r not in held:
                    held[r] = relation_matrix(r, layer, d, seed)
                at = rel == r
                x[at] = (x[at] @ held[r].T) / deg[at, None]
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, (b.num_rows + 1) * d, d, dtype=np.int32)), pa.array(x.ravel()))
            yield pa.RecordBatch.from_arrays([b.column("key"), lists], names=["key", "vec"])

    summed = vec_sum(msg.mapInArrow(run, "key string, vec array<float>"), "key").withColumnRenamed("vec", "around")
    joined = vectors.join(summed, "key", "left")
    return joined.select("key", F.when(F.col("around").isNull(), F.col("vec").cast("array<double>")).otherwise(F.zip_with("vec", "around", lambda x, y: F.greatest(x + y, (x + y) * 0.1))).alias("vec"))


def rgcn(edges: DataFrame, vectors: DataFrame, layers: int = 2, d: int = 32, seed: int = 1) -> DataFrame:
    for layer in range(layers):
        vectors = rgcn_layer(edges, vectors, layer, d, seed)
    return vectors

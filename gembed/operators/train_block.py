"""Training by blocks: entity parts are split, edges fall in buckets, and a task trains a chain of units.

A unit is the buckets between two parts. Edges are stored once, partitioned by unit, so a job reads the
folders of its own units and nothing else, and an epoch reads every edge once. A job runs chains, one
task each, on disjoint parts: a task holds two parts, trains its units one after another, and stores a
part only when the next unit needs another in its place; a part that the next unit shares stays where it
is. With one machine an epoch is one chain in the bucket order. With several, a round is a job, and the
units of single parts ride along with the first pair that holds them.

Parts are files on the shared store under a name of the attempt that wrote them, never changed, and only
the rows that a finished job returns say which are valid; a retried task starts again from the versions
of the job's beginning. All randomness comes from (seed, epoch, round, unit), so it returns the same
bytes. The driver adds up the changes of the shared parameters (fewer than a million numbers).
"""

from __future__ import annotations

import json
import time
import uuid
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import HASHED_BYTES, is_small, key_bytes, remove, scratch, stored
from . import kernels
from .costs import RssSampler
from .kernels import Counters, Matrix, Params
from .partition import bucket_edges, partition_entities
from .schedule import Unit, chains, order, units_in_order
from .spec import GraphSpec

#: Values of a part that go through Arrow at a time when vectors are read.
READ_VALUES = 4 << 20
SHARED_LIMIT = 8_000_000
_OUT = "kind int, etype int, part int, n int, path string, vec binary, acc binary, rel int, name string, stats array<double>"
_STATS = ("edges", "loss", "rows_gathered", "scores", "negatives", "violations", "loads", "stores", "seconds", "rss_mb")


@dataclass
class Prepared:
    """Edges with part offsets, in a folder per unit, and entities with parts, both stored once."""

    spec: GraphSpec
    parts: int
    entities: DataFrame
    edges: DataFrame
    sizes: dict[tuple[int, int], int]
    #: Of each featurised type: its features in order, and which of them each node has (as ``kernels.Bags``).
    bags: dict[int, tuple[list, np.ndarray, np.ndarray]] = field(default_factory=dict)
    #: Entities, and bytes of their keys.
    counted: tuple[int, int] = (1 << 62, 0)

    def unit_no(self, unit: Unit) -> int:
        return unit[0] * self.parts + unit[1]


def _bags_of(entities: DataFrame, etype: int, n: int, bags: DataFrame) -> tuple[list, np.ndarray, np.ndarray]:
    """The features of a type's nodes, on the driver: shared by all tasks, so of a checked size."""
    held = stored(entities.where(F.col("etype") == etype).join(bags.select(F.col("key").cast("string"), F.col("feature").cast("string")).distinct(), "key").select("offset", "feature"), "bags")
    if held.count() > SHARED_LIMIT:
        raise ValueError("too many features of shared nodes")
    names = sorted(r["feature"] for r in held.select("feature").distinct().collect())
    place = held.sparkSession.createDataFrame(list(enumerate(names)), "no int, feature string")
    # numbers only, in columns: rows of Python would take a hundred times as much
    rows = held.join(F.broadcast(place), "feature").select("offset", "no").orderBy("offset", "no").toArrow()
    ptr = np.concatenate([[0], np.cumsum(np.bincount(rows.column("offset").to_numpy(), minlength=n))]).astype(np.int64)
    return names, ptr, rows.column("no").to_numpy().astype(np.int32)


def prepare(edges: DataFrame, spec: GraphSpec, parts: int, portable: bool = False, bags: dict[str, DataFrame] | None = None) -> Prepared:
    """``bags`` has, for each featurised type, its nodes' features (key, feature)."""
    entities = stored(partition_entities(edges, spec, parts, portable), "entities")
    counted = key_bytes(entities, "key")
    unit = F.least("p_src", "p_dst") * F.lit(parts) + F.greatest("p_src", "p_dst")
    # a unit's edges come in a few files, dealt by their hash, and not one from every task
    bucketed = bucket_edges(edges, entities, spec, portable, is_small(*counted, most=HASHED_BYTES)).withColumn("unit", unit).repartition("unit", F.pmod("h", F.lit(4)))
    bucketed = stored(bucketed, "buckets", "unit")
    sizes = {(r["etype"], r["part"]): r["n"] for r in entities.groupBy("etype", "part").agg(F.count(F.lit(1)).alias("n")).collect()}
    held = {i: _bags_of(entities, i, sizes.get((i, 0), 0), (bags or {})[t.name]) for i, t in enumerate(spec.types) if t.featurised}
    return Prepared(spec, parts, entities, bucketed, sizes, held, counted)


def _file_system(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def store_part(folder: str, etype: int, part: int, m: Matrix) -> str:
    """Writes a part's vectors and optimiser state to a new file; its address."""
    fs, root = _file_system(folder)
    fs.create_dir(root, recursive=True)
    name = f"part-{etype}-{part}-{uuid.uuid4().hex[:12]}.f4"
    with fs.open_output_stream(f"{root}/{name}") as f:
        f.write(np.ascontiguousarray(m.x, "<f4"))
        f.write(np.ascontiguousarray(m.acc, "<f4"))
    return f"{folder}/{name}"


def load_part(path: str, n: int, dim: int, acc: bool = True) -> Matrix:
    fs, at = _file_system(path)
    with fs.open_input_file(at) as f:
        x = np.frombuffer(f.read(4 * n * dim), "<f4").reshape(n, dim).copy()
        rest = np.frombuffer(f.read(), "<f4").copy() if acc else np.zeros(n, np.float32)
    return Matrix(x, rest.reshape(n, dim) if acc and n and len(rest) == n * dim and dim > 1 else rest)


@dataclass
class Model:
    """``where`` has the valid file of each (entity type, part); a part without one has not been trained."""

    prepared: Prepared
    where: dict[tuple[int, int], str] = field(default_factory=dict)
    params: list[Params] = field(default_factory=list)
    shared: dict[int, Matrix] = field(default_factory=dict)
    log: list[dict] = field(default_factory=list)
    epoch: int = 0
    kept: set[str] = field(default_factory=set)

    @property
    def spec(self) -> GraphSpec:
        return self.prepared.spec

    def feature_vectors(self, name: str) -> DataFrame:
        """feature, vec of a featurised type."""
        t = self.spec.type_no(name)
        rows = [(f, self.shared[t].x[i].tolist()) for i, f in enumerate(self.prepared.bags[t][0])]
        return self.prepared.entities.sparkSession.createDataFrame(rows, "feature string, vec array<float>")

    def vectors(self) -> DataFrame:
        """etype, key, vec of every node."""
        spark, spec, sizes = self.prepared.entities.sparkSession, self.spec, self.prepared.sizes
        flat = None
        if self.where:
            dim = spec.dim
            step = max(1, READ_VALUES // dim)
            files = spark.createDataFrame([(t, p, at, sizes.get((t, p), 0)) for (t, p), at in sorted(self.where.items())], "etype int, part int, path string, n int")

            def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                for b in batches:
                    for row in b.to_pylist():
                        x = load_part(row["path"], row["n"], dim, acc=False).x
                        for lo in range(0, row["n"], step):
                            y = x[lo : lo + step]
                            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, y.size + 1, dim, dtype=np.int32)), pa.array(y.ravel()))
                            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(y), row["etype"], np.int32)), pa.array(np.full(len(y), row["part"], np.int32)), pa.array(np.arange(lo, lo + len(y), dtype=np.int32)), lists], names=["etype", "part", "offset", "vec"])

            flat = files.repartition(len(self.where), "etype", "part").mapInArrow(unpack, "etype int, part int, offset int, vec array<float>")
        shared, bags = self.shared, self.prepared.bags
        if shared or flat is None:
            step = max(1, READ_VALUES // spec.dim)
            count = {t: len(bags[t][1]) - 1 if t in bags else len(m.x) for t, m in shared.items()}
            cuts = [(t, lo, min(lo + step, n)) for t, n in count.items() for lo in range(0, n, step)]

            def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                for b in batches:
                    for row in b.to_pylist():
                        t, at = row["etype"], np.arange(row["lo"], row["hi"], dtype=np.int32)
                        y = (kernels.Bags(shared[t], *bags[t][1:]) if t in bags else shared[t]).x[at].astype(np.float32)
                        lists = pa.ListArray.from_arrays(pa.array(np.arange(0, y.size + 1, y.shape[1], dtype=np.int32)), pa.array(y.ravel()))
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), t, np.int32)), pa.array(np.zeros(len(at), np.int32)), pa.array(at), lists], names=["etype", "part", "offset", "vec"])

            extra = spark.createDataFrame(cuts, "etype int, lo int, hi int").mapInArrow(whole, "etype int, part int, offset int, vec array<float>")
            flat = extra if flat is None else flat.unionByName(extra)
        return self.prepared.entities.join(flat, ["etype", "part", "offset"]).select("etype", "key", "vec")


class Holder:
    """The parts that a task holds: at most two parts of every partitioned type, the longest unused leaves first."""

    def __init__(self, spec: GraphSpec, sizes: dict, where: dict, folder: str):
        self.spec, self.sizes, self.where, self.folder = spec, sizes, dict(where), folder
        self.types = [i for i, t in enumerate(spec.types) if t.partitioned]
        self.held: dict[int, dict[int, Matrix]] = {}
        self.written: dict[tuple[int, int], str] = {}
        self.loads = self.stores = 0

    def need(self, unit: Unit) -> dict[tuple[int, int], Matrix]:
        wanted = sorted(set(unit))
        for part in wanted:
            if part in self.held:
                self.held[part] = self.held.pop(part)  # used last
                continue
            while len(self.held) >= 2:
                self.leave(next(h for h in self.held if h not in wanted))
            self.loads += 1
            self.held[part] = {t: self.start(t, part) for t in self.types}
        return {(t, p): m for p in wanted for t, m in self.held[p].items()}

    def start(self, etype: int, part: int) -> Matrix:
        n, path = self.sizes.get((etype, part), 0), self.written.get((etype, part)) or self.where.get((etype, part))
        return load_part(path, n, self.spec.dim) if path else kernels.start_matrix(self.spec, etype, part, n)

    def leave(self, part: int) -> None:
        self.stores += 1
        for t, m in self.held.pop(part).items():
            self.written[t, part] = store_part(self.folder, t, part, m)


def _trainer(spec: GraphSpec, sizes: dict, plan: list[list[Unit]], where: dict, folder: str, params: list[Params], shared: dict[int, Matrix], stamp: tuple, bags: dict | None = None):
    """The function that trains the chains of one partition of the job's rows."""
    arrow = pa.schema([("kind", pa.int32()), ("etype", pa.int32()), ("part", pa.int32()), ("n", pa.int32()), ("path", pa.string()), ("vec", pa.binary()), ("acc", pa.binary()), ("rel", pa.int32()), ("name", pa.string()), ("stats", pa.list_(pa.float64()))])

    class Chain:
        def __init__(self, no: int):
            self.no, self.at, self.began = no, -1, time.time()
            self.holder = Holder(spec, sizes, where, folder)
            self.shared = {t: Matrix(m.x.copy(), m.acc.copy()) for t, m in shared.items()}
            self.params = [p.copy() for p in params]
            self.count, self.pending = Counters(), {}

        def go_to(self, seq: int) -> None:
            """Opens the unit of a place in the chain; units without edges on the way are passed through too."""
            while self.at < seq:
                self.finish()
                self.at += 1
                a, b = plan[self.no][self.at]
                self.parts = self.holder.need((a, b))
                self.rng = np.random.Generator(np.random.Philox(key=[spec.seed * 1_000_003 + stamp[0] * 10_007 + stamp[1], (a << 32) + b]))

        def finish(self) -> None:
            for key in list(self.pending):
                self.flush(key, True)

        def flush(self, key: tuple, last: bool) -> None:
            """Trains all full batches that wait under a (bucket, relation)."""
            s, d, w = (np.concatenate(x) for x in zip(*self.pending[key], strict=True))
            n = len(s) if last else len(s) // spec.batch * spec.batch
            ps, pd, r = key
            rel = spec.relations[r]
            ts, td = spec.type_no(rel.src_type), spec.type_no(rel.dst_type)
            src, dst = self.nodes(ts, ps), self.nodes(td, pd)
            if n and len(src.x) and len(dst.x):
                kernels.train_edges(spec, rel, self.params[r], src, dst, s[:n], d[:n], w[:n], self.rng, self.count)
            self.pending[key] = [(s[n:], d[n:], w[n:])]
            if last:
                del self.pending[key]

        def nodes(self, etype: int, part: int):
            own = self.shared.get(etype)
            if own is None:
                return self.parts[etype, part]
            return kernels.Bags(own, *bags[etype][1:]) if bags and etype in bags else own

        def close(self, rss: float) -> pa.RecordBatch:
            self.go_to(len(plan[self.no]) - 1)
            self.finish()
            for part in list(self.holder.held):
                self.holder.leave(part)
            rows: list[tuple] = [(0, t, p, sizes.get((t, p), 0), path, None, None, None, None, None) for (t, p), path in self.holder.written.items()]
            for r, (new, old) in enumerate(zip(self.params, params, strict=True)):
                for k, theta in new.theta.items():
                    rows.append((1, None, None, theta.size, None, (theta - old.theta[k]).astype("<f4").tobytes(), (new.acc[k] - old.acc[k]).astype("<f4").tobytes(), r, "/".join(k), None))
            for t, m in self.shared.items():
                rows.append((2, t, 0, len(m.x), None, (m.x - shared[t].x).astype("<f4").tobytes(), (m.acc - shared[t].acc).astype("<f4").tobytes(), None, None, None))
            rows.append((3, None, None, self.no, None, None, None, None, None, [float(getattr(self.count, k)) for k in _STATS[:6]] + [float(self.holder.loads), float(self.holder.stores), time.time() - self.began, rss]))
            return pa.RecordBatch.from_arrays([pa.array(col, f.type) for col, f in zip(zip(*rows, strict=True), arrow, strict=True)], schema=arrow)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now: Chain | None = None
        with RssSampler() as memory:
            for batch in batches:
                place = batch.column("chain").to_numpy().astype(np.int64) * 1_000_000 + batch.column("seq").to_numpy()
                cuts = np.flatnonzero(np.concatenate([[True], place[1:] != place[:-1], [True]]))
                for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
                    chain, seq = divmod(int(place[lo]), 1_000_000)
                    if now is None or now.no != chain:
                        if now is not None:
                            yield now.close(memory.peak)
                        now = Chain(chain)
                    now.go_to(seq)
                    piece = batch.slice(lo, hi - lo)
                    ps, pd, r, s, d, w = (piece.column(c).to_numpy(zero_copy_only=False) for c in ("p_src", "p_dst", "rel", "src_off", "dst_off", "weight"))
                    first = int((ps < 0).sum())  # the row that only marks a unit
                    if first == len(ps):
                        continue
                    ps, pd, r, s, d, w = (x[first:] for x in (ps, pd, r, s, d, w))
                    code = (ps.astype(np.int64) << 40) + (pd.astype(np.int64) << 20) + r
                    ends = np.flatnonzero(np.concatenate([[True], code[1:] != code[:-1], [True]]))
                    for a, b in zip(ends[:-1], ends[1:], strict=True):
                        key = (int(ps[a]), int(pd[a]), int(r[a]))
                        for other in [k for k in now.pending if k != key]:
                            now.flush(other, True)
                        now.pending.setdefault(key, []).append((s[a:b].astype(np.int64), d[a:b].astype(np.int64), w[a:b]))
                        now.flush(key, False)
            if now is not None:
                yield now.close(memory.peak)

    return run


def job_rows(prep: Prepared, plan: list[list[Unit]], sub: tuple[int, int] = (0, 1), epoch: int = 0) -> DataFrame:
    """The edges of some chains of units, each chain in a partition, its units in order; reads their folders only.

    Inside a bucket and relation every epoch has an order of its own, so an edge meets other negatives each time.
    """
    spark = prep.entities.sparkSession
    places = [(prep.unit_no(u), c, s) for c, chain in enumerate(plan) for s, u in enumerate(chain)]
    table = spark.createDataFrame(places, "unit int, chain int, seq int")
    edges = prep.edges.where(F.col("unit").isin([p[0] for p in places]))
    if sub[1] > 1:
        edges = edges.where(F.pmod("h", F.lit(sub[1])) == sub[0])
    rows = edges.join(F.broadcast(table), "unit").select("chain", "seq", "p_src", "p_dst", "rel", (F.xxhash64("h", F.lit(epoch)) if epoch else F.col("h")).alias("h"), "src_off", "dst_off", "weight")
    # a row per unit, so that chains without edges still hand on their parts
    none = [F.lit(-1).alias("p_src"), F.lit(-1).alias("p_dst"), F.lit(-1).alias("rel"), F.lit(-1).cast("long").alias("h"), F.lit(0).alias("src_off"), F.lit(0).alias("dst_off"), F.lit(0).cast("float").alias("weight")]
    rows = rows.unionByName(table.select("chain", "seq", *none))
    # a partition has one chain, whose places are in order of a number that decides nearly all comparisons of the sort
    bucket = F.when(F.col("p_src") < 0, 0).when(F.col("p_src") <= F.col("p_dst"), 1).otherwise(2)
    few = len(prep.spec.relations) < 1 << 16
    place = F.lit(0).cast("long")
    for value, bits in ((F.col("seq"), 20), (bucket, 2), *(((F.col("rel") + 1, 17), (F.shiftright("h", 40) + (1 << 23), 24)) if few else ())):
        place = F.shiftleft(place, bits) + value
    return rows.withColumn("place", place).repartitionById(len(plan), F.col("chain")).sortWithinPartitions("place", "seq", "p_src", "p_dst", "rel", "h", "src_off", "dst_off").drop("place", "h")


def _job(model: Model, plan: list[list[Unit]], stamp: tuple[int, int], sub: tuple[int, int], merge: str) -> dict:
    """Trains chains on disjoint parts, one task each, and takes over what they return."""
    prep, spec = model.prepared, model.spec
    spark = prep.entities.sparkSession
    folder = scratch(spark, f"parts-{stamp[0]}-{stamp[1]}")
    began = time.time()
    found = job_rows(prep, plan, sub, stamp[0]).mapInArrow(_trainer(spec, prep.sizes, plan, model.where, folder, model.params, model.shared, stamp, prep.bags), _OUT).collect()
    stats = dict.fromkeys(_STATS, 0.0) | {"round_seconds": time.time() - began}
    changes: dict[tuple, list] = {}
    gone = []
    for row in found:
        if row["kind"] == 0:
            gone.append(model.where.get((row["etype"], row["part"])))
            model.where[row["etype"], row["part"]] = row["path"]
        elif row["kind"] == 3:
            for k, v in zip(_STATS, row["stats"], strict=True):
                stats[k] = max(stats[k], v) if k in ("rss_mb", "seconds") else stats[k] + v
        else:
            key = (1, row["rel"], tuple(row["name"].split("/"))) if row["kind"] == 1 else (2, row["etype"])
            changes.setdefault(key, []).append((np.frombuffer(row["vec"], "<f4"), np.frombuffer(row["acc"], "<f4")))
    for key, parts in sorted(changes.items(), key=str):
        dx, da = merged(parts, merge)
        target = model.params[key[1]] if key[0] == 1 else model.shared[key[1]]
        x, acc = (target.theta[key[2]], target.acc[key[2]]) if key[0] == 1 else (target.x, target.acc)
        x += dx.reshape(x.shape)
        acc += da.reshape(acc.shape)
    for path in gone:
        if path and path not in model.kept:
            remove(spark, path)
    return stats


def merged(parts: list[tuple[np.ndarray, np.ndarray]], how: str) -> tuple[np.ndarray, np.ndarray]:
    """One change out of the chains' changes (of values, of squared gradients).

    ``sum`` adds them; ``mean`` takes their mean; ``adagrad`` adds the squared gradients and shrinks each
    chain's step by the root of its own over all of them, as if all had shared one optimiser.
    """
    dx, da = (np.sum([p[i] for p in parts], axis=0) for i in (0, 1))
    if how == "sum":
        return dx, da
    if how == "mean":
        return dx / len(parts), da / len(parts)
    if how == "adagrad":
        if dx.size == da.size:
            shrink = [np.sqrt(np.divide(p[1], da, out=np.zeros_like(da), where=da > 0)) for p in parts]
        else:  # one number a row
            width = dx.size // max(1, da.size)
            shrink = [np.repeat(np.sqrt(np.divide(p[1], da, out=np.zeros_like(da), where=da > 0)), width) for p in parts]
        return np.sum([p[0] * f for p, f in zip(parts, shrink, strict=True)], axis=0), da
    raise ValueError(f"unknown merge {how!r}")


def new_model(prepared: Prepared) -> Model:
    spec = prepared.spec
    model = Model(prepared, params=[Params.start(r, spec.dim, spec.seed + i) for i, r in enumerate(spec.relations)])
    for i, t in enumerate(spec.types):
        if not t.partitioned:
            n = len(prepared.bags[i][0]) if t.featurised else prepared.sizes.get((i, 0), 0)
            model.shared[i] = kernels.start_matrix(spec, i, 0, n)
    if sum(m.x.size for m in model.shared.values()) + spec.n_shared() > SHARED_LIMIT:
        raise ValueError("too many shared parameters; partition the large types")
    return model


def from_vectors(edges: DataFrame, spec: GraphSpec, vectors: DataFrame, parts: int = 1) -> Model:
    """A model of given vectors (etype, key, vec) for the nodes of a graph; nodes without one keep their starting vector."""
    prep = prepare(edges, spec, parts)
    model = new_model(prep)
    spark = prep.entities.sparkSession
    folder = scratch(spark, "parts-given")
    rows = prep.entities.join(vectors.select("etype", "key", F.col("vec").cast("array<float>").alias("vec")), ["etype", "key"]).select("etype", "part", "offset", "vec")
    whole = [i for i, t in enumerate(spec.types) if not t.partitioned]
    for r in rows.where(F.col("etype").isin(whole)).toLocalIterator() if whole else ():
        model.shared[r["etype"]].x[r["offset"]] = r["vec"]
    sizes, dim = prep.sizes, spec.dim

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, m = None, None

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_pydict({"etype": pa.array([now[0]], pa.int32()), "part": pa.array([now[1]], pa.int32()), "path": [store_part(folder, *now, m)]})

        for b in batches:
            etype, part, offset = (b.column(c).to_numpy() for c in ("etype", "part", "offset"))
            x = b.column("vec").flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, dim)
            edge = np.flatnonzero(np.concatenate([[True], (etype[1:] != etype[:-1]) | (part[1:] != part[:-1]), [True]])) if b.num_rows else []
            for lo, hi in zip(edge[:-1], edge[1:], strict=True):
                key = (int(etype[lo]), int(part[lo]))
                if key != now:
                    if now is not None:
                        yield out()
                    now, m = key, kernels.start_matrix(spec, *key, sizes[key])
                m.x[offset[lo:hi]] = x[lo:hi]
        if now is not None:
            yield out()

    cut = rows.where(~F.col("etype").isin(whole)) if whole else rows
    written = cut.repartition("etype", "part").sortWithinPartitions("etype", "part", "offset").mapInArrow(write, "etype int, part int, path string")
    model.where = {(r["etype"], r["part"]): r["path"] for r in written.collect()}
    return model


def fit(prepared: Prepared, epochs: int = 1, machines: int = 1, bucket_order: str = "inside_out", policy: str = "tournament", sub_epochs: int = 1, merge: str = "sum", model: Model | None = None, after_epoch=None, checkpoint: str | None = None, stop_after: int | None = None, sync_every: int | None = None) -> Model:
    """Trains; with one machine an epoch is one chain in the given bucket order, else rounds of up to ``machines`` chains.

    ``after_epoch(model)`` may return measures for the log; ``checkpoint`` names a folder that gets a
    manifest after every epoch; ``stop_after`` ends early after so many jobs (for tests of resuming);
    ``sync_every`` cuts a single machine's chain into jobs of so many units, between which shared parameters are taken over.
    """
    model = model or new_model(prepared)
    p, done = prepared.parts, 0
    for epoch in range(model.epoch, epochs):
        began, total = time.time(), dict.fromkeys((*_STATS, "round_seconds"), 0.0)
        jobs = 0
        for sub in range(sub_epochs):
            first = epoch == 0 and sub == 0
            if machines == 1:
                line = units_in_order(order(bucket_order, p, prepared.spec.seed))
                plan = [[line[i : i + (sync_every or len(line))]] for i in range(0, len(line), sync_every or len(line))]
            else:
                plan = chains(p, machines, policy, first)
            for r, lines in enumerate(plan):
                stats = _job(model, lines, (epoch, sub * 1000 + r), (sub, sub_epochs), merge)
                for k, v in stats.items():
                    total[k] = max(total[k], v) if k == "rss_mb" else total[k] + v
                done += 1
                if stop_after is not None and done >= stop_after:
                    return model
            jobs += len(plan)
        model.epoch = epoch + 1
        entry = {"epoch": epoch + 1, "seconds": time.time() - began, "rounds": jobs, "swaps": int(total["loads"])} | {k: total[k] for k in total if k != "seconds"} | {"train_seconds": total["seconds"]}
        if after_epoch is not None:
            entry |= after_epoch(model) or {}
        model.log.append(entry)
        if checkpoint:
            save(model, checkpoint)
    return model


def save(model: Model, folder: str) -> None:
    """Copies the parts to the folder, then writes the manifest that makes the version valid."""
    spark = model.prepared.entities.sparkSession
    version = f"{folder}/version={model.epoch}"
    sizes, spec, kept = model.prepared.sizes, model.spec, {}
    if model.where:
        files = spark.createDataFrame([(t, p, at, sizes.get((t, p), 0)) for (t, p), at in model.where.items()], "etype int, part int, path string, n int")

        def copy(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for row in b.to_pylist():
                    at = store_part(f"{version}/parts", row["etype"], row["part"], load_part(row["path"], row["n"], spec.dim))
                    yield pa.RecordBatch.from_pydict({"etype": pa.array([row["etype"]], pa.int32()), "part": pa.array([row["part"]], pa.int32()), "path": [at]})

        kept = {(r["etype"], r["part"]): r["path"] for r in files.repartition(len(model.where), "etype", "part").mapInArrow(copy, "etype int, part int, path string").collect()}
    small = {
        "epoch": model.epoch,
        "params": [[["/".join(k), list(v.shape), v.ravel().tolist(), p.acc[k].ravel().tolist()] for k, v in p.theta.items()] for p in model.params],
        "shared": {str(t): [m.x.tolist(), m.acc.tolist()] for t, m in model.shared.items()},
        "parts": [[t, p, at] for (t, p), at in sorted(kept.items())],
    }
    spark.createDataFrame([(json.dumps(small),)], "value string").coalesce(1).write.mode("overwrite").text(f"{version}/manifest")


def resume(prepared: Prepared, folder: str, epoch: int) -> Model:
    """The model of a checkpoint; training goes on from its files and never changes them."""
    spark = prepared.entities.sparkSession
    small = json.loads(spark.read.text(f"{folder}/version={epoch}/manifest", wholetext=True).first()["value"])
    model = new_model(prepared)
    model.epoch = small["epoch"]
    for p, rows in zip(model.params, small["params"], strict=True):
        for name, shape, theta, acc in rows:
            key = tuple(name.split("/"))
            p.theta[key] = np.array(theta, np.float32).reshape(shape)
            p.acc[key] = np.array(acc, np.float32).reshape(shape)
    for t, (x, acc) in small["shared"].items():
        model.shared[int(t)] = Matrix(np.array(x, np.float32), np.array(acc, np.float32))
    model.where = {(t, p): at for t, p, at in small["parts"]}
    model.kept = set(model.where.values())
    return model

"""Link-prediction evaluation: candidates, ranks (raw and filtered), and the measures over them."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import h32
from ..session import HASHED_BYTES, is_small, key_bytes, stored
from . import relops
from .spec import GraphSpec
from .train_block import Model, Prepared, load_part

#: A shared candidate pool larger than this is not broadcast; ``rank_all`` counts by blocks instead.
POOL_BYTES = 256 << 20
#: ``rank_all``: bytes of candidate vectors, and number of edges, that meet in one task.
BLOCK_BYTES, BLOCK_EDGES = 8 << 20, 16384
#: Bytes of scores that a task holds at a time.
SCORE_BYTES = 16 << 20


def candidate_keys(train: DataFrame, side: str, k: int, mode: str = "data", seed: int = 1, alpha: float = 0.5, restrict_type: bool = True) -> DataFrame:
    """Up to k candidates per relation (rel, key): endpoints of random training edges (``data``, so by
    prevalence, repeats included), random distinct nodes (``uniform``), a mixture, or ``all`` nodes; without ``restrict_type`` the nodes of both sides."""
    if mode == "data":
        rows = train.select("rel", F.col(side).alias("key"), h32(seed, "cand", side, F.col("rel"), F.col("src"), F.col("dst")).alias("_h"))
        return first_by_hash(rows, k)
    nodes = train.select("rel", F.col(side).alias("key")).distinct()
    if not restrict_type:
        nodes = nodes.union(train.select("rel", "dst" if side == "src" else "src")).distinct()
    if mode == "all":
        return nodes
    if mode == "uniform":
        return first_by_hash(nodes.withColumn("_h", h32(seed, "cand", side, F.col("rel"), F.col("key"))), k)
    if mode == "mixed":
        a = round(alpha * k)
        return candidate_keys(train, side, a, "data", seed).union(candidate_keys(train, side, k - a, "uniform", seed))
    raise ValueError(mode)


def first_by_hash(rows: DataFrame, k: int) -> DataFrame:
    """rel, key of the k rows of each relation with the smallest hash ``_h`` (32 bits), ties by key.

    A count per hash range, combined before its shuffle, tells where the k-th row lies; only rows up to
    there are sorted, so a relation that holds all edges sends about k of them to its task.
    """
    from pyspark.sql import Window

    at = F.shiftright("_h", 12)
    ranges = rows.groupBy("rel", at.alias("at")).agg(F.count(F.lit(1)).alias("n"))
    reached = ranges.withColumn("so_far", F.sum("n").over(Window.partitionBy("rel").orderBy("at")))
    cut = reached.where(F.col("so_far") >= k).groupBy("rel").agg(F.min("at").alias("cut"))  # one row a relation
    near = rows.join(F.broadcast(cut), "rel", "left").where(F.col("cut").isNull() | (at <= F.col("cut")))
    return near.withColumn("_n", F.row_number().over(Window.partitionBy("rel").orderBy("_h", "key"))).where(F.col("_n") <= k).select("rel", "key")


def _with_types(model: Model, keys: DataFrame, side: str) -> DataFrame:
    """rel, etype, key, times of the candidates."""
    spec = model.spec
    types = model.prepared.entities.sparkSession.createDataFrame([(r.name, spec.type_no(r.src_type if side == "src" else r.dst_type)) for r in spec.relations], "rel string, etype int")
    return keys.join(F.broadcast(types), "rel").groupBy("rel", "etype", "key").agg(F.count(F.lit(1)).alias("times"))


def _pool(model: Model, rows: DataFrame, vec: DataFrame | None = None) -> dict[str, tuple[np.ndarray, np.ndarray]]:
    """Candidate keys and vectors per relation, on the driver: few enough for it, and packed."""
    t = rows.join(model.vectors() if vec is None else vec, ["etype", "key"]).orderBy("rel", "key").select("rel", "key", "times", "vec").toArrow().combine_chunks()
    times, rels = t.column("times").to_numpy(), np.array(t.column("rel").to_pylist(), object)
    keys, x = np.array(t.column("key").to_pylist(), object), _floats(t.column("vec"), model.spec.dim)
    return {r: (np.repeat(keys[at], times[at]), np.repeat(x[at], times[at], axis=0)) for r in sorted(set(rels)) for at in [np.flatnonzero(rels == r)]}


def _floats(column, dim: int) -> np.ndarray:
    flat = column.flatten() if isinstance(column, pa.Array) else pa.chunked_array([c.flatten() for c in column.chunks], pa.float32())
    return np.asarray(flat.to_numpy(), np.float32).reshape(-1, dim)


_COUNTS = ("better", "ties", "raw_better", "raw_ties")


def _ranks_columns(raw: bool) -> str:
    return ", ".join(["rel string", "src string", "dst string", *[f"{c} long" for c in _COUNTS[: 4 if raw else 2]]])


def _ranks_schema(raw: bool) -> pa.Schema:
    return pa.schema([(c, pa.string()) for c in ("rel", "src", "dst")] + [(c, pa.int64()) for c in _COUNTS[: 4 if raw else 2]])


def rank_all(model: Model, part: DataFrame, candidates: DataFrame, size: int, side: str, exact: bool = False, raw: bool = False) -> DataFrame:
    """rel, src, dst, better, ties against any number of candidates: each block of edges meets each block
    of its relation's candidates in a task, and an edge's counts are summed over the blocks.

    ``part`` has the edges with their vectors, ``candidates`` rel, etype, key, times (``size`` rows).
    """
    spec, params = model.spec, model.params
    block = max(1, BLOCK_BYTES // (4 * spec.dim))
    cut = max(1, -(-size // block))
    edges = part.groupBy("rel", "rel_no", "src", "dst").agg(F.count(F.lit(1)).alias("copies"), *[F.first(c).alias(c) for c in ("sv", "dv", "seen", "drop")])
    edge_cut = max(1, -(-edges.count() // BLOCK_EDGES))
    number = lambda n, *key: F.pmod(F.xxhash64(*key), F.lit(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    left = edges.withColumn("eb", number(edge_cut, "src", "dst")).withColumn("cb", every(cut))
    right = candidates.join(model.vectors(), ["etype", "key"]).select(F.col("rel").alias("of"), "key", "times", "vec", number(cut, "key").alias("c")).withColumn("e", every(edge_cut))

    def run(x: pa.Table, y: pa.Table) -> pa.Table:
        pool = {}
        if y.num_rows:
            times = y.column("times").to_numpy()
            pool[y.column("of")[0].as_py()] = (np.repeat(np.array(y.column("key").to_pylist(), object), times), np.repeat(_floats(y.column("vec"), spec.dim), times, axis=0))
        cut = x.to_batches(max_chunksize=4096)
        ranked = [pa.Table.from_batches([b]).append_column("copies", pa.array(c.column("copies").to_pylist(), pa.int64())) for c, b in zip(cut, _ranker(spec, params, pool, side, exact, raw)(iter(cut)), strict=True)]
        schema = _ranks_schema(raw).append(pa.field("copies", pa.int64()))
        return pa.concat_tables(ranked).cast(schema) if ranked else schema.empty_table()

    counted = left.groupBy("rel", "eb", "cb").cogroup(right.groupBy("of", "e", "c")).applyInArrow(run, f"{_ranks_columns(raw)}, copies long")
    summed = counted.groupBy("rel", "src", "dst").agg(*[F.sum(c).alias(c) for c in _COUNTS[: 4 if raw else 2]], F.first("copies").alias("copies"))
    return summed.withColumn("copies", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).drop("copies")


def rank_edges(model: Model, test: DataFrame, train: DataFrame, k: int = 500, mode: str = "data", sides: tuple[str, ...] = ("src", "dst"), filtered: bool = False, known: DataFrame | None = None, seed: int = 1, exact: bool = False, pool_bytes: int | None = None, drawn: dict[str, DataFrame] | None = None, where: DataFrame | dict[str, DataFrame] | None = None, drops: dict[str, DataFrame] | None = None, raw: bool = False) -> DataFrame:
    """rel, src, dst, side, better, ties of every tested edge and side.

    A candidate equal to the true endpoint does not count; ``filtered`` also leaves out those that
    form an edge of ``known``. Vectors are joined to the edges by key; the pool of k candidates per
    relation goes to the tasks, or meets the edges by blocks (``rank_all``) above ``POOL_BYTES``. An edge with an endpoint that training has not seen is kept: the model
    cannot tell its candidates apart, so all of them tie. ``exact`` scores in double precision. ``drawn`` has
    the candidates of each side (``candidate_keys``) and ``where`` the edges' places (``placed``, or for filtered ranks ``placed_with`` of each side) and ``drops`` what is left out of each side (``known_candidates``) if they are at hand.
    ``raw``: filtered ranks come with the raw ones of the same scores (raw_better, raw_ties). Where vectors are few enough, tasks read
    them from the model's files, and neither the driver nor a shuffle carries them.
    """
    spec = model.spec
    pool_bytes = POOL_BYTES if pool_bytes is None else pool_bytes
    vec = model.vectors()
    held = not model.shared and is_small(*model.prepared.counted, 4 * spec.dim)
    edges = _with_numbers(spec, test)
    if held and where is None:
        where = placed(model.prepared, test)
    rows = edges.join(vec.select(F.col("etype").alias("_st"), F.col("key").alias("src"), F.col("vec").alias("sv")), ["_st", "src"], "left").join(vec.select(F.col("etype").alias("_dt"), F.col("key").alias("dst"), F.col("vec").alias("dv")), ["_dt", "dst"], "left")
    none = F.array_repeat(F.lit(0.0).cast("float"), spec.dim)
    rows = rows.withColumn("seen", F.col("sv").isNotNull() & F.col("dv").isNotNull()).withColumn("sv", F.coalesce("sv", none)).withColumn("dv", F.coalesce("dv", none))
    out = None
    for side in sides:
        kept = "dst" if side == "src" else "src"
        keys = drawn[side] if drawn else stored(candidate_keys(train, side, k, mode, seed), "candidates")
        candidates = _with_types(model, keys, side)
        size = candidates.agg(F.count(F.lit(1)).alias("rows"), F.sum("times").alias("all")).first()
        pooled = (size["all"] or 0) * spec.dim * 4 <= pool_bytes
        part = (where[side] if isinstance(where, dict) else where) if held and pooled else rows
        if filtered and "drop" in part.columns:
            pass
        elif filtered:
            drop = drops[side] if drops else known_candidates(test, known if known is not None else train, keys, side)
            part = part.join(drop, ["rel", kept], "left")
        else:
            part = part.withColumn("drop", F.lit(None).cast("array<string>"))
        if not pooled:
            ranked = rank_all(model, part, candidates, size["rows"], side, exact, raw)
        else:
            pool = _pool(model, candidates, vec)
            ranker, columns = _ranker(spec, model.params, pool, side, exact, raw), ("sv", "dv", "seen")
            if held:  # pooled, too
                ranker, columns = _from_parts(model, ranker), _PLACES
            ranked = part.select("rel", "rel_no", "src", "dst", "drop", *columns).mapInArrow(ranker, _ranks_columns(raw))
        ranked = ranked.withColumn("side", F.lit(side))
        out = ranked if out is None else out.unionByName(ranked)
    return out.select("rel", "src", "dst", "side", *_COUNTS[: 4 if raw else 2])


def known_candidates(test: DataFrame, known: DataFrame, keys: DataFrame, side: str) -> DataFrame:
    """rel, the endpoint that stays, and ``drop``: the candidates that form a known edge with it. The same for all models of a graph."""
    kept = "dst" if side == "src" else "src"
    pairs = known.select("rel", kept, F.col(side).alias("_c")).join(keys.select("rel", F.col("key").alias("_c")).distinct(), ["rel", "_c"], "left_semi")
    return pairs.join(test.select("rel", kept).distinct(), ["rel", kept], "left_semi").groupBy("rel", kept).agg(F.collect_set("_c").alias("drop"))


_PLACES = ("_st", "_sp", "_so", "_dt", "_dp", "_do")


def _with_numbers(spec: GraphSpec, test: DataFrame) -> DataFrame:
    types = [(r.name, i, spec.type_no(r.src_type), spec.type_no(r.dst_type)) for i, r in enumerate(spec.relations)]
    rel = test.sparkSession.createDataFrame(types, "rel string, rel_no int, _st int, _dt int")
    return test.select("rel", "src", "dst").join(F.broadcast(rel), "rel")


def placed(prepared: Prepared, test: DataFrame) -> DataFrame:
    """Edges with type, part and offset of their endpoints, stored; null where training has not seen one. The same for all models of a preparation."""
    edges, small = _with_numbers(prepared.spec, test), is_small(*prepared.counted, most=HASHED_BYTES)
    for kind, part, offset, key in (("_st", "_sp", "_so", "src"), ("_dt", "_dp", "_do", "dst")):
        at = prepared.entities.select(F.col("etype").alias(kind), F.col("key").alias(key), F.col("part").alias(part), F.col("offset").alias(offset))
        edges = edges.join(F.broadcast(at) if small else at, [kind, key], "left")
    return stored(edges, "placed-edges")


def placed_with(where: DataFrame, drops: dict[str, DataFrame]) -> dict[str, DataFrame]:
    """Of each side, the edges of ``placed`` with what filtered ranks leave out, dealt evenly to twice as many tasks as run at a time.

    Made once for all models: their ranks then need no join, which would put a few large groups in a few tasks."""
    out, n = {}, 2 * where.sparkSession.sparkContext.defaultParallelism
    for side, drop in drops.items():
        kept = "dst" if side == "src" else "src"
        out[side] = stored(where.join(drop, ["rel", kept], "left").repartition(n, "rel", "src", "dst").sortWithinPartitions("rel", kept), "placed-known")
    return out


def _from_parts(model: Model, ranker):
    """The ranker on edges with places: vectors come from the files of the model's parts, each read once by a task."""
    where, sizes, dim = dict(model.where), model.prepared.sizes, model.spec.dim

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts: dict = {}

        def vectors(kind, part, offset) -> tuple[np.ndarray, np.ndarray]:
            x, seen = np.zeros((len(kind), dim), np.float32), np.zeros(len(kind), bool)
            for at in sorted(set(zip(kind.tolist(), part.tolist(), strict=True)) & set(where)):
                if at not in parts:
                    parts[at] = load_part(where[at], sizes[at], dim, acc=False).x
                rows = np.flatnonzero((kind == at[0]) & (part == at[1]))
                x[rows], seen[rows] = parts[at][offset[rows]], True
            return x, seen

        def with_vectors() -> Iterator[pa.RecordBatch]:
            for b in batches:
                places = [b.column(c).fill_null(-1).to_numpy(zero_copy_only=False) for c in _PLACES]
                (sv, ss), (dv, ds) = vectors(*places[:3]), vectors(*places[3:])
                lists = (pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, dim, dtype=np.int32)), pa.array(x.ravel())) for x in (sv, dv))
                names = ("rel", "rel_no", "src", "dst", "drop")
                yield pa.RecordBatch.from_arrays([*(b.column(c) for c in names), *lists, pa.array(ss & ds)], names=[*names, "sv", "dv", "seen"])

        return ranker(with_vectors())

    return run


def _ranker(spec: GraphSpec, params, pool, side: str, exact: bool = False, raw: bool = False):
    arrow = _ranks_schema(raw)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ready: dict = {}
        kind = np.float64 if exact else np.float32
        for b in batches:
            cols = {c: b.column(c).to_pylist() for c in ("rel", "rel_no", "src", "dst", "seen", "drop")}
            sv, dv = (b.column(c).flatten().to_numpy(zero_copy_only=False).astype(kind).reshape(b.num_rows, -1) for c in ("sv", "dv"))
            better, ties, raw_better, raw_ties = (np.zeros(b.num_rows, np.int64) for _ in range(4))
            of: dict = {}
            for i, r in enumerate(cols["rel"]):
                of.setdefault(r, []).append(i)
            for r, at in of.items():
                if r not in pool:
                    continue
                at = np.array(at)
                no = cols["rel_no"][at[0]]
                rel, th = spec.relations[no], params[no].theta
                which = side if rel.reciprocal else "both"
                lhs, rhs = th.get((which, "lhs")), th.get((which, "rhs"))
                keys, x = pool[r]
                x = x.astype(kind)
                keep_src = side == "dst"
                kept, true = (sv[at], dv[at]) if keep_src else (dv[at], sv[at])
                op_k, t_k = (rel.lhs_op, lhs) if keep_src else (rel.rhs_op, rhs)
                op_c, t_c = ("identity", None) if rel.reciprocal else ((rel.rhs_op, rhs) if keep_src else (rel.lhs_op, lhs))
                if r not in ready:
                    c = relops.forward(op_c, x, t_c)
                    ready[r] = (relops.normalise(c)[0] if spec.sim == "cos" else c, {})
                    index: dict = {}
                    group = np.array([index.setdefault(key, len(index)) for key in keys], np.int64)
                    ready[r] = (ready[r][0], index, np.argsort(group, kind="stable"), np.concatenate([[0], np.cumsum(np.bincount(group, minlength=len(index)))]))
                c, index, members, ends = ready[r]
                a, t = relops.forward(op_k, kept, t_k), relops.forward(op_c, true, t_c)
                if spec.sim == "cos":
                    a, t = relops.normalise(a)[0], relops.normalise(t)[0]
                pos = (a * t).sum(1)
                # candidates that don't count for an edge: its own endpoint and those of ``drop``, as pairs of (edge, group of equal keys)
                own = cols["dst" if keep_src else "src"]
                drops = [(e, index[key]) for e, row in enumerate(at) for key in {own[row], *(cols["drop"][row] or ())} if key in index]
                gone_e, gone_g = (np.array(x, np.int64) for x in zip(*drops, strict=True)) if drops else (np.zeros(0, np.int64),) * 2
                # edges of the same kept endpoint share a row of scores; a piece of such rows, and of edges, is held at a time
                rows: dict = {}
                row_of = np.array([rows.setdefault(cols["src" if keep_src else "dst"][row], len(rows)) for row in at])
                turn = np.argsort(row_of, kind="stable")
                first = turn[np.searchsorted(row_of[turn], np.arange(len(rows)))]
                place = np.empty(len(turn), np.int64)
                place[turn] = np.arange(len(turn))
                by = np.argsort(place[gone_e], kind="stable")
                gone_p, gone_g = place[gone_e][by], gone_g[by]
                mine = np.array([index.get(key, -1) for key in (own[row] for row in at)], np.int64)
                step = max(1, SCORE_BYTES // (c.itemsize * max(1, len(c))))
                off = 1e-6 * np.maximum(1, np.abs(pos))
                seen = np.array(cols["seen"], bool)[at]
                for base in range(0, len(rows), step):
                    scores = a[first[base : base + step]] @ c.T
                    lo, end = np.searchsorted(row_of[turn], (base, base + step))
                    for lo in range(lo, end, step):
                        e = turn[lo : min(lo + step, end)]
                        s = scores[row_of[e] - base]
                        above, near = ((pos + off)[e], (pos - off)[e])
                        x, y = np.searchsorted(gone_p, (lo, lo + len(e)))
                        size = ends[gone_g[x:y] + 1] - ends[gone_g[x:y]]
                        who = np.repeat(gone_p[x:y] - lo, size)
                        which_c = members[np.repeat(ends[gone_g[x:y]] - np.cumsum(size) + size, size) + np.arange(len(who))]
                        out = s[who, which_c]
                        less = lambda hit: np.bincount(who, hit, len(e)).astype(np.int64)  # noqa: B023, E731
                        over, reach = np.count_nonzero(s > above[:, None], axis=1), np.count_nonzero(s >= near[:, None], axis=1)
                        self_only = np.repeat(gone_g[x:y] == mine[e][gone_p[x:y] - lo], size) if raw else True  # what raw ranks leave out, too
                        for counts, tied, which in ((better, ties, True), (raw_better, raw_ties, self_only))[: 2 if raw else 1]:
                            up = over - less((out > above[who]) & which)
                            counts[at[e]] = np.where(seen[e], up, 0)
                            tied[at[e]] = np.where(seen[e], reach - less((out >= near[who]) & which) - up, len(c) - less(np.ones(len(who)) * which))
            yield pa.RecordBatch.from_arrays([pa.array(cols["rel"]), pa.array(cols["src"]), pa.array(cols["dst"]), *map(pa.array, (better, ties, raw_better, raw_ties)[: 4 if raw else 2])], schema=arrow)

    return run


def score_edges(model: Model, edges: DataFrame) -> DataFrame:
    """rel, src, dst, score of given edges under a model; null where an endpoint has no vector."""
    spec, params = model.spec, model.params
    types = edges.sparkSession.createDataFrame([(r.name, i, spec.type_no(r.src_type), spec.type_no(r.dst_type)) for i, r in enumerate(spec.relations)], "rel string, rel_no int, _st int, _dt int")
    vec = model.vectors()
    rows = edges.select("rel", "src", "dst").join(F.broadcast(types), "rel")
    rows = rows.join(vec.select(F.col("etype").alias("_st"), F.col("key").alias("src"), F.col("vec").alias("sv")), ["_st", "src"], "left").join(vec.select(F.col("etype").alias("_dt"), F.col("key").alias("dst"), F.col("vec").alias("dv")), ["_dt", "dst"], "left")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            no = b.column("rel_no").to_numpy()
            held = b.column("sv").is_valid().to_numpy(zero_copy_only=False) & b.column("dv").is_valid().to_numpy(zero_copy_only=False)
            score = np.zeros(b.num_rows)
            for r in np.unique(no[held]):
                at = np.flatnonzero(held & (no == r))
                sv, dv = (b.column(c).take(pa.array(at)).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(at), -1) for c in ("sv", "dv"))
                rel, th = spec.relations[r], params[r].theta
                which = "dst" if rel.reciprocal else "both"
                left = relops.forward(rel.lhs_op, sv, th.get((which, "lhs")))
                right = dv if rel.reciprocal else relops.forward(rel.rhs_op, dv, th.get((which, "rhs")))
                score[at] = relops.pair_scores(spec.sim, left, right)
            yield pa.RecordBatch.from_arrays([b.column("rel"), b.column("src"), b.column("dst"), pa.array(score, mask=~held)], names=["rel", "src", "dst", "score"])

    return rows.select("rel", "rel_no", "src", "dst", "sv", "dv").mapInArrow(run, "rel string, src string, dst string, score double")


def with_rank(ranks: DataFrame, ties: str = "mean") -> DataFrame:
    extra = {"optimistic": F.lit(0.0), "pessimistic": F.col("ties").cast("double"), "mean": F.col("ties") / 2}[ties]
    return ranks.withColumn("rank", 1 + F.col("better") + extra)


def metrics(ranks: DataFrame, by: tuple[str, ...] = (), ties: str = "mean") -> DataFrame:
    """n, mrr, mr, hits1, hits10 over all rows, or rolled up over the given columns."""
    r = with_rank(ranks, ties)
    aggs = [F.count(F.lit(1)).alias("n"), F.avg(1 / F.col("rank")).alias("mrr"), F.avg("rank").alias("mr"), F.avg((F.col("rank") <= 1).cast("double")).alias("hits1"), F.avg((F.col("rank") <= 10).cast("double")).alias("hits10")]
    return (r.rollup(*by) if by else r.groupBy()).agg(*aggs)


def evaluate(model: Model, test: DataFrame, train: DataFrame, **kind) -> dict:
    row = metrics(rank_edges(model, test, train, **kind)).first()
    return {k: row[k] for k in ("n", "mrr", "mr", "hits1", "hits10")}


def evaluate_both(model: Model, test: DataFrame, train: DataFrame, **kind) -> list[dict]:
    """Measures of the raw and of the filtered ranks, of the same scores."""
    ranks = rank_edges(model, test, train, filtered=True, raw=True, **kind)
    each = F.explode(F.array(*[F.struct(F.lit(name).alias("kind"), F.col(a).alias("better"), F.col(b).alias("ties")) for name, a, b in (("raw", "raw_better", "raw_ties"), ("filtered", "better", "ties"))]))
    found = {row["kind"]: row for row in metrics(ranks.select(each.alias("x")).select("x.*"), ("kind",)).collect() if row["kind"]}
    none = dict.fromkeys(("mrr", "mr", "hits1", "hits10")) | {"n": 0}
    return [{k: found.get(name, none)[k] for k in ("n", "mrr", "mr", "hits1", "hits10")} for name in ("raw", "filtered")]


def random_mrr(k: int) -> float:
    """Expected reciprocal rank of a random score among the true endpoint and k candidates."""
    return sum(1 / i for i in range(1, k + 2)) / (k + 1)


def _pools(candidates: DataFrame) -> dict[str, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Keys, times and, if the candidates have one, ``deg`` of each relation's candidates, on the driver."""
    t = candidates.toArrow()
    rels = np.array(t.column("rel").to_pylist(), object)
    keys, times = np.array(t.column("key").to_pylist(), object), t.column("times").to_numpy()
    deg = t.column("deg").to_numpy() if "deg" in t.column_names else np.zeros(len(keys))
    return {r: (keys[at], times[at], deg[at]) for r in sorted(set(rels)) for at in [np.flatnonzero(rels == r)]}


class _Counted:
    """Candidates sorted by score, so that how many are better than an edge, or tie with it, are two searches."""

    def __init__(self, keys: np.ndarray, times: np.ndarray, score: np.ndarray):
        by = np.argsort(score, kind="stable")
        self.score, self.so_far = score[by], np.concatenate([[0], np.cumsum(times[by])])
        self.of = {key: (x, n) for key, x, n in zip(keys, score, times, strict=True)}

    def ranks(self, pos: np.ndarray, own: list) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """better, ties and all candidates that count, for edges of the score ``pos``; an edge's own endpoint does not count."""
        lo, hi = (self.so_far[np.searchsorted(self.score, pos, s)] for s in ("left", "right"))
        held = [self.of.get(key, (0, 0)) for key in own]
        x, n = (np.array(c) for c in zip(*held, strict=True)) if held else (np.zeros(0),) * 2
        total = self.so_far[-1]
        return total - hi - n * (x > pos), hi - lo - n * (x == pos), total - n


def _control(rows: DataFrame, side: str, count) -> DataFrame:
    """Ranks of a control: ``count(columns, relation, places)`` gives better, ties and counting candidates of a batch's edges of a relation.

    Candidates are few, so they go to the tasks and no row is made for a pair of an edge and a candidate.
    """
    arrow = pa.schema([("rel", pa.string()), ("src", pa.string()), ("dst", pa.string()), ("better", pa.int64()), ("ties", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cols = {c: b.column(c).to_pylist() for c in b.schema.names}
            better, ties, some = (np.zeros(b.num_rows, np.int64) for _ in range(3))
            rels = np.array(cols["rel"], object)
            for r in set(cols["rel"]):
                at = np.flatnonzero(rels == r)
                found = count(cols, r, at)
                if found is not None:
                    better[at], ties[at], some[at] = found
            out = pa.RecordBatch.from_arrays([*(b.column(c) for c in ("rel", "src", "dst")), pa.array(better), pa.array(ties)], schema=arrow)
            yield out.filter(pa.array(some > 0))

    return rows.mapInArrow(run, "rel string, src string, dst string, better long, ties long").withColumn("side", F.lit(side))


def random_ranks(test: DataFrame, train: DataFrame, k: int = 500, mode: str = "data", side: str = "dst", seed: int = 1, drawn: DataFrame | None = None) -> DataFrame:
    """Control: scores are hashes. Edges come in the order of their source, with which all its candidates are hashed once."""
    drawn = candidate_keys(train, side, k, mode, seed) if drawn is None else drawn
    pools = _pools(drawn.groupBy("rel", "key").agg(F.count(F.lit(1)).alias("times")))
    kept: dict = {}

    def of_source(r: str, src: str) -> tuple:
        if kept.get("at") != (r, src):
            keys, times, _ = pools[r]
            head = hashlib.md5(f"{seed}:rnd:{src}:".encode())
            kept.update(at=(r, src), head=head, counted=_Counted(keys, times, np.array([_with_tail(head, x) for x in keys], np.int64)))
        return kept["head"], kept["counted"]

    def count(cols, r, at):
        if r not in pools:
            return None
        out = np.zeros((3, len(at)), np.int64)
        src = [cols["src"][i] for i in at]
        ends = [j for j in range(len(at)) if j == 0 or src[j] != src[j - 1]] + [len(at)]
        for lo, hi in zip(ends[:-1], ends[1:], strict=True):
            head, counted = of_source(r, src[lo])
            pos = np.array([_with_tail(head, cols["dst"][i]) for i in at[lo:hi]], np.int64)
            out[:, lo:hi] = counted.ranks(pos, [cols[side][i] for i in at[lo:hi]])
        return out

    spark = test.sparkSession
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    return _control(test.select("rel", "src", "dst").repartitionByRange(parts, "rel", "src", "dst").sortWithinPartitions("rel", "src"), side, count)


def _with_tail(head, tail: str) -> int:
    """h32 of the parts in ``head``, already hashed up to the last colon, and one more."""
    h = head.copy()
    h.update(tail.encode())
    return int.from_bytes(h.digest()[:4], "big")


def degree_ranks(test: DataFrame, train: DataFrame, k: int = 500, mode: str = "data", side: str = "dst", seed: int = 1, drawn: DataFrame | None = None) -> DataFrame:
    """Control: the score is the endpoint's training degree, the degenerate solution of uniform negatives."""
    deg = stored(train.groupBy("rel", F.col(side).alias("key")).agg(F.count(F.lit(1)).alias("deg")), "degrees")
    drawn = candidate_keys(train, side, k, mode, seed) if drawn is None else drawn
    cand = F.broadcast(drawn.groupBy("rel", "key").agg(F.count(F.lit(1)).alias("times")))
    pools = {r: _Counted(*held) for r, held in _pools(cand.join(deg, ["rel", "key"], "left").na.fill({"deg": 0})).items()}
    near = deg.withColumnRenamed("key", side).withColumnRenamed("deg", "own")
    own = test.select("rel", "src", "dst").join(F.broadcast(near) if is_small(*key_bytes(deg, "key"), 48) else near, ["rel", side], "left").na.fill({"own": 0})

    def count(cols, r, at):
        return pools[r].ranks(np.array([cols["own"][i] for i in at]), [cols[side][i] for i in at]) if r in pools else None

    return _control(own.select("rel", "src", "dst", "own"), side, count)

"""Operator 10: n-gram Jaccard join by vertical partitioning of the global n-gram order.

The n-grams' hashes are the global order. It is cut into as many equal ranges (fragments) as a pair of
similar sets can differ in elements, plus two: with fewer differences than fragments, two similar sets
are equal in at least one non-empty fragment. So a document sends one key per fragment (the fragment's
number and a hash of what the set has in it), and only documents that share a key can be linked. At a
threshold of 0.9 a key stands for some eight n-grams, so a passage or word that many documents share
gives few candidates by itself.

At lower thresholds keys are shorter. There (``spare`` > 0) the sets are cut in more fragments than
needed, and a document leaves out up to that surplus of keys whose n-grams are all common ones: a
linked pair agrees on more fragments than either has left out, so one key still meets. Which n-grams
are common (counted over all documents) changes the number of candidates and never the links.

Every document that shares a key is a candidate of the smallest document that it shares one with. For
these pairs the n-gram order is cut again, into fragments of some ``FRAGMENT_GRAMS`` n-grams; both
documents send each fragment of their sets to the task of that fragment, which counts the partial
overlap and nothing else, and the partial counts are summed per pair. A document that leads very many
others has its fragments dealt to several tasks, each with some of its candidates, so a group that
holds a third of all rows stays linear.

Documents that share keys, directly or over others, form a cluster. Where the summed pairs leave a
cluster in one piece it is settled. Else its largest piece stays as it is, and only the documents
outside that piece are compared with the others: a cluster beyond a task's bound is cut into blocks, and
the documents outside the largest piece meet every block. A comparison counts overlaps fragment by
fragment and stops as soon as the rest cannot make up for what is missing, and it leaves out documents
that a link has reached already. No link between different components is lost.

Equal sets are collapsed first; they never meet as pairs. Small sets: those under nine n-grams cannot
be linked with a different set at 0.9 and send no keys.

Defined results: null, empty or blank text has no n-grams, ``n_shingles`` 0, and is its own component;
fewer than n words are one n-gram; rows that repeat a ``doc_id`` each give a row (their sets are all
linked with that id); null ids give a row with null ``component_id``; an empty table gives an empty
table; other columns are ignored.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import give_back, id_and_text, mapped, stored
from .components import components
from .wordhash import mix, windows, word_hashes

#: n-grams per block of a cluster; a task holds two blocks at most.
BLOCK_NGRAMS = 600_000
#: Fragments beyond the least number at any threshold: as many may be empty without a key of their own.
SPARE = 1
#: Parts of a set after which a comparison inside a cluster looks whether it can still reach the bound.
COUNT_FRAGMENTS = 8
#: n-grams of a leading set in one fragment of the order, and candidates that meet in one task for each fragment.
FRAGMENT_GRAMS, FRAGMENT_DOCS = 512, 400


#: Rows of ids up to which a list of copies or of cluster members is broadcast (under 50 MB); else a shuffle join.
BROADCAST_ROWS = 500_000
#: Keys that a task sorts at a time, and ranges of keys at most.
RANGE_KEYS = 700_000
#: Bound on the list of common n-grams (8 bytes each), and documents that have one at least.
COMMON, COMMON_LEAST = 500_000, 6


_SLICES = np.array([k << 60 for k in range(16)] + [2**64 - 1], np.uint64)
#: Characters whose keys a task holds at a time before it settles and sends them.
SEND_CHARS = 3_000_000


class Measure:
    """Jaccard threshold num/den over distinct n-grams of n words."""

    def __init__(self, n: int = 3, num: int = 90, den: int = 100, spare: float | None = None):
        self.n, self.num, self.den = n, num, den
        self.spare = spare if spare is not None else (0.3 if 100 * num < 85 * den else 0.0)
        self.common = np.zeros(0, np.uint64)  # sorted hashes of common n-grams
        self.starts = [1]
        while self.starts[-1] < 1 << 40:
            self.starts.append(max(self.starts[-1] + 1, -(-self.starts[-1] * den // num)))

    def shingles(self, text: str) -> np.ndarray:
        """Sorted distinct hashes of a text's n-grams."""
        h = word_hashes(text.encode("utf-8", "surrogatepass").lower())
        if not len(h):
            return h
        if len(h) < self.n:
            return windows(h, len(h), seed=100 + len(h))
        return np.unique(windows(h, self.n, seed=100 + self.n))

    def linked(self, overlap, size_a, size_b):
        return self.den * overlap >= self.num * (size_a + size_b - overlap)

    def least_overlap(self, size_a, size_b):
        """The smallest overlap that links sets of these sizes."""
        return -(-self.num * (size_a + size_b) // (self.num + self.den))

    def level(self, size: int) -> int:
        return int(np.searchsorted(self.starts, size, "right")) - 1

    def keys_per_gram(self) -> float:
        """About how many keys a set sends per n-gram."""
        return (1 + self.spare) * (self.den - self.num) / self.num * (1 + self.den / self.num)

    def differences(self, level: int) -> int:
        """The most elements by which two linked sets differ of which the smaller is of this level."""
        return (self.den - self.num) * (self.starts[level + 1] - 1) // self.num

    def surplus(self, level: int) -> int:
        """Keys that a document may leave out."""
        return SPARE + int(self.spare * self.differences(level))

    def fragments(self, level: int) -> int:
        """Fragments for pairs whose smaller set is of this level: one more than they can differ by, and the surplus."""
        return self.differences(level) + 1 + self.surplus(level)

    def keys(self, s: np.ndarray) -> np.ndarray:
        """One key per fragment, for partners that are larger and for partners that are smaller.

        Keys of empty fragments, and of fragments with common n-grams only, are left out if they are
        no more than the surplus; else all are sent.
        """
        size = len(s)
        if not size or not self.linked(size, size, size + 1):  # cannot be linked with any other set
            return np.zeros(0, np.uint64)
        level, out = self.level(size), []
        mixed = mix(s ^ np.uint64(0xA5A5))
        rare = None
        if len(self.common):
            at = np.minimum(np.searchsorted(self.common, s), len(self.common) - 1)
            rare = (self.common[at] != s).astype(np.int64)
        for at in (level, level - 1):
            if at < 0:
                continue
            m = self.fragments(at)
            place = ((s >> np.uint64(32)) * np.uint64(m)) >> np.uint64(32)
            first = np.flatnonzero(np.concatenate([[True], place[1:] != place[:-1]]))
            filled = place[first]
            head = lambda p: mix(p * np.uint64(2654435761) + np.uint64(at * 1_000_003 + 17))  # noqa: B023, E731
            key = mix(np.add.reduceat(mixed, first) + head(filled))
            plain = np.add.reduceat(rare, first) == 0 if rare is not None else np.zeros(len(first), bool)
            empty, surplus = m - len(filled), self.surplus(at)
            if empty + int(plain.sum()) <= surplus:
                key = key[~plain]
            elif empty:
                out.append(mix(head(np.setdiff1d(np.arange(m, dtype=np.uint64), filled)) + np.uint64(1)))
            out.append(key)
        return np.concatenate(out)


def _keyed(docs: DataFrame) -> DataFrame:
    return id_and_text(docs).withColumn("t", F.xxhash64("text"))


def profiles(rows: DataFrame, measure: Measure) -> DataFrame:
    """doc_id, hash of the text, number of n-grams and 128-bit hash of their set."""

    def run(batch: pa.RecordBatch) -> dict:
        n, h1, h2 = [], [], []
        for text in batch.column("text").to_pylist():
            s = measure.shingles(text)
            n.append(len(s))
            h1.append(int(mix(s).sum(dtype=np.uint64).astype(np.int64)) if len(s) else 0)
            h2.append(int((mix(s ^ np.uint64(0x5851F42D4C957F2D)) * np.uint64(0x9E3779B97F4A7C15)).sum(dtype=np.uint64).astype(np.int64)) if len(s) else 0)
        return {"doc_id": batch.column("doc_id"), "t": batch.column("t"), "n": n, "h1": h1, "h2": h2}

    return mapped(rows.select("doc_id", "t", "text"), run, "doc_id long, t long, n long, h1 long, h2 long")


def common_ngrams(rows: DataFrame, measure: Measure) -> np.ndarray:
    """The n-grams that most documents have, at most ``COMMON`` of them.

    A batch reports those that it has twice or more, and all reports are summed; the list has a fixed bound.
    """

    def run(batch: pa.RecordBatch) -> dict:
        sets = [measure.shingles(t) for t in batch.column("text").to_pylist()]
        grams, counts = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
        cuts = [np.searchsorted(x, _SLICES) for x in sets]
        for k in range(len(_SLICES) - 1):  # a slice of the order at a time, for memory
            part = [x[c[k] : c[k + 1]] for x, c in zip(sets, cuts, strict=True)]
            gram, n = np.unique(np.concatenate(part), return_counts=True) if part else (grams[0], counts[0])
            grams.append(gram[n > 1])
            counts.append(n[n > 1].astype(np.int64))
        return {"gram": np.concatenate(grams).view(np.int64), "n": np.concatenate(counts)}

    counted = mapped(rows.select("text"), run, "gram long, n long").groupBy("gram").agg(F.sum("n").alias("n")).where(F.col("n") >= COMMON_LEAST)
    return np.sort(np.array([r["gram"] for r in counted.orderBy(F.desc("n"), "gram").limit(COMMON).select("gram").collect()], np.int64).view(np.uint64))


def _pack(a: np.ndarray) -> bytes:
    """64-bit values, byte by byte in planes, compressed: keys of one range share their upper bytes, ids theirs."""
    import zstandard

    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(a.astype("<i8").view(np.uint8).reshape(-1, 8).T).tobytes())


def _unpack(data: bytes) -> np.ndarray:
    import zstandard

    return np.ascontiguousarray(np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8).reshape(8, -1).T).view("<i8").ravel()


def _lead(key: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted by key and document: the keys and the least document of each, and per row its key's least."""
    order = np.lexsort((doc, key))
    key, doc = key[order], doc[order]
    new = np.concatenate([[True], key[1:] != key[:-1]])
    lead = doc[np.maximum.accumulate(np.where(new, np.arange(len(key)), 0))]
    apart = doc != lead
    return np.stack([key[new], doc[new]]), np.unique(np.stack([doc[apart], lead[apart]]), axis=1), new


def _stars(rows: DataFrame, measure: Measure, ranges: int) -> DataFrame:
    """Each document that shares a key with a smaller one, and the smallest.

    A batch settles its own shared keys and sends one document per key, packed by range of keys; so a
    key of very many documents arrives once per batch. A task takes the ranges one by one.
    """

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def settled(docs: list, texts: list) -> pa.RecordBatch | None:
            keys = [measure.keys(measure.shingles(t)).view(np.int64) for t in texts]
            size = [len(k) for k in keys]
            if not sum(size):
                return None
            own, edges, _ = _lead(np.concatenate(keys), np.repeat(np.array([d or 0 for d in docs], np.int64), size))
            part = ((own[0].view(np.uint64) >> np.uint64(32)) * np.uint64(ranges) >> np.uint64(32)).astype(np.int64)
            order = np.argsort(part, kind="stable")
            ends = np.searchsorted(part[order], np.arange(ranges + 1))
            rows = [(r, False, _pack(own[0][order[a:b]]), _pack(own[1][order[a:b]])) for r, (a, b) in enumerate(zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)) if b > a]
            if edges.size:
                rows.append((int(edges[0, 0]) % ranges, True, _pack(edges[0]), _pack(edges[1])))
            return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int32(), pa.bool_(), pa.binary(), pa.binary()))], names=["part", "edges", "x", "y"])

        for batch in batches:
            docs, texts = batch.column("doc_id").to_pylist(), batch.column("text").to_pylist()
            lo = held = 0
            for hi, text in enumerate(texts, 1):
                held += len(text)
                if held >= SEND_CHARS or hi == len(texts):
                    out = settled(docs[lo:hi], texts[lo:hi])
                    if out is not None:
                        yield out
                    lo, held = hi, 0
        give_back()

    def settle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(pairs):
            return pa.RecordBatch.from_arrays([pa.array(pairs[0], pa.int64()), pa.array(pairs[1], pa.int64())], names=["doc", "lead"])

        now, held = None, []
        for batch in batches:
            for part, edges, x, y in zip(*(batch.column(c).to_pylist() for c in ("part", "edges", "x", "y")), strict=True):
                if edges:
                    yield out((_unpack(x), _unpack(y)))
                    continue
                if part != now:
                    if held:
                        yield out(_lead(*(np.concatenate(v) for v in zip(*held, strict=True)))[1])
                    now, held = part, []
                held.append((_unpack(x), _unpack(y)))
        if held:
            yield out(_lead(*(np.concatenate(v) for v in zip(*held, strict=True)))[1])
        held = []
        give_back()

    sent = rows.select("doc_id", "text").mapInArrow(send, "part int, edges boolean, x binary, y binary")
    tasks = max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), ranges // 4)
    return sent.repartition(tasks, "part").sortWithinPartitions("part").mapInArrow(settle, "doc long, lead long").distinct()


def summed_links(lone: DataFrame, pairs: DataFrame, sizes: DataFrame, measure: Measure) -> DataFrame:
    """The linked ones of ``pairs`` (doc, lead; one lead a doc): overlaps counted per fragment, summed per pair.

    ``sizes`` has doc and n of documents whose id stands for one set; ``lone`` a text of each.
    """
    known = pairs.join(sizes, "doc").join(sizes.select(F.col("doc").alias("lead"), F.col("n").alias("n_lead")), "lead")
    known = stored(known, "jaccard-pairs")
    leads = known.groupBy("lead").agg(F.count(F.lit(1)).alias("docs"), F.first("n_lead").alias("n_lead"))
    leads = leads.select("lead", F.ceil(F.col("docs") / F.lit(FRAGMENT_DOCS)).cast("int").alias("deals"), F.greatest(F.lit(1), F.ceil(F.col("n_lead") / F.lit(FRAGMENT_GRAMS))).cast("int").alias("cuts"))
    deal = F.pmod(F.xxhash64("doc"), F.col("deals")).cast("int")
    asked = known.join(leads, "lead").select("doc", F.struct("lead", F.lit(False).alias("leads"), deal.alias("deal"), "cuts").alias("a"))
    asked = asked.union(leads.select(F.col("lead").alias("doc"), F.struct("lead", F.lit(True).alias("leads"), F.col("deals").alias("deal"), "cuts").alias("a")))
    asked = stored(asked.groupBy("doc").agg(F.collect_list("a").alias("asked")), "jaccard-asked")  # one as candidate, one as lead
    few = asked.count() <= BROADCAST_ROWS
    texts = lone.select("doc_id", "text").join(F.broadcast(asked) if few else asked, F.col("doc_id") == F.col("doc")).select("doc", "text", "asked")

    def cut(batch: pa.RecordBatch) -> dict:
        out: dict = {c: [] for c in ("lead", "deal", "fragment", "other", "doc", "grams")}
        for doc, text, asked in zip(*(batch.column(c).to_pylist() for c in ("doc", "text", "asked")), strict=True):
            s = measure.shingles(text)
            for a in asked:
                place = ((s >> np.uint64(32)) * np.uint64(a["cuts"])) >> np.uint64(32)
                first = np.flatnonzero(np.concatenate([[True], place[1:] != place[:-1]])).tolist()
                for lo, hi in zip(first, [*first[1:], len(s)], strict=True):
                    for deal in range(a["deal"]) if a["leads"] else (a["deal"],):
                        for c, v in zip(out, (a["lead"], deal, int(place[lo]), not a["leads"], doc, s[lo:hi].tobytes()), strict=True):
                            out[c].append(v)
        return out

    parts = mapped(texts, cut, "lead long, deal int, fragment int, other boolean, doc long, grams binary", 400)
    parts = parts.repartition("lead", "deal", "fragment").sortWithinPartitions("lead", "deal", "fragment", "other", "doc")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, own, before = None, np.zeros(0, np.uint64), None
        for batch in batches:
            found: list[tuple[int, int, int]] = []
            for lead, deal, fragment, other, doc, grams in zip(*(batch.column(c).to_pylist() for c in ("lead", "deal", "fragment", "other", "doc", "grams")), strict=True):
                if (lead, deal, fragment) != now:
                    now, own, before = (lead, deal, fragment), np.zeros(0, np.uint64), None
                if not other:
                    own = np.frombuffer(grams, np.uint64)
                elif len(own) and doc != before:  # a row that is there twice counts once
                    before = doc
                    s = np.frombuffer(grams, np.uint64)
                    same = own[np.minimum(np.searchsorted(own, s), len(own) - 1)] == s
                    found.append((doc, lead, int(same.sum())))
            yield pa.RecordBatch.from_arrays([pa.array([f[i] for f in found], pa.int64()) for i in range(3)], names=["doc", "lead", "overlap"])
        give_back()

    summed = parts.mapInArrow(count, "doc long, lead long, overlap long").groupBy("doc", "lead").agg(F.sum("overlap").alias("overlap"))
    linked = F.lit(measure.den) * F.col("overlap") >= F.lit(measure.num) * (F.col("n") + F.col("n_lead") - F.col("overlap"))
    return summed.join(known, ["doc", "lead"]).where(linked).select(F.col("doc").alias("a"), F.col("lead").alias("b"))


def link_block(ids: list[int], sets: list[np.ndarray], measure: Measure, piece: list[int] | None = None, late: list[bool] | None = None) -> list[tuple[int, int]]:
    """Links that join the block's documents as far as links reach, beyond the pieces known already.

    ``piece`` numbers the known pieces; only documents that are ``late`` are compared with the others.
    """
    n = len(ids)
    comp = np.unique(np.array(piece), return_inverse=True)[1] if piece is not None else np.arange(n)
    late_docs = np.array(late) if late is not None else np.ones(n, bool)
    sizes = np.array([len(s) for s in sets], np.int64)
    flat = np.concatenate(sets)
    owner = np.repeat(np.arange(n), sizes)
    _, gram = np.unique(flat, return_inverse=True)
    start = np.concatenate([[0], np.cumsum(sizes)])
    cuts = [np.linspace(0, int(k), COUNT_FRAGMENTS + 1).astype(int) for k in sizes]

    def index(alive: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
        """Documents of each n-gram, of those alive, and how many those are."""
        keep = alive[owner]
        g, o = gram[keep], owner[keep]
        order = np.argsort(g, kind="stable")
        return np.searchsorted(g[order], np.arange(gram.max() + 2)), o[order], int(alive.sum())

    alive, done = np.ones(n, bool), np.zeros(n, bool)
    base = index(alive)
    out: list[tuple[int, int]] = []
    for seed in np.flatnonzero(late_docs).tolist():
        if done[seed]:
            continue
        if int(alive.sum()) * 2 < base[2]:
            base = index(alive)
        at, posts, held = base
        own = comp == comp[seed]
        waiting = alive & ~own
        stack = np.flatnonzero(own & late_docs).tolist()
        while stack:
            x = stack.pop()
            done[x] = True
            left_over = int(waiting.sum())
            if not left_over:
                continue
            if left_over * 2 < held:
                at, posts, held = index(waiting)
            able = waiting & (measure.den * np.minimum(sizes, sizes[x]) >= measure.num * np.maximum(sizes, sizes[x]))
            need = measure.least_overlap(sizes, sizes[x])
            count = np.zeros(n, np.int64)
            grams = gram[start[x] : start[x + 1]]
            for lo, hi in zip(cuts[x][:-1], cuts[x][1:], strict=True):
                if not able.any():
                    break
                part = grams[lo:hi]
                lengths = at[part + 1] - at[part]
                total = int(lengths.sum())
                if total:
                    first = np.repeat(at[part] - np.concatenate([[0], np.cumsum(lengths)[:-1]]), lengths)
                    count += np.bincount(posts[first + np.arange(total)], minlength=n)
                able &= count + (sizes[x] - hi) >= need
            for y in np.flatnonzero(able & (count >= need)).tolist():
                if waiting[y]:
                    joined = comp == comp[y]
                    out.append((ids[x], ids[y]))
                    comp[joined] = comp[x]
                    waiting &= ~joined
                    stack += np.flatnonzero(joined & late_docs & ~done).tolist()
        alive &= ~((comp == comp[seed]) & late_docs)
    return out


def _links(docs: DataFrame, members: DataFrame, measure: Measure, block: int) -> DataFrame:
    """Further links (a, b) inside the clusters. members: doc, n, root, piece, late."""
    bits = F.col("n").cast("long")
    size = members.groupBy("root").agg(F.sum(bits).alias("total"), F.sum(F.when(F.col("late"), bits).otherwise(0)).alias("outside"))
    cut = lambda c: F.greatest(F.lit(1), F.ceil(F.col(c) / F.lit(block))).cast("int")
    own = lambda c: F.pmod(F.xxhash64("doc"), F.col(c)).cast("int")
    placed = members.join(size, "root").withColumn("blocks", cut("total")).withColumn("lates", cut("outside"))
    placed = stored(placed.select("doc", "root", "piece", "late", "blocks", "lates", own("blocks").alias("i"), own("lates").alias("j")), "jaccard-members")
    few = placed.count() <= BROADCAST_ROWS
    texts = id_and_text(docs).join(F.broadcast(placed) if few else placed, F.col("doc_id") == F.col("doc")).drop("doc_id")

    def grams(batch: pa.RecordBatch) -> dict:
        sets = [measure.shingles(t).tobytes() for t in batch.column("text").to_pylist()]
        return {c: batch.column(c) for c in ("doc", "root", "piece", "late", "blocks", "lates", "i", "j")} | {"grams": sets}

    sets = mapped(texts, grams, "doc long, root long, piece long, late boolean, blocks int, lates int, i int, j int, grams binary")
    # block i of all documents meets block j of the late ones: everyone once per j, the late also once per i
    once = sets.withColumn("to", F.explode(F.sequence(F.lit(0), F.col("lates") - 1))).select("root", F.col("i").alias("bi"), F.col("to").alias("bj"), "doc", "piece", "late", "grams", (F.col("late") & (F.col("to") == F.col("j"))).alias("asks"))
    again = sets.where("late and blocks > 1").withColumn("to", F.explode(F.filter(F.sequence(F.lit(0), F.col("blocks") - 1), lambda b: b != F.col("i")))).select("root", F.col("to").alias("bi"), F.col("j").alias("bj"), "doc", "piece", "late", "grams", F.lit(True).alias("asks"))
    tasks = once.unionByName(again)
    tasks = tasks.repartition("root", "bi", "bj").sortWithinPartitions("root", "bi", "bj", "doc")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def emit(group):
            pairs = link_block([r[0] for r in group], [r[1] for r in group], measure, [r[2] for r in group], [r[3] for r in group])
            return pa.RecordBatch.from_arrays([pa.array([p[0] for p in pairs], pa.int64()), pa.array([p[1] for p in pairs], pa.int64())], names=["a", "b"])

        now, group = None, []
        for batch in batches:
            cols = [batch.column(c).to_pylist() for c in ("root", "bi", "bj", "doc", "grams", "piece", "asks")]
            for root, i, j, doc, grams, piece, asks in zip(*cols, strict=True):
                if (root, i, j) != now:
                    if len(group) > 1:
                        yield emit(group)
                    now, group = (root, i, j), []
                group.append((doc, np.frombuffer(grams, np.uint64), piece, asks))
        if len(group) > 1:
            yield emit(group)
        group = []
        give_back()

    return tasks.mapInArrow(run, "a long, b long")


def _unsettled(members: DataFrame, links: DataFrame) -> DataFrame:
    """The members (doc, n, root, sets) of clusters that the summed links leave in several pieces, with the
    piece of each and whether it is outside the largest."""
    pieces = components(links, "a", "b")
    told = members.join(pieces.select(F.col("node").alias("doc"), F.col("root").alias("of")), "doc", "left").withColumn("piece", F.coalesce("of", "doc"))
    told = stored(told.select("doc", "n", "root", "sets", "piece"), "jaccard-pieces")
    each = told.groupBy("root", "piece").agg(F.sum("sets").alias("sets"))
    # an id that stands for several sets may link with itself in each of them, so it is never part of a settled piece
    several = each.groupBy("root").agg(F.count(F.lit(1)).alias("pieces"), F.max_by("piece", F.struct("sets", F.col("piece"))).alias("main")).where("pieces > 1")
    odd = told.where("sets > 1").select("root").distinct()
    open_roots = several.join(odd.withColumn("odd", F.lit(True)), "root", "full").select("root", "main")
    return told.join(open_roots, "root").select("doc", "n", "root", "piece", (F.col("main").isNull() | (F.col("piece") != F.col("main")) | (F.col("sets") > 1)).alias("late"))


def similar_groups(docs: DataFrame, measure: Measure | None = None, block: int = BLOCK_NGRAMS) -> DataFrame:
    """doc_id, n_shingles, component_id of every row."""
    measure = measure or Measure()
    keyed = _keyed(docs)
    rows = stored(profiles(keyed, measure), "jaccard-profiles")
    plain = rows.select("doc_id", "n", "h1", "h2")
    known = rows.where("n > 0 and doc_id is not null")
    first = known.groupBy("n", "h1", "h2").agg(F.min(F.struct("doc_id", "t")).alias("f"))
    reps = stored(first.select("n", "h1", "h2", F.col("f.doc_id").alias("doc"), F.col("f.t").alias("t")), "jaccard-reps")
    spare = stored(rows.join(reps.select(F.col("doc").alias("doc_id"), "t"), ["doc_id", "t"], "left_anti").select(F.col("doc_id").alias("_d"), F.col("t").alias("_t")).distinct(), "jaccard-copies")
    few = spare.count() <= BROADCAST_ROWS
    spare = F.broadcast(spare) if few else spare
    lone = keyed.join(spare, keyed["doc_id"].eqNullSafe(spare["_d"]) & (keyed["t"] == spare["_t"]), "left_anti").where("doc_id is not null") if few else keyed.join(reps.select(F.col("doc").alias("doc_id"), "t"), ["doc_id", "t"], "left_semi")
    if measure.spare:
        measure.common = common_ngrams(lone, measure)
    total = reps.agg(F.sum("n")).first()[0] or 0
    ranges = int(max(2, total * measure.keys_per_gram() // RANGE_KEYS + 1))
    stars = stored(_stars(lone, measure, ranges), "jaccard-stars")
    clusters = components(stars, "doc", "lead")
    roots = clusters.select(F.col("root").alias("doc"), "root").distinct()
    by_doc = reps.groupBy("doc").agg(F.max("n").alias("n"), F.count(F.lit(1)).alias("sets"))
    members = clusters.select(F.col("node").alias("doc"), "root").union(roots).join(by_doc, "doc")
    pairs = stars.groupBy("doc").agg(F.min("lead").alias("lead"))
    summed = stored(summed_links(lone, pairs, members.where("sets = 1").select("doc", "n"), measure), "jaccard-summed")
    links = stored(_links(docs, _unsettled(members, summed), measure, block), "jaccard-links").union(summed)
    # an id that stands on rows with different texts links all of their sets
    same_id = known.join(reps, ["n", "h1", "h2"]).where("doc != doc_id").select(F.col("doc").alias("a"), F.col("doc_id").alias("b"))
    same_id = same_id.join(reps.select(F.col("doc").alias("b")), "b", "left_semi").select("a", "b")
    joined = components(links.union(same_id), "a", "b")
    by_set = reps.join(joined, reps["doc"] == joined["node"], "left").select("n", "h1", "h2", F.coalesce("root", "doc").alias("component_id"))
    out = plain.join(by_set, ["n", "h1", "h2"], "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"))


def one_of_each(docs: DataFrame, measure: Measure | None = None) -> DataFrame:
    """The rows of ``docs`` whose id leads its group: one document of each group stays."""
    told = stored(similar_groups(docs, measure).select(F.col("doc_id").alias("__gembed_id"), F.expr("doc_id <=> component_id").alias("leads")).distinct(), "jaccard-told")
    own = docs["doc_id"].cast("long")
    lost = told.where("not leads").select("__gembed_id")
    if lost.count() <= BROADCAST_ROWS:
        return docs.join(F.broadcast(lost), own.eqNullSafe(F.col("__gembed_id")), "left_anti")
    return docs.join(told.where("leads").select("__gembed_id"), own.eqNullSafe(F.col("__gembed_id")), "left_semi")

"""Operator 1: repeated passages by a sparse suffix array.

Of all suffixes of the corpus only those are retained that start at a minimiser: the word run of
``K`` words with the smallest hash in some window of ``min_words`` words. The choice depends on the
window's words alone, so two copies of a passage of ``min_words`` words retain a suffix at the same
place in it. The suffixes are sorted over the whole corpus (by ranges, in the order of the hashes of
their first K words, then by document, so that a start that a third of all documents have fills many
ranges) and each is compared with its neighbours; those without an equal neighbour in another document
are dropped, and what a range's edge leaves open is settled by the edges of the ranges beside it. The
rest are extended left and right over the windows that chose them. First whole extensions are compared (a passage in very many documents has one, and it is
pre-aggregated before the shuffle); only where a start has several different extensions are the
windows between compared one by one. The union of repeated windows gives the maximal passages.

Words are compared by hashes, 64 bits of the start and 128 bits of an extension (64 of the start and
64 of a window where windows are compared), which stand for the words with a chance of error of about
2^-64 a pair.

A passage counts as repeated when it stands in two different documents. Words are runs of characters
other than space and U+0009..U+000D, compared exactly.

Defined results: null, empty or short text has no passage; a document without a repeated passage has
no row; rows with equal id and text count as one document, rows with equal id and other text as two;
an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_and_text, mapped, stored
from .wordhash import Ranges, windows, word_hashes

MIN_WORDS = 50
#: Words of a suffix's start that are compared first.
K = 8
#: Bytes of the list of documents with shared suffixes up to which it is broadcast; else both sides are shuffled.
BROADCAST_BYTES = 64 << 20
#: Suffixes of one extension that meet in one task, and extensions at most that are dealt to several.
DEAL, DEALT = 5_000, 50_000
#: Documents whose suffixes and windows a task holds at a time.
ROWS = 400
_WORD = re.compile(r"[^\x20\x09-\x0D]+")
_BASES = (0x9E3779B97F4A7C15, 0xD1B54A32D192ED03)


def anchors(h: np.ndarray, min_words: int = MIN_WORDS, k: int = K) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Retained suffixes of a text: start, hash of its first k words, first and last window that chose it."""
    n_windows = len(h) - min_words + 1
    if n_windows <= 0:
        none = np.zeros(0, np.int64)
        return none, none.astype(np.uint64), none, none
    g = windows(h, k, seed=7)
    span, at, width = min_words - k + 1, np.arange(len(g)), 1
    while width * 2 <= span:
        at = _lesser(g, at[:-width], at[width:])
        width *= 2
    if width < span:
        rest = span - width
        at = _lesser(g, at[:-rest], at[rest:])
    first = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
    last = np.concatenate([first[1:] - 1, [n_windows - 1]])
    return at[first], g[at[first]], first, last


def _lesser(g: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.where(g[a] <= g[b], a, b)


def _keyed(docs: DataFrame) -> DataFrame:
    rows = id_and_text(docs)
    return rows.withColumn("uid", F.xxhash64("doc_id", "text"))


def _starts(rows: DataFrame, min_words: int, k: int) -> DataFrame:
    def run(batch: pa.RecordBatch) -> dict:
        found = [anchors(word_hashes(t.encode("utf-8", "surrogatepass")), min_words, k) for t in batch.column("text").to_pylist()]
        n = [len(f[0]) for f in found]
        return {
            "uid": np.repeat(batch.column("uid").to_numpy(), n),
            "lo": np.concatenate([f[2] for f in found] or [np.zeros(0, np.int64)]).astype(np.int32),
            "start": np.concatenate([f[1] for f in found] or [np.zeros(0, np.uint64)]).view(np.int64),
        }

    return mapped(rows.select("uid", "text"), run, "uid long, lo int, start long", ROWS)


def neighbours(starts: DataFrame) -> DataFrame:
    """uid, lo of the suffixes of which a neighbour in sorted order has the same start in another document."""
    ordered = starts.repartitionByRange("start", "uid").sortWithinPartitions("start", "uid", "lo")
    schema = pa.schema([("kind", pa.int32()), ("uid", pa.int64()), ("lo", pa.int32()), ("start", pa.int64()), ("other", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows(kind: int, uid, lo, start, other) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(np.full(len(uid), kind, np.int32)), *(pa.array(np.asarray(v)) for v in (uid, np.asarray(lo, np.int32), start, other))], schema=schema)

        def closed(first: bool, last: bool) -> Iterator[pa.RecordBatch]:
            """The run of one start that is held; at the range's edge its neighbours may lie in the next range."""
            uid, lo = (np.concatenate(v) for v in zip(*held, strict=True))
            start = np.full(len(uid), now, np.int64)
            if low != high:
                yield rows(0, uid, lo, start, uid)
            elif first or last:
                yield rows(1, uid, lo, start, uid)
            if first or last:
                yield rows(2, [low], [0], [now], [high])

        now, first, held, low, high = None, True, [], 0, 0
        for batch in batches:
            uid, lo, start = (batch.column(c).to_numpy() for c in ("uid", "lo", "start"))
            if not len(uid):
                continue
            edge = np.flatnonzero(np.concatenate([[True], start[1:] != start[:-1], [True]]))
            a, b = edge[:-1], edge[1:]
            inner = np.zeros(len(uid), bool)  # runs that neither begin nor end with the batch
            if len(a) > 2:
                keep = uid[a[1:-1]] != uid[b[1:-1] - 1]
                inner[a[1] : b[-2]] = np.repeat(keep, b[1:-1] - a[1:-1])
            for k in (0, len(a) - 1) if len(a) > 1 else (0,):
                piece = slice(a[k], b[k])
                if now is not None and start[a[k]] != now:
                    yield from closed(first, False)
                    first, held = False, []
                if not held:
                    now, low = start[a[k]], uid[a[k]]
                high = uid[b[k] - 1]
                held.append((uid[piece].copy(), lo[piece].copy()))
                if low != high and not first:  # known to be shared: nothing need be held
                    yield rows(0, *(np.concatenate(v) for v in zip(*held, strict=True)), np.full(sum(len(h[0]) for h in held), now, np.int64), np.full(sum(len(h[0]) for h in held), high, np.int64))
                    held = [(uid[:0], lo[:0])]
                if k == 0 and inner.any():
                    yield rows(0, uid[inner], lo[inner], start[inner], uid[inner])
        if now is not None:
            yield from closed(first, True)

    told = stored(ordered.mapInArrow(run, "kind int, uid long, lo int, start long, other long"), "suffix-neighbours")
    # two edges a range at most
    shared = told.where("kind = 2").groupBy("start").agg(F.min("uid").alias("a"), F.max("other").alias("b")).where("a != b").select("start")
    edges = told.where("kind = 1").join(F.broadcast(shared), "start", "left_semi")
    return told.where("kind = 0").select("uid", "lo").unionByName(edges.select("uid", "lo"))


def _extensions(texts: DataFrame, min_words: int, k: int) -> DataFrame:
    """The retained suffixes that have a neighbour, with a hash of their whole extension."""

    def run(batch: pa.RecordBatch) -> dict:
        out: dict = {c: [] for c in ("uid", "doc_id", "lo", "hi", "start", "c1", "c2")}
        for uid, doc, text, los in zip(*(batch.column(c).to_pylist() for c in ("uid", "doc_id", "text", "los")), strict=True):
            h = word_hashes(text.encode("utf-8", "surrogatepass"))
            _, g, lo, hi = anchors(h, min_words, k)
            pick = np.flatnonzero(np.isin(lo, np.array(los)))
            lo, hi, g = lo[pick], hi[pick], g[pick]
            out["uid"] += [uid] * len(lo)
            out["doc_id"] += [doc] * len(lo)
            out["lo"] += lo.tolist()
            out["hi"] += hi.tolist()
            out["start"].append(g.view(np.int64))
            out["c1"].append(Ranges(h, _BASES[0])(lo, hi + min_words).view(np.int64))
            out["c2"].append(Ranges(h, _BASES[1])(lo, hi + min_words).view(np.int64))
        for c in ("start", "c1", "c2"):
            out[c] = np.concatenate(out[c] or [np.zeros(0, np.int64)])
        return out

    return mapped(texts.select("uid", "doc_id", "text", "los"), run, "uid long, doc_id long, lo int, hi int, start long, c1 long, c2 long", ROWS)


def _windows_of(texts: DataFrame, owners: DataFrame, min_words: int) -> DataFrame:
    """(start, ctx, a, b, first, offset, win): the windows of some suffixes (uid, lo, hi and those columns)."""
    asked = owners.groupBy("uid").agg(F.collect_list(F.struct("start", "ctx", "a", "b", "first", "lo", "hi")).alias("asked"))

    def run(batch: pa.RecordBatch) -> dict:
        out: dict = {c: [np.zeros(0, np.int64)] for c in ("start", "ctx", "a", "b", "first", "offset", "win")}
        known: list = []
        for text, asked in zip(batch.column("text").to_pylist(), batch.column("asked").to_pylist(), strict=True):
            hashes = Ranges(word_hashes(text.encode("utf-8", "surrogatepass")), _BASES[0])
            for r in asked:
                at = np.arange(r["lo"], r["hi"] + 1)
                for c in ("start", "ctx", "a", "b"):
                    out[c].append(np.full(len(at), r[c], np.int64))
                out["first"].append(np.full(len(at), r["first"] or 0, np.int64))
                known.append(np.full(len(at), r["first"] is None))
                out["offset"].append(at - r["lo"])
                out["win"].append(hashes(at, at + min_words).view(np.int64))
        out = {c: np.concatenate(v) for c, v in out.items()}
        out["offset"] = out["offset"].astype(np.int32)
        out["first"] = pa.array(out["first"], pa.int64(), mask=np.concatenate([np.zeros(0, bool), *known]))
        return out

    return mapped(texts.join(asked, "uid").select("text", "asked"), run, "start long, ctx long, a long, b long, first long, offset int, win long", ROWS)


def _spans(rows: DataFrame, min_words: int) -> DataFrame:
    """Merges the repeated windows of each document and finds the passages in its text."""

    def run(batch: pa.RecordBatch) -> dict:
        out: dict = {c: [] for c in ("doc_id", "start_word", "n_words", "start", "end", "first_doc_id", "passage")}
        for doc, text, runs in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "text", "runs")), strict=True):
            merged: list[list[int]] = []
            for r in sorted(runs, key=lambda r: (r["lo"], r["hi"])):
                if merged and r["lo"] <= merged[-1][1] + 1:
                    merged[-1][1] = max(merged[-1][1], r["hi"])
                    merged[-1][2] = min(merged[-1][2], r["first"])
                else:
                    merged.append([r["lo"], r["hi"], r["first"]])
            at = [m.span() for m in _WORD.finditer(text)]
            for lo, hi, first in merged:
                a, b = at[lo][0], at[hi + min_words - 1][1]
                for c, v in zip(out, (doc, lo, hi - lo + min_words, a, b, first, text[a:b]), strict=True):
                    out[c].append(v)
        return out

    return mapped(rows.select("doc_id", "text", "runs"), run, "doc_id long, start_word long, n_words long, start long, end long, first_doc_id long, passage string", ROWS)


def repeated_passages(docs: DataFrame, min_words: int = MIN_WORDS, k: int = K) -> DataFrame:
    """doc_id, start_word, n_words, start, end (code points), first_doc_id and passage of every maximal
    run of windows that another document has too. ``first_doc_id`` is the smallest id that shares one."""
    rows = _keyed(docs)
    starts = stored(_starts(rows, min_words, k), "suffix-starts")
    chosen = stored(neighbours(starts).groupBy("uid").agg(F.collect_set("lo").alias("los")), "suffix-chosen")
    size = chosen.agg(F.sum(F.size("los") * 4 + 32)).first()[0] or 0
    texts = stored(rows.join(F.broadcast(chosen) if size <= BROADCAST_BYTES else chosen, "uid"), "suffix-texts")
    held = texts.agg(F.count("uid").alias("n"), F.count_distinct("uid").alias("different")).first()
    if held["n"] != held["different"]:
        texts = stored(texts.dropDuplicates(["uid"]), "suffix-texts-once")
    ext = stored(_extensions(texts, min_words, k), "suffix-extensions")

    key = ["start", "c1", "c2"]
    owner = F.min(F.struct("uid", "lo", "hi")).alias("f")
    whole = stored(ext.groupBy(*key).agg(owner, F.max("uid").alias("b"), F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("n")).withColumn("ctx", F.xxhash64("c1", "c2")), "suffix-contexts")
    several = whole.groupBy("start").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("start")
    # one suffix per different extension of a start that has several; its windows are compared with the others'
    owners = whole.join(several, "start").select("start", "ctx", F.col("f.uid").alias("a"), "b", "first", F.col("f.uid").alias("uid"), "f.lo", "f.hi")
    each = stored(_windows_of(texts, owners, min_words), "suffix-windows")
    common = each.groupBy("start", "win").agg(F.min("a").alias("u"), F.max("b").alias("v"), F.min("first").alias("least")).where("u != v").select("start", "win", "least")
    partly = each.where("a = b").select("start", "win", "ctx", "offset").join(common, ["start", "win"]).groupBy("start", "ctx").agg(F.collect_list(F.struct("offset", "least")).alias("offsets"))
    none = F.lit(None).cast("array<struct<offset:int,least:bigint>>")
    told = whole.where("f.uid != b").select("start", "ctx", "first", none.alias("offsets")).unionByName(partly.select("start", "ctx", F.lit(None).cast("long").alias("first"), "offsets"))

    # an extension that very many suffixes have is dealt to several tasks; those are at most DEALT
    deal = max(DEAL, (whole.agg(F.sum("n")).first()[0] or 0) // DEALT)
    hot = F.broadcast(whole.where(F.col("n") > deal).select("start", "ctx", F.ceil(F.col("n") / F.lit(deal)).cast("int").alias("deals")))
    dealt = lambda df: df.join(hot, ["start", "ctx"], "left").withColumn("deals", F.coalesce("deals", F.lit(1)))
    told = dealt(told).withColumn("deal", F.explode(F.sequence(F.lit(0), F.col("deals") - 1))).drop("deals")
    at = ext.select("uid", "lo", "hi", "start", F.xxhash64("c1", "c2").alias("ctx"))
    at = dealt(at).withColumn("deal", F.pmod(F.xxhash64("uid", "lo"), F.col("deals")).cast("int")).drop("deals").join(told, ["start", "ctx", "deal"])
    ranges = F.when(F.col("offsets").isNull(), F.array(F.struct("lo", "hi", "first"))).otherwise(F.transform("offsets", lambda o: F.struct((F.col("lo") + o["offset"]).cast("int").alias("lo"), (F.col("lo") + o["offset"]).cast("int").alias("hi"), o["least"].alias("first"))))
    runs = at.select("uid", F.explode(ranges).alias("r"))
    of_doc = runs.groupBy("uid").agg(F.collect_list("r").alias("runs"))
    return _spans(texts.join(of_doc, "uid"), min_words)

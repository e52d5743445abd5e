"""Operator 6: token-id output as one wavelet matrix per shard.

Documents are tokenised in ascending id order and cut into shards of about ``SHARD_TOKENS`` tokens. A
shard file holds its sequence as bit-planes, highest bit first: a plane stores one bit of every token
in the order that the planes above left, zeros before ones. Counts of ones before each block make
rank and select cheap, so a reader can fetch a token, count a token in a range, or find its k-th
occurrence from the one compressed file, touching one block per plane.

Layout: 8 bytes magic and version, 8 bytes length of the JSON header, the header, then the sections
it lists (document table, and per plane its blocks), each block compressed by zstandard alone.

Defined results: null or empty text is the end id alone; ids ascend, null ids first, repeated ids by
text; a document longer than a shard has a shard of its own; an empty table writes no file and gives
an empty table; other columns are ignored.
"""

from __future__ import annotations

import json
import os
import re
import struct
import uuid
import zlib
from collections.abc import Iterator
from functools import cache, lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import file_system, id_and_text, mapped, scratch, stored
from .wordhash import _BASE, _BYTES, Ranges

MAGIC = b"GEWAVE01"
SHARD_TOKENS = 1 << 22
BLOCK_BITS = 1 << 17
CACHE = 400_000


# -- tokens


class WordTokens:
    """Ids of whole texts through the tokenizers library, with a cache by word.

    The file's normaliser and splitter never look across a space, so a text's ids are those of its
    space-separated parts in order; ASCII capitals are lowered and a full stop or comma at a
    word's end is parted from it before the look-up (where no other sign stands before it), as the file
    itself does later. All this is checked on
    the file's settings, and else whole texts are encoded. Words that the cache lacks are encoded in
    one call, with a special token between them that marks their ends.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.lib = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        first = ((spec.get("pre_tokenizer") or {}).get("pretokenizers") or [{}])[0]
        added = spec.get("added_tokens", [])
        self.by_word = first.get("behavior") == "Removed" and first.get("invert") is True and bool(added) and not any(t["lstrip"] or t["rstrip"] or t["single_word"] or t["normalized"] or " " in t["content"] for t in added)
        kinds = [n.get("type") for n in (spec.get("normalizer") or {}).get("normalizers", [])]
        letters_apart = r"[\p{L}]+" in str((first.get("pattern") or {}).get("Regex", ""))
        self.lowers = self.by_word and "Lowercase" in kinds and letters_apart and all(t["content"].startswith("<|") for t in added)
        self.mark, self.mark_id = (added[0]["content"], added[0]["id"]) if added else ("", -1)
        self.kind = np.dtype("<u2") if self.lib.get_vocab_size(with_added_tokens=True) <= 1 << 16 else np.dtype("<u4")
        close = (spec.get("model") or {}).get("end_of_word_suffix")
        self.closes = None
        if self.lowers and close:
            self.closes = np.zeros(self.lib.get_vocab_size(with_added_tokens=True), bool)
            for token, i in self.lib.get_vocab(with_added_tokens=False).items():
                self.closes[i] = token.endswith(close)
        self.hashed: dict[int, tuple[bytes, bytes]] = {}
        self.hashed_old: dict[int, tuple[bytes, bytes]] = {}

    def _learn(self, words: list[str]) -> dict[str, bytes]:
        """Encodes different words, in their order.

        Words of plain Latin letters are one piece each, so with spaces between them every id that
        closes a word ends one; others are parted by the special token.
        """
        out: dict[str, bytes] = {}
        letters, apart, plain_word = [], [], _LATIN.fullmatch
        for w in words:
            (letters if self.closes is not None and plain_word(w) else apart).append(w)
        size = self.kind.itemsize
        if letters:
            ids = np.array(self.lib.encode_batch_fast([" ".join(letters)], add_special_tokens=False)[0].ids, self.kind)
            ends = (np.flatnonzero(self.closes[ids]) + 1) * size
            data, at = ids.tobytes(), 0
            for w, end in zip(letters, ends.tolist(), strict=True):
                out[w] = data[at:end]
                at = end
        plain = [w for w in apart if self.mark not in w]
        for w in apart if len(plain) < len(apart) else ():
            if self.mark in w:
                out[w] = np.array(self.lib.encode(w, add_special_tokens=False).ids, self.kind).tobytes()
        if plain:
            ids = np.array(self.lib.encode_batch_fast([self.mark.join(plain)], add_special_tokens=False)[0].ids, np.int64)
            ends = np.flatnonzero(ids == self.mark_id)
            data = ids.astype(self.kind).tobytes()
            starts = np.concatenate([[0], ends + 1]) * size
            for w, a, b in zip(plain, starts.tolist(), (np.concatenate([ends, [len(ids)]]) * size).tolist(), strict=True):
                out[w] = data[a:b]
        return {w: out[w] for w in words}

    def batch(self, texts: list[str], end: int | None) -> list[np.ndarray]:
        """The ids of each text, with the end id."""
        tail = np.array([] if end is None else [end], self.kind)
        out: list[np.ndarray | None] = [None] * len(texts)
        group, size = [], 0
        for i, text in enumerate(texts):
            if not self.by_word:
                out[i] = np.concatenate([np.array(self.lib.encode(text, add_special_tokens=False).ids, self.kind), tail])
            elif not self.lowers or "<|" in text:
                out[i] = np.concatenate([self._plainly(text), tail])
            else:
                group.append(i)
                size += len(text)
            if group and (size > 200_000 or i == len(texts) - 1):
                for k, ids in zip(group, self._together([texts[k] for k in group]), strict=True):
                    out[k] = np.concatenate([ids, tail])
                group, size = [], 0
        if group:
            for k, ids in zip(group, self._together([texts[k] for k in group]), strict=True):
                out[k] = np.concatenate([ids, tail])
        return out

    def _plainly(self, text: str) -> np.ndarray:
        words = text.replace("\n", " ").split(" ")
        known = self._learn(list(set(words)))
        return np.frombuffer(b"".join([known[w] for w in words]), self.kind)

    def _together(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of some texts at once: their words are hashed as arrays, and each different word is looked up once.

        A look-up compares the word itself, so equal hashes of different words do no harm.
        """
        raws = [t.encode("utf-8", "surrogatepass").lower() for t in texts]
        raw = b"\n".join(raws)
        b = np.frombuffer(raw, np.uint8)
        solid = np.zeros(len(b) + 2, np.int8)
        solid[1:-1] = (b != 32) & (b != 10)
        edges = np.flatnonzero(solid[1:] != solid[:-1])
        lo, hi = edges[0::2], edges[1::2]
        # a stop or comma after a letter or digit at a word's end is a word of its own
        last, before, lead = b[hi - 1], b[np.maximum(hi - 2, 0)], b[np.maximum(hi - 3, 0)]
        letter = _ALNUM[before] | ((before >= 128) & (before < 192) & (lead == 0xC3) & (before != 0x97) & (before != 0xB7) & (hi - lo > 2))
        parted = ((last == 46) | (last == 44)) & letter & (hi - lo > 1)
        at = np.flatnonzero(parted)
        lo = np.insert(lo, at + 1, hi[at] - 1)
        ends = hi.copy()
        ends[at] -= 1
        hi = np.insert(ends, at + 1, hi[at])
        key, first, inverse = np.unique(Ranges(_BYTES[b], _BASE)(lo, hi), return_index=True, return_inverse=True)
        starts, stops = lo[first].tolist(), hi[first].tolist()
        cache, old = self.hashed, self.hashed_old
        got: list[bytes | None] = []
        fresh: list[int] = []
        for i, (k, x, y) in enumerate(zip(key.tolist(), starts, stops, strict=True)):
            entry = cache.get(k)
            if entry is None:
                entry = old.get(k)
                if entry is not None:
                    cache[k] = entry
            if entry is not None and entry[0] == raw[x:y]:
                got.append(entry[1])
            else:
                got.append(None)
                fresh.append(i)
        for at_once in range(0, len(fresh), 4096):
            part = fresh[at_once : at_once + 4096]
            words = [raw[starts[i] : stops[i]] for i in part]
            told = self._learn([w.decode("utf-8", "surrogatepass") for w in words])
            keys = key[part].tolist()
            for i, k, w, ids in zip(part, keys, words, told.values(), strict=True):
                got[i] = ids
                cache[k] = (w, ids)
        if len(cache) > CACHE:
            self.hashed_old, self.hashed = cache, {}
        flat = np.frombuffer(b"".join(got), self.kind)
        length = np.array([len(g) for g in got], np.int64) // self.kind.itemsize
        begin = np.cumsum(length) - length
        n = length[inverse]
        total = np.concatenate([[0], np.cumsum(n)])
        ids = flat[np.repeat(begin[inverse] - total[:-1], n) + np.arange(total[-1])] if len(n) else flat
        cuts = np.cumsum([0] + [len(r) + 1 for r in raws])
        words_before = np.searchsorted(lo, cuts)
        return [ids[total[x] : total[y]] for x, y in zip(words_before[:-1].tolist(), words_before[1:].tolist(), strict=True)]


#: Words that are one run of letters; bytes that are ASCII letters or digits.
_LATIN = re.compile(r"[a-zà-öø-ÿ]+")
_ALNUM = np.array([chr(i).isalnum() and i < 128 for i in range(256)])


@cache
def word_tokens(path: str) -> WordTokens:
    return WordTokens(path)


# -- one shard


def build(ids: np.ndarray, doc_ids: list[int | None], lengths: list[int], bits: int) -> bytes:
    """The bytes of a shard file."""
    import zstandard

    pack = zstandard.ZstdCompressor(level=1)
    table = pa.table({"doc_id": pa.array(doc_ids, pa.int64()), "n": pa.array(lengths, pa.int64())})
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, table.schema) as w:
        w.write_table(table)
    sections = [pack.compress(sink.getvalue().to_pybytes())]
    planes = []
    rest = ids
    for bit in range(bits - 1, -1, -1):
        ones = (rest & rest.dtype.type(1 << bit)) != 0
        packed = np.packbits(ones, bitorder="little").tobytes()
        blocks, before, at = [], [], 0
        for start in range(0, len(rest), BLOCK_BITS):
            before.append(at)
            at += int(np.count_nonzero(ones[start : start + BLOCK_BITS]))
            sections.append(pack.compress(packed[start // 8 : (start + BLOCK_BITS) // 8]))
            blocks.append(len(sections) - 1)
        planes.append({"bit": bit, "zeros": len(rest) - at, "blocks": blocks, "ones_before": before})
        rest = np.concatenate([rest.take(np.flatnonzero(~ones)), rest.take(np.flatnonzero(ones))])
    at, spans = 0, []
    for s in sections:
        spans.append([at, len(s)])
        at += len(s)
    head = json.dumps({"n": len(ids), "docs": len(doc_ids), "bits": bits, "kind": ids.dtype.str, "block_bits": BLOCK_BITS, "planes": planes, "sections": spans}, separators=(",", ":")).encode()
    return b"".join([MAGIC, struct.pack("<Q", len(head)), head, *sections])


class Shard:
    """Reader of one shard; ``fetch(offset, length)`` gives a range of the file's bytes."""

    def __init__(self, fetch):
        lead = fetch(0, 16)
        if lead[:8] != MAGIC:
            raise ValueError("not a shard of this format")
        size = struct.unpack("<Q", lead[8:16])[0]
        self.head = json.loads(fetch(16, size))
        self._fetch, self._base = fetch, 16 + size
        self.n, self.kind = self.head["n"], np.dtype(self.head["kind"])
        self.block = lru_cache(256)(self._block)

    @classmethod
    def of_bytes(cls, data: bytes) -> Shard:
        return cls(lambda at, size: data[at : at + size])

    def _section(self, k: int) -> bytes:
        import zstandard

        at, size = self.head["sections"][k]
        return zstandard.ZstdDecompressor().decompress(self._fetch(self._base + at, size))

    def documents(self) -> tuple[list, np.ndarray]:
        with pa.ipc.open_stream(self._section(0)) as r:
            t = r.read_all()
        return t["doc_id"].to_pylist(), t["n"].to_numpy()

    def _block(self, plane: int, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Bits of a block, and ones before each of them inside it."""
        p = self.head["planes"][plane]
        size = min(self.head["block_bits"], self.n - k * self.head["block_bits"])
        bits = np.unpackbits(np.frombuffer(self._section(p["blocks"][k]), np.uint8), bitorder="little")[:size]
        return bits, np.concatenate([[0], np.cumsum(bits, dtype=np.int64)])

    def _ones(self, plane: int, i: int) -> int:
        """Ones before position i."""
        if i == 0:
            return 0
        k = min(i // self.head["block_bits"], len(self.head["planes"][plane]["blocks"]) - 1)
        return self.head["planes"][plane]["ones_before"][k] + int(self.block(plane, k)[1][i - k * self.head["block_bits"]])

    def access(self, i: int) -> int:
        """The token at position i."""
        if not 0 <= i < self.n:
            raise IndexError(i)
        value = 0
        for plane, p in enumerate(self.head["planes"]):
            k, at = divmod(i, self.head["block_bits"])
            bit = int(self.block(plane, k)[0][at])
            value = value << 1 | bit
            ones = self._ones(plane, i)
            i = p["zeros"] + ones if bit else i - ones
        return value

    def _walk(self, token: int, lo: int, hi: int) -> tuple[int, int]:
        for plane, p in enumerate(self.head["planes"]):
            a, b = self._ones(plane, lo), self._ones(plane, hi)
            lo, hi = (p["zeros"] + a, p["zeros"] + b) if token >> p["bit"] & 1 else (lo - a, hi - b)
        return lo, hi

    def count(self, token: int, lo: int = 0, hi: int | None = None) -> int:
        """Occurrences of a token in [lo, hi)."""
        if token >> self.head["bits"] or not self.n:
            return 0
        a, b = self._walk(token, lo, self.n if hi is None else hi)
        return b - a

    def locate(self, token: int, k: int) -> int:
        """Position of the k-th (from 0) occurrence of a token; -1 if it has fewer."""
        if k < 0 or k >= self.count(token):
            return -1
        at = self._walk(token, 0, self.n)[0] + k
        for plane in range(len(self.head["planes"]) - 1, -1, -1):
            p = self.head["planes"][plane]
            one = token >> p["bit"] & 1
            at = self._select(plane, at - p["zeros"] if one else at, one)
        return at

    def _select(self, plane: int, k: int, one: int) -> int:
        """Position of the k-th bit of a value in a plane."""
        size, before = self.head["block_bits"], self.head["planes"][plane]["ones_before"]
        lo, hi = 0, len(before) - 1
        while lo < hi:
            mid = (lo + hi + 1) // 2
            if (before[mid] if one else mid * size - before[mid]) <= k:
                lo = mid
            else:
                hi = mid - 1
        inside = k - (before[lo] if one else lo * size - before[lo])
        bits = self.block(plane, lo)[0]
        return lo * size + int(np.flatnonzero(bits == one)[inside])

    def decode(self) -> np.ndarray:
        """All tokens: the planes are undone from the lowest bit upwards, each in one sequential pass."""
        rest = np.zeros(self.n, self.kind)
        for p in reversed(self.head["planes"]):
            packed = b"".join(self._section(k) for k in p["blocks"])
            ones = np.unpackbits(np.frombuffer(packed, np.uint8), bitorder="little")[: self.n].view(bool)
            up = np.empty_like(rest)
            up[~ones] = rest[: p["zeros"]]
            up[ones] = rest[p["zeros"] :] | self.kind.type(1 << p["bit"])
            rest = up
        return rest


# -- Spark


def write_shards(docs: DataFrame, tokenizer: str, end: int | None = 2, shard_tokens: int = SHARD_TOKENS, folder: str | None = None) -> DataFrame:
    """Writes the shards and returns their manifest (path, part, seq, docs, tokens), in id order by (part, seq).

    A file's name is unique to the attempt that wrote it; readers go by the manifest alone.
    """
    folder = folder or scratch(docs.sparkSession, "token-shards")
    ordered = id_and_text(docs).repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens, (fs, root) = word_tokens(tokenizer), file_system(folder)
        fs.create_dir(root, recursive=True)
        part, seq, ids, lengths, held = TaskContext.get().partitionId(), 0, [], [], []
        bits = max(1, (tokens.lib.get_vocab_size(with_added_tokens=True) - 1).bit_length())

        def flush():
            nonlocal seq, ids, lengths, held
            name = f"{root}/shard-{part:06d}-{seq:04d}-{uuid.uuid4().hex[:8]}.wave"
            all_ids = np.concatenate(held)
            with fs.open_output_stream(name) as out:
                out.write(build(all_ids, ids, lengths, bits))
            row = {"path": [os.path.basename(name)], "part": [part], "seq": [seq], "docs": [len(ids)], "tokens": [len(all_ids)]}
            seq, ids, lengths, held = seq + 1, [], [], []
            return pa.RecordBatch.from_pydict(row, schema=pa.schema([("path", pa.string()), ("part", pa.int32()), ("seq", pa.int32()), ("docs", pa.int64()), ("tokens", pa.int64())]))

        total = 0
        for batch in batches:
            keys, texts = batch.column("doc_id").to_pylist(), batch.column("text").to_pylist()
            for lo in range(0, len(texts), 192):
                for key, got in zip(keys[lo : lo + 192], tokens.batch(texts[lo : lo + 192], end), strict=True):
                    if ids and total + len(got) > shard_tokens:
                        yield flush()
                        total = 0
                    ids.append(key)
                    lengths.append(len(got))
                    held.append(got)
                    total += len(got)
        if ids:
            yield flush()

    manifest = stored(ordered.mapInArrow(run, "path string, part int, seq int, docs long, tokens long"), "shard-manifest")
    return manifest.withColumn("folder", F.lit(folder))


def placed(manifest: DataFrame) -> DataFrame:
    """The manifest with each shard's first token's place in the whole corpus.

    Only one sum per range partition comes to the driver; inside a partition a window adds up.
    """
    from pyspark.sql import Window

    spark = manifest.sparkSession
    sums = {r["part"]: r["n"] for r in manifest.groupBy("part").agg(F.sum("tokens").alias("n")).collect()}
    at, rows = 0, []
    for part in sorted(sums):
        rows.append((part, at))
        at += sums[part]
    bases = spark.createDataFrame(rows, "part int, base long")
    inside = Window.partitionBy("part").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    return manifest.join(bases, "part").withColumn("start", F.col("base") + F.coalesce(F.sum("tokens").over(inside), F.lit(0)))


def read_shards(manifest: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, decoded from the shard files."""
    spark = manifest.sparkSession
    shards = placed(manifest).repartition(max(2, spark.sparkContext.defaultParallelism, min(4096, manifest.count())), "path")

    def run(batch: pa.RecordBatch) -> dict:
        out: dict = {"doc_id": [], "start": [], "n_tokens": [], "ids_crc32": []}
        for row in batch.to_pylist():
            fs, root = file_system(row["folder"])
            with fs.open_input_file(f"{root}/{row['path']}") as f:
                data = f.read()
            shard = Shard.of_bytes(data)
            keys, lengths = shard.documents()
            ids, at = shard.decode().astype("<u4"), 0
            for key, n in zip(keys, lengths.tolist(), strict=True):
                out["doc_id"].append(key)
                out["start"].append(row["start"] + at)
                out["n_tokens"].append(n)
                out["ids_crc32"].append(zlib.crc32(ids[at : at + n]))
                at += n
        return out

    return mapped(shards.select("folder", "path", "start"), run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_output(docs: DataFrame, tokenizer: str, end: int | None = 2) -> DataFrame:
    return read_shards(write_shards(docs, tokenizer, end))

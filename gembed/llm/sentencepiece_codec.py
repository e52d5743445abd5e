"""Operator 2: SentencePiece encoding and decoding with a merge-type prefix table.

A merge-type vocabulary gives every prefix of a text exactly one last token. The table holds that
token for each prefix: an automaton reports the vocabulary pieces that end at a position, and the
piece is the last token exactly when it is compatible with the last token of the prefix before it
(the two, merged from scratch, stay two). The ids come from walking the table backwards.

No piece of such a vocabulary continues over a new space after a non-space, or over a line feed, so
a text is a sequence of independent chunks and the table is built once per distinct chunk; a bounded
cache keeps the results. Both facts are checked when a model is loaded; where they do not hold, the
whole text is one chunk.

Defined results: null or empty text has no ids (``n_tokens`` 0, digest of the empty string); a very
long text is encoded whole; repeated rows each give a row; an empty table gives an empty table; other
columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from functools import cache
from heapq import heapify, heappop, heappush

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import Generations, id_and_text, mapped

SPACE = "▁"
#: Distinct chunks kept per half of a task's cache.
CACHE = 100_000
#: Above every token number and every code point beyond them; two tokens make one dictionary key.
_TOKENS = 1 << 22


class PrefixTable:
    """Encoder and decoder for one model file; no training, no sampling, no begin or end ids."""

    def __init__(self, model_file: str):
        import ahocorasick
        from sentencepiece import sentencepiece_model_pb2 as pb

        proto = pb.ModelProto()
        with open(model_file, "rb") as f:
            proto.ParseFromString(f.read())
        spec = proto.normalizer_spec
        if spec.precompiled_charsmap or not spec.escape_whitespaces or spec.remove_extra_whitespaces:
            raise ValueError("only models with the identity normaliser are supported")
        kinds = pb.ModelProto.SentencePiece
        self.prefix = spec.add_dummy_prefix
        self.pieces = [p.piece for p in proto.pieces]
        self.ids = {p.piece: i for i, p in enumerate(proto.pieces) if p.type in (kinds.NORMAL, kinds.USER_DEFINED)}
        self.score = {p.piece: p.score for p in proto.pieces if p.type in (kinds.NORMAL, kinds.USER_DEFINED)}
        self.bytes = {int(p.piece[3:5], 16): i for i, p in enumerate(proto.pieces) if p.type == kinds.BYTE}
        self.byte_of = {i: b for b, i in self.bytes.items()}
        self.unknown = next(i for i, p in enumerate(proto.pieces) if p.type == kinds.UNKNOWN)
        self.control = {i for i, p in enumerate(proto.pieces) if p.type == kinds.CONTROL}
        self.automaton = ahocorasick.Automaton()
        for piece, i in self.ids.items():
            self.automaton.add_word(piece, (len(piece), i))
        self.automaton.make_automaton()
        self.beyond = len(self.pieces)  # a character outside the vocabulary is this number plus its code point
        self.special = {*self.byte_of, *self.control, self.unknown}
        self.chunked = not any(SPACE in p.lstrip(SPACE) or (p[:1] == SPACE and p[1:2] == SPACE and p.strip(SPACE)) for p in self.ids)
        self.lines = self.chunked and not any("\n" in p and p != "\n" for p in self.ids)
        self.compatible = Generations(self._compatible, 150_000)
        self.forget()

    def forget(self) -> None:
        """Gives back the chunk caches."""
        self.spaced = Generations(lambda w: self._chunk(SPACE + w), CACHE)
        self.bare = Generations(self._chunk, CACHE)

    # -- merging from scratch: the definition that pair tests rest on

    def merged(self, text: str) -> list[str]:
        """Pieces after merging the best-scored neighbours, leftmost first among equals."""
        parts: list[str | None] = list(text)
        before, after = list(range(-1, len(parts) - 1)), list(range(1, len(parts) + 1))
        queue = [(-self.score[parts[i] + parts[i + 1]], i, parts[i] + parts[i + 1]) for i in range(len(parts) - 1) if parts[i] + parts[i + 1] in self.score]
        heapify(queue)
        while queue:
            _, i, joined = heappop(queue)
            j = after[i] if parts[i] is not None else len(parts)
            if j >= len(parts) or parts[i] + parts[j] != joined:
                continue
            parts[i], parts[j] = joined, None
            after[i] = after[j]
            if after[i] < len(parts):
                before[after[i]] = i
            for a, b in ((before[i], i), (i, after[i])):
                if a >= 0 and b < len(parts) and (pair := parts[a] + parts[b]) in self.score:
                    heappush(queue, (-self.score[pair], a, pair))
        return [p for p in parts if p is not None]

    def _piece(self, token: int) -> str:
        return self.pieces[token] if token < self.beyond else chr(token - self.beyond)

    def _compatible(self, pair: int) -> bool:
        a, b = (self._piece(token) for token in divmod(pair, _TOKENS))
        return self.merged(a + b) == [a, b]

    # -- the table

    def last_tokens(self, text: str) -> tuple[list[int], list[int]]:
        """For each non-empty prefix, its one last token and that token's length.

        The automaton reports ends in order and at each end the longer pieces first.
        """
        n, beyond, known, test = len(text), self.beyond, self.compatible.young, self.compatible
        table, size, filled = [-1] * n, [1] * n, 0
        for end, (length, token) in self.automaton.iter(text):
            while filled < end:
                if table[filled] < 0:
                    table[filled] = beyond + ord(text[filled])
                filled += 1
            if table[end] >= 0:
                continue
            start = end + 1 - length
            if start:
                pair = table[start - 1] * _TOKENS + token
                fits = known.get(pair)
                if fits is None:
                    fits = test(pair)
                    known = test.young
                if not fits:
                    continue
            table[end], size[end] = token, length
        while filled < n:
            if table[filled] < 0:
                table[filled] = beyond + ord(text[filled])
            filled += 1
        return table, size

    def _ids(self, text: str) -> list[int]:
        table, size = self.last_tokens(text)
        back, at = [], len(text)
        while at:
            back.append(table[at - 1])
            at -= size[at - 1]
        back.reverse()
        if max(back, default=0) < self.beyond:
            return back
        out: list[int] = []
        for token in back:
            if token < self.beyond:
                out.append(token)
            elif self.bytes:
                out.extend(self.bytes[b] for b in chr(token - self.beyond).encode("utf-8", "surrogatepass"))
            else:
                out.append(self.unknown)
        return out

    def _chunk(self, text: str) -> tuple[str, str]:
        """The ids of a chunk as text, and the text that they decode to (spaces restored)."""
        ids = self._ids(text)
        return ",".join(map(str, ids)), self._surface(ids)

    def _surface(self, ids) -> str:
        if self.special.isdisjoint(ids):
            return "".join([self.pieces[i] for i in ids]).replace(SPACE, " ")
        out, run = [], bytearray()
        for i in ids:
            b = self.byte_of.get(i)
            if b is not None:
                run.append(b)
                continue
            if run:
                out.append(_utf8(run))
                run = bytearray()
            if i == self.unknown:
                out.append(" ⁇ ")
            elif i not in self.control:
                out.append(self.pieces[i])
        if run:
            out.append(_utf8(run))
        return "".join(out).replace(SPACE, " ")

    def chunks(self, text: str) -> list[tuple[str, str]]:
        text = text.replace(SPACE, " ")
        if not text:
            return []
        if not self.chunked:
            return [self._chunk((SPACE if self.prefix else "") + text.replace(" ", SPACE))]
        bare, out = self.bare, []
        lines = text.split("\n") if self.lines else [text]
        for k, line in enumerate(lines):
            if k:
                out.append(bare("\n"))
            words = line.split(" ")
            first = 0 if (k == 0 and self.prefix) else 1
            if first and words[0]:
                out.append(bare(words[0]))
            words = words[first:]
            if "" in words:
                out.extend(bare(m) for m in re.findall(f"{SPACE}+[^{SPACE}]*", SPACE + SPACE.join(words)))
            else:
                out += self.spaced.many(words)
        return out

    def encode(self, text: str) -> list[int]:
        return [int(i) for ids, _ in self.chunks(text) for i in ids.split(",")]

    def decode(self, ids) -> str:
        out = self._surface(ids)
        return out[1:] if self.prefix and out[:1] == " " else out

    def digest(self, text: str) -> tuple[int, str, str]:
        """Number of ids, digest of the joined ids and digest of the decoded text."""
        got = self.chunks(text)
        ids = ",".join([g[0] for g in got])
        out = "".join([g[1] for g in got])
        out = out[1:] if self.prefix and out[:1] == " " else out
        return (ids.count(",") + 1 if ids else 0), hashlib.sha256(ids.encode()).hexdigest(), hashlib.sha256(out.encode("utf-8", "surrogatepass")).hexdigest()


def _utf8(run: bytearray) -> str:
    return bytes(run).decode("utf-8", "replace")


@cache
def codec(model_file: str) -> PrefixTable:
    return PrefixTable(model_file)


def encode_decode(docs: DataFrame, model_file: str) -> DataFrame:
    """One row per document: doc_id, n_tokens, ids_sha256, decoded_sha256. No shuffle."""

    def run(batch: pa.RecordBatch) -> dict:
        table = codec(model_file)
        rows = [table.digest(t) for t in batch.column("text").to_pylist()]
        return {"doc_id": batch.column("doc_id"), "n_tokens": [r[0] for r in rows], "ids_sha256": [r[1] for r in rows], "decoded_sha256": [r[2] for r in rows]}

    return mapped(id_and_text(docs), run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string", after=lambda: codec(model_file).forget())


def encode_ids(docs: DataFrame, model_file: str) -> DataFrame:
    """The operator's plain output: doc_id and the array of ids."""

    def run(batch: pa.RecordBatch) -> dict:
        table = codec(model_file)
        return {"doc_id": batch.column("doc_id"), "ids": [table.encode(t) for t in batch.column("text").to_pylist()]}

    return mapped(id_and_text(docs), run, "doc_id long, ids array<int>", after=lambda: codec(model_file).forget())


def decode_ids(rows: DataFrame, model_file: str) -> DataFrame:
    """doc_id and ids to doc_id and text; null ids decode to the empty text."""

    def run(batch: pa.RecordBatch) -> dict:
        table = codec(model_file)
        return {"doc_id": batch.column("doc_id"), "text": [table.decode(i or []) for i in batch.column("ids").to_pylist()]}

    return mapped(rows.select("doc_id", "ids"), run, "doc_id long, text string")

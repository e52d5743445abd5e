"""Operator 9: quality rules in a short-circuit cascade.

Each rule looks at lazily computed features of one text and either rejects it or lets it pass. On a
sample of documents the work of every rule is counted (bytes and words that its features look at, at the
fixed price of each feature) and its share of rejections; the cascade then runs the rules by rejections
per work, and a document meets no rule after the first that rejects it. A document is kept when no rule
rejects it, so the order changes the cost and never the verdict; and as work is counted and not timed, the
same table always gives the same order, and the same rule as the first that rejects.

Words are runs of characters other than space and U+0009..U+000D. Defined results: null or empty
text has no words, fails ``few_words`` and is not kept; repeated rows each give a row; an empty table
gives an empty table (the cascade then keeps the rules' given order); other columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import give_back, id_and_text, mapped

WINDOW = 8
_WS, _SYMBOLS = b" \t\n\x0b\x0c\r", b"#*$%&|<>"
#: Random odd multipliers, one per place in a window.
_PLACES = np.random.default_rng(8).integers(1, 2**63, WINDOW, dtype=np.uint64) | np.uint64(1)


#: Price of the features, about nanoseconds: for each byte of the text, and for each word.
PRICES = {"raw": (0.2, 0.0), "words": (4.0, 0.0), "solid": (1.0, 0.0), "n_symbols": (1.5, 0.0), "lines": (1.0, 0.0), "n_dup_lines": (0.5, 0.0), "n_repeat_words": (0.0, 250.0), "letters": (4.0, 0.0)}


class Text:
    """Features of one text, each computed when a rule or a column first asks for it."""

    def __init__(self, text: str | None):
        self.text = text or ""

    def work(self) -> float:
        """The price of the features that have been asked for so far; a fixed one for the look itself."""
        return 100.0 + sum(a * len(self.raw) + (b * self.n_words if b else 0.0) for k, (a, b) in PRICES.items() if k in self.__dict__)

    @cached_property
    def raw(self) -> bytes:
        return self.text.encode("utf-8", "surrogatepass")

    @cached_property
    def words(self) -> list[bytes]:
        return self.raw.split()

    @cached_property
    def n_words(self) -> int:
        return len(self.words)

    @cached_property
    def solid(self) -> bytes:
        return self.raw.translate(None, _WS)

    @cached_property
    def word_chars(self) -> int:
        return len(self.text) - (len(self.raw) - len(self.solid))

    @cached_property
    def n_symbols(self) -> int:
        return len(self.raw) - len(self.raw.translate(None, _SYMBOLS))

    @cached_property
    def lines(self) -> list[bytes]:
        return [line for line in self.raw.split(b"\n") if line and not line.isspace()]

    @cached_property
    def n_dup_lines(self) -> int:
        return len(self.lines) - len(set(self.lines))

    @cached_property
    def n_repeat_words(self) -> int:
        n = self.n_words
        if n <= WINDOW:
            return 0
        number: dict[bytes, int] = {}
        ids = np.fromiter([number.setdefault(w, len(number)) for w in self.words], np.int64, n)
        windows = n - WINDOW + 1
        if len(number) > n - WINDOW:  # too few repeated words for two equal windows
            return 0
        mixed = (ids.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
        mixed ^= mixed >> np.uint64(29)
        key = np.zeros(windows, np.uint64)
        for k in range(WINDOW):
            key += mixed[k : k + windows] * _PLACES[k]
        order = np.argsort(key, kind="stable")
        same = key[order[1:]] == key[order[:-1]]
        if not same.any():
            return 0
        often = np.zeros(windows, bool)
        often[order[1:][same]] = True
        often[order[:-1][same]] = True
        at = np.flatnonzero(often)
        exact = [ids[i : i + WINDOW].tobytes() for i in at.tolist()]  # equal keys are compared word by word
        count = Counter(exact)
        edge = np.zeros(n + 1, np.int64)
        for i, w in zip(at.tolist(), exact, strict=True):
            if count[w] > 1:
                edge[i] += 1
                edge[i + WINDOW] -= 1
        return int((np.cumsum(edge[:n]) > 0).sum())

    @cached_property
    def letters(self) -> tuple[int, int, int]:
        """Bytes of ASCII capitals, of ASCII small letters, and of characters beyond ASCII."""
        b = np.frombuffer(self.solid, np.uint8)
        return int(((b >= 65) & (b <= 90)).sum()), int(((b >= 97) & (b <= 122)).sum()), int((b >= 128).sum())


@dataclass(frozen=True)
class Rule:
    name: str
    rejects: Callable[[Text], bool]


def _shouts(t: Text) -> bool:
    upper, lower, _ = t.letters
    return upper + lower >= 50 and upper > 0.7 * (upper + lower)


def _few_letters(t: Text) -> bool:
    return sum(t.letters) < 0.5 * len(t.solid)


#: The first two are the base; every threshold is a plain constant of the rule.
BASE = (
    Rule("few_words", lambda t: t.n_words < 20),
    Rule("repeated_windows", lambda t: 100 * t.n_repeat_words > 30 * t.n_words),
)
RULES = (
    *BASE,
    Rule("symbols", lambda t: 100 * t.n_symbols > 30 * t.n_words),
    Rule("capitals", _shouts),
    Rule("word_length", lambda t: not 1.5 * t.n_words <= t.word_chars <= 40 * t.n_words),
    Rule("repeated_lines", lambda t: len(t.lines) >= 4 and 2 * t.n_dup_lines > len(t.lines)),
    Rule("few_letters", _few_letters),
)


def measure_rules(docs: DataFrame, rules: tuple[Rule, ...] = RULES, sample_rows: int = 2000, one_in: int | None = None) -> list[dict]:
    """Work per document and share of rejections of each rule on a hash sample: one document in ``one_in``,
    or as many as make about ``sample_rows`` of the table's. Nothing is sorted or cut off, so equal tables give equal samples."""
    rows = id_and_text(docs)
    share = 1.0 / one_in if one_in else min(1.0, sample_rows / max(1, docs.count()))
    picked = rows.where(F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 40)) < F.lit(int(share * (1 << 40)))) if share < 1 else rows

    def run(batch: pa.RecordBatch) -> dict:
        took, hits, texts = [0] * len(rules), [0] * len(rules), batch.column("text").to_pylist()
        for text in texts:
            for k, rule in enumerate(rules):
                fresh = Text(text)  # a rule is charged for all features that it needs
                hits[k] += bool(rule.rejects(fresh))
                took[k] += round(fresh.work())
        return {"rule": list(range(len(rules))), "docs": [len(texts)] * len(rules), "work": took, "rejected": hits}

    found = {r["rule"]: r for r in mapped(picked, run, "rule int, docs long, work long, rejected long").groupBy("rule").agg(F.sum("docs").alias("docs"), F.sum("work").alias("work"), F.sum("rejected").alias("rejected")).collect()}
    out = []
    for k, rule in enumerate(rules):
        r = found.get(k)
        n = r["docs"] if r else 0
        cost, share = (r["work"] / n, r["rejected"] / n) if n else (1.0, 0.0)
        out.append({"rule": rule.name, "docs": n, "cost": cost, "rejected": share, "rank": share / max(cost, 1e-9)})
    return out


def plan_cascade(docs: DataFrame, rules: tuple[Rule, ...] = RULES, **sample) -> tuple[Rule, ...]:
    """The rules by rejections per cost; among equals (none rejected any) the cheaper first."""
    measured = measure_rules(docs, rules, **sample)
    return tuple(rules[k] for k in sorted(range(len(rules)), key=lambda k: (-measured[k]["rank"], measured[k]["cost"], k)))


def first_rejection(text: Text, cascade: tuple[Rule, ...]) -> str | None:
    return next((rule.name for rule in cascade if rule.rejects(text)), None)


def verdicts(docs: DataFrame, cascade: tuple[Rule, ...] | None = None) -> DataFrame:
    """doc_id, kept and the rule that rejected it (null if kept): the cascade alone, short-circuited."""
    cascade = cascade or plan_cascade(docs)

    def run(batch: pa.RecordBatch) -> dict:
        why = [first_rejection(Text(t), cascade) for t in batch.column("text").to_pylist()]
        return {"doc_id": batch.column("doc_id"), "kept": [w is None for w in why], "rejected_by": why}

    return mapped(id_and_text(docs), run, "doc_id long, kept boolean, rejected_by string")


def quality_metrics(docs: DataFrame, cascade: tuple[Rule, ...] | None = None) -> DataFrame:
    """The base columns of every document and the cascade's verdict on those that pass the base."""
    cascade = cascade or plan_cascade(docs)
    more = tuple(r for r in cascade if r not in BASE)

    def run(batch: pa.RecordBatch) -> dict:
        out: dict = {k: [] for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "rejected_by")}
        for text in batch.column("text").to_pylist():
            t = Text(text)
            failed = t.n_words < 20 or 100 * t.n_repeat_words > 30 * t.n_words
            why = "base" if failed else first_rejection(t, more)
            for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"):
                out[k].append(getattr(t, k))
            out["base_failed"].append(failed)
            out["kept"].append(why is None)
            out["rejected_by"].append(why)
        return out | {"doc_id": batch.column("doc_id")}

    return mapped(id_and_text(docs), run, "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, rejected_by string")


def keep_good(docs: DataFrame, cascade: tuple[Rule, ...] | None = None) -> DataFrame:
    """The rows of ``docs`` that the cascade keeps, all columns unchanged; one pass, no shuffle."""
    import pyarrow.compute as pc

    cascade = cascade or plan_cascade(docs)

    def run(batches):
        for batch in batches:
            keep = [first_rejection(Text(t), cascade) is None for t in batch.column("text").to_pylist()]
            yield batch.filter(pa.array(keep, pa.bool_())) if not pc.all(pa.array(keep, pa.bool_())).as_py() else batch
        give_back()

    return docs.mapInArrow(run, docs.schema)

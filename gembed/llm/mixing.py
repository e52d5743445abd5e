"""Operator 7: mixing sources to target weights with soft memberships.

A classifier fitted on the labelled table predicts, for every document, the posterior of each domain
(``good``: quality 1 and not toxic, ``poor``: quality 0, ``toxic``). Documents then get nonnegative
rates, so that the expected tokens of each domain, sum of rate x tokens x posterior, meet the targets
in least squares. The fit is projected gradient descent: a rate is the projection on the nonnegative
numbers of its start (one) less the sum of all gradient steps so far, which is a closed expression in
one number per domain. The metric is diagonal (a document's tokens), the preconditioner the second
moments of the domains over the documents whose rate is not at its bound; a step that would raise the
miss is halved. Each step needs a few sums over all documents and no state between steps, so any step
may be repeated after a loss. Steps go on until every domain meets its target within ``TOLERANCE``; a
target outside what the posteriors can reach ends them when the miss stops falling, with the least
miss found, and the log's last entry says ``met`` false.

Only DataFrame functions and the JVM's logistic regression run. Fitting uses at most ``LABELLED_ROWS``
labelled documents (those with the smallest hash); every count, feature, sum and rate is over all.

Defined results: null or empty text has no tokens and rate 1 (no rate of it changes a total); repeated
rows each count and get a row; unlabelled corpora (no label joins, or one domain only) give that domain
posterior 1; an empty table gives an empty table; columns of the labels never clash with the documents'.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stored

DOMAINS = ("good", "poor", "toxic")
TARGETS = {"good": 0.92, "poor": 0.04, "toxic": 0.04}
#: Bound on the labelled rows that the classifier is fitted on, and words per domain in its lexicon.
LABELLED_ROWS = 4000
LEXICON = 30
#: Largest miss of a target, as a share of it, at which the fit ends; and steps without a fall of the miss by 1 % after which it gives up.
TOLERANCE = 1e-6
PATIENCE = 12
#: Rows of (id, copies) up to which the list of documents that do not stay once is broadcast.
BROADCAST_ROWS = 500_000
_NUMBERS = ("distinct", "caps", "symbols", "shouts", "long", *[f"lex_{d}" for d in DOMAINS])
DOMAIN_COLUMNS = tuple(f"p_{d}" for d in DOMAINS)
_SPLIT = r"[\s.,;:!?]+"


def _words(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), _SPLIT), lambda w: w != "")


def _shape(docs: DataFrame, *keep: str) -> DataFrame:
    """Tokens and format features, from the whole text in one projection."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(*keep, text.alias("_text")).withColumn("_words", _words(F.col("_text")))
    n = F.greatest(F.size("_words"), F.lit(1)).cast("double")
    return rows.select(
        *keep,
        "_words",
        F.size("_words").cast("long").alias("tokens"),
        (F.size(F.array_distinct("_words")) / n).alias("distinct"),
        (F.regexp_count("_text", F.lit(r"[A-Z]{2,}")) / n).alias("caps"),
        (F.regexp_count("_text", F.lit(r"[#*$%&|<>]+")) / n).alias("symbols"),
        (F.regexp_count("_text", F.lit(r"!+")) / n).alias("shouts"),
        (F.log1p(n) / 10).alias("long"),
    )


def domain(quality: Column, toxic: Column) -> Column:
    return F.when(toxic == 1, F.lit(2)).when(quality == 0, F.lit(1)).otherwise(F.lit(0))


@dataclass
class Classifier:
    """Lexicon (word, domain) and, per domain, the intercept and coefficients of the features."""

    lexicon: list[tuple[str, int]]
    intercepts: list[float]
    weights: list[list[float]]
    present: list[int] = field(default_factory=lambda: [0, 1, 2])

    def posteriors(self, columns: list[Column]) -> list[Column]:
        if len(self.present) < 2:
            return [F.lit(1.0 if k == (self.present or [0])[0] else 0.0) for k in range(len(DOMAINS))]
        z = []
        for k in range(len(DOMAINS)):
            if k in self.present:
                at = F.lit(self.intercepts[k])
                for w, c in zip(self.weights[k], columns, strict=True):
                    at = at + F.lit(w) * c
                z.append(at)
        top = F.greatest(*z)
        e = [F.exp(x - top) for x in z]
        total = sum(e[1:], e[0])
        out = dict(zip(self.present, [x / total for x in e], strict=True))
        return [out.get(k, F.lit(0.0)) for k in range(len(DOMAINS))]


def _lexicon_hits(rows: DataFrame, lexicon: list[tuple[str, int]]) -> DataFrame:
    """Share of each domain's listed words among a document's tokens, in the same scan: look-ups in small literal sets."""
    listed = {k: [w for w, d in lexicon if d == k] for k in range(len(DOMAINS))}
    every = [w for w, _ in lexicon]
    kept = [c for c in rows.columns if c != "_words"]
    hit = F.filter("_words", lambda w: w.isin(every)) if every else F.array().cast("array<string>")
    found = rows.select(*kept, hit.alias("_hits"))
    n = F.greatest(F.col("tokens"), F.lit(1)).cast("double")
    share = lambda words: F.log1p(F.size(F.filter("_hits", lambda w: w.isin(words))) * F.lit(1000.0) / n) if words else F.lit(0.0)
    return found.select(*kept, *[share(listed[k]).alias(f"lex_{d}") for k, d in enumerate(DOMAINS)])


def fit(docs: DataFrame, labels: DataFrame, rows: int = LABELLED_ROWS) -> Classifier:
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler

    told = labels.select(F.col("doc_id").cast("long").alias("_key"), domain(F.col("quality"), F.col("toxic")).alias("label")).where("label is not null and _key is not null").groupBy("_key").agg(F.min("label").alias("label"))
    picked = told.orderBy(F.xxhash64("_key"), "_key").limit(rows)
    texts = docs.select(F.col("doc_id").cast("long").alias("_key"), F.col("text").cast("string").alias("text")).join(F.broadcast(picked), "_key")
    known = stored(_shape(texts, "_key", "label"), "mix-labelled")
    sizes = {r["label"]: r["n"] for r in known.groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()}
    present = sorted(sizes)
    if len(present) < 2:
        return Classifier([], [], [], present)
    total = sum(sizes.values())
    seen = known.select("label", F.explode(F.array_distinct("_words")).alias("word")).groupBy("word").agg(*[F.count_if(F.col("label") == k).alias(f"n{k}") for k in present], F.count(F.lit(1)).alias("n")).where("n >= 5")
    lexicon: list[tuple[str, int]] = []
    for k in present:
        inside = (F.col(f"n{k}") + 0.5) / (sizes[k] + 1.0)
        outside = (F.col("n") - F.col(f"n{k}") + 0.5) / (total - sizes[k] + 1.0)
        best = seen.select("word", ((inside - outside) * F.log(inside / outside)).alias("gain"), (inside > outside).alias("up")).where("up").orderBy(F.desc("gain"), "word").limit(LEXICON)
        lexicon += [(r["word"], k) for r in best.collect()]
    lexicon = list(dict(reversed(lexicon)).items())
    features = _lexicon_hits(known, lexicon)
    data = VectorAssembler(inputCols=list(_NUMBERS), outputCol="features").transform(features.select(F.col("label").cast("double").alias("label"), *_NUMBERS)).select("label", "features").coalesce(2).cache()
    model = LogisticRegression(maxIter=40, regParam=1e-4, family="multinomial").fit(data)
    data.unpersist()
    matrix = model.coefficientMatrix.toArray().tolist()
    offsets = model.interceptVector.toArray().tolist()
    matrix += [[0.0] * len(_NUMBERS)] * (len(DOMAINS) - len(matrix))
    offsets += [0.0] * (len(DOMAINS) - len(offsets))
    return Classifier(lexicon, [float(x) for x in offsets], matrix, present)


def memberships(docs: DataFrame, model: Classifier) -> DataFrame:
    """doc_id, tokens and posterior of each domain (p_good, p_poor, p_toxic) of every row; one scan, no shuffle."""
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text"))
    features = _lexicon_hits(_shape(keyed, "doc_id"), model.lexicon)
    post = model.posteriors([F.col(c) for c in _NUMBERS])
    return features.select("doc_id", "tokens", *[p.alias(f"p_{d}") for p, d in zip(post, DOMAINS, strict=True)])


def _inverse(m: list[list[float]]) -> list[list[float]]:
    import numpy as np

    a = np.array(m)
    return np.linalg.pinv(a + 1e-9 * max(1e-12, float(np.trace(a))) * np.eye(len(a))).tolist()


def solve(members: DataFrame, targets: dict[str, float] | None = None, budget: float | None = None, tolerance: float = TOLERANCE) -> tuple[Column, list[dict]]:
    """The rate of a row as an expression, and what each step measured (``off``: largest miss as a share of its target).

    ``targets`` are shares; ``budget`` is the total of expected tokens (default: all tokens once). With
    targets 0.9, 0.08 and 0.02 and a budget of 100, the expected tokens become 90, 8 and 2. A domain
    without a target is left free.
    """
    targets = targets or TARGETS
    aimed = [d for d in DOMAINS if d in targets]
    k = len(aimed)
    p = [F.col(f"p_{d}") for d in aimed]
    n = F.col("tokens").cast("double")
    total = float(members.agg(F.sum(n)).first()[0] or 0.0)
    if not total:
        return F.lit(1.0), []
    share = sum(targets.values())
    want = [(budget or total) * targets[d] / share for d in aimed]
    scale = [max(w, 1e-6 * total) for w in want]

    def rate_of(moved: list[float]) -> Column:
        return F.greatest(F.lit(0.0), F.lit(1.0) - sum((F.lit(m) * x for m, x in zip(moved[1:], p[1:], strict=True)), F.lit(moved[0]) * p[0]))

    def measure(moved: list[float]) -> tuple[list[float], list[list[float]]]:
        rows = members.select(n.alias("n"), *DOMAIN_COLUMNS, rate_of(moved).alias("r"))
        free = F.when(F.col("r") > 0, F.col("n")).otherwise(0.0)
        got = rows.agg(*[F.sum(F.col("n") * F.col("r") * x).alias(d) for x, d in zip(p, aimed, strict=True)], *[F.sum(free * p[i] * p[j]).alias(f"g{i}{j}") for i in range(k) for j in range(i, k)]).first()
        return [float(got[d]) for d in aimed], [[float(got[f"g{min(i, j)}{max(i, j)}"]) for j in range(k)] for i in range(k)]

    moved, size, log, stale = [0.0] * k, 1.0, [], 0
    best, best_at, move = float("inf"), moved, [0.0] * k
    at = moved
    while True:
        got, gram = measure(at)
        off = [g - w for g, w in zip(got, want, strict=True)]
        miss = max(abs(x) / s for x, s in zip(off, scale, strict=True))
        log.append({"step": len(log), "off": miss, "met": miss <= tolerance} | dict(zip(aimed, got, strict=True)))
        stale = 0 if miss < 0.99 * best else stale + 1
        if miss < best or size < 1e-3:  # the step is taken, and the next one starts here
            if miss < best:
                best, best_at = miss, at
            inverse = _inverse(gram)
            move = [sum(inverse[i][j] * off[j] for j in range(k)) for i in range(k)]
            moved, size = at, 1.0
        else:
            size /= 2
        if miss <= tolerance or stale >= PATIENCE:
            log[-1]["met"] = best <= tolerance
            return F.when(n > 0, rate_of(best_at)).otherwise(F.lit(1.0)), log
        at = [m + size * x for m, x in zip(moved, move, strict=True)]


def mix(docs: DataFrame, labels: DataFrame, targets: dict[str, float] | None = None, budget: float | None = None) -> DataFrame:
    """doc_id, tokens, posteriors and rate of every document."""
    members = stored(memberships(docs, fit(docs, labels)), "mix-members")
    rate, _ = solve(members, targets, budget)
    return members.select("doc_id", "tokens", *DOMAIN_COLUMNS, rate.alias("rate"))


def apply_rates(docs: DataFrame, labels: DataFrame, targets: dict[str, float] | None = None, growth: float = 1.1) -> DataFrame:
    """The corpus after mixing: each row as often as its rate says, the fraction decided by a hash of its id.

    The budget is set so that the largest target's domain is repeated ``growth`` times; its documents
    therefore all stay. The other domains are thinned, or repeated, to their shares of that budget.
    """
    targets = targets or TARGETS
    lead = max(targets, key=lambda d: targets[d])
    members = stored(memberships(docs, fit(docs, labels)), "mix-members")
    held = members.agg(F.sum(F.col("tokens") * F.col(f"p_{lead}"))).first()[0] or 0.0
    rate = solve(members, targets, float(held) * growth / (targets[lead] / sum(targets.values())))[0] if held else F.lit(1.0)
    copies = members.select(F.col("doc_id").alias("__gembed_id"), copies_of(F.col("doc_id"), rate).alias("__gembed_copies")).groupBy("__gembed_id").agg(F.max("__gembed_copies").alias("__gembed_copies"))
    other = stored(copies.where("__gembed_copies != 1"), "mix-copies")  # documents that stay once are not listed
    if other.count() <= BROADCAST_ROWS:
        other = F.broadcast(other)
    rows = docs.join(other, docs["doc_id"].cast("long").eqNullSafe(F.col("__gembed_id")), "left").where("coalesce(__gembed_copies, 1) > 0")
    return rows.withColumn("__gembed_copy", F.explode(F.sequence(F.lit(1), F.coalesce("__gembed_copies", F.lit(1))))).drop("__gembed_id", "__gembed_copies", "__gembed_copy")


def copies_of(doc_id: Column, rate: Column) -> Column:
    """How often a row stands in the mixture: its rate, rounded up or down by a hash of its id."""
    chance = F.pmod(F.xxhash64(doc_id, F.lit("mix")), F.lit(1 << 20)) / float(1 << 20)
    return F.floor(rate + chance).cast("int")

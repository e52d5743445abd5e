"""The pipeline's stages, each against its own input."""

import corpus_pipeline
from gembed.llm.common import table

SF = "/root/testdata/sf0.001"


def test_stages_and_run(spark):
    docs = table(spark, SF, "documents")
    columns, before = docs.columns, docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == columns, name
        n = out.count()
        assert n > 0 and (name == "mix_sources" or n <= before)
        docs, before = out, n
    whole = corpus_pipeline.run(spark, SF)
    assert whole.columns[:4] == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"] and whole.count() == before


def test_clean_documents_stay(spark):
    """Labelled good documents of twenty words or more that are no copies survive the quality rules."""
    d = "/root/testdata/sf0.01"
    docs, labels = table(spark, d, "documents"), table(spark, d, "labels")
    kept = corpus_pipeline.quality_rules(spark, docs, d)
    lost = docs.join(kept.select("doc_id"), "doc_id", "left_anti").join(labels.where("quality = 1"), "doc_id")
    assert lost.where("size(split(trim(text), '\\\\s+')) >= 20").isEmpty()


def test_empty_tables(spark):
    docs = table(spark, SF, "documents").where("false")
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs, SF).count() == 0


def test_run_equals_brute_force(spark, tmp_path):
    """run() over a small folder of tables against plain Python for every stage, odd rows included."""
    import hashlib
    import math
    import random
    import re

    import sentencepiece
    from helpers import documents, prose, texts
    from test_documents import linked_components, metrics_of, words

    from gembed.llm import mixing
    from gembed.llm.catalog import tokenizer_file

    rows = texts() + [r for r in texts() if r[0] in (9, 12)]
    r = random.Random(5)
    for i in range(200, 260):  # near copies at the stage's own threshold, among prose of its own
        w = prose(i - i % 3, 90).split()
        for _ in range(r.randrange(6)):
            w[r.randrange(len(w))] = f"new{i}"
        rows.append((i, " ".join(w)))
    folder = f"{tmp_path}/sf"
    documents(spark, rows, repeat=False).repartition(3).write.parquet(f"{folder}/documents.parquet")
    told = [(i, int(i % 4 != 1), int(i % 9 == 2)) for i, _ in rows]
    spark.createDataFrame(told, "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")

    def good(t):
        n, chars, symbols, dup_lines, _, failed = metrics_of(t)
        solid = re.sub(r"[\x20\x09-\x0D]", "", t or "")
        upper, lower, far = (sum(map(f, solid.encode())) for f in (lambda b: 65 <= b <= 90, lambda b: 97 <= b <= 122, lambda b: b >= 128))
        lines = [x for x in (t or "").split("\n") if words(x)]
        return not (
            failed or 100 * symbols > 30 * n or (upper + lower >= 50 and upper > 0.7 * (upper + lower)) or not 1.5 * n <= chars <= 40 * n
            or (len(lines) >= 4 and 2 * dup_lines > len(lines)) or upper + lower + far < 0.5 * len(solid.encode())
        )

    kept = [(i, t) for i, t in rows if good(t)]
    once: dict = {}
    for i, t in sorted(kept):
        once.setdefault(re.sub(r"[\x20\x09-\x0D]+", " ", t), (i, t))
    groups = linked_components(list(once.values()), 5, 80, 100)
    left = {i: t for i, t in once.values() if groups[i][1] == i}
    assert 10 < len(left) < len(once) < len(kept) < len(rows)

    # the rates of what is left; every document stands as often as its rate says, rounded by a hash of its id
    docs = documents(spark, sorted(left.items()), repeat=False)
    labels = spark.read.parquet(f"{folder}/labels.parquet")
    members = mixing.memberships(docs, mixing.fit(docs, labels))
    held = {x["doc_id"]: x for x in members.collect()}
    lead = sum(x["tokens"] * x["p_good"] for x in held.values())
    rate, log = mixing.solve(members, corpus_pipeline.MIX_TARGETS, lead * 1.1 / corpus_pipeline.MIX_TARGETS["good"])
    told = {x["doc_id"]: (x["rate"], x["n"]) for x in members.select("doc_id", rate.alias("rate"), mixing.copies_of(members["doc_id"], rate).alias("n")).collect()}
    assert all(n in (math.floor(q), math.ceil(q)) for q, n in told.values())
    if log[-1]["met"]:
        for d, share in corpus_pipeline.MIX_TARGETS.items():
            assert abs(sum(told[i][0] * x["tokens"] * x[f"p_{d}"] for i, x in held.items()) / (lead * 1.1 / 0.95 * share) - 1) < 1e-4

    sp = sentencepiece.SentencePieceProcessor(model_file=tokenizer_file("piece_bpe_32k.model"))
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    want = sorted((i, len(ids := sp.encode(t)), sha(",".join(map(str, ids))), sha(sp.decode(ids))) for i, t in left.items() for _ in range(told[i][1]))
    got = sorted(tuple(x)[:4] for x in corpus_pipeline.run(spark, folder).collect())
    assert got == want

"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

``python bench.py --experiments`` also runs the sweeps and writes their tables to standard error.
"""

from __future__ import annotations

import json
import os
import sys
import time

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = int(os.environ.get("BENCH_CPUS", str(os.cpu_count() or 4)))


def main() -> None:
    os.environ.setdefault("OMP_NUM_THREADS", "1")
    from pyspark.sql import SparkSession

    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", str(2 * CPUS)).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "6g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    from gembed.operators import evaluate, experiments, partition, train_block
    from gembed.session import stored
    from gembed.sources import graphs, tables

    took: dict[str, float] = {}
    extra: dict[str, float] = {}

    def timed(name, f):
        began = time.time()
        out = f()
        took[name] = round(time.time() - began, 3)
        return out

    spark.range(1000).count()
    edges = timed("word_next", lambda: stored(graphs.word_next(spark, SF), "bench-edges"))
    timed("knowledge_base", lambda: tables.noop(graphs.kb(spark, SF)))
    split = timed("split", lambda: stored(partition.split_edges(edges, {"train": 0.9, "valid": 0.05, "test": 0.05}), "bench-split"))
    train, test = split.where("split = 'train'").drop("split"), split.where("split = 'test'").drop("split")
    prepared = timed("partition_and_bucket", lambda: train_block.prepare(train, experiments.one_type_spec(train, dim=64), 8))
    model = timed("train_epoch_8_parts_4_machines", lambda: train_block.fit(prepared, epochs=1, machines=4))
    extra["train_edges_per_second"] = round(model.log[0]["edges"] / model.log[0]["seconds"])
    extra["rss_mb"] = round(model.log[0]["rss_mb"])
    m = timed("evaluate_1000_candidates", lambda: evaluate.evaluate(model, test, train, k=1000))
    extra["mrr"], extra["hits10"] = round(m["mrr"], 4), round(m["hits10"], 4)
    speed = timed("negatives_speed", lambda: experiments.negatives_speed(spark, (10, 50, 100, 200), edges=20_000).collect())
    for r in speed:
        extra[f"{r['mode']}_{r['negatives']}_edges_per_second"] = round(r["edges_per_second"])
    try:
        from gembed.llm import catalog as llm
    except ImportError:
        llm = None
    if llm:
        for name, f in llm.queries().items():
            timed(name, lambda f=f: tables.noop(f(spark, SF)))
    if "--experiments" in sys.argv:
        small = f"{os.path.dirname(SF.rstrip('/'))}/sf0.01"
        e = stored(graphs.word_next(spark, small), "bench-small")
        for title, df in (
            ("partitions", experiments.partition_sweep(spark, e, (1, 4, 8, 16), epochs=3)),
            ("machines", experiments.parallel_sweep(spark, e, (1, 2, 4), epochs=3)),
            ("candidates", experiments.candidate_sampling(spark, e)),
            ("alpha", experiments.negative_ablation(spark, e)),
            ("orders", experiments.bucket_order(spark, e)),
            ("methods", experiments.link_prediction(spark, e, ("identity", "transe", "complex", "rescal"), epochs=4)),
            ("complex replicates", experiments.replicates(spark, e)),
            ("baselines", experiments.baselines(spark, e)),
        ):
            print(title, json.dumps([r.asDict() for r in df.collect()], default=str), file=sys.stderr, flush=True)
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "extra": extra, "sf": SF.rstrip("/").rsplit("/", 1)[-1], "cpus": CPUS}))


if __name__ == "__main__":
    main()

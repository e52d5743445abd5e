"""Cost measures: closed forms, and counters that the trainer reports."""

from __future__ import annotations

import threading
import time

from pyspark.sql import SparkSession

from .schedule import order, simulate_swaps


def model_bytes(nodes: int, dim: int, state: bool = False) -> int:
    return nodes * dim * 4 + (nodes * 4 if state else 0)


def negative_cost(batch: int, chunk: int, uniform: int, dim: int, mode: str = "batched") -> dict[str, int]:
    """Rows fetched, floats moved, scores and negatives of one batch, both sides corrupted."""
    each = chunk + uniform - 1
    if mode == "batched":
        rows, scores = 2 * batch + 2 * (-(-batch // chunk)) * uniform, batch + 2 * batch * (chunk + uniform)
    else:
        rows, scores = 2 * batch + 2 * batch * each, batch + 2 * batch * each
    return {"rows": rows, "floats": rows * dim, "scores": scores, "negatives": 2 * batch * each}


def partition_io(p: int, bytes_per_part: int, kind: str = "inside_out", slots: int = 2) -> dict[str, int]:
    s = simulate_swaps(order(kind, p), slots)
    return {"loads": s["loads"], "stores": s["stores"], "bytes": (s["loads"] + s["stores"]) * bytes_per_part}


def ps_bytes(edges: int, batch: int, chunk: int, uniform: int, dim: int, mode: str = "batched") -> int:
    """Bytes that a parameter server moves in an epoch: every batch pulls and pushes its rows."""
    return -(-edges // batch) * negative_cost(batch, chunk, uniform, dim, mode)["floats"] * 4 * 2


def speedup(seconds: dict[int, float]) -> list[dict]:
    """machines, seconds, speed-up over one machine and efficiency."""
    base = seconds[min(seconds)]
    return [{"machines": m, "seconds": s, "speedup": base / s, "efficiency": base / s / m} for m, s in sorted(seconds.items())]


class RssSampler:
    """Peak resident set of this process, sampled every 0.1 s."""

    def __enter__(self):
        self.peak, self._on = 0.0, True
        self._thread = threading.Thread(target=self._watch, daemon=True)
        self._thread.start()
        return self

    def _watch(self):
        while self._on:
            try:
                with open("/proc/self/status") as f:
                    self.peak = max(self.peak, next(int(x.split()[1]) / 1024 for x in f if x.startswith("VmRSS")))
            except (OSError, StopIteration):
                pass
            time.sleep(0.1)

    def __exit__(self, *_):
        self._on = False
        self._thread.join()


class Timer:
    def __enter__(self):
        self.began = time.time()
        return self

    def __exit__(self, *_):
        self.seconds = time.time() - self.began


def metric_rows(spark: SparkSession, run: str, log: list[dict]):
    """The training log in the long form (run, epoch, metric, value)."""
    rows = [(run, int(e["epoch"]), k, float(v)) for e in log for k, v in e.items() if k != "epoch" and isinstance(v, (int, float))]
    return spark.createDataFrame(rows, "run string, epoch int, metric string, value double")

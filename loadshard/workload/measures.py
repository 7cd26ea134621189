"""Response time and throughput of anything that turns a query id into a DataFrame."""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor, wait
from dataclasses import dataclass
from statistics import median

from pyspark.sql import DataFrame

Run = Callable[[str], DataFrame]


def drain(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def response_times(run: Run, queries: list[str], rounds: int = 3) -> dict[str, float]:
    """Median seconds of warm runs."""
    out = {}
    for q in queries:
        drain(run(q))
        took = []
        for _ in range(rounds):
            t = time.perf_counter()
            drain(run(q))
            took.append(time.perf_counter() - t)
        out[q] = median(took)
    return out


@dataclass
class Throughput:
    level: int
    completed: int
    timed_out: int
    seconds: float

    @property
    def per_minute(self) -> float:
        return 60 * self.completed / self.seconds if self.seconds else 0.0


def throughput(run: Run, queries: list[str], level: int, batches: int = 2, interval: float = 1.0, timeout: float = 120.0) -> Throughput:
    """The query set is issued ``batches`` times, one each ``interval`` seconds, to ``level`` workers; queries not done
    ``timeout`` seconds after the last issue count as timed out."""
    began = time.perf_counter()
    pool = ThreadPoolExecutor(level)
    jobs = []
    for b in range(batches):
        time.sleep(max(0.0, began + b * interval - time.perf_counter()))
        jobs += [pool.submit(lambda q=q: drain(run(q))) for q in queries]
    done, late = wait(jobs, timeout=timeout)
    took = time.perf_counter() - began
    pool.shutdown(wait=False, cancel_futures=True)
    return Throughput(level, sum(j.exception() is None for j in done), len(late), took)

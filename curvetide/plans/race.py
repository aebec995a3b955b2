"""Racing Spark jobs: start all, take the first n that end, cancel the rest by tag."""

from __future__ import annotations

import queue
import uuid
from collections.abc import Callable

from pyspark import InheritableThread
from pyspark.sql import SparkSession


def first_n(spark: SparkSession, jobs: list[Callable[[], object]], n: int) -> dict[int, object]:
    """{place: result} of the first n jobs to end.  A failed job counts as one that never
    ends; if fewer than n can end, its error is raised."""
    context, done = spark.sparkContext, queue.Queue()
    tags = [f"race-{uuid.uuid4().hex}" for _ in jobs]

    def work(k: int) -> None:
        context.addJobTag(tags[k])
        try:
            done.put((k, jobs[k](), None))
        except Exception as e:  # handed to the caller below
            done.put((k, None, e))
        finally:
            context.removeJobTag(tags[k])

    threads = [InheritableThread(target=work, args=(k,)) for k in range(len(jobs))]
    for t in threads:
        t.start()
    out: dict[int, object] = {}
    ended = 0
    while len(out) < n:
        k, value, error = done.get()
        ended += 1
        if error is None:
            out[k] = value
        elif len(jobs) - ended + len(out) < n:
            raise error
    for k, t in enumerate(threads):
        while t.is_alive():  # again, as a job may start after it was cancelled
            if k not in out:
                context.cancelJobsWithTag(tags[k])
            t.join(0.5)
    return out


def raced_sketch(spark: SparkSession, data, problem, w, sketch) -> tuple[list[int], dict]:
    """The sketched root of a Hessian from the first N of the N + e blocks to end, each
    block a job of its own: (blocks used, {block: rows})."""
    from .optimise import scan

    got = first_n(spark, [lambda k=k: scan(data, problem, (), (), w, sketch, [k]).rows for k in range(sketch.blocks)], sketch.n)
    return sorted(got), got

"""The next shard is fetched while the current one trains."""

from __future__ import annotations

from concurrent.futures import Future, ThreadPoolExecutor

from pyspark import StorageLevel, inheritable_thread_target
from pyspark.sql import DataFrame


class Prefetcher:
    """submit() caches a shard in the background (memory, then disk), in a scheduler pool of its own; take() waits for it and
    lets go of the one before. Only the next shard is kept."""

    def __init__(self, spark, pool: str = "prefetch"):
        self.spark, self.pool = spark, pool
        self.threads = ThreadPoolExecutor(1)
        self.waiting: Future | None = None
        self.current: DataFrame | None = None

    def submit(self, shard: DataFrame) -> None:
        if self.waiting is not None:
            raise RuntimeError("a shard is being fetched already")

        def fetch() -> DataFrame:
            self.spark.sparkContext.setLocalProperty("spark.scheduler.pool", self.pool)
            kept = shard.persist(StorageLevel.MEMORY_AND_DISK)
            kept.count()
            return kept

        self.waiting = self.threads.submit(inheritable_thread_target(self.spark)(fetch))

    def take(self) -> DataFrame:
        if self.waiting is None:
            raise RuntimeError("nothing was submitted")
        got, self.waiting = self.waiting.result(), None
        if self.current is not None:
            self.current.unpersist()
        self.current = got
        return got

    def close(self) -> None:
        if self.waiting is not None:
            self.take()
        if self.current is not None:
            self.current.unpersist()
        self.threads.shutdown()

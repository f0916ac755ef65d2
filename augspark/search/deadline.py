"""A watchdog that cancels a search's jobs when its budget ends, also those that begin later; the plan found so far stays."""

from __future__ import annotations

import threading
import uuid

from pyspark.sql import SparkSession


#: Seconds between cancellations once a budget has ended: one that ends between two jobs would else let the next ones run.
AGAIN_S = 0.3


class Deadline:
    def __init__(self, spark: SparkSession, seconds: float) -> None:
        self.sc, self.tag, self.expired = spark.sparkContext, f"search-{uuid.uuid4().hex}", False
        self.left = False
        self.timer = threading.Timer(max(0.0, seconds), self._expire)
        self.timer.daemon = True

    def _expire(self) -> None:
        if self.left:
            return
        self.expired = True
        self.sc.cancelJobsWithTag(self.tag)
        self.timer = threading.Timer(AGAIN_S, self._expire)
        self.timer.daemon = True
        self.timer.start()

    def move(self, seconds: float) -> None:
        """Set a new end, so many seconds from now: a larger plan leaves the search less time."""
        if not self.expired:
            self.timer.cancel()
            self.timer = threading.Timer(max(0.0, seconds), self._expire)
            self.timer.daemon = True
            self.timer.start()

    def __enter__(self) -> Deadline:
        self.sc.addJobTag(self.tag)
        self.timer.start()
        return self

    def __exit__(self, *_) -> None:
        self.left = True
        self.timer.cancel()
        self.sc.removeJobTag(self.tag)

"""Cached data that leaves memory with its last user."""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import DataFrame


class Held:
    """A cached table with a count of users: ``use`` hands it out, ``release`` gives one use back, and the last one frees it."""

    def __init__(self, df: DataFrame, level: StorageLevel = StorageLevel.MEMORY_AND_DISK):
        self.df, self.users = df.persist(level), 0

    def use(self) -> DataFrame:
        self.users += 1
        return self.df

    def release(self) -> None:
        self.users -= 1
        if self.users <= 0:
            self.df.unpersist()

    def __enter__(self) -> DataFrame:
        return self.use()

    def __exit__(self, *_) -> None:
        self.release()

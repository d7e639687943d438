"""Table functions for SQL: lanes of a word, and the filters that may hold an element."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="lane int")
class UnpackLanes:
    def eval(self, word: int):
        if word is not None:
            word &= (1 << 64) - 1
            while word:
                low = word & -word
                yield (low.bit_length() - 1,)
                word ^= low


def all_membership(path: str):
    """A table function over a saved pack: all_membership(element). The pack is opened once a worker, not once a row."""

    @udtf(returnType="filter_id bigint")
    class AllMembership:
        def eval(self, element: int):
            from filterfleet.sources.index_source import opened

            if element is not None:
                for _, filter_id in opened(path).search([element]):
                    yield (filter_id,)

    return AllMembership


def register(spark: SparkSession, path: str | None = None) -> None:
    spark.udtf.register("unpack_lanes", UnpackLanes)
    if path:
        spark.udtf.register("all_membership", all_membership(path.removeprefix("file://")))

"""Distances between filters, nearest filters, containment."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, functions as F

from filterfleet.functions.frames import stored

METRICS = ("hamming", "jaccard", "cosine")


def from_counts(metric: str, a: Column, b: Column, both: Column) -> Column:
    """Distance from the numbers of bits of A, of B, and of both."""
    if metric == "hamming":
        return (a + b - 2 * both).cast("double")
    if metric == "jaccard":
        return F.when(a + b - both == 0, F.lit(0.0)).otherwise(1 - both / (a + b - both))
    if metric == "cosine":
        return F.when((a == 0) & (b == 0), F.lit(0.0)).when((a == 0) | (b == 0), F.lit(1.0)).otherwise(1 - both / (F.sqrt(a.cast("double")) * F.sqrt(b.cast("double"))))
    raise ValueError(f"unknown metric {metric}")


def _dealt(left: DataFrame, right: DataFrame, side: int = 1024) -> DataFrame:
    """(right_side, filter_id, ixs, words), a partition for each pair of a block of left and a block of right filters;
    a block has about `side` filters, by the hash of their ids."""
    gather = lambda d: d.groupBy("filter_id").agg(F.collect_list(F.struct("word_ix", "word")).alias("at")).select("filter_id", F.col("at.word_ix").alias("ixs"), F.col("at.word").alias("words"))
    alike, left = left is right, stored(gather(left), "pair-filters")
    right = left if alike else stored(gather(right), "pair-filters")
    across, down = (max(1, -(-d.count() // side)) for d in (right, left))
    block = lambda n: F.pmod(F.xxhash64("filter_id"), F.lit(n)).cast("int")
    rows = left.select(F.explode(F.sequence(F.lit(0), F.lit(across - 1))).alias("to"), block(down).alias("own"), "filter_id", "ixs", "words").select((F.col("own") * across + F.col("to")).alias("task"), F.lit(False).alias("right_side"), "filter_id", "ixs", "words")
    more = right.select(F.explode(F.sequence(F.lit(0), F.lit(down - 1))).alias("to"), block(across).alias("own"), "filter_id", "ixs", "words").select((F.col("to") * across + F.col("own")).alias("task"), F.lit(True).alias("right_side"), "filter_id", "ixs", "words")
    return rows.unionByName(more).repartitionById(down * across, F.col("task")).drop("task")


def _dense(batch: pa.Table, width: int) -> np.ndarray:
    out = np.zeros((batch.num_rows, width), np.uint64)
    row = np.repeat(np.arange(batch.num_rows), pc.list_value_length(batch["ixs"]).to_numpy().astype(np.int64))
    out[row, pc.list_flatten(batch["ixs"]).to_numpy()] = pc.list_flatten(batch["words"]).to_numpy().view(np.uint64)
    return out


def _count_pairs(keep: Callable, rows_at_once: int = 256, words_at_once: int = 256) -> Callable[[Iterator], Iterator]:
    """A task over two blocks of filters: bits of both of all pairs, as products of matrices of bits (whole numbers below
    2^24, so exact). keep(left ids, right ids, their ones, both) gives the rows and columns of the pairs that go out."""

    def run(batches):
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        whole = pa.Table.from_batches(held)
        sides = [whole.filter(pc.equal(whole["right_side"], flag)).combine_chunks() for flag in (False, True)]
        if not all(s.num_rows for s in sides):
            return
        width = 1 + max(pc.max(pc.list_flatten(s["ixs"])).as_py() or 0 for s in sides)
        sides[1] = sides[1].sort_by("filter_id")
        left, right = (_dense(s, width) for s in sides)
        ids, ones = [s["filter_id"].to_numpy() for s in sides], [np.bitwise_count(x).sum(axis=1, dtype=np.int64) for x in (left, right)]
        bits = lambda x: np.unpackbits(np.ascontiguousarray(x).view(np.uint8), axis=1).astype(np.float32)
        both = np.zeros((len(left), len(right)), np.int64)
        for k in range(0, width, words_at_once):
            both += (bits(left[:, k : k + words_at_once]) @ bits(right[:, k : k + words_at_once]).T).astype(np.int64)
        for start in range(0, len(left), rows_at_once):
            part = slice(start, start + rows_at_once)
            row, column = keep(ids[0][part], ids[1], ones[0][part], ones[1], both[part])
            if len(row):
                columns = [ids[0][part][row], ids[1][column], ones[0][part][row], ones[1][column], both[part][row, column]]
                kinds = [whole.schema.field("filter_id").type] * 2 + [pa.int64()] * 3
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds)], names=["a", "b", "a_ones", "b_ones", "both"])

    return run


def _paired(left: DataFrame, right: DataFrame, keep: Callable) -> DataFrame:
    kind = dict(left.dtypes)["filter_id"]
    return _dealt(left, right).mapInArrow(_count_pairs(keep), f"a {kind}, b {kind}, a_ones bigint, b_ones bigint, both bigint")


def all_pairs(left: DataFrame, right: DataFrame, *metrics: str, ordered: bool = False) -> DataFrame:
    """(a, b, one column a metric) of every pair of different ids; ordered: both (a, b) and (b, a).

    A task counts the pairs of two blocks of filters, so a filter moves once for each block of the other side, and rows
    of words never meet one by one. The result is what is asked for: a row for each pair.
    """
    keep = lambda a, b, *_: np.nonzero(a[:, None] != b if ordered else a[:, None] < b)
    counted = _paired(left, right, keep)
    return counted.select("a", "b", *(from_counts(m, F.col("a_ones"), F.col("b_ones"), F.col("both")).alias(m) for m in metrics or METRICS))


def nearest(filter_words: DataFrame, metric: str = "hamming", top: int = 1) -> DataFrame:
    """(filter_id, neighbour, distance): the `top` nearest other filters of each; ties go to the smaller id.

    Each pair of blocks hands on its `top` alone, so what moves is a row for each filter and block.
    """
    from pyspark.sql import Window

    def keep(a, b, a_ones, b_ones, both):  # right ids are in order, so that a stable order leaves ties to the smaller one
        far = np.where(a[:, None] == b, np.inf, _distance(metric, a_ones[:, None], b_ones, both))
        best = np.argmin(far, axis=1)[:, None] if top == 1 else np.argsort(far, axis=1, kind="stable")[:, :top]
        row = np.repeat(np.arange(len(a)), best.shape[1])
        there = np.isfinite(far[row, best.ravel()])
        return row[there], best.ravel()[there]

    pairs = _paired(filter_words, filter_words, keep)
    pairs = pairs.select("a", "b", from_counts(metric, F.col("a_ones"), F.col("b_ones"), F.col("both")).alias(metric))
    place = F.row_number().over(Window.partitionBy("a").orderBy(metric, "b"))
    return pairs.withColumn("place", place).where(F.col("place") <= top).select(F.col("a").alias("filter_id"), F.col("b").alias("neighbour"), F.col(metric).alias("distance"))


def _distance(metric: str, a: np.ndarray, b: np.ndarray, both: np.ndarray) -> np.ndarray:
    """`from_counts` on arrays, by the same steps in the same type."""
    if metric == "hamming":
        return (a + b - 2 * both).astype(float)
    if metric == "jaccard":
        either = a + b - both
        return np.where(either == 0, 0.0, 1 - both / np.maximum(either, 1))
    if metric == "cosine":
        roots = np.sqrt(a.astype(float)) * np.sqrt(b.astype(float))
        return np.where((a == 0) & (b == 0), 0.0, np.where((a == 0) | (b == 0), 1.0, 1 - both / np.where(roots > 0, roots, 1.0)))
    raise ValueError(f"unknown metric {metric}")


def contained(inner: DataFrame, outer: DataFrame) -> DataFrame:
    """(a, b): filters of `inner` whose bits all are bits of `outer`'s filter of the same `b`; expects columns a, b, words."""
    stray = F.bit_or(F.expr("x & ~coalesce(y, 0)"))
    return inner.join(outer, ["b", "word_ix"], "left").groupBy("a", "b").agg(stray.alias("stray")).where("stray = 0").select("a", "b")

"""Measures: storage, shape, gap to the ideal, pruning, and times by the averaging protocol."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, functions as F

from filterfleet.functions.params import WORD, FilterSpec, expected_fp
from filterfleet.operators.tree import TreeIndex, ideal_cost


def repeat(fn, repeats: int = 10, keep: int = 5) -> float:
    """Mean seconds of the last `keep` of `repeats` runs."""
    seconds = []
    for _ in range(repeats):
        began = time.perf_counter()
        fn()
        seconds.append(time.perf_counter() - began)
    return sum(seconds[-keep:]) / len(seconds[-keep:])


def run(df: DataFrame) -> None:
    """Computes df and throws it away."""
    df.write.format("noop").mode("overwrite").save()


def storage_bytes(method: str, n: int, spec: FilterSpec, n_nodes: int | None = None) -> int:
    """Bytes of dense filters: all nodes of a tree, filters up to a multiple of 64 in a pack, the filters in a scan."""
    count = {"scan": n, "pack": -(-n // WORD) * WORD, "tree": n_nodes}[method]
    return count * spec.m // 8


def search_bf_cost(costs: DataFrame) -> DataFrame:
    """Mean nodes tested for a probe."""
    return costs.groupBy("query_id").agg(F.sum("checked").alias("n")).agg(F.avg("n").alias("bf_cost"))


def gap_to_ideal(costs: DataFrame, n: int, fanout: float) -> DataFrame:
    return search_bf_cost(costs).withColumn("gap", F.col("bf_cost") - ideal_cost(n, fanout))


def pruning_by_level(costs: DataFrame) -> DataFrame:
    """Share of tested nodes that turned a probe away, for each level."""
    return costs.groupBy("level").agg(F.sum("checked").alias("checked"), F.sum("matched").alias("matched")).withColumn("pruned", 1 - F.col("matched") / F.col("checked"))


def maintenance_bf_cost(accessed: DataFrame) -> DataFrame:
    return accessed.agg(F.avg("accessed").alias("bf_cost"))


def mean_matches(matches: DataFrame, n_probes: int) -> DataFrame:
    return matches.agg((F.count("*") / n_probes).alias("mean_matches"))


def level_fp(index: TreeIndex, elements: int) -> DataFrame:
    """Measured false-positive rate of each level beside the root's analytic one."""
    from filterfleet.operators.tree import level_fill

    return level_fill(index).withColumn("root_analytic", F.lit(expected_fp(elements, index.spec.m, index.spec.k)))


def messages(rounds: DataFrame) -> DataFrame:
    """Sites asked in each round of a provenance search, with the index and without."""
    return rounds.groupBy("round").agg(F.sum("asked").alias("with_index"), F.sum("all_sites").alias("without_index"))


def decay_report(costs: DataFrame, n: int, fanout: float, most_ratio: float = 3.0) -> DataFrame:
    """Mean nodes tested beside the ideal, and whether the index is due for a rebuild."""
    return search_bf_cost(costs).withColumns({"ideal": F.lit(ideal_cost(max(n, 2), fanout)), "ratio": F.col("bf_cost") / ideal_cost(max(n, 2), fanout)}).withColumn("rebuild", F.col("ratio") > most_ratio)

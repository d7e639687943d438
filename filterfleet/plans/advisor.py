"""Which method to use, how long filters should be, and where a forest is to be cut."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, functions as F

from filterfleet.functions.params import FilterSpec, expected_fp, pruning_sets, saturating_sets


def advise(n: int, spec: FilterSpec, mean_n: float, distinct: int, op_mix: str = "search") -> dict:
    """Method by the number of filters, the root's false-positive rate, and what is done most.

    cut_filters: how many filters a node may stand for and still turn away half of all absent probes; above that the
    hierarchy is useless, so a forest of such trees (or a pack) is the better plan.
    """
    root_fp = expected_fp(distinct, spec.m, spec.k)
    overlap = max(1.0, n * mean_n / max(distinct, 1))
    cut = pruning_sets(spec.m, spec.k, max(mean_n, 1e-9)) * overlap
    if n <= 64 and spec.m <= 1024:
        method = "scan"
    elif op_mix == "update":
        method = "tree"
    elif op_mix == "insert" or cut < 64 or n < 1000:
        method = "pack"
    else:
        method = "tree"
    return {"method": method, "root_fp": root_fp, "cut_filters": cut, "saturated_at": saturating_sets(spec.m, spec.k, max(mean_n, 1e-9)) * overlap, "trees": max(1, math.ceil(n / max(cut, 1)))}


def size_spec(membership: DataFrame, target_fp: float = 0.01, family: str = "md5_double", share: float = 1.0) -> FilterSpec:
    """A spec for the elements of all sites together (or a share of them, for shards); counted by a sketch."""
    n = membership.agg(F.approx_count_distinct("element", 0.02).alias("n")).first()["n"]
    return FilterSpec(max(1, math.ceil(n * share)), target_fp, family)


def build_path(rows: int, sites: int, tasks: int, spec: FilterSpec) -> str:
    """words: OR words before the shuffle (a task sees many rows of a site); rows: shuffle elements by site first."""
    per_task = rows / max(tasks, 1) / max(min(sites, rows / max(tasks, 1)), 1)
    return "words" if per_task * spec.k >= min(spec.words, per_task * spec.k) and per_task > 2 else "rows"

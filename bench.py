"""Runs the headline queries and prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import tempfile
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import SparkSession  # noqa: E402

HEADLINE = (
    "build_filter_words", "scan_search_block", "tree_search_bulk", "tree_bf_cost_bulk", "tree_search_greedy_hamming", "pack_search", "pack_search_overlap", "pack_search_fleet", "pack_hybrid_search",
    "pack_words_read", "tree_update_inplace", "pack_update", "window_filters_7day", "provenance_messages", "benchmark_overlap_docs", "join_sort_merge", "agg_cube_events",
)


KEPT = ("bf_cost", "build_s", "root_fp", "tree_ms", "pack_ms", "scan_ms", "tree_bytes", "pack_bytes", "scan_bytes", "insert_bf_cost", "update_bf_cost", "delete_bf_cost", "mean_matches")


def published(spark, sizes: tuple[int, ...] = (10_000, 100_000)) -> dict[str, float]:
    """One setting at a time: N = 1000 (all methods, 50,000 searches), then larger N with the rule on and off."""
    from filterfleet.plans.workloads import Setting, run_settings

    out = {}
    settings = [("1000", Setting(probes=50_000)), ("1000 half updated", Setting(probes=5000, after_update=True))]
    settings += [(f"{n} {'rule' if rule else 'no rule'}", Setting(n_filters=n, saturation_rule=rule, probes=2000, tree_only=True)) for n in sizes for rule in (True, False)]
    for label, setting in settings:
        out |= {f"{r['measure']}@{label}": round(r["result"], 5) for r in run_settings(spark, [setting]).collect() if r["measure"] in KEPT}
    return out


def distributed(spark, sf_dir: str) -> dict[str, float]:
    """Milliseconds a probe of distributed searches over one saved index of each kind, mean of the last runs, and its size."""
    from filterfleet.functions.frames import checkpointed
    from filterfleet.operators import filters, pack, scan, tree
    from filterfleet.plans import advisor, costs
    from filterfleet.sources.collections import collection, probes

    sets = checkpointed(collection(spark, sf_dir, "user"))
    spec, asked = advisor.size_spec(sets, share=0.1), checkpointed(probes(sets))
    words, n = checkpointed(filters.build_filters(sets, spec)), asked.count()
    dense, index, sliced = checkpointed(filters.to_dense(words, spec)), tree.bulk_load(words, spec), pack.pack_build(sets, spec)
    sliced.slices, sliced.slots = checkpointed(sliced.slices), checkpointed(sliced.slots)
    found = {"scan": lambda: scan.scan_search(dense, asked, spec), "tree": lambda: tree.tree_search(index, asked)[0], "pack": lambda: pack.pack_search(sliced, asked)}
    out = {f"spark_{k}_ms": round(1000 * costs.repeat(lambda: costs.run(search()), 3, 2) / n, 4) for k, search in found.items()}  # noqa: B023
    sites, nodes = sets.select("site_id").distinct().count(), index.nodes.count()
    return out | {f"spark_{k}_bytes": costs.storage_bytes(k, sites, spec, nodes) for k in found}


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", tempfile.mkdtemp(prefix="bench-"))  # one machine: its folder is the shared one
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from filterfleet import catalogue

    seconds = {}
    for name in HEADLINE:
        began = time.perf_counter()
        catalogue.QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - began, 3)
    began = time.perf_counter()
    measures = published(spark) | distributed(spark, sf_dir)
    seconds["published_settings"] = round(time.perf_counter() - began, 3)
    print(json.dumps({"metric": "total_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "measures": measures, "sf": sf_dir.rstrip("/").rsplit("/", 1)[-1]}))


if __name__ == "__main__":
    main()

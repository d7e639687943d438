"""Provenance across sites: all ancestors of items, asking only sites whose filter matches.

edges: (site_id, child, parent). A site's filter holds the children it has edges for. Each round looks the frontier up in
the index, reads edges of candidate sites alone, and goes on with parents not seen before. A false positive costs a
message, never a wrong ancestor; a true site is never missed.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from filterfleet.functions.frames import checkpointed, written, written_at
from filterfleet.functions.params import FilterSpec
from filterfleet.operators.pack import pack_build, pack_search


def trace(edges: DataFrame, starts: DataFrame, spec: FilterSpec, most_rounds: int = 1000) -> tuple[DataFrame, DataFrame]:
    """closure (start, item) with item an ancestor of start, and rounds (round, asked, all_sites): messages by round.

    Raises where ancestors are left after most_rounds; a closure that is returned is whole.
    """
    index = pack_build(edges.select("site_id", F.col("child").alias("element")), spec)
    index.slices, index.slots = checkpointed(index.slices), checkpointed(index.slots)
    spark, n_sites = edges.sparkSession, edges.select("site_id").distinct().count()
    edges = checkpointed(edges)
    schema = "start long, item long"
    paths = [written_at(starts.selectExpr("cast(item as bigint) as start", "cast(item as bigint) as item").distinct(), "frontier")]
    rounds = []
    for turn in range(most_rounds + 1):
        frontier = spark.read.schema(schema).parquet(paths[-1])
        items = frontier.select(F.col("item").alias("query_id"), F.col("item").alias("element")).distinct()
        n_items = items.count()
        if not n_items:
            break
        if turn == most_rounds:
            raise ValueError(f"{n_items} items are left after {most_rounds} rounds")
        asked = written(pack_search(index, items), "asked")
        rounds.append((turn, asked.count(), n_items * n_sites))
        parents = asked.select(F.col("query_id").alias("child"), F.col("filter_id").alias("site_id")).join(edges, ["site_id", "child"]).select("child", "parent").distinct()
        fresh = frontier.join(parents, frontier["item"] == parents["child"]).select("start", F.col("parent").alias("item")).distinct()
        paths.append(written_at(fresh.join(spark.read.schema(schema).parquet(*paths), ["start", "item"], "left_anti"), "frontier"))
    closure = spark.read.schema(schema).parquet(*paths).where("start <> item")
    return closure, spark.createDataFrame(rounds, "round int, asked long, all_sites long")

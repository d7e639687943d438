"""The union-filter tree: a balanced hierarchy in which a node's bits are the OR of its children's.

The shape (a few numbers a node) and the bits live apart: `nodes` (tree_id, node_id, parent_id, level, child_ord,
n_children, filter_id) and `words` (tree_id, node_id, word_ix, word). Level 0 holds the filters; node ids of level 0 are
positions in the load order, those above follow on level by level.

Sorted load has a closed form, so it needs no loop over filters: appending beside the right-most leaf with splits that
move the last d children leaves every node but the last with d+1 children.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from filterfleet.functions.frames import broadcast_if_small, checkpointed, numbered, ored_into, stored, written
from filterfleet.functions.hashing import positions, probe_words
from filterfleet.functions.params import FilterSpec


@dataclass
class SortedLoad:
    """What a sorted load is formed of: sets (site_id, element), places (filter_id, place), and the levels' numbers of nodes."""

    members: DataFrame
    places: DataFrame
    sizes: list[int]


@dataclass
class TreeIndex:
    nodes: DataFrame
    words: DataFrame
    spec: FilterSpec
    d: int

    #: While the tree is as a sorted load made it, and its sets are known.
    load = None


class LoadedIndex(TreeIndex):
    """A sorted load whose sets are known; its rows of words are formed when they are first read."""

    def __init__(self, nodes: DataFrame, form: Callable[[], DataFrame], spec: FilterSpec, d: int, load: SortedLoad):
        self.nodes, self.spec, self.d, self.load, self._form = nodes, spec, d, load, form

    @cached_property
    def words(self) -> DataFrame:
        return self._form()


def level_sizes(n: int, d: int) -> list[int]:
    """Nodes on each level after a sorted load of n filters, from the filters up to the root."""
    sizes = [n]
    while sizes[-1] > 1 or len(sizes) == 1 and n:
        below = sizes[-1]
        sizes.append(1 if below <= 2 * d else (below - d) // (d + 1) + 1)
        if sizes[-1] == 1:
            break
    return sizes


def parent_place(place: int, below: int, d: int) -> int:
    """Place, on its level, of the parent of a node."""
    last = 0 if below <= 2 * d else (below - d) // (d + 1)
    return min(place // (d + 1), last)


def ideal_cost(n: int, fanout: float) -> float:
    """Nodes tested along one path, all children of each node on it included."""
    return fanout * math.log(n) / math.log(fanout) + 1


def height_bound(n: int, d: int) -> int:
    return 1 if n <= 2 * d else 1 + math.floor(math.log(n / 2) / math.log(d) + 1e-9)


def order_filters(filter_words: DataFrame, order: str = "id") -> DataFrame:
    """(filter_id, place): load order by id, by number of set bits, by first set bit, or by a MinHash of the bits.

    These stand in, in linear time, for a chain of nearest neighbours, which is `grow.nearest_chain` inside a shard.
    """
    first_bit = F.expr("64 * word_ix + length(substring_index(reverse(lpad(bin(word), 64, '0')), '1', 1))")
    keys = {
        "id": F.first(F.lit(0)),
        "ones": F.sum(F.bit_count("word")),
        "first": F.min(first_bit),
        "minhash": F.min(F.xxhash64("word_ix", "word")),
    }
    keyed = checkpointed(filter_words.groupBy("filter_id").agg(keys[order].cast("double").alias("key")))  # a row for each filter, read once for each step of numbering
    if order == "id":
        return numbered(keyed.select("filter_id"), "filter_id", "place")
    # Equal keys are told apart by a small share of the id's hash, so ranks don't depend on the plan.
    spread = F.col("key") + F.pmod(F.xxhash64("filter_id"), F.lit(1 << 20)) / float(1 << 21)
    return numbered(keyed.select("filter_id", spread.alias("key")), "key", "place").drop("key")


def _bases(sizes: list[int]) -> list[int]:
    return [sum(sizes[:k]) for k in range(len(sizes))]


def lift(words: DataFrame, sizes: list[int], d: int, start: int, stride: int) -> DataFrame:
    """(level, place, word_ix, word) of the `stride` levels above level `start`, from words (place, word_ix, word) of it."""
    here, steps = F.col("place"), []
    for level in range(start + 1, min(start + stride, len(sizes) - 1) + 1):
        below = sizes[level - 1]
        here = F.least((here / (d + 1)).cast("bigint"), F.lit(0 if below <= 2 * d else (below - d) // (d + 1)).cast("bigint"))
        steps.append(F.struct(F.lit(level).alias("level"), here.alias("place")))
    return words.select(F.explode(F.array(*steps)).alias("a"), "word_ix", "word").groupBy("a.level", "a.place", "word_ix").agg(F.bit_or("word").alias("word"))


def bulk_nodes(places: DataFrame, sizes: list[int], d: int) -> DataFrame:
    """The shape of a sorted load, in one pass over the levels' numbers."""
    spark, base = places.sparkSession, _bases(sizes)
    shape = None
    for level, size in enumerate(sizes):
        place = spark.range(size).select(F.col("id").alias("place"), F.lit(None).cast(dict(places.dtypes)["filter_id"]).alias("filter_id")) if level else places
        last = 0 if size <= 2 * d else (size - d) // (d + 1)
        parent = F.least((F.col("place") / (d + 1)).cast("bigint"), F.lit(last).cast("bigint"))
        top = level == len(sizes) - 1
        parent_id = F.lit(None).cast("bigint") if top else parent + base[level + 1]
        if level:
            below = sizes[level - 1]
            children = F.when(F.col("place") == size - 1, F.lit(below) - (size - 1) * (d + 1)).otherwise(d + 1)
        else:
            children = F.lit(0)
        rows = place.select(
            F.lit(0).alias("tree_id"), (F.col("place") + base[level]).cast("bigint").alias("node_id"), parent_id.alias("parent_id"), F.lit(level).alias("level"),
            (F.col("place") - F.lit(0) if top else F.col("place") - parent * (d + 1)).cast("int").alias("child_ord"), children.cast("int").alias("n_children"), "filter_id",
        )
        shape = rows if shape is None else shape.unionByName(rows)
    return shape


def bulk_load(filter_words: DataFrame, spec: FilterSpec, d: int = 2, order: str = "id", places: DataFrame | None = None, stride: int = 3, members: DataFrame | None = None) -> TreeIndex:
    """A tree by sorted load. Node values are formed `stride` levels at a time, each step from the top level of the one
    before, so the words that move are `stride` times the leaves' and a small part more, whatever the height.

    places: (filter_id, place) of all filters, those without a set bit included; by default the filters in filter_words.
    members: the sets (site_id, element) that filter_words are formed of. Where they are known, rows of words come up only
    for a reader of `words`: `counted_cost` and `root_words` form the nodes from the sets, in tasks that hold their bits.
    """
    if members is not None:
        members = members.where("site_id is not null and element is not null").select("site_id", "element")
        if places is None and order == "id":
            places = numbered(checkpointed(members.select(F.col("site_id").alias("filter_id")).distinct()), "filter_id", "place")
    places = checkpointed(order_filters(filter_words, order) if places is None else places)
    sizes = level_sizes(places.count(), d)
    nodes = bulk_nodes(places, sizes, d)
    if members is not None:
        return LoadedIndex(nodes, lambda: _loaded_words(filter_words, places, sizes, d, stride), spec, d, SortedLoad(members, places, sizes))
    return TreeIndex(nodes, _loaded_words(filter_words, places, sizes, d, stride), spec, d)


def _loaded_words(filter_words: DataFrame, places: DataFrame, sizes: list[int], d: int, stride: int) -> DataFrame:
    """(tree_id, node_id, word_ix, word) of a sorted load's nodes."""
    number = F.element_at(F.array(*map(F.lit, _bases(sizes) or [0])), F.col("level") + 1).cast("bigint")
    here = checkpointed(filter_words.join(places, "filter_id").select(F.lit(0).alias("level"), "place", "word_ix", "word"))
    words = here
    for start in range(0, len(sizes) - 1, stride):
        above = checkpointed(lift(here, sizes, d, start, stride))
        words, here = words.unionByName(above), above.where(F.col("level") == start + stride)
    return words.select(F.lit(0).alias("tree_id"), (F.col("place") + number).alias("node_id"), "word_ix", "word")


def tree_search(index: TreeIndex, probes: DataFrame, most_pairs: int = 200_000_000) -> tuple[DataFrame, DataFrame]:
    """Matches (query_id, filter_id) and costs (query_id, level, checked, matched), from the roots downwards.

    One step a level for all probes at once: the frontier meets the probes' words and the level's words; nodes with all
    of the probe's bits pass their children on. The words are kept in a part for each level, so a step reads its level
    alone, and a frontier that is small goes to where they lie. A shard's trees are searched together: the frontier
    starts at all roots. Near full nodes turn no probe away, so frontiers grow with probes x nodes; where that is more
    than most_pairs, parts of the tree are searched in tasks (`search_parts`), and levels are passed there.
    """
    if probes.count() * index.nodes.count() > most_pairs:
        return _searched(index, probes)
    spec, nodes = index.spec, index.nodes
    wanted = checkpointed(probe_words(probes, spec))
    queries = wanted.select("query_id").distinct()
    top = nodes.agg(F.max("level").alias("h")).first()["h"]
    empty = queries.limit(0).select("query_id", F.lit(0).cast("bigint").alias("filter_id"))
    if top is None:
        return empty, empty.select("query_id", F.lit(0).alias("level"), F.lit(0).cast("bigint").alias("checked"), F.lit(0).cast("bigint").alias("matched"))
    shape = broadcast_if_small(nodes.select("tree_id", "node_id", "parent_id", "level", "filter_id"))
    heights = {r["level"] for r in nodes.where("parent_id is null").select("level").distinct().collect()}
    leveled = written(index.words.join(shape.select("tree_id", "node_id", "level"), ["tree_id", "node_id"]).select("tree_id", "node_id", "word_ix", "word", "level"), "tree-words", "level")
    roots = shape.where("parent_id is null").select("tree_id", "node_id", "level", "filter_id")
    frontier, costs = None, None
    for level in range(top, -1, -1):
        if level in heights:  # a probe asks every root: one, or one a shard
            asked = queries.crossJoin(roots.where(F.col("level") == level)).select("query_id", "tree_id", "node_id", "filter_id")
            frontier = asked if frontier is None else frontier.unionByName(asked)
        frontier = checkpointed(frontier)
        cells = frontier.join(wanted, "query_id")
        met = broadcast_if_small(cells).join(leveled.where(F.col("level") == level).drop("level"), ["tree_id", "node_id", "word_ix"]).where("word & mask = mask")
        hits = checkpointed(met.groupBy("query_id", "tree_id", "node_id", "filter_id").agg(F.count("*").alias("n"), F.first("n_words").alias("of")).where("n = of"))
        matched = hits.groupBy("query_id").agg(F.count("*").alias("matched"))
        cost = frontier.groupBy("query_id").agg(F.lit(level).alias("level"), F.count("*").alias("checked")).join(matched, "query_id", "left").fillna(0, ["matched"])
        costs = cost if costs is None else costs.unionByName(cost)
        below = shape.where(F.col("level") == level - 1).select("tree_id", F.col("parent_id").alias("up"), F.col("node_id").alias("down"), F.col("filter_id").alias("down_filter"))
        frontier = hits.withColumnRenamed("node_id", "up").join(below, ["tree_id", "up"]).select("query_id", "tree_id", F.col("down").alias("node_id"), F.col("down_filter").alias("filter_id"))
    return hits.select("query_id", "filter_id"), costs


def tree_parts(index: TreeIndex, most_bytes: int = 64 << 20) -> tuple[DataFrame, list[dict[int, int]], list[int]]:
    """(tree_id, node_id, part, level, ix, n_children, filter_id) of all nodes; each part's number of nodes by level, and
    the level from which on downwards all its nodes have their parents in it (-1: none).

    A part is a run of whole subtrees whose bits have about most_bytes, or of the nodes above all these subtrees. ix is
    a node's place among those of its part and level.
    """
    nodes = stored(index.nodes, "tree-shape")
    counts = {r["level"]: r["n"] for r in nodes.groupBy("level").agg(F.count("*").alias("n")).collect()}
    room = max(64, min(8 * most_bytes // index.spec.m, max(4096, sum(counts.values()) // 16)))
    held, cut = 0, 0
    for level in sorted(counts):
        held += counts[level]
        if level and held / counts[level] > room / 4:
            break
        cut = level
    key = ["tree_id", "node_id"]
    here = nodes.where(f"level = {cut} or (parent_id is null and level < {cut})").select(*key, F.struct(*key).alias("of"))
    roots, below = f"level = {cut} or (parent_id is null and level < {cut})", here
    for level in range(cut - 1, -1, -1):  # from each subtree's root downwards, on the shape alone
        up = here.select("tree_id", F.col("node_id").alias("parent_id"), "of")
        here = nodes.where(f"level = {level} and parent_id is not null").join(up, ["tree_id", "parent_id"]).select(*key, "of")
        here = stored(here, "subtree-level")
        below = below.unionByName(here)
        here = here.unionByName(nodes.where(f"level = {level} and parent_id is null").select(*key, F.struct(*key).alias("of")))
    below = stored(below, "subtree-nodes")
    run = lambda *order: Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    sizes = below.groupBy("of").agg(F.count("*").alias("n")).withColumn("run", F.floor(F.coalesce(F.sum("n").over(run("of")), F.lit(0)) / room))  # a row for each subtree
    above = nodes.join(below, key, "left_anti").withColumn("run", -1 - F.floor(F.count("*").over(run(F.desc("level"), *key)) / room))  # few nodes: those above the subtrees
    placed = nodes.join(below, key).join(sizes.select("of", "run"), "of").drop("of").unionByName(above)
    kept = stored(placed, "tree-runs")
    runs = [r["run"] for r in kept.select("run").distinct().orderBy("run").collect()]  # a row for each part
    number = kept.sparkSession.createDataFrame([(r, i) for i, r in enumerate(runs)], "run bigint, part int")
    ix = F.row_number().over(Window.partitionBy("part", "level").orderBy(*key)) - 1
    parts = stored(kept.join(F.broadcast(number), "run").select(*key, "part", "level", ix.alias("ix"), "n_children", "filter_id"), "tree-parts")
    shape: list[dict[int, int]] = [{} for _ in runs]
    for r in parts.groupBy("part", "level").agg(F.count("*").alias("n")).collect():
        shape[r["part"]][r["level"]] = r["n"]
    whole = {r["part"]: r["low"] for r in kept.where(roots).join(F.broadcast(number), "run").where("run >= 0").groupBy("part").agg(F.min("level").alias("low")).collect()}
    return parts, shape, [whole.get(i, -1) for i in range(len(runs))]


def _part_task(shape: list[dict[int, int]], whole: list[int], planes: int, spec: FilterSpec, leaves: bool, most_bytes: int = 8 << 20) -> Callable[[Iterator], Iterator]:
    """A task over a part's rows: words of its nodes, then probes. Nodes of a level lie bit-sliced in blocks of 64 lanes;
    all probes are tested level by level from the top, and one that no node of a level lets pass is done in a part of
    whole subtrees."""

    def run(batches):
        grid, one, start = None, np.uint64(1), {}
        for batch in batches:
            if not batch.num_rows:
                continue
            if grid is None:
                part = batch.column("part")[0].as_py()
                levels = {level: n for level, n in shape[part].items() if leaves or level}
                numeric, wide = pa.types.is_integer(batch.schema.field("filter_id").type), 0
                for level in sorted(levels, reverse=True):
                    start[level] = wide
                    wide += -(-levels[level] // 64)
                ends = {level: start[level] + -(-n // 64) for level, n in levels.items()}
                grid, weights = np.zeros((spec.m, wide), np.uint64), np.zeros((planes, wide), np.uint64)
                flat, names = grid.reshape(-1), np.zeros(64 * wide, np.int64 if numeric else object)
            asks = np.asarray(batch.column("asks").to_numpy(zero_copy_only=False), bool)
            mine = batch.filter(pa.array(~asks))
            if mine.num_rows:
                level, ix, kids, word_ix = (mine.column(c).to_numpy().astype(np.int64) for c in ("level", "ix", "n_children", "word_ix"))
                block = np.array([start.get(k, 0) for k in range(max(start) + 1)])[level] + (ix >> 6)
                lane = one << (ix & 63).astype(np.uint64)
                names[(64 * block + (ix & 63))[level == 0]] = mine.column("filter_id").filter(pa.array(level == 0)).to_numpy(zero_copy_only=False)
                for p in range(planes):
                    np.bitwise_or.at(weights[p], block, np.where(kids >> p & 1, lane, np.uint64(0)))
                row, bit = np.nonzero(np.unpackbits(mine.column("word").to_numpy().view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"))
                np.bitwise_or.at(flat, (word_ix[row] * 64 + bit) * wide + block[row], lane[row])
            asked = batch.filter(pa.array(asks))
            if not asked.num_rows:
                continue
            spots = asked.column("spots").flatten().to_numpy().astype(np.int64).reshape(asked.num_rows, -1)
            some = max(1, most_bytes // (8 * max(1, wide)))
            for first in range(0, asked.num_rows, some):
                rows = np.arange(first, min(first + some, asked.num_rows))
                for level in sorted(start, reverse=True):
                    own, which = slice(start[level], ends[level]), rows
                    here = grid[:, own]
                    left = here[spots[which, 0]]
                    for k in range(1, spots.shape[1]):
                        alive = left.any(axis=1)
                        if not alive.all():
                            which, left = which[alive], left[alive]
                        left &= here[spots[which, k]]
                    alive = left.any(axis=1)
                    which, left = which[alive], left[alive]
                    if level <= whole[part]:  # what no node of this level lets pass, none below will
                        rows = which
                    if not len(which):
                        continue
                    matched = np.bitwise_count(left).sum(axis=1, dtype=np.int64)
                    kids = sum(np.bitwise_count(left & weights[p][own]).sum(axis=1, dtype=np.int64) << p for p in range(planes))
                    queries = asked.column("query_id").take(pa.array(which))
                    none = pa.nulls(len(which), batch.schema.field("filter_id").type)
                    yield pa.RecordBatch.from_arrays([queries, none, pa.array(np.full(len(which), level, np.int32)), pa.array(matched), pa.array(kids + np.zeros_like(matched))], names=OUT)
                    if not level:
                        row, block = np.nonzero(left)
                        hit, lane = np.nonzero((left[row, block][:, None] >> np.arange(64, dtype=np.uint64)) & one)
                        found = pa.array(names[64 * (start[0] + block[hit]) + lane], batch.schema.field("filter_id").type)
                        ones = np.ones(len(hit), np.int64)
                        yield pa.RecordBatch.from_arrays([queries.take(pa.array(row[hit])), found, pa.array(np.zeros(len(hit), np.int32)), pa.array(0 * ones), pa.array(0 * ones)], names=OUT)

    return run


OUT = ["query_id", "filter_id", "level", "matched", "children"]


def search_parts(index: TreeIndex, probes: DataFrame, leaves: bool = True, most_bytes: int = 64 << 20) -> DataFrame:
    """(query_id, filter_id, level, matched, children): each part of the tree in a task, all probes asked of it.

    Rows with a filter are matches. Those without say, for a part and level, how many nodes matched a probe and how many
    children these have, which are the nodes tested on the level below. What moves is the words of the tree once and the
    probes once for each part; leaves=False leaves out level 0, which no count of tested nodes needs.
    """
    spec = index.spec
    parts, shape, whole = tree_parts(index, most_bytes)
    asked = stored(probes.where("element is not null").select("query_id", "element").distinct(), "tree-probes")
    kinds = dict(asked.dtypes) | {"filter_id": dict(index.nodes.dtypes)["filter_id"]}
    planes = ((parts.agg(F.max("n_children").alias("n")).first()["n"] or 0)).bit_length()
    void = lambda name, kind: F.lit(None).cast(kind).alias(name)
    inner = parts if leaves else parts.where("level > 0")
    rows = index.words.join(broadcast_if_small(inner), ["tree_id", "node_id"]).select("part", F.lit(False).alias("asks"), "level", "ix", "n_children", "filter_id", "word_ix", "word", void("query_id", kinds["query_id"]), void("element", kinds["element"]))
    dealt = asked.select(F.explode(F.sequence(F.lit(0), F.lit(max(0, len(shape) - 1)))).alias("part"), "query_id", "element") if shape else asked.limit(0).select(F.lit(0).alias("part"), "query_id", "element")
    dealt = dealt.select("part", F.lit(True).alias("asks"), *(void(n, dict(rows.dtypes)[n]) for n in ("level", "ix", "n_children", "filter_id", "word_ix", "word")), "query_id", "element")
    # Elements are hashed behind the shuffle, where a part's tasks read them.
    spots = F.when(F.col("asks"), positions(F.col("element"), spec)).alias("spots")
    rows = rows.unionByName(dealt).repartitionById(max(1, len(shape)), F.col("part")).sortWithinPartitions("asks").select("part", "asks", "level", "ix", "n_children", "filter_id", "word_ix", "word", "query_id", spots)
    return rows.mapInArrow(_part_task(shape, whole, planes, spec, leaves), f"query_id {kinds['query_id']}, filter_id {kinds['filter_id']}, level int, matched bigint, children bigint")


def nodes_tested(hits: DataFrame, index: TreeIndex, probes: DataFrame) -> DataFrame:
    """(query_id, nodes_checked) from `search_parts`: all roots, and the children of every node that matched."""
    roots = index.nodes.where("parent_id is null").count()
    queries = probes.where("element is not null").select("query_id").distinct()
    tested = hits.where("filter_id is null").groupBy("query_id").agg(F.sum("children").alias("children"))
    return queries.join(tested, "query_id", "left").select("query_id", (F.coalesce("children", F.lit(0)) + roots).alias("nodes_checked"))


def _searched(index: TreeIndex, probes: DataFrame) -> tuple[DataFrame, DataFrame]:
    """`tree_search` by parts."""
    hits = stored(search_parts(index, probes), "tree-hits")
    at = hits.where("filter_id is null")
    roots = index.nodes.where("parent_id is null").groupBy("level").agg(F.count("*").alias("checked"))
    queries = probes.where("element is not null").select("query_id").distinct()
    checked = queries.crossJoin(F.broadcast(roots)).select("query_id", "level", "checked")  # a row for each height
    checked = checked.unionByName(at.where("children > 0").select("query_id", (F.col("level") - 1).alias("level"), F.col("children").alias("checked")))
    costs = checked.groupBy("query_id", "level").agg(F.sum("checked").alias("checked"))
    matched = at.groupBy("query_id", "level").agg(F.sum("matched").alias("matched"))
    return hits.where("filter_id is not null").select("query_id", "filter_id"), costs.join(matched, ["query_id", "level"], "left").fillna(0, ["matched"])


def tree_search_local(index: TreeIndex, probes: DataFrame, most_bytes: int = 64 << 20) -> DataFrame:
    """(query_id, filter_id, nodes_checked): replicas in tasks, probes searched beside them. A tree of more than
    most_bytes is cut into subtrees that fit, each of them in a task of its own.

    nodes_checked repeats on each of a probe's matches; a probe without a match has one row with a null filter.
    """
    hits = stored(search_parts(index, probes, most_bytes=most_bytes), "tree-hits")
    found = hits.where("filter_id is not null").select("query_id", "filter_id")
    return nodes_tested(hits, index, probes).join(found, "query_id", "left").select("query_id", "filter_id", "nodes_checked")


def search_cost(costs: DataFrame) -> DataFrame:
    """(query_id, nodes_checked)."""
    return costs.groupBy("query_id").agg(F.sum("checked").alias("nodes_checked"))


def load_tiers(sizes: list[int], d: int, m: int, most_bytes: int = 64 << 20) -> list[tuple[int, int, int]]:
    """(low, high, run) of tiers that follow one another upwards and hold the levels above low up to high. A part of a tier
    is `run` neighbouring whole subtrees, whose roots lie on level high and whose bits have about most_bytes."""
    room = max(64, min(8 * most_bytes // m, max(4096, sum(sizes[1:]) // 16)))
    tiers, low, top = [], 0, len(sizes) - 1
    while low < top:
        high, held = low + 1, 1
        while high < top and held * (d + 1) + 1 <= room // 4:
            high, held = high + 1, held * (d + 1) + 1
        if sum(sizes[low + 1 :]) <= room:
            high = top
        tiers.append((low, high, max(1, room // held)))
        low = high
    return tiers


def _tier_task(sizes: list[int], d: int, spec: FilterSpec, low: int, high: int, run: int, most_bytes: int = 8 << 20) -> Callable[[Iterator], Iterator]:
    """A task over a part of a tier: first what lies on level low, as elements of sets or as nodes' bits, which set bits in
    all nodes above them up to level high; then probes, which are tested level by level from the top. Nodes lie bit-sliced
    in blocks of 64 lanes. Out come, for each probe, the children of nodes that match it, and the bits of the subtrees' roots."""
    top, one = len(sizes) - 1, np.uint64(1)
    out = pa.schema([("children", pa.int64()), ("place", pa.int64()), ("bits", pa.binary())])

    def roots(grid, start, first, n):
        for ix in range(n[high]):
            own = grid[:, start[high] + (ix >> 6)] >> np.uint64(ix & 63) & one
            yield first[high] + ix, np.packbits(own.astype(np.uint8), bitorder="little").tobytes()

    def task(batches):
        grid, given = None, False
        for batch in batches:
            if not batch.num_rows:
                continue
            if grid is None:
                part, kind, wide, start, first, n = batch.column("part")[0].as_py(), batch.schema.field("query_id").type, 0, {}, {}, {}
                for level in range(high, low, -1):
                    span = run * (d + 1) ** (high - level)
                    start[level], first[level] = wide, part * span
                    n[level] = sizes[level] - first[level] if (part + 1) * run >= sizes[high] else span
                    wide += -(-n[level] // 64)
                grid = np.zeros((spec.m, wide), np.uint64)
                flat = grid.reshape(-1)
            asks = np.asarray(batch.column("asks").to_numpy(zero_copy_only=False), bool)
            own = batch.num_rows - int(asks.sum())  # rows are in this order
            if own:
                mine = batch.slice(0, own)
                place = mine.column("place").to_numpy(zero_copy_only=False).astype(np.int64)
                if low:
                    spots = [np.flatnonzero(np.unpackbits(np.frombuffer(b, np.uint8), bitorder="little")) for b in mine.column("bits").to_pylist()]
                else:
                    spots = mine.column("spots").flatten().to_numpy().astype(np.int64).reshape(own, -1) * wide
                for level in range(low + 1, high + 1):
                    below = sizes[level - 1]
                    place = np.minimum(place // (d + 1), 0 if below <= 2 * d else (below - d) // (d + 1))
                    ix = place - first[level]
                    block, lane = start[level] + (ix >> 6), one << (ix & 63).astype(np.uint64)
                    if low:
                        for i, spot in enumerate(spots):
                            grid[spot, block[i]] |= lane[i]
                    else:
                        np.bitwise_or.at(flat, (spots + block[:, None]).ravel(), np.repeat(lane, spots.shape[1]))
            if own == batch.num_rows:
                continue
            if not given and high < top:  # all of level low is read
                given = True
                for place, bits in roots(grid, start, first, n):
                    yield pa.RecordBatch.from_arrays([pa.nulls(1, kind), pa.array([0], pa.int64()), pa.array([place], pa.int64()), pa.array([bits], pa.binary())], names=["query_id", *out.names])
            asked = batch.slice(own)
            spots = asked.column("spots").flatten().to_numpy().astype(np.int64).reshape(asked.num_rows, -1)
            some = max(1, most_bytes // (8 * max(-(-c // 64) for c in n.values())))
            total = np.zeros(asked.num_rows, np.int64)
            for begin in range(0, asked.num_rows, some):
                which = np.arange(begin, min(begin + some, asked.num_rows))
                for level in range(high, low, -1):
                    here = grid[:, start[level] : start[level] + -(-n[level] // 64)]
                    left = here[spots[which, 0]]
                    for k in range(1, spots.shape[1]):
                        alive = left.any(axis=1)
                        if not alive.all():
                            which, left = which[alive], left[alive]
                        left &= here[spots[which, k]]
                    alive = left.any(axis=1)
                    which, left = which[alive], left[alive]  # what no node of this level lets pass, none below will
                    if not len(which):
                        break
                    total[which] += np.bitwise_count(left).sum(axis=1, dtype=np.int64) * (d + 1)
                    if first[level] + n[level] == sizes[level]:  # the level's last node has what the others leave
                        end = n[level] - 1
                        total[which] += (left[:, end >> 6] >> np.uint64(end & 63) & one).astype(np.int64) * (sizes[level - 1] - sizes[level] * (d + 1))
            met = np.flatnonzero(total)
            if len(met):
                yield pa.RecordBatch.from_arrays([asked.column("query_id").take(pa.array(met)), pa.array(total[met]), pa.nulls(len(met), pa.int64()), pa.nulls(len(met), pa.binary())], names=["query_id", *out.names])

    return task


def _load_cost(index: TreeIndex, probes: DataFrame, most_bytes: int = 64 << 20) -> DataFrame:
    """`counted_cost` of a sorted load from its sets. The places of all nodes are known, so a part needs no table of nodes;
    what moves is the sets once, the roots of a tier's subtrees once, and the probes once for each part."""
    load, spec, d = index.load, index.spec, index.d
    asked = stored(probes.where("element is not null").select("query_id", "element").distinct(), "tree-probes")
    kinds = dict(asked.dtypes)
    void = lambda name, kind: F.lit(None).cast(kind).alias(name)
    places = broadcast_if_small(load.places.select(F.col("filter_id").alias("site_id"), F.col("place").cast("bigint").alias("place")))
    below = load.members.join(places, "site_id").select("place", void("bits", "binary"), F.col("element").cast(kinds["element"]).alias("element"))
    costs = asked.limit(0).select("query_id", F.lit(0).cast("bigint").alias("children"))
    for low, high, run in load_tiers(load.sizes, d, spec.m, most_bytes):
        above = F.col("place")
        for level in range(low, high):
            size = load.sizes[level]
            above = F.least(F.floor(above / (d + 1)).cast("bigint"), F.lit(0 if size <= 2 * d else (size - d) // (d + 1)).cast("bigint"))
        parts = -(-load.sizes[high] // run)
        rows = below.select(F.floor(above / run).cast("int").alias("part"), F.lit(False).alias("asks"), "place", "bits", void("query_id", kinds["query_id"]), "element")
        dealt = asked.select(F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"), F.lit(True).alias("asks"), void("place", "bigint"), void("bits", "binary"), "query_id", "element")
        # Elements are hashed behind the shuffle, where a part's tasks read them.
        spots = F.when(F.col("element").isNotNull(), positions(F.col("element"), spec)).alias("spots")
        rows = rows.unionByName(dealt).repartitionById(parts, F.col("part")).sortWithinPartitions("asks").select("part", "asks", "place", "bits", "query_id", spots)
        hits = stored(rows.mapInArrow(_tier_task(load.sizes, d, spec, low, high, run), f"query_id {kinds['query_id']}, children bigint, place bigint, bits binary"), "tree-tier")
        costs = costs.unionByName(hits.where("bits is null").select("query_id", "children"))
        below = hits.where("bits is not null").select("place", "bits", void("element", kinds["element"]))
    queries = asked.select("query_id").distinct()
    tested = costs.groupBy("query_id").agg(F.sum("children").alias("children"))
    return queries.join(tested, "query_id", "left").select("query_id", (F.coalesce("children", F.lit(0)) + int(load.sizes[0] > 0)).alias("nodes_checked"))


def counted_cost(index: TreeIndex, probes: DataFrame) -> DataFrame:
    """(query_id, nodes_checked) without the leaves: a node is tested if its parent matches, so the cost is one for each
    root and the children of each matching inner node. Reads every inner node; for measuring only."""
    if index.load is not None and dict(index.load.members.dtypes)["element"] == dict(probes.dtypes)["element"]:
        return _load_cost(index, probes)
    return nodes_tested(search_parts(index, probes, leaves=False), index, probes)


def root_words(index: TreeIndex) -> DataFrame:
    """(tree_id, word_ix, word) of the roots. That of a sorted load is the filter of all its sets' elements together."""
    if index.load is None:
        return index.words.join(index.nodes.where("parent_id is null").select("tree_id", "node_id"), ["tree_id", "node_id"], "left_semi").select("tree_id", "word_ix", "word")
    from filterfleet.operators.filters import build_filters

    return build_filters(index.load.members.select(F.lit(0).alias("site_id"), "element"), index.spec).withColumnRenamed("filter_id", "tree_id")


def any_match(index: TreeIndex, probes: DataFrame) -> DataFrame:
    """Probes that some filter may hold: the roots' answer, which cannot say where."""
    roots = index.words.join(index.nodes.where("parent_id is null").select("tree_id", "node_id"), ["tree_id", "node_id"], "left_semi")
    met = probe_words(probes, index.spec).join(roots, "word_ix").where("word & mask = mask")
    return met.groupBy("query_id", "tree_id").agg(F.count("*").alias("n"), F.first("n_words").alias("of")).where("n = of").select("query_id").distinct()


def site_match(index: TreeIndex, asked: DataFrame) -> DataFrame:
    """(query_id, filter_id) of asked (query_id, element, filter_id) whose own filter matches; no hierarchy is needed."""
    leaves = index.nodes.where("level = 0").select("filter_id", "tree_id", "node_id")
    wanted = probe_words(asked, index.spec).join(asked.select("query_id", "filter_id"), "query_id").join(leaves, "filter_id")
    met = wanted.join(index.words, ["tree_id", "node_id", "word_ix"]).where("word & mask = mask")
    return met.groupBy("query_id", "filter_id").agg(F.count("*").alias("n"), F.first("n_words").alias("of")).where("n = of").select("query_id", "filter_id")


def ancestors(nodes: DataFrame) -> DataFrame:
    """(tree_id, filter_id, node_id) of each filter's leaf and all nodes above it, by one join a level on the shape."""
    here = nodes.where("level = 0 and filter_id is not null").select("tree_id", "filter_id", "node_id", "parent_id")
    out, above = here.select("tree_id", "filter_id", "node_id"), nodes.select("tree_id", F.col("node_id").alias("up"), F.col("parent_id").alias("next"))
    for _ in range(nodes.agg(F.max("level").alias("h")).first()["h"] or 0):
        here = here.withColumnRenamed("parent_id", "up").join(above, ["tree_id", "up"]).select("tree_id", "filter_id", F.col("up").alias("node_id"), F.col("next").alias("parent_id"))
        out = out.unionByName(here.select("tree_id", "filter_id", "node_id"))
    return out


def tree_update(index: TreeIndex, delta: DataFrame) -> TreeIndex:
    """New bits (filter_id, word_ix, word) OR-ed into their leaves and every node above; the shape stays.

    Order-free for any number of updates; applying a batch twice changes nothing. Only the paths of changed leaves move.
    """
    lifted = delta.join(ancestors(index.nodes), "filter_id").select("tree_id", "node_id", "word_ix", "word")
    return TreeIndex(index.nodes, ored_into(index.words, lifted, "tree_id", "node_id", "word_ix"), index.spec, index.d)


def revalue(index: TreeIndex, leaf_words: DataFrame) -> DataFrame:
    """All node words, from leaf words (filter_id, word_ix, word) and the shape."""
    return leaf_words.join(ancestors(index.nodes), "filter_id").groupBy("tree_id", "node_id", "word_ix").agg(F.bit_or("word").alias("word"))


def tree_replace(index: TreeIndex, fresh: DataFrame, changed: DataFrame) -> TreeIndex:
    """Filters whose bits are to be set anew, elements gone included: changed (filter_id) take their words from fresh.

    Bits can't be taken out of an OR, so all node values are formed again from the leaves; the shape stays.
    """
    kept = leaf_words(index).join(changed, "filter_id", "left_anti")
    return TreeIndex(index.nodes, revalue(index, kept.unionByName(fresh.join(changed, "filter_id", "left_semi"))), index.spec, index.d)


def leaf_words(index: TreeIndex) -> DataFrame:
    leaves = index.nodes.where("level = 0").select("tree_id", "node_id", "filter_id")
    return index.words.join(leaves, ["tree_id", "node_id"]).select("filter_id", "word_ix", "word")


def rebuild(index: TreeIndex, order: str = "id", d: int | None = None) -> TreeIndex:
    """A fresh sorted load of the present filters."""
    present = numbered(index.nodes.where("level = 0 and filter_id is not null").select("filter_id"), "filter_id", "place") if order == "id" else None
    return bulk_load(leaf_words(index), index.spec, d or index.d, order, present)


def resize(membership: DataFrame, spec: FilterSpec, d: int = 2, order: str = "id") -> TreeIndex:
    """A tree over filters long enough for all elements of all sites together, built anew from the sets."""
    from filterfleet.operators.filters import build_filters

    total = membership.agg(F.countDistinct("element").alias("n")).first()["n"]
    wide = FilterSpec(max(1, total), spec.target_fp, spec.family)
    return bulk_load(build_filters(membership, wide), wide, d, order)


def shape(index: TreeIndex) -> DataFrame:
    """Height, nodes, inner nodes and mean fan-out of each tree."""
    inner = F.expr("level > 0")
    return index.nodes.groupBy("tree_id").agg(
        F.max("level").alias("height"), F.count("*").alias("n_nodes"), F.count_if(inner).alias("n_inner"), F.avg(F.when(inner, F.col("n_children"))).alias("mean_fanout")
    )


def level_fill(index: TreeIndex) -> DataFrame:
    """Fill and false-positive rate of the nodes of each level, mean over nodes."""
    ones = index.words.groupBy("tree_id", "node_id").agg(F.sum(F.bit_count("word")).alias("ones"))
    per = index.nodes.join(ones, ["tree_id", "node_id"], "left").withColumn("fill", F.coalesce("ones", F.lit(0)) / index.spec.m)
    return per.groupBy("level").agg(F.count("*").alias("n_nodes"), F.avg("fill").alias("mean_fill"), F.avg(F.pow("fill", F.lit(index.spec.k))).alias("mean_fp"))


def violations(index: TreeIndex) -> DataFrame:
    """(rule, tree_id, node_id) of every broken rule of the structure; empty for a sound tree."""
    nodes, words, d = index.nodes, index.words, index.d
    kids = nodes.where("parent_id is not null").select("tree_id", F.col("parent_id").alias("up"), "node_id", "level")
    ored = kids.join(words, ["tree_id", "node_id"]).groupBy("tree_id", F.col("up").alias("node_id"), "word_ix").agg(F.bit_or("word").alias("ored"))
    inner = nodes.where("level > 0").select("tree_id", "node_id", "level", "n_children", "parent_id")
    own = words.join(inner.select("tree_id", "node_id"), ["tree_id", "node_id"], "left_semi")
    value = own.join(ored, ["tree_id", "node_id", "word_ix"], "full").where("not (word <=> ored)").select(F.lit("value").alias("rule"), "tree_id", "node_id")
    counted = kids.groupBy("tree_id", F.col("up").alias("node_id")).agg(F.count("*").alias("kids"), F.min("level").alias("low"), F.max("level").alias("high"))
    full = words.groupBy("tree_id", "node_id").agg(F.sum(F.bit_count("word")).alias("ones"))
    placed = inner.join(counted, ["tree_id", "node_id"], "left").join(full, ["tree_id", "node_id"], "left")
    fanout = placed.where(f"kids is null or kids <> n_children or (parent_id is not null and kids < {d}) or (kids > {2 * d} and coalesce(ones, 0) < {index.spec.m})").select(F.lit("fanout").alias("rule"), "tree_id", "node_id")
    depth = placed.where("low <> level - 1 or high <> level - 1").select(F.lit("depth").alias("rule"), "tree_id", "node_id")
    twice = nodes.where("filter_id is not null").groupBy("filter_id").agg(F.count("*").alias("n"), F.min("tree_id").alias("tree_id"), F.min("node_id").alias("node_id")).where("n > 1").select(F.lit("id").alias("rule"), "tree_id", "node_id")
    return value.unionByName(fanout).unionByName(depth).unionByName(twice)

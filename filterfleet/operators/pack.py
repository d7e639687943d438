"""The bit-sliced pack: 64 filters side by side in the lanes of one word for each bit position.

`slices` (block_id, pos, word) holds words that aren't zero; `slots` (slot, block_id, lane, filter_id, in_use) says
which filter has which lane. A missing slice is a zero word, so an AND over a probe's positions has to count them.
"""

from __future__ import annotations

import os
import tempfile
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from filterfleet.functions.frames import broadcast_if_small, numbered, ored_into, stored
from filterfleet.functions.hashing import positions, probe_bits, set_bits
from filterfleet.functions.params import WORD, FilterSpec


@dataclass
class PackIndex:
    slices: DataFrame
    slots: DataFrame
    spec: FilterSpec
    #: The sets (site_id, element) that slices are formed of, while the index is as built.
    members: DataFrame | None = None


def with_lanes(slots: DataFrame) -> DataFrame:
    return slots.withColumns({"block_id": F.expr(f"slot div {WORD}").cast("int"), "lane": (F.col("slot") % WORD).cast("int")})


def assign_slots(filter_ids: DataFrame) -> DataFrame:
    """Slots 0, 1, 2 ... in order of id. Ids are kept first, so the sets behind them are read once for all of numbering."""
    return with_lanes(numbered(stored(filter_ids.select("filter_id").distinct(), "filter-ids"), "filter_id", "slot")).select("slot", "block_id", "lane", "filter_id", F.lit(True).alias("in_use"))


def _lane_bit(lane: str = "lane"):
    return F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col(lane))


def _sliced(bits: DataFrame, slots: DataFrame) -> DataFrame:
    """(block_id, pos, word) of set bits (filter_id, pos)."""
    placed = bits.join(broadcast_if_small(slots.where("in_use").select("filter_id", "block_id", "lane")), "filter_id")
    return placed.groupBy("block_id", "pos").agg(F.bit_or(_lane_bit()).alias("word"))


def pack_build(membership: DataFrame, spec: FilterSpec, slots: DataFrame | None = None) -> PackIndex:
    """From sets straight to slices: no filter is formed on the way."""
    members = membership.where("site_id is not null and element is not null").select("site_id", "element")
    slots = assign_slots(members.select(F.col("site_id").alias("filter_id"))) if slots is None else slots
    return PackIndex(_sliced(set_bits(membership, spec).withColumnRenamed("site_id", "filter_id"), slots), slots, spec, members)


def lanes(word):
    return F.filter(F.sequence(F.lit(0), F.lit(WORD - 1)), lambda i: F.getbit(word, i) == 1)


def _anded(index: PackIndex, probes: DataFrame) -> DataFrame:
    met = broadcast_if_small(probe_bits(probes, index.spec)).join(index.slices, "pos")
    return met.groupBy("query_id", "block_id").agg(F.bit_and("word").alias("word"), F.count("*").alias("n"), F.first("k_distinct").alias("k"))


def pack_search(index: PackIndex, probes: DataFrame, few_blocks: int = 16) -> DataFrame:
    """(query_id, filter_id): per block the AND of the probe's words; every lane left is a match.

    A row for each probe, position and block would be far more than sets and matches together, so an index as built that
    has more than few_blocks blocks is searched in tasks that hold slices of many blocks (`_search_blocks`).
    """
    if index.members is not None and dict(index.members.dtypes)["element"] == dict(probes.dtypes)["element"]:
        slots = stored(index.slots.where("in_use").select("slot", "block_id", "lane", "filter_id"), "slots")
        blocks = slots.agg(F.coalesce(F.max("block_id") + 1, F.lit(0)).alias("n")).first()["n"]
        if blocks > few_blocks:
            return _search_blocks(index.members, slots, blocks, probes, index.spec)
        index = PackIndex(index.slices, slots.withColumn("in_use", F.lit(True)), index.spec)
    hits = _anded(index, probes).where("n = k and word <> 0").select("query_id", "block_id", F.explode(lanes(F.col("word"))).alias("lane"))
    return hits.join(broadcast_if_small(index.slots.where("in_use").select("block_id", "lane", "filter_id")), ["block_id", "lane"]).select("query_id", "filter_id")


def _or_in(flat: np.ndarray, wide: int, slot: np.ndarray, spots: np.ndarray) -> None:
    """Sets the bits of elements in words that lie `wide` blocks to a position; blocks count from their part's first one."""
    place = slot % (wide * WORD)
    at = spots * wide + (place >> 6)[:, None]
    np.bitwise_or.at(flat, at.ravel(), np.repeat(np.uint64(1) << (place & 63).astype(np.uint64), at.shape[1]))


def _spots(batch: pa.RecordBatch) -> np.ndarray:
    return batch.column("spots").flatten().to_numpy().astype(np.int64).reshape(batch.num_rows, -1)


def _block_task(wide: int, spec: FilterSpec, most_bytes: int = 8 << 20) -> Callable[[Iterator], Iterator]:
    """A task over rows of a part: first its sets' elements, which set bits in its `wide` blocks' words (a row of words
    for each position), then probes. A probe's rows of words are ANDed one by one; when none is left, the rest isn't read."""

    def run(batches):
        words = np.zeros((spec.m, wide), np.uint64)
        flat, one, some = words.reshape(-1), np.uint64(1), max(1, most_bytes // (8 * wide))
        for batch in batches:
            if not batch.num_rows:
                continue
            asks = np.asarray(batch.column("asks").to_numpy(zero_copy_only=False), bool)
            spots = _spots(batch)
            slot = batch.column("slot").to_numpy(zero_copy_only=False).astype(np.int64)
            _or_in(flat, wide, slot[~asks], spots[~asks])
            for start in range(int((~asks).sum()), batch.num_rows, some):  # rows are in this order
                rows = np.arange(start, min(start + some, batch.num_rows))
                left = words[spots[rows, 0]]
                for k in range(1, spots.shape[1]):
                    alive = left.any(axis=1)
                    if not alive.all():
                        rows, left = rows[alive], left[alive]
                    left &= words[spots[rows, k]]
                row, block = np.nonzero(left)
                hit, lane = np.nonzero((left[row, block][:, None] >> np.arange(WORD, dtype=np.uint64)) & one)
                if len(hit):
                    first = slot[rows[row[hit]]]  # of the part
                    yield pa.RecordBatch.from_arrays([batch.column("query_id").take(pa.array(rows[row[hit]])), pa.array(first + block[hit] * WORD + lane)], names=["query_id", "slot"])

    return run


def _parts(blocks: int, spec: FilterSpec, most_bytes: int) -> tuple[int, int]:
    """How many neighbouring blocks are a part, whose words fit in most_bytes, and how many parts there are."""
    wide = max(1, min(most_bytes // (8 * spec.m), -(-blocks // 16)))
    return wide, -(-blocks // wide)


def _in_parts(members: DataFrame, slots: DataFrame, wide: int) -> DataFrame:
    """(site_id, element, slot, part)."""
    placed = members.join(broadcast_if_small(slots.select(F.col("filter_id").alias("site_id"), "slot")), "site_id")
    return placed.withColumn("part", F.expr(f"int(slot div {wide * WORD})"))


def write_words(index: PackIndex, folder: str, most_bytes: int = 64 << 20) -> None:
    """The words of an index as built, zero ones included, in a file for each part of blocks: spec.m rows of the part's
    words, which readers map into memory. Files are <first block>.npy in a folder that driver and executors share."""
    blocks = index.slots.agg(F.coalesce(F.max("block_id") + 1, F.lit(0)).alias("n")).first()["n"]
    wide, parts = _parts(max(1, blocks), index.spec, most_bytes)
    spec = index.spec

    def run(batches):
        words, part = None, 0
        for batch in batches:
            if batch.num_rows:
                slot = batch.column("slot").to_numpy(zero_copy_only=False).astype(np.int64)
                if words is None:
                    words, part = np.zeros((spec.m, wide), np.uint64), int(slot[0]) // (wide * WORD)
                _or_in(words.reshape(-1), wide, slot, _spots(batch))
        if words is not None:
            os.makedirs(folder, exist_ok=True)
            with tempfile.NamedTemporaryFile(dir=folder, suffix=".part", delete=False) as out:
                np.save(out, words)
            os.replace(out.name, f"{folder}/{part * wide}.npy")  # the same whichever attempt of a task comes last
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32())], names=["part"])

    rows = _in_parts(index.members, index.slots, wide).repartitionById(parts, F.col("part")).select("slot", positions(F.col("element"), spec).alias("spots"))
    rows.mapInArrow(run, "part int").agg(F.count("*")).collect()


def _search_blocks(members: DataFrame, slots: DataFrame, blocks: int, probes: DataFrame, spec: FilterSpec, most_bytes: int = 64 << 20) -> DataFrame:
    """Pack search by parts of neighbouring blocks whose words fit in most_bytes: a part's sets and all probes meet in
    its task. What moves is the sets once, and the probes once for each part."""
    wide, parts = _parts(blocks, spec, most_bytes)
    lanes_in = wide * WORD
    asked = probes.where("element is not null").select("query_id", "element").distinct()
    kind = dict(asked.dtypes)["query_id"]
    placed = _in_parts(members, slots, wide).select("part", F.lit(False).alias("asks"), "slot", F.lit(None).cast(kind).alias("query_id"), "element")
    dealt = asked.select(F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"), "query_id", "element")
    dealt = dealt.select("part", F.lit(True).alias("asks"), F.expr(f"part * {lanes_in}L").alias("slot"), "query_id", "element")
    # Elements are hashed behind the shuffle, where a part's tasks read them.
    rows = placed.unionByName(dealt).repartitionById(parts, F.col("part")).sortWithinPartitions("asks").select("asks", "slot", "query_id", positions(F.col("element"), spec).alias("spots"))
    hits = rows.mapInArrow(_block_task(wide, spec), f"query_id {kind}, slot bigint")
    return hits.join(broadcast_if_small(slots.select("slot", "filter_id")), "slot").select("query_id", "filter_id")


def words_read(index: PackIndex, probes: DataFrame) -> DataFrame:
    """(query_id, words_read): slices fetched for each probe; zero words aren't stored, so it is at most k for a block."""
    asked = probe_bits(probes, index.spec).select("query_id").distinct()
    return asked.join(_anded(index, probes).groupBy("query_id").agg(F.sum("n").alias("words_read")), "query_id", "left").fillna(0, ["words_read"])


def pack_insert(index: PackIndex, membership: DataFrame) -> PackIndex:
    """New filters take free slots from the lowest on, then new blocks."""
    fresh = membership.where("site_id is not null and element is not null").select(F.col("site_id").alias("filter_id")).distinct()
    ranked = numbered(fresh, "filter_id", "turn")
    free = numbered(index.slots.where("not in_use").select("slot"), "slot", "turn")
    blocks = index.slots.agg(F.coalesce(F.max("block_id") + 1, F.lit(0)).alias("n")).first()["n"]
    n_free = free.count()
    taken = with_lanes(ranked.join(free, "turn", "left").withColumn("slot", F.coalesce("slot", F.col("turn") - n_free + blocks * WORD)).drop("turn"))
    taken = taken.select("slot", "block_id", "lane", "filter_id", F.lit(True).alias("in_use"))
    slots = index.slots.join(taken.select("slot"), "slot", "left_anti").unionByName(taken)
    added = _sliced(set_bits(membership, index.spec).withColumnRenamed("site_id", "filter_id"), taken)
    return PackIndex(ored_into(index.slices, added, "block_id", "pos"), slots, index.spec)


def pack_delete(index: PackIndex, gone: DataFrame, compact: bool = True) -> PackIndex:
    """Clears the lanes of filters in all slices of their blocks and frees their slots; compact: blocks without a
    filter go, and later slots move down by 64 for each."""
    hit = index.slots.where("in_use").join(gone.select("filter_id").distinct(), "filter_id", "left_semi")
    masks = hit.groupBy("block_id").agg(F.bit_or(_lane_bit()).alias("mask"))
    words = index.slices.join(broadcast_if_small(masks), "block_id", "left").withColumn("word", F.expr("word & ~coalesce(mask, 0)")).where("word <> 0").select("block_id", "pos", "word")
    freed = index.slots.join(hit.select("slot", F.lit(True).alias("freed")), "slot", "left")
    slots = freed.select("slot", "block_id", "lane", F.expr("if(freed, null, filter_id)").alias("filter_id"), F.expr("in_use and freed is null").alias("in_use"))
    if not compact:
        return PackIndex(words, slots, index.spec)
    kept = slots.groupBy("block_id").agg(F.max("in_use").alias("used")).where("used").select(F.col("block_id").alias("old_block"))
    number = numbered(kept, "old_block", "new_block").withColumn("new_block", F.col("new_block").cast("int"))
    number = broadcast_if_small(number)
    moved = slots.join(number, F.col("block_id") == F.col("old_block")).select((F.col("new_block") * WORD + F.col("lane")).cast("bigint").alias("slot"), F.col("new_block").alias("block_id"), "lane", "filter_id", "in_use")
    shifted = words.join(number, F.col("block_id") == F.col("old_block")).select(F.col("new_block").alias("block_id"), "pos", "word")
    return PackIndex(shifted, moved, index.spec)


def pack_update(index: PackIndex, delta: DataFrame) -> PackIndex:
    """New elements (site_id, element) of filters that are there: their bits are OR-ed into the lanes."""
    added = _sliced(set_bits(delta, index.spec).withColumnRenamed("site_id", "filter_id"), index.slots)
    return PackIndex(ored_into(index.slices, added, "block_id", "pos"), index.slots, index.spec)


def pack_compact(index: PackIndex) -> PackIndex:
    """Packs the filters that are left into as few blocks as they need."""
    present = index.slots.where("in_use")
    fresh = assign_slots(present.select("filter_id"))
    bits = index.slices.select("block_id", "pos", F.explode(lanes(F.col("word"))).alias("lane")).join(present.select("block_id", "lane", "filter_id"), ["block_id", "lane"])
    return PackIndex(_sliced(bits.select("filter_id", "pos"), fresh), fresh, index.spec)


def to_wide(index: PackIndex) -> DataFrame:
    """(pos, words ARRAY<BIGINT>): one row a position, its words of all blocks side by side."""
    n = index.slots.agg(F.coalesce(F.max("block_id") + 1, F.lit(0)).alias("n")).first()["n"]
    at = F.map_from_entries(F.collect_list(F.struct("block_id", "word")))
    full = F.transform(F.sequence(F.lit(0), F.lit(max(n - 1, 0))), lambda b: F.coalesce(F.element_at(F.col("at"), b), F.lit(0).cast("bigint")))
    return index.slices.groupBy("pos").agg(at.alias("at")).select("pos", full.alias("words"))


def wide_search(wide: DataFrame, index: PackIndex, probes: DataFrame) -> DataFrame:
    met = probe_bits(probes, index.spec).join(wide, "pos").groupBy("query_id").agg(F.collect_list("words").alias("rows"), F.count("*").alias("n"), F.first("k_distinct").alias("k")).where("n = k")
    anded = F.aggregate("rows", F.element_at("rows", 1), lambda a, b: F.zip_with(a, b, lambda x, y: x.bitwiseAND(y)))
    hits = met.select("query_id", F.posexplode(anded).alias("block_id", "word")).where("word <> 0").select("query_id", "block_id", F.explode(lanes(F.col("word"))).alias("lane"))
    return hits.join(index.slots.where("in_use").select("block_id", "lane", "filter_id"), ["block_id", "lane"]).select("query_id", "filter_id")


def fragmentation(index: PackIndex) -> DataFrame:
    """Share of each block's 64 lanes that is in use."""
    return index.slots.groupBy("block_id").agg((F.count_if("in_use") / WORD).alias("used"))


def block_unions(index: PackIndex) -> DataFrame:
    """(block_id, pos): positions that any filter of a block has; the block's union filter."""
    return index.slices.select("block_id", "pos")


def hybrid_search(index: PackIndex, probes: DataFrame) -> DataFrame:
    """Pack search that skips blocks whose union filter lacks one of the probe's positions: only the presence of slices
    is read for those, and words of the rest alone."""
    wanted = probe_bits(probes, index.spec)
    alive = wanted.join(block_unions(index), "pos").groupBy("query_id", "block_id").agg(F.count("*").alias("n"), F.first("k_distinct").alias("k")).where("n = k").select("query_id", "block_id")
    met = alive.join(wanted, "query_id").join(index.slices, ["block_id", "pos"]).groupBy("query_id", "block_id").agg(F.bit_and("word").alias("word")).where("word <> 0")
    hits = met.select("query_id", "block_id", F.explode(lanes(F.col("word"))).alias("lane"))
    return hits.join(index.slots.where("in_use").select("block_id", "lane", "filter_id"), ["block_id", "lane"]).select("query_id", "filter_id")

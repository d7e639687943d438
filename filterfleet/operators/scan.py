"""The baseline: every filter is tested for every probe. Also its relational forms, its upkeep, and exact search."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from filterfleet.functions.frames import ored_into, stored
from filterfleet.functions.hashing import positions, probe_bits
from filterfleet.functions.params import WORD, FilterSpec
from filterfleet.operators.filters import bit_of


def scan_search(filters: DataFrame, probes: DataFrame, spec: FilterSpec) -> DataFrame:
    """(query_id, filter_id) by testing all pairs of a dense filter and a probe; pairs are filtered as they are formed.

    A probe is hashed once, into a word number and a mask for each position. The tests of a pair are a chain of plain
    comparisons in generated code, which ends at the first position whose bit is 0.
    """
    spots = probes.where("element is not null").select("query_id", positions(F.col("element"), spec).alias("spots"))
    flat = spots.select("query_id", *(c for i in range(spec.k) for c in (F.expr(f"spots[{i}] div {WORD}").cast("int").alias(f"ix{i}"), bit_of(F.col("spots")[i]).alias(f"mask{i}"))))
    return filters.join(flat, F.expr(" and ".join(f"words[ix{i}] & mask{i} <> 0" for i in range(spec.k)))).select("query_id", "filter_id")


def scan_search_positions(filter_bits: DataFrame, probes: DataFrame, spec: FilterSpec) -> DataFrame:
    """The same by an equality join on positions: a filter matches if it has as many of the probe's positions as differ."""
    met = probe_bits(probes, spec).join(filter_bits, "pos")
    return met.groupBy("query_id", "filter_id").agg(F.count("*").alias("n"), F.first("k_distinct").alias("k")).where("n = k").select("query_id", "filter_id")


def _ordered_task(spec: FilterSpec, guess: int, most_candidates: int = 1 << 20) -> Callable[[Iterator], Iterator]:
    """A task over a part of the filters: first its sets' elements in order of filter, each filter a row of bits and, for
    each position, a list of the filters that have it; then probes. A probe's rarest list gives its candidates, and each
    further position leaves those that have it."""

    def run(batches):
        width = -(-spec.m // 8)
        flat, known, lists, new = np.zeros(guess * width, np.uint8), np.empty(0, np.int64), None, [np.empty((2, 0), np.int32)]
        for batch in batches:
            if not batch.num_rows:
                continue
            spots = batch.column("spots").flatten().to_numpy().astype(np.int64).reshape(batch.num_rows, -1)
            own = batch.num_rows - int(np.asarray(batch.column("asks").to_numpy(zero_copy_only=False), bool).sum())
            if own:
                site = batch.column("site_id").slice(0, own).to_numpy(zero_copy_only=False).astype(np.int64)
                first = np.append(not len(known) or site[0] != known[-1], site[1:] != site[:-1])
                at = len(known) - 1 + np.cumsum(first)
                known = np.append(known, site[first])
                if len(known) * width > len(flat):
                    flat = np.append(flat, np.zeros(len(known) * width * 5 // 4 - len(flat), np.uint8))
                row, spot = np.divmod(np.unique(at[:, None] * spec.m + spots[:own]), spec.m)
                place = row * width + (spot >> 3)
                fresh = flat[place] >> (spot & 7).astype(np.uint8) & 1 == 0  # a filter may go on in the next batch
                np.bitwise_or.at(flat, place, np.uint8(1) << (spot & 7).astype(np.uint8))
                new.append(np.stack([row[fresh], spot[fresh]]).astype(np.int32))
            if own == batch.num_rows:
                continue
            if lists is None:  # all sets are read
                row, spot = np.concatenate(new, axis=1)
                lists, held, new = row[np.argsort(spot, kind="stable")], np.bincount(spot, minlength=spec.m), []
                starts = np.cumsum(held) - held
            asked = spots[own:]
            asked = np.take_along_axis(asked, np.argsort(held[asked], axis=1), axis=1)
            n = held[asked[:, 0]]
            for some in np.split(np.arange(len(asked)), np.flatnonzero(np.diff(np.cumsum(n) // most_candidates)) + 1):
                who = np.repeat(some, n[some])
                turn = np.arange(len(who)) - np.repeat(np.cumsum(n[some]) - n[some], n[some])
                left = lists[starts[asked[who, 0]] + turn].astype(np.int64)
                for k in range(1, asked.shape[1]):
                    spot = asked[who, k]
                    has = flat[left * width + (spot >> 3)] >> (spot & 7).astype(np.uint8) & 1 == 1
                    who, left = who[has], left[has]
                if len(left):
                    yield pa.RecordBatch.from_arrays([batch.column("query_id").take(pa.array(who + own)), pa.array(known[left])], names=["query_id", "filter_id"])

    return run


def scan_search_ordered(membership: DataFrame, probes: DataFrame, spec: FilterSpec, most_bytes: int = 64 << 20) -> DataFrame:
    """The same with early exit, from the sets: candidates have the probe's rarest position, each further one thins them out.

    Candidates are far more than sets and matches together, so they come up in tasks and are never rows: filters are dealt
    into parts whose bits and lists fit in most_bytes each. What moves is the sets once, and the probes once for each part.
    """
    sets = stored(membership.where("site_id is not null and element is not null").select(F.col("site_id").cast("bigint").alias("site_id"), "element"), "sets")
    n = sets.agg(F.count("*").alias("rows"), F.count_distinct("site_id").alias("sites")).first()
    fit = lambda size: -(-size // most_bytes)
    parts = max(1, min(16, n["sites"] // 64), fit(n["sites"] * -(-spec.m // 8)), fit(8 * n["rows"] * spec.k))
    asked = probes.where("element is not null").select("query_id", "element").distinct()
    kind = dict(asked.dtypes)["query_id"]
    placed = sets.select(F.expr(f"int(pmod(xxhash64(site_id), {parts}))").alias("part"), F.lit(False).alias("asks"), "site_id", F.lit(None).cast(kind).alias("query_id"), "element")
    dealt = asked.select(F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"), F.lit(True).alias("asks"), F.lit(None).cast("bigint").alias("site_id"), "query_id", "element")
    # Elements are hashed behind the shuffle, where a part's tasks read them.
    rows = placed.unionByName(dealt).repartitionById(parts, F.col("part")).sortWithinPartitions("asks", "site_id").select("asks", "site_id", "query_id", positions(F.col("element"), spec).alias("spots"))
    return rows.mapInArrow(_ordered_task(spec, n["sites"] // parts + 64), f"query_id {kind}, filter_id bigint")


def scan_cost(filters: DataFrame, probes: DataFrame) -> DataFrame:
    """Filters tested for each probe: all of them."""
    return probes.where("element is not null").select("query_id").crossJoin(filters.agg(F.countDistinct("filter_id").alias("nodes_checked")))  # one row


def scan_insert(filter_words: DataFrame, fresh: DataFrame) -> DataFrame:
    return filter_words.unionByName(fresh)


def scan_delete(filter_words: DataFrame, gone: DataFrame) -> DataFrame:
    return filter_words.join(gone, "filter_id", "left_anti")


def scan_update(filter_words: DataFrame, delta: DataFrame) -> DataFrame:
    return ored_into(filter_words, delta, "filter_id", "word_ix")


def exact_search(membership: DataFrame, probes: DataFrame) -> DataFrame:
    """(query_id, filter_id) from the sets themselves: the truth that filters approximate."""
    return probes.join(membership, "element").select("query_id", F.col("site_id").alias("filter_id")).distinct()

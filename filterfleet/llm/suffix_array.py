"""Substring dedup at byte level by difference-cover suffix sorting.

Contexts around repeated grams (see anchors.py) are dealt out by gram; a task strings the contexts of a block together
and sorts their suffixes: those at places that aren't multiples of three are named by their triples, sorted by
recursion on the names, and the others are merged in by their first byte and the rank of the suffix after it.
The recursion ends once names cover `least` bytes, as no deeper order is asked for. Neighbours in the sorted order
whose first `least` bytes are equal are repeats.

All bytes of windows that start anywhere else too (the same document included) are removed; windows are judged on the
input. Null text counts as empty; matches never cross documents; repeated rows remove each other's text (both);
null ids are kept as rows of their own; other columns are ignored; no rows give no rows.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from filterfleet.llm.anchors import byte_elements, covered, keyed, repeated_windows, with_stretches
from filterfleet.llm.common import table

LEAST = 200


def packed(*columns: np.ndarray) -> np.ndarray:
    """One number for each row of non-negative columns, in their lexicographic order."""
    out = columns[0].astype(np.int64)
    for c in columns[1:]:
        wide = int(c.max(initial=0)) + 1
        if int(out.max(initial=0)) >= (1 << 62) // wide:
            out = np.unique(out, return_inverse=True)[1]
        out = out * wide + c
    return out


def suffix_ranks(text: np.ndarray, depth: int) -> np.ndarray:
    """A rank for each suffix, in order of its first `depth` symbols (all above 0); deeper order is arbitrary."""
    n = len(text)
    if n < 3 or depth <= 1:
        order = np.argsort(text, kind="stable") if depth <= 1 else sorted(range(n), key=lambda i: text[i:].tolist())
        ranks = np.empty(n, np.int64)
        ranks[order] = np.arange(n)
        return ranks
    s = np.concatenate([text.astype(np.int64), np.zeros(3, np.int64)])
    zero, one, two = (np.arange(k, n, 3) for k in range(3))
    cover = np.concatenate([one, two])
    triples = packed(s[cover], s[cover + 1], s[cover + 2])
    distinct, names = np.unique(triples, return_inverse=True)
    if len(distinct) < len(cover):
        # The names of both classes in a row, with a least symbol between them.
        deeper = suffix_ranks(np.concatenate([names[: len(one)] + 2, [1], names[len(one) :] + 2]), -(-depth // 3))
        names = np.concatenate([deeper[: len(one)], deeper[len(one) + 1 :]])
    rank = np.zeros(n + 3, np.int64)
    rank[cover] = names + 1
    sort = np.argsort(names, kind="stable")
    sampled = cover[sort]
    is_one = sampled % 3 == 1
    ones, twos = sampled[is_one], sampled[~is_one]
    by_one, by_two = packed(s[:n], rank[1 : n + 1]), packed(s[:n], s[1 : n + 1], rank[2 : n + 2])
    zero = zero[np.argsort(by_one[zero], kind="stable")]
    # Place of each suffix in the merged order: those of its own class before it, and of the other class before it.
    at_zero = np.arange(len(zero)) + np.searchsorted(by_one[ones], by_one[zero]) + np.searchsorted(by_two[twos], by_two[zero])
    at_sample = np.arange(len(sampled))
    at_sample[is_one] += np.searchsorted(by_one[zero], by_one[ones], "right")
    at_sample[~is_one] += np.searchsorted(by_two[zero], by_two[twos], "right")
    merged = np.concatenate([zero, sampled])[np.argsort(np.concatenate([at_zero, at_sample]), kind="stable")]
    out = np.empty(n, np.int64)
    out[merged] = np.arange(n)
    return out


def search_contexts(contexts: list[tuple[bytes, int]], least: int = LEAST) -> list[np.ndarray]:
    """For each context, which of its windows equal another window of any of them."""
    joined = b"\x00".join(c for c, _ in contexts)
    raw = np.frombuffer(joined, np.uint8)
    sizes = np.array([len(c) for c, _ in contexts])
    begin = np.cumsum(sizes + 1) - sizes - 1
    text = raw.astype(np.int64) + 2
    text[begin[1:] - 1] = 1
    windows = np.array([w for _, w in contexts])
    ends = np.cumsum(windows)
    starts = np.repeat(begin, windows) + np.arange(ends[-1]) - np.repeat(ends - windows, windows)
    order = np.argsort(suffix_ranks(text, least)[starts])
    by_rank = starts[order]
    views = np.lib.stride_tricks.sliding_window_view(raw, least)
    same = np.zeros(max(len(by_rank) - 1, 0), bool)
    for k in range(0, len(same), 4096):
        part = slice(k, min(k + 4096, len(same)))
        a, b = by_rank[:-1][part], by_rank[1:][part]
        likely = np.flatnonzero((raw[a] == raw[b]) & (raw[a + least - 1] == raw[b + least - 1]))
        same[k + likely] = (views[a[likely]] == views[b[likely]]).all(axis=1)
    twice = np.zeros(len(starts), bool)
    twice[order[:-1]] |= same
    twice[order[1:]] |= same
    return np.split(twice, ends[:-1])


def _cut(text: bytes):
    return lambda first, count: text[first : first + count]


def repeats(docs: DataFrame, least: int = LEAST, gram: int = 64, **options) -> DataFrame:
    """(doc_id, mark, text, stretches) for every document; stretches: where repeated windows start."""
    base = keyed(docs)
    return with_stretches(base, repeated_windows(base, byte_elements, _cut, lambda c: search_contexts(c, least), least, gram, **options))


REMOVED = "doc_id bigint, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string"


def deduplicated(docs: DataFrame, least: int = LEAST, gram: int = 64, **options) -> DataFrame:
    def run(batches):
        for batch in batches:
            rows = []
            for doc_id, text, stretches in zip(*(batch.column(c) for c in ("doc_id", "text", "stretches"))):
                raw = np.frombuffer(text.as_py().encode(), np.uint8)
                gone = covered(len(raw), stretches.as_py(), least)
                spans = int(gone[:1].sum() + (gone[1:] & ~gone[:-1]).sum())
                rows.append((doc_id.as_py(), len(raw), int(gone.sum()), spans, hashlib.sha256(raw[~gone].tobytes()).hexdigest()))
            kinds = [pa.int64()] * 4 + [pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows) if rows else [[]] * 5, kinds)], names=[x.split()[0] for x in REMOVED.split(", ")])

    return repeats(docs, least, gram, **options).mapInArrow(run, REMOVED).withColumn("doc_id", F.expr(f"nullif(doc_id, {-(2**63) + 1}L - 1L)"))


def op5_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    return deduplicated(table(spark, sf_dir, "documents"))


QUERIES = {"op5_suffix_array": op5_suffix_array}
ORACLES: dict = {}

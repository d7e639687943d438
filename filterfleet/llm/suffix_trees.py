"""Substring dedup at word level by prefix-partitioned suffix trees.

Contexts around repeated grams (see anchors.py) are dealt out by gram. In a block, suffixes are split by prefixes of
variable length: a group of suffixes with one prefix is split by longer ones, and a group of one suffix is a leaf and
done with. Groups that still hold two suffixes at `least` words are the deep inner nodes of their subtree; the windows
below them are repeats (a longer repeat is a run of such windows). Words are compared by 64-bit hashes.

All words of windows that start anywhere else too (the same document included) are removed; windows are judged on the
input. Null text has no words; windows never cross documents; repeated rows remove each other's words (both); null
ids are kept as rows of their own; other columns are ignored; no rows give no rows.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from filterfleet.llm.anchors import Hashes, covered, keyed, repeated_windows, with_stretches, word_elements
from filterfleet.llm.common import table

LEAST = 35


def split_group(group: np.ndarray, label: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Numbers of the groups that have one old group and one label, and their sizes."""
    order = np.lexsort((label, group))
    g, e = group[order], label[order]
    fresh = np.concatenate([[True], (g[1:] != g[:-1]) | (e[1:] != e[:-1])])
    number = np.cumsum(fresh) - 1
    out = np.empty(len(group), np.int64)
    out[order] = number
    return out, np.bincount(number)


def deep_nodes(elements: np.ndarray, starts: np.ndarray, least: int) -> np.ndarray:
    """Which suffixes (by their first `least` elements) lie below an inner node of that depth.

    The tree is built from the root for all suffixes at once; an edge is the hash of the stretch that it spells, and
    edges get longer with depth: a prefix that one suffix alone has is not followed any further.
    """
    hashes, twice = Hashes(elements), np.zeros(len(starts), bool)
    alive, group, depth, step = np.arange(len(starts)), np.zeros(len(starts), np.int64), 0, 1
    while len(alive):
        upto = min(least, depth + step)
        group, sizes = split_group(group, hashes.of(starts[alive] + depth, starts[alive] + upto))
        shared = sizes[group] > 1
        alive, group, depth, step = alive[shared], group[shared], upto, 2 * step
        if depth == least:
            break
    twice[alive] = True
    return twice


def search_contexts(contexts: list[tuple[bytes, int]], least: int = LEAST) -> list[np.ndarray]:
    """For each context (words joined by blanks), which of its windows equal another window of any of them."""
    words = [c.split() for c, _ in contexts]
    elements = word_elements([w for ws in words for w in ws])
    sizes, windows = np.array([len(ws) for ws in words]), np.array([w for _, w in contexts])
    begin, ends = np.cumsum(sizes) - sizes, np.cumsum(windows)
    starts = np.repeat(begin, windows) + np.arange(ends[-1]) - np.repeat(ends - windows, windows)
    return np.split(deep_nodes(elements, starts, least), ends[:-1])


def _sequence(text: bytes) -> np.ndarray:
    return word_elements(text.split())


def _cut(text: bytes):
    words = text.split()
    return lambda first, count: b" ".join(words[first : first + count])


def repeats(docs: DataFrame, least: int = LEAST, gram: int = 12, **options) -> DataFrame:
    """(doc_id, mark, text, stretches) for every document; stretches: where repeated windows start."""
    base = keyed(docs)
    return with_stretches(base, repeated_windows(base, _sequence, _cut, lambda c: search_contexts(c, least), least, gram, **options))


REMOVED = "doc_id bigint, n_words bigint, n_removed bigint, kept_sha256 string"


def deduplicated(docs: DataFrame, least: int = LEAST, gram: int = 12, **options) -> DataFrame:
    def run(batches):
        for batch in batches:
            rows = []
            for doc_id, text, stretches in zip(*(batch.column(c) for c in ("doc_id", "text", "stretches"))):
                words = text.as_py().encode().split()
                if stretches.is_valid:
                    gone = covered(len(words), stretches.as_py(), least)
                    kept = [w for w, g in zip(words, gone.tolist()) if not g]
                else:
                    kept = words
                rows.append((doc_id.as_py(), len(words), len(words) - len(kept), hashlib.sha256(b" ".join(kept)).hexdigest()))
            kinds = [pa.int64()] * 3 + [pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows) if rows else [[]] * 4, kinds)], names=[x.split()[0] for x in REMOVED.split(", ")])

    return repeats(docs, least, gram, **options).mapInArrow(run, REMOVED).withColumn("doc_id", F.expr(f"nullif(doc_id, {-(2**63) + 1}L - 1L)"))


def op4_suffix_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    return deduplicated(table(spark, sf_dir, "documents"))


ORACLE = r"""
with d as (select doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') as ws from documents),
w as (select doc_id, unnest(ws) as word, generate_subscripts(ws, 1) as i, case when generate_subscripts(ws, 1) <= len(ws) - 34 then array_to_string(ws[generate_subscripts(ws, 1):generate_subscripts(ws, 1) + 34], ' ') end as win from d),
f as (select doc_id, i, word, case when win is not null and count(*) over (partition by win) > 1 then 1 else 0 end as twice from w),
c as (select doc_id, i, word, max(twice) over (partition by doc_id order by i rows between 34 preceding and current row) as gone from f),
k as (select doc_id, sum(gone)::bigint as n_removed, string_agg(word, ' ' order by i) filter (where gone = 0) as kept from c group by doc_id)
select d.doc_id, len(ws)::bigint as n_words, coalesce(n_removed, 0) as n_removed, sha256(coalesce(kept, '')) as kept_sha256 from d left join k using (doc_id)
"""

QUERIES = {"op4_suffix_trees": op4_suffix_trees}
ORACLES = {"op4_suffix_trees": ORACLE}

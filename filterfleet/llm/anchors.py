"""Where repeats of a least length can lie: content-chosen anchors, and the distinct contexts around them.

A window is `least` consecutive elements (bytes, or hashes of words). Of the grams inside it, the one with the
smallest hash is its anchor (the leftmost, of equal ones), so equal windows have equal anchors at equal offsets. All
windows of one anchor lie in one stretch, its context. A window can only occur twice if its anchor's gram does. So
anchors whose gram occurs once are dropped, and of equal contexts one stands for all; what is left is a small part of
a corpus without losing a single repeated window. Searching inside the contexts is the callers' part.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from filterfleet.llm.common import WordHashes, materialize, mix64, reduce_tasks, slices

BASE = np.uint64(0xD6E8FEB86659FD93)
INVERSE = np.uint64(pow(int(BASE), -1, 1 << 64))
PLACE_BITS = np.uint64(24)
MOST_ELEMENTS = 1 << 23
_powers = {"up": np.ones(1, np.uint64), "down": np.ones(1, np.uint64)}
_BYTES = mix64(np.arange(1, 257, dtype=np.uint64))
_words = WordHashes()


def byte_elements(text: bytes) -> np.ndarray:
    return _BYTES[np.frombuffer(text, np.uint8)]


def word_elements(words: list[bytes]) -> np.ndarray:
    return mix64(_words.array(words))


def _power(name: str, n: int) -> np.ndarray:
    if len(_powers[name]) < n:
        table = np.full(1 << max(16, n.bit_length()), BASE if name == "up" else INVERSE, np.uint64)
        table[0] = 1
        _powers[name] = np.multiply.accumulate(table)
    return _powers[name][:n]


class Hashes:
    """Hashes of any stretches of a sequence, from running sums of powers."""

    def __init__(self, elements: np.ndarray):
        self.sums = np.zeros(len(elements) + 1, np.uint64)
        np.cumsum(elements * _power("up", len(elements)), out=self.sums[1:])

    def grams(self, width: int) -> np.ndarray:
        n = len(self.sums) - width
        return mix64((self.sums[width:] - self.sums[:n]) * _power("down", n))

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix64((self.sums[end] - self.sums[start]) * _power("down", len(self.sums))[start] + (end - start).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def sliding_least(values: np.ndarray, width: int) -> np.ndarray:
    """Least value of each `width` neighbours."""
    if width == 1:
        return values
    n = len(values)
    padded = np.full(-(-n // width) * width, np.iinfo(np.uint64).max, np.uint64)
    padded[:n] = values
    blocks = padded.reshape(-1, width)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    behind = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(behind[: n - width + 1], ahead[width - 1 : n])


def anchors(elements: np.ndarray, least: int, gram: int) -> tuple[np.ndarray, ...]:
    """(gram hash, context hash, first window, anchor's offset from it, windows) of every anchor of a sequence."""
    if len(elements) < least:
        return tuple(np.empty(0, k) for k in (np.uint64, np.uint64, np.int64, np.int64, np.int64))
    if len(elements) > MOST_ELEMENTS:  # in pieces that share least - 1 elements, so each window lies in one
        parts = []
        for at in range(0, len(elements) - least + 1, MOST_ELEMENTS - least + 1):
            found = anchors(elements[at : at + MOST_ELEMENTS], least, gram)
            parts.append((*found[:2], found[2] + at, *found[3:]))
        return tuple(map(np.concatenate, zip(*parts)))
    hashes = Hashes(elements)
    grams = hashes.grams(gram)
    ordered = grams >> PLACE_BITS << PLACE_BITS | np.arange(len(grams), dtype=np.uint64)
    chosen = (sliding_least(ordered, least - gram + 1) & np.uint64((1 << int(PLACE_BITS)) - 1)).astype(np.int64)
    first = np.flatnonzero(np.concatenate([[True], chosen[1:] != chosen[:-1]]))
    windows = np.diff(first, append=len(chosen))
    place = chosen[first]
    context = hashes.of(first, first + windows + least - 1) ^ mix64((place - first).astype(np.uint64))
    return grams[place], context, first, place - first, windows


ANCHOR = "key bigint, context bigint, doc_id bigint, mark int, first int, lead int, windows int"


def _signed(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64))


def all_anchors(docs: DataFrame, sequence, least: int, gram: int) -> DataFrame:
    """sequence: text bytes -> elements."""

    def run(batches):
        for batch in batches:
            for part in slices(batch, "text", 1 << 20):
                found = [anchors(sequence((x or "").encode()), least, gram) for x in part.column("text").to_pylist()]
                ids, marks = (np.repeat(part.column(c).to_numpy(), [len(f[0]) for f in found]) for c in ("doc_id", "mark"))
                key, context, first, lead, windows = map(np.concatenate, zip(*found))
                yield pa.RecordBatch.from_arrays([_signed(key), _signed(context), pa.array(ids), pa.array(marks), *(pa.array(x.astype(np.int32)) for x in (first, lead, windows))], names=["key", "context", "doc_id", "mark", "first", "lead", "windows"])

    return docs.select("doc_id", "mark", "text").mapInArrow(run, ANCHOR)


def shared_anchors(found: DataFrame) -> DataFrame:
    """Anchors whose gram occurs again; stands: the first of its equal contexts; again: there are more of them.

    Rows come sorted; a task holds back one row, so very frequent grams pass through without being gathered.
    """

    names = [x.split()[0] for x in ANCHOR.split(", ")]

    def run(batches):
        held, same_key, same_context = None, False, False  # the last row; whether the row before it had its key, context

        def out(columns, end):
            nonlocal same_key, same_context
            key, context = columns[0], columns[1]
            k, c = key[1:] == key[:-1], (key[1:] == key[:-1]) & (context[1:] == context[:-1])
            before_k, before_c = np.concatenate([[same_key], k]), np.concatenate([[same_context], c])
            after_k, after_c = np.concatenate([k, [False]]), np.concatenate([c, [False]])
            n = len(key) if end else len(key) - 1
            same_key, same_context = bool(before_k[-1]), bool(before_c[-1])
            keep = np.flatnonzero((before_k | after_k)[:n])
            return pa.RecordBatch.from_arrays([*(pa.array(x[keep]) for x in columns), pa.array(~before_c[keep]), pa.array((before_c | after_c)[keep])], names=[*names, "stands", "again"])

        for batch in batches:
            columns = [batch.column(c).to_numpy() for c in names]
            if not len(columns[0]):
                continue
            if held is not None:
                columns = [np.concatenate([h, x]) for h, x in zip(held, columns)]
            held = [x[-1:] for x in columns]
            yield out(columns, False)
        if held is not None:
            yield out(held, True)

    return found.repartition(reduce_tasks(found.sparkSession), "key").sortWithinPartitions("key", "context").mapInArrow(run, f"{ANCHOR}, stands boolean, again boolean")


def keyed(docs: DataFrame) -> DataFrame:
    """doc_id, mark, text with neither null; mark tells rows of one id with different texts apart."""
    text = F.coalesce("text", F.lit(""))
    return docs.select(F.coalesce(F.col("doc_id").cast("bigint"), F.lit(-(2**63))).alias("doc_id"), F.xxhash64(text).bitwiseAND(0x7FFFFFFF).cast("int").alias("mark"), text.alias("text"))


WINDOWS = "doc_id bigint, mark int, first int, windows int"
CONTEXT = "key bigint, doc_id bigint, mark int, first int, windows int, again boolean, span binary"


def repeated_windows(base: DataFrame, sequence, cut, search, least: int, gram: int, block: int = 1 << 19, crowd: int = 20_000) -> DataFrame:
    """(doc_id, mark, first, windows): all stretches of window starts that occur again, of rows from `keyed`.

    sequence: text bytes -> elements; cut: (text bytes) -> function (first, count) -> bytes of that stretch of elements;
    search: list of (bytes of a context, its windows) -> list of boolean arrays, which windows occur twice among them.
    Equal contexts repeat as they are; only contexts of a kind are searched, beside all others with their gram. A task
    holds the contexts of one gram after the other, in blocks of about `block` bytes. Where more than `crowd` different
    contexts share a gram (a very common line amid ever new text), their windows choose anchors again among longer grams,
    which equal windows still have in common, so that such a crowd is dealt out too. Where that leaves a crowd, the gram
    becomes the whole window: equal windows then follow one another, and a task that looks for them keeps one row. So no
    task's memory depends on how often a gram occurs.
    """
    finer = gram + 2 * (least - gram) // 3
    found = materialize(shared_anchors(all_anchors(base, sequence, least, gram)), "repeat-anchors")
    groups = found.where("stands").groupBy("key").agg(F.max(~F.col("again")).alias("open"), F.count("*").alias("n")).where("open").select("key", (F.col("n") > crowd).alias("crowded"))
    wanted = (
        found.where("stands")
        .join(groups, "key")
        .groupBy("doc_id", "mark")
        .agg(F.collect_list(F.struct("key", "first", "windows", "again", "crowded")).alias("contexts"))
    )
    kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.bool_(), pa.binary()]
    names = [x.split()[0] for x in CONTEXT.split(", ")]

    def extract(batches):
        for batch in batches:
            rows, held = [], 0
            for doc_id, mark, text, contexts in zip(*(batch.column(c) for c in ("doc_id", "mark", "text", "contexts"))):
                piece, doc_id, mark = cut(text.as_py().encode()), doc_id.as_py(), mark.as_py()
                for c in contexts.as_py():
                    span = piece(c["first"], c["windows"] + least - 1)
                    parts = [(c["key"], 0, c["windows"])]
                    if c["crowded"]:
                        key, _, first, _, windows = anchors(sequence(span), least, finer)
                        parts = zip(key.view(np.int64).tolist(), first.tolist(), windows.tolist())
                    for key, first, windows in parts:
                        rows.append((key, doc_id, mark, c["first"] + first, windows, c["again"], cut(span)(first, windows + least - 1) if c["crowded"] else span))
                        held += len(rows[-1][-1])
                if held > 2 << 20:
                    yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows), kinds)], names=names)
                    rows, held = [], 0
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows), kinds)], names=names)

    def settle(rows):
        for (_, doc_id, mark, first, _, again, _), twice in zip(rows, search([(r[6], r[4]) for r in rows])):
            if not again and twice.any():
                edge = np.flatnonzero(np.diff(np.concatenate([[0], twice.view(np.int8), [0]])))
                for a, b in zip(edge[::2].tolist(), edge[1::2].tolist()):
                    yield doc_id, mark, first + a, b - a

    def compare(batches):
        rows, held, out = [], 0, []
        flush = lambda: pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*out), (pa.int64(), pa.int32(), pa.int32(), pa.int32()))], names=["doc_id", "mark", "first", "windows"])
        for batch in batches:
            for row in zip(*(batch.column(c).to_pylist() for c in names)):
                if held >= block and row[0] != rows[-1][0]:
                    out += settle(rows)
                    rows, held = [], 0
                    if out:
                        yield flush()
                        out = []
                rows.append(row)
                held += len(row[6])
        if rows:
            out += settle(rows)
            if out:
                yield flush()

    def windows_of(batches):
        for batch in batches:
            parts = []
            for key, doc_id, mark, first, windows, again, span in zip(*(batch.column(c).to_pylist() for c in names)):
                whole = Hashes(sequence(span)).grams(least)[:windows].view(np.int64)
                parts.append((whole, np.full(windows, key), np.full(windows, doc_id), np.full(windows, mark, np.int32), first + np.arange(windows, dtype=np.int32), np.full(windows, again)))
                if sum(len(x[0]) for x in parts) > 200_000:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*parts)], names=WINDOW_NAMES)
                    parts = []
            if parts:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*parts)], names=WINDOW_NAMES)

    tasks = reduce_tasks(base.sparkSession)
    spans = materialize(base.join(wanted, ["doc_id", "mark"]).mapInArrow(extract, CONTEXT), "repeat-spans")
    # Only keys that longer grams have made can still be crowds beyond what was counted above.
    crowds = spans.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > crowd).select("key")
    dealt = spans.join(crowds, "key", "left_anti").repartition(tasks, "key").sortWithinPartitions("key", "doc_id", "first")
    single = spans.join(crowds, "key", "left_semi").mapInArrow(windows_of, WINDOW).repartition(tasks, "whole", "key").sortWithinPartitions("whole", "key")
    out = found.where("again").select("doc_id", "mark", "first", "windows").unionByName(dealt.mapInArrow(compare, WINDOWS))
    return out.unionByName(single.mapInArrow(equal_windows, WINDOWS))


WINDOW = "whole bigint, key bigint, doc_id bigint, mark int, first int, again boolean"
WINDOW_NAMES = [x.split()[0] for x in WINDOW.split(", ")]


def equal_windows(batches):
    """Windows that have an equal one, from rows sorted by the window's and the gram's hash; one row is held back."""
    held, same = None, False

    def out(columns, end):
        nonlocal same
        whole, key, doc_id, mark, first, again = columns
        equal = (whole[1:] == whole[:-1]) & (key[1:] == key[:-1])
        before, after = np.concatenate([[same], equal]), np.concatenate([equal, [False]])
        n = len(whole) if end else len(whole) - 1
        same = bool(before[-1])
        keep = np.flatnonzero(((before | after) & ~again)[:n])
        return pa.RecordBatch.from_arrays([pa.array(doc_id[keep]), pa.array(mark[keep]), pa.array(first[keep]), pa.array(np.ones(len(keep), np.int32))], names=["doc_id", "mark", "first", "windows"])

    for batch in batches:
        columns = [batch.column(c).to_numpy(zero_copy_only=False) for c in WINDOW_NAMES]
        if not len(columns[0]):
            continue
        if held is not None:
            columns = [np.concatenate([h, x]) for h, x in zip(held, columns)]
        held = [x[-1:] for x in columns]
        yield out(columns, False)
    if held is not None:
        yield out(held, True)


def with_stretches(base: DataFrame, windows: DataFrame) -> DataFrame:
    """base with `stretches`: for each row a list of (first, windows), null where nothing of it repeats."""
    lists = windows.groupBy("doc_id", "mark").agg(F.collect_list(F.struct("first", "windows")).alias("stretches"))
    return base.join(lists, ["doc_id", "mark"], "left")


def covered(n: int, stretches: list | None, least: int) -> np.ndarray:
    """Which of n elements lie in a repeated window."""
    steps = np.zeros(n + 1, np.int32)
    if stretches:
        first = np.array([s["first"] for s in stretches])
        np.add.at(steps, first, 1)
        np.add.at(steps, first + [s["windows"] + least - 1 for s in stretches], -1)
    return np.cumsum(steps[:n]) > 0

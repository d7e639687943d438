"""Exact Jaccard self-join on word shingles by a grouped prefix join, and its connected components.

Each document is the set of hashes of its word shingles. All sets are put in one order, rare shingles first: a fixed
table of counts over all documents (a row of a count-min sketch) gives each shingle a class, and any two documents
agree on it, so the order is exact however full the table is. Two sets that reach the threshold share one of the
leading elements (the prefix) of each.

1. Equal sets become one representative; representatives with the same prefix and size become one group.
2. Groups meet on prefix elements. First every group meets only the smallest group of each element (a pivot), under
   the length and position filters, and pairs are verified on whole sets. Copies of one text are linked by that, at a
   cost that is linear in their number.
3. What is left are pairs of groups on elements whose groups are not all in one component yet. They meet by element
   and band of sizes, are filtered, expanded to members in different components, and verified. No pair of different
   components that could reach the threshold is left out.

Empty sets (null text or no word) link with nothing. Rows without an id link with nothing either and come out with a
null set and component, whatever their text. Rows that repeat an id count as one set of it each, in one component. Other columns are
ignored; no rows give no rows. Hashes have 64 bits (56 in the order); sets are compared by hash.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from filterfleet.llm.common import WordHashes, materialize, mix64, reduce_tasks, released, rolling, slices, table
from filterfleet.llm.components import components

CELLS = 1 << 20
BLOCKS = 64
_words = WordHashes()


def shingle_hashes(text: str | None, width: int = 5) -> np.ndarray:
    """Sorted distinct hashes of the word shingles; of the whole sequence if it is shorter."""
    if not text:
        return np.empty(0, np.uint64)
    words = _words.array(text.encode().lower().split())
    if not len(words):
        return words
    return np.unique(rolling(words, min(width, len(words)), seed=min(width, len(words))))


def prefix_length(n: int, percent: int) -> int:
    return n - -(-percent * n // 100) + 1


def needed(na, nb, percent: int):
    """Least intersection of sets of these sizes at the threshold."""
    return -(-percent * (na + nb) // (100 + percent))


def count_classes(docs: DataFrame, width: int) -> np.ndarray:
    """A class for each cell of the count table: 4 times the log2 of how many documents hold a shingle of it. CELLS bytes."""
    part = CELLS // BLOCKS

    def count(batches):
        cells = np.zeros(CELLS, np.uint32)
        for batch in batches:
            for piece in slices(batch, "text"):
                found = [shingle_hashes(x, width) for x in piece.column("text").to_pylist()]
                cells += np.bincount((np.concatenate(found) & np.uint64(CELLS - 1)).astype(np.int64), minlength=CELLS).astype(np.uint32)
        yield pa.RecordBatch.from_arrays([pa.array(range(BLOCKS), pa.int32()), pa.array([cells[k * part : (k + 1) * part].tobytes() for k in range(BLOCKS)], pa.binary())], names=["block", "cells"])

    def add(batches):
        at, total = None, None
        for batch in batches:
            for block, cells in zip(batch.column("block").to_pylist(), batch.column("cells")):
                if block != at:
                    if at is not None:
                        yield done(at, total)
                    at, total = block, np.zeros(part, np.uint64)
                total += np.frombuffer(cells.as_py(), np.uint32)
        if at is not None:
            yield done(at, total)

    def done(block, total):
        return pa.RecordBatch.from_arrays([pa.array([block], pa.int32()), pa.array([np.minimum(4 * np.log2(np.maximum(total, 1)), 255).astype(np.uint8).tobytes()], pa.binary())], names=["block", "classes"])

    partial = docs.select("text").mapInArrow(released(count), "block int, cells binary")
    merged = partial.repartition(min(BLOCKS, reduce_tasks(docs.sparkSession)), "block").sortWithinPartitions("block").mapInArrow(released(add), "block int, classes binary")
    found = {r["block"]: np.frombuffer(r["classes"], np.uint8) for r in merged.collect()}
    return np.concatenate([found.get(k, np.zeros(part, np.uint8)) for k in range(BLOCKS)])


def parity_sketch(hashes: np.ndarray) -> bytes:
    """Bit j is the parity of the elements that fall on j; 2 to 4 bits an element, a power of two of them."""
    bits = max(64, 1 << int(2 * len(hashes) - 1).bit_length())
    return np.packbits(np.bincount((hashes & np.uint64(bits - 1)).astype(np.int64), minlength=bits).astype(np.uint8) & 1, bitorder="little").tobytes()


def least_difference(a: bytes, b: bytes) -> int:
    """A bound that |A xor B| is never below: each element in one set only flips one bit. The longer sketch is folded."""
    x, y = np.frombuffer(a, np.uint64), np.frombuffer(b, np.uint64)
    if len(x) < len(y):
        x, y = y, x
    x = np.bitwise_xor.reduce(x.reshape(-1, len(y)), axis=0)
    return int(np.bitwise_count(x ^ y).sum())


def possible(pairs: DataFrame, sketches: DataFrame, percent: int) -> DataFrame:
    """The (a, b) of pairs that sizes and sketches don't rule out; sketches: (id, n, sketch)."""
    side = lambda s: sketches.select(F.col("id").alias(s), F.col("n").alias(f"{s}_n"), F.col("sketch").alias(f"{s}_sketch"))

    def run(batches):
        for batch in batches:
            keep = [
                na + nb - least_difference(x, y) >= 2 * needed(na, nb, percent)
                for na, nb, x, y in zip(*(batch.column(c).to_pylist() for c in ("a_n", "b_n", "a_sketch", "b_sketch")))
            ]
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b")], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))

    sized = pairs.join(side("a"), "a").join(side("b"), "b").where(f"100 * least(a_n, b_n) >= {percent} * greatest(a_n, b_n)")
    return sized.mapInArrow(released(run), "a bigint, b bigint")


SETS = "doc_id bigint, n bigint, key_a bigint, key_b bigint, prefix_key bigint, prefix binary, sketch binary"


def ordered(hashes: np.ndarray, classes: np.ndarray) -> np.ndarray:
    """The elements as numbers in the common order: class first, then hash."""
    return (classes[(hashes & np.uint64(CELLS - 1)).astype(np.int64)].astype(np.uint64) << np.uint64(56)) | (hashes >> np.uint64(8))


def prefixes(docs: DataFrame, classes, width: int, percent: int) -> DataFrame:
    """A row for each document: set size, 128-bit key of the set, key and elements of its prefix. classes: a broadcast."""

    def run(batches):
        for batch in batches:
            for piece in slices(batch, "text"):
                rows = []
                for text in piece.column("text").to_pylist():
                    hashes = shingle_hashes(text, width)
                    n = len(hashes)
                    if not n:
                        rows.append((0, 0, 0, 0, b"", b""))
                        continue
                    head = ordered(hashes, classes.value)
                    head.sort()
                    head = head[: prefix_length(n, percent)]
                    keys = [np.add.reduce(hashes), np.add.reduce(mix64(hashes ^ np.uint64(0x5851F42D4C957F2D))), np.add.reduce(mix64(head)) + np.uint64(n)]
                    rows.append((n, *(int(k.view(np.int64)) for k in keys), head.tobytes(), parity_sketch(hashes)))
                columns = list(zip(*rows)) or [[]] * 6
                yield pa.RecordBatch.from_arrays([piece.column("doc_id"), *(pa.array(c, pa.int64()) for c in columns[:4]), *(pa.array(c, pa.binary()) for c in columns[4:])], names=[x.split()[0] for x in SETS.split(", ")])

    return docs.select(F.col("doc_id").cast("bigint"), "text").mapInArrow(released(run), SETS)


def ends(pairs: DataFrame) -> DataFrame:
    return materialize(pairs.select(F.col("a").alias("id")).unionByName(pairs.select(F.col("b").alias("id"))).distinct(), "shingle-ids")


ELEMENT = "element bigint, gid bigint, n bigint, pos int"


def elements(groups: DataFrame) -> DataFrame:
    """A row for each element of a group's prefix."""

    def run(batches):
        for batch in batches:
            for start in range(0, batch.num_rows, 2000):
                piece = batch.slice(start, 2000)
                heads = [np.frombuffer(x.as_py(), np.int64) for x in piece.column("prefix")]
                sizes = np.array([len(x) for x in heads])
                total = np.concatenate(heads) if heads else np.empty(0, np.int64)
                repeat = lambda c: np.repeat(piece.column(c).to_numpy(), sizes)  # noqa: E731, B023
                pos = np.arange(len(total)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
                yield pa.RecordBatch.from_arrays([pa.array(total), pa.array(repeat("gid")), pa.array(repeat("n")), pa.array(pos.astype(np.int32))], names=["element", "gid", "n", "pos"])

    return groups.select("gid", "n", "prefix").mapInArrow(released(run), ELEMENT)


def shared_elements(rows: DataFrame) -> DataFrame:
    """rows whose element occurs again, with the smallest group of the element (gid, n, pos) as its pivot.

    Rows arrive sorted by element and group; a task keeps the pivot of the element it is at, never the element's rows.
    """
    tasks = reduce_tasks(rows.sparkSession)

    def run(batches):
        last = None  # last row of the batch before: element, gid, n, pos
        pivot = None  # of last's element, once its second row came
        for batch in batches:
            element, gid, n, pos = (batch.column(c).to_numpy() for c in ("element", "gid", "n", "pos"))
            if not len(element):
                continue
            start = np.concatenate([[last is None or element[0] != last[0]], element[1:] != element[:-1]])
            head = np.maximum.accumulate(np.where(start, np.arange(len(element)), -1))  # -1: the run began before this batch
            carried = head < 0
            more = ~start
            if last is None or pivot is None and not carried.any():
                first = None
            else:
                first = pivot or last
            safe = np.maximum(head, 0)
            p_gid, p_n, p_pos = gid[safe].copy(), n[safe].copy(), pos[safe].copy()
            if carried.any():
                p_gid[carried], p_n[carried], p_pos[carried] = first[1], first[2], first[3]
            heads_too = np.zeros(len(element), bool)
            heads_too[head[more & ~carried]] = True  # a head whose second row is here
            keep = more | heads_too
            out = [a[keep] for a in (element, gid, n, pos, p_gid, p_n, p_pos)]
            if carried.any() and pivot is None:  # the head stood last in the batch before
                out = [np.concatenate([[x], a]).astype(a.dtype) for x, a in zip((*last, *last[1:]), out)]
            yield pa.RecordBatch.from_arrays([pa.array(a) for a in out], names=["element", "gid", "n", "pos", "p_gid", "p_n", "p_pos"])
            end = head[-1]
            last = (element[-1], gid[-1], n[-1], pos[-1])
            if end < 0:
                pivot = first
            else:
                pivot = (element[end], gid[end], n[end], pos[end]) if end < len(element) - 1 else None

    return rows.repartition(tasks, "element").sortWithinPartitions("element", "gid").mapInArrow(released(run), f"{ELEMENT}, p_gid bigint, p_n bigint, p_pos int")


def may_reach(percent: int, a: str = "", b: str = "p_") -> str:
    """Length filter, and position filter for a pair's first common element: nothing before it is common, so what
    follows it has to suffice. A pair that reaches the threshold passes at its first common element, if at no other."""
    need = f"({percent} * ({a}n + {b}n) + {99 + percent}) div {100 + percent}"
    return f"100 * least({a}n, {b}n) >= {percent} * greatest({a}n, {b}n) and 1 + least({a}n - 1 - {a}pos, {b}n - 1 - {b}pos) >= {need}"


def blocked_pairs(rows: DataFrame, percent: int, ratio: float = 1.05) -> DataFrame:
    """Rows of one element side by side as a_ and b_, b's set not the smaller one: met by element and size.

    Sizes fall into bands, each `ratio` times the one before. A row looks for partners in its own band and those above
    that the threshold lets it reach, and only in bands whose smallest sets the rest of its own could still suffice for.
    """
    band = lambda n: f"cast(floor(ln({n}) / ln({ratio}D)) as int)"
    names = ("gid", "n", "pos", "low", "high")
    need = f"({percent} * (n + greatest(n, cast(floor(pow({ratio}D, x)) as bigint))) + {99 + percent}) div {100 + percent}"
    reach = F.expr(f"filter(sequence({band('n')}, {band(f'100 * n div {percent} + 1')}), x -> n - pos >= {need})")
    left = rows.withColumn("band", F.explode(reach)).select("element", "band", *(F.col(c).alias(f"a_{c}") for c in names))
    right = rows.select("element", F.expr(band("n")).alias("band"), *(F.col(c).alias(f"b_{c}") for c in names))
    return left.join(right, ["element", "band"])


def verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The (a, b) of pairs whose whole sets reach the threshold. A set travels with all partners it is the a of."""
    one = pairs.join(sets.select(F.col("id").alias("a"), F.col("elements").alias("a_set")), "a")
    two = one.join(sets.select(F.col("id").alias("b"), F.col("elements").alias("b_set")), "b")

    def run(batches):
        for batch in batches:
            keep = []
            for x, y in zip(batch.column("a_set"), batch.column("b_set")):
                x, y = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                common = 0
                if 100 * min(len(x), len(y)) >= percent * max(len(x), len(y)):
                    both = np.concatenate([x, y])
                    both.sort()
                    common = int((both[1:] == both[:-1]).sum())
                keep.append(100 * common >= percent * (len(x) + len(y) - common))
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b")], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return two.select("a", "b", "a_set", "b_set").mapInArrow(released(run), "a bigint, b bigint")


def whole_sets(docs: DataFrame, ids: DataFrame, width: int) -> DataFrame:
    """(id, elements) of the documents in ids."""

    def run(batches):
        for batch in batches:
            for piece in slices(batch, "text"):
                yield pa.RecordBatch.from_arrays([piece.column("doc_id"), pa.array([shingle_hashes(x, width).tobytes() for x in piece.column("text").to_pylist()], pa.binary())], names=["id", "elements"])

    texts = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").join(ids.withColumnRenamed("id", "doc_id"), "doc_id", "left_semi")
    return texts.mapInArrow(released(run), "id bigint, elements binary")


def similarity_classes(docs: DataFrame, width: int = 5, percent: int = 75) -> DataFrame:
    """doc_id, n_shingles, set_id (smallest doc_id with an equal set), component_id for every document."""
    spark = docs.sparkSession
    classes = spark.sparkContext.broadcast(count_classes(docs, width))
    rows = materialize(prefixes(docs, classes, width, percent), "shingle-prefixes")
    keys = ["key_a", "key_b", "n"]
    # The set key settles the prefix key, and prefixes themselves move once: those of the groups' own documents.
    reps = rows.where("n > 0 and doc_id is not null").groupBy(*keys).agg(F.min("doc_id").alias("rep"), F.first("prefix_key").alias("prefix_key"))
    members = materialize(reps, "shingle-sets")
    sketches = rows.select(F.col("doc_id").alias("id"), "n", "sketch", "key_a", "key_b")
    gids = members.groupBy("prefix_key", "n").agg(F.min("rep").alias("gid"))
    in_group = materialize(members.join(gids, ["prefix_key", "n"]).select("rep", "gid", "n"), "shingle-groups")
    groups = rows.select(F.col("doc_id").alias("gid"), "n", "prefix_key", "prefix").join(gids, ["gid", "n", "prefix_key"], "left_semi").select("gid", "n", "prefix")
    shared = materialize(shared_elements(elements(groups)), "shingle-shared")

    near = shared.where(f"gid <> p_gid and {may_reach(percent)}").select(F.col("p_gid").alias("a"), F.col("gid").alias("b"))
    inside = in_group.where("rep <> gid").select(F.col("gid").alias("a"), F.col("rep").alias("b"))
    sketched = materialize(sketches.join(members.select(F.col("rep").alias("id"), "n", "key_a", "key_b"), ["id", "n", "key_a", "key_b"], "left_semi").select("id", "n", "sketch"), "shingle-sketches")
    first_pairs = materialize(possible(near.unionByName(inside).distinct(), sketched, percent), "shingle-pairs")

    def checked(pairs):
        sets = materialize(whole_sets(docs, ends(pairs), width), "shingle-whole")
        return materialize(verified(pairs, sets, percent), "shingle-links")

    links = checked(first_pairs)

    # Pairs that pivots did not settle: on elements, and in groups, that still hold more than one component.
    label = components(links)
    labelled = in_group.join(label.withColumnRenamed("node", "rep"), "rep", "left").selectExpr("rep", "gid", "n", "coalesce(label, rep) as label")
    labelled = materialize(labelled, "shingle-labelled")
    spread = labelled.groupBy("gid").agg(F.min("label").alias("low"), F.max("label").alias("high"))
    placed = shared.select("element", "gid", "n", "pos").join(spread, "gid")
    mixed = placed.groupBy("element").agg(F.min("low").alias("least"), F.max("high").alias("most")).where("least <> most").select("element")
    open_rows = materialize(placed.join(mixed, "element"), "shingle-open")
    settled = "(a_low = a_high and b_low = b_high and a_low = b_low)"
    apart = "(a_n < b_n or a_n = b_n and a_gid < b_gid)"
    met = blocked_pairs(open_rows, percent).where(f"{apart} and not {settled} and {may_reach(percent, 'a_', 'b_')}").select("a_gid", "b_gid").distinct()
    crowds = spread.where("low <> high").selectExpr("gid as a_gid", "gid as b_gid")
    side = lambda s: labelled.select(F.col("gid").alias(f"{s}_gid"), F.col("rep").alias(s), F.col("label").alias(f"{s}_label"))
    later = met.unionByName(crowds).join(side("a"), "a_gid").join(side("b"), "b_gid").where("a_label <> b_label").selectExpr("least(a, b) as a", "greatest(a, b) as b").distinct()
    known = first_pairs.selectExpr("least(a, b) as a", "greatest(a, b) as b")
    more = checked(materialize(possible(later.join(known, ["a", "b"], "left_anti"), sketched, percent), "shingle-pairs"))

    final = components(links.unionByName(more)).select(F.col("node").alias("rep"), "label")
    of_set = members.drop("prefix_key").join(final, "rep", "left").selectExpr("key_a", "key_b", "n", "rep", "coalesce(label, rep) as label")
    of_id = lambda x: f"if(doc_id is null, null, coalesce({x}, doc_id))"
    return rows.join(of_set, keys, "left").selectExpr("doc_id", "n as n_shingles", f"{of_id('rep')} as set_id", f"{of_id('label')} as component_id")


def op3_shingle_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similarity_classes(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id")


ORACLE = r"""
with recursive d as (select doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as w from documents),
s as (select doc_id, list_distinct(case when len(w) = 0 then []::varchar[] when len(w) < 5 then [array_to_string(w, ' ')] else list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) end) as g from d),
n as (select doc_id, coalesce(len(g), 0) as n from s),
k as (select dense_rank() over (order by g1) as h, doc_id from (select doc_id, unnest(g) as g1 from s)),
u as (select h from k group by h having count(*) > 1),
r as (select k.* from k join u using (h)),
p as (select a.doc_id as a, b.doc_id as b, count(*) as common from r a join r b on a.h = b.h and a.doc_id <> b.doc_id group by 1, 2),
l as (select a, b from p join n x on x.doc_id = a join n y on y.doc_id = b where 100 * common >= 75 * (x.n + y.n - common)),
c as (select doc_id as a, doc_id as b from documents union select c.a, l.b from c join l on c.b = l.a)
select n.doc_id, n.n as n_shingles, m.component_id from n join (select a as doc_id, min(b) as component_id from c group by a) m on m.doc_id = n.doc_id
"""

QUERIES = {"op3_shingle_join": op3_shingle_join}
ORACLES = {"op3_shingle_join": ORACLE}

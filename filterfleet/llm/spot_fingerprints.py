"""Document fingerprints from spot signatures: chains of content words that follow common-word anchors.

At every common word of a text, the next `CHAIN` words that are no common words make one signature with it; a
fingerprint is the set of a text's signatures, written as base64 of sorted 32-bit hashes. Words are compared without
case (A-Z) and without punctuation at their ends. A text without a whole chain falls back on the set of its words, a
text without words on its own hash; null and empty text have the empty fingerprint, and two empty ones have likeness 1.

`near_duplicates` compares fingerprints as sets: rows are dealt by set length so that only lengths that can reach the
threshold meet, and only over signatures of the shorter set's leading part; the exact Jaccard decides. Null or repeated
ids are kept as rows of their own in fingerprints; other columns are ignored; no rows give no rows.
"""

from __future__ import annotations

import base64
import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from filterfleet.llm.common import id_buckets, mix64, reduce_tasks, slices, table

#: Common words of the four languages.
ANCHORS = (
    "the a an of to and in is it for on that this with as are was be by from "
    "le la les de des du un une et en est que qui pour dans sur par au "
    "der die das und ist in zu den von mit ein eine nicht auf für im dem "
    "el los las y que es un una por con para del al se lo"
).split()
CHAIN = 2
_EDGES = b".,;:!?\"'()[]{}"


class SpotWords(dict):
    """word bytes -> 64-bit hash whose lowest bit says whether it is an anchor."""

    def __init__(self, most: int = 200_000):
        super().__init__()
        self.most, self.anchors = most, {a.encode() for a in ANCHORS}

    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) >= self.most:
            self.clear()
        bare = word.lower().strip(_EDGES) or word
        self[word] = value = xxhash.xxh3_64_intdigest(bare) & ~1 | (bare in self.anchors)
        return value


_words = SpotWords()


def signatures(text: str | None) -> np.ndarray:
    """Sorted distinct 32-bit signatures."""
    if not text:
        return np.empty(0, np.uint32)
    words = text.encode().split()
    hashes = np.fromiter(map(_words.__getitem__, words), np.uint64, len(words))
    anchor = (hashes & np.uint64(1)).astype(bool)
    content = hashes[~anchor]
    follows = np.cumsum(~anchor)[anchor]  # place, among content words, of the first after each anchor
    whole = follows + CHAIN <= len(content)
    follows, found = follows[whole], hashes[anchor][whole]
    for k in range(CHAIN):
        found = mix64(found * np.uint64(0x9E3779B97F4A7C15) + content[follows + k])
    if not len(found):
        import xxhash

        found = hashes if len(hashes) else np.array([xxhash.xxh3_64_intdigest(text.encode())], np.uint64)
    return np.unique((found >> np.uint64(32)).astype(np.uint32))


def written(found: np.ndarray) -> str:
    return base64.b64encode(found.astype(">u4").tobytes()).decode()


def pruned_jaccard(a: np.ndarray, b: np.ndarray, least: float = 0.0) -> float:
    """Jaccard likeness; 0 at once where the lengths alone rule out `least`."""
    if not len(a) and not len(b):
        return 1.0
    if min(len(a), len(b)) < least * max(len(a), len(b)) or not len(a) or not len(b):
        return 0.0
    common = len(np.intersect1d(a, b, assume_unique=True))
    return common / (len(a) + len(b) - common)


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, fingerprint, n_signatures."""

    def run(batches):
        for batch in batches:
            for part in slices(batch, "text"):
                found = [signatures(x) for x in part.column("text").to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(map(written, found), pa.string()), pa.array(map(len, found), pa.int64())], names=["doc_id", "fingerprint", "n_signatures"])

    return docs.select(F.col("doc_id").cast("bigint"), "text").mapInArrow(run, "doc_id bigint, fingerprint string, n_signatures bigint")


def near_duplicates(prints: DataFrame, least: float = 0.75, band: float = 1.15) -> DataFrame:
    """(a, b, likeness) of classes of equal fingerprints at or above `least`; a, b are each class's smallest doc_id.

    Lengths are dealt to bands, each `band` times the one before; a set looks for partners in its own band and in those
    above that its length can reach, by the signatures of its leading part (enough of them that a pair cannot miss).
    """
    classes = prints.where("n_signatures > 0").groupBy("fingerprint", "n_signatures").agg(F.min("doc_id").alias("id"))
    places = classes.withColumns({"band": F.expr(f"cast(floor(ln(n_signatures) / ln({band})) as int)"), "raw": F.unbase64("fingerprint")})
    steps = int(np.ceil(-np.log(least) / np.log(band)))
    keyed = places.select("id", "n_signatures", "band", F.explode(F.expr(f"transform(sequence(0, cast(n_signatures - ceil({least} * n_signatures) as int)), i -> substr(raw, i * 4 + 1, 4))")).alias("spot"))
    probe = keyed.select(F.col("id").alias("a"), F.col("n_signatures").alias("na"), "spot", F.explode(F.sequence(F.col("band"), F.col("band") + steps)).alias("band"))
    pairs = (
        probe.join(keyed.select(F.col("id").alias("b"), F.col("n_signatures").alias("nb"), "spot", "band"), ["band", "spot"])
        .where(f"(na < nb or na = nb and a < b) and na >= {least} * nb")
        .select("a", "b")
        .distinct()
    )
    sides = lambda name: classes.select(F.col("id").alias(name), F.col("fingerprint").alias(f"{name}_print"))

    def likeness(batches):
        for batch in batches:
            sets = [[np.frombuffer(base64.b64decode(x), ">u4") for x in batch.column(c).to_pylist()] for c in ("a_print", "b_print")]
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b"), pa.array([pruned_jaccard(x, y, least) for x, y in zip(*sets)], pa.float64())], names=["a", "b", "likeness"])

    return pairs.join(sides("a"), "a").join(sides("b"), "b").select("a", "b", "a_print", "b_print").mapInArrow(likeness, "a bigint, b bigint, likeness double").where(F.col("likeness") >= least)


COMPARED = "doc_id bigint, n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def compare_with_next(docs: DataFrame) -> DataFrame:
    """Each text against its edited text and against the next text, in descending order of doc_id.

    Rows are dealt to ranges of doc_id; of each range the first row also goes, as an extra, to the end of the range
    before it, so one pass over sorted rows sees every pair of neighbours and a task holds two rows at a time.
    """
    tasks = reduce_tasks(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    dealt = rows.withColumn("bucket", id_buckets(rows, tasks))
    tops = {r["bucket"]: r["top"] for r in dealt.groupBy("bucket").agg(F.max("doc_id").alias("top")).collect()}  # a row for each bucket
    order = sorted(tops, reverse=True)
    extras = [(tops[b], before) for b, before in zip(order, [*order[-1:], *order])]
    extra = docs.sparkSession.createDataFrame(extras, "top bigint, to_bucket int")
    copies = rows.join(F.broadcast(extra), F.col("doc_id").eqNullSafe(F.col("top"))).select("doc_id", "text", F.col("to_bucket").alias("bucket"), F.lit(1).alias("extra"))

    def run(batches):
        held = None  # the row that waits for its next one
        out: list[tuple] = []

        def close(row, after):
            doc_id, text, found = row
            n = len(text)
            edited = text[: n - n // 2] + after[1][: n // 2]
            edited_found = signatures(edited)
            return (doc_id, n, hashlib.sha256(edited.encode()).hexdigest(), written(found), written(edited_found), pruned_jaccard(found, edited_found), pruned_jaccard(found, after[2]))

        def flush():
            columns = list(zip(*out))
            out.clear()
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names=[x.split()[0] for x in COMPARED.split(", ")])

        at = None
        for batch in batches:
            for doc_id, text, bucket, is_extra in zip(*(batch.column(c) for c in ("doc_id", "text", "bucket", "extra"))):
                bucket, text = bucket.as_py(), text.as_py()
                if bucket != at:
                    held, at = None, bucket
                row = (doc_id.as_py(), text, signatures(text))
                if held is not None:
                    out.append(close(held, row))
                held = None if is_extra.as_py() else row
                if len(out) >= 500:
                    yield flush()
        if out:
            yield flush()

    return (
        dealt.withColumn("extra", F.lit(0))
        .unionByName(copies)
        .repartitionById(tasks, F.col("bucket"))
        .sortWithinPartitions("bucket", "extra", F.col("doc_id").desc_nulls_last(), "text")
        .mapInArrow(run, COMPARED)
    )


def op8_spot_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return compare_with_next(table(spark, sf_dir, "documents"))


QUERIES = {"op8_spot_fingerprints": op8_spot_fingerprints}
ORACLES: dict = {}

"""Quality classifier: perplexity under an interpolated modified Kneser-Ney model of bytes, trained on trusted text.

The model is fitted on all labelled documents of good quality that aren't toxic, each with its whole text (`train` takes
bounds for trials; none is set by default). Its symbols are the bytes of UTF-8, so every alphabet is covered, and one
more value (255, which UTF-8 never has) for the start of a text; its grams have four symbols.

Fitting is aggregation: grams of order 4 are counted, an order below counts the distinct left neighbours of its grams,
contexts sum up their grams, and probabilities join a gram with its context and with the probability of its tail.
Nothing but the numbers of grams that occur once to four times (four an order) comes to the driver.

Scoring is a join of counts in shards. Each document's gram counts go, packed by runs of documents, to the shard that
owns the grams' two middle symbols; a shard holds its part of the model's counts (as probabilities and back-off weights)
and sends back each document's partial cost. Costs are whole numbers, so sums don't depend on their order. Nothing but
the model is bounded: the shuffled counts grow with the corpus, and shards are split by a salt into as many tasks as
the shuffle has. A document goes if its perplexity is above its language's fence: a high quantile over the trusted
documents of the language (of all languages where it has few), times a small margin, as the model has seen those
documents and finds others of the same kind a little harder.

Null and empty text has no gram and no perplexity; it is rejected, as it teaches nothing. Null languages form a group
of their own. Rows that repeat both id and text share one score; rows that repeat an id only do not. Other columns
pass through `accepted`; no rows give no rows. Without trusted text there is no model, so all text is kept.
"""

from __future__ import annotations

import struct
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from filterfleet.llm.common import materialize, mix64, reduce_tasks, released, slices, table

START, SYMBOLS, ORDER = 255, 256, 4
SCALE = 1 << 16  # costs are in 1/SCALE nats


def grams(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """Four-symbol grams of all texts, one for each byte, and how many each text has."""
    parts = [np.frombuffer((x or "").encode(), np.uint8) for x in texts]
    sizes = np.array([len(p) for p in parts], np.int64)
    ends = np.cumsum(sizes + 3)
    flat = np.full(int(ends[-1]) if len(ends) else 0, START, np.uint32)
    real = np.ones(len(flat), bool)
    for k in (3, 2, 1):
        real[ends - sizes - k] = False
    flat[real] = np.concatenate(parts) if parts else np.empty(0, np.uint8)
    gram = flat.copy()
    for k in (1, 2, 3):
        gram[k:] |= flat[:-k] << np.uint32(8 * k)
    return gram[real], sizes


def discounts(ones: int, twos: int, threes: int, fours: int) -> tuple[float, float, float]:
    """Modified Kneser-Ney discounts of counts 1, 2, and 3 or more, from how many grams have counts 1 to 4."""
    n = (0, ones, twos, threes, fours)
    y = n[1] / (n[1] + 2 * n[2]) if n[1] else 0.5
    of = lambda k: k - (k + 1) * y * n[k + 1] / n[k] if n[k] else k * 0.5
    return tuple(min(max(of(k), 0.05), k - 0.05) for k in (1, 2, 3))


@dataclass
class Fitted:
    """The model as tables: grams (ord, gram, prob) and contexts (ord, gram, weight), for orders 1 to 4."""

    probs: DataFrame
    backoff: DataFrame


def fit(counted: DataFrame) -> Fitted | None:
    """From (gram, n), the counts of distinct grams of order 4; None if there are none."""
    levels = {ORDER: materialize(counted, "gram-counts")}
    for order in range(ORDER - 1, 0, -1):
        levels[order] = materialize(levels[order + 1].groupBy(F.expr(f"gram & {(1 << 8 * order) - 1}").alias("gram")).agg(F.count("*").alias("n")), "gram-counts")
    tallies = None
    for order, level in levels.items():
        of = level.agg(F.lit(order).alias("ord"), *(F.count_if(F.col("n") == k).alias(f"n{k}") for k in (1, 2, 3, 4)), F.count("*").alias("all"))
        tallies = of if tallies is None else tallies.unionByName(of)
    tally = {r["ord"]: r for r in tallies.collect()}  # a row for each order
    if not tally[ORDER]["all"]:
        return None
    cuts = {order: discounts(*(r[f"n{k}"] for k in (1, 2, 3, 4))) for order, r in tally.items()}
    spark = counted.sparkSession
    lower = spark.range(SYMBOLS).select(F.col("id").alias("gram"), F.lit(1.0 / SYMBOLS).alias("prob"))  # order 0: all symbols alike
    probs, backoff = None, None
    for order in range(1, ORDER + 1):
        one, two, more = cuts[order]
        cut = f"case n when 1 then {one!r}D when 2 then {two!r}D else {more!r}D end"
        keyed = levels[order].withColumns({"context": F.expr("gram >> 8"), "tail": F.expr(f"gram & {(1 << 8 * max(order - 1, 1)) - 1}")})
        # Sums of whole numbers, so that a weight does not depend on the order of its grams.
        contexts = keyed.groupBy("context").agg(F.sum("n").alias("total"), *(F.count_if(F.expr(f"n {c}")).alias(a) for c, a in (("= 1", "n1"), ("= 2", "n2"), ("> 2", "n3"))))
        contexts = contexts.select("context", "total", F.expr(f"(n1 * {one!r}D + n2 * {two!r}D + n3 * {more!r}D) / total").alias("weight"))
        seen = keyed.join(contexts, "context").join(lower.select(F.col("gram").alias("tail"), F.col("prob").alias("below")), "tail", "right" if order == 1 else "inner")
        if order == 1:  # symbols that the texts lack have their share of what is cut off
            whole = contexts.select(F.col("weight").alias("w"))
            here = seen.crossJoin(F.broadcast(whole)).select(F.col("tail").alias("gram"), F.expr(f"coalesce((n - {cut}) / total, 0D) + w * below").alias("prob"))  # one row
        else:
            here = seen.select("gram", F.expr(f"(n - {cut}) / total + weight * below").alias("prob"))
            held = contexts.select(F.lit(order).alias("ord"), F.col("context").alias("gram"), "weight")
            backoff = held if backoff is None else backoff.unionByName(held)
        lower = materialize(here, f"gram-probs-{order}")
        of_order = lower.select(F.lit(order).alias("ord"), "gram", "prob")
        probs = of_order if probs is None else probs.unionByName(of_order)
    return Fitted(probs, backoff)


@dataclass
class Part:
    """What a task holds of the model. For orders 4 to 2: sorted grams with probabilities, sorted contexts with back-off
    weights; order 1 is a table."""

    probs: dict[int, tuple[np.ndarray, np.ndarray]]
    backoff: dict[int, tuple[np.ndarray, np.ndarray]]

    @classmethod
    def of(cls, pieces: list[tuple[str, int, np.ndarray, np.ndarray]]) -> Part:
        """From (kind, order, grams, values) in any order."""
        part = cls({}, {})
        for kind, into in (("prob", part.probs), ("weight", part.backoff)):
            for order in range(1, ORDER + 1):
                mine = [(g, v) for k, o, g, v in pieces if (k, o) == (kind, order)]
                keys, values = (np.concatenate([x[j] for x in mine]) if mine else np.empty(0, t) for j, t in ((0, np.uint32), (1, np.float64)))
                sort = np.argsort(keys)
                into[order] = keys[sort], values[sort]
        return part

    def prob(self, gram: np.ndarray, order: int = ORDER) -> np.ndarray:
        keys, probs = self.probs[order]
        if order == 1:
            return probs[gram]
        below, (contexts, weights) = np.uint32((1 << 8 * (order - 1)) - 1), self.backoff[order]
        seen, out = np.zeros(len(gram), bool), np.empty(len(gram))
        if len(keys):
            at = np.minimum(np.searchsorted(keys, gram), len(keys) - 1)
            seen, out = keys[at] == gram, probs[at]
        if not seen.all():
            rest, weight = gram[~seen], 1.0
            if len(contexts):
                where = np.minimum(np.searchsorted(contexts, rest >> np.uint32(8)), len(contexts) - 1)
                weight = np.where(contexts[where] == rest >> np.uint32(8), weights[where], 1.0)
            out[~seen] = weight * self.prob(rest & below, order - 1)
        return out

    def cost(self, gram: np.ndarray) -> np.ndarray:
        return np.round(-np.log(self.prob(gram)) * SCALE).astype(np.int64)


def owner(gram: np.ndarray, shards: int) -> np.ndarray:
    """Shard of a gram: by its two middle symbols, which its longer contexts and its order-3 part share."""
    return (mix64((gram >> np.uint32(8) & np.uint32(0xFFFF)).astype(np.uint64)) % np.uint64(shards)).astype(np.int64)


def trusted_ids(labels: DataFrame) -> DataFrame:
    return labels.where("quality = 1 and toxic = 0").select("doc_id").distinct()


def trusted_texts(docs: DataFrame, labels: DataFrame, most_ids: int = 2_000_000) -> DataFrame:
    """Texts of all trusted documents. Up to most_ids ids are sent to where texts are read; more are left to the planner."""
    good = materialize(trusted_ids(labels), "trusted")
    few = good.limit(most_ids + 1).count() <= most_ids
    return docs.where("text <> ''").join(F.broadcast(good) if few else good, "doc_id", "left_semi").select("text")


def trusted_sample(docs: DataFrame, labels: DataFrame, most_docs: int, most_chars: int) -> DataFrame:
    """For trials: texts of at most most_docs trusted documents, none longer than most_chars, by the smallest md5 of ids."""
    lengths = docs.select("doc_id", F.length("text").alias("n")).where(f"n between 1 and {most_chars}")
    chosen = lengths.join(trusted_ids(labels), "doc_id").select("doc_id").distinct().orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id").limit(most_docs)
    return docs.where(f"length(text) between 1 and {most_chars}").join(F.broadcast(chosen), "doc_id", "left_semi").select("text")  # most_docs ids


def gram_counts(texts: DataFrame) -> DataFrame:
    """(gram, n) of the grams of order 4 of column text; batches are counted before the shuffle."""

    def count(batches):
        for batch in batches:
            for part in slices(batch, "text"):
                keys, counts = np.unique(grams(part.column("text").to_pylist())[0], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(keys.astype(np.int64)), pa.array(counts.astype(np.int64))], names=["gram", "n"])

    return texts.mapInArrow(released(count), "gram bigint, n bigint").groupBy("gram").agg(F.sum("n").alias("n"))


def train(docs: DataFrame, labels: DataFrame, most_docs: int | None = None, most_chars: int | None = None) -> Fitted | None:
    """The model of all trusted texts, or of a sample where bounds are given."""
    if most_docs is None and most_chars is None:
        return fit(gram_counts(trusted_texts(docs, labels)))
    return fit(gram_counts(trusted_sample(docs, labels, most_docs or 1 << 30, most_chars or 1 << 30)))


PACK = "shard int, kind string, ord int, load binary"


def model_packs(fitted: Fitted, shards: int, salts: int) -> DataFrame:
    """The model dealt to shards, each of them `salts` times: orders 4 and 3 by their owner, orders 2 and 1 whole."""
    tables = fitted.probs.selectExpr("'prob' as kind", "ord", "gram", "prob as value").unionByName(fitted.backoff.selectExpr("'weight' as kind", "ord", "gram", "weight as value"))

    names = ("kind", "ord", "gram", "value")

    def packed(held):
        out = []
        kind, order, gram, value = (np.concatenate(c) for c in zip(*held))
        for k, shift in (("prob", 0), ("weight", 8)):  # a context lacks the last symbol
            for o in range(1, ORDER + 1):
                mine = (kind == k) & (order == o)
                keys, values = gram[mine].astype(np.uint32), value[mine].astype(np.float64)
                of = owner(keys << np.uint32(shift), shards)
                for s in range(shards):
                    here = of == s if o >= 3 else np.ones(len(keys), bool)
                    if here.any():
                        load = struct.pack("<q", int(here.sum())) + keys[here].tobytes() + values[here].tobytes()
                        out.append((s, k, o, load))
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), (pa.int32(), pa.string(), pa.int32(), pa.binary()))], names=["shard", "kind", "ord", "load"])

    def run(batches):
        held, rows = [], 0
        for batch in batches:
            if batch.num_rows:
                held.append([batch.column(c).to_numpy(zero_copy_only=False) for c in names])
                rows += batch.num_rows
            if rows > 100_000:
                yield packed(held)
                held, rows = [], 0
        if held:
            yield packed(held)

    # Copies are made row by row, outside of Python, whose batches hold one of each.
    salt = F.explode(F.sequence(F.lit(0), F.lit(salts - 1)))
    return tables.mapInArrow(released(run), PACK).withColumn("salt", salt).withColumn("shard", F.expr(f"shard + {shards} * salt")).drop("salt")


def _packs(shards: int, docs_in_pack: int = 1000):
    def run(batches):
        import zstandard

        squeeze, turn = zstandard.ZstdCompressor(level=1).compress, 0
        for batch in batches:
            for part in slices(batch, "text", 1 << 20):
                for start in range(0, part.num_rows, docs_in_pack):
                    piece = part.slice(start, docs_in_pack)
                    gram, sizes = grams(piece.column("text").to_pylist())
                    pair, counts = np.unique(gram.astype(np.uint64) << np.uint64(16) | np.repeat(np.arange(len(sizes), dtype=np.uint64), sizes), return_counts=True)
                    key, doc = (pair >> np.uint64(16)).astype(np.uint32), (pair & np.uint64(0xFFFF)).astype(np.uint16)
                    of = owner(key, shards)
                    ids = np.stack([np.asarray(piece.column(c).cast(pa.int64()).fill_null(-(2**63)).to_numpy(zero_copy_only=False), np.int64) for c in ("doc_id", "text_key")])
                    loads = []
                    for s in range(shards):
                        mine = of == s
                        distinct, runs = np.unique(key[mine], return_counts=True)
                        steps = np.diff(distinct, prepend=np.uint32(0)).astype(np.uint32)
                        arrays = [ids.ravel(), steps, runs.astype(np.uint32), doc[mine], counts[mine].astype(np.uint32)]
                        body = b"".join(np.ascontiguousarray(a.view(np.uint8).reshape(-1, a.itemsize).T).tobytes() for a in arrays)
                        loads.append(struct.pack("<5q", *(len(a) for a in arrays)) + squeeze(body))
                    yield pa.RecordBatch.from_arrays([pa.array([s + shards * turn for s in range(shards)], pa.int32()), pa.array(["text"] * shards), pa.array([0] * shards, pa.int32()), pa.array(loads, pa.binary())], names=["shard", "kind", "ord", "load"])
                    turn += 1

    return run


def _unpack(load: bytes) -> list[np.ndarray]:
    import zstandard

    sizes, kinds, at, out = struct.unpack_from("<5q", load), (np.int64, np.uint32, np.uint32, np.uint16, np.uint32), 0, []
    body = zstandard.ZstdDecompressor().decompress(load[40:], max_output_size=sum(n * np.dtype(k).itemsize for n, k in zip(sizes, kinds)) or 1)
    for n, kind in zip(sizes, kinds):
        wide = np.dtype(kind).itemsize
        out.append(np.ascontiguousarray(np.frombuffer(body, np.uint8, n * wide, at).reshape(wide, n).T).view(kind).ravel() if n else np.empty(0, kind))
        at += n * wide
    return out


def _score(batches):
    pieces, model = [], None
    for batch in batches:
        for kind, order, load in zip(batch.column("kind").to_pylist(), batch.column("ord").to_pylist(), batch.column("load")):
            load = load.as_py()
            if kind != "text":
                (n,) = struct.unpack_from("<q", load)
                pieces.append((kind, order, np.frombuffer(load, np.uint32, n, 8), np.frombuffer(load, np.float64, n, 8 + 4 * n)))
                continue
            if model is None:
                model, pieces = Part.of(pieces), []
            ids, steps, runs, doc, counts = _unpack(load)
            ids = ids.reshape(2, -1)
            cost = np.repeat(model.cost(np.cumsum(steps, dtype=np.uint32)), runs) * counts
            total, number = (np.bincount(doc, w, minlength=ids.shape[1]) for w in (cost, counts))
            there = number > 0
            yield pa.RecordBatch.from_arrays([pa.array(ids[0][there]), pa.array(ids[1][there]), pa.array(total[there].astype(np.int64)), pa.array(number[there].astype(np.int64))], names=["doc_id", "text_key", "cost", "n"])


def perplexities(docs: DataFrame, fitted: Fitted, shards: int = 8) -> DataFrame:
    """doc_id, text_key, n_grams, perplexity of every document with text. doc_id may be null (then it is the least number)."""
    salts = max(1, -(-reduce_tasks(docs.sparkSession) // shards))
    keyed = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.xxhash64("text").alias("text_key"), "text").where("text <> ''")
    loads = keyed.mapInArrow(released(_packs(shards)), PACK).withColumn("shard", F.expr(f"shard % {shards} + {shards} * pmod(shard div {shards} + spark_partition_id(), {salts})"))
    dealt = loads.unionByName(model_packs(fitted, shards, salts)).repartitionById(shards * salts, F.col("shard").cast("int")).sortWithinPartitions(F.expr("kind = 'text'"))
    parts = dealt.mapInArrow(released(_score), "doc_id bigint, text_key bigint, cost bigint, n bigint")
    return parts.groupBy("doc_id", "text_key").agg(F.sum("cost").alias("cost"), F.sum("n").alias("n_grams")).select("doc_id", "text_key", "n_grams", F.exp(F.col("cost") / F.col("n_grams") / SCALE).alias("perplexity"))


def judged(docs: DataFrame, labels: DataFrame, quantile: float = 0.99, margin: float = 1.06, least_group: int = 50, shards: int = 8, **training) -> DataFrame:
    """doc_id, text_key, lang, n_grams, perplexity, fence, kept for every document."""
    base = docs.select(F.coalesce(F.col("doc_id").cast("bigint"), F.lit(-(2**63))).alias("doc_id"), F.xxhash64("text").alias("text_key"), "lang", (F.coalesce(F.length("text"), F.lit(0)) > 0).alias("has_text"))
    fitted = train(docs, labels, **training)
    if fitted is None:
        return base.selectExpr("doc_id", "text_key", "lang", "0L as n_grams", "cast(null as double) as perplexity", "cast(null as double) as fence", "has_text as kept")
    scores = materialize(perplexities(docs, fitted, shards=shards), "perplexities")
    placed = base.join(scores, ["doc_id", "text_key"], "left")
    trusted = placed.join(trusted_ids(labels), "doc_id", "left_semi").where("perplexity is not null")
    by_lang = trusted.groupBy("lang").agg(F.percentile_approx("perplexity", quantile, 10_000).alias("q"), F.count("*").alias("size"))
    high = trusted.agg(F.percentile_approx("perplexity", quantile, 10_000).alias("q")).first()["q"]
    # A row for each language; written, its size is known, and the planner broadcasts it or not by that.
    fences = materialize(by_lang.where(F.col("size") >= least_group).select(F.col("lang").alias("of_lang"), "q"), "fences")
    fenced = placed.join(fences, F.col("lang").eqNullSafe(F.col("of_lang")), "left").withColumn("fence", F.coalesce("q", F.lit(high)) * margin)
    return fenced.select("doc_id", "text_key", "lang", F.coalesce("n_grams", F.lit(0)).alias("n_grams"), "perplexity", "fence", F.expr("has_text and coalesce(perplexity <= fence, true)").alias("kept"))


def accepted(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """docs without those that the classifier rejects."""
    of = judged(docs, labels, **options).where("kept").select(F.col("doc_id").alias("of_id"), F.col("text_key").alias("of_key")).distinct()
    return docs.join(of, (F.coalesce(F.col("doc_id").cast("bigint"), F.lit(-(2**63))) == F.col("of_id")) & (F.xxhash64("text") == F.col("of_key")), "left_semi")


def op6_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")).select("doc_id", "lang", "n_grams", "perplexity", "fence", "kept")


QUERIES = {"op6_language_model": op6_language_model}
ORACLES: dict = {}

"""Bloom filters as tables of non-zero words: build, unite, test, measure, convert."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from filterfleet.functions.hashing import positions, set_bits
from filterfleet.functions.params import WORD, FilterSpec, expected_fp_column


def bit_of(pos: Column | str) -> Column:
    pos = F.col(pos) if isinstance(pos, str) else pos
    return F.call_function("shiftleft", F.lit(1).cast("bigint"), (pos % WORD).cast("int"))


def word_of(pos: str) -> Column:
    return F.expr(f"{pos} div {WORD}").cast("int")


def build_filters(membership: DataFrame, spec: FilterSpec) -> DataFrame:
    """(filter_id, word_ix, word): the filters of all sites, without zero words. OR combines before the shuffle."""
    return set_bits(membership, spec).groupBy(F.col("site_id").alias("filter_id"), word_of("pos").alias("word_ix")).agg(F.bit_or(bit_of("pos")).alias("word"))


def union_filters(filter_words: DataFrame, *keys: str) -> DataFrame:
    """OR of filters by key: the filter of the union of their sets."""
    return filter_words.groupBy(*keys, "word_ix").agg(F.bit_or("word").alias("word"))


def fill_stats(filter_words: DataFrame, spec: FilterSpec, *keys: str) -> DataFrame:
    """Set bits, fill, false-positive rate from the fill, and whether all bits are set."""
    ones = F.sum(F.bit_count("word"))
    return (
        filter_words.groupBy(*keys)
        .agg(ones.alias("ones"))
        .withColumns({"fill": F.col("ones") / spec.m, "fp": F.pow(F.col("ones") / spec.m, spec.k), "saturated": F.col("ones") == spec.m})
    )


def fill_report(membership: DataFrame, spec: FilterSpec) -> DataFrame:
    """Measured and analytic fill of the union of all sites."""
    distinct = membership.where("site_id is not null and element is not null").agg(F.countDistinct("element").alias("n"))
    ones = union_filters(build_filters(membership, spec)).agg(F.coalesce(F.sum(F.bit_count("word")), F.lit(0)).alias("ones"))
    return distinct.crossJoin(ones).select(  # one row each
        "n", "ones", (F.col("ones") / spec.m).alias("fill"), (1 - F.exp(-spec.k * F.col("n") / spec.m)).alias("analytic_fill"), expected_fp_column("n", spec.m, spec.k).alias("analytic_fp")
    )


def cardinality(filter_words: DataFrame, spec: FilterSpec, *keys: str) -> DataFrame:
    """Elements estimated from the fill; null for a full filter."""
    return fill_stats(filter_words, spec, *keys).withColumn("estimate", F.when(~F.col("saturated"), -F.log(1 - F.col("fill")) * spec.m / spec.k))


def matches_expr(words: Column, element: Column, spec: FilterSpec) -> Column:
    """Test of one dense filter; stops at the first position whose bit is 0."""
    return F.forall(positions(element, spec), lambda p: F.getbit(F.element_at(words, F.floor(p / WORD).cast("int") + 1), p % WORD) == 1)


def to_dense(filter_words: DataFrame, spec: FilterSpec, key: str = "filter_id") -> DataFrame:
    """(key, words ARRAY<BIGINT>, ones)."""
    at = F.map_from_entries(F.collect_list(F.struct("word_ix", "word")))
    full = F.transform(F.sequence(F.lit(0), F.lit(spec.words - 1)), lambda i: F.coalesce(F.element_at(F.col("at"), i), F.lit(0).cast("bigint")))
    return filter_words.groupBy(key).agg(at.alias("at"), F.sum(F.bit_count("word")).alias("ones")).select(key, full.alias("words"), "ones")


def to_sparse(filters: DataFrame, key: str = "filter_id") -> DataFrame:
    return filters.select(key, F.posexplode("words").alias("word_ix", "word")).where("word <> 0")


def to_positions(filter_words: DataFrame, key: str = "filter_id") -> DataFrame:
    """(key, pos) of every set bit."""
    lanes = F.filter(F.sequence(F.lit(0), F.lit(WORD - 1)), lambda i: F.getbit(F.col("word"), i) == 1)
    return filter_words.select(key, "word_ix", F.explode(lanes).alias("lane")).select(key, (F.col("word_ix") * WORD + F.col("lane")).alias("pos"))


def to_bytes(filters: DataFrame, key: str = "filter_id") -> DataFrame:
    """(key, bits BINARY) of dense filters: words one after the other, position 0 in the lowest bit of the first byte."""
    word = lambda w: F.reverse(F.lpad(F.hex(w), 16, "0"))
    # hex is written from the highest digit on; reversed as a whole, each byte's two digits change places again
    swapped = lambda w: F.regexp_replace(word(w), "(.)(.)", "$2$1")
    return filters.select(key, F.unhex(F.array_join(F.transform("words", swapped), "")).alias("bits"))


def from_bytes(rows: DataFrame, key: str = "filter_id") -> DataFrame:
    """(key, words ARRAY<BIGINT>) of the bytes layout."""
    digits = F.regexp_replace(F.reverse(F.hex("bits")), "(.)(.)", "$2$1")  # the last word first, each from its highest digit on
    n = (F.length("digits") / 16).cast("int")
    part = lambda i: F.conv(F.expr("digits").substr((n - i - 1) * 16 + 1, F.lit(16)), 16, -10).cast("bigint")
    return rows.select(key, digits.alias("digits")).select(key, F.when(n > 0, F.transform(F.sequence(F.lit(0), n - 1), part)).otherwise(F.array().cast("array<bigint>")).alias("words"))


def to_bitmaps(membership: DataFrame, spec: FilterSpec) -> DataFrame:
    """(filter_id, bucket, bitmap BINARY): Spark's own bitmap layout, 32,768 positions a bucket."""
    bits = set_bits(membership, spec).select(F.col("site_id").alias("filter_id"), (F.col("pos") + 1).cast("bigint").alias("p"))
    return bits.groupBy("filter_id", F.bitmap_bucket_number("p").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("p")).alias("bitmap"))


def accuracy(matches: DataFrame, truth: DataFrame) -> DataFrame:
    """True and false positives, false negatives, precision and recall of (query_id, filter_id) pairs."""
    both = matches.select("query_id", "filter_id", F.lit(1).alias("m")).join(truth.select("query_id", "filter_id", F.lit(1).alias("t")), ["query_id", "filter_id"], "full")
    n = lambda cond: F.count_if(F.expr(cond))
    return both.agg(n("m = 1 and t = 1").alias("tp"), n("t is null").alias("fp"), n("m is null").alias("fn")).withColumns({"precision": F.expr("try_divide(tp, tp + fp)"), "recall": F.expr("try_divide(tp, tp + fn)")})

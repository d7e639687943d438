"""Quality rules whose cutoffs come from mergeable quantile sketches of each language and source.

Every document gets counts over its whole text. Four rates of it (symbols a word, repeated lines, repeated words,
letters a word) go into histogram sketches: values below 128 stay as they are, larger ones keep their seven leading
bits, so a bucket is under 1/64 of its value wide, a sketch has a fixed number of buckets, and sketches merge by
adding counts. A fence is a quartile plus or minus `reach` times the spread between the quartiles (or a least
spread, where all documents agree). A group of few documents takes its language's sketch, a small language that of
all documents. The fences join back to the rows under a salt, so a source with a third of all rows is dealt out.

Null text counts as no words and fails the base rule; null languages and sources form groups of their own; repeated
rows are judged each by itself; columns other than doc_id, text, lang and source are ignored; no rows give no rows.
"""

from __future__ import annotations

from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from filterfleet.llm.common import materialize, table

SYMBOLS = "#*$%&|<>"
#: Rate, least spread between quartiles, whether low values are odd too. Rates are in millionths.
RATES = {"symbol_rate": (20_000, False), "dup_line_rate": (80_000, False), "repeat_rate": (50_000, False), "word_length": (250_000, True)}
FEATURES = "doc_id bigint, lang string, source string, n_words bigint, word_chars bigint, n_symbols bigint, n_lines bigint, n_dup_lines bigint, n_repeat_words bigint"


def text_counts(text: str | None) -> tuple[int, int, int, int, int, int]:
    """words, code points in words, symbols, lines with a word, such lines seen before, words in repeated 3-word windows."""
    if not text:
        return 0, 0, 0, 0, 0, 0
    raw = text.encode()
    words = raw.split()
    lines = [x for x in raw.split(b"\n") if x.strip()]
    windows = list(zip(words, words[1:], words[2:]))
    seen, repeated, end = Counter(windows), 0, 0
    if len(seen) < len(windows):
        for i, w in enumerate(windows):
            if seen[w] > 1:
                repeated += i + 3 - max(i, end)
                end = i + 3
    letters = len(text) - sum(map(text.count, " \t\n\v\f\r"))
    return len(words), letters, sum(map(text.count, SYMBOLS)), len(lines), len(lines) - len(set(lines)), repeated


def _count_batches(batches):
    for batch in batches:
        counts = [text_counts(x) for x in batch.column("text").to_pylist()]
        columns = zip(*counts) if counts else [[]] * 6
        yield pa.RecordBatch.from_arrays(
            [*(batch.column(c) for c in ("doc_id", "lang", "source")), *(pa.array(c, pa.int64()) for c in columns)],
            names=[x.split()[0] for x in FEATURES.split(", ")],
        )


def features(docs: DataFrame) -> DataFrame:
    """Counts of every document, its rates in millionths, and the base verdict."""
    per = lambda a, b: F.expr(f"{a} * 1000000 div greatest({b}, 1)")
    return (
        docs.select(F.col("doc_id").cast("bigint"), "text", "lang", "source")
        .mapInArrow(_count_batches, FEATURES)
        .withColumns(
            {
                "symbol_rate": per("n_symbols", "n_words"),
                "dup_line_rate": per("n_dup_lines", "n_lines"),
                "repeat_rate": per("n_repeat_words", "n_words"),
                "word_length": per("word_chars", "n_words"),
                "base_failed": F.expr("n_words < 50 or 100 * n_repeat_words > 50 * n_words"),
            }
        )
    )


def _bucket_sql(name: str) -> str:
    """Least value of the sketch bucket that holds the column `name` (0 or more)."""
    return f"{name} - {name} % shiftleft(1L, greatest(length(bin({name})) - 7, 0))"


def sketches(counted: DataFrame) -> DataFrame:
    """(lang, source, rate, bucket, n): the histogram sketches, over documents that pass the base rule."""
    stacked = ", ".join(f"'{r}', {r}" for r in RATES)
    return (
        counted.where("not base_failed")
        .selectExpr("lang", "source", f"stack({len(RATES)}, {stacked}) as (rate, value)")
        .selectExpr("lang", "source", "rate", f"{_bucket_sql('value')} as bucket")
        .groupBy("lang", "source", "rate", "bucket")
        .agg(F.count("*").alias("n"))
    )


def merge(sketch: DataFrame, *keys: str) -> DataFrame:
    """Sketches of coarser groups: counts of equal buckets add up."""
    return sketch.groupBy(*keys, "rate", "bucket").agg(F.sum("n").alias("n"))


def quartiles(sketch: DataFrame, *keys: str) -> DataFrame:
    """Size, lower and upper quartile of every sketch: the first bucket at which a quarter, three quarters are reached."""
    group = Window.partitionBy(*keys, "rate")
    upto = group.orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0)
    return (
        sketch.withColumns({"size": F.sum("n").over(group), "upto": F.sum("n").over(upto)})
        .groupBy(*keys, "rate")
        .agg(F.max("size").alias("size"), F.expr("min(bucket) filter (where 4 * upto >= size)").alias("q1"), F.expr("min(bucket) filter (where 4 * upto >= 3 * size)").alias("q3"))
    )


def fences(sketch: DataFrame, least_group: int = 30, reach: int = 6) -> DataFrame:
    """One row for each language and source: <rate>_low and <rate>_high."""
    of = lambda d, tag: d.select(*[c for c in d.columns if c not in ("size", "q1", "q3")], *(F.col(c).alias(f"{tag}_{c}") for c in ("size", "q1", "q3")))
    own = of(quartiles(sketch, "lang", "source"), "own")
    lang = of(quartiles(merge(sketch, "lang"), "lang"), "lang").select(F.col("lang").alias("of_lang"), F.col("rate").alias("of_rate"), "lang_size", "lang_q1", "lang_q3")
    every = of(quartiles(merge(sketch)), "all").select(F.col("rate").alias("any_rate"), "all_q1", "all_q3")
    pick = lambda q: F.expr(f"case when own_size >= {least_group} then own_{q} when lang_size >= {least_group} then lang_{q} else all_{q} end")
    chosen = (
        own.join(lang, F.col("lang").eqNullSafe(F.col("of_lang")) & (F.col("rate") == F.col("of_rate")))
        .join(every, F.col("rate") == F.col("any_rate"))
        .select("lang", "source", "rate", pick("q1").alias("q1"), pick("q3").alias("q3"))
    )
    columns = []
    for rate, (least, both) in RATES.items():
        spread = f"greatest(q3 - q1, {least})"
        high, low = f"q3 + {reach} * {spread}", f"q1 - {reach} * {spread}" if both else "-1"
        columns += [F.expr(f"max(case when rate = '{rate}' then {x} end)").alias(f"{rate}_{side}") for side, x in (("low", low), ("high", high))]
    return chosen.groupBy("lang", "source").agg(*columns)


def quality_rules(docs: DataFrame, least_group: int = 30, reach: int = 6, salts: int = 16) -> DataFrame:
    """Counts, rates, base_failed and kept for every document."""
    counted = materialize(features(docs), "quality-features")
    limits = (
        fences(sketches(counted), least_group, reach)
        .withColumnsRenamed({"lang": "of_lang", "source": "of_source"})
        .withColumn("of_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    )
    salted = counted.withColumn("salt", F.expr(f"cast(pmod(xxhash64(doc_id, n_words, word_chars), {salts}) as int)"))
    joined = salted.join(limits, F.col("lang").eqNullSafe(F.col("of_lang")) & F.col("source").eqNullSafe(F.col("of_source")) & (F.col("salt") == F.col("of_salt")), "left")
    inside = " and ".join(f"{r} between coalesce({r}_low, {r}) and coalesce({r}_high, {r})" for r in RATES)
    return joined.select(*counted.columns, F.expr(f"not base_failed and {inside}").alias("kept"))


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def _oracle() -> str:
    rates = {"symbol_rate": "n_symbols * 1000000 // greatest(n_words, 1)", "dup_line_rate": "n_dup_lines * 1000000 // greatest(n_lines, 1)", "repeat_rate": "n_repeat_words * 1000000 // greatest(n_words, 1)", "word_length": "word_chars * 1000000 // greatest(n_words, 1)"}
    stacked = " union all ".join(f"select lang, source, '{r}' as rate, {r} as v from r where not base_failed" for r in RATES)
    level = lambda keys: f"select {keys}rate, max(size) as size, min(bucket) filter (where 4 * upto >= size) as q1, min(bucket) filter (where 4 * upto >= 3 * size) as q3 from (select {keys}rate, bucket, sum(n) over (partition by {keys}rate) as size, sum(n) over (partition by {keys}rate order by bucket) as upto from (select {keys}rate, bucket, sum(n)::bigint as n from s group by {keys}rate, bucket)) group by {keys}rate"
    least = " ".join(f"when '{r}' then {x}" for r, (x, _) in RATES.items())
    tests = " and ".join(f"not exists (select 1 from f where f.lang is not distinct from r.lang and f.source is not distinct from r.source and f.rate = '{r}' and (r.{r} > f.high" + (f" or r.{r} < f.low" if both else "") + "))" for r, (_, both) in RATES.items())
    return rf"""
with d as (select doc_id, coalesce(text, '') as text, lang, source, row_number() over () as k from documents),
w as (select k, unnest(ws) as word, generate_subscripts(ws, 1) as i from (select k, regexp_extract_all(text, '[^\x20\x09-\x0D]+') as ws from d)),
t as (select k, i, word || ' ' || lead(word) over (partition by k order by i) || ' ' || lead(word, 2) over (partition by k order by i) as tri from w),
m as (select k, i from (select k, i, tri, count(*) over (partition by k, tri) as c from t) where tri is not null and c > 1),
rep as (select k, count(distinct p) as n_repeat_words from (select k, i as p from m union all select k, i + 1 from m union all select k, i + 2 from m) group by k),
wc as (select k, count(*) as n_words, sum(length(word))::bigint as word_chars from w group by k),
ln as (select k, count(*) as n_lines, count(*) - count(distinct line) as n_dup_lines from (select k, unnest(str_split(text, chr(10))) as line from d) where regexp_matches(line, '[^\x20\x09-\x0D]') group by k),
b as (select d.k, doc_id, lang, source, coalesce(n_words, 0) as n_words, coalesce(word_chars, 0) as word_chars, length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) as n_symbols, coalesce(n_lines, 0) as n_lines, coalesce(n_dup_lines, 0) as n_dup_lines, coalesce(n_repeat_words, 0) as n_repeat_words from d left join wc using (k) left join ln using (k) left join rep using (k)),
r as (select *, {", ".join(f"{e} as {n}" for n, e in rates.items())}, (n_words < 50 or 100 * n_repeat_words > 50 * n_words) as base_failed from b),
s as (select lang, source, rate, v - v % (1::bigint << greatest(length(bin(v)) - 7, 0)) as bucket, count(*) as n from ({stacked}) group by 1, 2, 3, 4),
o as ({level("lang, source, ")}), l as ({level("lang, ")}), e as ({level("")}),
q as (select o.lang, o.source, o.rate, case when o.size >= 30 then o.q1 when l.size >= 30 then l.q1 else e.q1 end as q1, case when o.size >= 30 then o.q3 when l.size >= 30 then l.q3 else e.q3 end as q3, case o.rate {least} end as least
  from o join l on o.rate = l.rate and o.lang is not distinct from l.lang join e on o.rate = e.rate),
f as (select lang, source, rate, q3 + 6 * greatest(q3 - q1, least) as high, q1 - 6 * greatest(q3 - q1, least) as low from q)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, (not base_failed and {tests}) as kept from r
"""


QUERIES = {"op1_quality_rules": op1_quality_rules}
ORACLES = {"op1_quality_rules": _oracle()}

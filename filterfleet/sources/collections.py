"""Site collections on the given tables: (site_id, element), and probes for them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

from filterfleet.functions.frames import table

#: Largest key of any collection lies below this; probes from here on are certain negatives.
ABSENT = 1_000_000_000


def string_key(text):
    """A string as a non-negative number of 60 bits, the same in any engine that has md5."""
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("bigint")


def tokens(text: str = "text"):
    """Lower-cased words: runs of letters and digits."""
    return F.filter(F.split(F.lower(text), r"[^\p{L}0-9]+"), lambda w: w != "")


def _pairs(df: DataFrame, site, element) -> DataFrame:
    return df.select(F.expr(site).cast("bigint").alias("site_id") if isinstance(site, str) else site.alias("site_id"), F.expr(element).alias("element") if isinstance(element, str) else element.alias("element")).distinct()


def _of(name: str, site, element) -> Callable:
    return lambda spark, sf_dir: _pairs(table(spark, sf_dir, name), site, element)


def _supplier_nations(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").select("l_suppkey", "l_orderkey")
    return _pairs(lines.join(table(spark, sf_dir, "supplier"), F.expr("l_suppkey = s_suppkey")), "s_nationkey", "l_orderkey")


def _hosts(spark, sf_dir):
    host = F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1)
    return table(spark, sf_dir, "pages").select(string_key(host).alias("site_id"), string_key(F.col("url")).alias("element")).distinct()


def _words(name, key):
    words = lambda spark, sf_dir: table(spark, sf_dir, name).select(F.col(key).alias("site_id"), F.explode(tokens()).alias("word")).distinct()
    return lambda spark, sf_dir: words(spark, sf_dir).select("site_id", string_key(F.col("word")).alias("element"))


COLLECTIONS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "block100": _of("orders", "o_orderkey div 100", "o_orderkey"),
    "block1000": _of("orders", "o_orderkey div 1000", "o_orderkey"),
    "block10": _of("orders", "o_orderkey div 10", "o_orderkey"),
    "cust": _of("orders", "o_custkey", "o_orderkey"),
    "part": _of("lineitem", "l_partkey", "l_orderkey"),
    "supp": _of("lineitem", "l_suppkey", "l_partkey"),
    "order": _of("lineitem", "l_orderkey", "l_partkey"),
    "user": _of("events", "user_id", "event_id"),
    "day": _of("events", "datediff(to_date(ts), date'2024-01-01')", "user_id"),
    "hour": _of("events", "24 * datediff(to_date(ts), date'2024-01-01') + hour(ts)", "user_id"),
    "source": lambda s, d: table(s, d, "documents").select(F.substring("source", 4, 9).cast("bigint").alias("site_id"), string_key(F.col("text")).alias("element")).distinct(),
    "doc": _words("documents", "doc_id"),
    "conv": _words("conversations", "conv_id"),
    "host": _hosts,
    "label": _of("embeddings", "label", "vec_id"),
    "nation": _of("customer", "c_nationkey", "c_custkey"),
    "supnat": _supplier_nations,
}


def collection(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return COLLECTIONS[name](spark, sf_dir)


def ranges(spark: SparkSession, sites: int, n: int) -> DataFrame:
    """Sets of consecutive numbers that don't overlap: site i holds n numbers from i * n on."""
    return spark.range(sites * n).select(F.expr(f"id div {n}").alias("site_id"), F.col("id").alias("element"))


def random_ranges(spark: SparkSession, sites: int, n: int, domain: int, width: int | None = None, seed: str = "r") -> DataFrame:
    """Overlapping sets: each site draws n numbers from a range of its own that lies anywhere in the domain."""
    width = width or 10 * n
    draw = lambda *parts: F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), *parts)), 1, 15), 16, 10).cast("bigint")
    cells = spark.range(sites * n).select(F.expr(f"id div {n}").alias("site_id"), F.expr(f"id % {n}").alias("i"))
    start = F.pmod(draw(F.col("site_id").cast("string")), F.lit(max(1, domain - width)))
    return cells.select("site_id", (start + F.pmod(draw(F.col("site_id").cast("string"), F.col("i").cast("string")), F.lit(width))).alias("element")).distinct()


def probes(membership: DataFrame, every: int = 100) -> DataFrame:
    """(query_id, element, kind): the distinct elements divisible by `every`, and as many that no set holds."""
    there = membership.select("element").distinct().where(F.pmod("element", F.lit(every)) == 0)
    absent = there.select((F.col("element") * 2 + 1).alias("query_id"), (F.col("element") + ABSENT).alias("element"), F.lit("absent").alias("kind"))
    return there.select((F.col("element") * 2).alias("query_id"), "element", F.lit("present").alias("kind")).unionByName(absent)

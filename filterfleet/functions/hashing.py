"""Hash families: from an element to its k bit positions, as column expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from filterfleet.functions.params import FilterSpec

FAMILIES = ("linear_odd", "mod_identity", "md5_double", "xx64_double")


def _double(first: Column, second: Column, spec: FilterSpec) -> Column:
    """k positions from two residues: first + i * second. The residues are an array of one, so an element is hashed once
    for each of them and not anew for each of the k positions."""
    pair = F.array(F.struct(F.pmod(first, F.lit(spec.m)).alias("a"), F.pmod(second, F.lit(spec.m)).alias("b")))
    step = lambda h, i: ((h["a"] + F.lit(i).cast("bigint") * h["b"]) % spec.m).cast("int")
    return F.element_at(F.transform(pair, lambda h: F.array(*(step(h, i) for i in range(spec.k)))), 1)


def positions(element: Column, spec: FilterSpec) -> Column:
    """ARRAY<INT> of k positions; hash functions that collide give a position twice."""
    if spec.family == "linear_odd":
        seeds = F.array(*(F.lit(a % spec.m).cast("bigint") for a in spec.seeds))
        x = F.pmod(element.cast("bigint"), F.lit(spec.m))
        return F.transform(seeds, lambda a: (a * x % spec.m).cast("int"))
    if spec.family == "mod_identity":
        return F.array(F.pmod(element.cast("bigint"), F.lit(spec.m)).cast("int"))
    if spec.family == "md5_double":
        digest = F.md5(element.cast("string"))
        part = lambda at: F.conv(F.substring(digest, at, 15), 16, 10).cast("bigint")
        return _double(part(1), part(17), spec)
    if spec.family == "xx64_double":
        return _double(F.xxhash64(F.lit(spec.seeds[0]), element), F.xxhash64(F.lit(spec.seeds[-1] + 1), element), spec)
    raise ValueError(f"unknown hash family {spec.family}")


def set_bits(membership: DataFrame, spec: FilterSpec) -> DataFrame:
    """(site_id, pos): a row for each element and hash function; null sites and elements are dropped."""
    return membership.where("site_id is not null and element is not null").select("site_id", F.explode(positions(F.col("element"), spec)).alias("pos"))


def probe_bits(probes: DataFrame, spec: FilterSpec) -> DataFrame:
    """(query_id, pos, k_distinct): distinct positions of each probe; null elements are dropped."""
    spots = F.array_distinct(positions(F.col("element"), spec))
    return probes.where("element is not null").select("query_id", spots.alias("spots")).select("query_id", F.size("spots").alias("k_distinct"), F.explode("spots").alias("pos"))


def probe_words(probes: DataFrame, spec: FilterSpec) -> DataFrame:
    """(query_id, word_ix, mask, n_words): the probe's positions gathered into words."""
    bit = F.call_function("shiftleft", F.lit(1).cast("bigint"), F.expr("p % 64"))
    return (
        probes.where("element is not null")
        .select("query_id", F.explode(F.array_distinct(positions(F.col("element"), spec))).alias("p"))
        .groupBy("query_id", F.expr("p div 64").cast("int").alias("word_ix"))
        .agg(F.bit_or(bit).alias("mask"))
        .withColumn("n_words", F.count("*").over(_by_query()))
    )


def _by_query():
    from pyspark.sql import Window

    return Window.partitionBy("query_id")

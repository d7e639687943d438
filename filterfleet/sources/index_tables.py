"""Index tables on disk: versions of a tree or a pack, written side by side and switched by the newest manifest."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession

from filterfleet.functions.params import FilterSpec
from filterfleet.operators.pack import PackIndex, write_words
from filterfleet.operators.tree import TreeIndex


def _manifest(spark: SparkSession, path: str, version: int, kind: str, spec: FilterSpec, d: int) -> None:
    row = json.dumps({"version": version, "kind": kind, "expected_n": spec.expected_n, "target_fp": spec.target_fp, "family": spec.family, "k": spec.k, "m": spec.m, "seeds": spec.seeds, "d": d})
    spark.createDataFrame([(version, row)], "version int, manifest string").coalesce(1).write.mode("append").parquet(f"{path}/manifest")


def _newest(spark: SparkSession, path: str) -> dict:
    return json.loads(spark.read.parquet(f"{path}/manifest").orderBy("version", ascending=False).first()["manifest"])


def _spec(m: dict) -> FilterSpec:
    return FilterSpec(m["expected_n"], m["target_fp"], m["family"], m["k"], m["m"], tuple(m["seeds"]))


def next_version(spark: SparkSession, path: str) -> int:
    try:
        return _newest(spark, path)["version"] + 1
    except Exception as missing:  # no manifest yet
        if "PATH_NOT_FOUND" not in str(missing):
            raise
        return 0


def save_pack(index: PackIndex, path: str) -> int:
    """Slices sorted by position within ranges of it, so a probe's positions prune files and row groups."""
    spark, version = index.slices.sparkSession, next_version(index.slices.sparkSession, path)
    index.slices.repartitionByRange("pos").sortWithinPartitions("pos", "block_id").write.parquet(f"{path}/v{version}/slices")
    index.slots.write.parquet(f"{path}/v{version}/slots")
    _manifest(spark, path, version, "pack", index.spec, 0)
    return version


def save_words(index: PackIndex, path: str) -> int:
    """A pack as built, in files that a lookup maps into memory: it reads a probe's rows of words and nothing else, and
    readers on one machine share them. Takes the words' full size on disk, and a path that all tasks can open."""
    spark, version = index.slots.sparkSession, next_version(index.slots.sparkSession, path)
    at = f"{path}/v{version}"
    index.slots.write.parquet(f"{at}/slots")
    write_words(PackIndex(index.slices, spark.read.parquet(f"{at}/slots"), index.spec, index.members), f"{at}/words".removeprefix("file://"))
    _manifest(spark, path, version, "words", index.spec, 0)
    return version


def load_pack(spark: SparkSession, path: str, spec: FilterSpec | None = None) -> PackIndex:
    m = _newest(spark, path)
    found = _spec(m)
    if m["kind"] != "pack" or spec and spec.spec_id != found.spec_id:
        raise ValueError(f"{path} holds a {m['kind']} of {found.spec_id}")
    at = f"{path}/v{m['version']}"
    return PackIndex(spark.read.parquet(f"{at}/slices"), spark.read.parquet(f"{at}/slots"), found)


def save_tree(index: TreeIndex, path: str) -> int:
    """Words by level, so that a search reads only the levels it comes to."""
    spark, version = index.nodes.sparkSession, next_version(index.nodes.sparkSession, path)
    index.nodes.write.parquet(f"{path}/v{version}/nodes")
    leveled: DataFrame = index.words.join(index.nodes.select("tree_id", "node_id", "level"), ["tree_id", "node_id"])
    leveled.write.partitionBy("level").parquet(f"{path}/v{version}/words")
    _manifest(spark, path, version, "tree", index.spec, index.d)
    return version


def load_tree(spark: SparkSession, path: str, spec: FilterSpec | None = None) -> TreeIndex:
    m = _newest(spark, path)
    found = _spec(m)
    if m["kind"] != "tree" or spec and spec.spec_id != found.spec_id:
        raise ValueError(f"{path} holds a {m['kind']} of {found.spec_id}")
    at = f"{path}/v{m['version']}"
    return TreeIndex(spark.read.parquet(f"{at}/nodes"), spark.read.parquet(f"{at}/words").drop("level"), found, m["d"])

"""A Python data source over a saved pack: `where element = x` (or `in`) becomes a probe of the index.

An index answers for given elements only. So a read whose elements aren't bound by `=` or `in` is an error, not an empty
table; conditions joined by `or` that Spark does not hand on are such a read. Positions are hashed on the reader's side
by the linear and md5 families, which need no JVM. Paths have to be readable by pyarrow on the reader. Load the source
anew for each read: Spark keeps what the last condition on a loaded table left, for a later read without any.
"""

from __future__ import annotations

import hashlib
import json
from functools import reduce
from operator import and_

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualNullSafe, EqualTo, In, InputPartition


def python_positions(element: int, family: str, k: int, m: int, seeds: list[int]) -> list[int]:
    if family == "linear_odd":
        return [(a % m) * (element % m) % m for a in seeds]
    if family == "mod_identity":
        return [element % m]
    if family == "md5_double":
        digest = hashlib.md5(str(element).encode()).hexdigest()
        first, second = int(digest[:15], 16) % m, int(digest[16:31], 16) % m
        return [(first + i * second) % m for i in range(k)]
    raise ValueError(f"family {family} has no form outside Spark")


def newest(path: str) -> dict:
    import pyarrow.dataset as ds

    rows = ds.dataset(f"{path}/manifest", format="parquet").to_table().to_pylist()
    return json.loads(max(rows, key=lambda r: r["version"])["manifest"])


class PackLookup:
    """A saved pack, opened once: its newest spec, its files' footers, and the slots of blocks that probes came to."""

    def __init__(self, path: str, most_blocks: int = 20_000):
        import pyarrow.dataset as ds

        self.spec = newest(path)
        at = f"{path}/v{self.spec['version']}"
        self.slices, self.slots = ds.dataset(f"{at}/slices", format="parquet"), ds.dataset(f"{at}/slots", format="parquet")
        self.most_blocks, self.blocks = most_blocks, {}

    def lanes(self, blocks: list[int]) -> dict[int, list[tuple[int, int]]]:
        """(lane, filter_id) of the filters in use, for each block."""
        import pyarrow.dataset as ds

        if len(self.blocks) > self.most_blocks:
            self.blocks.clear()
        new = [b for b in blocks if b not in self.blocks]
        if new:
            self.blocks.update((b, []) for b in new)
            for r in self.slots.to_table(filter=ds.field("block_id").isin(new) & ds.field("in_use")).to_pylist():
                self.blocks[r["block_id"]].append((r["lane"], r["filter_id"]))
        return {b: self.blocks[b] for b in blocks}

    def search(self, elements: list[int]) -> list[tuple[int, int]]:
        """(element, filter_id); the slices of all elements are read at once."""
        import pyarrow.dataset as ds

        spec = self.spec
        spots = {x: sorted(set(python_positions(x, spec["family"], spec["k"], spec["m"], spec["seeds"]))) for x in elements}
        words: dict[int, dict[int, int]] = {}
        for r in self.slices.to_table(filter=ds.field("pos").isin(sorted({p for s in spots.values() for p in s}))).to_pylist():
            words.setdefault(r["pos"], {})[r["block_id"]] = r["word"]
        out = []
        for x, at in spots.items():
            blocks = set.intersection(*(set(words.get(p, ())) for p in at))
            left = {b: reduce(and_, (words[p][b] for p in at)) for b in blocks}
            left = {b: w for b, w in left.items() if w}
            for b, held in self.lanes(list(left)).items():
                out += [(x, filter_id) for lane, filter_id in held if left[b] >> lane & 1]
        return out


class WordLookup:
    """A pack saved by `save_words`, opened once: its words are mapped, and filter ids stand in order of slot."""

    def __init__(self, path: str):
        import glob
        import os

        import numpy as np
        import pyarrow.dataset as ds

        self.spec = newest(path)
        at = f"{path}/v{self.spec['version']}"
        slots = ds.dataset(f"{at}/slots", format="parquet").to_table(columns=["slot", "filter_id"]).sort_by("slot")
        self.ids = slots.column("filter_id").to_numpy()
        files = {int(os.path.basename(f).removesuffix(".npy")): f for f in glob.glob(f"{glob.escape(at)}/words/*.npy")}
        self.parts = [(64 * block, np.asarray(np.load(files[block], mmap_mode="r"))) for block in sorted(files)]

    def search(self, elements: list[int]) -> list[tuple[int, int]]:
        """(element, filter_id), part by part the AND of an element's rows of words."""
        import numpy as np

        spec, out = self.spec, []
        for x in dict.fromkeys(elements):
            at = python_positions(x, spec["family"], spec["k"], spec["m"], spec["seeds"])
            for first, words in self.parts:
                left = np.bitwise_and.reduce(words[at])
                for block in np.flatnonzero(left).tolist():
                    word = int(left[block])
                    while word:
                        low = word & -word
                        out.append((x, int(self.ids[first + 64 * block + low.bit_length() - 1])))
                        word ^= low
        return out


_opened: dict[str, PackLookup | WordLookup] = {}


def opened(path: str) -> PackLookup | WordLookup:
    """One lookup for each Python worker and saved pack; a path that is written again later needs a new worker."""
    if path not in _opened:
        _opened[path] = WordLookup(path) if newest(path)["kind"] == "words" else PackLookup(path)
    return _opened[path]


class ElementPartition(InputPartition):
    def __init__(self, elements: list[int]):
        self.elements = elements


class PackReader(DataSourceReader):
    def __init__(self, path: str, at_once: int = 64):
        self.path, self.at_once, self.elements = path, at_once, None

    def pushFilters(self, filters):
        for f in filters:
            if isinstance(f, (EqualTo, EqualNullSafe, In)) and f.attribute == ("element",):
                asked = {x for x in (f.value if isinstance(f, In) else (f.value,)) if x is not None}
                self.elements = asked if self.elements is None else self.elements & asked
            yield f  # Spark checks again

    def partitions(self):
        if self.elements is None:
            raise ValueError("the index answers for given elements: bind `element` by = or in")
        asked = sorted(self.elements)
        return [ElementPartition(asked[k : k + self.at_once]) for k in range(0, len(asked), self.at_once)] or [ElementPartition([])]

    def read(self, partition):
        yield from PackLookup(self.path).search(partition.elements) if partition.elements else ()


class FilterFleetSource(DataSource):
    @classmethod
    def name(cls):
        return "filterfleet"

    def schema(self):
        return "element bigint, filter_id bigint"

    def reader(self, schema):
        return PackReader(self.options["path"].removeprefix("file://"))


def lookup(spark: SparkSession, path: str, elements: list[int]):
    """(element, filter_id) of the elements, by a table that is loaded for this read alone."""
    from pyspark.sql import functions as F

    register(spark)
    return spark.read.format("filterfleet").option("path", path).load().where(F.col("element").isin(elements))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(FilterFleetSource)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")

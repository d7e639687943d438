"""Experiments: sweeps of one parameter at a time, each setting built and measured in the memory of one task.

The settings of a sweep are rows, so a cluster runs them side by side; inside a task everything is sequential and in
memory, which is the setup that published costs and times refer to. The sets are those of a collection of the given
tables, or synthetic ones of the published kinds; a setting's sets have to fit in its task. Distributed runs of the
same searches are queries of the catalogue (`curve_*` there are distributed and have SQL).
"""

from __future__ import annotations

import time
from dataclasses import asdict, dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from filterfleet.functions.params import FilterSpec, expected_fp
from filterfleet.operators.grow import ShardTree, nearest_chain
from filterfleet.operators.tree import ideal_cost


@dataclass(frozen=True)
class Setting:
    """The default parameters of the experiments.

    collection: a collection of the given tables; then n_filters is how many of its sites are taken (0: all), n is what
    its sites hold, and n_exp is scaled by its number of elements, 100,000 being the number that the defaults stand for
    (scaled=False: taken as it is).
    Searches are dealt to `runs` runs, and times are means of the last `keep` of them.
    """

    n_filters: int = 1000
    d: int = 2
    n_exp: int = 10_000
    n: int = 100
    target_fp: float = 0.01
    construction: str = "iterative"
    metric: str = "hamming"
    distribution: str = "nonrandom"
    saturation_rule: bool = True
    after_update: bool = False
    family: str = "mixing"
    probes: int = 5000
    runs: int = 10
    keep: int = 5
    maintained: int = 100
    seed: int = 7
    collection: str = ""
    tree_only: bool = False
    scaled: bool = True


def _mix(x: np.ndarray, salt: int) -> np.ndarray:
    x = x.astype(np.uint64) + np.uint64(salt * 0x9E3779B97F4A7C15 % (1 << 64))
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
    return x ^ (x >> np.uint64(31))


def spots(elements: np.ndarray, spec: FilterSpec, family: str) -> np.ndarray:
    """(elements, k) positions."""
    if family == "linear_odd":
        return np.stack([(a % spec.m) * (elements % spec.m) % spec.m for a in spec.seeds], axis=1)
    return np.stack([(_mix(elements, i + 1) % np.uint64(spec.m)).astype(np.int64) for i in range(spec.k)], axis=1)


def element_sets(s: Setting) -> list[np.ndarray]:
    rng = np.random.default_rng(s.seed)
    if s.distribution == "nonrandom":
        return [np.arange(i * s.n, (i + 1) * s.n) for i in range(s.n_filters)]
    domain, width = s.n_filters * s.n, 10 * s.n
    starts = rng.integers(0, max(1, domain - width), s.n_filters)
    return [np.unique(a + rng.integers(0, width, s.n)) for a in starts]


def filter_row(elements: np.ndarray, spec: FilterSpec, family: str) -> np.ndarray:
    row, at = np.zeros(spec.words, np.uint64), spots(elements, spec, family).ravel()
    np.bitwise_or.at(row, at // 64, np.uint64(1) << (at % 64).astype(np.uint64))
    return row


def sets_of(members: pd.DataFrame, n_filters: int) -> list[np.ndarray]:
    """The elements of each site, in order of the sites' ids; of the first n_filters sites (0: of all)."""
    members = members.sort_values(["site_id", "element"], kind="stable")
    cuts = np.flatnonzero(np.diff(members.site_id.to_numpy())) + 1
    sets = np.split(members.element.to_numpy(), cuts) if len(members) else []
    return sets[: n_filters or None]


class MemoryPack:
    """Slices of blocks side by side: one row of words a position. Room for blocks doubles when it is used up."""

    def __init__(self, rows: np.ndarray, m: int):
        self.m, self.blocks, self.slot_of, self.used = m, 0, {}, []
        self.room = np.zeros((m, max(1, -(-len(rows) // 64))), np.uint64)
        for key, row in enumerate(rows):
            self.insert(key, row)

    def _set(self, slot: int, row: np.ndarray) -> None:
        bits = np.flatnonzero(np.unpackbits(row.view(np.uint8), bitorder="little")[: self.m])
        self.room[bits, slot // 64] |= np.uint64(1) << np.uint64(slot % 64)

    def insert(self, key: int, row: np.ndarray) -> None:
        """Takes the first free slot; without one, a new block."""
        block = next((b for b in range(self.blocks - 1, -1, -1) if self.used[b] != (1 << 64) - 1), self.blocks)
        if block == self.blocks:
            if block == self.room.shape[1]:
                self.room = np.concatenate([self.room, np.zeros_like(self.room)], axis=1)
            self.blocks += 1
            self.used.append(0)
        lane = (~self.used[block] & (self.used[block] + 1)).bit_length() - 1
        self.used[block] |= 1 << lane
        self.slot_of[key] = slot = 64 * block + lane
        self._set(slot, row)

    def delete(self, key: int) -> None:
        """Clears the filter's lane; a block that held it alone goes, and later slots move down by 64."""
        block, lane = divmod(self.slot_of.pop(key), 64)
        self.used[block] &= ~(1 << lane)
        if self.used[block]:
            self.room[:, block] &= ~(np.uint64(1) << np.uint64(lane))
            return
        self.room[:, block : self.blocks - 1] = self.room[:, block + 1 : self.blocks]
        self.blocks -= 1
        self.room[:, self.blocks] = 0
        del self.used[block]
        self.slot_of = {k: s - 64 if s >= 64 * (block + 1) else s for k, s in self.slot_of.items()}

    def update(self, key: int, row: np.ndarray) -> None:
        self._set(self.slot_of[key], row)

    def search(self, at: np.ndarray) -> np.ndarray:
        """Slots that have all positions."""
        hits = np.bitwise_and.reduce(self.room[np.unique(at), : self.blocks], axis=0)
        return np.flatnonzero(np.unpackbits(hits.view(np.uint8), bitorder="little"))


class MemoryList:
    """The baseline: rows of words in a list, every one of them tested."""

    def __init__(self, rows: np.ndarray):
        self.rows, self.place = np.concatenate([rows, np.zeros((max(64, len(rows) // 8), rows.shape[1]), np.uint64)]), {k: k for k in range(len(rows))}
        self.keys = list(range(len(rows)))

    def insert(self, key: int, row: np.ndarray) -> None:
        if len(self.keys) == len(self.rows):
            self.rows = np.concatenate([self.rows, np.zeros_like(self.rows)])
        self.place[key] = len(self.keys)
        self.rows[len(self.keys)] = row
        self.keys.append(key)

    def delete(self, key: int) -> None:
        """The last row takes the place of the one that goes."""
        at, last = self.place.pop(key), self.keys.pop()
        if last != key:
            self.rows[at], self.keys[at], self.place[last] = self.rows[len(self.keys)], last, at

    def update(self, key: int, row: np.ndarray) -> None:
        self.rows[self.place[key]] |= row

    def search(self, at: np.ndarray) -> np.ndarray:
        word, mask = at // 64, np.uint64(1) << (at % 64).astype(np.uint64)
        return np.flatnonzero(((self.rows[: len(self.keys), word] & mask) == mask).all(axis=1))


def timed_runs(fn, items: list, runs: int, keep: int) -> tuple[list, float]:
    """(results of all items, mean milliseconds of an item): items are dealt to `runs` runs, the last `keep` of them count."""
    results, spent = [], []
    for part in np.array_split(np.arange(len(items)), max(1, min(runs, len(items)))):
        began = time.perf_counter()
        results += [fn(items[i]) for i in part]
        spent.append((time.perf_counter() - began, len(part)))
    return results, 1000 * sum(t for t, _ in spent[-keep:]) / max(1, sum(n for _, n in spent[-keep:]))


def measure(s: Setting, members: pd.DataFrame | None = None) -> dict[str, float]:
    """All measures of one setting; members: (site_id, element) where the setting names a collection."""
    sets, out = element_sets(s) if members is None else sets_of(members, s.n_filters), {}
    if not sets:
        return {"filters": 0.0}
    everything = np.unique(np.concatenate(sets))
    spec = FilterSpec(s.n_exp if members is None or not s.scaled else max(1, round(s.n_exp * len(everything) / 100_000)), s.target_fp)
    rows = np.stack([filter_row(x, spec, s.family) for x in sets])
    start = np.stack([filter_row(x[: len(x) // 2], spec, s.family) for x in sets]) if s.after_update else rows
    began = time.perf_counter()
    tree = ShardTree(spec.words, s.d, s.metric, s.saturation_rule, spec.m)
    order = nearest_chain(start, s.metric) if s.construction == "bulk" else range(len(start))
    for i in order:
        tree.insert(i, start[i], rightmost=s.construction == "bulk")
    out["build_s"], n = time.perf_counter() - began, len(sets)
    pack, plain = (None, None) if s.tree_only else (MemoryPack(start, spec.m), MemoryList(start))
    if s.after_update:
        for i in range(n):
            for index in (tree, pack, plain):
                index.update(i, rows[i])
    rng = np.random.default_rng(s.seed + 1)
    asked = rng.integers(0, n, s.probes)
    at = list(spots(np.array([sets[i][rng.integers(0, len(sets[i]))] for i in asked]), spec, s.family))
    by_tree, out["tree_ms"] = timed_runs(tree.search, at, s.runs, s.keep)
    out["found"] = float(all(i in set(r[0]) for i, r in zip(asked.tolist(), by_tree)))
    out["bf_cost"] = float(np.mean([c for _, c in by_tree]))
    out["mean_matches"] = float(np.mean([len(r) for r, _ in by_tree]))
    if not s.tree_only:
        by_pack, out["pack_ms"] = timed_runs(pack.search, at, s.runs, s.keep)
        by_scan, out["scan_ms"] = timed_runs(plain.search, at, s.runs, s.keep)
        out["agree"] = float(all(a[0] == b.tolist() == c.tolist() for a, b, c in zip(by_tree, by_pack, by_scan)))
    out["filters"], out["elements"], out["m"], out["k"] = float(n), float(len(everything)), float(spec.m), float(spec.k)
    out["ideal_low"], out["ideal_high"] = ideal_cost(max(n, 2), s.d), ideal_cost(max(n, 2), 2 * s.d)
    live = tree.order()
    out["nodes"], out["height"] = float(len(live)), float(tree.level[tree.root])
    out["tree_bytes"], out["scan_bytes"], out["pack_bytes"] = len(live) * spec.m / 8, n * spec.m / 8, -(-n // 64) * 64 * spec.m / 8
    out["root_fp"] = float((np.bitwise_count(tree.bits[tree.root]).sum() / spec.m) ** spec.k)
    out["root_fp_analytic"] = expected_fp(len(everything), spec.m, spec.k)

    fresh = [filter_row(np.arange(len(x)) + int(x.max()) + 1 + 10**7, spec, s.family) for x in sets[: s.maintained]]
    keys, old = list(range(n, n + len(fresh))), list(range(len(fresh)))
    for name, index in (("tree", tree), *((("pack", pack), ("scan", plain)) if not s.tree_only else ())):
        inserted, out[f"{name}_insert_ms"] = timed_runs(lambda p: index.insert(*p), list(zip(keys, fresh)), s.runs, s.keep)  # noqa: B023
        updated, out[f"{name}_update_ms"] = timed_runs(lambda p: index.update(*p), list(zip(old, fresh)), s.runs, s.keep)  # noqa: B023
        deleted, out[f"{name}_delete_ms"] = timed_runs(index.delete, keys, s.runs, s.keep)
        if name == "tree":
            for op, costs in (("insert", inserted), ("update", updated), ("delete", deleted)):
                out[f"{op}_bf_cost"] = float(np.mean(costs))
    return out


def run_settings(spark: SparkSession, settings: list[Setting], sf_dir: str | None = None) -> DataFrame:
    """(the setting's columns, measure, result), one task a setting; sf_dir: where the tables of collections are."""
    from pyspark.sql import functions as F

    from filterfleet.sources.collections import collection

    numbered = [(i, s.collection) for i, s in enumerate(settings)]
    asked = spark.createDataFrame(numbered, "run long, collection string")
    members = spark.createDataFrame([(i, "", None, None) for i, c in numbered if not c], "run long, collection string, site_id long, element long")
    for name in sorted({c for _, c in numbered if c}):
        rows = collection(spark, sf_dir, name).select(F.lit(name).alias("collection"), "site_id", "element")
        members = members.unionByName(rows.join(F.broadcast(asked), "collection").select(*members.columns))  # a row for each setting
    names = list(asdict(Setting()))

    def one(part: pd.DataFrame) -> pd.DataFrame:
        s = settings[int(part.run.iloc[0])]
        found = measure(s, part[["site_id", "element"]].dropna().astype("int64") if s.collection else None)
        return pd.DataFrame([asdict(s) | {"measure": k, "result": float(v)} for k, v in found.items()])[[*names, "measure", "result"]]

    kinds = {int: "long", float: "double", str: "string", bool: "boolean"}
    schema = ", ".join(f"{k} {kinds[type(v)]}" for k, v in asdict(Setting()).items()) + ", measure string, result double"
    return members.groupBy("run").applyInPandas(one, schema)


#: Experiment -> the collection, the parameter that varies, its values, and what else differs from the defaults.
EXPERIMENTS: dict[str, tuple[str, str, list, dict]] = {
    "filters": ("order", "n_filters", [100, 1000, 10_000], {}),
    "order": ("cust", "d", [2, 3, 4, 5, 8, 10, 16], {"n_filters": 1000}),
    "filter_size": ("cust", "n_exp", [100, 1000, 10_000, 100_000], {"n_filters": 1000}),
    "target": ("cust", "target_fp", [1e-7, 1e-5, 1e-3, 0.01, 0.1], {"n_filters": 1000}),
    "metric": ("part", "metric", ["hamming", "jaccard", "cosine"], {"n_filters": 1000}),
    "construction": ("cust", "construction", ["iterative", "bulk"], {"n_filters": 1000}),
    "saturation_rule": ("order", "saturation_rule", [True, False], {"n_filters": 10_000}),
    "after_update": ("cust", "after_update", [False, True], {"n_filters": 1000}),
    "family": ("cust", "family", ["mixing", "linear_odd"], {"n_filters": 1000}),
    "distribution": ("", "distribution", ["nonrandom", "random"], {}),
    "set_size": ("", "n", [10, 100, 300, 1000], {}),
    "maintenance": ("cust", "n_filters", [100, 300, 1000], {"probes": 500}),
}


#: The experiments on synthetic sets, where tables are given: a collection stands for each kind or size of sets.
ON_TABLES: dict[str, tuple[str, list, dict]] = {
    "distribution": ("collection", ["cust", "part"], {"n_filters": 1000}),
    "set_size": ("collection", ["block10", "block100", "block1000"], {"n_filters": 1000, "scaled": False}),
}


def sweep(spark: SparkSession, experiment: str, values: list | None = None, sf_dir: str | None = None, **changes) -> DataFrame:
    """(experiment, collection, value, measure, result) of a sweep; collection="" takes the synthetic sets instead."""
    from pyspark.sql import functions as F

    of, name, usual, others = EXPERIMENTS[experiment]
    if sf_dir and not of and "collection" not in changes:
        name, usual, others = ON_TABLES[experiment]
    settings = [replace(Setting(), **({"collection": of} | others | changes | {name: v})) for v in values or usual]
    return run_settings(spark, settings, sf_dir).select(F.lit(experiment).alias("experiment"), "collection", F.col(name).cast("string").alias("value"), "measure", "result")

"""Sequential growth and upkeep of union-filter trees, one shard a task.

Placing a filter depends on all placements before it, so a tree grows in one task; a large collection is a forest of
shards, each grown by itself. A tree here is a table of rows in numpy (bits) beside plain lists (parent, children), and
every operation keeps a count of the nodes it read or changed.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F

from filterfleet.functions.params import FilterSpec
from filterfleet.operators.filters import to_dense
from filterfleet.operators.tree import TreeIndex, order_filters


def bit_counts(words: np.ndarray) -> np.ndarray:
    return np.bitwise_count(words).sum(axis=-1, dtype=np.int64)


def distances(rows: np.ndarray, one: np.ndarray, metric: str) -> np.ndarray:
    """Distance of each row of words to one filter."""
    if metric == "hamming":
        return bit_counts(rows ^ one).astype(float)
    both, a, b = bit_counts(rows & one), bit_counts(rows), bit_counts(one)
    if metric == "jaccard":
        either = a + b - both
        return np.where(either > 0, 1 - both / np.maximum(either, 1), 0.0)
    if metric == "cosine":
        return np.where((a > 0) & (b > 0), 1 - both / np.sqrt(np.maximum(a * b, 1).astype(float)), np.where((a == 0) & (b == 0), 0.0, 1.0))
    raise ValueError(f"unknown metric {metric}")


class ShardTree:
    def __init__(self, n_words: int, d: int = 2, metric: str = "hamming", saturation_rule: bool = False, m: int | None = None):
        self.d, self.metric, self.rule, self.m = d, metric, saturation_rule, m or 64 * n_words
        self.bits = np.zeros((64, n_words), np.uint64)
        self.parent: list[int] = []
        self.kids: list[list[int]] = []
        self.level: list[int] = []
        self.leaf_of: dict[int, int] = {}
        self.id_of: dict[int, int] = {}
        self.root = -1
        self.touched: set[int] = set()

    def _node(self, level: int, words: np.ndarray | None = None) -> int:
        node = len(self.parent)
        if node == len(self.bits):
            self.bits = np.concatenate([self.bits, np.zeros_like(self.bits)])
        self.bits[node] = 0 if words is None else words
        self.parent.append(-1)
        self.kids.append([])
        self.level.append(level)
        return node

    def _adopt(self, node: int, kids: list[int]) -> None:
        self.kids[node] = kids
        for kid in kids:
            self.parent[kid] = node
        self.bits[node] = np.bitwise_or.reduce(self.bits[kids], axis=0)
        self.touched.update(kids, [node])

    def _saturated(self, node: int) -> bool:
        return int(bit_counts(self.bits[node])) >= self.m

    def insert(self, filter_id: int, words: np.ndarray, rightmost: bool = False) -> int:
        """Places a filter beside its nearest leaf (or the right-most one); returns how many nodes were accessed."""
        if filter_id in self.leaf_of:
            raise ValueError(f"filter {filter_id} is there already")
        self.touched = set()
        leaf = self._node(0, words)
        self.leaf_of[filter_id], self.id_of[leaf] = leaf, filter_id
        self.touched.add(leaf)
        if self.root < 0:
            self.root = self._node(1)
            self._adopt(self.root, [leaf])
            return len(self.touched)
        at = self.root
        while self.level[at] > 0:
            self.bits[at] |= words
            kids = self.kids[at]
            self.touched.update([at] if rightmost else [at, *kids])
            at, above = (kids[-1] if rightmost else kids[int(np.argmin(distances(self.bits[kids], words, self.metric)))]), at
        fresh, beside = leaf, at
        while True:  # put `fresh` after `beside`; an overfull node gives its last d children away, which may go on upwards
            kids = self.kids[above]
            kids.insert(kids.index(beside) + 1, fresh)
            self.parent[fresh] = above
            self.touched.add(above)
            if len(kids) <= 2 * self.d or self.rule and self._saturated(above):
                return len(self.touched)
            pieces = []
            while len(kids) > 2 * self.d:  # more than one cut only where a full node was left unsplit before
                pieces.append(kids[-self.d :])
                kids = kids[: -self.d]
            self._adopt(above, kids)
            siblings = []
            for piece in reversed(pieces):
                node = self._node(self.level[above])
                self._adopt(node, piece)
                siblings.append(node)
            if above == self.root:
                self.root = self._node(self.level[above] + 1)
                self._adopt(self.root, [above, *siblings])
                return len(self.touched)
            upper = self.parent[above]
            for before, node in zip([above, *siblings], siblings[:-1]):
                self.kids[upper].insert(self.kids[upper].index(before) + 1, node)
                self.parent[node] = upper
            fresh, beside, above = siblings[-1], ([above, *siblings])[-2], upper

    def update(self, filter_id: int, words: np.ndarray) -> int:
        """ORs new bits into a filter and all nodes above it."""
        at, n = self.leaf_of[filter_id], 0
        while at >= 0:
            self.bits[at] |= words
            at, n = self.parent[at], n + 1
        return n

    def delete(self, filter_id: int) -> int:
        """Takes a filter out; a node left with too few children borrows from a sibling or joins it."""
        if filter_id not in self.leaf_of:
            raise KeyError(f"no filter {filter_id}")
        gone = self.leaf_of.pop(filter_id)
        del self.id_of[gone]
        self.touched, node = {gone}, self.parent[gone]
        self.kids[node].remove(gone)
        self.parent[gone] = -1
        while node != self.root and len(self.kids[node]) < self.d:
            upper = self.parent[node]
            row = self.kids[upper]
            place = row.index(node)
            near = row[place - 1] if place else row[1]
            mine, theirs = self.kids[node], self.kids[near]
            self.touched.update([node, near, upper])
            move = (len(theirs) - len(mine)) // 2
            if len(theirs) > self.d and move:
                if place:
                    self._adopt(node, theirs[-move:] + mine)
                    self._adopt(near, theirs[:-move])
                else:
                    self._adopt(node, mine + theirs[:move])
                    self._adopt(near, theirs[move:])
                break
            self._adopt(near, theirs + mine if place else mine + theirs)
            row.remove(node)
            self.parent[node], self.kids[node] = -1, []
            node = upper
        while node >= 0:
            kids = self.kids[node]
            self.bits[node] = np.bitwise_or.reduce(self.bits[kids], axis=0) if kids else 0
            self.touched.update([node, *kids])
            node = self.parent[node]
        while self.level[self.root] > 1 and len(self.kids[self.root]) == 1:
            self.root = self.kids[self.root][0]
            self.parent[self.root] = -1
        if not self.kids[self.root]:
            self.root = -1
        return len(self.touched)

    def replace(self, filter_id: int, words: np.ndarray) -> int:
        """Takes a filter out and places its new value afresh; returns how many nodes were accessed."""
        return self.delete(filter_id) + self.insert(filter_id, words)

    def search(self, spots: np.ndarray) -> tuple[list[int], int]:
        """Filters that have all of a probe's positions, and the number of nodes tested."""
        if self.root < 0:
            return [], 0
        word, mask = spots // 64, np.uint64(1) << (spots % 64).astype(np.uint64)
        level, tested, found = np.array([self.root]), 0, []
        while len(level):
            tested += len(level)
            hits = level[((self.bits[level[:, None], word] & mask) == mask).all(axis=1)]
            found += [self.id_of[n] for n in hits.tolist() if n in self.id_of]
            level = np.array([k for n in hits.tolist() for k in self.kids[n]], dtype=np.int64)
        return sorted(found), tested

    def order(self) -> list[int]:
        """Live nodes, level by level from the left, leaves first."""
        rows = [[self.root]] if self.root >= 0 else []
        while rows and any(self.kids[n] for n in rows[-1]):
            rows.append([k for n in rows[-1] for k in self.kids[n]])
        return [n for row in reversed(rows) for n in row]

    def frames(self, tree_id: int) -> tuple[pd.DataFrame, np.ndarray]:
        nodes = self.order()
        number = {n: i for i, n in enumerate(nodes)}
        rows = [(tree_id, i, number.get(self.parent[n]) if n != self.root else None, self.level[n], self.kids[self.parent[n]].index(n) if n != self.root else 0, len(self.kids[n]), self.id_of.get(n)) for i, n in enumerate(nodes)]
        return pd.DataFrame(rows, columns=["tree_id", "node_id", "parent_id", "level", "child_ord", "n_children", "filter_id"]), self.bits[nodes]


def nearest_chain(bits: np.ndarray, metric: str = "hamming") -> list[int]:
    """Rows in the order of a chain of nearest neighbours that starts at the row nearest to the empty filter."""
    left, chain, last = np.arange(len(bits)), [], np.zeros(bits.shape[1], np.uint64)
    while len(left):
        k = int(np.argmin(distances(bits[left], last, metric)))
        chain.append(int(left[k]))
        last = bits[chain[-1]]
        left = np.delete(left, k)
    return chain


GROWN = "tree_id int, node_id long, parent_id long, level int, child_ord int, n_children int, filter_id long, accessed long, words array<long>"


#: Bytes of filters that one task grows a tree from, unless a caller says otherwise.
SHARD_BYTES = 256 << 20


def shard_count(filter_words: DataFrame, spec: FilterSpec, shard_bytes: int = SHARD_BYTES) -> int:
    """Shards that hold at most about shard_bytes of dense filters each."""
    n = filter_words.select("filter_id").distinct().count()
    return max(1, -(-n * spec.words * 8 // shard_bytes))


def shard_numbers(filter_words: DataFrame, shards: int, by: str = "hash") -> DataFrame:
    """(filter_id, tree_id): filters dealt by the hash of their id, or (by: ones, first, minhash) to shards that follow one
    another in such an order, so that a tree holds filters that are alike and more trees turn a probe away at the root."""
    if by == "hash":
        return filter_words.select("filter_id").distinct().withColumn("tree_id", F.pmod(F.xxhash64("filter_id"), F.lit(shards)).cast("int"))
    placed = order_filters(filter_words, by)
    n = placed.count()
    return placed.select("filter_id", F.least(F.expr(f"place * {shards} div {max(n, 1)}"), F.lit(shards - 1)).cast("int").alias("tree_id"))


def dense_shards(filter_words: DataFrame, spec: FilterSpec, numbers: DataFrame) -> DataFrame:
    """(tree_id, filter_id, words) of the filters in numbers (filter_id, tree_id)."""
    return to_dense(filter_words, spec).join(numbers, "filter_id").select("tree_id", "filter_id", "words")


def grow(
    filter_words: DataFrame,
    spec: FilterSpec,
    d: int = 2,
    metric: str = "hamming",
    saturation_rule: bool = False,
    method: str = "greedy",
    shards: int | None = None,
    deletes: DataFrame | None = None,
    updates: DataFrame | None = None,
    shard_by: str = "hash",
) -> TreeIndex:
    """A forest with one tree for each shard, its filters inserted by ascending id (or along their nearest chain).

    method: greedy (beside the nearest leaf) or chain (the sorted load with its exact order). deletes: filter_id to take
    out again; updates: (filter_id, word_ix, word) of filters in filter_words to OR in first. A shard has to fit in one task: bits / 8 bytes for each of
    its filters and up to as much again for the nodes above; by default there are as many shards as SHARD_BYTES asks for.
    """
    from filterfleet.functions.frames import checkpointed

    shards = shards or shard_count(filter_words, spec)
    numbers = checkpointed(shard_numbers(filter_words, shards, shard_by))
    n_words, m = spec.words, spec.m
    rows = dense_shards(filter_words, spec, numbers).withColumn("op", F.lit(0))
    if updates is not None:
        rows = rows.unionByName(dense_shards(updates, spec, numbers).withColumn("op", F.lit(1)))
    if deletes is not None:
        gone = deletes.join(numbers, "filter_id").select("tree_id", "filter_id", F.array().cast("array<bigint>").alias("words"), F.lit(2).alias("op"))
        rows = rows.unionByName(gone)

    def build(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["op", "filter_id"], kind="stable").reset_index(drop=True)
        tree, accessed = ShardTree(n_words, d, metric, saturation_rule, m), {}
        base = frame[frame.op == 0]
        bits = np.stack([np.asarray(w, np.int64) for w in base.words]).view(np.uint64) if len(base) else np.empty((0, n_words), np.uint64)
        places = nearest_chain(bits, metric) if method == "chain" else range(len(base))
        ids = base.filter_id.tolist()
        for k in places:
            accessed[ids[k]] = tree.insert(ids[k], bits[k], rightmost=method == "chain")
        for filter_id, words in frame[frame.op == 1][["filter_id", "words"]].itertuples(index=False):
            accessed[filter_id] = tree.update(filter_id, np.asarray(words, np.int64).view(np.uint64))
        for filter_id in frame[frame.op == 2].filter_id:
            tree.delete(filter_id)
        nodes, values = tree.frames(int(frame.tree_id.iloc[0]))
        nodes["accessed"] = [accessed.get(f) for f in nodes.filter_id]
        nodes["words"] = list(values.view(np.int64))
        return nodes.astype({c: "Int64" for c in ("parent_id", "filter_id", "accessed")})

    grown = checkpointed(rows.groupBy("tree_id").applyInPandas(build, GROWN))
    words = grown.select("tree_id", "node_id", F.posexplode("words").alias("word_ix", "word")).where("word <> 0")
    index = TreeIndex(grown.drop("accessed", "words"), words, spec, d)
    index.accessed = grown.where("filter_id is not null").select("filter_id", "accessed")
    return index


def shard_search(filter_words: DataFrame, probe_spots: DataFrame, spec: FilterSpec, d: int = 2, metric: str = "hamming", shards: int | None = None, saturation_rule: bool = False) -> DataFrame:
    """(query_id, tree_id, filter_ids, nodes_checked): each shard's tree in the memory of a task, all probes asked of it.

    probe_spots: (query_id, spots); probes are a bounded batch and go to every shard.
    """
    n_words, m = spec.words, spec.m
    shards = shards or shard_count(filter_words, spec)
    asked = probe_spots.join(F.broadcast(probe_spots.sparkSession.range(shards).select(F.col("id").cast("int").alias("tree_id"))), F.lit(True))  # each shard answers all

    def answer(key, filters: pd.DataFrame, probes: pd.DataFrame) -> pd.DataFrame:
        tree = ShardTree(n_words, d, metric, saturation_rule, m)
        for filter_id, words in filters.sort_values("filter_id")[["filter_id", "words"]].itertuples(index=False):
            tree.insert(filter_id, np.asarray(words, np.int64).view(np.uint64))
        out = [(q, key[0], *tree.search(np.asarray(s, np.int64))) for q, s in probes[["query_id", "spots"]].itertuples(index=False)]
        return pd.DataFrame(out, columns=["query_id", "tree_id", "filter_ids", "nodes_checked"])

    dealt = dense_shards(filter_words, spec, shard_numbers(filter_words, shards)).groupBy("tree_id")
    return dealt.cogroup(asked.groupBy("tree_id")).applyInPandas(answer, "query_id long, tree_id int, filter_ids array<long>, nodes_checked long")

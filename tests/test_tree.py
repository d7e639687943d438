"""The worked examples (bit strings list position 0 first), sorted load, growth, upkeep."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from filterfleet.functions.frames import numbered
from filterfleet.functions.params import FilterSpec
from filterfleet.operators import filters, grow, pack, scan, tree
from filterfleet.operators.grow import ShardTree, distances, nearest_chain
from filterfleet.sources.collections import probes, random_ranges, ranges

EIGHT = FilterSpec(1, family="mod_identity", k=1, m=64)
START = {1: "10000000", 2: "01000000", 3: "00100000", 4: "00010000", 5: "00001000", 6: "00000010"}


def row(bits):
    return np.array([sum(1 << i for i, b in enumerate(bits) if b == "1")], np.uint64)


def bits(tree_, node):
    return "".join(str(int(tree_.bits[node][0]) >> i & 1) for i in range(8))


def example():
    t = ShardTree(1, 2, m=8)
    leaves = {}
    for k, b in START.items():
        leaves[k] = t._node(0, row(b))
        t.leaf_of[k], t.id_of[leaves[k]] = leaves[k], k
    seven, eight, nine = t._node(1), t._node(1), t._node(2)
    t._adopt(seven, [leaves[k] for k in (1, 2, 3, 4)])
    t._adopt(eight, [leaves[5], leaves[6]])
    t._adopt(nine, [seven, eight])
    t.root = nine
    return t, seven, eight, nine


def under(t, node):
    return [t.id_of.get(k, k) for k in t.kids[node]]


def test_example_search():
    t, *_ = example()
    assert t.search(np.array([4])) == ([5], 5)
    assert t.search(np.array([5])) == ([], 1) and t.search(np.array([7])) == ([], 1)


def test_example_insert_splits():
    t, seven, eight, nine = example()
    t.insert(10, row("00100100"))
    eleven = t.kids[nine][1]
    assert t.root == nine and t.kids[nine] == [seven, eleven, eight]
    assert (under(t, seven), under(t, eleven), under(t, eight)) == ([1, 2, 3], [10, 4], [5, 6])
    assert [bits(t, n) for n in (seven, eleven, eight, nine)] == ["11100000", "00110100", "00001010", "11111110"]


def test_example_delete_borrows():
    t, seven, eight, nine = example()
    t.delete(5)
    assert (under(t, seven), under(t, eight)) == ([1, 2, 3], [4, 6])
    assert [bits(t, n) for n in (seven, eight, nine)] == ["11100000", "00010010", "11110010"]


def test_example_update():
    t, seven, eight, nine = example()
    assert t.update(6, row("00000011")) == 3
    assert [bits(t, n) for n in (t.leaf_of[6], eight, nine)] == ["00000011", "00001011", "11111011"]


def test_distances():
    a, b = row("11110000"), row("00100100")
    assert distances(a[None], b, "hamming")[0] == 4
    assert distances(a[None], b, "jaccard")[0] == pytest.approx(1 - 1 / 5)
    assert distances(a[None], b, "cosine")[0] == pytest.approx(1 - 1 / 8**0.5)
    zero = row("00000000")
    assert [distances(zero[None], zero, m)[0] for m in ("hamming", "jaccard", "cosine")] == [0, 0, 0]


@pytest.mark.parametrize("d", [2, 3, 4, 5, 8])
def test_closed_form_equals_appending(d):
    for n in [1, 2, 2 * d, 2 * d + 1, *range(3, 260, 17)]:
        t = ShardTree(1, d)
        for i in range(n):
            t.insert(i, row("10000000"), rightmost=True)
        by_level = {}
        for node in t.order():
            by_level[t.level[node]] = by_level.get(t.level[node], 0) + 1
        sizes = tree.level_sizes(n, d)
        assert [by_level[k] for k in sorted(by_level)] == sizes
        leaves = [x for x in t.order() if t.level[x] == 0]
        above = [x for x in t.order() if t.level[x] == 1]
        assert [above.index(t.parent[x]) for x in leaves] == [tree.parent_place(i, n, d) for i in range(n)]


@pytest.mark.parametrize("metric", ["hamming", "jaccard", "cosine"])
@pytest.mark.parametrize("rule", [False, True])
def test_random_operations_keep_the_rules(metric, rule):
    rng = np.random.default_rng(3)
    t, held = ShardTree(4, 2, metric, rule, 256), {}
    for step in range(600):
        op = rng.random()
        if op < 0.55 or not held:
            held[step] = rng.integers(0, 2**63, 4).astype(np.uint64) & rng.integers(0, 2**63, 4).astype(np.uint64)
            t.insert(step, held[step])
        elif op < 0.8:
            key = int(rng.choice(list(held)))
            t.delete(key)
            del held[key]
        else:
            key, more = int(rng.choice(list(held))), rng.integers(0, 2**63, 4).astype(np.uint64)
            held[key] = held[key] | more
            t.update(key, more)
        live = t.order()
        assert {t.id_of[x] for x in live if t.level[x] == 0} == set(held)
        for x in live:
            if t.level[x]:
                assert (t.bits[x] == np.bitwise_or.reduce(t.bits[t.kids[x]], axis=0)).all()
                assert all(t.level[k] == t.level[x] - 1 for k in t.kids[x])
                assert x == t.root or len(t.kids[x]) >= 2
                assert len(t.kids[x]) <= 4 or rule
    for key, words in held.items():
        spot = np.flatnonzero(np.unpackbits(words.view(np.uint8), bitorder="little"))[:3]
        found, _ = t.search(spot)
        assert key in found and found == sorted(k for k, w in held.items() if ((w[spot // 64] >> (spot % 64).astype(np.uint64)) & np.uint64(1)).all())


def test_edges_of_upkeep():
    t = ShardTree(1, 2)
    assert t.search(np.array([1])) == ([], 0)
    t.insert(1, row("10000000"))
    with pytest.raises(ValueError):
        t.insert(1, row("10000000"))
    with pytest.raises(KeyError):
        t.delete(9)
    t.delete(1)
    assert t.root == -1 and t.order() == []
    t.insert(2, row("01000000"))
    assert t.search(np.array([1])) == ([2], 2)


def test_chain_starts_at_the_emptiest():
    rows = np.stack([row("11110000"), row("11000000"), row("10000000")])
    assert nearest_chain(rows) == [2, 1, 0]


@pytest.mark.parametrize("sets", ["ranges", "random"])
def test_all_methods_agree(spark, sets):
    data = (ranges(spark, 70, 6) if sets == "ranges" else random_ranges(spark, 70, 6, 400)).cache()
    spec, asked = FilterSpec(40), probes(data, 7)
    words = filters.build_filters(data, spec).cache()
    truth = {tuple(r) for r in scan.exact_search(data, asked).collect()}
    base = {tuple(r) for r in scan.scan_search(filters.to_dense(words, spec), asked, spec).collect()}
    assert truth <= base  # nothing is missed
    index = pack.pack_build(data, spec)
    for found in (
        pack.pack_search(index, asked), pack.hybrid_search(index, asked), pack.wide_search(pack.to_wide(index), index, asked),
        tree.tree_search(tree.bulk_load(words, spec, 3, "minhash"), asked)[0], tree.tree_search(grow.grow(words, spec, 2, shards=3), asked)[0], tree.tree_search(grow.grow(words, spec, 2, "jaccard", True, "chain"), asked)[0],
    ):
        assert {tuple(r) for r in found.collect()} == base


def test_search_counts_and_shape(spark):
    data, spec = ranges(spark, 65, 5), FilterSpec(30)
    words = filters.build_filters(data, spec)
    for index in (tree.bulk_load(words, spec, 2), grow.grow(words, spec, 2)):
        assert tree.violations(index).count() == 0
        asked = probes(data, 5)
        counted = {r.query_id: r.nodes_checked for r in tree.counted_cost(index, asked).collect()}
        assert counted == {r.query_id: r.nodes_checked for r in tree.search_cost(tree.tree_search(index, asked)[1]).collect()}
        made = tree.shape(index).first()
        assert made.n_nodes <= 65 + 64 and all(1 <= c <= made.n_nodes for c in counted.values())


def test_update_in_halves_is_a_full_build(spark):
    data, spec = ranges(spark, 30, 6), FilterSpec(40)
    places = numbered(data.select(F.col("site_id").alias("filter_id")).distinct(), "filter_id", "place")
    half = tree.bulk_load(filters.build_filters(data.where("element % 2 = 0"), spec), spec, places=places)
    delta = filters.build_filters(data.where("element % 2 = 1"), spec)
    full = tree.bulk_load(filters.build_filters(data, spec), spec, places=places)
    once = tree.tree_update(half, delta)
    twice = tree.tree_update(once, delta)
    want = sorted(map(tuple, full.words.select("node_id", "word_ix", "word").collect()))
    assert want == sorted(map(tuple, once.words.select("node_id", "word_ix", "word").collect())) == sorted(map(tuple, twice.words.select("node_id", "word_ix", "word").collect()))


def test_numbering_is_dense_and_ordered(spark):
    rows = numbered(spark.createDataFrame([(x * x,) for x in range(50)], "k long"), "k", "n", 7).orderBy("k").collect()
    assert [r.n for r in rows] == list(range(50))

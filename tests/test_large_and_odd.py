"""Small cases of what larger or odd tables brought up, each query against its SQL on tables made for it."""

import datetime

import duckdb
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import functions as F

from filterfleet import catalogue
from filterfleet.functions.hashing import set_bits
from filterfleet.functions.params import FilterSpec
from filterfleet.operators import distance, filters, grow, pack, scan, tree
from filterfleet.plans import relational
from filterfleet.sources import index_source, index_tables, udtfs
from filterfleet.sources.collections import ranges


def same(spark, folder, name, **tables):
    """A query and its SQL on given tables, compared by how values print (0.0 is not -0.0)."""
    con = duckdb.connect()
    con.execute("set timezone = 'UTC'")
    for table, rows in tables.items():
        pq.write_table(rows, f"{folder}/{table}.parquet")
        con.execute(f"create view {table} as select * from '{folder}/{table}.parquet'")
    got = catalogue.QUERIES[name](spark, str(folder))
    found = con.execute(f"select {', '.join(sorted(got.columns))} from ({catalogue.ORACLES[name]})").fetchall()
    rows = sorted(repr(tuple(r)) for r in got.select(*sorted(got.columns)).collect())
    assert rows == sorted(map(repr, found)) and rows
    return rows


def events(seconds, users=None, kinds=None):
    start = datetime.datetime(2024, 1, 5)
    n = len(seconds)
    return pa.table(
        {
            "event_id": pa.array(range(n), pa.int64()),
            "ts": pa.array([start + datetime.timedelta(seconds=s) for s in seconds], pa.timestamp("us")),
            "user_id": pa.array(users or [1] * n, pa.int64()),
            "event_type": kinds or ["click"] * n,
            "value": [1.0] * n,
            "props": ["{}"] * n,
        }
    )


def test_rounded_zero_keeps_its_sign(spark, tmp_path):
    rows = [[-0.00001, 0.00001, -0.0, 0.3], [0.5, -0.03125, 0.03125, -1.0], [0.3], []]
    vectors = pa.table({"vec_id": pa.array(range(4), pa.int64()), "embedding": pa.array(rows, pa.list_(pa.float32())), "label": pa.array([0] * 4, pa.int32())})
    assert "-0.0" in same(spark, tmp_path, "array_functions", embeddings=vectors)[0]


def test_seconds_are_rounded_not_cut(spark, tmp_path):
    same(spark, tmp_path, "win_range_seconds", events=events([0.4, 0.5, 0.6, 1.5, 2.5, 3600.4, 3600.5, 3600.6, 3601.5, 3602.5]))


def test_many_blocks_are_searched_in_tasks(spark):
    """65 sites a block and more: found by tasks over parts of blocks are the pairs that bits by themselves give."""
    sets = ranges(spark, 1500, 4).unionByName(spark.createDataFrame([(7, 5999), (1499, 0), (None, 3), (3, None)], "site_id long, element long"))
    asked = spark.range(6000).selectExpr("cast(id as string) as query_id", "id as element").unionByName(spark.createDataFrame([("x", None), ("7", 7)], "query_id string, element long"))
    spec = FilterSpec(6)
    bits = set_bits(sets, spec).select(F.col("site_id").alias("filter_id"), "pos").distinct()
    want = sorted(map(tuple, scan.scan_search_positions(bits, asked.distinct(), spec).collect()))
    index = pack.pack_build(sets, spec)
    found = pack.pack_search(index, asked)
    assert sorted(map(tuple, found.collect())) == want and len(want) > 6000
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in plan  # no row for each probe, position and block
    assert sorted(map(tuple, pack.pack_search(pack.PackIndex(index.slices, index.slots, spec), asked.distinct()).collect())) == want


def test_candidates_are_thinned_in_tasks(spark):
    """Filters of one and of several parts, dense ones, a set that spans batches of rows, and no sets at all."""
    wide = spark.range(12_000).selectExpr("cast(-5 as bigint) as site_id", "3 * id as element")
    sets = ranges(spark, 900, 4).unionByName(wide).unionByName(spark.createDataFrame([(7, 3599), (7, 3599), (1 << 60, 0), (None, 3), (3, None)], "site_id long, element long"))
    asked = spark.range(4000).selectExpr("cast(id as string) as query_id", "id as element").unionByName(spark.createDataFrame([("x", None), ("7", 7)], "query_id string, element long"))
    for spec in (FilterSpec(6), FilterSpec(1500)):
        bits = set_bits(sets, spec).select(F.col("site_id").alias("filter_id"), "pos").distinct()
        want = sorted(map(tuple, scan.scan_search_positions(bits, asked.distinct(), spec).collect()))
        for most in (64 << 20, 1 << 17):
            found = scan.scan_search_ordered(sets, asked, spec, most)
            assert sorted(map(tuple, found.collect())) == want and len(want) > 6000
        plan = found._jdf.queryExecution().optimizedPlan().toString()
        assert "MapInArrow" in plan and "Join" not in plan  # candidates are no rows, and no bits are broadcast
    assert scan.scan_search_ordered(sets.where("site_id = 5000"), asked, spec).count() == 0


def test_lookups_map_words(spark, tmp_path):
    """Saved words give what a search of the index does, in lanes of either sign and over several parts; so does the table
    function, which maps them and reads no table for an element."""
    sets = ranges(spark, 1500, 4).unionByName(spark.createDataFrame([(7, 5999), (1499, 0), (None, 3), (3, None)], "site_id long, element long"))
    spec, keys = FilterSpec(6), [*range(0, 6100, 7), -1]
    index = pack.pack_build(sets, spec)
    asked = spark.createDataFrame([(k, k) for k in keys] + [(-2, None)], "query_id long, element long")
    want = sorted(map(tuple, pack.pack_search(index, asked).collect()))
    path = f"file://{tmp_path}/words"
    assert index_tables.save_words(index, path) == 0
    found = index_source.opened(f"{tmp_path}/words")
    assert len(found.parts) > 1
    assert sorted(found.search(keys)) == want and {f % 64 for _, f in want} == set(range(64))
    udtfs.register(spark, path)
    rows = spark.sql("select q.query_id, a.filter_id from {asked} q, lateral all_membership(q.element) a", asked=asked)
    assert sorted(map(tuple, rows.collect())) == want
    index_tables.save_words(pack.pack_build(sets.where("site_id < 0"), spec), f"{tmp_path}/none")
    assert index_source.opened(f"{tmp_path}/none").search(keys) == []


def orders(keys):
    """(o_custkey, o_orderkey) pairs."""
    return pa.table({"o_orderkey": pa.array([k for _, k in keys], pa.int64()), "o_custkey": pa.array([c for c, _ in keys], pa.int64())})


def test_ranges_are_counted_without_pairs(spark, tmp_path):
    n = 40
    found = same(spark, tmp_path, "join_range_blocks", events=events(list(range(n)), kinds=["purchase"] * n), orders=orders([(1, 0), (1, 9), (2, 9), (2, 20), (3, 5), (4, 21), (4, 30), (5, 5), (None, 3), (6, None), (7, 39)]))
    assert len(found) == 32
    plan = catalogue.QUERIES["join_range_blocks"](spark, str(tmp_path))._jdf.queryExecution().optimizedPlan().toString()
    assert "explode(sequence" not in plan and "between" not in plan


def test_pairs_of_ranges_come_from_arrays(spark, tmp_path):
    """Events of one cell that all sites' ranges hold, sites without a key, equal and negative ids."""
    ids = [3, 3, None, *range(-4, 5), 4999, 5000, 5001, 12_000]
    table = events([0] * len(ids), kinds=["purchase"] * len(ids)).set_column(0, "event_id", pa.array(ids, pa.int64()))
    same(spark, tmp_path, "join_range_whole", events=table, orders=orders([(1, -4), (1, 5000), (2, 5001), (2, 20_000), (3, 3), (None, 0), (None, 4), (4, None), (5, -3), (5, -1)]))
    plan = catalogue.QUERIES["join_range_whole"](spark, str(tmp_path))._jdf.queryExecution().optimizedPlan().toString()
    assert "explode(events" in plan  # pairs are no rows of the join
    points, spans = spark.createDataFrame([(7,)] * 250 + [(8,)], "event_id long"), spark.range(3).selectExpr("id as site_id", "id as lo", "7 as hi")
    found = relational.range_pairs(points, spans, 5000)
    assert found.groupBy("site_id").count().orderBy("site_id").collect() == [(0, 250), (1, 250), (2, 250)]
    assert relational.range_pairs(points, spans.where("hi > 7"), 5000).count() == 0


def test_measures_read_a_given_table(spark):
    for name in ("optimal_hash_count", "filter_params", "fp_curve_by_size", "ideal_cost_curve", "tree_height_bounds"):
        assert "Relation [" in catalogue.QUERIES[name](spark, "/root/testdata/sf0.001")._jdf.queryExecution().optimizedPlan().toString(), name


def test_pairs_are_counted_in_blocks(spark):
    """More filters than a block has, words with the highest bit, none in common, equal ones, ids out of order."""
    rows = [(i * 7919 % 1300, k, (i * 2654435761 * (k + 1)) % (1 << 64) - (1 << 63)) for i in range(1300) for k in range(i % 3, 3)]
    words = spark.createDataFrame([*rows, (5000, 7, 1), (5001, 7, 1), (5002, 9, -1)], "filter_id long, word_ix int, word long")
    bits = {}
    for f, k, w in words.collect():
        bits[f] = bits.get(f, 0) | (w % (1 << 64)) << 64 * k
    some = [f for f in sorted(bits) if f % 97 == 0 or f >= 5000]
    apart = lambda a, b: float((bits[a] ^ bits[b]).bit_count())
    pairs = distance.all_pairs(words, words, "hamming")
    assert pairs.count() == len(bits) * (len(bits) - 1) // 2
    assert {(r.a, r.b): r.hamming for r in pairs.where(F.col("a").isin(some) & F.col("b").isin(some)).collect()} == {(a, b): apart(a, b) for a in some for b in some if a < b}
    near = {(r.filter_id, r.neighbour): r.distance for r in distance.nearest(words, top=2).where(F.col("filter_id").isin(some)).collect()}
    assert near == {(a, b): d for a in some for d, b in sorted((apart(a, b), b) for b in bits if b != a)[:2]}
    plan = pairs._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "MapInArrow" in plan  # rows of words don't meet one by one
    one = words.where("filter_id = 5000")
    assert [tuple(r) for r in distance.all_pairs(one, words.where("filter_id > 5000"), "jaccard").orderBy("b").collect()] == [(5000, 5001, 0.0), (5000, 5002, 1.0)]
    assert distance.all_pairs(one, one).count() == distance.nearest(one).count() == 0


def test_trees_are_searched_in_parts(spark):
    """Subtrees in tasks find and count what the search by levels does: one tree, and shards of different heights."""
    spec = FilterSpec(40, 0.1)
    sets = ranges(spark, 900, 3).unionByName(spark.createDataFrame([(7, 2699), (899, 0), (1 << 60, 5)], "site_id long, element long"))
    asked = spark.range(0, 5400, 3).selectExpr("id as query_id", "id as element").unionByName(spark.createDataFrame([(-1, None)], "query_id long, element long"))
    words = filters.build_filters(sets, spec)
    numbers = words.select("filter_id").distinct().where("filter_id < 3 or filter_id > 20")
    for index in (tree.bulk_load(words, spec, 2), grow.grow(words.join(numbers, "filter_id"), spec, 2, shards=2, saturation_rule=True)):
        matches, costs = tree.tree_search(index, asked, most_pairs=1 << 60)
        want, tested = sorted(map(tuple, matches.collect())), sorted(map(tuple, tree.search_cost(costs).collect()))
        found, spent = tree.tree_search(index, asked, most_pairs=0)
        assert sorted(map(tuple, found.collect())) == want and sorted(map(tuple, tree.search_cost(spent).collect())) == tested and want
        levels = lambda c: sorted(tuple(r) for r in c.select("query_id", "level", "checked", "matched").collect())
        assert levels(spent) == levels(costs)
        local = [tuple(r) for r in tree.tree_search_local(index, asked, 1).collect()]  # parts of 64 nodes
        assert sorted((q, f) for q, f, _ in local if f is not None) == want and sorted({(q, n) for q, _, n in local}) == tested
        cost = tree.counted_cost(index, asked)
        assert sorted(map(tuple, cost.collect())) == tested
        assert "MapInArrow" in cost._jdf.queryExecution().optimizedPlan().toString()  # no row for each probe and node


def test_sweeps_read_a_given_table(spark):
    for name in ("sweep_distribution", "sweep_set_size"):
        assert "Relation [" in catalogue.QUERIES[name](spark, "/root/testdata/sf0.001")._jdf.queryExecution().optimizedPlan().toString(), name


def test_loads_are_counted_from_their_sets(spark):
    """Known sets give the costs and root that rows of words give: tiers of parts, orders, orders of the tree, odd sets."""
    spec = FilterSpec(40, 0.1)
    sets = ranges(spark, 900, 3).unionByName(spark.createDataFrame([(7, 2699), (899, 0), (1 << 60, 5), (None, 3), (3, None)], "site_id long, element long"))
    asked = spark.range(0, 5400, 3).selectExpr("id as query_id", "id as element").unionByName(spark.createDataFrame([(-1, None), (-2, 7), (-2, 8)], "query_id long, element long"))
    words = filters.build_filters(sets, spec)
    for d, order in ((2, "id"), (2, "ones"), (5, "minhash")):
        plain, loaded = tree.bulk_load(words, spec, d, order), tree.bulk_load(words, spec, d, order, members=sets)
        want = sorted(map(tuple, tree.counted_cost(plain, asked).collect()))
        for most in (1, 64 << 20):
            assert len(tree.load_tiers(loaded.load.sizes, d, spec.m, most)) == (2 if most == 1 else 1)
            assert sorted(map(tuple, tree._load_cost(loaded, asked, most).collect())) == want
        assert "words" not in vars(loaded)  # no row of words was formed
        assert sorted(tree.root_words(loaded).collect()) == sorted(tree.root_words(plain).collect())
        assert sorted(loaded.nodes.collect(), key=lambda r: r.node_id) == sorted(plain.nodes.collect(), key=lambda r: r.node_id)
    none = tree.bulk_load(words.limit(0), spec, 2, members=sets.limit(0))
    assert {r.nodes_checked for r in tree.counted_cost(none, asked).collect()} == {0} and not none.words.collect()


def test_elements_are_hashed_once(spark):
    """Not once for each of their positions: the digest stands outside of the function over positions."""
    from filterfleet.functions.hashing import positions

    plan = spark.range(1).select(positions(F.col("id"), FilterSpec(1500)).alias("spots"))._jdf.queryExecution().optimizedPlan().toString()
    assert plan.rindex("md5") < plan.index("lambdafunction")


def test_ranges_move_a_row_for_each_band(spark):
    """A range over many cells is few rows of the join, on either side of zero and at the bands' ends."""
    points = spark.range(-200, 200).withColumnRenamed("id", "event_id")
    spans = spark.createDataFrame([(1, -200, 199), (2, -1, 0), (3, -33, -32), (4, 31, 32), (5, 16, 15), (6, -165, 165)], "site_id long, lo long, hi long").where("lo <= hi")
    found = relational.range_pairs(points, spans, 2, band=16)
    want = sorted((e, s) for s, lo, hi in [tuple(r) for r in spans.collect()] for e in range(-200, 200) if lo <= e <= hi)
    assert sorted(map(tuple, found.collect())) == want
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert "inline(cells" in plan and "explode(sequence(FLOOR" in plan

from pyspark.sql import functions as F

from filterfleet.functions.params import FilterSpec
from filterfleet.operators import pack
from filterfleet.sources.collections import probes, ranges

EIGHT = FilterSpec(1, family="mod_identity", k=1, m=64)
START = [(1, 0), (2, 1), (3, 2), (4, 3), (5, 4), (6, 6)]


def frame(spark, rows):
    return spark.createDataFrame(rows, "site_id long, element long")


def words(index):
    return {(r.block_id, r.pos): r.word for r in index.slices.collect()}


def test_example_words_and_probe(spark):
    index = pack.pack_build(frame(spark, START), EIGHT)
    assert words(index) == {(0, 0): 1, (0, 1): 2, (0, 2): 4, (0, 3): 8, (0, 4): 16, (0, 6): 32}
    asked = spark.createDataFrame([(1, 4), (2, 5), (3, None)], "query_id long, element long")
    assert [tuple(r) for r in pack.pack_search(index, asked).collect()] == [(1, 5)]
    assert {r.query_id: r.words_read for r in pack.words_read(index, asked).collect()} == {1: 1, 2: 0}


def test_example_delete_then_reuse(spark):
    index = pack.pack_delete(pack.pack_build(frame(spark, START), EIGHT), spark.createDataFrame([(5,)], "filter_id long"))
    assert (0, 4) not in words(index)
    again = pack.pack_insert(index, frame(spark, [(9, 5)]))
    assert words(again)[0, 5] == 16 and again.slots.where("filter_id = 9").first().lane == 4


def test_last_in_block_goes_with_it(spark):
    data = ranges(spark, 65, 2)
    index = pack.pack_build(data, FilterSpec(20))
    assert index.slots.agg(F.max("block_id")).first()[0] == 1
    gone = pack.pack_delete(index, spark.createDataFrame([(64,)], "filter_id long"))
    assert gone.slots.agg(F.max("block_id")).first()[0] == 0 and gone.slices.where("block_id > 0").count() == 0
    first = pack.pack_delete(index, spark.range(64).withColumnRenamed("id", "filter_id"))
    assert [tuple(r) for r in first.slots.where("in_use").select("filter_id", "slot").collect()] == [(64, 0)]


def test_sign_lane_and_sizes(spark):
    for n in (1, 63, 64, 65, 128):
        data = ranges(spark, n, 2)
        spec, asked = FilterSpec(50), probes(ranges(spark, n, 2), 1)
        found = {tuple(r) for r in pack.pack_search(pack.pack_build(data, spec), asked).collect()}
        assert {(2 * e, e // 2) for e in range(2 * n)} <= found


def test_empty(spark):
    index = pack.pack_build(frame(spark, []), EIGHT)
    assert pack.pack_search(index, spark.createDataFrame([(1, 4)], "query_id long, element long")).count() == 0

"""Mixing sources to target weights by weighted fair queueing, with DataFrame and SQL functions only.

A source's documents stand in one shuffled row (by the md5 of their id and a seed), up to `most_epochs` times over.
Each copy's virtual finish time is the source's words up to and with it, divided by the source's target; the mix takes
copies by finish time until the budget (the sum of targets) is used up. Targets are the weights' shares of the budget,
stopped at `most_epochs` times the source's words; what is cut off is shared again by weight among the rest.

Running sums never put a source, or all rows, in one task: rows are dealt to slots of the shuffle order (a source with
a third of all rows has as many slots as any), the slots' sums are added up on a table of sources x slots, and only
rows of one slot are summed row by row. The same goes for the cut at the budget: finish times fall into bins, the bins
are summed on a small table, and only copies of the one bin that the budget ends in are ranked.

Null text has size 0 and uses no budget; a null source is a source of its own, last in order; null and repeated ids
are kept, each row by itself (`mixed` takes rows that are alike in id, source and size equally often); all columns of
docs pass through `mixed`, whatever they are called (names that start with `of_` or `_` aside); no rows give no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from filterfleet.llm.common import WORD_CLASS, materialize, reduce_tasks, table


WORDS = f"cast(coalesce(regexp_count(text, r'{WORD_CLASS}'), 0) as bigint)"


def sizes(docs: DataFrame) -> DataFrame:
    """doc_id, source and size, the words of the text; columns of docs with such names don't matter."""
    return docs.select("doc_id", "source", F.expr(WORDS).alias("size"))


def targets(source_sizes: DataFrame, weights: tuple[int, ...] = (1, 2, 3), most_epochs: int = 3) -> DataFrame:
    """(sid, source_size, target) from (sid, source_size): the shares of the whole, stopped at the most epochs.

    With sources in order of stop / weight, a source is stopped if the level that those before it leave (what is left
    of the whole, over the weights left) reaches its stop; the first that isn't stopped sets the level of all others.
    """
    every = Window.partitionBy(F.lit(0))
    filling = every.orderBy(F.col("stop") / F.col("weight"), "sid")
    before, whole = filling.rowsBetween(Window.unboundedPreceding, -1), filling.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    exact = lambda c: F.col(c).cast("decimal(38,0)")
    wheel = F.array(*map(F.lit, weights))
    placed = (
        source_sizes.withColumn("weight", F.element_at(wheel, (F.row_number().over(every.orderBy("sid")) - 1) % len(weights) + 1).cast("bigint"))
        .withColumn("stop", most_epochs * F.col("source_size"))
        .withColumn("left", F.sum("source_size").over(every) - F.coalesce(F.sum("stop").over(before), F.lit(0)))
        .withColumn("shares", F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0)))
        .withColumn("stopped", exact("stop") * exact("shares") <= exact("left") * exact("weight"))
    )
    first_open = lambda c: F.first(F.when(~F.col("stopped"), F.col(c)), ignorenulls=True).over(whole).cast("double")
    level = F.col("weight").cast("double") * first_open("left") / first_open("shares")
    return placed.select("sid", "source_size", F.when(F.col("stopped"), F.col("stop").cast("double")).otherwise(level).alias("target"))


def decisions(docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), most_epochs: int = 3, slots: int = 1024, bins: int = 16384, seed: str = "mix") -> DataFrame:
    """doc_id, source, size, source_size, target, key, finish (an array: of each copy taken), copies of every document."""
    sized = materialize(sizes(docs), "mix-sizes")
    # Rows without an id are told apart by their size, so that they don't all stand in one place of the shuffle.
    key = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col("doc_id").cast("string"), F.concat(F.lit("?"), "size"))))
    rows = sized.withColumns({"key": key, "sid": F.when(F.col("source").isNull(), "1").otherwise(F.concat(F.lit("0"), "source"))}).withColumn(
        "slot", F.expr(f"cast(conv(substr(key, 1, 8), 16, 10) as bigint) * {slots} div 4294967296")
    )
    by_slot = rows.groupBy("sid", "slot").agg(F.sum("size").alias("slot_size"))
    goals = targets(by_slot.groupBy("sid").agg(F.sum("slot_size").alias("source_size")), weights, most_epochs)
    earlier = Window.partitionBy("sid").orderBy("slot").rowsBetween(Window.unboundedPreceding, -1)
    starts = by_slot.withColumn("before", F.coalesce(F.sum("slot_size").over(earlier), F.lit(0))).join(goals, "sid").drop("slot_size")
    inner = Window.partitionBy("sid", "slot").orderBy("key", "size").rowsBetween(Window.unboundedPreceding, 0)
    finish = lambda e: f"cast({e} * source_size + upto as double) / greatest(target, 1e-6D)"
    placed = materialize(rows.withColumn("within", F.sum("size").over(inner)).join(starts, ["sid", "slot"]).withColumn("upto", F.expr("before + within")).drop("before", "within", "slot"), "mix-places")

    copies = placed.selectExpr("size", "key", "sid", f"posexplode(array({', '.join(map(finish, range(most_epochs)))})) as (epoch, finish)").withColumn("bin", F.expr(f"least(cast(finish * {bins // 2} as bigint), {2 * bins})"))
    every = Window.partitionBy(F.lit(0)).orderBy("bin")
    budget = goals.agg(F.coalesce(F.sum("source_size"), F.lit(0)).alias("budget")).first()["budget"]
    binned = copies.groupBy("bin").agg(F.sum("size").alias("bin_size")).withColumn("bin_upto", F.sum("bin_size").over(every.rowsBetween(Window.unboundedPreceding, 0)))
    over = binned.where(F.col("bin_upto") > budget).orderBy("bin").first()  # the one bin that the budget ends in
    last = (float("inf"), "2", "")
    if over:
        ends = Window.partitionBy("bin").orderBy("finish", "sid", "key", "size", "epoch").rowsBetween(Window.unboundedPreceding, 0)
        ranked = copies.where(F.col("bin") == over["bin"]).withColumn("used", over["bin_upto"] - over["bin_size"] + F.sum("size").over(ends))
        within = ranked.where(F.col("used") <= budget).orderBy(F.desc("finish"), F.desc("sid"), F.desc("key")).select("finish", "sid", "key").first()
        last = tuple(within) if within else (over["bin"] / (bins // 2), "", "")
    cut = F.struct(*map(F.lit, last))
    taken = F.array_compact(F.array(*(F.when(F.struct(F.expr(finish(e)), "sid", "key") <= cut, F.expr(finish(e))) for e in range(most_epochs))))
    return placed.select("doc_id", "source", "size", "source_size", "target", "key", taken.alias("finish")).withColumn("copies", F.size("finish").cast("bigint"))


def mixed(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: a row for each copy that is taken, in order of virtual finish time.

    The result has a partition for each range of finish times, ascending, and is sorted inside; written as it is, its
    files follow one another. The mix uses words at an even rate in finish time (each source at its target's), so equal
    ranges hold about equal work and need no sample. Rows alike in id, source and size take the finish times of one.
    """
    made = decisions(docs, **options)
    tasks = reduce_tasks(docs.sparkSession)
    of = made.where("copies > 0").groupBy(*(F.col(c).alias(f"of_{c}") for c in ("doc_id", "source", "size"))).agg(F.max(F.struct("copies", "finish"))["finish"].alias("of_finish"), F.max("key").alias("of_key"))
    same = F.col("doc_id").eqNullSafe(F.col("of_doc_id")) & F.col("source").eqNullSafe(F.col("of_source")) & (F.expr(WORDS) == F.col("of_size"))
    end = made.agg(F.max(F.array_max("finish")).alias("end")).first()["end"] or 1.0
    copies = docs.join(of, same).select(*(F.col(c) for c in docs.columns), F.explode("of_finish").alias("_finish"), F.col("of_key").alias("_key"))
    place = F.least(F.floor(F.col("_finish") / F.lit(end) * tasks), F.lit(tasks - 1)).cast("int")
    return copies.repartitionById(tasks, place).sortWithinPartitions("_finish", "_key").select(*docs.columns)


def op7_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decisions(table(spark, sf_dir, "documents")).selectExpr("doc_id", "size", "source_size", "target", "copies", "size * copies as taken")


ORACLE = r"""
with recursive w as (select doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint as size from documents),
d as (select *, md5('mix:' || coalesce(doc_id::varchar, '?' || size)) as key, case when source is null then '1' else '0' || source end as sid from w),
src as (select sid, sum(size)::bigint as source_size, (row_number() over (order by sid) - 1) % 3 + 1 as weight from d group by sid),
f as (select *, 3 * source_size as stop, row_number() over (order by 3 * source_size / weight, sid) as r from src),
g as (select *, (sum(source_size) over () - coalesce(sum(stop) over (order by r rows between unbounded preceding and 1 preceding), 0))::bigint as rest, (sum(weight) over () - coalesce(sum(weight) over (order by r rows between unbounded preceding and 1 preceding), 0))::bigint as shares from f),
h as (select *, stop::hugeint * shares <= rest::hugeint * weight as stopped from g),
o as (select rest::double as rest, shares::double as shares from h where not stopped order by r limit 1),
t as (select sid, source_size, case when stopped then stop::double else weight::double * (select rest from o) / (select shares from o) end as target from h),
p as (select d.*, source_size, target, (sum(size) over (partition by d.sid order by key, size rows between unbounded preceding and current row))::bigint as upto from d join t using (sid)),
c as (select p.*, e, (e * source_size + upto)::double / greatest(target, 1e-6) as finish from p, (select unnest([0, 1, 2]) as e)),
u as (select *, sum(size) over (order by finish, sid, key, size, e rows between unbounded preceding and current row) as used from c)
select doc_id, any_value(size) as size, any_value(source_size) as source_size, any_value(target) as target, count(*) filter (where used <= (select sum(size) from d)) as copies, any_value(size) * count(*) filter (where used <= (select sum(size) from d)) as taken from u group by doc_id
"""

QUERIES = {"op7_source_mix": op7_source_mix}
ORACLES = {"op7_source_mix": ORACLE}

"""Helpers around DataFrames: cutting lineage in the shared folder, and row numbers that no single task makes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window, functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. One of our own only where none is set and all
    runs in one process; on a cluster such a folder would go with its machine, so there an unset one is an error."""
    context = spark.sparkContext
    current = context._jsc.sc().getCheckpointDir()
    place = spark.conf.get("spark.checkpoint.dir", None) or (current.get() if current.isDefined() else None)
    if not place:
        if not context.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir has to name a folder that the driver and all executors share")
        import tempfile

        place = tempfile.mkdtemp(prefix="filterfleet-")
        context.setCheckpointDir(place)
    return place


def checkpointed(df: DataFrame) -> DataFrame:
    """df, computed once and kept in the shared folder."""
    context = df.sparkSession.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        context.setCheckpointDir(shared_dir(df.sparkSession))
    return df.checkpoint()


def written(df: DataFrame, what: str, *by: str) -> DataFrame:
    """df as a table in the shared folder, in a part for each value of `by`, so that a reader takes only the parts it asks
    for. Unlike a checkpoint it leaves no trace of the plan behind, which loops of many rounds need."""
    return df.sparkSession.read.schema(df.schema).parquet(written_at(df, what, *by))


def written_at(df: DataFrame, what: str, *by: str) -> str:
    """Where such a table was written."""
    import uuid

    path = f"{shared_dir(df.sparkSession)}/{what}-{uuid.uuid4().hex}"
    df.write.partitionBy(*by).parquet(path)
    return path


def stored(df: DataFrame, what: str) -> DataFrame:
    """As `written`, without parts; the shuffles behind it serve nothing once it is there, so their files go then."""
    spark, clean = df.sparkSession, "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(clean, None)
    if before is not None:
        spark.conf.set(clean, "true")
    try:
        return written(df, what)
    finally:
        if before is not None:
            spark.conf.set(clean, before)


def range_buckets(df: DataFrame, column: str, buckets: int):
    """Expression for the range of `column` that a row lies in; the bounds are approximate quantiles (buckets - 1 numbers)."""
    shares = [k / buckets for k in range(1, buckets)]
    bounds = sorted(set(df.agg(F.percentile_approx(column, shares, 20 * buckets).alias("b")).first()["b"] or [])) if shares else []
    if not bounds:
        return F.lit(0)
    # a chain of halving steps, so cost grows with the log of the number of bounds
    array, steps = F.array(*map(F.lit, bounds)), F.array(*(F.lit(1 << k) for k in range(len(bounds).bit_length() - 1, -1, -1)))
    return F.aggregate(steps, F.lit(0), lambda at, s: F.when((at + s <= len(bounds)) & (F.element_at(array, F.least(at + s, F.lit(len(bounds)))) <= F.col(column)), at + s).otherwise(at))


def numbered(df: DataFrame, column: str, name: str, buckets: int | None = None) -> DataFrame:
    """df with `name`: 0, 1, 2 ... in order of the numeric `column` (distinct values).

    Rows are ranked inside ranges, and the ranges' sizes are added up on a table of one row each.
    """
    buckets = buckets or max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    placed = df.withColumn("_range", range_buckets(df, column, buckets))
    sizes = placed.groupBy("_range").agg(F.count("*").alias("_size"))
    before = F.coalesce(F.sum("_size").over(Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = sizes.select("_range", before.alias("_before"))
    rank = F.row_number().over(Window.partitionBy("_range").orderBy(column)) - 1
    return placed.withColumn("_rank", rank).join(F.broadcast(offsets), "_range").withColumn(name, F.col("_before") + F.col("_rank")).drop("_range", "_rank", "_before")


def small(df: DataFrame, most_rows: int = 1_000_000) -> bool:
    """Whether df has at most most_rows rows, found without counting further."""
    return df.limit(most_rows + 1).count() <= most_rows


def broadcast_if_small(df: DataFrame, most_rows: int = 200_000) -> DataFrame:
    """A broadcast hint behind a check of size; larger tables are left to the planner. df is computed once, for both."""
    df = checkpointed(df)
    return F.broadcast(df) if small(df, most_rows) else df


def ored_into(words: DataFrame, delta: DataFrame, *keys: str, most_rows: int = 200_000) -> DataFrame:
    """words with delta's words OR-ed in by key (words has a row for each key).

    A small delta goes to where the words lie, which then don't move; otherwise both are grouped anew.
    """
    delta = checkpointed(delta.groupBy(*keys).agg(F.bit_or("word").alias("word")))
    if not small(delta, most_rows):
        return words.unionByName(delta).groupBy(*keys).agg(F.bit_or("word").alias("word"))
    merged = words.join(F.broadcast(delta.withColumnRenamed("word", "more")), list(keys), "left").select(*keys, F.expr("word | coalesce(more, 0)").alias("word"))
    known = words.join(F.broadcast(delta.select(*keys)), list(keys), "left_semi").select(*keys)
    return merged.unionByName(delta.join(known, list(keys), "left_anti"))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")

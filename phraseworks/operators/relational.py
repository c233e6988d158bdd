"""Joins that phrase work needs and Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.io import settle


def asof_join(left: DataFrame, right: DataFrame, key: str, left_at: str, right_at: str, values: list[str]) -> DataFrame:
    """left with the values of right's last row at or before left's time, for the same key: one shuffle and one window over both."""
    tag = lambda df, at, vals: df.select(F.col(key).alias("_k"), F.col(at).alias("_t"), *vals)
    rows = tag(left, left_at, [F.lit(1).alias("_side"), F.struct(*left.columns).alias("_l"), F.lit(None).cast(right.select(F.struct(*values)).schema[0].dataType).alias("_r")])
    rows = rows.unionByName(tag(right, right_at, [F.lit(0).alias("_side"), F.lit(None).cast(left.select(F.struct(*left.columns)).schema[0].dataType).alias("_l"), F.struct(*values).alias("_r")]))
    w = Window.partitionBy("_k").orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumn("_last", F.last("_r", ignorenulls=True).over(w)).where("_side = 1").select("_l.*", *[F.col(f"_last.{v}").alias(v) for v in values])


def range_join(points: DataFrame, spans: DataFrame, key: str, at: str, start: str, end: str, width: int) -> DataFrame:
    """points (key, at) with the spans (key, start, end) that hold them, start <= at < end: an equi-join on cells of the given
    width, which spans cover, then the exact condition."""
    p = points.withColumn("_cell", F.floor(F.col(at) / width))
    s = spans.withColumnRenamed(key, "_key").where(F.col(end) > F.col(start)).withColumn("_cell_s", F.explode(F.sequence(F.floor(F.col(start) / width), F.floor((F.col(end) - 1) / width))))
    return p.join(s, (F.col(key) == F.col("_key")) & (F.col("_cell") == F.col("_cell_s"))).where((F.col(at) >= F.col(start)) & (F.col(at) < F.col(end))).drop("_cell", "_cell_s", "_key")


def containment(counts: DataFrame) -> DataFrame:
    """(inner, outer) of frequent phrases in which one is a contiguous part of another: the outer's parts are listed, so the theta
    condition becomes an equi-join."""
    ws = F.split("phrase", " ")
    parts = counts.where("n > 1").select(F.col("phrase").alias("outer_p"), "n", ws.alias("ws")).select("outer_p", "n", "ws", F.explode(F.sequence(F.lit(1), F.col("n") - 1)).alias("m")).select("outer_p", F.explode(F.transform(F.sequence(F.lit(1), F.col("n") - F.col("m") + 1), lambda i: F.concat_ws(" ", F.slice("ws", i, F.col("m"))))).alias("inner_p")).distinct()
    return parts.join(counts.select(F.col("phrase").alias("inner_p")), "inner_p").select("inner_p", "outer_p")


def cumulative(rows: DataFrame, group: list[str], order: list[Column], value: str, name: str = "cdf") -> DataFrame:
    """rows with the running share of value in their group, for inverse-law draws. Rows are sorted by ranges and summed within a range;
    a range then starts from the sums of those before it, so no task holds a whole group."""
    ranged = settle(rows.orderBy(*group, *order).withColumn("_at", F.monotonically_increasing_id()).withColumn("_part", F.shiftright("_at", 33)), "ranges")
    sums = ranged.groupBy(*group, "_part").agg(F.sum(value).alias("_sum"))
    # a row for each group and range that meet
    line = Window.partitionBy(*group)
    starts = sums.select(*[F.col(g).alias(f"_{g}") for g in group], F.col("_part").alias("_of"), (F.sum("_sum").over(line.orderBy("_part")) - F.col("_sum")).alias("_start"), F.sum("_sum").over(line).alias("_whole"))
    same = F.col("_part") == F.col("_of")
    for g in group:
        same &= F.col(g).eqNullSafe(F.col(f"_{g}"))
    within = F.sum(value).over(Window.partitionBy(*group, "_part").orderBy("_at").rowsBetween(Window.unboundedPreceding, 0))
    out = ranged.withColumn("_run", within).join(starts, same)
    return out.withColumn(name, (F.col("_start") + F.col("_run")) / F.col("_whole")).select(*rows.columns, name)

"""Running totals and dense numbers over a global order, without a single-task window.

Rows are range-partitioned and written to the shared folder with their partition's number; the partitions' totals
(one row each) give every partition its base, and a window inside each partition does the rest.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ruleworld.sources.scratch import settle

_PART = "__rw_part"


def running_total(frame: DataFrame, order: list, amount: Column, name: str, within: list[str] | None = None) -> DataFrame:
    """``frame`` plus ``name``: the sum of ``amount`` over all rows up to and including each, in ``order``.

    ``order`` should be a total order; ties are broken the same way for one call only. With ``within``, columns that
    lead ``order``, the sum starts anew for each of their values.
    """
    keys = within or []
    placed = settle(frame.withColumn(name, amount).repartitionByRange(*order).withColumn(_PART, F.spark_partition_id()))
    sums = placed.groupBy(_PART, *keys).agg(F.sum(name).alias("__rw_sum"))
    before = Window.partitionBy(*keys).orderBy(_PART).rowsBetween(Window.unboundedPreceding, -1)  # one row a partition and value
    base = sums.select(_PART, *keys, F.coalesce(F.sum("__rw_sum").over(before), F.lit(0)).alias("__rw_base"))
    inside = Window.partitionBy(_PART, *keys).orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    match = [placed[_PART] == base[_PART], *[placed[k].eqNullSafe(base[k]) for k in keys]]
    joined = placed.withColumn("__rw_run", F.sum(name).over(inside)).alias("a")
    match = [F.col(f"a.{c}").eqNullSafe(F.col(f"b.{c}")) for c in [_PART, *keys]]
    out = joined.join(base.alias("b"), match)
    return out.select(*[F.col(f"a.`{c}`") for c in frame.columns], (F.col("a.__rw_run") + F.col("b.__rw_base")).cast("long").alias(name))

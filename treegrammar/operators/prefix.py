"""Prefix sums over long ordered tables, without ordering a whole table in one task."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Rows of an inner window; the outer one sees a row for each so many.
GROUP = 4096


def before(df: DataFrame, part: str, order: str, values: dict[str, str]) -> DataFrame:
    """Add for each new column the sum of a value over the rows before, within ``part`` in the order of the integer ``order``.

    Rows are cut into groups of ``GROUP`` consecutive order values; the sums of the groups are summed up first (a short table),
    then each group runs on its own."""
    cut = df.withColumn("__grp", F.floor(F.col(order) / GROUP))
    totals = cut.groupBy(part, "__grp").agg(*[F.sum(v).alias(f"__t_{n}") for n, v in values.items()])
    outer = Window.partitionBy(part).orderBy("__grp").rowsBetween(Window.unboundedPreceding, -1)
    bases = totals.select(part, "__grp", *[F.coalesce(F.sum(f"__t_{n}").over(outer), F.lit(0)).alias(f"__b_{n}") for n in values])
    inner = Window.partitionBy(part, "__grp").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    own = cut.join(bases, [part, "__grp"])
    own = own.select("*", *[(F.coalesce(F.sum(v).over(inner), F.lit(0)) + F.col(f"__b_{n}")).alias(n) for n, v in values.items()])
    return own.drop("__grp", *[f"__b_{n}" for n in values])

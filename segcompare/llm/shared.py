"""Intermediate tables in the folder that driver and executors share, and joins that stand hot keys.

The folder is that of `segcompare.storage`. Tables written here cut lineage: a lost executor costs a re-read,
not a re-computation. `emptied` frees a table that nothing reads any more.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import new_path as fresh

#: Rows of a few numbers that are broadcast at most: about 20 MB.
BROADCAST_ROWS = 200_000
#: Keys that hold this share of the rows or more are hot; there are 100,000 of them at most.
HOT_SHARE = 100_000


def saved(df: DataFrame, name: str, path: str | None = None) -> DataFrame:
    """df written as Parquet to the shared folder and read again."""
    spark = df.sparkSession
    path = path or fresh(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def emptied(spark: SparkSession, path: str) -> None:
    """Removes the rows of a table that was written there."""
    spark.range(0, 0, 1, 1).write.mode("overwrite").parquet(path)


def broadcast_if_small(df: DataFrame, name: str, most_rows: int = BROADCAST_ROWS) -> DataFrame:
    """df for a join: written and counted, broadcast up to most_rows narrow rows, joined by shuffle beyond."""
    kept = saved(df, name)
    return F.broadcast(kept) if kept.count() <= most_rows else kept


def matched(rows: DataFrame, facts: DataFrame, key: str, weight: str, how: str = "inner", most_rows: int = BROADCAST_ROWS) -> DataFrame:
    """rows joined with facts (one row a key, `weight` the key's rows) on a key that is not null.

    Few facts are broadcast. Else the facts of hot keys are, which their share of all rows bounds in number, so
    that rows of a hot key stay where they are; the other rows meet their facts by shuffle.
    """
    n, total = facts.agg(F.count(F.lit(1)), F.sum(weight)).first()
    if n <= most_rows:
        return rows.join(F.broadcast(facts), key, how)
    limit = max(64, (total or 0) // HOT_SHARE)
    hot = F.broadcast(facts.filter(F.col(weight) >= limit))
    cold = rows.join(F.broadcast(facts.filter(F.col(weight) >= limit).select(key)), key, "left_anti")
    return rows.join(hot, key).unionByName(cold.join(facts.filter(F.col(weight) < limit), key, how))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")

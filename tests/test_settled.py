"""Settled runs on tables of more nodes than the default stop rule lets change at the end."""

from pyspark.sql import functions as F

import __spark_entry__ as entry


def test_last_changes_are_made(spark, tmp_path):
    """Conversations of one turn change nothing; they only raise the number of nodes, and with it the default theta."""
    long = spark.range(320, 360).select(F.col("id").alias("conv_id"), F.explode(F.sequence(F.lit(0), F.lit(60))).alias("turn"))
    single = spark.range(1000, 211_000).select(F.col("id").alias("conv_id"), F.lit(0).alias("turn"))
    found = []
    for folder, rows in (("few", long), ("many", long.union(single))):
        rows.write.parquet(f"{tmp_path}/{folder}/conversations.parquet")
        labels = entry.queries()["lp_settled_turns"](spark, f"{tmp_path}/{folder}")
        found.append(sorted(map(tuple, labels.where(F.col("id") < 1000 << 24).collect())))
    assert found[0] == found[1]

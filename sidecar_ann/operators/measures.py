"""Accuracy and balance measures over result tables (qid, vec_id, distance)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def recall_per_query(result: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    hit = truth.select("qid", "vec_id").join(result.select("qid", "vec_id").withColumn("_hit", F.lit(1)), ["qid", "vec_id"], "left")
    return hit.groupBy("qid").agg((F.count("_hit") / F.least(F.lit(k), F.count("*"))).alias("recall"))


def recall_at_k(result: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    return recall_per_query(result, truth, k).agg(F.avg("recall").alias("recall"))


def distance_ratio(result: DataFrame, truth: DataFrame) -> DataFrame:
    """Mean of the last returned distance over the last true one."""
    last = lambda d: d.groupBy("qid").agg(F.max("distance").alias("far"))
    a, b = last(result).withColumnRenamed("far", "got"), last(truth)
    return a.join(b, "qid").agg(F.avg(F.col("got") / F.col("far")).alias("ratio"))


def shard_balance(rows: DataFrame, shard: str = "shard") -> DataFrame:
    return rows.groupBy(shard).agg(F.count("*").alias("n")).agg(F.count("*").alias("shards"), F.max("n").alias("most"), F.min("n").alias("least"), (F.max("n") / F.avg("n")).alias("balance"))

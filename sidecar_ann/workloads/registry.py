"""Registry of queries, and the vector sets and fixtures that they share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import distance as D
from ..operators.exact import vectors_of
from ..operators.index import IndexManager
from ..sources.catalog import Table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return put


# ---------------------------------------------------------------- tables
def read(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def uniform(spark: SparkSession, sf: str) -> DataFrame:
    return read(spark, sf, "embeddings").select("vec_id", F.col("embedding").alias("v"), "label")


def clustered(spark: SparkSession, sf: str, hub: bool = False) -> DataFrame:
    """Islands around the first 32 vectors; hub keeps these as the centres of their clusters."""
    e = uniform(spark, sf)
    a = e.filter("vec_id < 32").select(F.col("vec_id").alias("a"), F.col("v").alias("av"))
    mixed = e.join(F.broadcast(a), F.col("vec_id") % 32 == F.col("a")).select("vec_id", F.zip_with("av", "v", lambda x, y: x.cast("double") + y.cast("double") * 0.35).alias("w"), "label")
    out = mixed.select("vec_id", D.normalize(F.col("w")).alias("v"), "label").filter("vec_id >= 32")
    return out.unionByName(e.filter("vec_id < 32").select("vec_id", F.transform("v", lambda x: x.cast("double")).alias("v"), "label")) if hub else out


def queries_of(rows: DataFrame, every: int = 25) -> DataFrame:
    return rows.filter(F.col("vec_id") % every == 0).select(F.col("vec_id").alias("qid"), F.col("v").alias("qv"))


U = "u AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v, label FROM embeddings)"
UQ = U + ", q AS (SELECT vec_id AS qid, v AS qv FROM u WHERE vec_id % 25 = 0)"


def topk_sql(k: int = 10, where: str = "true", queries: str = "true", select: str = "qid, vec_id, round(distance, 6) AS distance, CAST(rank AS INTEGER) AS rank") -> str:
    return f"""WITH {UQ}, d AS (
  SELECT qid, vec_id, list_distance(v, qv) AS distance FROM q, u WHERE ({where}) AND ({queries})
), r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY distance, vec_id) AS rank FROM d)
SELECT {select} FROM r WHERE rank <= {k}"""


def out_topk(df: DataFrame) -> DataFrame:
    return df.select("qid", "vec_id", F.round("distance", 6).alias("distance"), F.col("rank").cast("int").alias("rank"))


# ---------------------------------------------------------------- places
_folders: list[str] = []


@atexit.register
def _clean() -> None:
    for f in _folders:
        shutil.rmtree(f, ignore_errors=True)


def warehouse(spark: SparkSession) -> str:
    """A folder of its own for a query's tables: under the session's shared folder where that is set."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        import uuid

        return f"{root.rstrip('/')}/warehouse-{uuid.uuid4().hex}"
    _folders.append(tempfile.mkdtemp(prefix="sidecar-"))
    return _folders[-1]


_built: dict[tuple, tuple[Table, IndexManager]] = {}


def table_of(spark: SparkSession, sf: str, where: str = "true", files: int = 20, per_file: int = 25) -> Table:
    rows = uniform(spark, sf).filter(where)
    return Table.create(spark, f"{warehouse(spark)}/t", rows, "vec_id", files, file_no=(F.col("vec_id") / per_file).cast("int"))


def per_file(spark: SparkSession, sf: str, files: int = 20) -> int:
    return -(-uniform(spark, sf).count() // files)


SMALL = {"R": 10, "L": 24, "num_shards": 4, "cells": 8, "pq_nbits": 4, "n_entries": 6}


def shared(spark: SparkSession, sf: str, **options) -> tuple[Table, IndexManager]:
    """A table with an index "ix", built once a process for each set of options. Read only."""
    key = (id(spark.sparkContext), sf, tuple(sorted(options.items())))
    if key not in _built:
        table = table_of(spark, sf, per_file=per_file(spark, sf))
        manager = IndexManager(table)
        manager.create("ix", "v", **{**SMALL, **options})
        _built[key] = table, manager
    return _built[key]


EXHAUSTIVE = {"L": 1 << 20, "shard_oversample": 1 << 20, "rerank_oversample": 1 << 20}


def violations(spark: SparkSession, **checks: int) -> DataFrame:
    return spark.createDataFrame([(k, int(v)) for k, v in checks.items()], "check string, violations int")


def no_violations(*checks: str) -> str:
    return " UNION ALL ".join(f"SELECT '{c}' AS \"check\", 0 AS violations" for c in checks)


def matrix(rows: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(ids, vectors) of a small test set, in id order."""
    got = rows.select(F.col("vec_id").cast("long"), "v").toArrow().combine_chunks().sort_by("vec_id")
    return np.asarray(got.column("vec_id")), vectors_of(got.column("v").combine_chunks())

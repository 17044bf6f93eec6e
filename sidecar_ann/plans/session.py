"""Front end: tables by name, index statements, and SQL whose distance patterns run through indexes."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..errors import BadParameter, EngineError, UnknownIndex, UnsupportedPattern
from ..functions import distance as D
from ..operators.exact import exact_range
from ..operators.index import IndexManager
from ..sources.catalog import Table
from .cost import PROBE_LIMIT_BYTES, choose_tier
from .detect import AnnPattern, detect, kind, parse, seq

_NUMBERS = ("R", "L", "alpha", "num_shards", "n_entries", "pq_m", "pq_nbits", "cells", "seed", "sample_fraction", "sample_cap", "tombstone_limit")


class AnnSession:
    def __init__(self, spark: SparkSession, warehouse: str, probe_limit_bytes: int = PROBE_LIMIT_BYTES):
        self.spark, self.warehouse, self.probe_limit_bytes = spark, warehouse.rstrip("/"), probe_limit_bytes
        self.tables: dict[str, Table] = {}
        self.last_plan: dict = {}

    # ---- tables
    def create_table(self, name: str, df: DataFrame, id_column: str, **how) -> Table:
        self.tables[name] = Table.create(self.spark, f"{self.warehouse}/{name}", df, id_column, **how)
        return self.tables[name]

    def table(self, name: str) -> Table:
        if name not in self.tables:
            self.tables[name] = Table(self.spark, f"{self.warehouse}/{name}")
        return self.tables[name]

    def indexes(self, table: str) -> IndexManager:
        return IndexManager(self.table(table))

    def register_functions(self) -> None:
        D.register_functions(self.spark)

    # ---- statements
    def sql(self, text: str) -> DataFrame:
        """Index statements, distance patterns through an index, all else as Spark runs it."""
        done = self._statement(text)
        if done is not None:
            return done
        pattern = detect(self.spark, text)
        if pattern is None:
            self.last_plan = {"tier": "exact", "pattern": False}
            return self._plain(text)
        return self._run(pattern)

    def explain(self, text: str) -> dict:
        pattern = detect(self.spark, text)
        return {"tier": "exact", "pattern": None} if pattern is None else {**self._choose(pattern), "pattern": pattern}

    def _statement(self, text: str) -> DataFrame | None:
        word = text.strip().split()[0].upper() if text.strip() else ""
        row = lambda *r: self.spark.createDataFrame([r], "index string, state string")
        if word in ("REFRESH", "REBUILD") or re.match(r"(?i)\s*SHOW\s+INDEXES", text):
            if m := re.fullmatch(r"(?i)\s*(REFRESH|REBUILD)\s+INDEX\s+(\w+)\s+ON\s+(?:TABLE\s+)?(\w+)\s*;?\s*", text):
                self.indexes(m[3]).refresh(m[2], rebuild_all=m[1].upper() == "REBUILD")
                return row(m[2], m[1].lower() + "ed" if m[1].upper() != "REBUILD" else "rebuilt")
            if m := re.fullmatch(r"(?i)\s*REBUILD\s+INDEX\s+(\w+)\s+ON\s+(?:TABLE\s+)?(\w+)\s+SHARD\s+(\d+)\s*;?\s*", text):
                self.indexes(m[2]).rebuild_shard(m[1], int(m[3]))
                return row(m[1], "rebuilt")
            if m := re.fullmatch(r"(?i)\s*SHOW\s+INDEXES\s+(?:ON|IN|FROM)\s+(\w+)\s*;?\s*", text):
                return self.spark.createDataFrame([(n, "bound") for n in self.indexes(m[1]).list()], "index string, state string")
            if word != "REFRESH" or re.match(r"(?i)\s*REFRESH\s+INDEX", text):
                raise UnsupportedPattern(text)
            return None
        if word not in ("CREATE", "DROP"):
            return None
        node = parse(self.spark, text)
        if kind(node) not in ("CreateIndex", "DropIndex"):
            return None
        table = seq(node.table().multipartIdentifier())[-1]
        manager, name = self.indexes(table), node.indexName()
        if kind(node) == "DropIndex":
            if name not in manager.list() and node.ignoreIfNotExists():
                return row(name, "absent")
            manager.drop(name)
            return row(name, "dropped")
        if name in manager.list() and node.ignoreIfExists():
            return row(name, "exists")
        columns = seq(node.columns())
        if len(columns) != 1:
            raise BadParameter("an index has one vector column")
        column = seq(columns[0]._1().name() if hasattr(columns[0]._1(), "name") else columns[0]._1().nameParts())[-1]
        options = {e._1(): e._2() for e in seq(node.properties().toSeq())}
        typed = {k: (float(v) if "." in v else int(v)) if k in _NUMBERS else {"true": True, "false": False}.get(v.lower(), v) for k, v in options.items()}
        using = node.indexType().lower()
        kinds = {"vamana": "graph", "graph": "graph", "centroid": "centroid", "hnsw": "hnsw", "": "graph"}
        if using not in kinds:
            raise BadParameter(f"unknown kind of index {using}")
        if kinds[using] == "hnsw":
            typed["keep_vectors"] = True
        manager.create(name, column, kind=kinds[using], **typed)
        return row(name, "created")

    # ---- patterns
    def _choose(self, p: AnnPattern) -> dict:
        """Tier, index and probe of a pattern: by bytes of the shards, exact where none fits. Thresholds and indexes without
        shards go through the file centroids, which the driver probes."""
        try:
            table = self.table(p.table)
            snap = table.log.at(p.version)
        except EngineError:  # no such table or version; errors of the store are not hidden
            return {"tier": "exact", "index": None}
        for name in sorted(snap.indexes):
            index = IndexManager(table).open(name, p.version)
            if index.column == p.column and index.options.metric == p.metric:
                size = sum(s["bytes"] for s in index.shards)
                if p.threshold is not None or not index.shards:
                    return {"tier": "driver", "index": name, "bytes": size, "probe": "centroids"}
                return {"tier": choose_tier(size, self.probe_limit_bytes), "index": name, "bytes": size, "probe": "shards"}
        return {"tier": "exact", "index": None}

    def _run(self, p: AnnPattern) -> DataFrame:
        self.last_plan = {**self._choose(p), "pattern": True}
        try:
            table = self.table(p.table)
            snap = table.log.at(p.version)
        except EngineError as e:
            raise UnknownIndex(f"no table {p.table}") from e
        rows = table.df(p.version)
        where = F.expr(p.where) if p.where else None
        key, name = snap.id_column, p.alias or "_distance"
        d = D.metric(p.metric)(F.col(p.column), D.literal(p.vector)) if p.metric != "ip" else D.dot(F.col(p.column), D.literal(p.vector))
        own = rows if where is None else rows.filter(where)
        if self.last_plan["index"] is None or (p.threshold is not None and p.metric != "l2") or p.metric == "ip":
            if p.threshold is not None:
                out = own.withColumn(name, d).filter(F.col(name) < p.threshold if p.strict else F.col(name) <= p.threshold)
            else:
                out = own.withColumn(name, d).orderBy(name, key).offset(p.offset).limit(p.k)
            return self._project(out, p, name)
        manager = IndexManager(table)
        if p.threshold is not None:
            hit = manager.search_range(self.last_plan["index"], list(p.vector), p.threshold, p.version)
            self.last_plan |= manager.last_metrics
            hit = hit.filter(F.col("distance") < p.threshold) if p.strict else hit
            return self._project(own.join(hit.select(F.col("vec_id").alias(key), F.col("distance").alias(name)), key), p, name)
        want = p.k + p.offset
        if self.last_plan["probe"] == "centroids":
            hit = manager.search_centroid(self.last_plan["index"], list(p.vector), want, version=p.version, where=where)
            self.last_plan |= manager.last_metrics
        else:
            queries = self.spark.createDataFrame([(0, list(p.vector))], "qid long, qv array<double>")
            hit = manager.search(self.last_plan["index"], queries, want, version=p.version, where=where)
        out = own.join(F.broadcast(hit.select(F.col("vec_id").alias(key), F.col("distance").alias(name))), key)
        return self._project(out.orderBy(name, key).offset(p.offset).limit(p.k), p, name)

    @staticmethod
    def _project(out: DataFrame, p: AnnPattern, name: str) -> DataFrame:
        columns: list[str] = []
        for c in p.columns:
            columns += [x for x in out.columns if x != name] if c == "*" else [c]
        return out.select(*columns, *([name] if p.alias else []))

    def _plain(self, text: str) -> DataFrame:
        for name, table in self.tables.items():
            table.df().createOrReplaceTempView(name)
        return self.spark.sql(text)

    def compare(self, text: str) -> DataFrame:
        """The same query with no index."""
        pattern = detect(self.spark, text)
        if pattern is None:
            return self._plain(text)
        rows = self.table(pattern.table).df(pattern.version)
        if pattern.threshold is not None:
            return exact_range(rows if pattern.where is None else rows.filter(pattern.where), pattern.vector, pattern.threshold, pattern.column, pattern.metric, pattern.strict)
        d = D.metric(pattern.metric)(F.col(pattern.column), D.literal(pattern.vector))
        own = rows if pattern.where is None else rows.filter(pattern.where)
        return own.withColumn("distance", d).orderBy("distance", self.table(pattern.table).log.current().id_column).offset(pattern.offset).limit(pattern.k)

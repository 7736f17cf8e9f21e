"""Versioned views on a shared store. A version's folders are written first and named by the pointer last; a log of factors
beside the base defers the addition of a change, and is folded once its rank is over a limit."""

from __future__ import annotations

import json
import uuid

from pyspark.sql import SparkSession

from ..operators import coo
from ..operators.coo import SCHEMA, Coo


class ViewStore:
    """base + sum of factors, per view. All under one folder that every executor can reach."""

    def __init__(self, spark: SparkSession, path: str, max_rank: int = 64):
        self.spark, self.path, self.max_rank = spark, path, max_rank

    def _meta(self, name: str) -> dict | None:
        f = f"{self.path}/{name}/versions"
        try:
            row = self.spark.read.schema("version long, meta string").json(f).orderBy("version", ascending=False).first()
        except Exception as e:  # noqa: BLE001
            if "PATH_NOT_FOUND" in str(e):
                return None
            raise
        return json.loads(row.meta) if row else None

    def _commit(self, name: str, meta: dict) -> None:
        self.spark.createDataFrame([(meta["version"], json.dumps(meta))], "version long, meta string").coalesce(1).write.mode("append").json(f"{self.path}/{name}/versions")

    def _write(self, name: str, m: Coo) -> str:
        folder = f"{self.path}/{name}/{uuid.uuid4().hex}"
        m.df.select("i", "j", "v").write.parquet(folder)
        return folder

    def put(self, name: str, m: Coo) -> None:
        old = self._meta(name)
        self._commit(name, {"version": (old or {"version": -1})["version"] + 1, "rows": m.rows, "cols": m.cols, "base": self._write(name, m), "log": []})

    def add(self, name: str, left: Coo, right: Coo, source: str | None = None, batch: int | None = None) -> int:
        """Appends a change; one named by a source that is already there, or of a batch up to the last one, is left out. Gives the
        version."""
        meta = self._meta(name)
        if source is not None and source in meta.get("sources", []) or batch is not None and batch <= meta.get("batch", -1):
            return meta["version"]
        if batch is not None:
            meta["batch"] = batch
        log = [*meta["log"], [self._write(name, left), self._write(name, right), left.cols]]
        meta |= {"version": meta["version"] + 1, "log": log, "sources": [*meta.get("sources", []), *([source] if source is not None else [])]}
        if sum(r for *_, r in log) > self.max_rank:
            meta |= {"base": self._write(name, self._value(meta)), "log": []}
        self._commit(name, meta)
        return meta["version"]

    def _read(self, folder: str, rows: int, cols: int) -> Coo:
        return Coo(self.spark.read.schema(SCHEMA).parquet(folder), rows, cols)

    def _value(self, meta: dict) -> Coo:
        out = self._read(meta["base"], meta["rows"], meta["cols"])
        if meta["log"]:
            lefts = coo.hstack([self._read(a, meta["rows"], r) for a, _, r in meta["log"]])
            rights = coo.hstack([self._read(b, meta["cols"], r) for _, b, r in meta["log"]])
            out = coo.add_outer(out, lefts, rights)
        return out

    def get(self, name: str) -> Coo:
        return self._value(self._meta(name))

    def times(self, name: str, x: Coo) -> Coo:
        """view @ x without adding the log up: base @ x + L (R' x)."""
        meta = self._meta(name)
        out = coo.mul(self._read(meta["base"], meta["rows"], meta["cols"]), x)
        for a, b, r in meta["log"]:
            out = coo.add(out, coo.mul(self._read(a, meta["rows"], r), coo.tmul(self._read(b, meta["cols"], r), x)))
        return out

    def has(self, name: str) -> bool:
        return self._meta(name) is not None

    def batch(self, name: str) -> int:
        """The last batch that was added, or -1."""
        return self._meta(name).get("batch", -1)

    def version(self, name: str) -> int:
        return self._meta(name)["version"]

    def rank(self, name: str) -> int:
        return sum(r for *_, r in self._meta(name)["log"])

"""Exact dedup by Grace hash: partition to spill files until each bucket fits an open-addressing table.

Each input partition is first reduced by the same table (a combiner), so a text that a third of all rows share leaves
every partition once. Survivors are dealt by their 64-bit hash; a task then fills its table, and where that passes
``table_mb`` it spills by the next hash bits to files of its own and takes the files one by one, recursively. Texts are
compared in full, so equal hashes never merge different texts. Spill files live in the task's temporary folder and go
with it; a lost executor repeats its task from the shuffle.

Nulls count as empty text, null ids lose to any other id, repeated rows are copies, an empty table gives an empty one,
and further columns pass through untouched whatever their names. Of rows that tie in id and content any one stays. A very long
text is one entry of a table, whatever its size.
"""

from __future__ import annotations

import hashlib
import os
import pickle
import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import small_batches, tidy


class OpenTable:
    """Linear probing over a power-of-two array of entry numbers; an entry is [hash, content, id, count, row]."""

    def __init__(self, bits: int = 10):
        self.slots, self.entries, self.bytes = np.full(1 << bits, -1, np.int64).tolist(), [], 0

    def add(self, h: int, content: bytes, ident, count: int, row) -> None:
        slots, entries = self.slots, self.entries
        mask = len(slots) - 1
        at = h & mask
        while (k := slots[at]) >= 0:
            e = entries[k]
            if e[0] == h and e[1] == content:
                e[3] += count
                if ident is not None and (e[2] is None or ident > e[2]):
                    e[2], e[4] = ident, row
                return
            at = (at + 1) & mask
        slots[at] = len(entries)
        entries.append([h, content, ident, count, row])
        self.bytes += 200 + 2 * len(content)
        if 2 * len(entries) > len(slots):
            self.grow()

    def grow(self) -> None:
        self.slots = [-1] * (2 * len(self.slots))
        mask = len(self.slots) - 1
        for k, e in enumerate(self.entries):
            at = e[0] & mask
            while self.slots[at] >= 0:
                at = (at + 1) & mask
            self.slots[at] = k


def grace(rows: Iterator[tuple], limit: int, folder: str, depth: int = 0, fan_bits: int = 4) -> Iterator[list]:
    """Entries of distinct contents, each once. rows: (hash, content, id, count, row)."""
    table, files = OpenTable(), None
    for r in rows:
        if files is None:
            table.add(*r)
            if table.bytes > limit and (depth + 1) * fan_bits <= 48:
                files = [open(os.path.join(folder, f"{depth}-{k}-{id(table)}"), "w+b", buffering=1 << 16) for k in range(1 << fan_bits)]
                for e in table.entries:
                    pickle.dump(e, files[(e[0] >> (60 - depth * fan_bits)) & ((1 << fan_bits) - 1)], -1)
                table = OpenTable()
        else:
            pickle.dump(list(r), files[(r[0] >> (60 - depth * fan_bits)) & ((1 << fan_bits) - 1)], -1)
    if files is None:
        yield from table.entries
        return
    for f in files:
        f.seek(0)
        yield from grace(_load(f), limit, folder, depth + 1, fan_bits)
        f.close()
        os.unlink(f.name)


def _load(f) -> Iterator[list]:
    while True:
        try:
            yield pickle.load(f)
        except EOFError:
            return


def distinct_rows(df: DataFrame, text_col: str = "text", id_col: str = "doc_id", carry: bool = True, table_mb: int = 48) -> DataFrame:
    """One row per distinct content: the columns of the row of the largest id as ``_g_0``, ``_g_1``, ... in order, ``_g_size`` (rows
    of that content) and ``_g_sha`` (SHA-256 of the normalised text). With carry False only the id, as ``_g_0``, and the two figures.
    Equal: identical after lower-casing A-Z."""
    small_batches(df.sparkSession)
    keep = df.columns if carry else [id_col]
    fields = [df.schema[c] for c in keep]
    limit, has_text = table_mb << 20, text_col in keep
    inner = T.StructType([T.StructField("_g_h", T.LongType()), T.StructField("_g_n", T.LongType()), T.StructField("_g_t", T.StringType()), *([T.StructField(f"_g_{i}", f.dataType) for i, f in enumerate(fields)])])
    n, at_id = len(keep), keep.index(id_col)
    at_text = keep.index(text_col) if has_text else -1

    def out_batch(rows: list, schema: pa.Schema) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], f.type) for i, f in enumerate(schema)], schema=schema)

    def chunks(rows: Iterator[tuple], schema: pa.Schema, of_bytes: int = 8 << 20):
        got, size = [], 0
        for r in rows:
            got.append(r)
            size += 64 + sum(len(x) for x in r if isinstance(x, (str, bytes)))
            if size > of_bytes or len(got) >= 5000:
                yield out_batch(got, schema)
                got, size = [], 0
        if got:
            yield out_batch(got, schema)

    from pyspark.sql.pandas.types import to_arrow_schema

    inner_arrow = to_arrow_schema(inner)
    outer = T.StructType([*[T.StructField(f"_g_{i}", f.dataType) for i, f in enumerate(fields)], T.StructField("_g_size", T.LongType()), T.StructField("_g_sha", T.StringType())])
    outer_arrow = to_arrow_schema(outer)

    def combine(batches):
        table = OpenTable()

        def emit():
            for h, content, _, count, row in table.entries:
                yield (h - (1 << 64) if h >> 63 else h, count, None if has_text else content.decode(), *row)

        for b in batches:
            texts = b.column(n).to_pylist()
            cols = [b.column(i).to_pylist() for i in range(n)]
            for k, t in enumerate(texts):
                content = (t or "").encode().lower()
                row = tuple(c[k] for c in cols)
                table.add(xxhash.xxh3_64_intdigest(content), content, row[at_id], 1, row)
                if table.bytes > limit:
                    yield from chunks(emit(), inner_arrow)
                    table = OpenTable()
        yield from chunks(emit(), inner_arrow)

    def reduce(batches):
        def rows():
            for b in batches:
                cols = [c.to_pylist() for c in b.columns]
                for r in zip(*cols, strict=True):
                    row = r[3:]
                    content = ((row[at_text] or "") if has_text else r[2]).encode().lower()
                    yield r[0] & ((1 << 64) - 1), content, row[at_id], r[1], row

        with tempfile.TemporaryDirectory(prefix="grace-") as folder:
            yield from chunks(((*e[4], e[3], hashlib.sha256(e[1]).hexdigest()) for e in grace(rows(), limit, folder)), outer_arrow)

    slim = df.select(*[F.col(f"`{c}`").alias(f"_g_{i}") for i, c in enumerate(keep)], F.col(f"`{text_col}`").alias("_g_text"))
    dealt = slim.mapInArrow(tidy(combine), inner).repartition("_g_h")
    return dealt.mapInArrow(tidy(reduce), outer)


def survivors(df: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """The rows that stay, all columns of df, one per distinct content."""
    return distinct_rows(df, text_col, id_col).select(*[F.col(f"_g_{i}").alias(c) for i, c in enumerate(df.columns)])


def groups(df: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """One row per row of df: id, keep_id, group_size, kept, text_sha256."""
    lower = F.translate(F.coalesce(F.col(f"`{text_col}`"), F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    of = distinct_rows(df, text_col, id_col, carry=False).select(F.col("_g_0").alias("keep_id"), F.col("_g_size").alias("group_size"), F.col("_g_sha").alias("text_sha256"))
    mine = df.select(F.col(f"`{id_col}`"), F.sha2(lower, 256).alias("text_sha256"))
    return mine.join(of, "text_sha256").select(id_col, "keep_id", "group_size", F.col(id_col).eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256")

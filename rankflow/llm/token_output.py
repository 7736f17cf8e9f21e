"""Token-ID output in range-coded blocks.

A block holds whole documents in order, about ``block_ids`` ids, and starts from an empty model, so it can be decoded alone.
Its ids are dealt to lanes, one stretch each, that are coded in step as vectors. Three predictors drive one range coder per
lane: order 0 (counts of ids in the block so far), order 1 and order 2 (the id last seen after the last one or two ids, with
a confidence). Their probabilities are mixed, weighted by how often a predictor of that confidence was right in the block.
CRC-32 guards the block. Blocks are rows of a binary column (Spark has no sink for raw bytes that works on any store).

Null or empty texts are the end id alone. Null ids sort first. Rows with equal ids keep a fixed order by content.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import small_batches, tidy
from .tokens import encoder

MAGIC = b"RFT2"
TOTAL_BITS, REFRESH, MOST_LANES = 28, 64, 4096
ORDER2 = 1 << 19
U = np.uint64
SHORT = U(1 << 32)


def _next_sure() -> tuple[np.ndarray, np.ndarray]:
    """By (hit * 8 + confidence): what a cell (id * 8 + confidence) gains, and whether its id is replaced instead."""
    sure = np.arange(8)
    gain = np.concatenate((np.where(sure > 1, sure >> 1, 1) - sure, np.minimum(sure + 1, 7) - sure))
    return gain, np.concatenate((sure <= 1, np.zeros(8, bool)))


class Model:
    """Shared by the lanes of a block; the encoder and the decoder change it in the same way after each step.

    A cell of order 1 or 2 holds the id it predicts and its confidence (0 to 7) in the low three bits."""

    GAIN, REPLACED = _next_sure()

    def __init__(self, vocab: int, lanes: int):
        self.vocab, self.zero_bits = vocab, vocab.bit_length() + 3
        if self.zero_bits >= TOTAL_BITS - 3:
            raise ValueError("vocabulary too large")
        self.counts = np.zeros(vocab, np.int64)
        self.cells1, self.cells2 = np.zeros(vocab, np.int32), np.zeros(ORDER2, np.int32)
        self.tries, self.hits = np.full(64, 4.0), np.full((2, 64), 1.0)
        self.prev, self.mixed = np.zeros(lanes, np.int64), np.zeros(lanes, np.int64)
        self.kept, self.wait = [], 1
        self.refresh()

    def refresh(self) -> None:
        if self.kept:
            ids, cells, got2, got1 = (np.concatenate(x) for x in zip(*self.kept, strict=True))
            self.counts += np.bincount(ids, minlength=self.vocab)
            self.tries += np.bincount(cells, minlength=64)
            self.hits[0] += np.bincount(cells[got2], minlength=64)
            self.hits[1] += np.bincount(cells[got1], minlength=64)
            self.kept, self.wait = [], min(2 * self.wait, REFRESH)
        # Every id has one share at least; the shares make up 2**zero_bits.
        share = 1 + self.counts * ((1 << self.zero_bits) - self.vocab) // max(1, int(self.counts.sum()))
        share[-1] += (1 << self.zero_bits) - int(share.sum())
        self.upto = np.concatenate(([0], np.cumsum(share)))
        self.share = share
        self.owner = None
        room = (1 << TOTAL_BITS) - (1 << self.zero_bits + 1)
        # The two kinds of hits exclude each other, so their masses together stay under the total.
        self.mass2, self.mass1 = (self.hits / self.tries * 0.97 * room).astype(np.int64)
        self.rest = (1 << TOTAL_BITS) - self.mass2 - self.mass1

    def owners(self) -> np.ndarray:
        """The id of each share of order 0."""
        if self.owner is None:
            self.owner = np.repeat(np.arange(self.vocab, dtype=np.int32), self.share)
        return self.owner

    def predict(self) -> None:
        """p1, p2: ids of orders 1 and 2 for each lane; m1, m2: their masses; left: the mass of order 0."""
        self.at2 = (self.mixed + self.prev * 2654435761 >> 7) & (ORDER2 - 1)
        self.e1, self.e2 = self.cells1.take(self.prev).astype(np.int64), self.cells2.take(self.at2).astype(np.int64)
        self.p1, self.p2 = self.e1 >> 3, self.e2 >> 3
        self.sure1, self.sure2 = self.e1 & 7, self.e2 & 7
        self.cell = (self.sure2 << 3) + self.sure1
        self.m1, self.m2, self.left = self.mass1.take(self.cell), self.mass2.take(self.cell), self.rest.take(self.cell)

    def interval(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Begin and width of each lane's id in the mixture of the three orders."""
        base, top = self.upto.take(ids) * self.left >> self.zero_bits, self.upto.take(ids + 1) * self.left >> self.zero_bits
        self.hit1, self.hit2 = self.p1 == ids, self.p2 == ids
        return base + self.m1 * (self.p1 < ids) + self.m2 * (self.p2 < ids), top - base + self.m1 * self.hit1 + self.m2 * self.hit2

    def find(self, v: np.ndarray) -> np.ndarray:
        """The ids whose intervals hold v."""
        zero = self.upto.take(self.p1), self.upto.take(self.p1 + 1), self.upto.take(self.p2), self.upto.take(self.p2 + 1)
        from1, to1, from2, to2 = (z * self.left >> self.zero_bits for z in zero)
        ahead2 = self.m2 * (self.p2 < self.p1)  # mass of order 2 before the id of order 1, and the other way round
        ahead1 = self.m1 * (self.p1 < self.p2)
        same = self.p1 == self.p2
        from1, to1 = from1 + ahead2, to1 + ahead2 + self.m1 + self.m2 * same
        from2, to2 = from2 + ahead1, to2 + ahead1 + self.m2 + self.m1 * same
        past1, past2 = v >= to1, v >= to2
        ids = np.where(past1 | (v < from1), self.p2, self.p1)
        k = np.flatnonzero((past1 | (v < from1)) & (past2 | (v < from2)))
        x = (v - self.m1 * past1 - self.m2 * past2)[k]
        # Exact in doubles: the dividend has under 2**53, the quotient under 2**25, and divisors are under 2**28.
        slot = ((((x + 1) << self.zero_bits) - 1) / self.left[k]).astype(np.int64)
        ids[k] = self.owners().take(slot, mode="clip")
        return ids

    def learn(self, ids: np.ndarray) -> None:
        """After interval(ids)."""
        self.kept.append((ids, self.cell, self.hit2, self.hit1 & ~self.hit2))
        fresh = ids << 3 | 1
        for cells, at, e, sure, hit in ((self.cells1, self.prev, self.e1, self.sure1, self.hit1), (self.cells2, self.at2, self.e2, self.sure2, self.hit2)):
            case = sure + (hit << 3)
            cells[at] = np.where(self.REPLACED.take(case), fresh, e + self.GAIN.take(case))
        self.mixed = self.prev * 506832829
        self.prev = ids
        if len(self.kept) == self.wait:
            self.refresh()

    def narrow(self, n: int) -> None:
        self.prev, self.mixed = self.prev[:n], self.mixed[:n]


def _lanes(n: int) -> tuple[int, int]:
    """Lanes and steps: lane k holds ids k*steps to (k+1)*steps."""
    lanes = max(1, min(MOST_LANES, n // 128))
    return lanes, -(-n // lanes)


def encode_ids(ids: np.ndarray, vocab: int) -> bytes:
    """A lane keeps a low end and a range of 64 bits; 32 bits go out when the range falls under 2**32.

    A carry out of the low end is added to the words that went out."""
    n = len(ids)
    if not n:
        return b""
    lanes, steps = _lanes(n)
    grid = np.zeros(lanes * steps, np.int64)
    grid[:n] = ids
    grid = np.ascontiguousarray(grid.reshape(lanes, steps).T)
    model, wide = Model(vocab, lanes), steps + 2
    out, pos = np.zeros(wide * lanes, np.uint32), np.arange(lanes)  # a lane's words are `lanes` apart
    low, rng = np.zeros(lanes, U), np.full(lanes, (1 << 64) - 1, U)

    def end(low, first):
        k = np.arange(first, first + len(low))
        out[pos[k]], out[pos[k] + lanes] = low >> U(32), low & U(0xFFFFFFFF)
        pos[k] += 2 * lanes

    for t in range(steps):
        live = max(0, -(-(n - t) // steps))  # lanes that reach this far; a prefix of them
        if live < len(low):
            end(low[live:], live)
            low, rng = low[:live], rng[:live]
            model.narrow(live)
        s = grid[t, :live]
        model.predict()
        begin, width = model.interval(s)
        step = rng >> U(TOTAL_BITS)
        add = step * begin.view(U)
        low = low + add
        rng = step * width.view(U)
        k = np.flatnonzero(low < add)
        at = pos[k] - lanes
        while len(at):
            out[at] += np.uint32(1)
            at = at[out[at] == 0] - lanes
        k = np.flatnonzero(rng < SHORT)
        lo, at = low[k], pos[k]
        out[at] = lo >> U(32)
        pos[k] = at + lanes
        low[k] = lo << U(32)
        rng[k] <<= U(32)
        model.learn(s)
    end(low, 0)
    sizes = (pos // lanes).astype("<u4")
    filled = np.arange(wide) < sizes[:, None]
    return struct.pack("<II", n, lanes) + sizes.tobytes() + out.reshape(wide, lanes).T[filled].astype("<u4").tobytes()


def decode_ids(data: bytes, vocab: int) -> np.ndarray:
    if not data:
        return np.zeros(0, np.int64)
    n, lanes = struct.unpack_from("<II", data)
    sizes = np.frombuffer(data, "<u4", lanes, 8).astype(np.int64)
    body = np.concatenate([np.frombuffer(data, "<u4", offset=8 + 4 * lanes), np.zeros(2, np.uint32)]).astype(U)
    pos = np.cumsum(sizes) - sizes
    steps = _lanes(n)[1]
    model = Model(vocab, lanes)
    code, rng = body[pos] << U(32) | body[pos + 1], np.full(lanes, (1 << 64) - 1, U)  # code: above the low end
    pos += 2
    grid = np.zeros((steps, lanes), np.int64)
    for t in range(steps):
        live = max(0, -(-(n - t) // steps))
        if live < len(code):
            code, rng, pos = code[:live], rng[:live], pos[:live]
            model.narrow(live)
        model.predict()
        step = rng >> U(TOTAL_BITS)
        s = model.find(np.minimum(code // step, U((1 << TOTAL_BITS) - 1)).view(np.int64))
        begin, width = model.interval(s)
        code = code - step * begin.view(U)
        rng = step * width.view(U)
        k = np.flatnonzero(rng < SHORT)
        at = pos[k]
        code[k] = code[k] << U(32) | body[at]
        rng[k] <<= U(32)
        pos[k] = at + 1
        model.learn(s)
        grid[t, :live] = s
    return grid.T.reshape(-1)[:n]


def write_block(doc_ids: list, lengths: np.ndarray, ids: np.ndarray, vocab: int) -> bytes:
    """MAGIC, sizes, the documents' ids and lengths (deflated), the coded ids, CRC-32 of all before it."""
    nulls = np.packbits(np.array([d is None for d in doc_ids], bool)).tobytes()
    head = zlib.compress(nulls + np.array([d or 0 for d in doc_ids], "<i8").tobytes() + lengths.astype("<u4").tobytes())
    data = MAGIC + struct.pack("<IIII", vocab, len(doc_ids), len(ids), len(head)) + head + encode_ids(ids, vocab)
    return data + struct.pack("<I", zlib.crc32(data))


def read_block(data: bytes) -> tuple[list, np.ndarray, np.ndarray]:
    """(doc ids, lengths, ids); ValueError if it isn't such a block or its checksum differs."""
    if data[:4] != MAGIC or struct.unpack("<I", data[-4:])[0] != zlib.crc32(data[:-4]):
        raise ValueError("damaged block")
    vocab, docs, n, size = struct.unpack_from("<IIII", data, 4)
    head = zlib.decompress(data[20 : 20 + size])
    k = -(-docs // 8)
    nulls = np.unpackbits(np.frombuffer(head, np.uint8, k))[:docs]
    doc_ids = [None if z else int(d) for d, z in zip(np.frombuffer(head, "<i8", docs, k), nulls, strict=True)]
    ids = decode_ids(data[20 + size : -4], vocab)
    if len(ids) != n:
        raise ValueError("damaged block")
    return doc_ids, np.frombuffer(head, "<u4", docs, k + 8 * docs).astype(np.int64), ids


def write_tokens(docs: DataFrame, path: str, tokenizer_path: str, vocab: int, end_id: int, keeps_space: bool = True, block_ids: int = 1 << 21, added_tokens: bool = False) -> None:
    """Writes docs (doc_id, text) in ascending doc_id order: shards by range of doc_id, blocks in order within a shard.

    added_tokens: strings of the vocabulary's added tokens become their ids; else no text can make a control id."""

    def run(batches):
        encode, end = encoder(tokenizer_path, keeps_space, added_tokens), struct.pack("<I", end_id)
        held, lengths, ids, n, shard, number = [], [], [], 0, None, 0
        kinds = pa.schema([("shard", pa.int32()), ("block", pa.int32()), ("n_ids", pa.int64()), ("data", pa.binary())])

        def block():
            data = write_block(held, np.array(lengths), np.frombuffer(b"".join(ids), "<u4"), vocab)
            return pa.RecordBatch.from_arrays([pa.array([x], f.type) for x, f in zip((shard, number, n, data), kinds, strict=True)], schema=kinds)

        for b in batches:
            if shard is None and b.num_rows:
                shard = b.column(2)[0].as_py()
            for doc, mine in zip(b.column(0).to_pylist(), encode.each(b.column(1)), strict=True):
                held.append(doc)
                lengths.append((len(mine) >> 2) + 1)
                ids += (mine, end)
                n += lengths[-1]
                if n >= block_ids:
                    yield block()
                    held, lengths, ids, n, number = [], [], [], 0, number + 1
        if held:
            yield block()

    small_batches(docs.sparkSession)
    ordered = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id", F.md5("text"))
    blocks = ordered.withColumn("shard", F.spark_partition_id()).mapInArrow(tidy(run), "shard int, block int, n_ids long, data binary")
    blocks.write.mode("overwrite").option("compression", "none").parquet(path)


def read_tokens(spark, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) from the files alone; start counts the ids of all documents before."""
    blocks = spark.read.parquet(path)
    shards = blocks.groupBy("shard").agg(F.sum("n_ids").alias("all"))
    before = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    shards = shards.select("shard", F.coalesce(F.sum("all").over(before), F.lit(0)).alias("shard_from"))  # a row for each shard only
    inside = Window.partitionBy("shard").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    starts = blocks.select("shard", "block", F.coalesce(F.sum("n_ids").over(inside), F.lit(0)).alias("from")).join(shards, "shard").select("shard", "block", (F.col("shard_from") + F.col("from")).alias("from"))

    def run(batches):
        kinds = pa.schema([("shard", pa.int32()), ("block", pa.int32()), ("doc_id", pa.int64()), ("at", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])
        for b in batches:
            for shard, block, data in zip(*(c.to_pylist() for c in b.columns), strict=True):
                doc_ids, lengths, ids = read_block(data)
                raw, ends = ids.astype("<u4").tobytes(), np.cumsum(lengths)
                crc = [zlib.crc32(raw[4 * (e - n) : 4 * e]) for e, n in zip(ends.tolist(), lengths.tolist(), strict=True)]
                k = len(doc_ids)
                yield pa.RecordBatch.from_arrays([pa.array([shard] * k, pa.int32()), pa.array([block] * k, pa.int32()), pa.array(doc_ids, pa.int64()), pa.array(ends - lengths, pa.int64()), pa.array(lengths, pa.int64()), pa.array(crc, pa.int64())], schema=kinds)

    docs = blocks.select("shard", "block", "data").mapInArrow(tidy(run), "shard int, block int, doc_id long, at long, n_tokens long, ids_crc32 long")
    return docs.join(starts, ["shard", "block"]).select("doc_id", (F.col("from") + F.col("at")).alias("start"), "n_tokens", "ids_crc32")


def documents_of(data: bytes) -> dict:
    """doc_id -> ids of one block."""
    doc_ids, lengths, ids = read_block(data)
    return dict(zip(doc_ids, np.split(ids, np.cumsum(lengths)[:-1]), strict=True))

"""MinHash near-dedup with odd sketches.

A document is the set of its distinct word shingles. 128 of 256 MinHash samples give 32 bands of 4 for candidates (a pair at
similarity 0.75 is missed with probability 5e-6); all of them, folded into a 1024-bit parity bitmap, are an odd sketch. The
population count of two sketches' XOR estimates their similarity; pairs estimated under 0.55, five deviations below the
threshold, are left out, and all others are confirmed on their full shingle sets.

Documents with equal sets are one class, so copies never become pairs. Within a bucket, pairs first go to one leader each
(linear in the bucket), by a different order of leaders each round, and only where member and leader are in different
components; rounds end when they settle little. What is still in different components after that is compared in full, each
pair in the first bucket it shares, so no link between components is lost.

Nulls and texts without words have no shingles and link with nothing. Repeated rows are copies; rows of one id with different
texts are documents of their own that share a name. Null ids are never a component's name if another id is there. Very long
texts are compared whole. Empty tables give empty results; further columns are ignored, and pass through ``survivors``.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, cut, small_batches, tidy

SAMPLES, BANDED, BANDS, SKETCH = 256, 128, 32, 1024
FLOOR = 0.55
LARGE, BLOCK = 64, 256  # components from this size are compared in blocks of about so many documents
_MUL = np.uint64(0x9E3779B97F4A7C15)


def _mix(x: np.ndarray) -> np.ndarray:
    """Finaliser of splitmix64."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Shingles:
    """Distinct shingle hashes (uint64, sorted) of each text of an Arrow column, all texts at once."""

    def __init__(self, words: int = 5):
        self.words = words
        self.power = np.ones(1, np.uint64)
        self.inverse = np.uint64(pow(int(_MUL), -1, 1 << 64))
        self.back = np.ones(1, np.uint64)

    def _powers(self, n: int) -> None:
        if len(self.power) < n:
            n = max(n, 2 * len(self.power))
            with np.errstate(over="ignore"):
                self.power = np.concatenate(([np.uint64(1)], np.cumprod(np.full(n - 1, _MUL))))
                self.back = np.concatenate(([np.uint64(1)], np.cumprod(np.full(n - 1, self.inverse))))

    def __call__(self, texts: pa.Array) -> list[np.ndarray]:
        out, size, at = [], 0, 0
        lengths = pa.compute.fill_null(pa.compute.binary_length(texts), 0).to_pylist()
        for k, n in enumerate(lengths):  # stretches of about 1 MB, to stay in the cache
            size += n
            if size > 1 << 20:
                out += self._some(texts.slice(at, k + 1 - at))
                at, size = k + 1, 0
        return out + self._some(texts.slice(at))

    def _some(self, texts: pa.Array) -> list[np.ndarray]:
        raw = [b"" if x is None else x for x in texts.cast(pa.large_string()).cast(pa.large_binary()).to_pylist()]
        if not raw:
            return []
        data = np.frombuffer(b" ".join(raw) + b" ", np.uint8)
        ends_of = np.cumsum([len(x) + 1 for x in raw])
        space = (data == 32) | ((data >= 9) & (data <= 13))
        edge = np.flatnonzero(np.diff(np.concatenate(([True], space, [True])).view(np.int8)))
        start, end = edge[::2], edge[1::2]
        if not len(start):
            return [np.zeros(0, np.uint64)] * len(raw)
        self._powers(len(data) + 1)
        value = np.where((data >= 65) & (data <= 90), data + np.uint8(32), data).astype(np.uint64) + np.uint64(1)
        upto = np.concatenate((np.zeros(1, np.uint64), np.cumsum(value * self.power[: len(data)], dtype=np.uint64)))
        word = _mix((upto[end] - upto[start]) * self.back[start] + (end - start).astype(np.uint64))
        first = np.searchsorted(start, np.concatenate(([0], ends_of)))  # first word of each text
        n, w = len(word), self.words
        if n >= w:
            sh = word[: n - w + 1].copy()
            for k in range(1, w):
                sh = _mix(sh * _MUL + word[k : n - w + 1 + k])
        out = []
        for a, b in zip(first[:-1], first[1:], strict=True):
            if b - a >= w:
                out.append(np.unique(sh[a : b - w + 1]))
            elif b > a:
                x = word[a]
                for k in range(a + 1, b):
                    x = _mix(np.array([x * _MUL + word[k]]))[0]
                out.append(np.array([_mix(np.array([x + np.uint64(b - a)]))[0]]))
            else:
                out.append(np.zeros(0, np.uint64))
        return out


def _family() -> tuple[np.ndarray, np.ndarray]:
    g = np.random.default_rng(20240)
    return (g.integers(0, 1 << 32, SAMPLES, dtype=np.uint64) | np.uint64(1)).astype(np.uint32), g.integers(0, 1 << 32, SAMPLES, dtype=np.uint64).astype(np.uint32)


def minhash(shingles: np.ndarray, mul: np.ndarray, add: np.ndarray) -> np.ndarray:
    x = (shingles >> np.uint64(32)).astype(np.uint32)
    least = np.full(SAMPLES, 0xFFFFFFFF, np.uint32)
    for k in range(0, len(x), 512):
        least = np.minimum(least, (x[None, k : k + 512] * mul[:, None] + add[:, None]).min(axis=1))
    return least


def odd_sketch(least: np.ndarray) -> np.ndarray:
    """Parity, for each of SKETCH places, of the (sample, value) pairs that hash there."""
    place = _mix(least.astype(np.uint64) * np.uint64(SAMPLES) + np.arange(SAMPLES, dtype=np.uint64)) & np.uint64(SKETCH - 1)
    return np.packbits((np.bincount(place.astype(np.int64), minlength=SKETCH) & 1).astype(np.uint8)).view("<i8")


def most_different_bits(similarity: float) -> int:
    """Expected XOR count of two sketches at that similarity."""
    return int(np.ceil(SKETCH / 2 * (1 - np.exp(-4 * SAMPLES * (1 - similarity) / SKETCH))))


def signatures(docs: DataFrame, words: int = 5) -> DataFrame:
    """(doc_id, mark, n_shingles, set1, set2, bands, sketch): mark is a hash of the text as it is, set1 and set2 name the set,
    bands are hashes of (band, samples)."""
    id_type = docs.schema["doc_id"].dataType.simpleString()
    small_batches(docs.sparkSession)

    def run(batches):
        shingle, (mul, add) = Shingles(words), _family()
        band_no = np.arange(BANDS, dtype=np.uint64)
        with np.errstate(over="ignore"):
            for b in batches:
                sizes, one, two, bands, sketches = [], [], [], [], []
                for s in shingle(b.column(2)):
                    sizes.append(len(s))
                    one.append(int(np.bitwise_xor.reduce(_mix(s * _MUL)).view(np.int64)) if len(s) else None)
                    two.append(int(np.add.reduce(_mix(s + _MUL)).view(np.int64)) if len(s) else None)
                    if len(s):
                        least = minhash(s, mul, add)
                        x = band_no
                        for col in least[:BANDED].reshape(BANDS, -1).T:
                            x = _mix(x * _MUL + col)
                        bands.append(x.view(np.int64))
                        sketches.append(odd_sketch(least))
                    else:
                        bands.append(None)
                        sketches.append(None)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(sizes, pa.int64()), pa.array(one, pa.int64()), pa.array(two, pa.int64()), pa.array(bands, pa.list_(pa.int64())), pa.array(sketches, pa.list_(pa.int64()))], ["doc_id", "mark", "n_shingles", "set1", "set2", "bands", "sketch"])

    return docs.select("doc_id", F.xxhash64("text").alias("mark"), "text").mapInArrow(tidy(run), f"doc_id {id_type}, mark long, n_shingles long, set1 long, set2 long, bands array<long>, sketch array<long>")


def confirmed(pairs: DataFrame, texts: DataFrame, percent: int, words: int) -> DataFrame:
    """Those of pairs (a, b) whose full shingle sets have 100 * common >= percent * union; texts: (id, text)."""
    a, b = texts.select(F.col("id").alias("a"), F.col("text").alias("text_a")), texts.select(F.col("id").alias("b"), F.col("text").alias("text_b"))

    def run(batches):
        shingle = Shingles(words)
        with np.errstate(over="ignore"):
            for x in batches:
                keep = []
                for p, q in zip(shingle(x.column(2)), shingle(x.column(3)), strict=True):
                    common = len(np.intersect1d(p, q, assume_unique=True))
                    keep.append(bool(100 * common >= percent * (len(p) + len(q) - common)))
                yield pa.RecordBatch.from_arrays([x.column(0), x.column(1)], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return pairs.join(a, "a").join(b, "b").select("a", "b", "text_a", "text_b").mapInArrow(tidy(run), "a long, b long")


def _against_blocks(live: DataFrame, named: DataFrame, sizes: DataFrame, few: DataFrame, texts: DataFrame, percent: int, words: int, far: int) -> DataFrame:
    """Links (a, b) between documents and large components other than theirs; one link to a block is enough for each."""
    block = F.pmod(F.xxhash64("id"), F.col("blocks"))
    there = live.filter("blocks is not null").select("bucket", "c", block.alias("block")).distinct()
    here = live.select("bucket", F.col("id").alias("x"), F.col("c").alias("own"))
    meets = here.join(there, "bucket").filter("own <> c").select("x", "c", "block").distinct()
    chunks = meets.groupBy("c", "block").agg(F.ceil(F.count("*") / BLOCK).alias("chunks"))
    meets = meets.join(chunks, ["c", "block"]).select("c", "block", F.pmod(F.xxhash64("x"), F.col("chunks")).alias("chunk"), F.col("x").alias("id"))
    members = named.select(F.col("node").alias("id"), F.col("component").alias("c")).join(sizes, "c").withColumn("blocks", F.ceil(F.col("size") / BLOCK)).select("id", "c", block.alias("block"))
    members = members.join(chunks, ["c", "block"]).select("c", "block", F.explode(F.sequence(F.lit(0).cast("long"), F.col("chunks") - 1)).alias("chunk"), "id")

    def with_text(df: DataFrame):
        # Fresh names, since both sides read the same tables.
        all_ = df.join(few, "id").join(texts, "id").select(*[F.col(c).alias(c) for c in ("c", "block", "chunk", "id", "n", "sketch", "text")])
        return all_.groupBy("c", "block", "chunk")

    def compare(left: pa.Table, right: pa.Table) -> pa.Table:
        out = []
        if left.num_rows and right.num_rows:
            shingle = Shingles(words)
            with np.errstate(over="ignore"):
                ids, n, bits, sets = [], [], [], []
                for t in (left, right):
                    t = t.combine_chunks()
                    ids.append(t.column("id").to_numpy())
                    n.append(t.column("n").to_numpy())
                    bits.append(np.array(t.column("sketch").combine_chunks().flatten().to_numpy()).view(np.uint64).reshape(t.num_rows, -1))
                    sets.append(shingle(t.column("text").combine_chunks()))
                for k in range(left.num_rows):
                    near = (np.bitwise_count(bits[0][k] ^ bits[1]).sum(1) <= far) & (100 * np.minimum(n[0][k], n[1]) >= percent * np.maximum(n[0][k], n[1]))
                    for m in np.flatnonzero(near):
                        p, q = sets[0][k], sets[1][m]
                        common = len(np.intersect1d(p, q, assume_unique=True))
                        if 100 * common >= percent * (len(p) + len(q) - common):
                            out.append((int(ids[0][k]), int(ids[1][m])))
                            break
        return pa.table({"a": pa.array([a for a, _ in out], pa.int64()), "b": pa.array([b for _, b in out], pa.int64())})

    return with_text(meets).cogroup(with_text(members)).applyInArrow(compare, "a long, b long")


def classes(docs: DataFrame, percent: int = 75, words: int = 5) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for each row of docs (doc_id, text)."""
    return _classes(docs, percent, words).drop("mark")


def _classes(docs: DataFrame, percent: int, words: int, leader_rounds: int = 2, most_rounds: int = 6) -> DataFrame:
    """classes and mark, the hash of the row's text."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    sig = cut(signatures(docs, words))
    # One class for each set, numbered; its name is its smallest doc_id, and the text of that row stands for all of them.
    reps = sig.filter("set1 is not null and doc_id is not null").groupBy("set1", "set2", "n_shingles").agg(F.min("doc_id").alias("name"), F.min_by(F.struct("bands", "sketch", "mark"), "doc_id").alias("s"))
    reps = cut(reps.select("name", "set1", "set2", F.col("n_shingles").alias("n"), "s.bands", "s.sketch", "s.mark"))
    reps = reps.withColumn("id", F.monotonically_increasing_id())  # over checkpointed partitions: the same each time
    rows = reps.select("id", F.posexplode("bands").alias("band", "bucket"))
    shared = rows.groupBy("bucket").agg(F.count("*").alias("members")).filter("members > 1").select("bucket")
    rows = cut(rows.join(shared, "bucket"))
    few = reps.select("id", "n", "sketch")
    far = most_different_bits(FLOOR)
    differing = sum((F.bit_count(F.col("sa")[k].bitwiseXOR(F.col("sb")[k])) for k in range(SKETCH // 64)), F.lit(0))

    def likely(pairs: DataFrame) -> DataFrame:
        both = pairs.join(few.select(F.col("id").alias("a"), F.col("n").alias("na"), F.col("sketch").alias("sa")), "a").join(few.select(F.col("id").alias("b"), F.col("n").alias("nb"), F.col("sketch").alias("sb")), "b")
        near = (100 * F.least("na", "nb") >= percent * F.greatest("na", "nb")) & (differing <= far)
        return both.filter(near).select("a", "b")

    wanted = reps.join(rows.select("id").distinct(), "id", "left_semi").select("id", F.col("name").alias("doc_id"), "mark")
    texts = docs.withColumn("mark", F.xxhash64("text")).join(cut(wanted), ["doc_id", "mark"]).select("id", "text")
    texts = cut(texts.dropDuplicates(["id"]))

    def leaders(live: DataFrame, turn: int) -> DataFrame:
        order = F.col("id") if turn == 0 else F.xxhash64("id", F.lit(turn))
        lead = live.groupBy("bucket").agg(F.min_by(F.struct(F.col("id").alias("lead"), F.col("c").alias("lead_c")), order).alias("l")).select("bucket", "l.*")
        return live.join(lead, "bucket").filter("c <> lead_c").select(F.least("id", "lead").alias("a"), F.greatest("id", "lead").alias("b")).distinct()

    def joined_up(named: DataFrame | None, new: DataFrame) -> DataFrame:
        edges = new.select(F.col("a").alias("src"), F.col("b").alias("dst"))
        return cut(components(edges if named is None else edges.unionByName(named.select(F.col("node").alias("src"), F.col("component").alias("dst")))))

    named, live, apart_before = None, rows.withColumn("c", F.col("id")), None
    for turn in range(most_rounds):
        named = joined_up(named, confirmed(likely(leaders(live, turn)), texts, percent, words))
        marked = rows.join(named, rows["id"] == named["node"], "left").select("bucket", "band", "id", F.coalesce("component", "id").alias("c"))
        open_ = marked.groupBy("bucket").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).filter("lo < hi").select("bucket", "lo")
        live = cut(marked.join(open_, "bucket"))
        # Leaders are worth another round while they settle a tenth of the members outside their bucket's first component.
        apart = live.filter("c <> lo").count()
        if turn + 1 >= leader_rounds and apart_before is not None and apart > 0.9 * apart_before or not apart:
            break
        apart_before = apart
    # The rest: all members of a bucket in different components, held against their sketches where they meet.
    # Large components are held block by block, each block against chunks of the documents that share a bucket with it.
    sizes = named.groupBy(F.col("component").alias("c")).agg(F.count("*").alias("size")).filter(F.col("size") >= LARGE)
    live = cut(live.join(sizes, "c", "left").withColumn("blocks", F.ceil(F.col("size") / BLOCK)).drop("size"))
    against = _against_blocks(live, named, sizes, few, texts, percent, words, far)
    known = live.filter("blocks is null").select("bucket", "band", "id", "c")
    many = known.groupBy("bucket").agg(F.ceil(F.count("*") / BLOCK).alias("parts"))
    known = known.join(many, "bucket").join(reps.select("id", "n", "bands", "sketch"), "id").withColumn("part", F.pmod(F.xxhash64("id"), F.col("parts")))
    # A bucket is cut into parts; the members of parts i and j meet under (lesser, greater), so a hot bucket is many small joins.
    other = F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)).alias("other")
    known = known.select("bucket", "band", "id", "c", "n", "bands", "sketch", "part", other).withColumns({"lo": F.least("part", "other"), "hi": F.greatest("part", "other")})
    x, y = (known.select("bucket", "lo", "hi", *[F.col(c).alias(f"{c}_{t}") for c in ("band", "id", "c", "n", "bands", "sketch", "part")]) for t in "xy")
    bits = sum((F.bit_count(F.col("sketch_x")[k].bitwiseXOR(F.col("sketch_y")[k])) for k in range(SKETCH // 64)), F.lit(0))
    near = (F.col("id_x") < F.col("id_y")) & (F.col("c_x") != F.col("c_y")) & (100 * F.least("n_x", "n_y") >= percent * F.greatest("n_x", "n_y")) & (bits <= far)
    once = (F.col("part_x") != F.col("part_y")) | (x["lo"] == x["hi"])
    earlier = F.zip_with(F.slice("bands_x", F.lit(1), F.col("band_x")), F.slice("bands_y", F.lit(1), F.col("band_x")), lambda p, q: p == q)
    meet = (x["bucket"] == y["bucket"]) & (x["lo"] == y["lo"]) & (x["hi"] == y["hi"])
    rest = x.join(y, meet & once & near & ~F.exists(earlier, lambda same: same)).select(F.col("id_x").alias("a"), F.col("id_y").alias("b"))
    named = joined_up(named, confirmed(rest, texts, percent, words).unionByName(against))
    placed = cut(reps.select("id", "name", "set1", "set2").join(named, F.col("id") == F.col("node"), "left").select("name", "set1", "set2", F.coalesce("component", "id").alias("component")))
    of_set = placed.join(placed.groupBy("component").agg(F.min("name").alias("component_id")), "component").select("set1", "set2", "component_id")
    some = sig.filter("set1 is not null").select("doc_id", "mark", "n_shingles", "set1", "set2").join(of_set, ["set1", "set2"], "left").select("doc_id", "mark", "n_shingles", "component_id")
    none = sig.filter("set1 is null").select("doc_id", "mark", "n_shingles", F.col("doc_id").alias("component_id"))
    return some.unionByName(none).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def survivors(docs: DataFrame, percent: int = 75, words: int = 5) -> DataFrame:
    """The rows of docs that stay: of each component the document with the smallest id; rows without words all stay."""
    gone = _classes(docs, percent, words).filter("not kept").select("doc_id", "mark").distinct()
    same = docs["doc_id"].cast("long").eqNullSafe(gone["doc_id"]) & (F.xxhash64(docs["text"]) == gone["mark"])
    return docs.join(gone, same, "left_anti")

"""Embedding near-dedup with a forest of random-projection trees.

Vectors of one label and length with equal components are one class; classes are indexed, each (label, length) by itself. A
tree splits them by random directions, one for each level, at medians of a bounded sample; vectors within ``spill`` of a split
go to both sides. Leaves hold about ``leaf`` vectors whatever the input's size, since depth follows the count; a group of at
most ``leaf`` is one leaf of one tree. Rows are first placed by id alone, then meet their vectors, once for each leaf. A leaf
over ``block`` vectors is compared block by block in as many tasks, so none is dropped. Within a leaf pairs are compared in
double precision; a pair counts only in the first leaf that brings it together, and a leaf returns a row for each vector (how
many it links with, and the least vector it reaches there). Groups with many links are counted as matrices, so nothing grows with
the square of a group but products and comparisons of whole matrices.

Vectors that are null, zero, or hold null or non-finite components, and those with a null label or vec_id, link with nothing.
Repeated rows are copies; different vectors of one vec_id are compared each, and its rows all get the sum and the least name.
An empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import pickle

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, cut, small

SAMPLE = 20_000  # about so many vectors of a group fit its splits
CHUNK = 20_000  # vectors of a group that one task places
KEY = ["label", "dim"]


class Forest:
    """Directions by tree and level (from a seed), thresholds by node; nodes that the sample doesn't reach use their level's."""

    def __init__(self, dim: int, depth: int, trees: int, seed: int):
        g = np.random.default_rng((seed, dim))
        self.directions = g.standard_normal((trees, depth, dim))
        self.directions /= np.linalg.norm(self.directions, axis=2, keepdims=True)
        self.cuts: list[list[tuple[float, np.ndarray, np.ndarray]]] = []

    def fit(self, x: np.ndarray) -> Forest:
        for tree in self.directions:
            node, levels = np.zeros(len(x), np.int64), []
            for direction in tree:
                p = x @ direction
                base = float(np.median(p)) if len(p) else 0.0
                names, inverse, many = np.unique(node, return_inverse=True, return_counts=True)
                own = np.array([np.median(p[inverse == k]) if n >= 12 else base for k, n in enumerate(many)]) if len(names) <= 4096 else np.full(len(names), base)
                levels.append((base, names, own))
                node = 2 * node + (p >= own[inverse])
            self.cuts.append(levels)
        return self

    def leaves(self, x: np.ndarray, spill: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row, tree, leaf): all leaves that each row of x goes to."""
        out = []
        for t, tree in enumerate(self.directions):
            row, node = np.arange(len(x)), np.zeros(len(x), np.int64)
            for direction, (base, names, own) in zip(tree, self.cuts[t], strict=True):
                p = (x @ direction)[row]
                at = np.minimum(np.searchsorted(names, node), len(names) - 1)
                cuts = np.where(names[at] == node, own[at], base) if len(names) else np.full(len(p), base)
                left, right = p < cuts + spill, p >= cuts - spill
                row, node = np.concatenate((row[left], row[right])), np.concatenate((2 * node[left], 2 * node[right] + 1))
            out.append((row, np.full(len(row), t, np.int32), node))
        return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def _unit(vectors: pa.ChunkedArray | pa.Array, rows: int) -> np.ndarray:
    if isinstance(vectors, pa.ChunkedArray):
        vectors = vectors.combine_chunks()
    x = np.array(vectors.flatten().to_numpy(zero_copy_only=False), np.float64).reshape(rows, -1)
    x /= np.abs(x).max(axis=1, keepdims=True)  # so that no square is lost or overflows
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _near(x: np.ndarray, threshold: float) -> np.ndarray:
    """Which pairs of unit rows have cosine >= threshold in double precision, none with itself. Single precision decides the clear
    ones; those within its error of the threshold are computed again."""
    single, margin = x.astype(np.float32), 1e-6 * (8 + x.shape[1])
    cosines = single @ single.T
    near = cosines >= threshold - margin
    u, w = np.nonzero(near & (cosines < threshold + margin))
    for at in range(0, len(u), 1 << 16):
        part = slice(at, at + (1 << 16))
        near[u[part], w[part]] = np.einsum("ij,ij->i", x[u[part]], x[w[part]]) >= threshold
    np.fill_diagonal(near, False)
    return near & near.T


def _least_reached(u: np.ndarray, w: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """The least id that each row reaches over the links (u, w), both ways."""
    least = ids.copy()
    while True:
        new = least.copy()
        np.minimum.at(new, u, least[w])
        np.minimum.at(new, w, least[u])
        if (new == least).all():
            return least
        least = new


DENSE = 64  # links of a row from which its group is counted as a matrix


def _group(near: np.ndarray, row: int) -> np.ndarray:
    """The rows that row reaches, itself included."""
    seen = np.zeros(len(near), bool)
    seen[row] = True
    edge = np.array([row])
    while len(edge):
        edge = np.flatnonzero(near[edge].any(axis=0) & ~seen)
        seen[edge] = True
    return np.flatnonzero(seen)


def _met_before(earlier: pa.Array, u: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Whether the rows u and w share a leaf of those listed in earlier, a list for each row."""
    size = earlier.value_lengths().to_numpy()
    codes = np.repeat(-1 - np.arange(len(size))[:, None], size.max(initial=0), axis=1)  # padded by a number of that row only
    codes[np.arange(codes.shape[1]) < size[:, None]] = earlier.flatten().to_numpy()
    out = np.zeros(len(u), bool)
    for at in range(0, len(u), 1 << 14):
        part = slice(at, at + (1 << 14))
        a, b = codes[u[part]], codes[w[part]]
        for k in range(codes.shape[1]):
            out[part] |= (a[:, k : k + 1] == b).any(axis=1)
    return out


def _met_in_group(earlier: pa.Array) -> np.ndarray:
    """As _met_before for all pairs of rows: the product of the matrix of rows and listed leaves with itself."""
    _, code = np.unique(earlier.flatten().to_numpy(), return_inverse=True)
    in_leaf = np.zeros((len(earlier), int(code.max(initial=-1)) + 1), np.float32)
    in_leaf[np.repeat(np.arange(len(earlier)), earlier.value_lengths().to_numpy()), code] = 1.0
    return in_leaf @ in_leaf.T > 0


def _counted(near: np.ndarray, earlier: pa.Array, copies: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(others, least) of each row: copies of the rows it links with here and in no earlier leaf, and the least id it reaches. Groups
    with many links stay matrices, so that their pairs are neither listed nor held against each other's leaves one by one."""
    others, least, sparse = np.zeros(len(ids), np.int64), ids.copy(), np.ones(len(ids), bool)
    for row in np.flatnonzero(near.sum(axis=1) >= DENSE):
        if not sparse[row]:
            continue
        rows = _group(near, row)
        sparse[rows], least[rows] = False, ids[rows].min()
        new = near[np.ix_(rows, rows)] & ~_met_in_group(earlier.take(pa.array(rows)))
        for at in range(0, len(rows), 512):
            others[rows[at : at + 512]] = (new[at : at + 512].astype(np.float64) @ copies[rows]).astype(np.int64)
    rows = np.flatnonzero(sparse & near.any(axis=1))
    u, w = (rows[k] for k in np.nonzero(np.triu(near[np.ix_(rows, rows)])))
    least = _least_reached(u, w, least)
    new = ~_met_before(earlier, u, w)
    np.add.at(others, u[new], copies[w[new]])
    np.add.at(others, w[new], copies[u[new]])
    return others, least


def links(vectors: DataFrame, threshold: float = 0.93, trees: int = 10, leaf: int = 512, spill: float = 0.022, block: int = 1536, seed: int = 7) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(classes, members, found): classes (id, name, label, dim, copies, v), members (vec_id, id), found (id, others, least): rows
    for a class, how many vectors it links with (to be summed), and the least id it reaches in that leaf."""
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), "label", F.col("embedding").alias("v"))
    element = rows.schema["v"].dataType.elementType.simpleString()
    if element != "float":  # floats stay floats on the way: half the bytes, and no digit is lost
        element, rows = "double", rows.withColumn("v", F.col("v").cast("array<double>"))
    fine = F.col("label").isNotNull() & F.col("v").isNotNull() & F.coalesce(~F.exists("v", lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf"))) & F.exists("v", lambda c: c != 0.0), F.lit(False))
    good = rows.filter(fine & F.col("vec_id").isNotNull()).withColumn("v", F.transform("v", lambda c: (c + F.lit(0.0)).cast(element)))
    classes = cut(good.groupBy("label", "v").agg(F.min("vec_id").alias("name"), F.count("*").alias("copies")))
    classes = classes.withColumns({"id": F.monotonically_increasing_id(), "dim": F.size("v")})  # over checkpointed partitions: the same each time
    members = good.join(classes.select("label", "v", "id"), ["label", "v"]).select("vec_id", "id")
    label = f"label {vectors.schema['label'].dataType.simpleString()}, dim int"
    sizes = cut(classes.groupBy(*KEY).agg(F.count("*").alias("n")).filter("n > 1"))
    large = small(sizes.filter(F.col("n") > leaf).withColumn("chunks", F.ceil(F.col("n") / CHUNK)))
    split = classes.join(large, KEY)

    def fit(key: tuple, t: pa.Table) -> pa.Table:
        n = int(t.column("n")[0].as_py())
        depth = int(np.ceil(np.log2(n / leaf)))
        forest = Forest(key[1].as_py(), depth, trees, seed).fit(_unit(t.column("v"), t.num_rows))
        return pa.table({"label": t.column("label").slice(0, 1), "dim": t.column("dim").slice(0, 1), "model": pa.array([pickle.dumps(forest.cuts)], pa.binary()), "depth": pa.array([depth], pa.int32())})

    sampled = split.filter(F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(1 << 40)) < F.lit(float(SAMPLE << 40)) / F.col("n")).select(*KEY, "n", "v")
    models = cut(sampled.groupBy(*KEY).applyInArrow(fit, f"{label}, model binary, depth int"))

    def place(left: pa.Table, right: pa.Table) -> pa.Table:
        kinds = {"id": pa.int64(), "tree": pa.int32(), "node": pa.int64(), "earlier": pa.list_(pa.int64())}
        if not left.num_rows or not right.num_rows:
            return pa.table({k: pa.array([], t) for k, t in kinds.items()})
        ids = left.column("id").to_numpy()
        x = _unit(left.column("v"), len(ids))
        forest = Forest(x.shape[1], right.column("depth")[0].as_py(), trees, seed)
        forest.cuts = pickle.loads(right.column("model")[0].as_py())
        row, tree, node = forest.leaves(x, spill)
        order = np.lexsort((node, tree, row))
        row, tree, node = row[order], tree[order], node[order]
        code = (tree.astype(np.int64) << 48) + node
        first = np.searchsorted(row, row)  # the row's first entry, in order of tree and leaf
        before = np.arange(len(row)) - first
        ends = np.cumsum(before)
        listed = np.repeat(first - (ends - before), before) + np.arange(int(before.sum()))  # for each entry, those of its row before it
        earlier = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], ends)).astype(np.int32)), pa.array(code[listed]))
        return pa.table([pa.array(ids[row]), pa.array(tree), pa.array(node), earlier], names=list(kinds))

    dealt = split.withColumn("chunk", F.pmod(F.xxhash64("id"), F.col("chunks"))).select(*KEY, "chunk", "id", "v")
    sent = models.join(large, KEY).select(*KEY, F.explode(F.sequence(F.lit(0).cast("long"), F.col("chunks") - 1)).alias("chunk"), "model", "depth")
    placed = dealt.groupBy(*KEY, "chunk").cogroup(sent.groupBy(*KEY, "chunk")).applyInArrow(place, "id long, tree int, node long, earlier array<long>")
    whole = classes.join(small(sizes.filter(F.col("n") <= leaf)), KEY).select("id", F.lit(0).alias("tree"), F.lit(0).cast("long").alias("node"), F.array().cast("array<long>").alias("earlier"))
    placed = cut(placed.unionByName(whole))
    met = placed.join(classes.select("id", *KEY, "copies", "v"), "id")
    at = [*KEY, "tree", "node"]
    over = placed.join(classes.select("id", *KEY), "id").groupBy(*at).agg(F.count("*").alias("n")).filter(F.col("n") > block).select(*at, F.ceil(F.col("n") / block).alias("blocks"))
    met = met.join(small(cut(over)), at, "left").withColumn("blocks", F.coalesce("blocks", F.lit(1).cast("long"))).withColumn("i", F.pmod(F.xxhash64("id"), F.col("blocks")))
    # Row r of block i goes to the tasks (i, j) and (j, i): each pair of blocks meets in one task.
    met = met.withColumn("j", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    met = met.select(*at, F.greatest("i", "j").alias("p"), F.least("i", "j").alias("q"), "i", "id", "copies", "earlier", "v")

    def compare(t: pa.Table) -> pa.Table:
        none = pa.table({"id": pa.array([], pa.int64()), "others": pa.array([], pa.int64()), "least": pa.array([], pa.int64())})
        if t.num_rows < 2:
            return none
        ids, i, copies = (t.column(c).to_numpy() for c in ("id", "i", "copies"))
        x = _unit(t.column("v"), len(ids))
        near = _near(x, threshold)
        if t.column("p")[0].as_py() != t.column("q")[0].as_py():
            near &= i[:, None] != i[None, :]
        some = near.any(axis=1)
        if not some.any():
            return none
        others, least = _counted(near, t.column("earlier").combine_chunks(), copies, ids)
        return pa.table({"id": ids[some], "others": others[some], "least": least[some]})

    found = cut(met.groupBy(*at, "p", "q").applyInArrow(compare, "id long, others long, least long"))
    return classes, members, found


def classes_of(vectors: DataFrame, threshold: float = 0.93, **how) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for each row of vectors (vec_id, label, embedding)."""
    classes, members, found = links(vectors, threshold, **how)
    linked = found.groupBy(F.col("id").alias("own")).agg(F.sum("others").alias("others"))
    named = components(found.filter("id <> least").select(F.col("id").alias("src"), F.col("least").alias("dst")).distinct())
    figures = classes.select("id", "name", "copies").join(linked, F.col("id") == F.col("own"), "left").join(named, F.col("id") == F.col("node"), "left")
    figures = cut(figures.select("id", "name", (F.col("copies") - 1 + F.coalesce("others", F.lit(0))).alias("n_links"), F.coalesce("component", "id").alias("component")))
    figures = figures.join(figures.groupBy("component").agg(F.min("name").alias("component_id")), "component")
    some = members.distinct().join(figures, "id").groupBy(F.col("vec_id").alias("own")).agg(F.sum("n_links").alias("n_links"), F.min("component_id").alias("component_id"))
    every = vectors.select(F.col("vec_id").cast("long").alias("vec_id"))
    got = every.join(some, F.col("vec_id") == F.col("own"), "left")
    return got.select("vec_id", F.coalesce("n_links", F.lit(0).cast("long")).alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id")).withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))

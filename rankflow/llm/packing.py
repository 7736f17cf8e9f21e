"""Best-fit packing by bin completion with branch and bound, on the histogram of piece lengths.

Only lengths matter to a packing, and there are at most ``capacity`` of them, so the driver plans with counts: a list of
(filling, how often). Best-fit decreasing gives the first incumbent. The search is depth first with undo: it completes the bin
of the largest piece left with the undominated fillings in order of waste, each as often as the counts allow and then, as a
branch of its own, once; and it turns back where bins so far and remaining volume can't beat the incumbent, that is where the
waste is over what a better packing may waste. A filling is dominated if a longer piece fits in place of one of its pieces, or
a single one in place of two. The search ends at the lower bound, when all branches are done (both prove the result), or
after ``nodes`` steps, a number that grows with the distinct lengths; either way all pieces are placed. Pieces are numbered
within their length by two-level counts and find their place by one search in the plan, which stays under a few times
``capacity`` entries however many rows there are.

Null or empty texts are the end id alone; equal or repeated rows are separate pieces, and which of equal pieces goes where is
open; a very long text is cut into many pieces, worked on by one task; an empty table gives an empty one. Only doc_id and text
are read, so further columns can't clash.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, small_batches, tidy
from .tokens import encoder


def lower_bound(counts: np.ndarray, capacity: int) -> int:
    """Bins that any packing needs: volume, raised by pieces over half that no small piece can join (Martello-Toth)."""
    size = np.arange(len(counts))
    best = -(-int((size * counts).sum()) // capacity)
    for k in np.flatnonzero(counts[: capacity // 2 + 1]):
        big, mid = size > capacity - k, (size <= capacity - k) & (2 * size > capacity)
        low = (size >= k) & (2 * size <= capacity)
        room = int(counts[mid].sum()) * capacity - int((size * counts)[mid].sum())
        best = max(best, int(counts[big].sum() + counts[mid].sum()) + max(0, -(-(int((size * counts)[low].sum()) - room) // capacity)))
    return best


def best_fit(counts: np.ndarray, capacity: int) -> list[tuple[dict, int]]:
    """Best-fit decreasing, all pieces of a length at once. Open bins are stacked by the room they have."""
    room: dict[int, list] = {}
    for size in range(len(counts) - 1, 0, -1):
        left = int(counts[size])
        while left:
            fit = min((r for r in room if r >= size), default=None)
            if fit is None:
                room.setdefault(capacity, []).append([{}, left])
                continue
            filling, n = room[fit].pop()
            if not room[fit]:
                del room[fit]
            each = min(fit // size, left)
            use = min(n, left // each)
            if n > use:
                room.setdefault(fit, []).append([filling, n - use])
            room.setdefault(fit - each * size, []).append([filling | {size: filling.get(size, 0) + each}, use])
            left -= use * each
    return [(f, n) for stack in room.values() for f, n in stack if f]


def dominated(filling: tuple[int, ...], room: int, left: np.ndarray, sizes: np.ndarray) -> bool:
    """Whether a piece not in the filling fits in place of a shorter one of its pieces (but the first), or of two of them."""

    def spare(low: int, high: int) -> bool:
        for s in sizes[np.searchsorted(sizes, low) : np.searchsorted(sizes, high, "right")]:
            if left[s] > filling.count(int(s)):
                return True
        return False

    rest = filling[1:]
    if room and any(spare(s + 1, s + room) for s in set(rest)):
        return True
    return any(spare(s + t, s + t + room) for s, t in set(combinations(rest, 2)))


def fillings(left: np.ndarray, capacity: int, width: int, effort: int) -> tuple[list[dict], bool]:
    """(undominated fillings around the largest piece left, least waste first; whether these are all of them).

    Depth first from long pieces to short ones; where one piece or two fill the room exactly that is tried first. Ends after
    ``width`` fillings without waste or ``effort`` steps."""
    sizes = np.flatnonzero(left)
    top = int(sizes[-1])
    found: dict[tuple[int, ...], int] = {}

    def have(chosen: tuple[int, ...], *more: int) -> bool:
        return all(left[s] >= (*chosen, *more).count(s) for s in more)

    def put(chosen: tuple[int, ...], room: int) -> None:
        chosen = (top, *sorted(chosen[1:], reverse=True))
        if chosen not in found and not dominated(chosen, room, left, sizes):
            found[chosen] = room

    def enter(chosen: tuple[int, ...], room: int) -> None:
        longest = min(chosen[-1], room)
        if room and room <= chosen[-1] and have(chosen, room):
            put((*chosen, room), 0)
        elif room > 1:
            firsts = sizes[np.searchsorted(sizes, (room + 1) // 2) : np.searchsorted(sizes, min(longest, room - 1), "right")]
            pairs = firsts[left[room - firsts] > 0][::-1] if len(firsts) else firsts
            for s in pairs[:width].tolist():
                if have(chosen, s, room - s):
                    put((*chosen, s, room - s), 0)
        at = int(np.searchsorted(sizes, longest, "right")) - 1
        fits = False
        if at >= 0:
            stack.append((chosen, room, at))
            fits = any(have(chosen, int(s)) for s in sizes[: at + 1][::-1][: len(chosen) + 1])
        if not fits:
            put(chosen, room)

    stack: list[tuple[tuple[int, ...], int, int]] = []
    enter((top,), capacity - top)
    steps = 0
    while stack and steps < effort and sum(not w for w in found.values()) < width:
        chosen, room, at = stack.pop()
        if at > 0:
            stack.append((chosen, room, at - 1))
        s = int(sizes[at])
        if have(chosen, s):
            steps += 1
            enter((*chosen, s), room - s)
    whole = not stack
    if not found:  # out of effort before any filling was whole: first fit
        chosen, room = (top,), capacity - top
        for s in sizes[::-1].tolist():
            while s <= room and have(chosen, s):
                chosen, room = (*chosen, s), room - s
        found[chosen] = room
    order = sorted(found, key=lambda c: (found[c], len(c), [-s for s in c]))
    return [{s: c.count(s) for s in dict.fromkeys(c)} for c in order[: None if whole else 2 * width]], whole


def search(counts: np.ndarray, capacity: int, nodes: int | None = None, width: int = 3, effort: int = 120) -> tuple[list[tuple[dict, int]], bool]:
    """(plan, whether it is proved to have the fewest bins). The plan: fillings and how often each is used; together they hold
    exactly counts[length] pieces of each length."""
    left = counts.astype(np.int64).copy()
    left[0] = 0
    best = best_fit(left, capacity)
    used, bound = sum(n for _, n in best), lower_bound(left, capacity)
    nodes = 1000 + 3 * int(np.count_nonzero(left)) // 2 if nodes is None else nodes
    volume, bins, whole = int((np.arange(len(left)) * left).sum()), 0, True
    path: list[tuple[dict, int]] = []
    branches: list[list[tuple[dict, int]]] = []  # what is still to be tried, for each depth
    while used > bound:
        if not volume:
            if bins < used:
                best, used = list(path), bins
        elif bins + -(-volume // capacity) < used:
            if nodes <= 0:
                return best, False
            nodes -= 1
            options, all_ = fillings(left, capacity, width, effort)
            whole &= all_
            often = [min(int(left[s]) // k for s, k in f.items()) for f in options]
            branches.append([*((f, 1) for f, n in zip(options, often, strict=True) if n > 1), *reversed(list(zip(options, often, strict=True)))])
            path.append(({}, 0))
        while branches:  # to the next branch, from the deepest
            filling, n = path.pop()
            for s, k in filling.items():
                left[s] += n * k
                volume += s * n * k
            bins -= n
            if branches[-1]:
                filling, n = branches[-1].pop()
                for s, k in filling.items():
                    left[s] -= n * k
                    volume -= s * n * k
                bins += n
                path.append((filling, n))
                break
            branches.pop()
        else:
            return best, whole
    return best, True


def plan(counts: np.ndarray, capacity: int, **how) -> list[tuple[dict, int]]:
    return search(counts, capacity, **how)[0]


def pieces(docs: DataFrame, tokenizer_path: str, end_id: int, capacity: int, keeps_space: bool, added_tokens: bool = False) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32): each document's ids with the end id, cut only where longer than capacity."""
    id_type = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        encode = encoder(tokenizer_path, keeps_space, added_tokens)
        tail = np.array([end_id], "<u4").tobytes()
        for b in batches:
            rows = []
            for doc, ids in zip(b.column(0).to_pylist(), encode.each(b.column(1)), strict=True):
                mine = ids + tail
                for p in range(0, len(mine), 4 * capacity):
                    part = mine[p : p + 4 * capacity]
                    rows.append((doc, p // (4 * capacity), p >> 2, len(part) >> 2, zlib.crc32(part)))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (b.column(0).type, pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)] if rows else [pa.array([], t) for t in (b.column(0).type, pa.int32(), pa.int64(), pa.int64(), pa.int64())], ["doc_id", "piece", "start", "length", "ids_crc32"])

    small_batches(docs.sparkSession)
    return docs.select("doc_id", "text").mapInArrow(tidy(run), f"doc_id {id_type}, piece int, start long, length long, ids_crc32 long")


def pack(items: DataFrame, capacity: int, planner: Callable = plan, rows_per_rank: int = 1_000) -> DataFrame:
    """items (with doc_id, piece, length) and sequence_id, offset. Lengths must be 1 to capacity."""
    items = cut(items)
    hist = {r[0]: r[1] for r in items.groupBy("length").count().collect()}  # capacity rows at most
    if not hist:
        return items.withColumns({"sequence_id": F.lit(0).cast("long"), "offset": F.lit(0).cast("long")})
    counts = np.zeros(capacity + 1, np.int64)
    for k, n in hist.items():
        counts[k] = n
    keys, first_bin, per_bin, before, bins = [], [], [], [], 0
    taken = np.zeros(capacity + 1, np.int64)
    for filling, n in planner(counts, capacity):
        at = 0
        for size, k in sorted(filling.items(), reverse=True):
            keys.append((size << 44) + int(taken[size]))
            first_bin.append(bins)
            per_bin.append(k)
            before.append(at)
            taken[size] += n * k
            at += size * k
        bins += n
    if (taken != counts).any():
        raise AssertionError("the plan doesn't hold every piece once")
    order = np.argsort(np.array(keys, np.int64))
    keys, first_bin, per_bin, before = (np.array(x, np.int64)[order] for x in (keys, first_bin, per_bin, before))

    # The rank of a piece among those of its length: pieces before its slice, and its place in the slice.
    spark = items.sparkSession
    cuts = spark.createDataFrame([(int(k), int(n // rows_per_rank + 1)) for k, n in hist.items()], "length long, cuts long")
    part = items.join(F.broadcast(cuts), "length").withColumn("slice", F.pmod(F.xxhash64("doc_id", "piece"), F.col("cuts"))).drop("cuts")
    upto = Window.partitionBy("length").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    starts = part.groupBy("length", "slice").count().withColumn("from", F.coalesce(F.sum("count").over(upto), F.lit(0))).drop("count")
    within = Window.partitionBy("length", "slice").orderBy("doc_id", "piece")
    ranked = part.join(starts, ["length", "slice"]).withColumn("rank", F.col("from") + F.row_number().over(within) - 1).drop("slice", "from")
    names = [c for c in items.columns]
    ranked = ranked.select(*names, "rank")
    at_length, at_rank = names.index("length"), len(names)

    def place(batches):
        for b in batches:
            size, rank = b.column(at_length).to_numpy(), b.column(at_rank).to_numpy()
            k = np.searchsorted(keys, (size << 44) + rank, "right") - 1
            nth = (size << 44) + rank - keys[k]
            cols = [b.column(i) for i in range(at_rank)] + [pa.array(first_bin[k] + nth // per_bin[k]), pa.array(before[k] + nth % per_bin[k] * size)]
            yield pa.RecordBatch.from_arrays(cols, [*names, "sequence_id", "offset"])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in items.schema)
    return ranked.mapInArrow(place, f"{kinds}, sequence_id long, offset long")


def pack_documents(docs: DataFrame, tokenizer_path: str, end_id: int = 1, capacity: int = 4096, keeps_space: bool = False, added_tokens: bool = False) -> DataFrame:
    """added_tokens: strings of the vocabulary's added tokens become their ids, as the library does by default; else no text
    can make a control id."""
    return pack(pieces(docs, tokenizer_path, end_id, capacity, keeps_space, added_tokens), capacity).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")

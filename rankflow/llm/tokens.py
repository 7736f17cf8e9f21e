"""Exact fast tokenising with byte-level BPE vocabularies of the tokenizers library.

Both public vocabularies cut a text at single white space before any merge, so the ids of a text are those of its pieces in
order. Arrow cuts a stretch of texts and numbers its distinct pieces. A piece of Latin letters goes through the vocabulary's
merges together with all others not met before, as rows of one array (neither splitting nor normalising changes such a
piece); other pieces go to the library. Texts with irregular white space or with the string of an added token go to the
library whole. Pieces that occur more than once in a stretch are remembered, up to a bound of memory; an encoder is kept
between the tasks of a worker process.
"""

from __future__ import annotations

import json
import re
from array import array
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

_S = r"[\t-\r \x1c-\x1f]"
IRREGULAR = rf"{_S}{_S}|^{_S}|{_S}$|[\x1f\x{{85}}\x{{A0}}\x{{1680}}\x{{2000}}-\x{{200A}}\x{{2028}}\x{{2029}}\x{{202F}}\x{{205F}}\x{{3000}}]"
#: Latin letters with and without marks; both vocabularies keep a run of them in one piece. Without U+0130, whose lower case is two code points.
LETTER = "A-Za-z\u00C0-\u00D6\u00D8-\u00F6\u00F8-\u012F\u0131-\u02AF"
#: ASCII marks but the apostrophe, which may begin a piece together with letters.
MARK = r"!-&(-/:-@\[-`{-~"
NONE = np.int32(1 << 30)  # the rank of a pair that is never merged


def _byte_letters() -> dict[int, str]:
    """Byte-level vocabularies write a byte as a letter: printable ones as themselves, the rest as those from 256 on."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    others = (b for b in range(256) if b not in plain)
    return {b: chr(b) for b in plain} | {b: chr(256 + k) for k, b in enumerate(others)}


@cache
def encoder(path: str, keeps_space: bool, added_tokens: bool) -> Encoder:
    """One for each process."""
    return Encoder(path, keeps_space, added_tokens)


class Merges:
    """A vocabulary's merges on many short words at once: in each step every word merges its first pair of least rank."""

    BITS = 18

    def __init__(self, model: dict):
        vocab, letters, suffix = model["vocab"], _byte_letters(), model.get("end_of_word_suffix") or ""
        self.inner = np.array([vocab[letters[b]] for b in range(256)], np.int32)
        self.last = np.array([vocab[letters[b] + suffix] for b in range(256)], np.int32)
        pairs = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        self.made = np.array([vocab[a + b] for a, b in pairs], np.int32)
        keys = np.array([vocab[a] for a, _ in pairs], np.int64) << 32 | np.array([vocab[b] for _, b in pairs], np.int64)
        # Open addressing; all keys that are still to be placed try their next slot together.
        self.keys, self.rank = np.full(1 << self.BITS, -1, np.int64), np.full(1 << self.BITS, NONE, np.int32)
        left, slot = np.arange(len(keys)), self._slot(keys)
        while len(left):
            free = self.keys[slot] < 0
            at, first = np.unique(slot[free], return_index=True)
            own = left[free][first]
            self.keys[at], self.rank[at] = keys[own], own
            rest = ~np.isin(left, own)
            left, slot = left[rest], (slot[rest] + 1) & ((1 << self.BITS) - 1)

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return (keys.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - self.BITS)).view(np.int64)

    def ranks(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        key = a.astype(np.int64) << 32 | b
        slot = self._slot(key)
        found = self.keys[slot]
        out = self.rank[slot]
        k = np.flatnonzero((found != key) & (found >= 0))
        out[found != key] = NONE
        while len(k):
            slot[k] = (slot[k] + 1) & ((1 << self.BITS) - 1)
            found = self.keys[slot[k]]
            hit = found == key[k]
            out[k[hit]] = self.rank[slot[k[hit]]]
            k = k[~hit & (found >= 0)]
        return out

    def __call__(self, words: pa.Array) -> list[bytes]:
        """Ids (little-endian, 4 bytes each) of words, none of them empty."""
        words = words.cast(pa.large_binary())
        start = np.frombuffer(words.buffers()[1], np.int64)[words.offset : words.offset + len(words) + 1]
        data, size = np.frombuffer(words.buffers()[2], np.uint8), np.diff(start)
        out: list[bytes] = [b""] * len(words)
        order = np.argsort(size, kind="stable")
        for at in range(0, len(order), 4096):  # words of about one length, few enough to stay in the cache
            rows = order[at : at + 4096]
            for r, ids in zip(rows.tolist(), self._merged(data, start[rows], size[rows]), strict=True):
                out[r] = ids
        return out

    def _merged(self, data: np.ndarray, start: np.ndarray, size: np.ndarray) -> list[bytes]:
        n, width = len(size), int(size.max()) + 1  # one column to spare, never filled
        col = np.arange(width)
        byte = data[np.minimum(start[:, None] + col, len(data) - 1)]
        sym = np.where(col < size[:, None], self.inner[byte], np.int32(-1))
        sym[np.arange(n), size - 1] = self.last[byte[np.arange(n), size - 1]]
        rank = np.full((n, width), NONE, np.int32)
        inside = col[1:] < size[:, None]
        rank[:, :-1][inside] = self.ranks(sym[:, :-1][inside], sym[:, 1:][inside])
        done, live = np.full((n, width), -1, np.int32), np.arange(n)
        while len(live):
            p = rank.argmin(1)
            row = np.arange(len(live))
            least = rank[row, p]
            over = least == NONE
            if over.any():
                done[live[over]] = sym[over]
                go = ~over
                live, sym, rank, p, least, row = live[go], sym[go], rank[go], p[go], least[go], row[: int(go.sum())]
                if not len(live):
                    break
            after = col[:-1] > p[:, None]
            sym[:, :-1] = np.where(after, sym[:, 1:], sym[:, :-1])
            rank[:, :-1] = np.where(after, rank[:, 1:], rank[:, :-1])
            new = self.made[least]
            sym[row, p] = new
            follow = sym[row, p + 1]
            rank[row, p] = np.where(follow >= 0, self.ranks(new, np.maximum(follow, 0)), NONE)
            k = np.flatnonzero(p)
            rank[k, p[k] - 1] = self.ranks(sym[k, p[k] - 1], new[k])
        ids = done[done >= 0].astype("<u4").tobytes()
        ends = 4 * np.cumsum((done >= 0).sum(1))
        return [ids[a:b] for a, b in zip([0, *ends[:-1].tolist()], ends.tolist(), strict=True)]


class Encoder:
    """keeps_space: the vocabulary's pieces carry the space before them. added_tokens: their strings in a text become their own
    ids, as is the library's default; else they are ordinary text. most: pieces that are remembered."""

    def __init__(self, path: str, keeps_space: bool, added_tokens: bool = True, most: int = 300_000):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = not added_tokens
        with open(path, encoding="utf-8") as f:
            self.merges = Merges(json.load(f)["model"])
        added = sorted(t.content for t in self.tokenizer.get_added_tokens_decoder().values()) if added_tokens else []
        # In any case of letters: pieces are made lower, and that must not make an added token.
        self.irregular = "|".join([IRREGULAR, *["(?i:" + re.sub(r"([^0-9A-Za-z_\x80-\U0010ffff])", r"\\\1", a) + ")" for a in added]])
        self.keeps_space, self.most = keeps_space, most
        self.word, self.known = f"^{' ?' if keeps_space else ''}[{LETTER}]+$", {"": b""}

    def whole(self, text: str) -> bytes:
        return array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()

    def each(self, texts: pa.Array, stretch: int = 8 << 20) -> Iterator[bytes]:
        """Ids of each text in order (little-endian, 4 bytes each; null: none), worked on in stretches of about so many bytes."""
        texts = pc.fill_null(texts.cast(pa.large_string()), "")
        part = np.cumsum(pc.binary_length(texts).to_numpy()) // stretch
        cuts = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), len(texts)]
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            if a < b:
                yield from self._some(texts.slice(a, b - a))

    def __call__(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in a row (uint32), and where each text's begin, with the end (int64)."""
        got = list(self.each(texts))
        return np.frombuffer(b"".join(got), "<u4"), np.concatenate(([0], np.cumsum([len(g) >> 2 for g in got], dtype=np.int64)))

    def _some(self, texts: pa.Array) -> Iterator[bytes]:
        odd = pc.match_substring_regex(texts, self.irregular)
        cut = pc.if_else(odd, "", texts)
        # Marks between a letter and white space are a piece of their own in either vocabulary.
        if self.keeps_space:
            cut = pc.replace_substring(pc.replace_substring(cut, " ", "\x1f "), "\n", "\x1f\n\x1f")
            cut, mark = pc.replace_substring_regex(cut, rf"([{LETTER}])([{MARK}]+)(\x1f|$)", "\\1\x1f\\2\\3"), "\x1f"
        else:
            cut = pc.ascii_lower(pc.replace_substring(cut, "\n", " "))
            cut, mark = pc.replace_substring_regex(cut, rf"([{LETTER}])([{MARK}]+)( |$)", r"\1 \2\3"), " "
        lists = pc.split_pattern(cut, mark)
        del cut
        numbered = lists.flatten().dictionary_encode()
        of_piece = self._pieces(numbered.dictionary, np.bincount(numbered.indices.to_numpy(), minlength=len(numbered.dictionary)))
        ids = pa.array(of_piece, pa.large_binary()).take(numbered.indices)
        first = lists.offsets.to_numpy()
        ends = np.frombuffer(ids.buffers()[1], np.int64)[first - first[0]].tolist()
        data = memoryview(ids.buffers()[2] or b"")
        for k, whole in enumerate(odd.to_pylist()):
            yield self.whole(texts[k].as_py()) if whole else bytes(data[ends[k] : ends[k + 1]])

    def _pieces(self, pieces: pa.Array, counts: np.ndarray) -> list[bytes]:
        """Ids of distinct pieces."""
        names = pieces.to_numpy(zero_copy_only=False).tolist()
        out = list(map(self.known.get, names))
        new = np.array([k for k, ids in enumerate(out) if ids is None], np.int64)
        if not len(new):
            return out
        texts = pieces.take(pa.array(new))
        words = pc.and_(pc.match_substring_regex(texts, self.word), pc.less_equal(pc.binary_length(texts), 100)).to_numpy(zero_copy_only=False)
        plain = texts.filter(pa.array(words))
        for k, ids in zip(new[words].tolist(), self.merges(plain if self.keeps_space else pc.utf8_lower(plain)) if len(plain) else [], strict=True):
            out[k] = ids
        for k in new[~words].tolist():
            out[k] = self.whole(names[k])
        if len(self.known) + len(new) > self.most:
            self.known = {"": b""}
        often = new[counts[new] > 1][: self.most]
        self.known.update((names[k], out[k]) for k in often.tolist() if len(names[k]) <= 40)
        return out

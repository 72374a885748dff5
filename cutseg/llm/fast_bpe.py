"""Word-level byte-pair encoding in numpy, equal to the tokenizers library.

A vocabulary file with word ends merges inside words only, so a text's ids are
those of its words.  The distinct plain words of a batch (Latin letters, then
full stops, commas and the like) are merged together, one array lane for each;
whatever else a text holds goes through the library itself.
"""

from __future__ import annotations

import json
import os
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

_PLAIN = "^(?P<word>[A-Za-zÀ-ÖØ-öø-ÿ]*)(?P<mark>[.,;:!?]*)$"
_LONGEST = 48
_NONE = np.iinfo(np.int32).max


def _byte_symbols() -> list[str]:
    """The printable stand-in of each byte in byte-level vocabularies."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    other = iter(range(256, 512))
    return [chr(b) if b in set(plain) else chr(next(other)) for b in range(256)]


class _PairTable:
    """(left id, right id) -> merge rank, by two-choice hashing."""

    BITS = 19

    def __init__(self, keys: np.ndarray):
        for seed in range(1, 200):
            self.factors = [np.uint64((2 * seed + k) * 0x9E3779B97F4A7C15 % 2**64 | 1) for k in (0, 7919)]
            self.keys = np.zeros((2, 1 << self.BITS), np.uint64)
            self.ranks = np.full((2, 1 << self.BITS), _NONE, np.int32)
            order, left = np.arange(len(keys), dtype=np.int32), keys
            for t in (0, 1):
                slot = self._slot(t, left)
                _, first = np.unique(slot, return_index=True)
                self.keys[t, slot[first]], self.ranks[t, slot[first]] = left[first], order[first]
                rest = np.ones(len(left), bool)
                rest[first] = False
                order, left = order[rest], left[rest]
            if not len(left):
                return
        raise RuntimeError("no collision-free hash constants found")

    def _slot(self, t: int, keys: np.ndarray) -> np.ndarray:
        return ((keys * self.factors[t]) >> np.uint64(64 - self.BITS)).astype(np.int64)

    def __call__(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        keys = ((left.astype(np.int64) << 20) | (right.astype(np.int64) + 1)).view(np.uint64)
        a, b = self._slot(0, keys), self._slot(1, keys)
        return np.where(self.keys[0][a] == keys, self.ranks[0][a], np.where(self.keys[1][b] == keys, self.ranks[1][b], _NONE))


class WordEncoder:
    """Ids of whole texts; keeps nothing between batches."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)["model"]
        vocab, merges = spec["vocab"], [m.split(" ") if isinstance(m, str) else m for m in spec["merges"]]
        symbols = _byte_symbols()
        self.inner = np.array([vocab[s] for s in symbols], np.int32)
        self.last = np.array([vocab[s + "</w>"] for s in symbols], np.int32)
        left = np.array([vocab[a] for a, _ in merges], np.int64)
        right = np.array([vocab[b] for _, b in merges], np.int64)
        self.merged = np.array([vocab[a + b] for a, b in merges], np.int32)
        self.ranks = _PairTable(((left << 20) | (right + 1)).view(np.uint64))

    def _merge(self, words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of distinct words of at most 48 bytes, flat, and their numbers."""
        words = words.cast(pa.large_binary())
        offsets = np.frombuffer(words.buffers()[1], np.int64)[words.offset:words.offset + len(words) + 1]
        raw = np.concatenate((np.frombuffer(words.buffers()[2] or b"", np.uint8), np.zeros(_LONGEST, np.uint8)))
        length = np.diff(offsets)
        grids, sizes = [], np.zeros(len(words), np.int64)
        for low, high in ((0, 6), (6, 9), (9, 12), (12, 16), (16, 24), (24, _LONGEST)):
            which = np.flatnonzero((length > low) & (length <= high))
            for i in range(0, len(which), 20_000):
                part = which[i:i + 20_000]
                ids, n = self._merge_equal(raw[offsets[part][:, None] + np.arange(high)], length[part], high)
                sizes[part] = n
                grids.append((part, ids))
        start = np.cumsum(sizes) - sizes
        flat = np.empty(int(sizes.sum()), np.int32)
        for part, ids in grids:
            inside = np.arange(ids.shape[1]) < sizes[part][:, None]
            flat[(start[part][:, None] + np.arange(ids.shape[1]))[inside]] = ids[inside]
        return flat, sizes

    def _merge_equal(self, raw: np.ndarray, n: np.ndarray, wide: int) -> tuple[np.ndarray, np.ndarray]:
        cur = self.inner[raw]
        lanes = np.arange(len(raw))
        cur[lanes, n - 1] = self.last[raw[lanes, n - 1]]
        cur[np.arange(wide)[None, :] >= n[:, None]] = -1
        rank = self.ranks(cur[:, :-1], cur[:, 1:])
        done, sizes = cur.copy(), n.copy()
        while len(lanes):
            at = rank.argmin(1)
            rows = np.arange(len(lanes))
            best = rank[rows, at]
            go = best != _NONE
            if not go.all():
                done[lanes[~go]], sizes[lanes[~go]] = cur[~go], n[~go]
                cur, rank, n, lanes, at, best = cur[go], rank[go], n[go], lanes[go], at[go], best[go]
                rows = rows[:len(lanes)]
                if not len(lanes):
                    break
            cur[rows, at] = self.merged[best]
            take = np.arange(wide)[None, :] + (np.arange(wide)[None, :] > at[:, None])
            cur = np.take_along_axis(np.pad(cur, ((0, 0), (0, 1)), constant_values=-1), take, 1)
            rank = np.take_along_axis(np.pad(rank, ((0, 0), (0, 1)), constant_values=_NONE), take[:, :-1], 1)
            n = n - 1
            right = np.minimum(at + 1, wide - 1)
            inside = at < wide - 1
            fresh = self.ranks(cur[rows, at], cur[rows, right])
            rank[rows[inside], at[inside]] = fresh[inside]
            before = at > 0
            rank[rows[before], at[before] - 1] = self.ranks(cur[rows[before], at[before] - 1], cur[rows[before], at[before]])
        return done, sizes

    def _library(self, chunks: list[str]) -> tuple[np.ndarray, np.ndarray]:
        ids = [e.ids for e in self.library.encode_batch(chunks, add_special_tokens=False)] if chunks else []
        return np.array([i for own in ids for i in own], np.int32), np.array([len(own) for own in ids], np.int64)

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids of a string array, and the end of each text's ids; a null
        text has none."""
        lists = pc.ascii_split_whitespace(pc.fill_null(texts, "").cast(pa.large_string()))
        coded = lists.flatten().dictionary_encode()
        chunks, at = coded.dictionary, coded.indices.to_numpy()
        fields = pc.extract_regex(chunks, _PLAIN)
        word, mark = (pc.fill_null(pc.struct_field(fields, f), "") for f in ("word", "mark"))
        plain = pc.and_(pc.is_valid(fields), pc.and_(pc.less_equal(pc.binary_length(word), _LONGEST), pc.less_equal(pc.binary_length(mark), _LONGEST)))
        odd = np.flatnonzero(~plain.to_numpy(zero_copy_only=False))
        word, mark = (pc.if_else(plain, x, "") for x in (pc.utf8_lower(word), mark))
        both = pa.concat_arrays([word, mark]).dictionary_encode()
        flat, size = self._merge(both.dictionary)
        odd_flat, odd_size = self._library(chunks.take(pa.array(odd)).to_pylist())
        flat, size = np.concatenate((flat, odd_flat)), np.concatenate((size, odd_size))
        unit = both.indices.to_numpy().astype(np.int64).reshape(2, len(chunks))
        if len(odd):
            unit = np.concatenate((unit, unit[1:]))  # an odd chunk is a unit of its own, and has no word or mark
            unit[2] = -1
            unit[2, odd] = len(both.dictionary) + np.arange(len(odd))
            size = np.append(size, 0)
        start = np.cumsum(size) - size
        order = unit[:, at].T.ravel()
        each = size[order]
        ends = np.cumsum(each)
        place = np.arange(ends[-1] if len(ends) else 0) + np.repeat(start[order] - (ends - each), each)
        offsets = len(unit) * lists.value_lengths().to_numpy(zero_copy_only=False).cumsum()
        return flat[place], np.concatenate(([0], ends))[offsets]


@lru_cache(2)
def encoder(path: str) -> WordEncoder:
    """One encoder for each Python worker and file."""
    return WordEncoder(path)

"""Byte-level BPE ids of whole texts by the tokenizers library, with a bounded table of short stretches of text.

In a byte-level BPE of this kind, a token that holds a blank after another character that is not white space does not exist: before such a blank a text can be cut,
and likewise between a letter and a point. The stretches between the cuts are hashed all at once, over the bytes of an Arrow batch; those that a worker has met lately are looked up in its table
of ids, the others go to the library. The table keeps the bytes of a stretch as three numbers, and a hit counts only if they are equal; longer stretches, and those whose hash another one has, are kept by their bytes. The
ids of a text are those of its stretches in a row.
"""

from __future__ import annotations

import os

import numpy as np

from graphslices.llm.shingles import KEPT, lanes, scramble

BLOCK = 1 << 20
WIDE = 24
SLOT = np.uint64(64 - 21)
_WHITE = np.zeros(256, bool)
_WHITE[[*range(0x09, 0x0E), *range(0x1C, 0x21)]] = True
_LAST = np.zeros(256, bool)  # bytes that end white space of two or three bytes
_LAST[[*range(0x80, 0x8B), 0x85, 0x9F, 0xA0, 0xA8, 0xA9, 0xAF]] = True
_LETTER = np.zeros(256, bool)
_LETTER[[*range(65, 91), *range(97, 123)]] = True
_POINT = np.zeros(256, bool)
_POINT[list(b".,;:!?")] = True
_ENCODERS: dict[str, "Encoder"] = {}


def encoder(path: str) -> "Encoder":
    """One encoder for each file and worker process, kept between batches and tasks."""
    if path not in _ENCODERS:
        _ENCODERS[path] = Encoder(path)
    return _ENCODERS[path]


def cut_places(data: np.ndarray) -> np.ndarray:
    """Places where no token can reach across: blanks after a character other than white space (where a few bytes leave that open, there is no cut), points after an ASCII letter, and ASCII letters after a lone line feed."""
    at = np.flatnonzero(data == 0x20)
    at = at[at > 0]
    before = data[at - 1]
    fine = ~_WHITE[before]
    odd = np.flatnonzero(fine & _LAST[before])
    if len(odd):
        two, three = data[np.maximum(at[odd] - 2, 0)], data[np.maximum(at[odd] - 3, 0)]
        fine[odd] = ~((two == 0xC2) | ((three >= 0xE1) & (three <= 0xE3)))
    points = np.flatnonzero(_POINT[data[1:]] & _LETTER[data[:-1]]) + 1
    lines = np.flatnonzero(_LETTER[data[2:]] & (data[1:-1] == 0x0A) & (data[:-2] < 0x80) & ~_WHITE[data[:-2]]) + 2
    return np.concatenate([at[fine], points, lines])


def stretch_keys(data: np.ndarray, starts: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of stretches of a byte string, and what they hash: length and the first WIDE bytes, as four rows of numbers."""
    eight, keys = lanes(data), np.zeros((WIDE // 8 + 1, len(starts)), np.uint64)
    keys[0] = size
    h = keys[0] << np.uint64(56)  # up to seven bytes, the hash is a bijection of length and bytes
    own, at, left = slice(None), starts, size
    for row in keys[1:]:
        row[own] = eight[at] & KEPT[np.minimum(left, 8)]
        h[own] = scramble(h[own] + row[own])
        own = np.flatnonzero(size > 8) if isinstance(own, slice) else own[left > 8]
        at, left = at[left > 8] + 8, left[left > 8] - 8
    return h, keys


class Encoder:
    def __init__(self, path: str, bound: int = 1_000_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer, self.bound = Tokenizer.from_file(path), bound
        vocabulary = self.tokenizer.get_vocab(with_added_tokens=True)
        self.begins = np.zeros(max(vocabulary.values()) + 1, bool)
        for piece, i in vocabulary.items():
            self.begins[i] = piece[:1] == "Ġ"  # stands for a blank in byte-level vocabularies
        self._forget()

    def _forget(self) -> None:
        self.hashes, self.at, self.size = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int32)
        self.bytes = np.zeros((4, 0), np.uint64)
        self.apart: dict[bytes, tuple[int, int]] = {}
        self.pool, self.used = np.zeros(1 << 20, np.uint32), 0
        self.slots = np.zeros(1 << 64 - int(SLOT), np.int32)

    def _keep(self, ids: np.ndarray) -> int:
        """Puts ids into the pool; their place."""
        if self.used + len(ids) > len(self.pool):
            self.pool = np.concatenate([self.pool[: self.used], np.zeros(max(len(self.pool), len(ids)), np.uint32)])
        self.pool[self.used : self.used + len(ids)] = ids
        self.used += len(ids)
        return self.used - len(ids)

    def _direct(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(x.ids, np.uint32) for x in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)] if texts else []

    def _learn(self, hashes: np.ndarray, keys: np.ndarray, texts: list[bytes]) -> None:
        """Ids of stretches not met lately. Those with a blank at the start only are encoded in a row and told apart by the tokens that begin with a blank."""
        plain = [i for i, t in enumerate(texts) if t[:1] == b" " and t.count(b" ") == 1]
        if plain:
            ids = self._direct([b"".join([texts[i] for i in plain]).decode()])[0]
            starts = np.flatnonzero(self.begins[ids])
            if len(starts) != len(plain):  # a vocabulary in which a blank begins other tokens
                plain = []
        if not plain:
            ids, starts = np.zeros(0, np.uint32), np.zeros(0, np.int64)
        simple = set(plain)
        rest = [i for i in range(len(texts)) if i not in simple]
        others = self._direct([texts[i].decode() for i in rest])
        sizes = np.concatenate([np.diff(np.append(starts, len(ids))), [len(x) for x in others]]).astype(np.int32)
        new = np.concatenate([ids, *others]).astype(np.uint32)
        at = self._keep(new) + np.cumsum(sizes, dtype=np.int64) - sizes
        order = np.array(plain + rest)
        hashes = np.concatenate([self.hashes, hashes[order]])
        by = np.argsort(hashes, kind="stable")
        self.hashes, self.at, self.size = hashes[by], np.concatenate([self.at, at])[by], np.concatenate([self.size, sizes])[by]
        self.bytes = np.concatenate([self.bytes, keys[:, order]], axis=1)[:, by]
        self.slots[self.hashes >> SLOT] = np.arange(len(self.hashes), dtype=np.int32)

    def _found(self, h: np.ndarray) -> np.ndarray:
        place = np.searchsorted(self.hashes, h)
        place[place == len(self.hashes)] = 0
        return place

    def _block(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the stretches of a block of bytes, and how many each has."""
        if len(data) > BLOCK:  # one stretch longer than a block
            ids = self._direct([data.tobytes().decode()])[0]
            return ids, np.array([len(ids)])
        if len(self.hashes) + len(self.apart) > self.bound:
            self._forget()
        long = ends - starts
        h, keys = stretch_keys(data, starts, long)
        at, size, hit = np.zeros(len(h), np.int64), np.zeros(len(h), np.int64), np.zeros(len(h), bool)
        if len(self.hashes):  # the entry that a few bits of the hash lead to, for most
            e = self.slots[h >> SLOT]
            hit = (self.hashes[e] == h) & self._same(keys, e)
            at, size = self.at[e], self.size[e].astype(np.int64)
        left = np.flatnonzero(~hit)
        if len(left):
            at[left], size[left] = self._slowly(data, starts[left], ends[left], h[left], keys[:, left])
        before = np.cumsum(size) - size
        return self.pool[np.repeat(at - before, size) + np.arange(int(size.sum()))], size

    def _same(self, keys: np.ndarray, e: np.ndarray, of: np.ndarray | None = None) -> np.ndarray:
        """Whether the bytes of stretches are those of the entries e, given equal hashes. Below eight bytes, equal hashes and lengths leave no doubt."""
        of = self.bytes if of is None else of
        same = of[0][e] == keys[0]
        wide = np.flatnonzero(keys[0] > 7)
        same[wide] &= (of[1:, e[wide]] == keys[1:, wide]).all(axis=0) & (keys[0, wide] <= WIDE)
        return same

    def _slowly(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray, h: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places and sizes of stretches' ids in the pool, where new ones are put."""
        words, first, which = np.unique(h, return_index=True, return_inverse=True)
        raw, mine = data.tobytes(), keys[:, first]
        missing = np.flatnonzero((mine[0] <= WIDE) & (self.hashes[self._found(words)] != words if len(self.hashes) else True))
        if len(missing):
            self._learn(words[missing], mine[:, missing], [raw[a:b] for a, b in zip(starts[first[missing]].tolist(), ends[first[missing]].tolist(), strict=True)])
        at, size, fine = np.zeros(len(h), np.int64), np.zeros(len(h), np.int64), np.zeros(len(h), bool)
        if len(self.hashes):
            place = self._found(words)
            fine = ((self.hashes[place] == words) & self._same(mine, place))[which] & self._same(keys, which, mine)
            at, size = self.at[place][which], self.size[place][which].astype(np.int64)
        other = np.flatnonzero(~fine)
        if len(other):
            texts = [raw[a:b] for a, b in zip(starts[other].tolist(), ends[other].tolist(), strict=True)]
            new = [t for t in dict.fromkeys(texts) if t not in self.apart]
            for t, ids in zip(new, self._direct([t.decode() for t in new]), strict=True):
                self.apart[t] = self._keep(ids), len(ids)
            at[other], size[other] = np.array([self.apart[t] for t in texts]).T
        return at, size

    def encode_arrow(self, column) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts of an Arrow string array in a row, and the place where each text's begin (with the end last). Nulls have none."""
        import pyarrow as pa

        column = column.cast(pa.large_string()).fill_null("")
        offsets = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, 8 * column.offset)
        raw = column.buffers()[2]
        if not len(column) or raw is None or offsets[-1] == offsets[0]:
            return np.zeros(0, np.uint32), np.zeros(len(column) + 1, np.int64)
        data, offsets = np.frombuffer(raw, np.uint8)[offsets[0] : offsets[-1]], offsets - offsets[0]
        begun = np.zeros(len(data) + 1, bool)
        begun[offsets[:-1]] = True
        begun[cut_places(data)] = True
        starts = np.flatnonzero(begun[:-1])
        ends = np.append(starts[1:], len(data))
        ids, sizes, i = [], [], 0
        while i < len(starts):
            j = max(i + 1, int(np.searchsorted(ends, starts[i] + BLOCK, "right")))
            got, size = self._block(data[starts[i] : ends[j - 1]], starts[i:j] - starts[i], ends[i:j] - starts[i])
            ids.append(got)
            sizes.append(size)
            i = j
        total = np.concatenate([[0], np.cumsum(np.concatenate(sizes))])
        return np.concatenate(ids), total[np.searchsorted(starts, offsets)]

    def encode_many(self, texts: list[str | None]) -> list[np.ndarray]:
        import pyarrow as pa

        ids, at = self.encode_arrow(pa.array(texts, pa.string()))
        return [ids[a:b] for a, b in zip(at, at[1:], strict=False)]

"""Unigram piece encoding: the most probable segmentation of a text into pieces with log scores, by dynamic programming over a double-array trie.

The pieces come from a given vocabulary file, whose format is SentencePiece's; nothing is trained. A vocabulary of merges holds ranks, not log scores; then
a piece of rank r scores -ln(r + 2), in the manner of Zipf's law. White space is marked: a text gets a leading marker and its spaces become
markers. A character that no piece covers costs the least score less ten and is written as byte pieces. No piece has a marker after another character, so words are
segmented apart: all new words of a batch go through the trie together, position by position, as arrays; words lately met come from a bounded cache.

Decoding joins the pieces' bytes, turns markers into spaces and drops the first. A marker character in the text itself is written as bytes, so
decode(encode(text)) == text for every text.

Edge cases: a null or empty text has no pieces; a text of any length is encoded word by word, a word of any length too; repeated rows are encoded alike; an empty
table gives an empty table; other columns take no part.
"""

from __future__ import annotations

import math
import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphslices.session import ship

MARK = "▁"
_SEGMENT = re.compile(f"{MARK}+[^{MARK}]*|[^{MARK}]+")


@dataclass(frozen=True)
class Vocabulary:
    """base, check: the double array over bytes, state 0 being the root; piece: id at a state or -1; score: log score by id; raw: bytes by id; byte_id: id of each byte's piece."""

    base: np.ndarray
    check: np.ndarray
    piece: np.ndarray
    score: np.ndarray
    raw: list
    byte_id: np.ndarray
    longest: int


def double_array(keys: list[bytes], ids: list[int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The trie of keys as (base, check, piece): the child of state s by byte c is base[s] + c + 1 if check there is s."""
    tree: list[dict[int, int]] = [{}]
    leaf = {0: -1}
    for key, i in zip(keys, ids, strict=True):
        at = 0
        for c in key:
            if c not in tree[at]:
                tree[at][c] = len(tree)
                leaf[len(tree)] = -1
                tree.append({})
            at = tree[at][c]
        leaf[at] = i
    size = 3 * len(tree) + 2048
    base, check, piece = np.zeros(size, np.int32), np.full(size, -1, np.int32), np.full(size, -1, np.int32)
    used = bytearray(size)
    used[0] = 1
    place, order = {0: 0}, [0]
    piece[0] = leaf[0]
    single = several = 0  # where the search for a free place begins, for nodes with one child and with more
    for node in order:  # grows while it runs: breadth first
        kids = sorted(tree[node])
        if not kids:
            continue
        if len(kids) == 1:
            single = b = max(used.index(0, single + kids[0] + 1) - kids[0] - 1, 0)
        else:
            b = several
            while any(used[b + c + 1] for c in kids):
                b += 1
            several = max(several, b - 64)
        s = place[node]
        base[s] = b
        for c in kids:
            t = b + c + 1
            used[t] = 1
            check[t] = s
            child = tree[node][c]
            place[child] = t
            piece[t] = leaf[child]
            order.append(child)
    return base, check, piece


def load_vocabulary(path: str, scores: dict[str, float] | None = None) -> Vocabulary:
    """The pieces of a SentencePiece file. scores: log scores by piece, else those of the file (if it is a unigram model) or by rank."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    n = model.vocab_size()
    names = [model.id_to_piece(i) for i in range(n)]
    plain = [i for i in range(n) if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i) or model.is_unused(i))]
    given = np.array([model.get_score(i) for i in range(n)])
    ranks = all(x == int(x) for x in given[plain])
    score = -np.log(np.maximum(-given, 0) + 2) if ranks else given
    if scores:
        score = np.array([scores.get(x, s) for x, s in zip(names, score, strict=True)])
    raw = [x.replace(MARK, " ").encode() for x in names]
    byte_id = np.full(256, -1, np.int64)
    for i in range(n):
        if model.is_byte(i):
            byte_id[int(names[i][3:5], 16)] = i
            raw[i] = bytes([int(names[i][3:5], 16)])
        elif model.is_control(i) or model.is_unknown(i):
            raw[i] = b""
    base, check, piece = double_array([names[i].encode() for i in plain], plain)
    return Vocabulary(base, check, piece, np.asarray(score, float), raw, byte_id, max(len(names[i].encode()) for i in plain))


class Segmenter:
    LITERAL = "\x00\x00"  # the key of a marker character that stands in a text; no other key has two NULs at its start

    def __init__(self, v: Vocabulary, bound: int = 300_000):
        self.v, self.bound, self.known = v, bound, {}
        plain = v.piece[v.piece >= 0]
        self.unknown = float(v.score[plain].min()) - 10.0

    def segment(self, words: list[bytes]) -> list[list[int]]:
        """Piece ids of each word, -1 - b for a byte b that is written by itself."""
        out: list = [None] * len(words)
        order = sorted(range(len(words)), key=lambda i: len(words[i]))
        at = 0
        while at < len(order):
            # rows of like length: at most some millions of cells at once, and a very long word alone
            to, width = at + 1, len(words[order[at]])
            while to < len(order) and (to - at + 1) * (len(words[order[to]]) + 1) <= 4_000_000 and len(words[order[to]]) <= 2 * width + 16:
                to += 1
            self._many([words[i] for i in order[at:to]], order[at:to], out)
            at = to
        return out

    def _many(self, words: list[bytes], places: list[int], out: list) -> None:
        v, n = self.v, len(words)
        size = np.array([len(w) for w in words])
        width = int(size.max()) if n else 0
        cells = np.zeros((n, width + 1), np.int32)
        flat = np.frombuffer(b"".join(words), np.uint8)
        cells[np.arange(width + 1) < size[:, None]] = flat
        best = np.full((n, width + 1), -np.inf)
        came, used = np.zeros((n, width + 1), np.int32), np.full((n, width + 1), -1, np.int32)
        best[:, 0] = 0
        lead = np.where(cells < 0x80, 1, np.where(cells >= 0xF0, 4, np.where(cells >= 0xE0, 3, np.where(cells >= 0xC0, 2, 0))))
        for i in range(width):
            rows = np.flatnonzero((size > i) & np.isfinite(best[:, i]))
            if not len(rows):
                continue
            char = lead[rows, i]
            covered = np.zeros(n, bool)
            live, state = rows, np.zeros(len(rows), np.int64)
            for d in range(min(v.longest, width - i)):
                nxt = v.base[state] + cells[live, i + d] + 1
                ok = (v.check[nxt] == state) & (size[live] > i + d)
                live, state = live[ok], nxt[ok]
                if not len(live):
                    break
                ids = v.piece[state]
                hit = ids >= 0
                r, p = live[hit], ids[hit]
                value = best[r, i] + v.score[p]
                better = value > best[r, i + d + 1]
                r, p = r[better], p[better]
                best[r, i + d + 1], came[r, i + d + 1], used[r, i + d + 1] = value[better], i, p
                covered[live[hit][lead[live[hit], i] == d + 1]] = True
            bare = rows[~covered[rows]]
            to = i + lead[bare, i]
            value = best[bare, i] + self.unknown
            better = value > best[bare, to]
            bare, to = bare[better], to[better]
            best[bare, to], came[bare, to], used[bare, to] = value[better], i, -1
        for k, (w, place) in enumerate(zip(words, places, strict=True)):
            ids, j, c, u = [], len(w), came[k], used[k]
            while j:
                i = int(c[j])
                if u[j] >= 0:
                    ids.append(int(u[j]))
                else:
                    ids.extend(-1 - b for b in reversed(w[i:j]))
                j = i
            out[place] = ids[::-1]

    def encode_many(self, texts: list[str | None]) -> list[np.ndarray]:
        """Ids of each text."""
        split = [self._segments(t) if t else [] for t in texts]
        if self.LITERAL not in self.known:
            self.known[self.LITERAL] = self.v.byte_id[list(MARK.encode())].astype("<u4").tobytes()
        new = set().union(*split).difference(self.known) if split else set()
        if new:
            if len(self.known) + len(new) > self.bound:
                literal = self.known[self.LITERAL]
                self.known.clear()
                self.known[self.LITERAL] = literal
                new = set().union(*split).difference(self.known)
            new = list(new)
            ids = self.segment([self._bytes(x) for x in new])
            byte = self.v.byte_id
            for word, got in zip(new, ids, strict=True):
                self.known[word] = np.array([g if g >= 0 else byte[-1 - g] for g in got], "<u4").tobytes()
        get = self.known.__getitem__
        return [np.frombuffer(b"".join(map(get, s)), "<u4") for s in split]

    @staticmethod
    def _bytes(word: str) -> bytes:
        """The bytes of a cache key: plain words come without their marker, other segments as they are after a NUL."""
        return word[1:].encode() if word[:1] == "\x00" else (MARK + word).encode()

    def _segments(self, text: str) -> list[str]:
        if MARK in text or "\x00" in text or text[:1] == " " or text[-1:] == " " or "  " in text:
            out: list[str] = []
            for k, part in enumerate(text.split(MARK)):
                if k:
                    out.append(self.LITERAL)
                marked = (MARK if not k else "") + part.replace(" ", MARK)
                out.extend("\x00" + s for s in _SEGMENT.findall(marked))
            return out
        return text.split(" ")

    def decode(self, ids: np.ndarray) -> str:
        raw = self.v.raw
        return b"".join([raw[i] for i in ids.tolist()])[1:].decode()


_SEGMENTERS: dict[int, Segmenter] = {}


def kept_segmenter(v: Vocabulary) -> Segmenter:
    """The worker's segmenter for a vocabulary, with its cache from earlier tasks."""
    key = zlib.crc32(v.score.tobytes(), zlib.crc32(v.base.tobytes()))
    if key not in _SEGMENTERS:
        _SEGMENTERS.clear()
        _SEGMENTERS[key] = Segmenter(v)
    return _SEGMENTERS[key]


def encode(docs: DataFrame, vocabulary: Vocabulary, text: str = "text", with_ids: bool = False) -> DataFrame:
    """Per document: doc_id, n_pieces, n_byte_pieces, score (log score of the segmentation), ids_crc32, whether decoding gives the text again, and with_ids the ids."""
    spark = docs.sparkSession
    ship(spark)
    sent = spark.sparkContext.broadcast(vocabulary)  # a vocabulary: its size does not grow with the data
    schema = "doc_id long, n_pieces long, n_byte_pieces long, score double, ids_crc32 long, round_trip boolean" + ", ids array<int>" * with_ids

    def rows(batches: Iterator) -> Iterator:
        import pyarrow as pa

        v = sent.value
        seg = kept_segmenter(v)
        is_byte = np.zeros(len(v.score), bool)
        is_byte[v.byte_id[v.byte_id >= 0]] = True
        cost = v.score.copy()
        cost[is_byte] = 0
        # some hundred texts at a time: all words of a whole Arrow batch would be held at once
        for batch in (b.slice(at, 256) for b in batches for at in range(0, len(b), 256)):
            texts = batch.column(1).to_pylist()
            cols: list[list] = [[] for _ in range(6 + with_ids)]
            for doc, t, ids in zip(batch.column(0).to_pylist(), texts, seg.encode_many(texts), strict=True):
                b = int(is_byte[ids].sum())
                row = [doc, len(ids), b, float(cost[ids].sum()), zlib.crc32(ids.tobytes()), (seg.decode(ids) if len(ids) else "") == (t or "")]
                for c, x in zip(cols, row + [ids.tolist()] * with_ids, strict=True):
                    c.append(x)
            types = [pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.bool_(), pa.list_(pa.int32())]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, types, strict=False)], names=[x.split()[0] for x in schema.split(", ")])

    return docs.select("doc_id", F.col(text).alias("text")).mapInArrow(rows, schema)

"""Packing documents, in their order, into sequences of bounded length by dynamic programming.

The documents of a range of ids form one stream of tokens. A sequence may end at the end of a document at no cost, at the end of a sentence
for a small one and inside a sentence, at places no more than `stride` tokens apart, for a larger one; it also costs its padding: up to the full length, or none if its
length is a power of two. The cheapest cuts are found in one pass: of all places a sequence could start that are at most a full
length back, a queue with increasing costs keeps those that can still win, so its head is the best one.

Ranges are independent, and a range longer than `block` tokens is cut into blocks of whole documents or of `block` tokens, so memory is bounded.

Edge cases: a null or empty text has the end id alone; a document longer than a sequence is cut as often as needed; rows with equal ids follow each other in the
order of their texts; a null doc_id sorts first; an empty table gives no pieces; other columns take no part.
"""

from __future__ import annotations

import zlib
from collections import deque
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from graphslices.session import ship
from graphslices.llm.dac import in_order, token_batches

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


@dataclass(frozen=True)
class PackingCosts:
    length: int = 1024
    sentence: float = 4.0
    inside: float = 24.0
    sequence: float = 1.0
    stride: int = 48
    block: int = 4_000_000


def padded(n: int, length: int) -> int:
    """Tokens of padding of a sequence of n tokens."""
    return 0 if n & (n - 1) == 0 else length - n


def cuts(places: np.ndarray, costs: np.ndarray, p: PackingCosts) -> list[int]:
    """Indexes into places (ascending, the first 0) of the cheapest chain from the first to the last, no step longer than p.length."""
    n, at = len(places), places.tolist()
    extra = costs.tolist()
    jumps: dict[int, list[int]] = {}
    k = 1
    while k < p.length:
        back = np.searchsorted(places, places - k)
        for j in np.flatnonzero((places >= k) & (places[back] == places - k)).tolist():
            jumps.setdefault(j, []).append(int(back[j]))
        k *= 2
    best, came = [0.0] * n, [0] * n
    queue, keys = deque([0]), deque([0.0])
    for j in range(1, n):
        t = at[j]
        low = t - p.length
        while at[queue[0]] < low:
            queue.popleft()
            keys.popleft()
        cost, frm = keys[0] + p.length - t, queue[0]
        for i in jumps.get(j, ()):
            if best[i] < cost:
                cost, frm = best[i], i
        cost += extra[j] + p.sequence
        best[j], came[j] = cost, frm
        key = cost + t
        while keys and keys[-1] >= key:
            queue.pop()
            keys.pop()
        queue.append(j)
        keys.append(key)
    chain, j = [n - 1], n - 1
    while j:
        j = came[j]
        chain.append(j)
    return chain[::-1]


def candidates(ids: np.ndarray, ends: np.ndarray, closing: np.ndarray, p: PackingCosts) -> tuple[np.ndarray, np.ndarray]:
    """Places where a sequence may end, and what that costs. ends: of documents; closing: whether an id ends a sentence."""
    n = len(ids)
    cost = np.full(n + 1, np.inf)
    cost[1:][closing[ids]] = p.sentence
    cost[ends] = 0
    cost[0] = 0
    known = np.flatnonzero(np.isfinite(cost))
    gaps = np.diff(known)
    wide = np.flatnonzero(gaps > p.stride)
    if len(wide):
        count = (gaps[wide] - 1) // p.stride
        first = np.repeat(known[wide], count)
        step = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count) + 1
        cost[first + step * p.stride] = p.inside
        known = np.flatnonzero(np.isfinite(cost))
    return known, cost[known]


def closing_ids(tokenizer: str) -> np.ndarray:
    """For each id of a byte-level vocabulary, whether its text ends like a sentence or a line."""
    from graphslices.llm.bpe import encoder

    vocabulary = encoder(tokenizer).tokenizer.get_vocab(with_added_tokens=True)
    out = np.zeros(max(vocabulary.values()) + 1, bool)
    for piece, i in vocabulary.items():
        out[i] = piece[-1:] in ".!?Ċ"  # the last stands for a line feed in such vocabularies
    return out


def pack(docs: DataFrame, tokenizer: str, costs: PackingCosts = PackingCosts(), end_id: int = 0, text: str = "text") -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""

    def packed(batches: Iterator) -> Iterator:
        import pyarrow as pa
        from pyspark import TaskContext

        closing, number = None, TaskContext.get().partitionId() << 33
        held: list[tuple] = []  # (doc, ids as bytes, first token in the document, tokens of the document)

        def block() -> pa.RecordBatch:
            nonlocal number
            ids = np.frombuffer(b"".join(x[1] for x in held), "<u4")
            ends = np.cumsum([len(x[1]) // 4 for x in held])
            places, cost = candidates(ids, ends, closing, costs)
            chain = places[cuts(places, cost, costs)].tolist()
            rows, d, begun = [], 0, 0
            for a, b in zip(chain, chain[1:], strict=False):
                at = a
                while at < b:
                    to = min(b, int(ends[d]))
                    doc, raw, first, total = held[d]
                    part = raw[(at - begun) * 4 : (to - begun) * 4]
                    rows.append((doc, first + at - begun, to - at, zlib.crc32(part), total, number, at - a))
                    if to == ends[d]:
                        begun, d = to, d + 1
                    at = to
                number += 1
            held.clear()
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], names=[x.split()[0] for x in PIECES.split(", ")])

        size = 0
        for doc, raw in token_batches(batches, tokenizer, end_id):
            if closing is None:
                closing = closing_ids(tokenizer)
            total = len(raw) // 4
            for first in range(0, total, costs.block):
                part = raw[first * 4 : (first + costs.block) * 4]
                held.append((doc, part, first, total))
                size += len(part) // 4
                if size >= costs.block:
                    yield block()
                    size = 0
        if held:
            yield block()

    ship(docs.sparkSession)
    return in_order(docs, text).mapInArrow(packed, PIECES)

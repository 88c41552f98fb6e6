"""Approximate nearest neighbours by inner product over learned partitions.

Fitting: on a bounded sample (a 64th of the rows, `sample` at least and `most_sample` at most, chosen by a hash of their ids) the exact neighbour graph is cut into parts of about equal size: from clusters of bounded size,
refined by moving vertices to the part most of their neighbours are in, under a cap on sizes. A small network, a linear layer that starts at the parts' centres beside a hidden one, learns from a vector the
distribution of its neighbours over the parts. An eighth of the sample is kept from it, and tells, with as many rows that it learned from, what share of the probability a query's parts must hold for a recall of `recall`.
Indexing: every row goes to its most probable part. Searching: a query is routed to its most probable parts, and all their rows are ranked exactly. `rows_read` tells how many they are.

Parts are numbered along halvings of their centres, so that neighbouring numbers are near each other, and packed into shards of bounded size: a query is sent to a shard once, whatever number of its parts lie there.
Shards are dealt out in blocks of rows and of queries, so neither a large part nor many copies of one vector land in one task; each block returns
at most k rows per query. A query whose parts hold fewer than k rows is ranked against all rows. The number of parts grows with the rows up to an eighth of `most_sample`; beyond, the parts grow.

Edge cases: vectors that are null, empty, all zero, of another length than most of the sample's, or hold null or non-finite components take no part, as queries or rows; ties go to the smaller id, over all
equal rows; with k candidates or fewer, all are returned; a repeated id is never its own neighbour; an empty table gives an empty table; other columns take no part.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphslices.llm.common import cut, written
from graphslices.session import ship


@dataclass(frozen=True)
class PartitionSearch:
    """recall: what the kept-back queries must reach. rows_a_part: parts are made for so many rows, with 8 rows of a sample at least."""

    k: int = 20
    sample: int = 8192
    most_sample: int = 65536
    graph: int = 20
    rows_a_part: int = 4
    recall: float = 0.94
    hidden: int = 64
    epochs: int = 18
    slack: float = 0.2
    rows_block: int = 4096
    query_block: int = 1024
    seed: int = 3

    def sampled(self, n: int) -> int:
        return int(min(self.most_sample, max(self.sample, n // 64)))

    def parts(self, n: int) -> int:
        whole = n if n <= self.sample else 0  # a table that is its own sample may have smaller parts
        return int(min(max(8, 2 ** round(np.log2(max(1, n / self.rows_a_part)))), max(8, (whole // self.rows_a_part) or self.sampled(n) // 8)))


def _rows_at_once(width: int) -> int:
    """How many rows of so many doubles are worked on at once: eight megabytes, whatever the sample, as the driver holds several such blocks."""
    return max(1, (1 << 20) // max(1, width))


def neighbour_graph(x: np.ndarray, k: int) -> np.ndarray:
    """The k nearest other rows of each row by inner product, in blocks."""
    n, out = len(x), []
    k = min(k, n - 1)
    for at in range(0, n, step := _rows_at_once(n)):
        s = x[at : at + step] @ x.T
        s[np.arange(len(s)), np.arange(at, at + len(s))] = -np.inf
        out.append(np.argpartition(-s, k - 1, axis=1)[:, :k].copy() if k else np.zeros((len(s), 0), int))
    return np.concatenate(out)


def _centres(x: np.ndarray, part: np.ndarray, parts: int) -> np.ndarray:
    out = np.zeros((parts, x.shape[1]))
    np.add.at(out, part, x)
    return out / np.maximum(np.bincount(part, minlength=parts), 1)[:, None]


def _preferences(x: np.ndarray, centres: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """The nearest centres of each row, nearest first, and by how much the first is nearer than the second."""
    best, lead = [], []
    for at in range(0, len(x), step := _rows_at_once(len(centres))):
        near = x[at : at + step] @ centres.T - (centres**2).sum(axis=1) / 2
        top = np.argpartition(-near, most - 1, axis=1)[:, :most] if most < near.shape[1] else np.tile(np.arange(near.shape[1]), (len(near), 1))
        values = np.take_along_axis(near, top, axis=1)
        order = np.argsort(-values, axis=1, kind="stable")
        best.append(np.take_along_axis(top, order, axis=1))
        first = np.take_along_axis(values, order[:, :2], axis=1)
        lead.append(first[:, 0] - first[:, -1])
    return np.concatenate(best), np.concatenate(lead)


def balanced_parts(x: np.ndarray, near: np.ndarray, parts: int, slack: float = 0.2, rounds: int = 10) -> np.ndarray:
    """A part for each vertex of the graph, of at most len(x) / parts vertices and the slack."""
    n, cap = len(x), int(np.ceil(len(x) / parts * (1 + slack)))
    centres = x[np.linspace(0, n - 1, parts).astype(int)]
    for _ in range(rounds):
        best, lead = _preferences(x, centres, min(parts, 32))
        room, part = [cap] * parts, np.zeros(n, int)
        for i in np.argsort(-lead, kind="stable").tolist():  # who loses most chooses first
            k = next((k for k in best[i].tolist() if room[k]), None)
            k = int(np.argmax(room)) if k is None else k
            room[k] -= 1
            part[i] = k
        centres = _centres(x, part, parts)
    u, v = np.repeat(np.arange(n), near.shape[1]), near.ravel()
    kept = lambda part: int((part[u] == part[v]).sum())
    for _ in range(rounds):
        # the part that most neighbours of a vertex are in, either way, and how many more than in its own
        votes, count = np.unique(np.concatenate([u * parts + part[v], v * parts + part[u]]), return_counts=True)
        voter, voted = votes // parts, votes % parts
        own = np.zeros(n, int)
        own[voter[voted == part[voter]]] = count[voted == part[voter]]
        order = np.lexsort((count, voter))
        last = order[np.flatnonzero(np.diff(voter[order], append=-1))]
        moved, sizes, gain = part.copy(), np.bincount(part, minlength=parts).tolist(), count[last] - own[voter[last]]
        for j in np.argsort(-gain, kind="stable").tolist():
            if gain[j] <= 0:
                break
            i, to = int(voter[last[j]]), int(voted[last[j]])
            if sizes[to] < cap and sizes[moved[i]] > 1:
                sizes[moved[i]] -= 1
                sizes[to] += 1
                moved[i] = to
        if kept(moved) <= kept(part):  # moves at once can undo each other
            break
        part = moved
    return part


def numbered(x: np.ndarray, part: np.ndarray, parts: int) -> np.ndarray:
    """The parts with numbers along halvings of their centres by principal directions."""
    centres, rows, done = _centres(x, part, parts), [np.arange(parts)], []
    while rows:
        own = rows.pop()
        if len(own) < 3:
            done.extend(own.tolist())
            continue
        c = centres[own] - centres[own].mean(axis=0)
        side = own[np.argsort(c @ np.linalg.eigh(c.T @ c)[1][:, -1], kind="stable")]
        rows += [side[len(own) // 2 :], side[: len(own) // 2]]
    place = np.empty(parts, int)
    place[done] = np.arange(parts)
    return place[part]


class Router:
    """From a vector to the probabilities of the parts. targets: for each row the parts of its neighbours, -1 for none."""

    def __init__(self, x: np.ndarray, targets: np.ndarray, centres: np.ndarray, p: PartitionSearch):
        rng = np.random.default_rng(p.seed)
        d, parts = x.shape[1], len(centres)
        self.scale = 1 / max(float(np.sqrt((x**2).mean())), 1e-30)
        x, centres = x * self.scale, centres * self.scale
        start = centres * (1 / max(float(np.std(x @ centres.T)), 1e-30)) if len(x) else centres
        w = [start.T.copy(), np.zeros(parts), rng.normal(0, np.sqrt(2 / d), (d, p.hidden)), np.zeros(p.hidden), rng.normal(0, 0.01, (p.hidden, parts))]
        m, s, t = [np.zeros_like(a) for a in w], [np.zeros_like(a) for a in w], 0
        self.w = w
        for epoch in range(p.epochs):
            rate = 3e-3 * (1 - epoch / p.epochs) + 1e-4
            order = rng.permutation(len(x))
            for at in range(0, len(x), 256):
                i = order[at : at + 256]
                goal = np.zeros((len(i), parts))
                real = targets[i] >= 0
                np.add.at(goal, (np.nonzero(real)[0], targets[i][real]), 1)
                goal /= np.maximum(goal.sum(axis=1, keepdims=True), 1)
                h = np.maximum(x[i] @ w[2] + w[3], 0)
                d2 = (self._softmax(x[i] @ w[0] + w[1] + h @ w[4]) - goal) / len(i)
                d1 = (d2 @ w[4].T) * (h > 0)
                grads, t = [x[i].T @ d2, d2.sum(0), x[i].T @ d1, d1.sum(0), h.T @ d2], t + 1
                for k, g in enumerate(grads):
                    m[k] = 0.9 * m[k] + 0.1 * g
                    s[k] = 0.999 * s[k] + 0.001 * g * g
                    w[k] -= rate * (m[k] / (1 - 0.9**t)) / (np.sqrt(s[k] / (1 - 0.999**t)) + 1e-8)

    @staticmethod
    def _softmax(z: np.ndarray) -> np.ndarray:
        e = np.exp(z - z.max(axis=1, keepdims=True))
        return e / e.sum(axis=1, keepdims=True)

    def __call__(self, x: np.ndarray) -> np.ndarray:
        x, w = x * self.scale, self.w
        return self._softmax(x @ w[0] + w[1] + np.maximum(x @ w[2] + w[3], 0) @ w[4])


def mass_for(router: Router, rows: np.ndarray, queries: np.ndarray, p: PartitionSearch, own: bool = False) -> float:
    """The least share of the probability with which the parts of the queries hold `recall` of their nearest rows. own: the queries are the first rows, and no neighbours of themselves."""
    k = min(p.k, len(rows) - own)
    if k < 1 or not len(queries):
        return 1.0
    parts, needed = router.w[1].size, []
    step = _rows_at_once(parts)
    part = np.concatenate([router(rows[at : at + step]).argmax(axis=1) for at in range(0, len(rows), step)])
    for at in range(0, len(queries), step := _rows_at_once(max(len(rows), parts))):
        some = queries[at : at + step]
        chance, near = router(some), some @ rows.T
        if own:
            near[np.arange(len(some)), np.arange(at, at + len(some))] = -np.inf
        top = np.argpartition(-near, k - 1, axis=1)[:, :k]
        order = np.argsort(-chance, axis=1, kind="stable")
        held = np.cumsum(np.take_along_axis(chance, order, axis=1), axis=1)
        before = held - np.take_along_axis(chance, order, axis=1)
        place = np.empty_like(order)
        np.put_along_axis(place, order, np.arange(order.shape[1])[None, :], axis=1)
        # a part is taken if the parts before it hold less than the share
        needed.append(np.take_along_axis(before, np.take_along_axis(place, part[top], axis=1), axis=1).ravel())
    needed = np.sort(np.concatenate(needed))
    return float(needed[min(len(needed) - 1, int(np.ceil(p.recall * len(needed))))]) + 1e-9


def fit(x: np.ndarray, parts: int, p: PartitionSearch) -> tuple[Router, float]:
    """The router of a sample, and the share of the probability that a query's parts must hold."""
    rng = np.random.default_rng(p.seed)
    asked = np.zeros(len(x), bool)
    asked[rng.permutation(len(x))[: len(x) // 8]] = True
    rows = x[~asked]
    near = neighbour_graph(rows, p.graph)
    part = numbered(rows, balanced_parts(rows, near, parts, p.slack), parts)
    router = Router(rows, np.concatenate([part[near], part[:, None]], axis=1), _centres(rows, part, parts), p)
    # the router knows the rows it learned from better than others: both kinds of queries must be served
    return router, max(mass_for(router, rows, x[asked], p), mass_for(router, rows, rows[: len(x) // 8], p, True))


def valid(vectors: DataFrame) -> DataFrame:
    """(vec_id, v) of the rows that take part."""
    v = F.col("embedding")
    sound = F.forall(v, lambda x: F.coalesce(~F.isnan(x) & (F.abs(x) < float("inf")), F.lit(False))) & F.exists(v, lambda x: x != 0)
    return vectors.where("vec_id is not null").where(F.coalesce(sound, F.lit(False))).select(F.col("vec_id").cast("long"), v.cast("array<double>").alias("v"))


def _best(rough: np.ndarray, ids: np.ndarray, rows: np.ndarray, qids: np.ndarray, queries: np.ndarray, k: int) -> tuple[list, list, list]:
    """The k best rows of a block for each query, -inf standing for rows that it does not ask for: exact scores, ties by id."""
    out: tuple[list, list, list] = [], [], []
    rough[qids[:, None] == ids[None, :]] = -np.inf
    top = min(k, rough.shape[1])
    kth = np.partition(rough, rough.shape[1] - top, axis=1)[:, rough.shape[1] - top]
    for i, (q, line, low) in enumerate(zip(queries, rough, kth, strict=True)):
        near = np.flatnonzero((line >= low - 1e-9 * (1 + abs(low) if np.isfinite(low) else 0)) & np.isfinite(line)) if np.isfinite(low) else np.flatnonzero(np.isfinite(line))
        score = (rows[near] * q).sum(axis=1)
        order = np.lexsort((ids[near], -score))[:k]
        out[0].extend([int(qids[i])] * len(order))
        out[1].extend(ids[near][order].tolist())
        out[2].extend(score[order].tolist())
    return out


def _block(rows, queries, k: int) -> tuple[list, list, list]:
    """The best rows of a block (vec_id, v, near: its part) for each query (near: the parts it asks for), part by part."""
    rows = rows.assign(part=[int(x[0]) for x in rows.near]).sort_values("part", kind="stable")
    r, q = np.stack(rows.v.to_numpy()), np.stack(queries.v.to_numpy())
    asked: dict[int, list[int]] = {}
    for i, near in enumerate(queries.near):
        for part in near:
            asked.setdefault(int(part), []).append(i)
    rough = np.full((len(q), len(r)), -np.inf)
    part, first = np.unique(rows.part.to_numpy(), return_index=True)
    for k_, a, b in zip(part.tolist(), first, [*first[1:], len(r)], strict=True):
        if k_ in asked:
            rough[asked[k_], a:b] = q[asked[k_]] @ r[a:b].T
    return _best(rough, rows.vec_id.to_numpy(), r, queries.vec_id.to_numpy(), q, k)


def _matrix(sample: DataFrame) -> tuple[int, np.ndarray]:
    """The most frequent length of the vectors (v), and those that have it, as one array: doubles as they come, no Python objects."""
    import pyarrow.compute as pc

    v = sample.toArrow()["v"]
    if not len(v):
        return 0, np.zeros((0, 0))
    length = pc.list_value_length(v).to_numpy()
    dims = int(np.bincount(length).argmax())
    return dims, pc.list_flatten(v.filter(pc.equal(pc.list_value_length(v), dims))).to_numpy().reshape(-1, dims)


def search(vectors: DataFrame, is_query, p: PartitionSearch = PartitionSearch()) -> DataFrame:
    """(query_id, rank, vec_id, score, rows_read) for the rows of `vectors` (vec_id, embedding) that fulfil the column is_query."""
    spark, result = vectors.sparkSession, "query_id long, rank int, vec_id long, score double, rows_read long"
    ship(spark)
    rows = valid(vectors)
    # A bounded sample, of p.most_sample rows at most, comes to the driver.
    dims, x = _matrix(rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(p.sampled(rows.count())).select("v"))
    if not len(x):
        return spark.createDataFrame([], result)
    rows = rows.where(F.size("v") == int(dims))
    total = rows.count()
    parts = p.parts(total)
    if len(x) >= 2 * parts:
        router, mass = fit(x, parts, p)
    else:  # too few rows to learn from: one part
        parts = 1
        router, mass = Router(x, np.zeros((len(x), 1), int), x[:1], p), 1.0
    k, sent = p.k, spark.sparkContext.broadcast(router)  # of p.most_sample / 8 parts at most

    def routed(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for whole in batches:
            for at in range(0, len(whole), 1024):
                batch = whole.slice(at, 1024)
                chance = sent.value(np.asarray(batch.column(1).flatten()).reshape(len(batch), -1))
                order = np.argsort(-chance, axis=1, kind="stable").astype(np.int32)
                held = np.take_along_axis(chance, order, axis=1)
                n = np.where(np.asarray(batch.column(2)), np.maximum((np.cumsum(held, axis=1) - held < mass).sum(axis=1), 1), 1)
                near = pa.array([o[:m] for o, m in zip(order, n, strict=True)], pa.list_(pa.int32()))
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), near], names=["vec_id", "v", "asked", "near"])

    marked = rows.withColumn("asked", F.coalesce(is_query, F.lit(False)))
    index = written(marked.mapInArrow(routed, "vec_id long, v array<double>, asked boolean, near array<int>"), "partitions")
    stored = index.select("vec_id", "v", F.slice("near", 1, 1).alias("near"))
    asked = index.where("asked").select("vec_id", "v", "near")
    # A number for each part: rows, the shard it lies in, and blocks of that shard's rows.
    size = np.zeros(parts, np.int64)
    for r in stored.groupBy(F.get("near", F.lit(0)).alias("part")).count().collect():
        size[r.part] = r["count"]
    shard, open_, last = [], 0, 0
    for n in size.tolist():
        if last and last + n > p.rows_block:
            open_, last = open_ + 1, 0
        shard.append(open_)
        last += n
    load = np.bincount(shard, size)
    blocks = [int(max(1, -(-n // p.rows_block))) for n in load.tolist()]
    layout = spark.createDataFrame([(shard, blocks, size.tolist())], "shards array<int>, blocks array<int>, sizes array<bigint>")  # one row

    def ranked(queries: DataFrame) -> DataFrame:
        """queries: (vec_id, v, near)."""
        at = F.broadcast(layout)
        where = lambda part: F.get("shards", part)
        asks = queries.crossJoin(at).withColumn("shard", F.explode(F.array_distinct(F.transform("near", where))))
        asks = asks.select("vec_id", "v", "shard", F.get("blocks", F.col("shard")).alias("rb"), F.filter("near", lambda x: F.get("shards", x) == F.col("shard")).alias("near"))
        loads = asks.groupBy("shard").agg(F.ceil(F.count("*") / p.query_block).cast("int").alias("qb"))  # a row a shard, p.most_sample / 8 at most
        upto = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
        own = lambda n: F.pmod(F.xxhash64("vec_id"), n).cast("int")
        r = stored.crossJoin(at).withColumn("shard", where(F.get("near", F.lit(0)))).withColumn("rb", F.get("blocks", F.col("shard"))).join(F.broadcast(loads), "shard")
        r = r.select("shard", own(F.col("rb")).alias("r"), upto("qb").alias("q"), F.lit(0).alias("side"), "vec_id", "v", "near")
        q = asks.join(F.broadcast(loads), "shard").select("shard", upto("rb").alias("r"), own(F.col("qb")).alias("q"), F.lit(1).alias("side"), "vec_id", "v", "near")

        def block(group):
            import pandas as pd

            a, b = group[group.side == 0], group[group.side == 1]
            got = _block(a, b, k) if len(a) and len(b) else ([], [], [])
            return pd.DataFrame(dict(zip(("query_id", "vec_id", "score"), got, strict=True))).astype({"query_id": "int64", "vec_id": "int64", "score": "float64"})

        found = r.unionByName(q).groupBy("shard", "r", "q").applyInPandas(block, "query_id long, vec_id long, score double")
        rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
        best = found.withColumn("rank", rank).where(F.col("rank") <= k)
        read = queries.crossJoin(at).select(F.col("vec_id").alias("query_id"), F.aggregate("near", F.lit(0).cast("long"), lambda n, x: n + F.get("sizes", x)).alias("rows_read"))
        return best.join(read.groupBy("query_id").agg(F.max("rows_read").alias("rows_read")), "query_id")

    names = ["query_id", "rank", "vec_id", "score", "rows_read"]
    first = cut(ranked(asked))
    need = min(k, total - 1)
    full = first.groupBy("query_id").agg(F.count("*").alias("n")).where(F.col("n") >= need).select("query_id")
    short = cut(asked.join(full, F.col("vec_id") == F.col("query_id"), "left_anti").select("vec_id", "v"))
    if short.isEmpty():
        return first.select(*names)
    again = ranked(short.withColumn("near", F.sequence(F.lit(0), F.lit(parts - 1))))
    whole = first.join(short.select(F.col("vec_id").alias("query_id")), "query_id", "left_anti").select(*names).unionByName(again.select(*names))
    return whole.select(*names)

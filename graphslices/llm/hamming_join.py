"""Near-duplicate documents: a multi-index Hamming join of b-bit MinHash signatures, confirmed on the full shingle sets.

A document's signature has `symbols` MinHash values of its set of five-word shingles, `bits` bits each. Signatures at distance `distance` or less (differing symbols)
agree, in one of `chunks` chunks at least, up to distance // chunks errors, by the pigeonhole principle. So each chunk is indexed under every way to leave that
many of its symbols out, and signatures within the distance always meet under a key. At similarity 0.85 a pair differs in 64 * 0.15 = 9.6 symbols on average; more
than the allowed 23 have a chance of some millionths.

Documents with one shingle set are one class and are compared once. Under a key, every class is paired with the key's least one, so a key costs a row per member;
pairs within the distance are confirmed by set overlap, centre by centre, in groups of bounded size. What such stars leave apart is then settled exactly: of each set of classes
connected by keys, the classes outside its largest confirmed component are compared, in blocks of bounded numbers of rows and shingles, with all others. Links between different sets
within reach of the index are thus not lost, whatever the size of a group, and no list of pairs is made.

Edge cases: a null or empty text, or one without words, has no shingles and links with nothing; fewer than five words are one shingle; repeated rows are copies of each other;
rows with a null doc_id link with nothing and are kept, with a null component; texts of any length are hashed in parts; an empty table gives an empty table; other columns take no part.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphslices.llm.common import cut, written
from graphslices.llm.components import components
from graphslices.llm.shingles import scramble, text_sets
from graphslices.session import ship


@dataclass(frozen=True)
class HammingJoin:
    percent: int = 85
    symbols: int = 64
    bits: int = 16
    chunks: int = 12
    distance: int = 23
    block: int = 1024
    shingles_block: int = 1 << 20
    seed: int = 5


def signature(shingle_set: np.ndarray, p: HammingJoin) -> np.ndarray:
    factors = np.random.Generator(np.random.PCG64(p.seed)).integers(0, 2**63, p.symbols, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    least = np.full(p.symbols, 2**64 - 1, np.uint64)
    for at in range(0, len(shingle_set), 16_384):
        least = np.minimum(least, (shingle_set[at : at + 16_384, None] * factors).min(axis=0))
    return (scramble(least) & np.uint64(2**p.bits - 1)).astype(np.int64)


def index_keys(signatures: np.ndarray, p: HammingJoin) -> np.ndarray:
    """For each signature (rows) its keys: of every chunk, all ways to leave out as many symbols as it may have errors."""
    errors, out = p.distance // p.chunks, []
    for c, part in enumerate(np.array_split(np.arange(p.symbols), p.chunks)):
        for k, gone in enumerate(combinations(range(len(part)), min(errors, len(part) - 1))):
            h = np.full(len(signatures), c * 1000 + k + 1, np.uint64)
            for s in np.delete(part, gone):
                h = scramble(h * np.uint64(0x9E3779B97F4A7C15) + signatures[:, s].astype(np.uint64))
            out.append(h.view(np.int64))
    return np.stack(out, axis=1) if out else np.zeros((len(signatures), 0), np.int64)


def features(docs: DataFrame, p: HammingJoin, text: str = "text") -> DataFrame:
    """(doc_id, n_shingles, c1, c2, sig): c1 and c2 are 64-bit digests of the shingle set."""

    def rows(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for batch in batches:
            sets = text_sets(batch.column(1))
            digests = [(s.sum(dtype=np.uint64), np.bitwise_xor.reduce(scramble(s + np.uint64(1)))) for s in sets]
            sigs = [signature(s, p) for s in sets]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([len(s) for s in sets], pa.int64()), *(pa.array(np.array(c, np.uint64).view(np.int64)) for c in (zip(*digests, strict=True) if digests else ((), ()))),
                 pa.array(sigs, pa.list_(pa.int64()))], names=["doc_id", "n_shingles", "c1", "c2", "sig"])

    ship(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long"), F.col(text).alias("text")).mapInArrow(rows, "doc_id long, n_shingles long, c1 long, c2 long, sig array<bigint>")


def overlaps(xs: list[np.ndarray], ys: list[np.ndarray]) -> Iterator[np.ndarray]:
    """For each y the sizes of its intersections with all xs, by an inverted index of the xs' shingles."""
    sizes = np.array([len(x) for x in xs])
    shingle = np.concatenate(xs) if xs else np.zeros(0, np.uint64)
    order = np.argsort(shingle, kind="stable")
    shingle, owner = shingle[order], np.repeat(np.arange(len(xs)), sizes)[order]
    for y in ys:
        a, b = np.searchsorted(shingle, y, "left"), np.searchsorted(shingle, y, "right")
        n = b - a
        at = np.repeat(a - (np.cumsum(n) - n), n) + np.arange(n.sum())
        yield np.bincount(owner[at], minlength=len(xs))


def _confirmed(group, percent: int):
    """Spanning links of the rows of one group: those of side 0 against all, by exact similarity."""
    import pandas as pd

    group = group.drop_duplicates(["side", "doc"])
    x, y = group[group.side == 0], group[group.side == 1]
    xs, ys = ([np.frombuffer(v, np.uint64) for v in g.shingles] for g in (x, y))
    xid, yid = x.doc.to_numpy(), y.doc.to_numpy()
    sizes = np.array([len(v) for v in xs])
    root: dict[int, int] = {}

    def find(i: int) -> int:
        while root.setdefault(i, i) != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    out = []
    for j, (common, v) in enumerate(zip(overlaps(xs, ys), ys, strict=True)):
        for i in np.flatnonzero(100 * common >= percent * (sizes + len(v) - common)):
            a, b = find(int(xid[i])), find(int(yid[j]))
            if a != b:
                root[max(a, b)] = min(a, b)
                out.append((int(xid[i]), int(yid[j])))
    return pd.DataFrame(out, columns=["u", "v"]).astype("int64")


def _links(tasks: DataFrame, sets: DataFrame, keys: list[str], p: HammingJoin) -> DataFrame:
    """Confirmed links of tasks: rows (keys, side, doc); the sets come by doc."""
    percent = p.percent

    def confirmed(group):
        return _confirmed(group, percent)

    return tasks.join(sets, "doc").groupBy(*keys).applyInPandas(confirmed, "u long, v long")


def near_components(docs: DataFrame, p: HammingJoin = HammingJoin(), text: str = "text") -> DataFrame:
    """Per document: doc_id, n_shingles, component_id, kept."""
    spark = docs.sparkSession
    ship(spark)
    seen = written(features(docs, p, text), "features")
    some = seen.where("n_shingles > 0 and doc_id is not null")
    reps = some.groupBy("c1", "c2", "n_shingles").agg(F.min("doc_id").alias("doc"), F.first("sig").alias("sig"))
    reps = written(reps, "classes")

    def keyed(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for batch in batches:
            sigs = np.asarray(batch.column(1).flatten()).reshape(len(batch), p.symbols)
            keys = index_keys(sigs, p)
            docs_ = np.repeat(np.asarray(batch.column(0)), keys.shape[1])
            yield pa.RecordBatch.from_arrays([pa.array(keys.ravel()), pa.array(docs_)], names=["key", "doc"])

    index = reps.select("doc", "sig").mapInArrow(keyed, "key long, doc long")
    centres = index.groupBy("key").agg(F.min("doc").alias("centre"), F.max("doc").alias("last")).where("centre < last").drop("last")
    pairs = cut(index.join(centres, "key").where("doc > centre").select("doc", "centre").distinct())

    sig = reps.select("doc", "sig")
    apart = F.aggregate(F.zip_with("sig", "sig0", lambda a, b: (a != b).cast("int")), F.lit(0), lambda a, x: a + x)
    close = cut(
        pairs.join(sig, "doc").join(sig.select(F.col("doc").alias("centre"), F.col("sig").alias("sig0")), "centre").where(apart <= p.distance).select("doc", "centre")
    )
    # Stars: each centre with its members, in groups of `block` members and `shingles_block` shingles on average.
    size = reps.select("doc", "n_shingles")
    blocks = lambda rows, shingles: F.ceil(F.greatest(rows / p.block, shingles / p.shingles_block))
    count = close.join(size, "doc").groupBy("centre").agg(blocks(F.count("*"), F.sum("n_shingles")).alias("parts"))
    stars = close.join(count, "centre").select("centre", F.pmod(F.xxhash64("doc"), "parts").alias("part"), "doc")
    middle = stars.select("centre", "part").distinct().select("centre", "part", F.lit(0).alias("side"), F.col("centre").alias("doc"))
    stars = stars.select("centre", "part", F.lit(1).alias("side"), "doc").unionByName(middle)

    # The sets of all classes that meet another under a key. Class ids are document ids.
    met = pairs.select("doc").union(pairs.select("centre")).distinct()
    ids = docs.select(F.col("doc_id").cast("long").alias("doc"), F.col(text).alias("text"))

    def binary(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([s.tobytes() for s in text_sets(batch.column(1))], pa.binary())], names=["doc", "shingles"])

    sets = written(ids.join(met, "doc", "left_semi").mapInArrow(binary, "doc long, shingles binary"), "sets")
    links = cut(_links(stars, sets, ["centre", "part"], p))

    linked = components(links)
    within = components(pairs.select(F.col("doc").alias("u"), F.col("centre").alias("v")))
    known = cut(within.select(F.col("node").alias("doc"), F.col("component").alias("family")).join(linked.withColumnRenamed("node", "doc"), "doc", "left").withColumn("component", F.coalesce("component", "doc")))
    # The rest: classes outside the largest component of their family, against the whole family, in blocks.
    sizes = known.groupBy("family", "component").count()
    main = sizes.groupBy("family").agg(F.max(F.struct("count", "component")).alias("m"), F.count("*").alias("n")).where("n > 1")
    open_ = cut(known.join(main, "family").select("family", "doc", (F.col("component") != F.col("m.component")).alias("open")).join(size, "doc"))
    rest = open_.groupBy("family").agg(
        blocks(F.count_if("open"), F.sum(F.when(F.col("open"), F.col("n_shingles")).otherwise(0))).cast("int").alias("xparts"), blocks(F.count("*"), F.sum("n_shingles")).cast("int").alias("yparts"))
    own = open_.join(rest, "family")
    part = lambda n: F.pmod(F.xxhash64("doc"), n).cast("int")
    upto = lambda n: F.sequence(F.lit(0), F.col(n) - 1)
    left = own.where("open").select("family", part(F.col("xparts")).alias("xpart"), F.explode(upto("yparts")).alias("ypart"), F.lit(0).alias("side"), "doc")
    right = own.select("family", F.explode(upto("xparts")).alias("xpart"), part(F.col("yparts")).alias("ypart"), F.lit(1).alias("side"), "doc")
    more = _links(left.unionByName(right), sets, ["family", "xpart", "ypart"], p)
    more = cut(more)
    if more.isEmpty():
        final = linked
    else:
        final = components(linked.select(F.col("node").alias("u"), F.col("component").alias("v")).unionByName(more))
    classes = reps.join(final.withColumnRenamed("node", "doc"), "doc", "left").select("c1", "c2", "n_shingles", F.coalesce("component", "doc").alias("component_id"))
    out = seen.drop("sig").join(classes, ["c1", "c2", "n_shingles"], "left")
    component = F.when((F.col("n_shingles") == 0) | F.col("doc_id").isNull(), F.col("doc_id")).otherwise(F.col("component_id"))
    out = out.select("doc_id", "n_shingles", component.alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))

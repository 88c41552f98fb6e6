"""Matrix-vector products over a semiring: over CSR, slices, grids, sparse vectors and, for tiny graphs, dense matrices."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphslices.kernels import slice_products
from graphslices.layout import Grid, Layout, entries
from graphslices.semiring import Semiring
from graphslices.session import cut, ship

BROADCAST_BYTES = 256 << 20
DENSE_LIMIT = 4096


def _along(s: Semiring, weighted: bool):
    x = F.col("x").cast(s.sql_type)
    return s.edge(x) * F.col("val") if weighted else s.edge(x)


def combine(cells: DataFrame, vector: DataFrame, s: Semiring, weighted: bool = False) -> DataFrame:
    """(row, y): the sum over the semiring of what the rows' cells (row, col[, val]) bring from a vector (pos, x). Sums are partial before the shuffle."""
    return cells.join(vector.withColumnRenamed("pos", "col"), "col").groupBy("row").agg(s.aggregate(_along(s, weighted)).alias("y"))


def mv_csr(csr: DataFrame, vector: DataFrame, s: Semiring, weighted: bool = False) -> DataFrame:
    """Over (vertex, nbrs, val) rows; vector (pos, x) by vertex."""
    cells = csr.select(F.col("vertex").alias("row"), F.explode(F.arrays_zip("nbrs", "val")).alias("e")).select("row", F.col("e.nbrs").alias("col"), F.col("e.val").alias("val"))
    return combine(cells, vector, s, weighted)


def mv_csr_unrolled(csr: DataFrame, vector: DataFrame, s: Semiring, k: int = 4, weighted: bool = False) -> DataFrame:
    """As mv_csr with k partial results a row, slot modulo k, reduced at the end; a row's last slots need no padding, as missing ones bring nothing."""
    cells = csr.select(F.col("vertex").alias("row"), F.posexplode(F.arrays_zip("nbrs", "val")).alias("slot", "e"))
    cells = cells.select("row", (F.col("slot") % k).alias("part"), F.col("e.nbrs").alias("col"), F.col("e.val").alias("val"))
    parts = cells.join(vector.withColumnRenamed("pos", "col"), "col").groupBy("row", "part").agg(s.aggregate(_along(s, weighted)).alias("p"))
    return parts.groupBy("row").agg(s.aggregate(F.col("p")).alias("y"))


def mv_slices(layout: Layout, vector: DataFrame, s: Semiring, weighted: bool = False) -> DataFrame:
    """The relational product of slices, by place and for any size. Pattern slices have no values: each real slot stands for the semiring's edge value."""
    return combine(entries(layout.slices, layout.c, layout.valued and weighted), vector, s, weighted)


def dense_vector(vector: DataFrame, n: int, s: Semiring) -> np.ndarray:
    """A vector (pos, x) as one array for broadcasting. Its size is checked: beyond the bound take mv_slices or mv_grid."""
    if 8 * n > BROADCAST_BYTES:
        raise ValueError(f"a vector of {n} places is not broadcast; take the relational or the grid product")
    out = np.full(max(n, 1), s.zero, dtype=s.dtype)
    got = vector.select("pos", F.col("x").cast(s.sql_type).alias("x")).toArrow()
    out[np.asarray(got["pos"])] = np.asarray(got["x"])
    return out


def kernel_partials(layout: Layout, vector: np.ndarray, s: Semiring, settled: np.ndarray | None = None, weighted: bool = False) -> DataFrame:
    """(chunk_id, lanes) a row for each tile of the unsettled chunks: the layout stays where it is, the vector is broadcast."""
    spark, c = layout.slices.sparkSession, layout.c
    ship(spark)
    sent = spark.sparkContext.broadcast((vector, settled))  # bounded by BROADCAST_BYTES

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        x, done = sent.value
        for batch in batches:
            ids = np.asarray(batch.column(0))
            live = np.arange(len(ids)) if done is None else np.flatnonzero(~done[ids])
            if not len(live):
                continue
            batch = batch.take(pa.array(live))
            vals = np.asarray(batch.column(3).flatten()) if weighted else None
            lanes = slice_products(np.asarray(batch.column(2).flatten()), np.asarray(batch.column(1)).astype(np.int64), x, s, c, vals)
            flat = pa.array(lanes.ravel())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(np.arange(0, len(flat) + 1, c, dtype=np.int32)), flat)], names=["chunk_id", "lanes"])

    cols = ["chunk_id", "width", "col"] + (["val"] if weighted else [])
    return layout.slices.select(*cols).mapInArrow(run, f"chunk_id long, lanes array<{s.sql_type}>")


def packed_partials(layout: Layout, sent, s: Semiring) -> DataFrame:
    """As kernel_partials over the packed pattern. sent: a broadcast (vector, chunks left out or None, chunks whose lanes nobody needs or None). Lanes that are all zero stay where they are."""
    c = layout.c
    ship(layout.slices.sparkSession)

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        x, done, quiet = sent.value
        for batch in batches:
            for parts in zip(*batch.columns, strict=True):
                ids, widths, cols = (np.frombuffer(p.as_buffer(), np.int32) for p in parts)
                if done is not None:
                    live = ~done[ids]
                    if not live.any():
                        continue
                    if not live.all():
                        cols, ids, widths = cols[np.repeat(live, widths * c)], ids[live], widths[live]
                lanes = slice_products(cols, widths.astype(np.int64), x, s, c)
                some = (lanes != s.zero).any(axis=1)
                if quiet is not None:
                    some &= ~quiet[ids]
                flat = pa.array(lanes[some].ravel())
                if len(flat):
                    yield pa.RecordBatch.from_arrays([pa.array(ids[some].astype(np.int64)), pa.ListArray.from_arrays(pa.array(np.arange(0, len(flat) + 1, c, dtype=np.int32)), flat)], names=["chunk_id", "lanes"])

    return layout.packed.mapInArrow(run, f"chunk_id long, lanes array<{s.sql_type}>")


def merge_lanes(partials: DataFrame, s: Semiring, c: int) -> DataFrame:
    """(chunk_id, lanes): the tiles of a chunk summed lane by lane, in one hash aggregation with c values a key."""
    lanes = [s.aggregate(F.get("lanes", F.lit(i))).alias(f"l{i}") for i in range(c)]
    return partials.groupBy("chunk_id").agg(*lanes).select("chunk_id", F.array(*[f"l{i}" for i in range(c)]).alias("lanes"))


def lanes_to_vector(lanes: DataFrame, c: int) -> DataFrame:
    return lanes.select("chunk_id", F.posexplode("lanes").alias("lane", "y")).select((F.col("chunk_id") * c + F.col("lane")).alias("row"), "y")


def mv_tiles(layout: Layout, vector: DataFrame, s: Semiring, weighted: bool = False) -> DataFrame:
    """(row, y) by place of all rows, phantom ones among them: the kernel on broadcast vectors, tiles merged by chunk."""
    partials = kernel_partials(layout, dense_vector(vector, layout.chunks * layout.c, s), s, None, weighted)
    return lanes_to_vector(merge_lanes(partials, s, layout.c), layout.c)


def vector_segments(vector: DataFrame, col_block: int) -> DataFrame:
    """A sparse vector (pos, x) as (col_block, at, x) arrays, a row for each block that has values."""
    own = vector.select(F.floor(F.col("pos") / col_block).alias("col_block"), (F.col("pos") % col_block).alias("p"), "x")
    return own.groupBy("col_block").agg(F.collect_list("p").alias("seg_at"), F.collect_list("x").alias("seg_x"))


def chunk_bits(chunks: DataFrame, n: int) -> np.ndarray:
    """Chunks (chunk_id) as a bit for each of n, packed where they lie: the driver gets a word for each 63 of them."""
    if 16 * (n // 63 + 1) > BROADCAST_BYTES:
        raise ValueError(f"a bit for each of {n} chunks is not broadcast")
    one = F.expr("shiftleft(1L, cast(chunk_id % 63 AS INT))")
    got = chunks.groupBy(F.floor(F.col("chunk_id") / 63).alias("word")).agg(F.bit_or(one).alias("bits")).toArrow()
    out = np.zeros((n // 63 + 1, 63), bool)
    words, bits = np.asarray(got["word"]), np.asarray(got["bits"])
    for k in range(63):
        out[words, k] = bits >> k & 1
    return np.packbits(out.ravel()[:n])


def mv_grid(grid: Grid, vector: DataFrame, s: Semiring, open_chunks: np.ndarray | None = None) -> DataFrame:
    """(row, y) over grid tiles: tiles meet the segment of the vector in their columns by the buckets they are stored in; what is shuffled are segments, a copy for each part of a block, and partial lanes, never neighbours.

    A segment holds at most col_block values and is spread out once for a part, whose cells are bounded, so a task's memory is bounded whatever n is. open_chunks: as chunk_bits, others are left out.
    """
    spark, c, width = grid.tiles.sparkSession, grid.c, grid.col_block
    ship(spark)
    parts = vector_segments(vector, width).join(grid.parts, "col_block").withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    sent = None if open_chunks is None else spark.sparkContext.broadcast(open_chunks)  # bounded by BROADCAST_BYTES
    lane_type = s.sql_type

    def run(tiles, segments):
        import pyarrow as pa

        tiles, lane = tiles.combine_chunks(), pa.from_numpy_dtype(np.dtype(s.dtype))
        ids, keep = np.asarray(tiles["chunk_id"]), np.arange(tiles.num_rows)
        if sent is not None:
            keep = np.flatnonzero(sent.value[ids >> 3] >> (7 - (ids & 7)) & 1)
        if not len(keep) or not segments.num_rows:
            return pa.table({"chunk_id": pa.array([], pa.int64()), "lanes": pa.array([], pa.list_(lane))})
        x = np.full(width, s.zero, s.dtype)
        for at, value in zip(segments["seg_at"].to_pylist(), segments["seg_x"].to_pylist(), strict=True):
            x[at] = value
        taken = tiles.take(pa.array(keep)).combine_chunks()
        lanes_of, at = taken["lane"].combine_chunks(), taken["at"].combine_chunks()
        chunk, own = np.unique(ids[keep], return_inverse=True)
        place = np.repeat(own, np.asarray(lanes_of.value_lengths())) * c + np.asarray(lanes_of.flatten())
        out = np.full(len(chunk) * c, s.zero, s.dtype)
        s.np_plus.at(out, place, s.np_edge(x[np.asarray(at.flatten())]))
        some = (out.reshape(-1, c) != s.zero).any(axis=1)
        flat = out.reshape(-1, c)[some].ravel()
        return pa.table({"chunk_id": pa.array(chunk[some], pa.int64()), "lanes": pa.ListArray.from_arrays(pa.array(np.arange(0, len(flat) + 1, c, dtype=np.int32)), pa.array(flat, lane))})

    partials = grid.tiles.groupBy("col_block", "part").cogroup(parts.select("col_block", "part", "seg_at", "seg_x").groupBy("col_block", "part")).applyInArrow(run, f"chunk_id long, lanes array<{lane_type}>")
    return lanes_to_vector(merge_lanes(partials, s, c), c).where(F.col("y") != F.lit(s.zero).cast(s.sql_type))


def mv_sparse(edges: DataFrame, vector: DataFrame, s: Semiring) -> DataFrame:
    """(row, y) for the neighbours of a sparse vector's places, by vertex."""
    return combine(edges.select(F.col("dst").alias("row"), F.col("src").alias("col")), vector, s)


def mv_dense(edges: DataFrame, vertices: DataFrame, vector: DataFrame, s: Semiring) -> DataFrame:
    """The textbook product over all n * n cells. n is checked: this baseline is for tiny graphs."""
    n = vertices.count()
    if n > DENSE_LIMIT:
        raise ValueError(f"{n} vertices; the dense product takes at most {DENSE_LIMIT}")
    cells = vertices.select(F.col("id").alias("row")).crossJoin(vertices.select(F.col("id").alias("col")))
    full = cells.join(edges.select(F.col("dst").alias("row"), F.col("src").alias("col"), F.lit(1).alias("hit")), ["row", "col"], "left")
    x = s.edge(F.col("x").cast(s.sql_type))
    full = full.join(vector.withColumnRenamed("pos", "col"), "col", "left")
    value = F.when(F.col("hit").isNotNull() & F.col("x").isNotNull(), x).otherwise(F.lit(s.zero).cast(s.sql_type))
    return full.groupBy("row").agg(s.aggregate(value).alias("y"))


def dense_bits(edges: DataFrame, ranked: DataFrame) -> DataFrame:
    """The matrix for mv_dense_bits: (row, col), rows by id and columns by place, a row's columns together in one task. ranked: (id, pos)."""
    placed = edges.join(ranked, F.col("src") == F.col("id")).select(F.col("dst").alias("row"), F.col("pos").alias("col"))
    return cut(placed.repartition("row").sortWithinPartitions("row", "col"))


def mv_dense_bits(matrix: DataFrame, vector: DataFrame, n: int) -> DataFrame:
    """The textbook product in the boolean semiring: (row) where it is true. Tasks lay each row out in full, n bits of 64 a word, and go through all of them. vector: (pos) of its ones, broadcast as n bits under a checked bound."""
    if n > 8 * BROADCAST_BYTES:
        raise ValueError(f"a vector of {n} bits is not broadcast")
    spark, words = matrix.sparkSession, max(1, -(-n // 64))
    ship(spark)
    x = np.zeros(words, np.uint64)
    ones = np.asarray(vector.toArrow()["pos"]).astype(np.int64)
    np.bitwise_or.at(x, ones >> 6, np.uint64(1) << (ones & 63).astype(np.uint64))
    sent = spark.sparkContext.broadcast(x)

    def multiply(batches: Iterator) -> Iterator:
        import pyarrow as pa

        x = sent.value
        dense = np.zeros((max(1, (1 << 20) // (8 * len(x))), len(x)), np.uint64)  # about a megabyte of rows at once
        for batch in batches:
            row, col = np.asarray(batch.column(0)), np.asarray(batch.column(1))
            first = np.flatnonzero(np.diff(row, prepend=row[:1] - 1))
            ends, true = np.append(first[1:], len(row)), np.zeros(len(first), bool)
            at, bit = np.repeat(np.arange(len(first)), ends - first), np.uint64(1) << (col & 63).astype(np.uint64)
            for k in range(0, len(first), len(dense)):
                some = dense[: len(first) - k]
                a, b = first[k], ends[k + len(some) - 1]
                some.fill(0)
                np.bitwise_or.at(some.reshape(-1), (at[a:b] - k) * len(x) + (col[a:b] >> 6), bit[a:b])
                np.bitwise_and(some, x, out=some)
                true[k : k + len(some)] = some.any(axis=1)
            yield pa.RecordBatch.from_arrays([pa.array(row[first[true]])], names=["row"])

    # a row that two batches share is multiplied in two parts
    return matrix.mapInArrow(multiply, "row long").distinct()


def mv_power(layout: Layout, vector: DataFrame, s: Semiring, k: int) -> DataFrame:
    """k products in a row."""
    from graphslices.session import cut

    for _ in range(k):
        vector = cut(mv_slices(layout, vector, s).select(F.col("row").alias("pos"), F.col("y").alias("x")))
    return vector

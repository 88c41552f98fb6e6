"""Representations of a graph: adjacency list, CSR, valued and pattern slices, tiles and grids.

Slices: rows are ordered by degree inside scopes of sigma rows, C rows make a chunk, a chunk's rows are padded to its longest one and stored column by column. Pattern
slices keep no values, only neighbours' places and a marker in padded slots. A chunk wider than `tile_width` columns is stored as several tiles, so no row of the table grows with a hub.
"""

from __future__ import annotations

import math
import uuid
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphslices.edges import all_degrees, global_rank
from graphslices.schema import MARK
from graphslices.session import cut, shared_dir, ship, stored

LANES = {"avx32": 8, "knl32": 16, "gpu": 32}
WIDE = 4096
PLACES_BYTES = 64 << 20
PLACES_ARRAYS = 256 << 20
BUCKET = 1 << 21


def lane_width(unit: str) -> int:
    return LANES[unit]


def sigma_ladder(n: int, c: int) -> list[int]:
    """Scopes to try: 1, C, the power of two at sqrt(n) and above, further powers of four, n."""
    root = 1 << max(0, math.ceil(math.log2(max(1.0, math.sqrt(n)))))
    steps = {1, c, max(root, 1), n}
    k = root * 4
    while k < n:
        steps.add(k)
        k *= 4
    return sorted(x for x in steps if 1 <= x <= max(n, 1))


def default_sigma(n: int, c: int) -> int:
    return max(c, 1 << max(0, math.ceil(math.log2(max(1.0, math.sqrt(n))))))


def sorted_positions(deg: DataFrame, sigma: int | None) -> DataFrame:
    """(id, deg, pos) with rows ordered by (degree descending, id) in scopes of sigma ids; None: over all rows."""
    if sigma is None:
        return global_rank(deg, F.desc("deg"), F.asc("id"))
    ranked = global_rank(deg, F.asc("id"))
    if sigma == 1:
        return ranked
    block = F.floor(F.col("pos") / sigma)
    inside = F.row_number().over(Window.partitionBy("block").orderBy(F.desc("deg"), "id")) - 1
    return ranked.withColumn("block", block).withColumn("pos", (F.col("block") * sigma + inside).cast("long")).drop("block")


def restore_ids(vector: DataFrame, positions: DataFrame) -> DataFrame:
    """A vector by place (pos, ...) as one by vertex (vertex, ...)."""
    return vector.join(positions.select("pos", F.col("id").alias("vertex")), "pos").drop("pos")


def build_adjacency(edges: DataFrame, values: str | None = None) -> DataFrame:
    """(vertex, nbrs[, val]): neighbours in ascending order."""
    if values is None:
        return edges.groupBy(F.col("src").alias("vertex")).agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))
    both = F.sort_array(F.collect_list(F.struct("dst", F.col(values).alias("v"))))
    return edges.groupBy(F.col("src").alias("vertex")).agg(both.alias("b")).select("vertex", F.col("b.dst").alias("nbrs"), F.col("b.v").alias("val"))


def build_csr(edges: DataFrame, values: str | None = None) -> DataFrame:
    """Adjacency with explicit values and the offset of each row among all entries."""
    adj = build_adjacency(edges if values else edges.withColumn("__one", F.lit(1.0)), values or "__one")
    sized = global_rank(adj.withColumn("__k", F.size("nbrs").cast("long")), F.asc("vertex")).withColumn("__b", F.floor(F.col("pos") / 65536))
    # prefix sums in two levels: within blocks of rows, then over the blocks
    before = Window.rowsBetween(Window.unboundedPreceding, -1)
    blocks = sized.groupBy("__b").agg(F.sum("__k").alias("__s")).withColumn("__base", F.coalesce(F.sum("__s").over(before.orderBy("__b")), F.lit(0)))
    own = F.coalesce(F.sum("__k").over(before.partitionBy("__b").orderBy("pos")), F.lit(0))
    return sized.withColumn("__own", own).join(blocks.drop("__s"), "__b").select("vertex", "nbrs", "val", (F.col("__own") + F.col("__base")).cast("long").alias("offset"))


@dataclass(frozen=True)
class Layout:
    """slices: (chunk_id, tile_id, width, col[, val]); positions: (id, deg, pos)."""

    slices: DataFrame
    positions: DataFrame
    c: int
    sigma: int
    n: int
    nnz: int
    tile_width: int
    valued: bool = False

    @property
    def chunks(self) -> int:
        return -(-self.n // self.c)

    @cached_property
    def packed(self) -> DataFrame:
        """(chunks, widths, cols): the pattern as bytes, many slices a row, for products that read it level by level. Slices stay in their tasks."""
        return cut(_packed(self.slices))

    def meta(self) -> DataFrame:
        pad = self.slices.agg(F.coalesce(F.sum(F.col("width").cast("long") * self.c), F.lit(0)).alias("s"))
        return pad.select(
            F.lit(self.c).alias("c"), F.lit(self.sigma).cast("long").alias("sigma"), F.lit(self.n).cast("long").alias("n"), F.lit(self.nnz).cast("long").alias("nnz"),
            F.lit(self.chunks).cast("long").alias("chunks"), (F.col("s") - self.nnz).alias("pad_slots"), F.lit(self.tile_width).alias("tile_width"), F.lit(self.valued).alias("valued"),
        )


def build_slices(
    edges: DataFrame, c: int = 8, sigma: int | None = None, values: str | None = None, valued: bool = False, tile_width: int = WIDE,
    vertices: DataFrame | None = None, pad_value: float = 0.0, spread: int = 1 << 20, deg: DataFrame | None = None,
) -> Layout:
    """Slices of (src, dst[, values]). sigma None: one scope over all rows. vertices (id) adds isolated ones. deg: (id, deg) of all vertices, where it is known.

    Places under a checked bound go to the edges as arrays, and buckets of chunks are laid out at once; with more places, values or hubs, places are joined and slots are ranked by windows.
    """
    valued = valued or values is not None
    deg = stored(all_degrees(edges, vertices)) if deg is None else deg
    n, nnz, top, least = deg.agg(F.count("*"), F.coalesce(F.sum("deg"), F.lit(0)), F.coalesce(F.max("deg"), F.lit(0)), F.coalesce(F.min("deg"), F.lit(0))).first()
    pos = stored(sorted_positions(deg, sigma).select("id", "deg", "pos"))
    if values is None and nnz and 16 * n <= PLACES_ARRAYS and c * top <= 4 * spread:
        slices = _bucketed(edges, pos, c, nnz, tile_width, valued, pad_value)
        return Layout(stored(slices if least else slices.unionByName(_isolated(pos, c, valued))), pos, c, sigma or n, n, nnz, tile_width, valued)
    kept = ["v"] if valued else []
    value = [F.col(values).cast("double").alias("v") if values else F.lit(1.0).alias("v")] if valued else []
    sent = F.broadcast if 32 * n <= PLACES_BYTES else lambda df: df  # places under a checked bound go to the edges, which then are shuffled once
    entry = edges.select("src", "dst", *value).join(sent(pos.select(F.col("id").alias("src"), F.col("pos").alias("row"))), "src")
    entry = entry.join(sent(pos.select(F.col("id").alias("dst"), F.col("pos").alias("col"))), "dst").select("row", "col", *kept)
    entry = entry.withColumn("chunk_id", F.floor(F.col("row") / c))
    if n > spread:
        # A slot is a neighbour's rank in its row: inside stretches of columns, after the counts of the stretches before, so that a hub's row is not one window.
        part = F.floor(F.col("col") / spread)
        counts = entry.groupBy("row", part.alias("part")).agg(F.count("*").alias("k"))
        before = Window.partitionBy("row").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
        base = counts.select("row", "part", F.coalesce(F.sum("k").over(before), F.lit(0)).alias("base"))
        own = F.row_number().over(Window.partitionBy("row", "part").orderBy("col")) - 1
        entry = entry.withColumn("part", part).withColumn("own", own).join(base, ["row", "part"]).withColumn("slot", (F.col("own") + F.col("base")).cast("int"))
    else:
        # One stretch holds every column: dealt by chunk once, the ranks and the tiles need no further shuffle.
        entry = entry.repartition("chunk_id").withColumn("slot", F.row_number().over(Window.partitionBy("chunk_id", "row").orderBy("col")) - 1)
    place = ((F.col("slot") % tile_width) * c + F.col("row") % c).cast("int")
    tile = F.floor(F.col("slot") / tile_width).cast("int").alias("tile_id")
    tiles = entry.groupBy("chunk_id", tile).agg(F.collect_list(F.struct(place.alias("k"), "col", *kept)).alias("cells"))
    parts = tiles.select("chunk_id", "tile_id", F.col("cells.k").alias("k"), F.col("cells.col").alias("col"), *([F.col("cells.v").alias("v")] if valued else []))
    slices = _filled(parts, c, valued, pad_value)
    return Layout(stored(slices.unionByName(_isolated(pos, c, valued))), pos, c, sigma or n, n, nnz, tile_width, valued)


def _isolated(pos: DataFrame, c: int, valued: bool) -> DataFrame:
    """Slices of no width for the chunks whose rows have no neighbours."""
    return pos.groupBy(F.floor(F.col("pos") / c).alias("chunk_id")).agg(F.max("deg").alias("top")).where("top = 0").select(
        "chunk_id", F.lit(0).alias("tile_id"), F.lit(0).alias("width"), F.array().cast("array<bigint>").alias("col"), *([F.array().cast("array<double>").alias("val")] if valued else [])
    )


def _places(pos: DataFrame) -> tuple:
    """Places by vertex as arrays: (first id, places) where ids are dense, else (sorted ids, their places)."""
    import numpy as np

    got = pos.select("id", "pos").toArrow()
    ids, at = np.asarray(got["id"]), np.asarray(got["pos"]).astype(np.int32)
    low, high = int(ids.min()), int(ids.max())
    if high - low < 4 * len(ids):
        table = np.zeros(high - low + 1, np.int32)
        table[ids - low] = at
        return low, table
    order = np.argsort(ids)
    return ids[order], at[order]


def _bucketed(edges: DataFrame, pos: DataFrame, c: int, nnz: int, tile_width: int, valued: bool, pad_value: float) -> DataFrame:
    """Slices of unvalued edges. Cells move once, as bytes, to buckets of about BUCKET cells; a bucket's cells are sorted by row and column and written at their slots. A bucket holds whole chunks."""
    spark = edges.sparkSession
    ship(spark)
    buckets = max(spark.sparkContext.defaultParallelism, -(-nnz // BUCKET))
    sent = spark.sparkContext.broadcast(_places(pos))  # bounded by PLACES_ARRAYS

    def deal(batches: Iterator) -> Iterator:
        import numpy as np
        import pyarrow as pa

        first, table = sent.value

        def place(ids):
            return (table[ids - first] if isinstance(first, int) else table[np.searchsorted(first, ids)]).astype(np.int64)

        def moved(held):
            row, col = (place(np.concatenate([np.asarray(b.column(i)) for b in held])) for i in (0, 1))
            own = (row // c % buckets).astype(np.int16 if buckets < 1 << 15 else np.int32)
            order = np.argsort(own, kind="stable")
            own, cells = own[order], ((row << 32) | col)[order]
            start = np.flatnonzero(np.diff(own, prepend=-1))
            offsets = pa.py_buffer(np.append(start, len(own)).astype(np.int32) * 8)
            blobs = pa.Array.from_buffers(pa.binary(), len(start), [None, offsets, pa.py_buffer(cells)])
            return pa.RecordBatch.from_arrays([pa.array(own[start].astype(np.int32)), blobs], names=["bucket", "cells"])

        held, size = [], 0
        for b in batches:
            held.append(b)
            size += len(b)
            if size >= 1 << 20:
                yield moved(held)
                held, size = [], 0
        if size:
            yield moved(held)

    def laid(cells) -> Iterator:
        import numpy as np
        import pyarrow as pa

        cells = np.sort(cells)
        row, col = cells >> 32, cells & 0xFFFFFFFF
        at = np.arange(len(row))
        opens = np.flatnonzero(np.diff(row, prepend=-1))
        slot = at - np.repeat(opens, np.diff(np.append(opens, len(row))))
        begins = np.flatnonzero(np.diff(row // c, prepend=-1))
        size = np.diff(np.append(begins, len(row)))
        chunk, top = row[begins] // c, np.maximum.reduceat(slot, begins) + 1
        group = np.cumsum(top * c) >> 22  # batches of some four million slots
        bounds = np.append(np.flatnonzero(np.diff(group, prepend=-1)), len(chunk))
        for a, b in zip(bounds[:-1], bounds[1:], strict=True):
            some = slice(begins[a], begins[a] + size[a:b].sum())
            ends = np.cumsum(top[a:b] * c)
            target = np.repeat(ends - top[a:b] * c, size[a:b]) + slot[some] * c + row[some] % c
            tiles = -(-top[a:b] // tile_width)
            tile = np.arange(tiles.sum()) - np.repeat(np.cumsum(tiles) - tiles, tiles)
            width = np.minimum(np.repeat(top[a:b], tiles) - tile * tile_width, tile_width)
            offsets = pa.array(np.append(0, np.cumsum(width * c)).astype(np.int32))
            arrays = [pa.array(np.repeat(chunk[a:b], tiles)), pa.array(tile.astype(np.int32)), pa.array(width.astype(np.int32))]
            for values, fill, kind in ((col[some], MARK, np.int64), (1.0, pad_value, np.float64))[: 1 + valued]:
                flat = np.full(int(ends[-1]), fill, kind)
                flat[target] = values
                arrays.append(pa.ListArray.from_arrays(offsets, pa.array(flat)))
            yield pa.RecordBatch.from_arrays(arrays, names=["chunk_id", "tile_id", "width", "col", "val"][: 4 + valued])

    def lay(batches: Iterator) -> Iterator:
        import numpy as np

        now, held = None, []
        for b in batches:
            for bucket, cells in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                if bucket != now and held:
                    yield from laid(np.concatenate(held))
                    held = []
                now = bucket
                held.append(np.frombuffer(cells.as_buffer(), np.int64))
        if held:
            yield from laid(np.concatenate(held))

    dealt = edges.select(F.col("src").cast("long"), F.col("dst").cast("long")).mapInArrow(deal, "bucket int, cells binary")
    return dealt.repartition(buckets, "bucket").sortWithinPartitions("bucket").mapInArrow(lay, "chunk_id long, tile_id int, width int, col array<bigint>" + ", val array<double>" * valued)


def _packed(slices: DataFrame, slots: int = 1 << 18) -> DataFrame:
    """Slices as rows of bytes, each of about `slots` slots: chunks and places of up to 2^31 rows as 32-bit numbers."""
    ship(slices.sparkSession)

    def run(batches: Iterator) -> Iterator:
        import numpy as np
        import pyarrow as pa

        for b in batches:
            if not len(b):
                continue
            chunk, width = np.asarray(b.column(0)).astype(np.int32), np.asarray(b.column(1)).astype(np.int32)
            cols, sizes = np.asarray(b.column(2).flatten()).astype(np.int32), np.asarray(b.column(2).value_lengths()).astype(np.int64)
            ends = np.cumsum(sizes)
            bounds = np.append(np.flatnonzero(np.diff(ends // slots, prepend=-1)), len(ends))
            parts = [(i, j, ends[i] - sizes[i], ends[j - 1]) for i, j in zip(bounds[:-1], bounds[1:], strict=True)]
            arrays = [[chunk[i:j].tobytes() for i, j, _, _ in parts], [width[i:j].tobytes() for i, j, _, _ in parts], [cols[x:y].tobytes() for _, _, x, y in parts]]
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.binary()) for a in arrays], names=["chunks", "widths", "cols"])

    return slices.select("chunk_id", "width", "col").mapInArrow(run, "chunks binary, widths binary, cols binary")


def _filled(parts: DataFrame, c: int, valued: bool, pad_value: float) -> DataFrame:
    """Slices from their cells (k, col[, v]) in any order: the longest row gives the width, markers and pad values fill the rest."""
    ship(parts.sparkSession)

    def run(batches: Iterator) -> Iterator:
        import numpy as np
        import pyarrow as pa

        for b in batches:
            if not len(b):
                continue
            k = np.asarray(b.column(2).flatten()).astype(np.int64)
            size = np.asarray(b.column(2).value_lengths()).astype(np.int64)
            width = np.maximum.reduceat(k, np.cumsum(size) - size) // c + 1
            ends = np.cumsum(width * c)
            at = np.repeat(ends - width * c, size) + k
            offsets = pa.array(np.append(0, ends).astype(np.int32))
            arrays = [b.column(0), b.column(1), pa.array(width.astype(np.int32))]
            for i, fill, kind in ((3, MARK, np.int64), (4, pad_value, np.float64))[: 1 + valued]:
                flat = np.full(int(ends[-1]), fill, kind)
                flat[at] = np.asarray(b.column(i).flatten())
                arrays.append(pa.ListArray.from_arrays(offsets, pa.array(flat)))
            yield pa.RecordBatch.from_arrays(arrays, names=["chunk_id", "tile_id", "width", "col", "val"][: 4 + valued])

    return parts.mapInArrow(run, "chunk_id long, tile_id int, width int, col array<bigint>" + ", val array<double>" * valued)


def build_pattern_slices(edges: DataFrame, c: int = 8, sigma: int | None = None, tile_width: int = WIDE, vertices: DataFrame | None = None) -> Layout:
    return build_slices(edges, c, sigma, tile_width=tile_width, vertices=vertices)


def build_valued_slices(edges: DataFrame, c: int = 8, sigma: int | None = None, values: str | None = None, tile_width: int = WIDE, vertices: DataFrame | None = None, pad_value: float = 0.0) -> Layout:
    return build_slices(edges, c, sigma, values, True, tile_width, vertices, pad_value)


def implied_values(col: Column, zero: float, one: float) -> Column:
    """The values a pattern stands for: `one` in real slots, `zero` in padded ones."""
    return F.transform(col, lambda x: F.when(x == MARK, F.lit(zero)).otherwise(F.lit(one)))


def tile_slices(layout: Layout, width: int) -> Layout:
    """The same slots in tiles of at most `width` columns; nothing is shuffled."""
    c = layout.c
    pieces = F.ceil(F.greatest("width", F.lit(1)) / width).cast("int")
    step = F.explode(F.sequence(F.lit(0), pieces - 1)).alias("piece")
    cut_at = lambda name: F.slice(name, F.col("piece") * (width * c) + 1, F.lit(width * c))
    made = layout.slices.select("*", step).select(
        "chunk_id", (F.col("tile_id") * F.lit(-(-layout.tile_width // width)) + F.col("piece")).cast("int").alias("tile_id"),
        F.least(F.col("width") - F.col("piece") * width, F.lit(width)).alias("width"), cut_at("col").alias("col"), *([cut_at("val").alias("val")] if layout.valued else []),
    )
    return Layout(made, layout.positions, c, layout.sigma, layout.n, layout.nnz, width, layout.valued)


def grid_tiles(layout: Layout, col_block: int) -> DataFrame:
    """Tiles (chunk_id, col_block, width, col) whose neighbours lie in one block of columns, places counted from the block's first: rows for a product that moves only vectors."""
    c = layout.c
    cells = layout.slices.select("chunk_id", F.posexplode("col").alias("i", "col")).where(F.col("col") != MARK)
    cells = cells.select("chunk_id", (F.col("i") % c).cast("int").alias("lane"), F.floor(F.col("col") / col_block).alias("col_block"), (F.col("col") % col_block).alias("at"))
    slot = F.row_number().over(Window.partitionBy("chunk_id", "lane", "col_block").orderBy("at")) - 1
    cells = cells.withColumn("slot", slot)
    return cells.groupBy("chunk_id", "col_block", F.floor(F.col("slot") / layout.tile_width).cast("int").alias("tile_id")).agg(
        F.collect_list("lane").alias("lane"), F.collect_list("at").alias("at")
    )


@dataclass(frozen=True)
class Grid:
    """tiles: (chunk_id, col_block, tile_id, part, lane, at), a table bucketed by (col_block, part); parts: (col_block, parts). A part holds about `cells_a_part` cells of one block, so a hub's block is no single task."""

    tiles: DataFrame
    parts: DataFrame
    c: int
    col_block: int


def build_grid(layout: Layout, col_block: int = 1 << 16, cells_a_part: int = 1 << 22) -> Grid:
    """The layout's grid tiles as a bucketed table in the shared folder: joined by its buckets, it is not shuffled again."""
    spark = layout.slices.sparkSession
    tiles = cut(grid_tiles(layout, col_block))
    parts = cut(tiles.groupBy("col_block").agg(F.ceil(F.sum(F.size("at")) / cells_a_part).cast("int").alias("parts")))
    own = F.pmod(F.xxhash64("chunk_id"), F.col("parts")).cast("int").alias("part")
    name, buckets = f"graphslices_grid_{uuid.uuid4().hex}", int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = tiles.join(parts, "col_block").select("chunk_id", "col_block", "tile_id", own, "lane", "at").repartition(buckets, "col_block", "part")
    dealt.write.bucketBy(buckets, "col_block", "part").sortBy("col_block", "part").option("path", f"{shared_dir(spark)}/{name}").saveAsTable(name)
    return Grid(spark.table(name), parts, layout.c, col_block)


def chunk_directory(layout: Layout) -> DataFrame:
    """(chunk_id, cl, cs): widths and starts of the chunks among all slots, by prefix sums in two levels."""
    w = layout.slices.groupBy("chunk_id").agg(F.sum("width").cast("long").alias("cl")).withColumn("b", F.floor(F.col("chunk_id") / 65536))
    before = Window.rowsBetween(Window.unboundedPreceding, -1)
    blocks = w.groupBy("b").agg(F.sum("cl").alias("s")).withColumn("base", F.coalesce(F.sum("s").over(before.orderBy("b")), F.lit(0)))
    own = F.coalesce(F.sum("cl").over(before.partitionBy("b").orderBy("chunk_id")), F.lit(0))
    return w.withColumn("own", own).join(blocks, "b").select("chunk_id", "cl", ((F.col("own") + F.col("base")) * layout.c).cast("long").alias("cs"))


def chunk_row(layout: Layout, lane: int) -> DataFrame:
    """(chunk_id, tile_id, col): the entries of one lane of each slice, row-wise."""
    return layout.slices.select("chunk_id", "tile_id", F.filter("col", lambda x, i: (i % layout.c == lane) & (x != MARK)).alias("col"))


def entries(slices: DataFrame, c: int, valued: bool = False) -> DataFrame:
    """(row, col[, val]) of the real slots, by place."""
    source = F.posexplode(F.arrays_zip("col", "val")).alias("i", "e") if valued else F.posexplode("col").alias("i", "col")
    cells = slices.select("chunk_id", source)
    if valued:
        cells = cells.select("chunk_id", "i", "e.col", "e.val")
    cells = cells.where(F.col("col") != MARK)
    return cells.select((F.col("chunk_id") * c + F.col("i") % c).alias("row"), "col", *(["val"] if valued else []))


def slices_to_edges(layout: Layout) -> DataFrame:
    """(src, dst[, val]) by vertex: the inverse of building."""
    p = layout.positions
    e = entries(layout.slices, layout.c, layout.valued)
    e = e.join(p.select(F.col("pos").alias("row"), F.col("id").alias("src")), "row").join(p.select(F.col("pos").alias("col"), F.col("id").alias("dst")), "col")
    return e.select("src", "dst", *(["val"] if layout.valued else []))


def save_layout(layout: Layout, path: str) -> None:
    """Slices sorted by chunk, so that ranges of settled chunks are skipped by file statistics; positions; one row of parameters. (A grid is stored by build_grid, bucketed by column block.)"""
    layout.slices.repartitionByRange("chunk_id").sortWithinPartitions("chunk_id", "tile_id").write.parquet(f"{path}/slices")
    layout.positions.write.parquet(f"{path}/positions")
    layout.meta().coalesce(1).write.parquet(f"{path}/layout_meta")


def open_layout(spark: SparkSession, path: str) -> Layout:
    m = spark.read.parquet(f"{path}/layout_meta").first()
    return Layout(spark.read.parquet(f"{path}/slices"), spark.read.parquet(f"{path}/positions"), m.c, m.sigma, m.n, m.nnz, m.tile_width, m.valued)

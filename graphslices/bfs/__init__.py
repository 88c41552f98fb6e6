"""Breadth-first traversals: dense-frontier over slices, and the baselines."""

from graphslices.bfs.dense import BfsResult, bfs_dense, bfs_many
from graphslices.bfs.frontier import bfs_bag, bfs_csr, bfs_direction, bfs_queue, bfs_recursive_sql, bfs_sparse, bfs_textbook_dense
from graphslices.bfs.parents import recover_parents

__all__ = ["BfsResult", "bfs_bag", "bfs_csr", "bfs_dense", "bfs_direction", "bfs_many", "bfs_queue", "bfs_recursive_sql", "bfs_sparse", "bfs_textbook_dense", "recover_parents"]

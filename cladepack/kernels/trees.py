"""Rebuilding trees from their clusters."""

from __future__ import annotations

import numpy as np


def sort_clusters(rows: np.ndarray) -> np.ndarray:
    """Clusters (boolean matrix, one row each) by ascending cardinality, the root of all leaves added as the last row."""
    rows = rows[np.argsort(rows.sum(1), kind="stable")]
    return np.vstack([rows, np.ones((1, rows.shape[1]), bool)])


def leaf_path(rows: np.ndarray, early_stop: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Parents of the leaves and of the clusters of a matrix from sort_clusters; the root's parent is -1.

    The clusters of a leaf, by ascending size, are its path to the root. Paths are walked leaf after leaf; a walk ends at
    the first cluster that another one has placed, since the rest of the path is there.
    """
    n_clusters, n = rows.shape
    return walk_paths(*np.nonzero(rows.T), n, n_clusters, early_stop)


def memberships(bits: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(leaf, cluster) by leaf and cluster, of packed bits (one row for each cluster) and the root, which comes last. No more
    than some million bits stand unpacked at once."""
    step, leaves, clusters = max(1, 8_000_000 // max(1, n)), [np.arange(n)], [np.full(n, len(bits))]
    for lo in range(0, len(bits), step):
        c, x = np.nonzero(np.unpackbits(bits[lo : lo + step], axis=1)[:, :n])
        leaves.append(x)
        clusters.append(c + lo)
    leaf, cluster = np.concatenate(leaves), np.concatenate(clusters)
    order = np.lexsort((cluster, leaf))
    return leaf[order], cluster[order]


def by_leaf(cluster: np.ndarray, leaf: np.ndarray, n: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    """memberships of k clusters that are given by their members (cluster, leaf)."""
    return np.divmod(np.sort(np.concatenate((leaf * (k + 1) + cluster, np.arange(n) * (k + 1) + k))), k + 1)


def walk_paths(leaf: np.ndarray, cluster: np.ndarray, n: int, n_clusters: int, early_stop: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """leaf_path over memberships, by leaf and ascending cluster."""
    starts = np.searchsorted(leaf, np.arange(n + 1)).tolist()
    path = cluster.tolist()
    leaf_parent, parent, built = [-1] * n, [-1] * n_clusters, [False] * n_clusters
    for x in range(n):
        below = -1
        for k in range(starts[x], starts[x + 1]):
            c = path[k]
            if below < 0:
                leaf_parent[x] = c
            else:
                parent[below] = c
            if built[c] and early_stop:
                break
            built[c] = True
            below = c
    return np.array(leaf_parent), np.array(parent)


def pairwise(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The same by comparing all pairs: a parent is the least strict superset."""
    size = rows.sum(1)
    inside = (rows.astype(np.int32) @ rows.T.astype(np.int32)) == size[:, None]  # i within j
    parent = np.full(len(rows), -1)
    for i in range(len(rows)):
        above = np.flatnonzero(inside[i] & (size > size[i]))
        if len(above):
            parent[i] = above[np.argmin(size[above])]
    return rows.argmax(0), parent


def refine(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The same by refining a star: clusters enter in descending size, each below the node its leaves hang on."""
    n_clusters, n = rows.shape
    at = np.full(n, n_clusters - 1)
    parent = np.full(n_clusters, -1)
    for c in range(n_clusters - 2, -1, -1):
        parent[c] = at[np.argmax(rows[c])]
        at[rows[c]] = c
    return at, parent


def is_laminar(rows: np.ndarray) -> bool:
    """Whether any two clusters are nested or disjoint."""
    common = rows.astype(np.int32) @ rows.T.astype(np.int32)
    size = rows.sum(1)
    return bool(((common == 0) | (common == size[:, None]) | (common == size[None, :])).all())


METHODS = {"leaf_path": leaf_path, "pairwise": pairwise, "refine": refine, "leaf_path_full": lambda rows: leaf_path(rows, False)}


def children_lists(leaf_parent: np.ndarray, parent: np.ndarray) -> list[list[int]]:
    """Child lists of the nodes: leaves 0..n-1, then clusters, the root last. A root that repeats the largest cluster is
    not possible, since clusters are proper."""
    n = len(leaf_parent)
    kids: list[list[int]] = [[] for _ in range(n + len(parent))]
    for x, p in enumerate(leaf_parent.tolist()):
        kids[n + p].append(x)
    for c, p in enumerate(parent.tolist()):
        if p >= 0:
            kids[n + p].append(n + c)
    return kids

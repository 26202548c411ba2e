"""Vertex programs in Catalyst expressions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from shardgraph.model.graph import VertexProgram


def pagerank(damping: float = 0.85, tol: float = 0.0, weighted: bool = False, decimal: bool = False, seeds: object = None) -> VertexProgram:
    """(1 - d) / V + d * sum of value / out-degree over in-edges; all active at first.

    Vertices without out-edges pass nothing on, so the sum may fall below 1; see engine.pagerank for
    redistribution. weighted shares a value by the edges' weights over their sum. decimal makes sums independent of order. seeds, a set of ids, personalises the restart.
    """
    share = (lambda v, w, d: v * w / d) if weighted else (lambda v, w, d: v / d)

    def restart(n: int):
        if seeds is None:
            return F.lit((1 - damping) / n)
        return F.when(F.col("id").isin(sorted(seeds)), F.lit((1 - damping) / len(seeds))).otherwise(0.0)

    def gather(v, w, d):
        m = share(v, w, d)
        return m.cast("decimal(38,18)") if decimal else m

    return VertexProgram(
        "pagerank",
        init=lambda n: (F.lit(1.0 / n), F.lit(True)),
        gather=gather,
        combine="sum",
        apply=lambda old, c, n: restart(n) + F.lit(damping) * F.coalesce(c.cast("double"), F.lit(0.0)),
        changed=lambda old, new: F.abs(new - old) > tol if tol else new != old,
        kernel=None if weighted or decimal or seeds is not None else lambda row, col, val, old, deg, lo, n, sent=None: (1 - damping) / n + damping * _sums(row, _shares(col, old, deg) if sent is None else sent[col]),
        pieces=None if weighted or decimal or tol or seeds is not None else (lambda v, w, d: v / np.maximum(d, 1), lambda old, c, n: (1 - damping) / n + damping * c),
        outgoing=None if weighted or decimal or seeds is not None else lambda old, deg: old / np.maximum(deg, 1),
        idempotent=tol == 0,
        degree="out_weight" if weighted else "out_deg",
    )


def _sums(row: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Sums between offsets, zero for empty ranges."""
    out = np.zeros(len(row) - 1)
    some = np.flatnonzero(row[1:] > row[:-1])
    if len(some):
        out[some] = np.add.reduceat(x, row[some])
    return out


def _shares(col: np.ndarray, old: np.ndarray, deg: np.ndarray) -> np.ndarray:
    """Each source's value by its out-degree, divided for the vertices or for the edges, whichever are fewer."""
    return old[col] / np.maximum(deg[col], 1) if len(col) < len(old) else (old / np.maximum(deg, 1))[col]


_FAR = np.iinfo(np.int64).max // 4


def _least(row: np.ndarray, x: np.ndarray) -> np.ndarray:
    out = np.full(len(row) - 1, _FAR)
    some = np.flatnonzero(row[1:] > row[:-1])
    if len(some):
        out[some] = np.minimum.reduceat(x, row[some])
    return out


def sssp(sources=(0,), weighted: bool = True) -> VertexProgram:
    """Least distances from the nearest source; null where no path leads. Unweighted distances are BFS levels."""
    at = F.col("id").isin(sorted(sources))
    return VertexProgram(
        "sssp",
        init=lambda n: (F.when(at, F.lit(0).cast("long")), at),
        gather=(lambda v, w, d: v + w) if weighted else (lambda v, w, d: v + 1),
        combine="min",
        apply=lambda old, c, n: F.least(old, c),
        changed=lambda old, new: ~new.eqNullSafe(old),
        kernel=lambda row, col, val, old, deg, lo, n: np.minimum(old[lo : lo + len(row) - 1], _least(row, np.minimum(old[col] + (val if weighted else 1), _FAR))),
        pieces=(lambda v, w, d: np.minimum(v + (w if weighted else 1), _FAR), lambda old, c, n: np.minimum(old, c)),
    )


def components(pick: str = "min") -> VertexProgram:
    """The least (or greatest) id that reaches a vertex; components where every edge has its reverse."""
    low = pick == "min"
    return VertexProgram(
        "cc",
        init=lambda n: (F.col("id"), F.lit(True)),
        gather=lambda v, w, d: v,
        combine=pick,
        apply=lambda old, c, n: F.least(old, c) if low else F.greatest(old, c),
        changed=lambda old, new: new != old,
        kernel=(lambda row, col, val, old, deg, lo, n: np.minimum(old[lo : lo + len(row) - 1], _least(row, old[col]))) if low else None,
        pieces=(lambda v, w, d: v, lambda old, c, n: np.minimum(old, c)) if low else None,
        jumps=True,
    )


def bfs(source: int = 0) -> VertexProgram:
    return sssp((source,), weighted=False)


def reachability(sources=(0,)) -> VertexProgram:
    """1 where a path from a source leads, else 0."""
    at = F.col("id").isin(sorted(sources))
    return VertexProgram("reach", lambda n: (at.cast("long"), at), lambda v, w, d: v, "max", lambda old, c, n: F.greatest(old, c), lambda old, new: new != old)


def widest_path(source: int = 0) -> VertexProgram:
    """The greatest least edge value over paths from the source; null where none leads."""
    at = F.col("id") == source
    top = F.lit(2**62)
    return VertexProgram("widest", lambda n: (F.when(at, top), at), lambda v, w, d: F.when(v.isNotNull(), F.least(v, w)), "max", lambda old, c, n: F.greatest(old, c), lambda old, new: ~new.eqNullSafe(old))


def max_propagation() -> VertexProgram:
    return components("max")


def in_degree() -> VertexProgram:
    """One round: the number of in-edges."""
    return VertexProgram("in_degree", lambda n: (F.lit(1).cast("long"), F.lit(True)), lambda v, w, d: F.lit(1).cast("long"), "sum", lambda old, c, n: F.coalesce(c, F.lit(0).cast("long")), lambda old, new: F.lit(False))


def label_propagation() -> VertexProgram:
    """The commonest label among in-neighbours, the least of equals; own id at first."""
    return VertexProgram("labels", lambda n: (F.col("id"), F.lit(True)), lambda v, w, d: v, "mode", lambda old, c, n: F.coalesce(c, old), lambda old, new: new != old, idempotent=True)


def influence(damping: float = 0.5) -> VertexProgram:
    """Katz-like sums: 1 + damping * sum of in-neighbours' values."""
    return VertexProgram("influence", lambda n: (F.lit(1.0), F.lit(True)), lambda v, w, d: v, "sum", lambda old, c, n: F.lit(1.0) + F.lit(damping) * F.coalesce(c, F.lit(0.0)), lambda old, new: new != old)

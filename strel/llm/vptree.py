"""Nearest neighbours by vantage-point trees, one for each shard of the vectors.

Largest inner products are smallest distances after one more component levels all lengths, so the
triangle inequality holds. A tree node has a vantage point and the median distance to it; a batch
of queries descends together, each first into its own side, and skips the other side when its
distance to the median sphere, times ``factor``, exceeds that of its k-th best so far. A factor of
one is exact search; a larger one skips more.

Shards are parts of cells: every vector belongs to the nearest of a bounded number of centres
(fitted on a bounded sample), and a cell of more than ``shard_rows`` rows has several shards. A
query first searches its own cell. Its k-th best then bounds which other cells it goes to: those
whose ring around the centre may hold something better, by the triangle inequality and the same
factor. Vectors are stored once by shard and never copied for a query; only a shard that very many
queries come to is read by several tasks. A task holds one shard (and its tree, built in a few
milliseconds) and a batch of queries.

Results are merged by (score, smaller vec_id). Vectors that are null, zero, or hold null or
non-finite components take no part, and neither do null ids; vectors of different lengths are never
compared. Rows that repeat a vec_id are candidates each for itself, and queries each for itself. An
empty table gives no row. Other columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from strel.runtime import materialize, ship

#: Rows aimed at in a cell, and rows of a shard at most (about).
CELL_ROWS, SHARD_ROWS = 2_000, 20_000
#: Centres of a length of vectors at most, rows they are fitted on for each of them, and lengths of
#: vectors (the most frequent ones) that have centres; vectors of another length are one cell.
MAX_CELLS, SAMPLE_A_CELL, CENTRED_DIMS = 4_096, 16, 4
#: Queries of one task at a shard.
TASK_QUERIES = 50_000
LEAF = 256
_FUZZ = 1e-9


class VantageTree:
    """A tree over the rows of ``x`` with integer ids; ties go to the smaller id."""

    def __init__(self, x: np.ndarray, ids: np.ndarray, leaf: int = LEAF, seed: int = 7):
        self.x, self.ids, self.leaf = x, ids, leaf
        norm2 = np.einsum("nd,nd->n", x, x)
        self.top2 = float(norm2.max()) if len(x) else 0.0
        self.lift = np.sqrt(np.maximum(self.top2 - norm2, 0.0))
        self._rng = np.random.default_rng(seed)
        self.root = self._build(np.arange(len(x)))

    def _apart(self, v: int, rows: np.ndarray) -> np.ndarray:
        dot = self.x[rows] @ self.x[v] + self.lift[rows] * self.lift[v]
        return np.sqrt(np.maximum(2 * self.top2 - 2 * dot, 0.0))

    def _build(self, rows: np.ndarray):
        if len(rows) <= self.leaf:
            return rows
        v = int(rows[self._rng.integers(len(rows))])
        d = self._apart(v, rows)
        half = len(rows) // 2
        order = np.argpartition(d, half)
        mu = float(d[order[half]])
        if d.max() - d.min() <= _FUZZ:  # copies of one vector: no sphere parts them
            return rows
        return v, mu, self._build(rows[order[:half]]), self._build(rows[order[half:]])

    def search(self, q: np.ndarray, own: np.ndarray, k: int, factor: float = 1.0, least: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The k best rows for each query but its own id: (query number, row, score) arrays.

        ``least``: scores below which rows do not matter.
        """
        nq = len(q)
        best = np.full((nq, k), -np.inf) if least is None else np.repeat((least - _FUZZ * (1 + np.abs(least)))[:, None], k, 1)
        where = np.full((nq, k), -1)
        q2 = np.einsum("nd,nd->n", q, q)

        def look(rows: np.ndarray, qs: np.ndarray) -> None:
            for at in range(0, len(rows), 4096):
                part = rows[at : at + 4096]
                rough = q[qs] @ self.x[part].T
                rough[own[qs][:, None] == self.ids[part][None, :]] = -np.inf
                i, j = np.nonzero(rough >= best[qs, k - 1][:, None] - _FUZZ * (1 + np.abs(best[qs, k - 1][:, None])) if np.isfinite(best[qs, k - 1]).all() else rough > -np.inf)
                if not len(i):
                    continue
                s = np.einsum("nd,nd->n", q[qs[i]], self.x[part[j]])
                hit, first = np.unique(i, return_index=True)
                some = qs[hit]
                alls = np.concatenate([best[some].ravel(), s])
                allr = np.concatenate([where[some].ravel(), part[j]])
                allq = np.concatenate([np.repeat(hit, k), i])
                ids = np.where(allr >= 0, self.ids[allr], np.iinfo(np.int64).max)
                order = np.lexsort((ids, -alls, allq))
                allq = allq[order]
                begin = np.searchsorted(allq, hit)
                take = order[begin[:, None] + np.arange(k)[None, :]]
                best[some], where[some] = alls[take], allr[take]

        def visit(node, qs: np.ndarray) -> None:
            if not len(qs):
                return
            if isinstance(node, np.ndarray):
                look(node, qs)
                return
            v, mu, inner, outer = node
            d = np.sqrt(np.maximum(q2[qs] + self.top2 - 2 * (q[qs] @ self.x[v]), 0.0))
            inside = d < mu
            gap = np.abs(d - mu) * factor

            def open_(mask: np.ndarray) -> np.ndarray:
                kth = best[qs[mask], k - 1]
                reach = np.sqrt(np.maximum(q2[qs[mask]] + self.top2 - 2 * np.where(np.isfinite(kth), kth, 0.0), 0.0))
                return qs[mask][~np.isfinite(kth) | (gap[mask] <= reach + _FUZZ)]

            visit(inner, qs[inside])
            visit(outer, qs[~inside])
            visit(outer, open_(inside))
            visit(inner, open_(~inside))

        visit(self.root, np.arange(nq))
        i, j = np.nonzero(where >= 0)
        return i, where[i, j], best[i, j]


def _vectors(col: Column) -> Column:
    """The vector in double precision; null where it takes no part."""
    v = F.transform(col, lambda x: x.cast("double"))
    odd = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf"))))
    return F.when(col.isNotNull() & ~odd & F.exists(v, lambda x: x != 0), v)


def _rows(v) -> np.ndarray:
    v = v.combine_chunks() if hasattr(v, "combine_chunks") else v
    return np.asarray(v.flatten(), np.float64).reshape(len(v), -1)


def centres_of(x: np.ndarray, cells: int, rounds: int = 4, seed: int = 3) -> np.ndarray:
    """Centres by a few rounds of k-means."""
    c = x[np.random.default_rng(seed).permutation(len(x))[:cells]]
    for _ in range(rounds):
        near = _nearest_centre(x, c)[0]
        n = np.bincount(near, minlength=len(c))
        total = np.zeros_like(c)
        np.add.at(total, near, x)
        c = np.where(n[:, None] > 0, total / np.maximum(n, 1)[:, None], c)
    return c


def _nearest_centre(x: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    c2 = np.einsum("nd,nd->n", c, c)
    near, far = [], []
    for at in range(0, len(x), 1024):
        part = x[at : at + 1024]
        d = c2[None, :] - 2 * (part @ c.T)
        i = d.argmin(1)
        near.append(i)
        far.append(np.sqrt(np.maximum(np.einsum("nd,nd->n", part, part) + d[np.arange(len(part)), i], 0.0)))
    return (np.concatenate(near), np.concatenate(far)) if near else (np.zeros(0, int), np.zeros(0))


def _lift(x: np.ndarray, top2: float) -> np.ndarray:
    """One more component that gives all vectors the same length."""
    return np.column_stack([x, np.sqrt(np.maximum(top2 - np.einsum("nd,nd->n", x, x), 0.0))])


def _assign(centres: dict[int, np.ndarray], top2: dict[int, float], lifted: bool):
    """Cell of each vector and its distance to the centre; queries get no lift."""

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for b in batches:
            dim = np.asarray(b.column("dim"))
            cell, far = np.zeros(len(dim), np.int32), np.zeros(len(dim))
            for d, c in centres.items():
                at = np.flatnonzero(dim == d)
                if len(at):
                    x = _rows(b.column("v").take(pa.array(at)))
                    cell[at], far[at] = _nearest_centre(_lift(x, top2[d]) if lifted else np.column_stack([x, np.zeros(len(x))]), c)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(cell), pa.array(far)], [*b.schema.names, "cell", "far"])

    return run


def _route(centres: dict[int, np.ndarray], top2: dict[int, float], rings: dict[int, tuple[np.ndarray, np.ndarray]], factor: float):
    """Cells, but its own, that a query must still visit."""

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for b in batches:
            dim, least, own = (np.asarray(b.column(c)) for c in ("dim", "least", "cell"))
            rows, cells = [], []
            for d, c in centres.items():
                at = np.flatnonzero(dim == d)
                lo, hi = rings[d]
                for some in np.array_split(at, max(1, -(-len(at) // 512))):
                    if not len(some):
                        continue
                    q = np.column_stack([_rows(b.column("v").take(pa.array(some))), np.zeros(len(some))])
                    q2 = np.einsum("nd,nd->n", q, q)
                    far = np.sqrt(np.maximum(q2[:, None] + np.einsum("nd,nd->n", c, c)[None] - 2 * (q @ c.T), 0.0))
                    gap = np.maximum(np.maximum(far - hi[None], lo[None] - far), 0.0) * factor
                    kth = least[some]
                    reach = np.where(np.isfinite(kth), np.sqrt(np.maximum(q2 + top2[d] - 2 * np.where(np.isfinite(kth), kth, 0.0), 0.0)), np.inf)
                    go = (gap <= reach[:, None] + 1e-6 * (1 + math.sqrt(top2[d]))) & np.isfinite(hi)[None]
                    go[np.arange(len(some)), own[some]] = False
                    i, j = np.nonzero(go)
                    rows.append(some[i])
                    cells.append(j)
            if rows:
                i = pa.array(np.concatenate(rows))
                yield pa.RecordBatch.from_arrays([b.column("qrow").take(i), b.column("vec_id").take(i), b.column("v").take(i), b.column("dim").take(i), pa.array(np.concatenate(cells), pa.int32()), b.column("least").take(i)], ["qrow", "vec_id", "v", "dim", "cell", "least"])

    return run


def _visit(k: int, factor: float):
    """Reads each shard's vectors, then its queries: rows come sorted by shard and kind."""

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        names = ["qrow", "query_id", "vec_id", "score"]
        here, parts, tree = None, [], None
        for b in batches:
            if not b.num_rows:
                continue
            keys = np.column_stack([np.asarray(b.column(c)).astype(np.int64) for c in ("dim", "cell", "shard", "block", "asks")])
            first = np.flatnonzero(np.concatenate([[True], (keys[1:] != keys[:-1]).any(1)])).tolist()
            for i, j in zip(first, [*first[1:], len(keys)], strict=True):
                part, place = b.slice(i, j - i), tuple(keys[i][:4].tolist())
                if place != here:
                    here, parts, tree = place, [], None
                if not keys[i][4]:
                    parts.append((_rows(part.column("v")), np.asarray(part.column("vec_id"))))
                    continue
                if tree is None:
                    if not parts:
                        continue
                    tree = VantageTree(np.concatenate([x for x, _ in parts]), np.concatenate([ids for _, ids in parts]))
                    parts = []
                qrow, own, least = (np.asarray(part.column(c)) for c in ("qrow", "vec_id", "least"))
                x = _rows(part.column("v"))
                for at in range(0, len(x), 1024):
                    m, row, s = tree.search(x[at : at + 1024], own[at : at + 1024], k, factor, least[at : at + 1024])
                    yield pa.RecordBatch.from_arrays([pa.array(qrow[at + m]), pa.array(own[at + m]), pa.array(tree.ids[row]), pa.array(s)], names)

    return run


def _searched(shards: DataFrame, asked: DataFrame, tasks: int, k: int, factor: float) -> DataFrame:
    """The k best of every query in every shard of the cells that it comes to."""
    per = asked.groupBy("dim", "cell").agg(F.count(F.lit(1)).alias("asks"))
    blocks = per.select("dim", "cell", F.ceil(F.col("asks") / TASK_QUERIES).cast("int").alias("blocks"))
    sizes = shards.groupBy("dim", "cell", "shard").agg(F.count(F.lit(1)).alias("rows"))
    places = materialize(sizes.join(blocks, ["dim", "cell"]).select("dim", "cell", "shard", "blocks"), "places")
    # a shard's vectors are copied only for further blocks of TASK_QUERIES queries
    kind = lambda d, asks, *more: d.select("dim", "cell", "shard", "block", F.lit(asks).alias("asks"), *more, "vec_id", "v")
    rows = shards.join(places, ["dim", "cell", "shard"]).withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rows = kind(rows, 0, F.lit(None).cast("long").alias("qrow"), F.lit(None).cast("double").alias("least"))
    come = asked.join(places, ["dim", "cell"]).withColumn("block", F.expr("pmod(xxhash64(qrow), blocks)").cast("int"))
    both = rows.unionByName(kind(come, 1, "qrow", "least"))
    both = both.repartition(tasks, "dim", "cell", "shard", "block").sortWithinPartitions("dim", "cell", "shard", "block", "asks")
    found = both.mapInArrow(_visit(k, factor), "qrow long, query_id long, vec_id long, score double")
    best = Window.partitionBy("qrow").orderBy(F.col("score").desc(), "vec_id")
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)


def nearest(
    vectors: DataFrame, queries: DataFrame, k: int = 20, factor: float = 1.0, id_col: str = "vec_id", vec_col: str = "embedding", shard_rows: int = SHARD_ROWS, cell_rows: int = CELL_ROWS
) -> DataFrame:
    """The k rows of ``vectors`` of largest inner product for each row of ``queries``.

    Columns: query_id, rank, vec_id, score. A query's own id is no candidate.
    """
    spark = vectors.sparkSession
    ship(spark)
    narrow = "float" in dict(vectors.dtypes)[vec_col] and "float" in dict(queries.dtypes)[vec_col]
    kept = F.col("v").cast(f"array<{'float' if narrow else 'double'}>")
    clean = lambda d: d.select(F.col(id_col).cast("long").alias("vec_id"), _vectors(F.col(vec_col)).alias("v")).where("vec_id IS NOT NULL AND v IS NOT NULL").withColumn("dim", F.size("v"))
    rows = clean(vectors)
    norm2 = F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x)
    dims = rows.groupBy("dim").agg(F.count(F.lit(1)).alias("n"), F.max(norm2).alias("top2")).orderBy(F.col("n").desc(), "dim").limit(CENTRED_DIMS).collect()
    n = sum(r["n"] for r in dims)
    top2 = {r["dim"]: r["top2"] * (1 + 1e-9) for r in dims}
    centres = {}
    for r in dims:
        cells = min(MAX_CELLS, math.ceil(r["n"] / cell_rows))
        if cells > 1:
            some = rows.where(F.col("dim") == r["dim"]).select("vec_id", "v").orderBy(F.xxhash64("vec_id"), "vec_id").limit(SAMPLE_A_CELL * cells).collect()
            centres[r["dim"]] = centres_of(_lift(np.array([x["v"] for x in some]), top2[r["dim"]]), cells)
    kinds = lambda d: ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in d.schema.fields)
    slim = rows.select("vec_id", kept.alias("v"), "dim")
    stored = materialize(slim.mapInArrow(_assign(centres, top2, True), f"{kinds(slim)}, cell int, far double"), "cells")
    per = stored.groupBy("dim", "cell").agg(F.count(F.lit(1)).alias("n"), F.min("far").alias("lo"), F.max("far").alias("hi"))
    per = materialize(per, "rings")
    rings = {}
    for d, c in centres.items():
        lo, hi = np.zeros(len(c)), np.full(len(c), np.inf)  # a cell without rows keeps inf: nobody goes there
        for x in per.where(F.col("dim") == d).collect():  # at most MAX_CELLS
            lo[x["cell"]], hi[x["cell"]] = x["lo"], x["hi"]
        rings[d] = lo, hi
    shards = stored.join(per.select("dim", "cell", F.ceil(F.col("n") / shard_rows).alias("shards")), ["dim", "cell"])
    shards = shards.select("dim", "cell", F.expr("pmod(xxhash64(vec_id, 2), shards)").cast("int").alias("shard"), "vec_id", "v")
    slim = clean(queries).select(F.monotonically_increasing_id().alias("qrow"), "vec_id", kept.alias("v"), "dim")
    asked = materialize(slim.mapInArrow(_assign(centres, top2, False), f"{kinds(slim)}, cell int, far double"), "queries").drop("far")
    tasks = max(16, math.ceil(n / shard_rows))
    low = F.lit(float("-inf"))
    first = materialize(_searched(shards, asked.withColumn("least", low), tasks, k, factor), "found")
    if not centres:
        return first.select("query_id", "rank", "vec_id", "score")
    kth = first.where(F.col("rank") == k).select("qrow", F.col("score").alias("least"))
    bound = asked.join(kth, "qrow", "left").withColumn("least", F.coalesce("least", low)).select("qrow", "vec_id", "v", "dim", "cell", "least")
    kind = dict(asked.dtypes)["v"]
    more = materialize(bound.mapInArrow(_route(centres, top2, rings, factor), f"qrow long, vec_id long, v {kind}, dim int, cell int, least double"), "routes")
    second = _searched(shards, more, tasks, k, factor)
    best = Window.partitionBy("qrow").orderBy(F.col("score").desc(), "vec_id")
    out = first.unionByName(second).withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
    return out.select("query_id", "rank", "vec_id", "score")

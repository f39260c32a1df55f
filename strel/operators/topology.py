"""Extrema, merge trees and persistence of functions on the graph of regions and steps.

Points of one region at neighbouring steps are linked, and adjacent regions at one step. Of two
points, for peaks, the one of higher value is higher, and of equal values the one of smaller
(t, region); for valleys the same holds with values negated. So no two points are equal.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from strel.runtime import materialize, ship

HEAD = ["function_id", "space_res", "time_res"]
PAIR = "function_id string, space_res string, time_res string, side string, creator_region string, creator_t int, destroyer_region string, destroyer_t int, birth double, death double, persistence double, essential boolean"
TREE = "function_id string, space_res string, time_res string, side string, upper_region string, upper_t int, lower_region string, lower_t int"
#: Pairs of adjacent regions (a, b), for all functions or by spatial resolution; none: time alone.
Adjacency = DataFrame | dict[str, DataFrame] | None
LEAF = "function_id string, space_res string, time_res string, region string, t int, value double, leaf_region string, leaf_t int"


def neighbours(fn: DataFrame, adjacency: Adjacency = None) -> DataFrame:
    """Every point with each of its neighbours: HEAD, region, t, value, region2, t2, value2."""
    base = fn.select(*HEAD, "region", "t", "value")
    by = Window.partitionBy(*HEAD, "region").orderBy("t")
    near = lambda f, d: F.when(f("t").over(by) == F.col("t") + d, F.struct(F.col("region").alias("region2"), f("t").over(by).alias("t2"), f("value").over(by).alias("value2")))
    in_time = base.select("*", F.array(near(F.lag, -1), near(F.lead, 1)).alias("xs"))
    in_time = in_time.select(*base.columns, F.explode("xs").alias("x")).where("x IS NOT NULL").select(*base.columns, "x.*")
    near = links_of(base, adjacency)
    if near is None:
        return in_time
    other = base.select(*HEAD, F.col("region").alias("region2"), F.col("t").alias("t2"), F.col("value").alias("value2"))
    links = base.join(near.withColumnsRenamed({"a": "region", "b": "region2"}), [*HEAD, "region"])
    in_space = links.withColumn("t2", F.col("t")).join(other, [*HEAD, "region2", "t2"]).select(*in_time.columns)
    return in_time.unionByName(in_space)


def _order(value: str, t: str, region: str, sign: int) -> Column:
    """A sort key: larger is higher."""
    return F.struct((F.col(value) * sign).alias("v"), (-F.col(t)).alias("t"), (-F.col(region).cast("int")).alias("r"))


def extrema(fn: DataFrame, adjacency: Adjacency = None) -> DataFrame:
    """Points without a higher neighbour (``max``) or without a lower one (``min``)."""
    near = neighbours(fn, adjacency).groupBy(*HEAD, "region", "t").agg(
        F.max(_order("value2", "t2", "region2", 1)).alias("top"), F.max(_order("value2", "t2", "region2", -1)).alias("low")
    )
    all_ = fn.select(*HEAD, "region", "t", "value").join(near, [*HEAD, "region", "t"], "left")
    is_max = F.col("top").isNull() | (_order("value", "t", "region", 1) > F.col("top"))
    is_min = F.col("low").isNull() | (_order("value", "t", "region", -1) > F.col("low"))
    kind = F.explode(F.filter(F.array(F.when(is_max, "max"), F.when(is_min, "min")), lambda x: x.isNotNull())).alias("kind")
    return all_.select(*HEAD, "region", "t", "value", kind)


class Sweep:
    """Join tree of one function, from its basins.

    Every point climbs to its highest neighbour, and so on up to a peak: that is its basin. Two
    basins meet at the highest point that touches both; a union-find over those meetings alone, from
    high to low, gives the tree. All but that last loop works on whole arrays.

    ``links``: pairs of adjacent regions, by name. Attributes: ``pairs`` (creator, destroyer,
    essential), ``edges`` of the tree (upper, lower), ``leaf`` (of each point the peak whose
    component it joins), ``part`` (of each point the highest one of its connected part), all as
    positions in the given arrays.
    """

    def __init__(self, value: np.ndarray, t: np.ndarray, region: np.ndarray, links: tuple[np.ndarray, np.ndarray] | None = None):
        n = len(value)
        regions, code = np.unique(region, return_inverse=True)
        ints = np.array([int(r) if r.lstrip("-").isdigit() else k for k, r in enumerate(regions.tolist())])
        order = np.lexsort((ints[code], t, -value))
        rank = np.empty(n, np.int64)
        rank[order] = np.arange(n)
        u, v = self._touching(n, regions, code, t, links)
        swap = rank[u] > rank[v]
        high, low = np.where(swap, v, u), np.where(swap, u, v)
        top = rank.copy()  # a point itself, unless a neighbour is higher
        np.minimum.at(top, low, rank[high])
        best = order[top]
        while True:  # pointer jumping: basins double their height in each step
            up = best[best]
            if np.array_equal(up, best):
                break
            best = up
        self._merge(n, order, rank, best, high, low)

    @staticmethod
    def _touching(n: int, regions: np.ndarray, code: np.ndarray, t: np.ndarray, links) -> tuple[np.ndarray, np.ndarray]:
        """Pairs of neighbouring points: in time, and in space at one step."""
        by = np.lexsort((t, code))
        a, b = by[:-1], by[1:]
        near = (code[a] == code[b]) & (t[b] - t[a] == 1)
        us, vs = [a[near]], [b[near]]
        if links is not None and len(links[0]):
            where = [np.searchsorted(regions, x) for x in links]
            ok = [(w < len(regions)) & (regions[np.minimum(w, len(regions) - 1)] == x) for w, x in zip(where, links, strict=True)]
            x, y = (w[ok[0] & ok[1]] for w in where)
            x, y = np.unique(np.column_stack([np.minimum(x, y), np.maximum(x, y)]), axis=0).T if len(x) else (x, y)
            begin = np.searchsorted(code[by], np.arange(len(regions) + 1))
            for i, j in zip(x.tolist(), y.tolist(), strict=True):
                p, q = by[begin[i] : begin[i + 1]], by[begin[j] : begin[j + 1]]
                _, k, m = np.intersect1d(t[p], t[q], assume_unique=True, return_indices=True)
                us.append(p[k])
                vs.append(q[m])
        return np.concatenate(us), np.concatenate(vs)

    def _merge(self, n: int, order: np.ndarray, rank: np.ndarray, basin: np.ndarray, high: np.ndarray, low: np.ndarray) -> None:
        cross = basin[high] != basin[low]
        at, x, y = rank[low[cross]], basin[high[cross]], basin[low[cross]]
        lo, hi = np.minimum(x, y), np.maximum(x, y)
        by = np.lexsort((at, hi, lo))
        at, lo, hi = at[by], lo[by], hi[by]
        first = np.concatenate([[True], (lo[1:] != lo[:-1]) | (hi[1:] != hi[:-1])]) if len(at) else np.zeros(0, bool)
        at, lo, hi = at[first], lo[first], hi[first]  # where two basins first meet
        by = np.argsort(at, kind="stable")
        peaks = np.unique(basin)
        parent, tail = {p: p for p in peaks.tolist()}, {p: p for p in peaks.tolist()}
        age = rank  # of a component: the rank of its highest point, which names it

        def find(k: int) -> int:
            while parent[k] != k:
                parent[k] = parent[parent[k]]
                k = parent[k]
            return k

        self.pairs: list[tuple[int, int, bool]] = []
        self.edges: list[tuple[int, int]] = []
        death, heir = np.full(n, n, np.int64), np.arange(n)
        meets = list(zip(at[by].tolist(), lo[by].tolist(), hi[by].tolist(), strict=True))
        i = 0
        while i < len(meets):
            j = i
            k = int(order[meets[i][0]])
            while j < len(meets) and meets[j][0] == meets[i][0]:
                j += 1
            # all basins that meet at this point touch it, so they become one component
            roots = sorted({find(b) for m in meets[i:j] for b in m[1:]}, key=lambda r: age[r])
            if len(roots) > 1:
                for r in roots:
                    self.edges.append((tail[r], k))
                for r in roots[1:]:
                    self.pairs.append((r, k, False))
                    parent[r] = roots[0]
                    death[r], heir[r] = meets[i][0], roots[0]
                tail[roots[0]] = k
            i = j
        root = np.array([find(p) for p in peaks.tolist()], dtype=np.int64)
        of = np.zeros(n, np.int64)
        of[peaks] = root
        self.part = of[basin]
        last = np.zeros(n, np.int64)
        np.maximum.at(last, self.part, rank)
        for r in np.unique(root).tolist():
            k = int(order[last[r]])
            self.pairs.append((r, k, True))
            if tail[r] != k:
                self.edges.append((tail[r], k))
        leaf = basin.copy()
        while True:
            older = death[leaf] <= rank
            if not older.any():
                break
            leaf[older] = heir[leaf[older]]
        self.leaf = leaf


def links_of(fn: DataFrame, adjacency: Adjacency) -> DataFrame | None:
    """Pairs of adjacent regions for every function: HEAD, a, b.

    ``adjacency`` has a and b, or is one such table for each spatial resolution. A function gets a
    copy of its resolution's links, which are fewer than its points; nothing goes to the driver.
    """
    if adjacency is None or adjacency == {}:
        return None
    heads = fn.select(*HEAD).distinct()
    if isinstance(adjacency, DataFrame):
        return heads.crossJoin(adjacency.select("a", "b"))
    every = None
    for res, pairs in adjacency.items():
        one = pairs.select(F.lit(res).alias("space_res"), "a", "b")
        every = one if every is None else every.unionByName(one)
    return heads.join(every, "space_res").select(*HEAD, "a", "b")


def _per_function(fn: DataFrame, adjacency: Adjacency, schema: str, make, sides: tuple = (("join", 1), ("split", -1))) -> DataFrame:
    """Applies ``make`` to the sweeps of every function; a task holds one function and its links."""
    ship(fn.sparkSession)

    def run(pdf: pd.DataFrame, near: pd.DataFrame | None = None) -> pd.DataFrame:
        if not len(pdf):
            return pd.DataFrame()
        links = (near["a"].to_numpy().astype(str), near["b"].to_numpy().astype(str)) if near is not None else None
        value, t, region = pdf["value"].to_numpy(), pdf["t"].to_numpy(), pdf["region"].to_numpy().astype(str)
        out = pd.concat([make(pdf, Sweep(value * sign, t, region, links), side) for side, sign in sides], ignore_index=True)
        for k, c in enumerate(HEAD):
            out.insert(k, c, pdf[c].iloc[0])
        return out

    rows = fn.select(*HEAD, "region", "t", "value").where("value IS NOT NULL")
    links = links_of(rows, adjacency)
    if links is None:
        return rows.groupBy(*HEAD).applyInPandas(lambda pdf: run(pdf), schema)
    links = links.select(*[F.col(c).alias(f"of_{c}") for c in HEAD], "a", "b")
    return rows.groupBy(*HEAD).cogroup(links.groupBy(*[f"of_{c}" for c in HEAD])).applyInPandas(lambda pdf, near: run(pdf, near), schema)


def persistence(fn: DataFrame, adjacency: Adjacency = None) -> DataFrame:
    """Creator, destroyer and persistence of every peak (``join``) and valley (``split``).

    One task sweeps one function (``persistence_large`` spreads one over tasks). A component that is
    never destroyed is paired with the last point of its connected part.
    """

    def make(pdf: pd.DataFrame, s: Sweep, side: str) -> pd.DataFrame:
        a, b, e = (np.array(x) for x in zip(*s.pairs, strict=True))
        v, t, r = pdf["value"].to_numpy(), pdf["t"].to_numpy(), pdf["region"].to_numpy()
        return pd.DataFrame({"side": side, "creator_region": r[a], "creator_t": t[a], "destroyer_region": r[b], "destroyer_t": t[b], "birth": v[a], "death": v[b], "persistence": np.abs(v[a] - v[b]), "essential": e.astype(bool)})

    return _per_function(fn, adjacency, PAIR, make)


def merge_tree(fn: DataFrame, adjacency: Adjacency = None) -> DataFrame:
    """Edges of the join and the split tree, from each extremum or saddle to the saddle that ends it."""

    def make(pdf: pd.DataFrame, s: Sweep, side: str) -> pd.DataFrame:
        a, b = (np.array(x, dtype=int) for x in (zip(*s.edges, strict=True) if s.edges else ([], [])))
        t, r = pdf["t"].to_numpy(), pdf["region"].to_numpy()
        return pd.DataFrame({"side": side, "upper_region": r[a], "upper_t": t[a], "lower_region": r[b], "lower_t": t[b]})

    return _per_function(fn, adjacency, TREE, make)


def segmentation(fn: DataFrame, adjacency: Adjacency = None) -> DataFrame:
    """Every point with the peak whose component it joins in the sweep."""

    def make(pdf: pd.DataFrame, s: Sweep, side: str) -> pd.DataFrame:
        t, r = pdf["t"].to_numpy(), pdf["region"].to_numpy()
        return pd.DataFrame({"region": r, "t": t, "value": pdf["value"].to_numpy(), "leaf_region": r[s.leaf], "leaf_t": t[s.leaf]})

    return _per_function(fn, adjacency, LEAF, make, (("join", 1),))


def level_components(fn: DataFrame, theta: float, adjacency: Adjacency = None, side: str = "join") -> DataFrame:
    """Points of a level set with the extremum that names their component. Columns as ``segmentation``."""

    def make(pdf: pd.DataFrame, s: Sweep, _side: str) -> pd.DataFrame:
        t, r = pdf["t"].to_numpy(), pdf["region"].to_numpy()
        return pd.DataFrame({"region": r, "t": t, "value": pdf["value"].to_numpy(), "leaf_region": r[s.part], "leaf_t": t[s.part]})

    return _per_function(level_set(fn, theta, side), adjacency, LEAF, make, ((side, 1 if side == "join" else -1),))


def persistence_1d(fn: DataFrame) -> DataFrame:
    """The same pairs for functions of time alone, in joins and aggregates only.

    A peak dies at the higher of the two lowest points that part it from the nearest higher points
    on its left and right. Each range is cut at gaps of the time axis.
    """
    by = Window.partitionBy(*HEAD).orderBy("t")
    base = fn.select(*HEAD, "region", "t", "value")
    base = base.withColumn("part", F.sum(F.when(F.lag("t").over(by) == F.col("t") - 1, 0).otherwise(1)).over(by))
    out = None
    for side, sign in (("join", 1), ("split", -1)):
        p = base.withColumn("x", _order("value", "t", "region", sign))
        inner = Window.partitionBy(*HEAD, "part").orderBy("t")
        peak = p.where("true").withColumn("l", F.lag("x").over(inner)).withColumn("r", F.lead("x").over(inner))
        peak = peak.where((F.col("l").isNull() | (F.col("x") > F.col("l"))) & (F.col("r").isNull() | (F.col("x") > F.col("r"))))
        q = p.select(*HEAD, "part", F.col("t").alias("t2"), F.col("x").alias("x2"), F.col("value").alias("v2"))
        m = peak.select(*HEAD, "part", "region", "t", "value", "x")
        walls = m.join(q, [*HEAD, "part"]).groupBy(*HEAD, "part", "region", "t", "value", "x").agg(
            F.max(F.when((F.col("x2") > F.col("x")) & (F.col("t2") < F.col("t")), F.col("t2"))).alias("left"),
            F.min(F.when((F.col("x2") > F.col("x")) & (F.col("t2") > F.col("t")), F.col("t2"))).alias("right"),
        )
        floor = lambda a, b: F.min(F.when((F.col("t2") >= a) & (F.col("t2") <= b), F.col("x2")))
        deaths = walls.join(q, [*HEAD, "part"]).groupBy(*HEAD, "part", "region", "t", "value", "left", "right").agg(
            floor(F.col("left"), F.col("t")).alias("fl"), floor(F.col("t"), F.col("right")).alias("fr"), F.min("x2").alias("bottom")
        )
        end = F.coalesce(F.greatest("fl", "fr"), F.col("bottom"))
        one = deaths.select(
            *HEAD, F.lit(side).alias("side"), F.col("region").alias("creator_region"), F.col("t").alias("creator_t"), F.col("region").alias("destroyer_region"),
            (-end["t"]).alias("destroyer_t"), F.col("value").alias("birth"), (end["v"] * sign).alias("death"), F.abs(F.col("value") - end["v"] * sign).alias("persistence"),
            (F.col("left").isNull() & F.col("right").isNull()).alias("essential"),
        )
        out = one if out is None else out.unionByName(one)
    return out


def component_count(pairs: DataFrame, thetas: DataFrame) -> DataFrame:
    """Number of components of the points at or above each theta, from births and deaths alone."""
    joined = pairs.where("side = 'join'").crossJoin(F.broadcast(thetas))
    return joined.groupBy(*HEAD, "theta").agg(F.sum(F.when((F.col("birth") >= F.col("theta")) & (F.col("essential") | (F.col("death") < F.col("theta"))), 1).otherwise(0)).alias("n_components"))


def level_set(fn: DataFrame, theta: float, side: str = "join") -> DataFrame:
    """Points at or above theta (``join``) or at or below it (``split``)."""
    return fn.where(F.col("value") >= theta if side == "join" else F.col("value") <= theta)


def leaves_past(pairs: DataFrame, theta: float | Column, side: str = "join") -> DataFrame:
    """Stored extrema at or past theta: where a feature query starts. HEAD, region, t."""
    past = F.col("birth") >= theta if side == "join" else F.col("birth") <= theta
    return pairs.where((F.col("side") == side) & past).select(*HEAD, F.col("creator_region").alias("region"), F.col("creator_t").alias("t"))


def flood(fn: DataFrame, theta: float, adjacency: Adjacency = None, leaves: DataFrame | None = None, side: str = "join") -> DataFrame:
    """The level set by walking from the extrema that pass theta, with the points touched.

    ``leaves`` are those extrema (from the index; without it they are found first). Work follows the
    size of the output: only points of the set and their rim are looked at. One row a function that
    has leaves; ``points`` are region:t.
    """
    ship(fn.sparkSession)
    sign = 1 if side == "join" else -1
    if leaves is None:
        kind = "max" if side == "join" else "min"
        leaves = extrema(fn, adjacency).where((F.col("kind") == kind) & (F.col("value") * sign >= theta * sign)).select(*HEAD, "region", "t")
    links = links_of(fn, adjacency)
    kinds = F.lit(0).alias("what")
    rows = fn.select(*HEAD, kinds, "region", F.col("t").cast("int").alias("t"), "value", F.lit(None).cast("string").alias("b"))
    rows = rows.unionByName(leaves.select(*HEAD, F.lit(1).alias("what"), "region", F.col("t").cast("int").alias("t"), F.lit(0.0).alias("value"), F.lit(None).cast("string").alias("b")))
    if links is not None:
        rows = rows.unionByName(links.select(*HEAD, F.lit(2).alias("what"), F.col("a").alias("region"), F.lit(0).alias("t"), F.lit(0.0).alias("value"), "b"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        begin = [(r, int(t)) for r, t in pdf.loc[pdf["what"] == 1, ["region", "t"]].itertuples(index=False)]
        if not begin:
            return pd.DataFrame()
        own = pdf[pdf["what"] == 0]
        value = dict(zip(zip(own["region"], own["t"].tolist(), strict=True), own["value"].tolist(), strict=True))
        near: dict[str, list[str]] = {}
        for a, b in pdf.loc[pdf["what"] == 2, ["region", "b"]].itertuples(index=False):
            near.setdefault(a, []).append(b)
        seen, stack, touched = set(begin), list(begin), 0
        while stack:
            r, t = stack.pop()
            for q in ((r, t - 1), (r, t + 1), *((x, t) for x in near.get(r, ()))):
                touched += 1
                if q not in seen and q in value and value[q] * sign >= theta * sign:
                    seen.add(q)
                    stack.append(q)
        row = {c: pdf[c].iloc[0] for c in HEAD} | {"n_points": len(seen), "touched": touched, "points": [f"{r}:{t}" for r, t in sorted(seen)]}
        return pd.DataFrame([row])

    return rows.groupBy(*HEAD).applyInPandas(run, "function_id string, space_res string, time_res string, n_points long, touched long, points array<string>")


def islands(points: DataFrame) -> DataFrame:
    """Components of points of functions of time alone: runs of neighbouring steps."""
    by = Window.partitionBy("function_id").orderBy("t")
    new = F.when(F.lag("t").over(by) == F.col("t") - 1, 0).otherwise(1)
    return points.withColumn("component", F.sum(new).over(by))


def simplify(pairs: DataFrame, eps: float) -> DataFrame:
    """Pairs that noise below eps / 2 cannot remove."""
    return pairs.where((F.col("persistence") >= eps) | F.col("essential"))


def classify(fn: DataFrame, adjacency: Adjacency = None) -> DataFrame:
    """Regular points, extrema and saddles, by the components of upper and lower links.

    Neighbours of a point that are adjacent to each other form one component of its link. A point
    has at most two neighbours in time and its region's neighbours in space; those of one side are
    counted as nodes less links between them where no two regions near one region are adjacent, and
    by search otherwise.
    """
    ship(fn.sparkSession)
    higher = _order("value2", "t2", "region2", 1) > _order("value", "t", "region", 1)
    near = neighbours(fn, adjacency).groupBy(*HEAD, "region", "t", "value").agg(F.collect_list(F.struct("region2", "t2", higher.alias("up"))).alias("near"))
    links = links_of(fn, adjacency)
    if links is None:
        triangles = None
    else:  # pairs of a region's neighbours that are adjacent to each other
        x, y = links.withColumnsRenamed({"a": "region", "b": "p"}), links.withColumnsRenamed({"a": "region", "b": "q"})
        both = x.join(y, [*HEAD, "region"]).where("p < q").join(links.withColumnsRenamed({"a": "p", "b": "q"}), [*HEAD, "p", "q"])
        triangles = both.groupBy(*HEAD, "region").agg(F.collect_set(F.struct("p", "q")).alias("tri"))
    near = near.withColumn("tri", F.lit(None).cast("array<struct<p:string,q:string>>")) if triangles is None else near.join(triangles, [*HEAD, "region"], "left")

    def count(points: list, touching: set) -> int:
        n = 0
        left = list(points)
        while left:
            n += 1
            stack = [left.pop()]
            while stack:
                r, t = stack.pop()
                found = [q for q in left if (q[1] == t and (min(q[0], r), max(q[0], r)) in touching) or (q[0] == r and abs(q[1] - t) == 1)]
                left = [q for q in left if q not in found]
                stack += found
        return n

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            kinds = []
            for points, tri in zip(pdf["near"], pdf["tri"], strict=True):
                touching = {(x["p"], x["q"]) for x in tri} if tri is not None else set()
                u, d = (count([(x["region2"], x["t2"]) for x in points if x["up"] == want], touching) for want in (True, False))
                kinds.append("max" if u == 0 and d else "min" if d == 0 else "regular" if u == d == 1 else "saddle" if max(u, d) == 2 else "degenerate")
            yield pdf.assign(kind=kinds)[[*HEAD, "region", "t", "value", "kind"]]

    return near.mapInPandas(run, "function_id string, space_res string, time_res string, region string, t int, value double, kind string")


def persistence_large(fn: DataFrame, adjacency: Adjacency = None, edges_per_task: int = 200_000) -> DataFrame:
    """The pairs of ``persistence`` for functions too large for a task, one sign after the other.

    Points climb to their basins by joins and pointer jumping; where two basins first meet comes
    from one aggregate. Of those meetings only the highest that connect something matter: tasks drop
    the others from their share until few are left, and the last loop runs over basins alone.
    """
    ship(fn.sparkSession)
    out = None
    for side, sign in (("join", 1), ("split", -1)):
        key = _order("value", "t", "region", sign)
        other = _order("value2", "t2", "region2", sign)
        near = materialize(neighbours(fn, adjacency).select(*HEAD, "region", "t", key.alias("own"), "region2", "t2", other.alias("far")), "neighbours")
        name = lambda k: F.concat_ws(":", (-k["r"]).cast("string"), (-k["t"]).cast("string"))
        points = fn.where("value IS NOT NULL").select(*HEAD, key.alias("k"))
        top = near.groupBy(*HEAD, F.col("own").alias("k")).agg(F.max("far").alias("far"))
        up = points.join(top, [*HEAD, "k"], "left").select(*HEAD, "k", F.when(F.col("far") > F.col("k"), F.col("far")).otherwise(F.col("k")).alias("up"))
        up, before = materialize(up, "climb"), None
        while True:
            higher = up.select(*HEAD, F.col("k").alias("up"), F.col("up").alias("upper"))
            up = materialize(up.join(higher, [*HEAD, "up"]).select(*HEAD, "k", F.col("upper").alias("up")), "climb", up)
            total = up.agg(F.sum(F.expr("xxhash64(up) div 4096"))).first()[0]
            if total == before:
                break
            before = total
        own, far = up.select(*HEAD, F.col("k").alias("own"), F.col("up").alias("x")), up.select(*HEAD, F.col("k").alias("far"), F.col("up").alias("y"))
        met = near.where("own < far").join(own, [*HEAD, "own"]).join(far, [*HEAD, "far"]).where("x <> y")
        met = met.groupBy(*HEAD, F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y")).agg(F.max("own").alias("at"))
        met, n = materialize(met, "meetings"), None
        schema = met.schema
        while True:
            now = met.count()
            parts = -(-now // edges_per_task)
            if parts <= 1 or now == n:
                break
            n = now
            share = met.withColumn("share", F.expr(f"pmod(xxhash64(x, y, {now}L), {parts})"))
            met = materialize(share.groupBy(*HEAD, "share").applyInPandas(_forest, schema), "meetings", met)
        ends = materialize(up.groupBy(*HEAD, "up").agg(F.min("k").alias("low")), "basins", up)  # the lowest point of every basin

        one = ends.groupBy(*HEAD).cogroup(met.groupBy(*HEAD)).applyInPandas(_last_loop(side, sign), PAIR)
        out = one if out is None else out.unionByName(one)
    return out


def _last_loop(side: str, sign: int):
    """Pairs of basins from the highest meeting down."""

    def run(basins: pd.DataFrame, met: pd.DataFrame) -> pd.DataFrame:
        if not len(basins):
            return pd.DataFrame()
        as_key = lambda x: (x["v"], x["t"], x["r"])
        parent = {as_key(x): as_key(x) for x in basins["up"]}

        def find(k):
            while parent[k] != k:
                parent[k] = parent[parent[k]]
                k = parent[k]
            return k

        rows = []
        for at, x, y in sorted(((as_key(a), as_key(x), as_key(y)) for a, x, y in zip(met["at"], met["x"], met["y"], strict=True)), reverse=True):
            a, b = sorted((find(x), find(y)))
            if a != b:
                rows.append((a, at, False))
                parent[a] = b
        low = {}
        for x, k in zip(basins["up"], basins["low"], strict=True):
            r = find(as_key(x))
            low[r] = min(low.get(r, as_key(k)), as_key(k))
        rows += [(r, k, True) for r, k in low.items()]
        cols = {"side": side, "creator_region": [str(-a[2]) for a, _, _ in rows], "creator_t": [-a[1] for a, _, _ in rows], "destroyer_region": [str(-b[2]) for _, b, _ in rows], "destroyer_t": [-b[1] for _, b, _ in rows]}
        cols |= {"birth": [a[0] * sign for a, _, _ in rows], "death": [b[0] * sign for _, b, _ in rows], "persistence": [abs(a[0] - b[0]) for a, b, _ in rows], "essential": [e for _, _, e in rows]}
        df = pd.DataFrame(cols)
        for k, c in enumerate(HEAD):
            df.insert(k, c, basins[c].iloc[0])
        return df

    return run


def _forest(pdf: pd.DataFrame) -> pd.DataFrame:
    """The meetings of a share that connect something that higher ones of it do not."""
    key = lambda x: (x["v"], x["t"], x["r"])
    parent: dict = {}

    def find(k):
        parent.setdefault(k, k)
        while parent[k] != k:
            parent[k] = parent[parent[k]]
            k = parent[k]
        return k

    keep = []
    for _, x, y, i in sorted(((key(a), key(x), key(y), i) for i, (a, x, y) in enumerate(zip(pdf["at"], pdf["x"], pdf["y"], strict=True))), reverse=True):
        a, b = find(x), find(y)
        if a != b:
            parent[a] = b
            keep.append(i)
    return pdf.iloc[keep].drop(columns="share")

"""Regions: adjacency, maps between resolutions, and points in cells and polygons."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def lattice(spark: SparkSession, rows: int, cols: int) -> DataFrame:
    """Adjacency (a, b), both directions, of a rows x cols lattice numbered row by row."""
    at = spark.range(rows * cols).select(F.col("id").cast("int").alias("a"))
    r, c = F.expr(f"a div {cols}"), F.expr(f"a % {cols}")
    steps = F.array(
        F.when(r > 0, F.col("a") - cols), F.when(r < rows - 1, F.col("a") + cols), F.when(c > 0, F.col("a") - 1), F.when(c < cols - 1, F.col("a") + 1)
    )
    return at.select("a", F.explode(steps).alias("b")).where("b IS NOT NULL").select(F.col("a").cast("string").alias("a"), F.col("b").cast("int").cast("string").alias("b"))


def lattice_of(regions: DataFrame, cols: int) -> DataFrame:
    """Adjacency (a, b), both directions, of the numbers from 0 in ``regions`` (a column region), laid out row by row.

    Numbers that do not occur have no neighbours; repeated ones have theirs repeatedly.
    """
    r = F.col("region")
    steps = F.array(r - cols, r + cols, F.when(r % cols > 0, r - 1), F.when(r % cols < cols - 1, r + 1))
    near = regions.select(r.alias("a"), F.explode(steps).alias("b")).where("b >= 0").join(regions.select(r.alias("b")), "b")
    return near.select(F.col("a").cast("string").alias("a"), F.col("b").cast("string").alias("b"))


def cube_cells(spark: SparkSession, g: int, cells: DataFrame | None = None) -> DataFrame:
    """Adjacency of g x g x g cells, six neighbours each; ``cells`` (a column a): of these alone."""
    at = spark.range(g**3).select(F.col("id").cast("int").alias("a")) if cells is None else cells.select(F.col("a").cast("int").alias("a")).distinct()
    x, y, z = F.expr(f"a div {g * g}"), F.expr(f"(a div {g}) % {g}"), F.expr(f"a % {g}")
    steps = []
    for axis, width in ((x, g * g), (y, g), (z, 1)):
        steps += [F.when(axis > 0, F.col("a") - width), F.when(axis < g - 1, F.col("a") + width)]
    near = at.select("a", F.explode(F.array(*steps)).alias("b")).where("b IS NOT NULL").select(F.col("a"), F.col("b").cast("int").alias("b"))
    return near if cells is None else near.join(at.withColumnRenamed("a", "b"), "b", "left_semi").select("a", "b")


def quotient(adjacency: DataFrame, space_map: DataFrame) -> DataFrame:
    """Adjacency of coarser regions: two touch if members of them touch."""
    m = space_map
    left = adjacency.join(m.withColumnsRenamed({"region": "a", "to_region": "x"}), "a")
    both = left.join(m.withColumnsRenamed({"region": "b", "to_region": "y"}), "b")
    return both.where("x <> y").select(F.col("x").alias("a"), F.col("y").alias("b")).distinct()


def from_polygons(corners: DataFrame) -> DataFrame:
    """Adjacency of polygons (region, i, x, y: corners in order) that share a boundary segment."""
    from pyspark.sql import Window

    by = Window.partitionBy("region").orderBy("i")
    whole = Window.partitionBy("region").orderBy("i").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    nxt = lambda c: F.coalesce(F.lead(c).over(by), F.first(c).over(whole))
    seg = corners.select("region", F.struct("x", "y").alias("p"), F.struct(nxt("x").alias("x"), nxt("y").alias("y")).alias("q"))
    seg = seg.select("region", F.least("p", "q").alias("p"), F.greatest("p", "q").alias("q"))
    pairs = seg.withColumnRenamed("region", "a").join(seg.withColumnRenamed("region", "b"), ["p", "q"]).where("a <> b")
    return pairs.select("a", "b").distinct()


def cell_of(x: Column, y: Column, lo: float, hi: float, g: int) -> Column:
    """Cell of a g x g grid over a square; points outside fall into the nearest cell."""
    at = lambda v: F.least(F.greatest(F.floor((v - lo) / (hi - lo) * g), F.lit(0)), F.lit(g - 1)).cast("int")
    return at(y) * g + at(x)


def cell3d_of(v: Column, lo: float, hi: float, g: int) -> Column:
    """Cell of a g x g x g grid over a cube, by the first three components of a vector; points
    outside fall into the nearest cell. Null without three finite components."""
    at = lambda c: F.least(F.greatest(F.floor((c - lo) / (hi - lo) * g), F.lit(0)), F.lit(g - 1)).cast("int")
    x, y, z = (F.get(v, F.lit(i)).cast("double") for i in range(3))
    ok = F.greatest(*[F.coalesce(F.abs(c), F.lit(float("inf"))) for c in (x, y, z)]) < float("inf")
    return F.when(ok, (at(x) * g + at(y)) * g + at(z))


def in_polygon(points: DataFrame, polygons: DataFrame, cell: float) -> DataFrame:
    """Points (id, x, y) with the polygon (region, i, x, y) that holds them.

    Cells of side ``cell`` are an equality key of both sides, so only polygons whose box touches a
    point's cell are tried; a ray to the right then counts crossings of the boundary.
    """
    from pyspark.sql import Window

    by = Window.partitionBy("region").orderBy("i")
    whole = by.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    edges = polygons.select("region", F.col("x").alias("x1"), F.col("y").alias("y1"), F.coalesce(F.lead("x").over(by), F.first("x").over(whole)).alias("x2"), F.coalesce(F.lead("y").over(by), F.first("y").over(whole)).alias("y2"))
    index = lambda v: F.floor(F.col(v) / cell).cast("int")
    box = polygons.groupBy("region").agg(F.min("x").alias("a"), F.max("x").alias("b"), F.min("y").alias("c"), F.max("y").alias("d"))
    box = box.select("region", F.explode(F.sequence(index("a"), index("b"))).alias("cx"), "c", "d").select("region", "cx", F.explode(F.sequence(index("c"), index("d"))).alias("cy"))
    tried = points.withColumn("cx", index("x")).withColumn("cy", index("y")).join(box, ["cx", "cy"]).join(edges, "region")
    cross = ((F.col("y1") > F.col("y")) != (F.col("y2") > F.col("y"))) & (F.col("x") < (F.col("x2") - F.col("x1")) * (F.col("y") - F.col("y1")) / (F.col("y2") - F.col("y1")) + F.col("x1"))
    hits = tried.groupBy("id", "region").agg(F.sum(F.when((F.col("y1") != F.col("y2")) & cross, 1).otherwise(0)).alias("n"))
    return hits.where("n % 2 = 1").select("id", "region")

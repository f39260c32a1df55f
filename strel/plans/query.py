"""The index of a corpus, and relationship queries over it.

``index_corpus`` turns data sets into stored functions and feature bits; queries read only those.
A clause on score and strength is applied before the permutation test, which is the costly part;
with a least strength, words of pairs whose feature sets are too unlike in size never meet.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterable
from dataclasses import asdict, dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from strel.operators import features as feat
from strel.operators import permute, relate, scalar, topology
from strel.runtime import materialize, shared_dir
from strel.sources.catalog import DatasetSpec


@dataclass(frozen=True)
class Clause:
    """What a relationship must satisfy; ``thresholds`` replace those of listed functions."""

    min_abs_score: float = 0.0
    min_score: float | None = None
    max_score: float | None = None
    min_strength: float = 0.0
    alpha: float = 0.05
    feature_types: tuple[str, ...] = ("salient", "extreme")
    thresholds: dict[str, tuple[float | None, float | None]] = field(default_factory=dict)
    #: Resolutions to evaluate; none: every one that the functions of a pair have in common.
    space_res: tuple[str, ...] = ()
    time_res: tuple[str, ...] = ()
    statistic: str = "score"
    tail: str = "directional"
    estimator: str = "plain"

    def keeps(self):
        c = (F.abs("score") >= self.min_abs_score) & (F.col("strength") >= self.min_strength)
        if self.min_score is not None:
            c = c & (F.col("score") >= self.min_score)
        if self.max_score is not None:
            c = c & (F.col("score") <= self.max_score)
        return c


@dataclass
class Index:
    """Stored functions, their spans, thresholds, feature points and feature bits."""

    functions: DataFrame
    meta: DataFrame
    pairs: DataFrame
    salient: DataFrame
    extreme: DataFrame
    points: DataFrame
    bits: DataFrame
    adjacency: dict[str, DataFrame]


def index_functions(fn: DataFrame, adjacency: DataFrame | dict[str, DataFrame] | None = None, seasonal: bool = True, space_res: str = "world") -> Index:
    """Topology, thresholds and features of functions of any resolutions; each step is stored once.

    ``adjacency`` links regions: one table for ``space_res``, or one for each spatial resolution.
    """
    near = adjacency if isinstance(adjacency, dict) or adjacency is None else {space_res: adjacency}
    fn = materialize(fn, "functions")
    pairs = materialize(topology.persistence(fn, near), "persistence")
    salient = materialize(feat.salient_thresholds(pairs, seasonal), "thresholds")
    extreme = materialize(feat.extreme_thresholds(pairs, salient, seasonal), "thresholds")
    points = materialize(feat.features(fn, salient, extreme, seasonal), "features")
    bits = materialize(feat.to_bits(points), "bits")
    return Index(fn, materialize(relate.spans(fn), "spans"), pairs, salient, extreme, points, bits, near or {})


def index_corpus(specs: Iterable[DatasetSpec], adjacency: dict[str, DataFrame] | None = None, spaces: Iterable[str] = ("world",), times: Iterable[str] = scalar.EVALUATED_TIME, missing: str = "carry") -> Index:
    """The index of every function at every viable resolution; each raw table is scanned once.

    Without the links of a resolution its regions would be islands: give ``adjacency`` for all
    ``spaces`` but ``world``.
    """
    near = adjacency or {}
    lacking = [s for s in spaces if s != "world" and s not in near]
    if lacking:
        raise ValueError(f"no adjacency for {lacking}")
    return index_functions(scalar.all_functions(specs, spaces, times, missing), {s: a for s, a in near.items() if s in tuple(spaces)}, True)


_STORED = {"functions": ("space_res", "time_res"), "meta": (), "pairs": ("side",), "salient": (), "extreme": (), "points": ("space_res", "time_res", "feature_type"), "bits": ("space_res", "time_res", "feature_type")}


def store_index(index: Index, path: str) -> None:
    """Writes an index so that a query's resolution and feature type prune files.

    Functions are sorted by value inside a function, and extrema by height, so a question about
    points past a threshold reads only the row groups that hold some.
    """
    for name, by in _STORED.items():
        df = getattr(index, name)
        if name in ("functions", "pairs"):
            df = df.repartition("function_id").sortWithinPartitions(*by, "function_id", "value" if name == "functions" else "birth")
        df.write.mode("overwrite").partitionBy(*by).parquet(f"{path}/{name}")
    for res, pairs in index.adjacency.items():
        pairs.write.mode("overwrite").parquet(f"{path}/adjacency/{res}")


def load_index(spark: SparkSession, path: str, spaces: Iterable[str] = ()) -> Index:
    """An index that ``store_index`` wrote, with the adjacency of the named resolutions."""
    read = {name: spark.read.parquet(f"{path}/{name}") for name in _STORED}
    return Index(**read, adjacency={s: spark.read.parquet(f"{path}/adjacency/{s}") for s in spaces})


def features_through_index(index: Index, thresholds: dict[str, tuple[float | None, float | None]]) -> DataFrame:
    """Features of listed functions under given (lower, upper) thresholds, from the merge-tree index.

    Stored extrema past a threshold are where the search starts; from there it walks over the level
    set alone. Columns as ``features.from_user``.
    """
    none = F.lit(None).cast("boolean")
    out = None
    for fn, (lo, hi) in thresholds.items():
        own = index.functions.where(F.col("function_id") == fn)
        for theta, side, pos in ((hi, "join", True), (lo, "split", False)):
            if theta is None:
                continue
            leaves = topology.leaves_past(index.pairs.where(F.col("function_id") == fn), theta, side)
            near = {s: a for s, a in index.adjacency.items()}
            found = topology.flood(own, theta, near or None, leaves, side)
            at = found.select(*topology.HEAD, F.explode("points").alias("p"))
            at = at.select(*topology.HEAD, F.substring_index("p", ":", 1).alias("region"), F.substring_index("p", ":", -1).cast("int").alias("t"), (F.lit(True) if pos else none).alias("pos"), (none if pos else F.lit(True)).alias("neg"))
            out = at if out is None else out.unionByName(at)
    if out is None:
        raise ValueError("no threshold is given")
    both = out.groupBy(*topology.HEAD, "region", "t").agg(F.coalesce(F.max("pos"), F.lit(False)).alias("pos"), F.coalesce(F.max("neg"), F.lit(False)).alias("neg"))
    return both.withColumn("feature_type", F.lit("user")).select(*topology.HEAD, "feature_type", "region", "t", "pos", "neg")


@dataclass
class RelationshipQuery:
    """All relationships between two groups of data sets (no right group: the whole corpus)."""

    index: Index
    left: tuple[str, ...] = ()
    right: tuple[str, ...] = ()
    clause: Clause = Clause()
    n_maps: int = 1000

    def plan_pairs(self) -> DataFrame:
        """Candidate pairs, each once, at common resolutions."""
        pairs = relate.candidate_pairs(self.index.meta)
        for res in ("space_res", "time_res"):
            if getattr(self.clause, res):
                pairs = pairs.where(F.col(res).isin(*getattr(self.clause, res)))
        inside = lambda c, names: F.col(c).isin(*names) if names else F.lit(True)
        a = inside("left_dataset", self.left) & inside("right_dataset", self.right)
        b = inside("left_dataset", self.right) & inside("right_dataset", self.left)
        return pairs.where(a | b)

    def points(self) -> DataFrame:
        """Stored features, or those under the clause's thresholds for the functions it lists."""
        stored = self.index.points
        if self.clause.thresholds:
            own = features_through_index(self.index, self.clause.thresholds)
            kinds = F.explode(F.array(*[F.lit(k) for k in self.clause.feature_types]))
            own = own.withColumn("feature_type", kinds).select(*stored.columns)
            stored = stored.where(~F.col("function_id").isin(*self.clause.thresholds)).unionByName(own)
        return stored.where(F.col("feature_type").isin(*self.clause.feature_types))

    def bits(self) -> DataFrame:
        """The features as words."""
        return feat.to_bits(self.points()) if self.clause.thresholds else self.index.bits.where(F.col("feature_type").isin(*self.clause.feature_types))

    def evaluate(self) -> DataFrame:
        """Every candidate at every common resolution with its measures, before clause and test.

        With a least strength, candidates that cannot reach it by their sizes are left out.
        """
        pairs, bits = self.plan_pairs(), self.bits()
        if self.clause.min_strength > 0:
            pairs = relate.within_strength(pairs, bits, self.clause.min_strength)
        return relate.measures(relate.pair_counts(pairs, bits))

    def run(self, significant_only: bool = True) -> DataFrame:
        """Relationships with p-values: rotations in time for one region, maps of regions for more.

        Each resolution is tested with maps of its own links. Pairs over several regions whose
        resolution has no adjacency cannot be tested: asking for them is an error.
        """
        c = self.clause
        kept = materialize(self.evaluate().where("n_common > 0").where(c.keeps()), "candidates")
        key = ["left_fn", "right_fn", "space_res", "time_res", "feature_type"]
        tests = relate.rotation_test_words(kept.where("n_regions = 1"), self.bits(), c.statistic, c.tail, c.estimator).withColumn("test", F.lit("rotation"))
        wide = kept.where("n_regions > 1")
        lacking = [r[0] for r in wide.where(~F.col("space_res").isin(*self.index.adjacency) if self.index.adjacency else F.lit(True)).select("space_res").distinct().limit(9).collect()]
        if lacking:
            raise ValueError(f"no adjacency to test pairs at {lacking}")
        if self.index.adjacency and wide.limit(1).count():
            links = None
            for res, a in self.index.adjacency.items():
                one = a.select(F.lit(res).alias("space_res"), "a", "b")
                links = one if links is None else links.unionByName(one)
            maps = materialize(permute.graph_maps(links, self.n_maps), "maps")
            tests = tests.unionByName(relate.spatial_test(wide, self.points(), maps, c.statistic, c.tail, c.estimator).withColumn("test", F.lit("region maps")))
        out = kept.join(tests, key, "left").withColumn("significant", F.coalesce(F.col("p_value") <= c.alpha, F.lit(False)))
        return out.where("significant") if significant_only else out

    def key(self, version: str) -> str:
        """Identity of the question, for the cache."""
        text = json.dumps([sorted(self.left), sorted(self.right), {k: v for k, v in sorted(asdict(self.clause).items())}, self.n_maps, version], sort_keys=True, default=list)
        return hashlib.sha256(text.encode()).hexdigest()


class ResultCache:
    """Answers of earlier queries, as tables in the shared folder."""

    def __init__(self, spark: SparkSession, version: str):
        self.spark, self.version = spark, version

    def _path(self, query: RelationshipQuery) -> str:
        return f"{shared_dir(self.spark)}/strel/answers/{query.key(self.version)}"

    def get(self, query: RelationshipQuery) -> DataFrame | None:
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self._path(query) + "/_SUCCESS")
        there = path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(path)
        return self.spark.read.parquet(self._path(query)) if there else None

    def answer(self, query: RelationshipQuery) -> DataFrame:
        """The stored answer, or the answer after storing it."""
        found = self.get(query)
        if found is None:
            query.run().write.mode("overwrite").parquet(self._path(query))
            found = self.spark.read.parquet(self._path(query))
        return found


def rank_relationships(found: DataFrame, k: int = 10) -> DataFrame:
    """The k strongest relationships of every left data set."""
    from pyspark.sql import Window

    by = Window.partitionBy("left_dataset").orderBy(F.abs("score").desc(), F.col("strength").desc(), "left_fn", "right_fn", "feature_type")
    return found.withColumn("rank", F.row_number().over(by)).where(F.col("rank") <= k)


def dataset_degree(found: DataFrame) -> DataFrame:
    """How many other data sets each one is related to."""
    both = found.select(F.col("left_dataset").alias("dataset"), F.col("right_dataset").alias("other")).unionByName(found.select(F.col("right_dataset").alias("dataset"), F.col("left_dataset").alias("other")))
    return both.groupBy("dataset").agg(F.count_distinct("other").alias("degree"))


def explain(index: Index, left_fn: str, right_fn: str, feature_type: str = "salient") -> DataFrame:
    """Where and when a relation holds."""
    p = index.points.where(F.col("feature_type") == feature_type)
    return relate.related_points(p.where(F.col("function_id") == left_fn), p.where(F.col("function_id") == right_fn))

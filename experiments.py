"""Cost experiments: time against edges, tables and cores, the rate of relationships, and space.

``python experiments.py [sf_dir] [cores]`` prints one JSON line an experiment. With ``--speedup`` the
index and the query of the split corpus run once for 1, 2, 4 and 8 cores, each in a process of its own.
"""

from __future__ import annotations

import json
import subprocess
import sys
import time


def session(cores: str):
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", max(8, int(cores))).config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "10g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    spark.range(1000).selectExpr("sum(id)").collect()
    return spark


def timed(f):
    began = time.time()
    out = f()
    return round(time.time() - began, 2), out


def say(**figures) -> None:
    print(json.dumps(figures), flush=True)


def edges(spark, side: int, steps: int) -> None:
    """Index and feature query of one function on a lattice of side x side regions."""
    from pyspark.sql import functions as F

    from strel.operators import features, space, topology
    from strel.runtime import materialize

    n = side * side
    fn = spark.range(n * steps).select(
        F.lit("grid.density").alias("function_id"), F.lit("cell").alias("space_res"), F.lit("hour").alias("time_res"), (F.col("id") % n).cast("string").alias("region"),
        F.expr(f"id div {n}").cast("int").alias("t"), (F.pmod(F.xxhash64("id"), F.lit(40)) + 20 * F.sin(F.expr(f"id div {n}") / 24.0)).cast("double").alias("value"),
    )
    fn = materialize(fn, "functions")
    near = space.lattice(spark, side, side)
    count = n * (steps - 1) + 2 * side * (side - 1) * steps
    index_s, pairs = timed(lambda: materialize(topology.persistence(fn, near), "persistence"))

    def query():
        salient = features.salient_thresholds(pairs, False)
        return features.features(fn, salient, features.extreme_thresholds(pairs, salient, False), False).count()

    query_s, points = timed(query)
    say(experiment="edges", edges=count, index_s=index_s, query_s=query_s, features=points, edges_a_second=round(count / index_s))


def collection(spark, sf: str) -> None:
    """A collection that grows table by table: functions, index, relationships."""
    from strel.operators import scalar
    from strel.plans.query import RelationshipQuery, index_functions
    from strel.runtime import materialize
    from strel.sources import catalog

    specs = catalog.whole_and_parts(spark, sf)
    for k in range(1, len(specs) + 1):
        scan_s, fn = timed(lambda k=k: materialize(scalar.all_functions(specs[:k], ("world",), ("day", "week", "month")), "functions"))
        index_s, ix = timed(lambda fn=fn: index_functions(fn))
        count_s, n = timed(lambda ix=ix: RelationshipQuery(ix).evaluate().count())
        query_s, kept = timed(lambda ix=ix: RelationshipQuery(ix).run(False).count())
        say(experiment="collection", tables=k, datasets=fn.selectExpr("substring_index(function_id, '.', 1) AS d").distinct().count(), functions=ix.meta.count(), function_s=scan_s, feature_s=index_s, relations=n, query_s=query_s, relations_a_minute=round(60 * n / query_s), share_of_tests=round(max(0.0, 1 - count_s / query_s), 2))


def many(spark, sf: str) -> None:
    """Hundreds of small tables: rate of relationships, with and without a clause, and space."""
    from strel.operators import scalar
    from strel.plans.query import Clause, RelationshipQuery, index_functions
    from strel.runtime import materialize, table
    from strel.sources import catalog

    scan_s, fn = timed(lambda: materialize(scalar.all_functions(catalog.many(spark, sf), ("world",), ("week",)), "functions"))
    index_s, ix = timed(lambda: index_functions(fn))
    count_s, n = timed(lambda: RelationshipQuery(ix).evaluate().count())
    query_s, _ = timed(lambda: RelationshipQuery(ix).run(False).count())
    clause_s, _ = timed(lambda: RelationshipQuery(ix, clause=Clause(min_abs_score=0.6, min_strength=0.3)).run(False).count())
    say(experiment="many", functions=ix.meta.count(), function_s=scan_s, feature_s=index_s, relations=n, query_s=query_s, clause_s=clause_s, relations_a_minute=round(60 * n / query_s), with_clause=round(60 * n / clause_s), share_of_tests=round(max(0.0, 1 - count_s / query_s), 2))
    raw = sum(scalar.stored_bytes(table(spark, sf, t)) for t in ("orders", "lineitem", "events", "customer", "supplier"))
    say(experiment="space", raw=raw, functions=scalar.stored_bytes(ix.functions), extrema=scalar.stored_bytes(ix.pairs), features=scalar.stored_bytes(ix.bits))


def split_corpus(spark, sf: str) -> dict:
    from strel.operators import scalar
    from strel.plans.query import RelationshipQuery, index_functions
    from strel.runtime import materialize
    from strel.sources import catalog

    scan_s, fn = timed(lambda: materialize(scalar.all_functions(catalog.splits(spark, sf), ("world",), ("day", "week")), "functions"))
    index_s, ix = timed(lambda: index_functions(fn))
    query_s, _ = timed(lambda: RelationshipQuery(ix).run(False).count())
    return {"function_s": scan_s, "feature_s": index_s, "query_s": query_s}


def main(args: list[str]) -> None:
    if args[:1] == ["--one"]:
        say(experiment="speed-up", cores=int(args[2]), **split_corpus(session(args[2]), args[1]))
        return
    plain = [a for a in args if not a.startswith("--")]
    sf, cores = (plain + ["/root/testdata/sf0.1", "8"][len(plain) :])[:2]
    if "--speedup" in args:
        for k in ("1", "2", "4", "8"):
            subprocess.run([sys.executable, __file__, "--one", sf, k], check=True)
        return
    spark = session(cores)
    for side, steps in ((1, 720), (5, 720), (20, 720), (40, 720), (40, 2880)):
        edges(spark, side, steps)
    collection(spark, sf)
    many(spark, sf)


if __name__ == "__main__":
    main(sys.argv[1:])

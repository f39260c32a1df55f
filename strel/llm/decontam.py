"""Size-partitioned MinHash containment search for benchmark items inside documents.

Items are partitioned by the number of their distinct shingles. An item's sketch is its bottom-k
MinHash: the k shingles of smallest rank. Containment of an item is estimated by the share of its
sketch that a document holds, whatever the document's length. In a partition of items of at most
M shingles k is floor((1-t) M) + 1, so that a document with a share of at least t of an item's
shingles holds at least one of its sketch: candidates lose nothing. Candidates with too few hits
for t are dropped; the rest is verified by exact containment of the shingles themselves.

Shingles are of five words; an item of fewer words is one shingle of its length, looked for among
the runs of that length. Items without words are never found; null texts hold nothing. Rows with
one doc_id (null included) are one document, items with one item_id one item. Empty tables give no
row. Columns but ids and texts are not read.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from strel.llm.words import window_hashes, window_texts, words
from strel.runtime import materialize

WIDTH = 5
#: Rows of sketches (16 bytes each) that may be sent to every executor; more are shuffled.
BROADCAST_ROWS = 1_000_000


def _sized(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def contained(docs: DataFrame, items: DataFrame, num: int = 75, den: int = 100, width: int = WIDTH) -> DataFrame:
    """Pairs of a document and an item of which it holds at least num/den of the shingles.

    ``docs`` has doc_id and text, ``items`` item_id and text. Columns: doc_id, item_id, n_shingles
    (of the item), n_found, containment.
    """
    own = items.select(F.col("item_id").cast("long").alias("item_id"), words(F.col("text")).alias("w"))
    own = own.withColumn("width", F.least(F.size("w"), F.lit(width))).where("width > 0")
    widths = sorted(r[0] for r in own.select("width").distinct().limit(width).collect())
    if not widths:
        return docs.sparkSession.createDataFrame([], "doc_id long, item_id long, n_shingles long, n_found long, containment double")
    each = lambda f, col: F.flatten(F.array(*[F.when(F.col("width") == k, f(F.col(col), k)).otherwise(f(F.array().cast("array<string>" if f is window_texts else "array<long>"), k)) for k in widths]))
    own = own.withColumn("h", F.transform("w", lambda x: F.xxhash64(x)))
    exact = materialize(own.select("item_id", F.explode(each(window_texts, "w")).alias("s")).distinct(), "item-shingles")
    sizes = exact.groupBy("item_id").agg(F.count(F.lit(1)).alias("n_shingles"))
    sized = sizes.withColumn("most", F.expr("shiftleft(2L, cast(floor(log2(n_shingles)) as int)) - 1"))
    sized = sized.withColumn("k", F.expr(f"least(n_shingles, most * {den - num} div {den} + 1)"))
    # ranks are taken among the hashes of an item, which is never longer than a document
    hashed = own.select("item_id", F.explode(F.array_distinct(each(window_hashes, "h"))).alias("x")).distinct()
    low = hashed.groupBy("item_id").agg(F.array_sort(F.collect_list(F.struct(F.xxhash64("x", F.lit("rank")).alias("r"), "x"))).alias("all"))
    sketch = low.join(sized, "item_id").select("item_id", F.explode(F.slice("all", 1, F.col("k").cast("int"))).alias("z")).select("item_id", F.col("z.x").alias("x"))
    sketch = materialize(sketch, "item-sketches")
    count = sketch.count()

    h = F.transform(words(F.col("text")), lambda x: F.xxhash64(x))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), h.alias("h"))
    runs = [window_hashes(F.col("h"), k) for k in widths]
    found = texts.select("doc_id", F.explode(F.concat(*runs) if len(runs) > 1 else runs[0]).alias("x")).join(_sized(sketch, count), "x")
    hits = found.distinct().groupBy("doc_id", "item_id").agg(F.count(F.lit(1)).alias("hits"))
    likely = hits.join(_sized(sized, count), "item_id").where(F.expr(f"hits >= k - n_shingles * {den - num} div {den}"))
    likely = materialize(likely.select("doc_id", "item_id", "n_shingles"), "candidates")

    some = materialize(likely.select("doc_id").distinct(), "candidate-docs")
    n = some.count()
    whole = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(_sized(some, n), "doc_id", "left_semi")
    whole = whole.select("doc_id", words(F.col("text")).alias("w"))  # a column of its own: the runs read it once a word
    runs = [window_texts(F.col("w"), k) for k in widths]
    held = whole.select("doc_id", F.explode(F.concat(*runs) if len(runs) > 1 else runs[0]).alias("s"))
    held = held.join(_sized(exact, exact.count()), "s").distinct()
    held = held.groupBy("doc_id", "item_id").agg(F.count(F.lit(1)).alias("n_found"))
    out = likely.join(held, ["doc_id", "item_id"]).where(F.expr(f"{den} * n_found >= {num} * n_shingles"))
    return out.select("doc_id", "item_id", "n_shingles", "n_found", (F.col("n_found") / F.col("n_shingles")).alias("containment"))


def clean(docs: DataFrame, items: DataFrame) -> DataFrame:
    """``docs`` without the rows that hold an item, each judged by its own text, whatever its id."""
    row = F.xxhash64(F.col("doc_id"), F.col("text"))
    bad = materialize(contained(docs.select(row.alias("doc_id"), "text"), items).select(F.col("doc_id").alias("__row")).distinct(), "contaminated")
    return docs.withColumn("__key", row).join(_sized(bad, bad.count()), F.col("__key") == bad["__row"], "left_anti").drop("__key")


ORACLE = r"""
WITH iw AS (SELECT item_id, list_filter(regexp_split_to_array(lower(text), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM benchmark),
i AS (SELECT item_id, w, least(len(w), 5) AS k FROM iw WHERE len(w) > 0),
ish AS (SELECT DISTINCT item_id, k, unnest([array_to_string(w[j:j + k - 1], ' ') FOR j IN range(1, len(w) - k + 2)]) AS s FROM i),
n AS (SELECT item_id, count(*) AS n_shingles FROM ish GROUP BY item_id),
dw AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM documents),
dsh AS (SELECT DISTINCT doc_id, k, unnest([array_to_string(w[j:j + k - 1], ' ') FOR j IN range(1, len(w) - k + 2)]) AS s FROM dw, (SELECT DISTINCT k FROM i))
SELECT doc_id, item_id, any_value(n_shingles) AS n_shingles, count(*) AS n_found, count(*) / any_value(n_shingles) AS containment
FROM dsh JOIN ish USING (k, s) JOIN n USING (item_id) GROUP BY doc_id, item_id HAVING 100 * count(*) >= 75 * any_value(n_shingles)
"""

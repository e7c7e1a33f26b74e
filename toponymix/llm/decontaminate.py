"""Benchmark decontamination: size-partitioned MinHash containment search with exact verification, native plans only.

Containment of an item Q in a document X is |Q & X| / |Q| over word shingles. Shingles of X outside the union of all
items never change it, so each document is first cut down to that union by a semi-join inside the scan; long documents
then have sets about as small as the items they hold and MinHash works well. Documents are partitioned by the size of the cut set;
for each pair of size classes the band width is the widest whose miss probability stays below `MISS`; class pairs
where no width reaches that go through the exact inverted index instead. All candidates are verified exactly.

Edge cases: null and empty texts have no shingles and match nothing; an item with fewer than `width` words is one
shingle of all its words; rows that share a doc_id count as one document (null ids take no part); repeated items
each report; empty tables give an empty result; extra columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialise, passing, without_rows

HASHES = 64
MISS = 1e-9
#: Rows of item shingles up to which the item side is broadcast (16 bytes a row); beyond it joins shuffle.
BROADCAST_ROWS = 500_000


def words(text: Column) -> Column:
    return F.array_remove(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[\x20\x09-\x0D]+"), "")


def _shingles(hashed: Column, width: int) -> Column:
    last = F.size(hashed) - F.lit(width)
    at = lambda i: F.xxhash64(F.lit(width), *[F.get(hashed, i + j) for j in range(width)])
    return F.when(last >= 0, F.transform(F.sequence(F.lit(0), F.greatest(last, F.lit(0))), at)).otherwise(F.array().cast("array<bigint>"))


def item_shingles(items: DataFrame, width: int = 5, text: str = "text") -> DataFrame:
    """Distinct (item_id, w, h): w is the shingle width of the item, below `width` only for shorter items."""
    h = items.where(F.col("item_id").isNotNull()).select("item_id", F.transform(words(F.col(text)), lambda x: F.xxhash64(x)).alias("ws"))
    h = h.withColumn("w", F.least(F.lit(width), F.size("ws"))).where("w > 0")
    per = F.array().cast("array<bigint>")
    for k in range(1, width + 1):
        per = F.when(F.col("w") == k, _shingles(F.col("ws"), k)).otherwise(per)
    return h.select("item_id", "w", F.explode(per).alias("h")).distinct()


def _maybe_broadcast(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def size_class(n: Column) -> Column:
    return F.floor(F.log2(n.cast("double"))).cast("int")


def band_width(item_class: int, doc_class: int, threshold: float) -> int:
    """Widest band r whose miss probability is at most MISS for the class pair; 0 where there is none."""
    q, u = 2**item_class, 2 ** (doc_class + 1) - 1
    jaccard = min(1.0, threshold * q / (q + max(u, threshold * q) - threshold * q))
    fit = [r for r in (1, 2, 4) if (HASHES // r) * math.log1p(-min(jaccard**r, 1 - 1e-12)) <= math.log(MISS)]
    return max(fit, default=0)


def _band_keys(item_class: int, doc_class: int, r: int) -> Column:
    """One key for each band of r sketch values, told apart by class pair and band."""
    key = lambda b: F.xxhash64(F.lit(item_class), F.lit(doc_class), b, F.slice("m", b * r + 1, F.lit(r)))
    return F.transform(F.sequence(F.lit(0), F.lit(HASHES // r - 1)), key)


def contained_items(spark: SparkSession, docs: DataFrame, items: DataFrame, threshold: float = 0.8, width: int = 5, text: str = "text") -> DataFrame:
    """(doc_id, item_id, n_item, n_shared, containment) of every pair with containment >= threshold."""
    its = materialise(item_shingles(items, width, text), spark)
    stat = its.groupBy("w").agg(F.count(F.lit(1)).alias("n")).collect()
    n_rows, widths = sum(r.n for r in stat), sorted(r.w for r in stat)
    sizes = its.groupBy("item_id", "w").agg(F.count(F.lit(1)).alias("q"))
    smallest = sizes.agg(F.min("q")).first()[0] or 1
    universe = _maybe_broadcast(its.select("h").distinct(), n_rows)

    hashed = docs.where(F.col("doc_id").isNotNull()).select("doc_id", F.transform(words(F.col(text)), lambda x: F.xxhash64(x)).alias("ws"))
    every = F.concat(*[_shingles(F.col("ws"), k) for k in widths]) if widths else F.array().cast("array<bigint>")
    hits = hashed.select("doc_id", F.explode(every).alias("h")).join(universe, "h", "left_semi").distinct()
    need = threshold * smallest
    seeds = F.sequence(F.lit(0), F.lit(HASHES - 1))
    sketch = F.transform(seeds, lambda i: F.array_min(F.transform("hs", lambda h: F.xxhash64(h, i)))).alias("m")
    hits = materialise(hits, spark)
    signed = hits.groupBy("doc_id").agg(F.collect_list("h").alias("hs")).where(F.size("hs") >= need)
    signed = materialise(signed.select("doc_id", size_class(F.size("hs")).alias("uc"), sketch), spark)
    queries = its.groupBy("item_id", "w").agg(F.collect_list("h").alias("hs")).select("item_id", size_class(F.size("hs")).alias("qc"), sketch)

    doc_classes = [r.uc for r in signed.select("uc").distinct().collect()]
    item_classes = [r.qc for r in sizes.select(size_class(F.col("q")).alias("qc")).distinct().collect()]
    plan = [(a, j, band_width(a, j, threshold)) for a in item_classes for j in doc_classes if 2 ** (j + 1) - 1 >= threshold * 2**a]

    def bands(side: DataFrame, key_column: str, own: str, kind: int) -> DataFrame:
        of: dict[int, list[Column]] = {}
        for a, j, r in plan:
            if r:
                of.setdefault((a, j)[kind], []).append(_band_keys(a, j, r))
        out = F.array().cast("array<bigint>")
        for c, keys in of.items():
            out = F.when(F.col(own) == c, F.concat(*keys)).otherwise(out)
        return side.select(key_column, F.explode(out).alias("band"))

    by_band = bands(signed, "doc_id", "uc", 1).join(_maybe_broadcast(bands(queries, "item_id", "qc", 0), n_rows * HASHES // 8), "band").select("doc_id", "item_id").distinct()
    by_index = None
    exact = [(a, j) for a, j, r in plan if not r]
    small_items = _maybe_broadcast(its, n_rows)
    if exact:
        pair = F.lit(False)
        for a, j in exact:
            pair = pair | ((F.col("qc") == a) & (F.col("uc") == j))
        rare = hits.join(signed.select("doc_id", "uc"), "doc_id").join(small_items, "h").join(_maybe_broadcast(sizes.select("item_id", size_class(F.col("q")).alias("qc")), n_rows), "item_id")
        by_index = rare.where(pair).select("doc_id", "item_id").distinct()
    candidates = by_band if by_index is None else by_band.unionByName(by_index)
    shared = candidates.join(small_items, "item_id").select("doc_id", "item_id", "h").join(hits, ["doc_id", "h"]).groupBy("doc_id", "item_id").agg(F.count(F.lit(1)).alias("n_shared"))
    out = shared.join(_maybe_broadcast(sizes, n_rows), "item_id").withColumn("containment", F.col("n_shared") / F.col("q"))
    return out.where(F.col("containment") >= threshold).select("doc_id", "item_id", F.col("q").alias("n_item"), "n_shared", "containment")


def remove_contaminated(spark: SparkSession, docs: DataFrame, items: DataFrame, threshold: float = 0.8) -> DataFrame:
    """The rows that hold no item. Each row is judged by itself: its key is its place in the table, so null ids take part."""
    row = F.monotonically_increasing_id()
    with passing(spark) as stays:
        gone = stays(contained_items(spark, docs.select(row.alias("doc_id"), "text"), items, threshold).select(F.col("doc_id").alias("_row")).distinct())
    return without_rows(docs, gone)


ORACLE = r"""
WITH w AS (
  SELECT 0 AS kind, doc_id AS id, list_filter(string_split_regex(lower(coalesce(text, '')), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents
  UNION ALL
  SELECT 1, item_id, list_filter(string_split_regex(lower(coalesce(text, '')), '[\x20\x09-\x0D]+'), lambda x: x <> '') FROM benchmark),
i AS (SELECT DISTINCT id AS item_id, unnest(list_transform(range(1, greatest(len(ws) - 4, 1) + 1), lambda k: array_to_string(ws[k:k + 4], ' '))) AS s FROM w WHERE kind = 1 AND len(ws) > 0),
d AS (SELECT DISTINCT id AS doc_id, unnest(list_transform(range(1, greatest(len(ws) - 3, 1)), lambda k: array_to_string(ws[k:k + 4], ' '))) AS s FROM w WHERE kind = 0),
q AS (SELECT item_id, count(*) AS q FROM i GROUP BY 1),
p AS (SELECT doc_id, item_id, count(*) AS n_shared FROM d JOIN i USING (s) GROUP BY 1, 2)
SELECT doc_id, item_id, q AS n_item, n_shared, n_shared / q AS containment FROM p JOIN q USING (item_id) WHERE n_shared / q >= 0.8
"""

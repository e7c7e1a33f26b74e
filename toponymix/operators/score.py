"""Pairs of names, their scores, and the acceptance rule."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.geo import great_circle_m

INF = float("inf")


def within_district(standard: DataFrame, candidates: DataFrame) -> DataFrame:
    """All (standard, candidate) pairs of a district; names of other districts are never aliases."""
    s = standard.select("city", "district", F.col("name").alias("std_name"))
    return s.join(candidates.select("city", "district", F.col("name").alias("cand_name")), ["city", "district"])


def candidates(addr: DataFrame, standard: DataFrame) -> DataFrame:
    """Names written in addresses that are no standard name of their district."""
    written = addr.select("city", "district", F.col("place_name").alias("name")).distinct()
    return written.join(standard, ["city", "district", "name"], "left_anti")


def minhash_candidates(dens: DataFrame, pairs: DataFrame, tables: int = 5, most: float = 0.9) -> DataFrame:
    """Pairs of a district whose cell sets are likely closer than Jaccard distance `most`: an approximate stand-in for all pairs.

    A cell is a place of a bounded number line, so the sets become sparse vectors; hashing keeps those that share a bucket.
    Its recall must be measured against all pairs before it replaces them.
    """
    from pyspark.ml.feature import MinHashLSH
    from pyspark.ml.linalg import SparseVector, VectorUDT

    cells = dens.groupBy("city", "district", "place_name").agg(F.array_sort(F.collect_set((F.col("r") * 1024 + F.col("c")).cast("int"))).alias("cells"))

    @F.udf(VectorUDT())
    def sparse(x):
        return SparseVector(1 << 20, x, [1.0] * len(x))

    v = cells.select("city", "district", "place_name", sparse("cells").alias("v"))
    model = MinHashLSH(inputCol="v", outputCol="h", numHashTables=tables, seed=7).fit(v)
    near = model.approxSimilarityJoin(v, v, most, "dist").select(F.col("datasetA.district").alias("district"), F.col("datasetA.place_name").alias("std_name"), F.col("datasetB.district").alias("other"), F.col("datasetB.place_name").alias("cand_name"))
    near = near.where("district = other").select("district", "std_name", "cand_name")
    return pairs.join(near, ["district", "std_name", "cand_name"], "left_semi")


def reciprocal(x: Column) -> Column:
    """1/x with +infinity at or below zero; null stays null."""
    return F.when(x <= 0, F.lit(INF)).otherwise(F.try_divide(F.lit(1.0), x))


def distance(pairs: DataFrame, anchors: DataFrame) -> DataFrame:
    """pairs with dist_m between both anchors and score = 1/dist_m; null where a footprint is empty."""
    s = anchors.select("city", F.col("place_name").alias("std_name"), F.col("lat").alias("a1"), F.col("lon").alias("o1"))
    c = anchors.select("city", F.col("place_name").alias("cand_name"), F.col("lat").alias("a2"), F.col("lon").alias("o2"))
    j = pairs.join(s, ["city", "std_name"], "left").join(c, ["city", "cand_name"], "left")
    d = great_circle_m(F.col("a1"), F.col("o1"), F.col("a2"), F.col("o2"))
    return j.select("city", "district", "std_name", "cand_name", d.alias("dist_m")).withColumn("score", reciprocal(F.col("dist_m")))


def near(anchors: DataFrame, metres: float, cell_u: int = 20_000) -> DataFrame:
    """Pairs of anchors of a city within `metres`: equal buckets and their neighbours, then the exact distance.

    `cell_u` must be at least as wide as `metres` on both axes.
    """
    keyed = anchors.select("city", "place_name", "lat", "lon", F.floor(F.col("lat") * 1e6 / cell_u).alias("i"), F.floor(F.col("lon") * 1e6 / cell_u).alias("j"))
    around = F.explode(F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b")) for a in (-1, 0, 1) for b in (-1, 0, 1)]))
    left = keyed.select("city", F.col("place_name").alias("std_name"), F.col("lat").alias("a1"), F.col("lon").alias("o1"), "i", "j", around.alias("d"))
    left = left.withColumns({"i": F.col("i") + F.col("d.a"), "j": F.col("j") + F.col("d.b")})
    j = left.join(keyed.withColumnRenamed("place_name", "cand_name"), ["city", "i", "j"]).where("std_name < cand_name")
    return j.withColumn("dist_m", great_circle_m(F.col("a1"), F.col("o1"), F.col("lat"), F.col("lon"))).where(F.col("dist_m") <= metres).select("city", "std_name", "cand_name", "dist_m")


def distribution(compared: DataFrame, method: str = "M4", form: str = "overlap") -> DataFrame:
    """Adds score: M3 is 1/kl; M4 the overlap, 1/(1-overlap), or (ablation) 1/overlap as printed."""
    if method == "M3":
        return compared.withColumn("score", reciprocal(F.col("kl")))
    o = F.col("overlap")
    return compared.withColumn("score", {"overlap": o, "reciprocal": reciprocal(1 - o), "as_printed": reciprocal(o)}[form])


def accept(scored: DataFrame, cut: float | Column) -> DataFrame:
    """Adds is_alias: strictly above the cut; a null score is never accepted."""
    cut = cut if isinstance(cut, Column) else F.lit(cut)
    return scored.withColumn("is_alias", F.coalesce(F.col("score") > cut, F.lit(False)))


def matrix(accepted: DataFrame, dense: bool = False) -> DataFrame:
    """The alias matrix: accepted pairs, or one column per candidate (small inputs)."""
    ones = accepted.where("is_alias")
    return ones.groupBy("std_name").pivot("cand_name").agg(F.lit(1)) if dense else ones.select("city", "district", "std_name", "cand_name")


def best_match(scored: DataFrame, k: int = 1) -> DataFrame:
    """The k best standard names of each candidate; ties by name."""
    w = W.partitionBy("city", "district", "cand_name").orderBy(F.col("score").desc_nulls_last(), "std_name")
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)

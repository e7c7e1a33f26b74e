"""Text baselines. T1 is exact; T2 and T3 are stand-ins for neural models, with a pluggable encoder, and are named so."""

from __future__ import annotations

import zlib
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.tables import settle

GRAMS = 256


def edit(pairs: DataFrame, normalise: str = "none", max_edits: int | None = None) -> DataFrame:
    """T1: edits between both names; score = -edits (or 1 - edits / longer length). Above max_edits: no score."""
    d = F.levenshtein("std_name", "cand_name") if max_edits is None else F.levenshtein("std_name", "cand_name", max_edits)
    out = pairs.withColumn("edits", F.when(d >= 0, d))
    longest = F.greatest(F.length("std_name"), F.length("cand_name"))
    score = -F.col("edits").cast("double") if normalise == "none" else 1 - F.try_divide(F.col("edits").cast("double"), longest)
    return out.withColumn("score", score)


def trigrams(name: Column) -> Column:
    """Distinct character trigrams of the padded name."""
    padded = F.concat(F.lit("  "), F.lower(name), F.lit(" "))
    return F.array_distinct(F.transform(F.sequence(F.lit(1), F.length(padded) - 2), lambda i: F.substr(padded, i, F.lit(3))))


def hashed_trigrams(names: pd.Series, dims: int = GRAMS) -> pd.Series:
    """Unit vectors of hashed trigram counts: the default encoder."""

    def one(name: str) -> list[float]:
        padded = f"  {name.lower()} "
        v = np.bincount([zlib.crc32(padded[i : i + 3].encode()) % dims for i in range(len(padded) - 2)], minlength=dims).astype(float)
        return (v / np.linalg.norm(v)).tolist()

    return names.map(one)


def cosine(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0).cast("double"), lambda t, x: t + x)


def encode(names: DataFrame, encoder: Callable[[pd.Series], pd.Series] | None = None) -> DataFrame:
    """(city, district, name, v): each name once; an encoder maps a series of names to lists of floats."""
    encoder = encoder or hashed_trigrams

    @F.pandas_udf("array<double>")
    def run(x: pd.Series) -> pd.Series:
        return encoder(x)

    return names.withColumn("v", run(F.col("name")))


def embed_match(pairs: DataFrame, names: DataFrame, encoder: Callable[[pd.Series], pd.Series] | None = None) -> DataFrame:
    """T3 stand-in: cosine of both names' vectors."""
    v = settle(encode(names.select("city", "district", "name").distinct(), encoder))  # each name is encoded once, not once a pair
    s = v.select("city", "district", F.col("name").alias("std_name"), F.col("v").alias("a"))
    c = v.select("city", "district", F.col("name").alias("cand_name"), F.col("v").alias("b"))
    j = pairs.join(s, ["city", "district", "std_name"]).join(c, ["city", "district", "cand_name"])
    return j.withColumn("score", cosine(F.col("a"), F.col("b"))).drop("a", "b")


def alignment_counts(pairs: DataFrame) -> DataFrame:
    """Adds what the alignment features are made of: m shared trigrams, a1 and b1 trigrams, a2 and b2 lengths of both names."""
    a, b = trigrams(F.col("std_name")), trigrams(F.col("cand_name"))
    n = {"m": F.size(F.array_intersect(a, b)), "a1": F.size(a), "a2": F.length("std_name"), "b1": F.size(b), "b2": F.length("cand_name")}
    return pairs.withColumns({k: v.cast("bigint") for k, v in n.items()})


def alignment_features() -> list[Column]:
    """Soft alignment of both names' trigrams: matched share of each side, their product and difference, length ratio."""
    both = F.col("m").cast("double")
    one, two = F.try_divide(both, F.col("a1")), F.try_divide(both, F.col("b1"))
    ratio = F.try_divide(F.least("a2", "b2").cast("double"), F.greatest("a2", "b2"))
    return [one, two, one * two, F.abs(one - two), ratio]


def align_fit(train: DataFrame) -> Column:
    """Logistic regression on alignment features; train has m, a1, a2, b1, b2, k and h. The chance of a hit, in the same columns.

    Equal pairs enter as one row of their weight. Features are scaled by their deviation over all pairs, so the penalty is
    that of the same fit on single rows.
    """
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector

    fs = [F.col(f"f{j}") for j in range(5)]
    data = train.groupBy("m", "a1", "a2", "b1", "b2").agg(F.sum("k").alias("k"), F.sum("h").alias("h"))
    data = settle(data.select("k", "h", *[f.alias(f"f{j}") for j, f in enumerate(alignment_features())]))
    n, *means = data.agg(F.sum("k"), *[F.sum(f * F.col("k")) / F.sum("k") for f in fs]).first()
    spread = data.agg(*[F.sum(F.col("k") * (f - mean) * (f - mean)) / max(n - 1, 1) for f, mean in zip(fs, means, strict=True)]).first()
    scale = [v**0.5 if v else 1.0 for v in spread]
    x = array_to_vector(F.array(*[f / s for f, s in zip(fs, scale, strict=True)])).alias("x")
    sides = [data.where(w > 0).select(x, F.lit(y).alias("y"), w.cast("double").alias("w")) for y, w in ((1.0, F.col("h")), (0.0, F.col("k") - F.col("h")))]
    model = LogisticRegression(featuresCol="x", labelCol="y", weightCol="w", maxIter=30, regParam=1e-3, standardization=False).fit(sides[0].unionByName(sides[1]))
    # Nine digits: sums in another order of rows give the same model.
    margin = F.lit(round(float(model.intercept), 9))
    for f, w, s in zip(alignment_features(), model.coefficients, scale, strict=True):
        margin = margin + f * F.lit(round(float(w / s), 9))
    return 1 / (1 + F.exp(-margin))


def align_match(train: DataFrame, test: DataFrame) -> DataFrame:
    """T2 stand-in for pairs: train has `hit`; score is the chance of a hit."""
    score = align_fit(alignment_counts(train).withColumns({"k": F.lit(1).cast("bigint"), "h": F.col("hit").cast("bigint")}))
    return alignment_counts(test).withColumn("score", score).select(*test.columns, "score")


def product_cosine() -> Column:
    """T3's cosine from integer products, so equal names' pairs tie exactly."""
    return F.col("m") / F.sqrt(F.col("a1").cast("double") * F.col("b1"))

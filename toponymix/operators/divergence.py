"""Divergence of rasterised footprints: Kullback-Leibler with policies for empty cells, and overlap of supports.

Both need one inner join of standard and candidate cells on (district, r, c): an inverted index, so only pairs that share
a cell are formed. Everything else about a pair follows from per-name totals in closed form. `by` names extra columns
(for instance n_grid) that keep several rasters apart in one plan.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PAIR = ["city", "district", "std_name", "cand_name"]


def shared_cells(shares: DataFrame, standard: DataFrame, candidates: DataFrame, eps: float, n: int | None, by: list[str], salt: int = 1) -> DataFrame:
    """Per pair with a shared cell: counts of both in shared cells and the sums that KL needs. `salt` splits hot cells."""
    std = shares.join(standard.select("city", "district", F.col("name").alias("place_name")), ["city", "district", "place_name"])
    cand = shares.join(candidates.select("city", "district", F.col("name").alias("place_name")), ["city", "district", "place_name"])
    std = std.select(*by, "city", "district", "r", "c", F.col("place_name").alias("std_name"), F.col("n").alias("sn"), F.col("p").alias("sp"))
    cand = cand.select(*by, "city", "district", "r", "c", F.col("place_name").alias("cand_name"), F.col("n").alias("cn"), F.col("total").alias("ct"), F.col("p").alias("cp"))
    keys = [*by, "city", "district", "r", "c"]
    if salt > 1:
        std = std.withColumn("_salt", F.pmod(F.xxhash64("std_name"), F.lit(salt)))
        cand = cand.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(salt - 1).cast("bigint"))))
        keys = [*keys, "_salt"]
    grid = F.lit(float(n) * n) if n else F.col("n_grid").cast("double") * F.col("n_grid")
    q = (F.col("cn") + eps) / (F.col("ct") + F.lit(eps) * grid)
    lift = lambda n: F.ln((F.col(n) + eps) / eps)
    return std.join(cand, keys).groupBy(*by, *PAIR).agg(
        F.count(F.lit(1)).alias("n_shared_cells"),
        F.sum("sn").alias("shared_std_n"),
        F.sum("cn").alias("shared_cand_n"),
        F.sum(F.col("sp") * F.ln(q)).alias("p_ln_q"),
        F.sum(F.col("sn") * lift("cn")).alias("std_by_cand"),
        F.sum(F.col("cn") * lift("sn")).alias("cand_by_std"),
        F.sum(F.col("sp") * F.ln(F.col("sp") / F.col("cp"))).alias("skip"),
        F.sum(F.col("cp") * F.ln(F.col("cp") / F.col("sp"))).alias("skip_reverse"),
        F.sum("sp").alias("mass"),
    )


def totals(shares: DataFrame, by: list[str], eps: float) -> DataFrame:
    """Per name: pings, sum of p ln p, and what smoothing its own cells adds (`lifted` by n + eps, `rim` by eps alone)."""
    lift = F.ln((F.col("n") + eps) / eps)
    sums = [F.sum("n").alias("total"), F.sum(F.col("p") * F.ln("p")).alias("plogp"), F.sum((F.col("n") + eps) * lift).alias("lifted"), F.sum(eps * lift).alias("rim")]
    return shares.groupBy(*by, "city", "district", "place_name").agg(*sums)


def smoothed_both(eps: float, grid: Column) -> tuple[Column, Column]:
    """KL of standard to candidate and back when eps is added to every cell of both.

    Against the log of eps each cell's log is zero outside its own footprint, so the sum over all cells of the raster needs
    per-name sums and the shared cells only.
    """
    s, c, zero = F.col("total_std") + eps * grid, F.col("total_cand") + eps * grid, F.lit(0.0)
    there = F.ln(c / s) + (F.col("lifted_std") - F.col("rim_cand") - F.coalesce("std_by_cand", zero)) / s
    back = F.ln(s / c) + (F.col("lifted_cand") - F.col("rim_std") - F.coalesce("cand_by_std", zero)) / c
    return there, back


def compare(shares: DataFrame, pairs: DataFrame, standard: DataFrame, candidates: DataFrame, eps: float = 1e-3, n: int | None = 50, by: list[str] | None = None, zero_policy: str = "smooth", salt: int = 1) -> DataFrame:
    """One row per pair: overlap, kl and their parts.

    zero_policy: `smooth` adds eps to every candidate cell and renormalises; `strict` is infinite where the standard
    name has mass that the candidate lacks; `skip` sums over shared cells only; `reverse` is `skip` from candidate to
    standard; `smooth_both` adds eps to every cell of both names; `symmetric` is the mean of its two directions. A pair
    with an empty footprint has nulls.
    """
    by = by or []
    cells = shared_cells(shares, standard, candidates, eps, n, by, salt)
    t = totals(shares, by, eps)
    s = t.select(*by, "city", "district", F.col("place_name").alias("std_name"), F.col("total").alias("total_std"), "plogp", F.col("lifted").alias("lifted_std"), F.col("rim").alias("rim_std"))
    c = t.select(*by, "city", "district", F.col("place_name").alias("cand_name"), F.col("total").alias("total_cand"), F.col("lifted").alias("lifted_cand"), F.col("rim").alias("rim_cand"))
    zero = F.lit(0).cast("bigint")
    joined = pairs.join(s, [*by, "city", "district", "std_name"], "left").join(c, [*by, "city", "district", "cand_name"], "left").join(cells, [*by, *PAIR], "left")
    joined = joined.withColumns({k: F.coalesce(k, zero) for k in ("n_shared_cells", "shared_std_n", "shared_cand_n")})
    whole = F.col("total_std").isNotNull() & F.col("total_cand").isNotNull()
    grid = F.lit(float(n) * n) if n else F.col("n_grid").cast("double") * F.col("n_grid")
    none = F.col("n_shared_cells") == 0
    missing = F.when(F.col("shared_std_n") == F.col("total_std"), 0.0).otherwise(1 - F.coalesce("mass", F.lit(0.0)))
    smooth = F.col("plogp") - F.coalesce("p_ln_q", F.lit(0.0)) - missing * F.ln(F.lit(eps) / (F.col("total_cand") + F.lit(eps) * grid))
    infinite = F.col("shared_std_n") < F.col("total_std")
    there, back = smoothed_both(eps, grid)
    kl = {
        "smooth_both": there,
        "symmetric": (there + back) / 2,
        "smooth": smooth,
        "strict": F.when(infinite, F.lit(float("inf"))).otherwise(F.col("skip")),
        "skip": F.when(none, 0.0).otherwise(F.col("skip")),
        "reverse": F.when(none, 0.0).otherwise(F.col("skip_reverse")),
    }[zero_policy]
    over = (F.col("shared_std_n") / F.col("total_std") + F.col("shared_cand_n") / F.col("total_cand")) / 2
    return joined.select(*by, *PAIR, "n_shared_cells", "shared_std_n", "shared_cand_n", "total_std", "total_cand", F.when(whole, over).alias("overlap"), F.when(whole, kl).alias("kl"), F.when(whole, infinite).alias("is_inf"))


def overlap_by_maps(dens: DataFrame, pairs: DataFrame) -> DataFrame:
    """The overlap from one cell map per name: a second form for small footprints, equal to `compare`."""
    m = dens.groupBy("city", "district", "place_name").agg(F.map_from_entries(F.collect_list(F.struct((F.col("r") * 100000 + F.col("c")).alias("k"), "n"))).alias("m"))
    s = m.select("city", "district", F.col("place_name").alias("std_name"), F.col("m").alias("a"))
    c = m.select("city", "district", F.col("place_name").alias("cand_name"), F.col("m").alias("b"))
    both = F.map_filter(F.map_zip_with("a", "b", lambda k, x, y: F.struct(x.alias("x"), y.alias("y"))), lambda k, v: v["x"].isNotNull() & v["y"].isNotNull())
    add = lambda col, f: F.aggregate(col, F.lit(0).cast("bigint"), lambda t, v: t + f(v))
    j = pairs.join(s, ["city", "district", "std_name"]).join(c, ["city", "district", "cand_name"]).withColumn("v", F.map_values(both))
    return j.select(*PAIR, ((add("v", lambda v: v["x"]) / add(F.map_values("a"), lambda v: v) + add("v", lambda v: v["y"]) / add(F.map_values("b"), lambda v: v)) / 2).alias("overlap"))

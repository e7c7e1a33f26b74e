"""Rasterised footprints: cells, densities, shares, and a pyramid of resolutions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..sources.tables import settle

#: Resolution from which all its divisors roll up exactly.
BASE = 6000


def assign(pings: DataFrame, box: DataFrame, n: int = 50, outside: str = "drop") -> DataFrame:
    """Adds r, c: the cell of each ping on an n x n grid over its city's box; the far edges belong to the last cells.

    `outside` = drop leaves pings off the box out; clamp moves them to the edge. Integer arithmetic throughout.
    """
    out = pings.join(F.broadcast(box), "city")
    if outside == "drop":
        out = out.where("lat_u between lat_min_u and lat_max_u and lon_u between lon_min_u and lon_max_u")
    else:
        out = out.withColumns({"lat_u": F.greatest("lat_min_u", F.least("lat_u", "lat_max_u")), "lon_u": F.greatest("lon_min_u", F.least("lon_u", "lon_max_u"))})
    cell = lambda v: F.expr(f"cast(least({n - 1}, ({v}_u - {v}_min_u) * {n} div ({v}_max_u - {v}_min_u)) as int)")
    return out.withColumns({"r": cell("lat"), "c": cell("lon")}).drop("lat_min_u", "lat_max_u", "lon_min_u", "lon_max_u")


def density(auth: DataFrame, cells: DataFrame) -> DataFrame:
    """(city, district, place_name, r, c, n): counts per user and cell first, then per name: raw pings shuffle once."""
    per_user = cells.groupBy("user_id", "r", "c").agg(F.count(F.lit(1)).alias("n"))
    return auth.join(per_user, "user_id").groupBy("city", "district", "place_name", "r", "c").agg(F.sum("n").alias("n"))


def packed(auth: DataFrame, cells: DataFrame, n: int) -> DataFrame:
    """(city, district, name, cells, total): one row per name with the cell r * n + c of each of its pings, and its pings in the city.

    Pings are shuffled once as bare cells, then as one array per user; names have no row per cell.
    """
    per_user = cells.select("user_id", (F.col("r") * n + F.col("c")).alias("cell")).repartition("user_id").groupBy("user_id").agg(F.collect_list("cell").alias("cells"))
    spread = auth.join(per_user, "user_id").repartition("city", "place_name")
    out = spread.groupBy("city", "district", F.col("place_name").alias("name")).agg(F.flatten(F.collect_list("cells")).alias("cells"))
    return out.withColumn("total", F.sum(F.size("cells")).over(W.partitionBy("city", "name")).cast("bigint"))


def coarsen(dens: DataFrame, base: int, n: int) -> DataFrame:
    """A density of resolution `base` at resolution n, exact where n divides base."""
    if base % n:
        raise ValueError(f"{n} does not divide {base}")
    k = base // n
    coarse = dens.withColumns({"r": F.expr(f"cast(r div {k} as int)"), "c": F.expr(f"cast(c div {k} as int)")})
    return coarse.groupBy("city", "district", "place_name", "r", "c").agg(F.sum("n").alias("n"))


def parents(sizes: list[int], base: int = BASE) -> dict[int, int]:
    """Size -> the smallest larger size that it divides, or the base: what each level is rolled up from."""
    if bad := [n for n in sizes if base % n]:
        raise ValueError(f"{bad} do not divide {base}")
    return {n: min((m for m in sizes if m > n and m % n == 0), default=base) for n in sizes}


def pyramid(dens: DataFrame, sizes: list[int], base: int = BASE) -> DataFrame:
    """All resolutions at once with a column n_grid: the base is read for the finest ones only, the rest roll up from those."""
    of = parents(sizes, base)
    keys = ["n_grid", "city", "district", "place_name", "r", "c"]

    def level(upper: DataFrame, wanted: list[int]) -> DataFrame:
        pairs = F.explode(F.array(*[F.struct(F.lit(of[n]).alias("of"), F.lit(n).alias("n")) for n in wanted])).alias("x")
        out = upper.select("*", pairs).where("n_grid = x.of")
        cell = lambda v: F.expr(f"cast({v} div (n_grid div x.n) as int)")
        return out.select(F.col("x.n").alias("n_grid"), *keys[1:4], cell("r").alias("r"), cell("c").alias("c"), "n").groupBy(*keys).agg(F.sum("n").alias("n"))

    upper, todo, out = dens.withColumn("n_grid", F.lit(base)), list(sizes), None
    above = {base}
    while todo:
        wanted = [n for n in todo if of[n] in above]
        upper = settle(level(upper, wanted))
        out = upper if out is None else out.unionByName(upper)
        todo, above = [n for n in todo if n not in wanted], set(wanted)
    return out


def share(dens: DataFrame, *by: str) -> DataFrame:
    """Adds total and p = n / total per name; totals are summed before the join, so a large footprint stays spread."""
    keys = [*by, "city", "place_name"]
    totals = dens.groupBy(*keys).agg(F.sum("n").alias("total"))
    return dens.join(totals, keys).withColumn("p", F.col("n") / F.col("total"))

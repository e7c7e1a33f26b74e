"""Anchors: overall centroid and centroid of the densest window, in four engines (`bounded` is the one for large footprints).

`densest` is `bounded` from author sets and pings: a name's pings come as one array, and its blocks are bounded and swept in
place; names with more than LARGE pings are spread over tasks by `densest_window`.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.geo import degrees, extent_u
from ..sources.tables import settle
from . import footprint

NAME = ["city", "place_name"]
#: Pings of a name that one array may hold, and cells of a part of the matrix of edges and pings.
LARGE, CHUNK = 1 << 21, 1 << 18
WINDOW = "city int, place_name string, n_window bigint, lat0_u bigint, lon0_u bigint, lat double, lon double"


def centroid(totals: DataFrame) -> DataFrame:
    """(city, district, place_name, n, lat, lon) from footprint totals (n, lat_sum, lon_sum)."""
    return totals.select("city", "district", "place_name", "n", degrees(F.col("lat_sum") / F.col("n")).alias("lat"), degrees(F.col("lon_sum") / F.col("n")).alias("lon"))


def extents(box: DataFrame, side_m: float) -> dict[int, tuple[int, int]]:
    """City -> window extents in micro-degrees; one row per city reaches the driver."""
    rows = box.select("city", ((F.col("lat_min_u") + F.col("lat_max_u")) / 2e6).alias("ref")).collect()
    return {r.city: extent_u(side_m, r.ref) for r in rows}


def _of_city(values: dict[int, int]) -> Column:
    out = F.lit(None).cast("bigint")
    for city, v in values.items():
        out = F.when(F.col("city") == city, F.lit(v).cast("bigint")).otherwise(out)
    return out


def _with_extents(points: DataFrame, box: DataFrame, side_m: float) -> DataFrame:
    """Adds the window extents and the multiplicity k of a ping."""
    e = extents(box, side_m)
    return points.withColumns({"dlat": _of_city({k: v[0] for k, v in e.items()}), "dlon": _of_city({k: v[1] for k, v in e.items()}), "k": F.lit(1).cast("bigint")})


def densest_window(points: DataFrame, box: DataFrame, side_m: float = 640.0, engine: str = "bounded", bins: int = 16) -> DataFrame:
    """(city, place_name, n_window, lat0_u, lon0_u, lat, lon): the closed window with most pings and its centroid.

    Lower edges lie on pings of the window; ties go to the smallest (lat0_u, lon0_u). Engines: `bounded` (bounds from counts of
    half-cells leave few blocks per name, each swept by itself), `sql` (all edges), `sweep` (one pandas group per
    footprint), `microbin` (bounds of the count only).
    """
    e = extents(box, side_m)
    pts = _with_extents(points, box, side_m)
    if engine == "microbin":
        return _microbin(pts, bins)
    if engine == "bounded":
        pts, best = _blocks(pts)
    else:
        best = _sweep(pts) if engine == "sweep" else _windows(pts, e)
    near = pts.join(best, NAME).where(F.col("lat_u").between(F.col("lat0_u"), F.col("lat0_u") + F.col("dlat")) & F.col("lon_u").between(F.col("lon0_u"), F.col("lon0_u") + F.col("dlon")))
    out = near.groupBy(*NAME, "n_window", "lat0_u", "lon0_u").agg(F.sum(F.col("lat_u") * F.col("k")).alias("a"), F.sum(F.col("lon_u") * F.col("k")).alias("b"))
    return out.select(*NAME, "n_window", "lat0_u", "lon0_u", degrees(F.col("a") / F.col("n_window")).alias("lat"), degrees(F.col("b") / F.col("n_window")).alias("lon"))


def _windows(pts: DataFrame, e: dict[int, tuple[int, int]]) -> DataFrame:
    strip = F.expr("floor(lat_u / dlat)")
    edges = pts.select(*NAME, F.col("lat_u").alias("lat0_u"), "dlat", strip.alias("s")).distinct()
    edges = edges.withColumn("s", F.explode(F.array(F.col("s"), F.col("s") + 1)))
    inside = edges.join(pts.select(*NAME, "lat_u", "lon_u", strip.alias("s")), [*NAME, "s"])
    inside = inside.where(F.col("lat_u").between(F.col("lat0_u"), F.col("lat0_u") + F.col("dlat")))
    counted = None
    for city, (_, dlon) in e.items():
        w = W.partitionBy(*NAME, "lat0_u").orderBy("lon_u").rangeBetween(0, dlon)
        part = inside.where(F.col("city") == city).select(*NAME, "lat0_u", F.col("lon_u").alias("lon0_u"), F.count(F.lit(1)).over(w).alias("n"), F.min("lat_u").over(w).alias("low"))
        part = part.where("low = lat0_u").drop("low")  # both edges lie on pings of the window itself
        counted = part if counted is None else counted.unionByName(part)
    top = F.max(F.struct("n", (-F.col("lat0_u")).alias("a"), (-F.col("lon0_u")).alias("b"))).alias("t")
    return counted.groupBy(*NAME).agg(top).select(*NAME, F.col("t.n").alias("n_window"), (-F.col("t.a")).alias("lat0_u"), (-F.col("t.b")).alias("lon0_u"))


def _block_bounds(cells: DataFrame) -> DataFrame:
    """(name, bi, bj) of the half-cells in which the lower corner of a best window can lie.

    A box of 2x2 half-cells fits a window, so the fullest one bounds the optimum from below; a window with its corner in
    a half-cell lies in the 3x3 half-cells from there, so their total bounds it from above.
    """
    near = F.explode(F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b")) for a in range(3) for b in range(3)])).alias("d")
    boxes = cells.select(*NAME, "i", "j", "k", near).groupBy(*NAME, (F.col("i") - F.col("d.a")).alias("bi"), (F.col("j") - F.col("d.b")).alias("bj"))
    inner = (F.col("d.a") < 2) & (F.col("d.b") < 2)
    boxes = settle(boxes.agg(F.sum("k").alias("most"), F.sum(F.when(inner, F.col("k"))).alias("fits"), F.max((F.col("d.a") == 0).cast("int")).alias("row"), F.max((F.col("d.b") == 0).cast("int")).alias("col")))
    lower = boxes.groupBy(*NAME).agg(F.max("fits").alias("least"))
    # Both edges lie on pings, so the first row and the first column of the block hold some.
    return boxes.where("row = 1 and col = 1").join(lower, NAME).where("most >= least").select(*NAME, "bi", "bj")


def _blocks(pts: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(pings of surviving blocks with multiplicity k, the best window per name). Footprints are read twice, then only survivors."""
    half = {"i": F.expr("floor(lat_u * 2 / dlat)"), "j": F.expr("floor(lon_u * 2 / dlon)")}
    cells = pts.withColumns(half).groupBy(*NAME, "i", "j").agg(F.count(F.lit(1)).alias("k"))
    corners = settle(_block_bounds(cells))
    around = F.explode(F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b")) for a in range(3) for b in range(3)])).alias("d")
    blocks = corners.select(*NAME, "bi", "bj", around).select(*NAME, "bi", "bj", (F.col("bi") + F.col("d.a")).alias("i"), (F.col("bj") + F.col("d.b")).alias("j"))
    held = pts.withColumns(half).join(blocks.select(*NAME, "i", "j").distinct(), [*NAME, "i", "j"], "left_semi")
    held = settle(held.groupBy(*NAME, "lat_u", "lon_u", "dlat", "dlon", "i", "j").agg(F.count(F.lit(1)).alias("k")))
    swept = _sweep(held.join(blocks, [*NAME, "i", "j"]), ["bi", "bj"])
    top = F.max(F.struct("n_window", (-F.col("lat0_u")).alias("a"), (-F.col("lon0_u")).alias("b"))).alias("t")
    best = swept.groupBy(*NAME).agg(top).select(*NAME, F.col("t.n_window").alias("n_window"), (-F.col("t.a")).alias("lat0_u"), (-F.col("t.b")).alias("lon0_u"))
    return held, best


def _best(lat: np.ndarray, lon: np.ndarray, k: np.ndarray, dlat: int, dlon: int, first: np.ndarray, column: np.ndarray) -> tuple[int, int, int]:
    """(pings, -lat0, -lon0) of the best window; points come by lon, lower edges lie on those of `first` and of `column`."""
    # Strips by falling number of pings: the sweep ends where no strip can beat the best window.
    edges = np.unique(lat[first])
    order = np.argsort(lat, kind="stable")
    total = np.append(0, np.cumsum(k[order]))
    held = total[np.searchsorted(lat[order], edges + dlat, side="right")] - total[np.searchsorted(lat[order], edges)]
    by = np.argsort(-held, kind="stable")
    left, right = np.searchsorted(lon, lon), np.searchsorted(lon, lon + dlon, side="right")
    best, at, step = (0, 0, 0), 0, 1
    while at < len(by) and held[by[at]] >= best[0]:
        # A few strips at first, as most names are settled by these; then as many as a part of the matrix may have.
        a = edges[by[at : at + step]][:, None]
        inside = (lat >= a) & (lat <= a + dlat)
        upto = np.zeros((len(a), len(lat) + 1), np.int64)
        np.cumsum(inside * k, axis=1, out=upto[:, 1:])
        n = (upto[:, right] - upto[:, left]) * (inside & column)
        np.cumsum(lat == a, axis=1, out=upto[:, 1:])
        n *= upto[:, right] > upto[:, left]
        top = int(n.max(initial=0))
        if top:
            r, c = np.nonzero(n == top)
            best = max(best, max(zip([top] * len(r), (-a[r, 0]).tolist(), (-lon[c]).tolist(), strict=True)))
        at, step = at + step, max(1, min(4 * step, CHUNK // len(lat)))
    return best


def _of_name(code: np.ndarray, dlat: int, dlon: int) -> tuple[int, int, int, int, int]:
    """(pings, lat0, lon0, sum of lat, sum of lon) of the best window of one name, by the bounds of `_block_bounds`."""
    code, k = np.unique(code, return_counts=True)
    lat, lon = unpacked(code)
    by = np.argsort(lon, kind="stable")
    lat, lon, k = lat[by], lon[by], k[by]
    i, j = lat * 2 // dlat, lon * 2 // dlon
    i, j = i - i.min() + 2, j - j.min() + 2
    width = int(j.max()) + 3
    cell, of = np.unique(i * width + j, return_inverse=True)
    number = np.bincount(of, k).astype(np.int64)
    offsets = np.array([(a, b) for a in range(3) for b in range(3)])
    corners, box = np.unique((cell[:, None] - offsets[:, 0] * width - offsets[:, 1]).ravel(), return_inverse=True)
    total = lambda keep: np.bincount(box, (number[:, None] * keep).ravel(), len(corners)).astype(np.int64)
    most, fits = total(np.ones(9, np.int64)), total((offsets < 2).all(1))
    can = (most >= fits.max()) & (total(offsets[:, 0] == 0) > 0) & (total(offsets[:, 1] == 0) > 0)
    best = (0, 0, 0)
    for corner in corners[can][np.argsort(-most[can], kind="stable")].tolist():
        bi, bj = divmod(corner, width)
        own = (i >= bi) & (i < bi + 3) & (j >= bj) & (j < bj + 3)
        if k[own].sum() < best[0]:
            break
        best = max(best, _best(lat[own], lon[own], k[own], dlat, dlon, i[own] == bi, j[own] == bj))
    n, a, o = best[0], -best[1], -best[2]
    near = (lat >= a) & (lat <= a + dlat) & (lon >= o) & (lon <= o + dlon)
    return n, a, o, int((lat[near] * k[near]).sum()), int((lon[near] * k[near]).sum())


def unpacked(code: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """lat_u and lon_u from lat_u * 2^32 + lon_u."""
    lat = (code + (1 << 31)) >> 32
    return lat, code - (lat << 32)


def densest(auth: DataFrame, pings: DataFrame, box: DataFrame, side_m: float = 640.0) -> DataFrame:
    """What `densest_window` gives for the footprints of these authors, with neither a row per ping of a name nor one per block."""
    of = extents(box, side_m)
    code = (F.col("lat_u") * F.lit(1 << 32) + F.col("lon_u")).alias("code")
    users = settle(pings.where("lat_u is not null and lon_u is not null").select("user_id", code).repartition("user_id").groupBy("user_id").agg(F.collect_list("code").alias("codes")), release=True)
    sizes = auth.join(users.select("user_id", F.size("codes").cast("bigint").alias("n")), "user_id").groupBy(*NAME).agg(F.sum("n").alias("n"))
    large = [tuple(r) for r in sizes.where(F.col("n") > LARGE).select(*NAME).collect()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cities, names, rows = batch.column("city").to_pylist(), batch.column("place_name").to_pylist(), []
            for x, (city, name) in enumerate(zip(cities, names, strict=True)):
                code = batch.column("codes")[x].values.to_numpy(zero_copy_only=False)
                if city in of and len(code):
                    n, a, o, lat, lon = _of_name(code, *of[city])
                    rows.append((city, name, n, a, o, lat / n / 1e6, lon / n / 1e6))
            kinds = (pa.int32(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64())
            cols = zip(*rows, strict=True) if rows else [()] * len(kinds)
            yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(cols, kinds, strict=True)], [*NAME, "n_window", "lat0_u", "lon0_u", "lat", "lon"])

    rest = auth
    if large:
        big = F.broadcast(auth.sparkSession.createDataFrame(large, "city int, place_name string"))
        rest = auth.join(big, NAME, "left_anti")
    spread = rest.select("user_id", *NAME).join(users, "user_id").repartition(*NAME).groupBy(*NAME).agg(F.flatten(F.collect_list("codes")).alias("codes"))
    out = spread.mapInArrow(run, WINDOW)
    return out if not large else out.unionByName(densest_window(footprint.build(auth.join(big, NAME, "left_semi"), pings), box, side_m, "bounded"))


def _sweep(pts: DataFrame, block: list[str] | None = None) -> DataFrame:
    """The best window of each name, or of each block of a name: lower edges then lie in the block's first row and column."""
    import pandas as pd

    def one(key: tuple, g: pd.DataFrame) -> pd.DataFrame:
        lat, lon, k = g["lat_u"].to_numpy(), g["lon_u"].to_numpy(), g["k"].to_numpy()
        dlat, dlon = int(g["dlat"].iloc[0]), int(g["dlon"].iloc[0])
        by = np.argsort(lon, kind="stable")
        lat, lon, k = lat[by], lon[by], k[by]
        first = np.ones(len(lat), bool)
        if block:
            first = lat * 2 // dlat == key[2]
        column = lon * 2 // dlon == key[3] if block else first
        best = _best(lat, lon, k, dlat, dlon, first, column)
        found = [(*key[:2], best[0], -best[1], -best[2])] if best[0] else []
        return pd.DataFrame(found, columns=[*NAME, "n_window", "lat0_u", "lon0_u"])

    return pts.groupBy(*NAME, *(block or [])).applyInPandas(one, "city int, place_name string, n_window bigint, lat0_u bigint, lon0_u bigint")


def _microbin(pts: DataFrame, bins: int) -> DataFrame:
    """(city, place_name, lower, upper): counts of the best boxes of `bins` and `bins`+1 sub-bins bound the optimum."""
    cell = pts.select(*NAME, F.expr(f"floor(lat_u * {bins} / dlat)").alias("i"), F.expr(f"floor(lon_u * {bins} / dlon)").alias("j")).groupBy(*NAME, "i", "j").agg(F.count(F.lit(1)).alias("n"))
    # Every box that matters has its lower row on an occupied row: rows are copied down, then columns summed by frames.
    out = None
    for label, side in (("lower", bins), ("upper", bins + 1)):
        rows = cell.withColumn("i0", F.explode(F.sequence(F.col("i") - side + 1, F.col("i")))).groupBy(*NAME, "i0", "j").agg(F.sum("n").alias("n"))
        w = W.partitionBy(*NAME, "i0").orderBy("j").rangeBetween(0, side - 1)
        part = rows.select(*NAME, F.sum("n").over(w).alias("b")).groupBy(*NAME).agg(F.max("b").alias(label))
        out = part if out is None else out.join(part, NAME)
    return out

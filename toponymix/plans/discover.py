"""End-to-end plans: from addresses and pings to scored and accepted pairs."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators import blocks, evaluate, footprint, locate, pairwise, raster, score, textbase
from ..sources.fixtures import Tables
from ..sources.tables import settle

#: The parameters the experiments use: window side in metres, raster resolution, smoothing of empty cells.
WINDOW_M, GRID, EPS = 640.0, 50, 1e-3
#: Columns of a compared pair.
COMPARED = ("n_shared_cells", "shared_std_n", "shared_cand_n", "total_std", "total_cand", "overlap", "kl", "is_inf")
METHODS = ("T1", "M1", "M2", "M3", "M4")
#: With the stand-ins of the neural text baselines, which no SQL scores.
ALL_METHODS = ("T1", "T2", "T3", "M1", "M2", "M3", "M4")


def author_sets(t: Tables) -> DataFrame:
    return footprint.authors(t.address)


def all_pairs(t: Tables) -> DataFrame:
    return score.within_district(t.standard, score.candidates(t.address, t.standard))


def centroids(t: Tables) -> DataFrame:
    return locate.centroid(footprint.rollup(author_sets(t), footprint.user_partials(t.ping)))


def windows(t: Tables, side_m: float = WINDOW_M, engine: str = "bounded") -> DataFrame:
    if engine == "bounded":
        return locate.densest(author_sets(t), t.ping, t.box, side_m)
    return locate.densest_window(footprint.build(author_sets(t), t.ping), t.box, side_m, engine)


def densities(t: Tables, n: int = GRID) -> DataFrame:
    return raster.density(author_sets(t), raster.assign(t.ping, t.box, n))


def sides(t: Tables, attrs: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Standard names and candidates as `pairwise` takes them; `attrs` is written once and read by both."""
    return pairwise.named(t.standard, score.candidates(t.address, t.standard), t.truth, None if attrs is None else settle(attrs, release=True))


def footprint_sides(t: Tables, n: int = GRID, pings: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Both sides with the cells of their footprints at resolution n."""
    return sides(t, raster.packed(author_sets(t), raster.assign(t.ping if pings is None else pings, t.box, n), n))


def compared(t: Tables, n: int = GRID, zero_policy: str = "smooth", columns: tuple[str, ...] = COMPARED, places: dict[str, int] | None = None) -> DataFrame:
    """(pair, columns) of every pair: what `divergence.compare` gives, by blocks of names, doubles rounded to `places`."""
    return pairwise.compared(*footprint_sides(t, n), list(columns), n, n, EPS, zero_policy, places=places)


def scored(t: Tables, method: str, n: int = GRID, side_m: float = WINDOW_M) -> DataFrame:
    """(city, district, std_name, cand_name, score) by one method, in its order-preserving form.

    Distances and divergences enter negated and rounded (millimetres, 1e-6): the ranking and every accepted set equal
    those of their reciprocals, without infinities.
    """
    keys = ["city", "district", "std_name", "cand_name"]
    if method == "T1":
        return textbase.edit(all_pairs(t)).select(*keys, "score")
    if method in ("T2", "T3"):
        return text_rows(t, method).select(*keys, text_score(t, method).alias("score"))
    if method in ("M1", "M2"):
        d = score.distance(all_pairs(t), centroids(t) if method == "M1" else windows(t, side_m))
        return d.select(*keys, (-F.round("dist_m", 3)).alias("score"))
    c = compared(t, n, columns=("kl",) if method == "M3" else ("overlap",))
    return c.select(*keys, (-F.round("kl", 6) if method == "M3" else F.col("overlap")).alias("score"))


def anchors(t: Tables, method: str) -> DataFrame:
    """(city, name, lat, lon) of M1 or M2."""
    return (centroids(t) if method == "M1" else windows(t)).select("city", F.col("place_name").alias("name"), "lat", "lon")


def scores_counted(t: Tables, methods: list[str], sizes: list[int] | None = None, scheme: str = "disjoint", universe: str = "all_pairs") -> DataFrame:
    """(method, n_grid, city, district, score, k, h) of the scores of T1 and M1 to M4, whole wherever a cut is decided (`pairwise.counted`).

    M3 and M4 come at every resolution of `sizes`, which divide a base raster; without it at the usual one.
    """
    training: dict[int, list[int]] = {}
    for f, d, role in evaluate.folds(scheme=scheme):
        if role == "train":
            training.setdefault(f, []).append(d)
    count = lambda both, scores: pairwise.counted(*both, t.truth, scores, list(training.values()), universe == "labelled_standard")
    parts = []
    if "T1" in methods:
        parts.append(count(sides(t), pairwise.edit_scores))
    parts += [count(sides(t, anchors(t, m)), pairwise.distance_scores(m)) for m in ("M1", "M2") if m in methods]
    if by_cells := [m for m in ("M3", "M4") if m in methods]:
        base = raster.BASE if sizes else GRID
        parts.append(count(footprint_sides(t, base), pairwise.raster_scores(base, sizes or [GRID], by_cells, EPS)))
    return reduce(DataFrame.unionByName, parts)


MEASURES = {"T2": blocks.shared_trigrams, "T3": blocks.hashed_products}


def text_rows(t: Tables, method: str) -> DataFrame:
    """Every pair with the integers that T2 or T3 scores it by."""
    return blocks.rows(t.standard, score.candidates(t.address, t.standard), t.truth, MEASURES[method])


def text_counts(t: Tables, method: str) -> DataFrame:
    """How many pairs of each district, and true ones, share the integers of T2 or T3. Written once."""
    return settle(blocks.counts(t.standard, score.candidates(t.address, t.standard), t.truth, MEASURES[method]))


def text_score(t: Tables, method: str, counts: DataFrame | None = None) -> Column:
    """T3's cosine, or T2's chance of a hit by a model of the whole source city."""
    if method == "T3":
        return textbase.product_cosine()
    return textbase.align_fit((text_counts(t, method) if counts is None else counts).where("city = 0"))


def text_scored(t: Tables, method: str) -> DataFrame:
    """(city, district, score, k, h) of T2 or T3: all that evaluation needs."""
    counts = text_counts(t, method)
    return evaluate.gathered(counts.select("city", "district", text_score(t, method, counts).alias("score"), "k", "h"))


def fold_models(t: Tables, counts: DataFrame) -> dict[int, Column]:
    """Fold -> T2's chance of a hit by a model that sees the pairs of the fold's training districts only."""
    training: dict[int, list[int]] = {}
    for f, d, role in evaluate.folds():
        if role == "train":
            training.setdefault(f, []).append(d)
    return {f: textbase.align_fit(counts.where("city = 0").where(F.col("district").isin(ds))) for f, ds in training.items()}


def fold_scored(t: Tables) -> DataFrame:
    """(fold, pair, score) of T2 in the source city."""
    pairs = settle(text_rows(t, "T2").where("city = 0"))
    parts = [pairs.select(F.lit(f).alias("fold"), "city", "district", "std_name", "cand_name", s.alias("score")) for f, s in fold_models(t, text_counts(t, "T2")).items()]
    return reduce(DataFrame.unionByName, parts)


def fold_counted(t: Tables) -> DataFrame:
    """(fold, city, district, score, k, h) of T2 in the source city."""
    counts = text_counts(t, "T2").where("city = 0")
    parts = [counts.select(F.lit(f).alias("fold"), "city", "district", s.alias("score"), "k", "h") for f, s in fold_models(t, counts).items()]
    return evaluate.gathered(reduce(DataFrame.unionByName, parts))


def discover(t: Tables, method: str = "M4", cut: float = 0.5, **params) -> DataFrame:
    """Accepted (standard, candidate) pairs at a given cut."""
    return score.matrix(score.accept(scored(t, method, **params), cut))


def missing_mass(t: Tables, sizes: list[int]) -> DataFrame:
    """(n_grid, pairs, missing): pairs of two footprints and those with mass that the candidate lacks, from one base raster."""
    raster.parents(sizes)
    return pairwise.missing(*footprint_sides(t, raster.BASE), raster.BASE, sizes, EPS)

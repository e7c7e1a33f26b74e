"""Registry of the engine's queries over the given tables, each beside the SQL that checks it."""

from __future__ import annotations

import re
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.geo import EARTH_M, extent_u, great_circle_m
from ..operators import cost, divergence, evaluate, footprint, locate, raster, rollup, score, textbase
from ..sources.fixtures import Tables, oracle_prefix
from ..sources.tables import settle
from . import discover as D

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_ORACLES: dict[str, str] = {}

FP = """authors AS (SELECT DISTINCT city, district, place_name, user_id FROM address),
fp AS (SELECT a.city, a.district, a.place_name, a.user_id, p.lat_u, p.lon_u FROM authors a JOIN ping p ON p.user_id = a.user_id)"""
PAIRS = """std AS (SELECT city, district, name FROM place_name WHERE kind = 'standard'),
cand AS (SELECT DISTINCT city, district, place_name AS name FROM address a WHERE NOT EXISTS (SELECT 1 FROM std s WHERE s.district = a.district AND s.name = a.place_name)),
pairs AS (SELECT s.city, s.district, s.name AS std_name, c.name AS cand_name FROM std s JOIN cand c ON s.district = c.district)"""
KEYS = "city, district, std_name, cand_name"


def register(name: str, query: Callable[[Tables], DataFrame], sql: str | None = None, *parts: str) -> None:
    """`parts` are further WITH entries between the fixture views and the final SELECT."""
    _QUERIES[name] = lambda spark, sf_dir: query(Tables(spark, sf_dir))
    if sql is not None:
        _ORACLES[name] = ",\n".join([oracle_prefix(), *parts]) + "\n" + sql


def plain(name: str, query: Callable[[Tables], DataFrame], sql: str) -> None:
    """A query whose SQL needs no fixture view."""
    _QUERIES[name] = lambda spark, sf_dir: query(Tables(spark, sf_dir))
    _ORACLES[name] = sql


# ---- SQL building blocks -------------------------------------------------------------------------------------------


def sql_distance(a: str) -> str:
    """(KEYS, dist_m) from anchors `a` (city, place_name, lat, lon)."""
    lat, lon = "sin((radians(c.lat) - radians(s.lat)) / 2)", "sin((radians(c.lon) - radians(s.lon)) / 2)"
    return f"""dist AS (SELECT p.city, p.district, p.std_name, p.cand_name, {2 * EARTH_M!r}::DOUBLE * asin(least(1e0, sqrt({lat} * {lat} + cos(radians(s.lat)) * cos(radians(c.lat)) * {lon} * {lon}))) AS dist_m
  FROM pairs p LEFT JOIN {a} s ON s.city = p.city AND s.place_name = p.std_name LEFT JOIN {a} c ON c.city = p.city AND c.place_name = p.cand_name)"""


M1_SQL = "m1 AS (SELECT city, district, place_name, count(*) AS n, sum(lat_u)::DOUBLE / count(*) / 1e6 AS lat, sum(lon_u)::DOUBLE / count(*) / 1e6 AS lon FROM fp GROUP BY ALL)"


def sql_windows(side_m: float) -> str:
    (a0, o0), (a1, o1) = extent_u(side_m, 30.15), extent_u(side_m, 39.15)
    return f"""ext AS (SELECT 0 AS city, {a0} AS dlat, {o0} AS dlon UNION ALL SELECT 1, {a1}, {o1}),
win AS (SELECT e.city, e.place_name, lat0_u, lon_u AS lon0_u, dlat, dlon, count(*) OVER w AS n_window, min(lat_u) OVER w AS low
  FROM (SELECT DISTINCT city, place_name, lat_u AS lat0_u FROM fp) e JOIN ext ON ext.city = e.city JOIN fp p ON p.city = e.city AND p.place_name = e.place_name AND p.lat_u BETWEEN lat0_u AND lat0_u + dlat
  WINDOW w AS (PARTITION BY e.city, e.place_name, lat0_u ORDER BY lon_u RANGE BETWEEN CURRENT ROW AND dlon FOLLOWING)),
best AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY city, place_name ORDER BY n_window DESC, lat0_u, lon0_u) AS rn FROM win WHERE low = lat0_u) WHERE rn = 1),
m2 AS (SELECT b.city, b.place_name, n_window, lat0_u, lon0_u, sum(lat_u)::DOUBLE / n_window / 1e6 AS lat, sum(lon_u)::DOUBLE / n_window / 1e6 AS lon
  FROM best b JOIN fp p ON p.city = b.city AND p.place_name = b.place_name AND p.lat_u BETWEEN lat0_u AND lat0_u + dlat AND p.lon_u BETWEEN lon0_u AND lon0_u + dlon GROUP BY b.city, b.place_name, n_window, lat0_u, lon0_u)"""


def sql_raster(sizes: list[int]) -> str:
    """dens, shr, tot and cmp (per n_grid and pair: overlap and all kl forms)."""
    grids = " UNION ALL ".join(f"SELECT {n} AS n_grid" for n in sizes)
    return f"""grids AS ({grids}),
dens AS (SELECT n_grid, f.city, district, place_name, least(n_grid - 1, (lat_u - off_lat) * n_grid // 300000)::INTEGER AS r, least(n_grid - 1, (lon_u - off_lon) * n_grid // 300000)::INTEGER AS c, count(*) AS n
  FROM fp f JOIN city_box b ON b.city = f.city CROSS JOIN grids WHERE lat_u BETWEEN off_lat AND off_lat + 300000 AND lon_u BETWEEN off_lon AND off_lon + 300000 GROUP BY ALL),
shr AS (SELECT *, (sum(n) OVER (PARTITION BY n_grid, city, place_name))::BIGINT AS total, n::DOUBLE / total AS p FROM dens),
tot AS (SELECT n_grid, city, district, place_name, sum(n)::BIGINT AS total, sum(p * ln(p)) AS plogp FROM shr GROUP BY ALL),
cel AS (SELECT s.n_grid, p.std_name, p.cand_name, count(*) AS n_shared_cells, sum(s.n)::BIGINT AS shared_std_n, sum(c.n)::BIGINT AS shared_cand_n, sum(s.p) AS mass,
    sum(s.p * ln((c.n + 1e-3) / (c.total + 1e-3 * s.n_grid * s.n_grid))) AS p_ln_q, sum(s.p * ln(s.p / c.p)) AS skip, sum(c.p * ln(c.p / s.p)) AS rev
  FROM pairs p JOIN shr s ON s.place_name = p.std_name AND s.district = p.district JOIN shr c ON c.place_name = p.cand_name AND c.district = p.district AND c.n_grid = s.n_grid AND c.r = s.r AND c.c = s.c GROUP BY ALL),
cmp AS (SELECT g.n_grid, p.city, p.district, p.std_name, p.cand_name, coalesce(n_shared_cells, 0) AS n_shared_cells, coalesce(shared_std_n, 0) AS shared_std_n, coalesce(shared_cand_n, 0) AS shared_cand_n,
    s.total AS total_std, c.total AS total_cand, (coalesce(shared_std_n, 0)::DOUBLE / s.total + coalesce(shared_cand_n, 0)::DOUBLE / c.total) / 2 AS overlap,
    s.plogp - coalesce(p_ln_q, 0) - CASE WHEN shared_std_n = s.total THEN 0 ELSE 1 - coalesce(mass, 0) END * ln(1e-3 / (c.total + 1e-3 * g.n_grid * g.n_grid)) AS smooth,
    CASE WHEN s.total IS NULL OR c.total IS NULL THEN NULL ELSE coalesce(shared_std_n, 0) < s.total END AS is_inf, CASE WHEN s.total IS NOT NULL AND c.total IS NOT NULL THEN coalesce(skip, 0) END AS skip,
    CASE WHEN s.total IS NOT NULL AND c.total IS NOT NULL THEN coalesce(rev, 0) END AS rev
  FROM pairs p CROSS JOIN grids g LEFT JOIN tot s ON s.place_name = p.std_name AND s.district = p.district AND s.n_grid = g.n_grid LEFT JOIN tot c ON c.place_name = p.cand_name AND c.district = p.district AND c.n_grid = g.n_grid
    LEFT JOIN cel x ON x.n_grid = g.n_grid AND x.std_name = p.std_name AND x.cand_name = p.cand_name)"""


def sql_method(m: str) -> list[str]:
    """WITH entries that end in `sc_<m>`(KEYS, score)."""
    return {
        "T1": [f"sc_T1 AS (SELECT {KEYS}, -levenshtein(std_name, cand_name)::DOUBLE AS score FROM pairs)"],
        "M1": [M1_SQL, sql_distance("m1").replace("dist AS", "dist1 AS", 1), f"sc_M1 AS (SELECT {KEYS}, -round(dist_m, 3) AS score FROM dist1)"],
        "M2": [sql_windows(D.WINDOW_M), sql_distance("m2").replace("dist AS", "dist2 AS", 1), f"sc_M2 AS (SELECT {KEYS}, -round(dist_m, 3) AS score FROM dist2)"],
        "M3": [sql_raster([D.GRID]), f"sc_M3 AS (SELECT {KEYS}, -round(smooth, 6) AS score FROM cmp)"],
        "M4": [f"sc_M4 AS (SELECT {KEYS}, overlap AS score FROM cmp)"],
    }[m]


def sql_scored(methods: list[str]) -> list[str]:
    parts = [FP, PAIRS]
    for m in methods:
        if m == "M4" and "M3" not in methods:
            parts.append(sql_raster([D.GRID]))
        parts += sql_method(m)
    union = " UNION ALL ".join(f"SELECT '{m}' AS method, {KEYS}, score FROM sc_{m}" for m in methods)
    return [*parts, f"scored AS ({union})"]


DISJOINT = "SELECT f::INTEGER AS fold, d AS fd, d // 2 = f AS test FROM range(5) x(f), range(10) y(d)"
ALL_ROUNDS = "SELECT (a * (19 - a) // 2 + b - a - 1)::INTEGER AS fold, d AS fd, d = a OR d = b AS test FROM range(10) x(a), range(10) y(b), range(10) z(d) WHERE a < b"


def sql_eval(by: str = "method", rounds: str = DISJOINT, universe: str = "") -> list[str]:
    """cv(by, fold, ...) and tr(by, cut, ...) from scored(by, KEYS, score)."""
    ratio = "round(coalesce(c::DOUBLE / nullif(a, 0), 0), 6) AS precision, round(coalesce(c::DOUBLE / nullif(t, 0), 0), 6) AS recall, round(CASE WHEN a + t > 0 THEN 2e0 * c / (a + t) ELSE 0 END, 6) AS f1"
    lowest = "-1.7976931348623157e308::DOUBLE"
    return [
        f"""lab AS (SELECT s.*, CASE WHEN t.cand_name IS NULL THEN 0 ELSE 1 END AS hit FROM scored s LEFT JOIN truth t ON t.district = s.district AND t.std_name = s.std_name AND t.cand_name = s.cand_name WHERE score IS NOT NULL {universe}),
fold AS ({rounds}),
trn AS (SELECT {by}, fold, score, count(*) AS k, sum(hit) AS h FROM lab JOIN fold ON district = fd WHERE NOT test GROUP BY ALL UNION ALL SELECT {by}, -9, score, count(*), sum(hit) FROM lab WHERE city = 0 GROUP BY ALL),
ntr AS (SELECT fold, count(*) AS t FROM truth JOIN fold ON district = fd WHERE NOT test GROUP BY ALL UNION ALL SELECT -9, count(*) FROM truth WHERE city = 0),
cur AS (SELECT {by}, fold, score, sum(k) OVER w AS a, sum(h) OVER w AS c, t, lead(score) OVER (PARTITION BY {by}, fold ORDER BY score DESC) AS lower FROM trn JOIN ntr USING (fold) WINDOW w AS (PARTITION BY {by}, fold ORDER BY score DESC ROWS UNBOUNDED PRECEDING)),
cut AS (SELECT {by}, fold, coalesce(lower, {lowest}) AS cut, 2e0 * c / (a + t) AS best_f1 FROM (SELECT *, row_number() OVER (PARTITION BY {by}, fold ORDER BY 2e0 * c / (a + t) DESC, a) AS rn FROM cur) WHERE rn = 1),
got AS (SELECT {by}, fold, sum((score > cut)::INT) AS a, sum((score > cut)::INT * hit) AS c FROM lab JOIN fold ON district = fd AND test JOIN cut USING ({by}, fold) GROUP BY ALL),
per AS (SELECT g.*, coalesce(t, 0) AS t FROM got g LEFT JOIN (SELECT fold, count(*) AS t FROM truth JOIN fold ON district = fd AND test GROUP BY ALL) w USING (fold)),
cv AS (SELECT {by}, fold, a, c, t, {ratio} FROM per UNION ALL SELECT {by}, -1, a, c, t, {ratio} FROM (SELECT {by}, sum(a) AS a, sum(c) AS c, sum(t) AS t FROM per GROUP BY ALL)
  UNION ALL SELECT {by}, -2, sum(a), sum(c), sum(t), round(avg(coalesce(c::DOUBLE / nullif(a, 0), 0)), 6), round(avg(coalesce(c::DOUBLE / nullif(t, 0), 0)), 6), round(avg(CASE WHEN a + t > 0 THEN 2e0 * c / (a + t) ELSE 0 END), 6) FROM per GROUP BY {by}),
tr AS (SELECT {by}, cut, a, c, t, {ratio} FROM (SELECT {by}, cut, sum((score > cut)::INT) AS a, sum((score > cut)::INT * hit) AS c, (SELECT count(*) FROM truth WHERE city = 1) AS t
  FROM lab JOIN (SELECT * FROM cut WHERE fold = -9) USING ({by}) WHERE city = 1 GROUP BY ALL))"""
    ]


def rounded(df: DataFrame, places: int = 6) -> DataFrame:
    """Doubles rounded for comparison."""
    return df.select(*[F.round(c, places).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


# ---- Data, footprints, sales ---------------------------------------------------------------------------------------


def dataset_stats(t: Tables) -> DataFrame:
    """Places, users, pings and labels of each city."""
    places = t.view("place").groupBy("city").agg(F.count(F.lit(1)).alias("places"))
    pings = t.ping.groupBy("city").agg(F.countDistinct("user_id").alias("users"), F.count(F.lit(1)).alias("pings"))
    labels = t.truth.groupBy("city").agg(F.count(F.lit(1)).alias("labels"))
    return places.join(pings, "city").join(labels, "city", "left").fillna(0, ["labels"])


register(
    "w_dataset_stats",
    dataset_stats,
    """SELECT city, places, users, pings, coalesce(labels, 0) AS labels FROM (SELECT city, count(*) AS places FROM place GROUP BY 1) a
JOIN (SELECT city, count(DISTINCT user_id) AS users, count(*) AS pings FROM ping GROUP BY 1) b USING (city) LEFT JOIN (SELECT city, count(*) AS labels FROM truth GROUP BY 1) c USING (city)""",
)
register(
    "w_label_stats",
    lambda t: D.all_pairs(t).groupBy("city", "district").agg(F.countDistinct("std_name").alias("n_std"), F.countDistinct("cand_name").alias("n_cand"), F.count(F.lit(1)).alias("n_pairs"))
    .join(t.truth.groupBy("district").agg(F.count(F.lit(1)).alias("n_true")), "district", "left").fillna(0, ["n_true"]),
    "SELECT p.city, p.district, count(DISTINCT std_name) AS n_std, count(DISTINCT cand_name) AS n_cand, count(*) AS n_pairs, coalesce(any_value(n), 0) AS n_true FROM pairs p LEFT JOIN (SELECT district, count(*) AS n FROM truth GROUP BY 1) t ON t.district = p.district GROUP BY 1, 2",
    PAIRS,
)
register("w_address_parts", lambda t: footprint.parse(t.address), "SELECT user_id, addr_seq, city, district, split_part(addr_text, '/', 1) AS region_name, split_part(addr_text, '/', 2) AS nation_name, place_name FROM address")
register("w_authors", lambda t: D.author_sets(t), "SELECT * FROM authors", FP)
NAMES = "SELECT city, district, name FROM place_name"
register(
    "w_mentions_contains",
    lambda t: footprint.authors(footprint.mentions(t.address, t.view("place_name").select("city", "district", "name"), "contains")),
    "SELECT DISTINCT a.city, a.district, n.name AS place_name, a.user_id FROM address a JOIN place_name n ON n.district = a.district AND contains(a.addr_text, n.name)",
)
register("w_footprint", lambda t: footprint.build(D.author_sets(t), t.ping).groupBy("place_name", "lat_u", "lon_u").agg(F.count(F.lit(1)).alias("n")), "SELECT place_name, lat_u, lon_u, count(*) AS n FROM fp GROUP BY ALL", FP)
register("w_footprint_set", lambda t: footprint.build(D.author_sets(t), t.ping, "set").select("place_name", "lat_u", "lon_u"), "SELECT DISTINCT place_name, lat_u, lon_u FROM fp", FP)
register("w_footprint_size", lambda t: footprint.sizes(D.author_sets(t), t.ping), "SELECT place_name, count(DISTINCT user_id) AS n_users, count(*) AS n_pings, count(DISTINCT (lat_u, lon_u)) AS n_points_distinct FROM fp GROUP BY ALL", FP)

VOLUME = """alias_of AS (SELECT city, district, std_name, cand_name AS place_name, 0 AS own FROM truth UNION ALL SELECT city, district, name, name, 1 FROM place_name WHERE kind = 'standard'),
vol AS (SELECT a.city, a.district, std_name, count(*) FILTER (own = 1) AS orders_name_only, count(*) AS orders_with_alias,
  coalesce(sum(round(o_totalprice * 100)::BIGINT) FILTER (own = 1), 0)::BIGINT AS value_name_only, sum(round(o_totalprice * 100)::BIGINT)::BIGINT AS value_with_alias
  FROM alias_of a JOIN sales_order o ON o.district = a.district AND o.place_name = a.place_name GROUP BY ALL)"""


def _volume(t: Tables) -> DataFrame:
    return rollup.volume(t.view("sales_order"), t.standard, t.truth)


register("w_name_only_volume", lambda t: _volume(t).select("city", "district", "std_name", "orders_name_only", "value_name_only"), "SELECT city, district, std_name, orders_name_only, value_name_only FROM vol", VOLUME)
register("w_alias_volume", _volume, "SELECT * FROM vol", VOLUME)
register(
    "w_volume_gap",
    lambda t: _volume(t).groupBy("city").agg(F.sum("value_name_only").alias("by_name"), F.sum("value_with_alias").alias("with_alias"), F.sum((F.col("value_with_alias") > F.col("value_name_only")).cast("int")).alias("places_understated")),
    "SELECT city, sum(value_name_only)::BIGINT AS by_name, sum(value_with_alias)::BIGINT AS with_alias, count(*) FILTER (value_with_alias > value_name_only) AS places_understated FROM vol GROUP BY 1",
    VOLUME,
)

# ---- The four measures and their variants --------------------------------------------------------------------------

register("m1_centroid", lambda t: rounded(D.centroids(t).drop("city", "district")), "SELECT place_name, n, round(lat, 6) AS lat, round(lon, 6) AS lon FROM m1", FP, M1_SQL)
DIST = f"SELECT {KEYS}, round(dist_m, 3) AS dist_m, CASE WHEN dist_m IS NULL THEN NULL WHEN dist_m <= 0 THEN -1e0 ELSE round(1 / dist_m, 6) END AS score, coalesce(dist_m <= 0, false)::INT AS is_inf FROM dist"


def _distances(t: Tables, anchors: DataFrame) -> DataFrame:
    d = score.distance(D.all_pairs(t), anchors)
    inf = F.coalesce(F.col("dist_m") <= 0, F.lit(False))
    return d.select("city", "district", "std_name", "cand_name", F.round("dist_m", 3).alias("dist_m"), F.when(inf, -1.0).otherwise(F.round("score", 6)).alias("score"), inf.cast("int").alias("is_inf"))


register("m1_score", lambda t: _distances(t, D.centroids(t)), DIST, FP, PAIRS, M1_SQL, sql_distance("m1"))
WINDOW = "SELECT city, place_name, n_window, lat0_u, lon0_u, round(lat, 6) AS lat, round(lon, 6) AS lon FROM m2"
for _engine in ("sql", "bounded", "sweep"):
    register("m2_window" + ("" if _engine == "sql" else "_" + _engine), lambda t, e=_engine: rounded(D.windows(t, engine=e)), WINDOW, FP, sql_windows(D.WINDOW_M))
register("m2_score", lambda t: _distances(t, D.windows(t)), DIST, FP, PAIRS, sql_windows(D.WINDOW_M), sql_distance("m2"))
register(
    "m2_microbin",
    lambda t: D.windows(t, engine="microbin").join(D.windows(t), ["city", "place_name"]).agg(F.count(F.lit(1)).alias("names"), F.sum(((F.col("lower") <= F.col("n_window")) & (F.col("n_window") <= F.col("upper"))).cast("int")).alias("bounded_rows")),
    "SELECT count(*) AS names, count(*) AS bounded_rows FROM (SELECT DISTINCT city, place_name FROM fp)",
    FP,
)
SIDES = (160.0, 320.0, 640.0, 1280.0, 2560.0)


def _d_sweep(t: Tables) -> DataFrame:
    """Window counts by side: a larger window never holds fewer pings. Each side is written by itself, so one side's broadcasts are held at a time."""
    parts = [settle(D.windows(t, s, "bounded").select(F.lit(int(s)).alias("side_m"), "place_name", "n_window")) for s in SIDES]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _sides_sql() -> tuple[list[str], str]:
    """The windows of all sides: one set of views per side."""
    parts, selects = [FP], []
    for side in map(int, SIDES):
        text = sql_windows(side)
        for view in ("ext", "win", "best", "m2"):
            text = re.sub(rf"\b{view}\b(?=\s+(AS \(|ON|b |WHERE|e )|\.)", f"{view}{side}", text)
        parts.append(text)
        selects.append(f"SELECT {side} AS side_m, place_name, n_window FROM best{side}")
    return parts, " UNION ALL ".join(selects)


_parts, _select = _sides_sql()
register("m2_d_sweep", _d_sweep, _select, *_parts)
register("m3_density", lambda t: D.densities(t).select("place_name", "r", "c", "n"), "SELECT place_name, r, c, n FROM dens", FP, PAIRS, sql_raster([50]))
register("m3_share", lambda t: rounded(raster.share(D.densities(t)).select("place_name", "r", "c", "n", "total", "p")), "SELECT place_name, r, c, n, total, round(p, 6) AS p FROM shr", FP, PAIRS, sql_raster([50]))
register(
    "m3_density_clamped",
    lambda t: raster.density(D.author_sets(t), raster.assign(t.ping.withColumn("lat_u", F.col("lat_u") + 5000), t.box, 50, "clamp")).select("place_name", "r", "c", "n"),
    "SELECT place_name, least(49, (least(lat_u + 5000, off_lat + 300000) - off_lat) * 50 // 300000)::INTEGER AS r, least(49, (lon_u - off_lon) * 50 // 300000)::INTEGER AS c, count(*) AS n FROM fp f JOIN city_box b ON b.city = f.city GROUP BY ALL",
    FP,
)
_RASTER = (FP, PAIRS, sql_raster([50]))


def _kl(policy: str) -> Callable[[Tables], DataFrame]:
    def run(t: Tables) -> DataFrame:
        c = D.compared(t, zero_policy=policy, columns=("n_shared_cells", "kl", "is_inf"), places={"kl": 6})
        kl = F.when(F.isnull("kl") | (F.abs("kl") == float("inf")), F.lit(None)).otherwise(F.col("kl"))
        return c.select("city", "district", "std_name", "cand_name", "n_shared_cells", kl.alias("kl"), F.col("is_inf").cast("int").alias("is_inf"))

    return run


for _policy, _col in (("smooth", "smooth"), ("strict", "CASE WHEN NOT is_inf THEN skip END"), ("skip", "skip"), ("reverse", "rev")):
    register(f"m3_kl_{_policy}", _kl(_policy), f"SELECT {KEYS}, n_shared_cells, round({_col}, 6) AS kl, is_inf::INT AS is_inf FROM cmp", *_RASTER)
# Both sides smoothed, by the definition: terms of the cells that either name holds, and one term for each cell of neither.
BOTH_SQL = """either AS (SELECT p.city, p.district, p.std_name, p.cand_name, r, c, max(sn) AS sn, max(cn) AS cn FROM (
    SELECT p.*, s.r, s.c, s.n AS sn, 0 AS cn FROM pairs p JOIN shr s ON s.place_name = p.std_name AND s.district = p.district
    UNION ALL SELECT p.*, s.r, s.c, 0, s.n FROM pairs p JOIN shr s ON s.place_name = p.cand_name AND s.district = p.district) p GROUP BY ALL),
q2 AS (SELECT e.std_name, e.cand_name, s.total + 2.5e0 AS st, c.total + 2.5e0 AS ct, (sn + 1e-3) / st AS a, (cn + 1e-3) / ct AS b
  FROM either e JOIN tot s ON s.place_name = e.std_name AND s.district = e.district JOIN tot c ON c.place_name = e.cand_name AND c.district = e.district),
both2 AS (SELECT std_name, cand_name, sum(a * ln(a / b)) + (2500 - count(*)) * (1e-3 / any_value(st)) * ln(any_value(ct) / any_value(st)) AS kl, sum(b * ln(b / a)) + (2500 - count(*)) * (1e-3 / any_value(ct)) * ln(any_value(st) / any_value(ct)) AS back
  FROM q2 GROUP BY 1, 2)"""
for _policy, _col in (("smooth_both", "kl"), ("symmetric", "(kl + back) / 2")):
    register(f"m3_kl_{_policy}", lambda t, p=_policy: _kl(p)(t).drop("is_inf"), f"SELECT {', '.join('c.' + k for k in KEYS.split(', '))}, n_shared_cells, round({_col}, 6) AS kl FROM cmp c LEFT JOIN both2 b ON b.std_name = c.std_name AND b.cand_name = c.cand_name", *_RASTER, BOTH_SQL)
register(
    "m3_score",
    lambda t: D.compared(t, columns=("kl", "inverse"), places={"kl": 6, "inverse": 4}).withColumnRenamed("inverse", "score"),  # the score of `score.distribution`
    f"SELECT {KEYS}, round(smooth, 6) AS kl, round(1 / smooth, 4) AS score FROM cmp",
    *_RASTER,
)
register(
    "m4_overlap",
    lambda t: rounded(D.compared(t, columns=D.COMPARED[1:6]), 9),
    f"SELECT {KEYS}, shared_std_n, shared_cand_n, total_std, total_cand, round(overlap, 9) AS overlap FROM cmp",
    *_RASTER,
)
register("m4_score", lambda t: D.scored(t, "M4").select("std_name", "cand_name", F.round("score", 9).alias("score")), "SELECT std_name, cand_name, round(overlap, 9) AS score FROM cmp", *_RASTER)
for _form, _sql in (("reciprocal", "1 - overlap"), ("as_printed", "overlap")):
    register(
        f"m4_{_form}",
        lambda t, f=_form: score.distribution(D.compared(t, columns=("overlap",)), "M4", f).select("std_name", "cand_name", F.when(F.col("score") == float("inf"), -1.0).otherwise(F.round("score", 6)).alias("score")),
        f"SELECT std_name, cand_name, CASE WHEN overlap IS NULL THEN NULL WHEN {_sql} <= 0 THEN -1e0 ELSE round(1 / ({_sql}), 6) END AS score FROM cmp",
        *_RASTER,
    )
register(
    "f_map_overlap",
    lambda t: rounded(D.compared(t, columns=("overlap",)).where("overlap IS NOT NULL"), 9),  # `overlap_by_maps` is its twin for few pairs
    f"SELECT {KEYS}, round(overlap, 9) AS overlap FROM cmp WHERE overlap IS NOT NULL",
    *_RASTER,
)
register("t1_edit", lambda t: textbase.edit(D.all_pairs(t)).select("city", "district", "std_name", "cand_name", "edits"), f"SELECT {KEYS}, levenshtein(std_name, cand_name)::INTEGER AS edits FROM pairs", PAIRS)
register(
    "t1_edit_norm",
    lambda t: rounded(textbase.edit(D.all_pairs(t), "maxlen").select("std_name", "cand_name", "score")),
    "SELECT std_name, cand_name, round(1 - levenshtein(std_name, cand_name)::DOUBLE / greatest(length(std_name), length(cand_name)), 6) AS score FROM pairs",
    PAIRS,
)


def _text(method: str) -> Callable[[Tables], DataFrame]:
    return lambda t: rounded(D.scored(t, method))


register("t2_align", _text("T2"))
register("t3_embed", _text("T3"))


def _vec(t: Tables) -> DataFrame:
    """Cosine of each vector with the next id: the embedding carrier of T3."""
    e = t.base("embeddings")
    n = e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("b"), F.col("label").alias("other"))
    return e.join(n, "vec_id").select("vec_id", F.round(textbase.cosine(F.col("embedding"), F.col("b")), 5).alias("cosine"), (F.col("label") == F.col("other")).cast("int").alias("same"))


plain(
    "t3_vec_cosine",
    _vec,
    "SELECT a.vec_id, round(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: p[1]::DOUBLE * p[2]::DOUBLE)), 5) AS cosine, (a.label = b.label)::INT AS same FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1",
)

# ---- Evaluation ----------------------------------------------------------------------------------------------------

register("e_pairs", D.all_pairs, f"SELECT {KEYS} FROM pairs", PAIRS)


def _counted(t: Tables, methods=D.METHODS, **kind: str) -> DataFrame:
    """Scores of a district with their numbers of pairs, written once: every fold, cut and test reads these instead of pairs."""
    pairs = [m for m in methods if m not in D.MEASURES]
    parts = [D.scores_counted(t, pairs, **kind).drop("n_grid")] if pairs else []
    parts += [D.text_scored(t, m).withColumn("method", F.lit(m)) for m in methods if m in D.MEASURES]
    return settle(reduce(DataFrame.unionByName, parts))


def _cv(t: Tables, methods, counted: DataFrame | None = None) -> DataFrame:
    fixed = [m for m in methods if m != "T2"]
    runs = []
    if fixed:
        runs.append((_counted(t, fixed) if counted is None else counted).where(F.col("method") != "T2"))
    if "T2" in methods:
        runs.append(settle(D.fold_counted(t).withColumn("method", F.lit("T2"))))
    return rounded(reduce(DataFrame.unionByName, [evaluate.cross_validate(r, t.truth, ["method"]) for r in runs]))


def _tr(t: Tables, methods, counted: DataFrame | None = None) -> DataFrame:
    return rounded(evaluate.transfer(_counted(t, methods) if counted is None else counted, t.truth, ["method"]))


EVAL_COLS = "a::BIGINT AS n_accepted, c::BIGINT AS n_correct, t::BIGINT AS n_true, precision, recall, f1"
for _m in D.METHODS:
    register(f"e_cv_{_m.lower()}", lambda t, m=_m: _cv(t, [m]), f"SELECT method, fold, {EVAL_COLS} FROM cv", *sql_scored([_m]), *sql_eval())
    register(f"e_transfer_{_m.lower()}", lambda t, m=_m: _tr(t, [m]), f"SELECT method, round(cut, 6) AS cut, {EVAL_COLS} FROM tr", *sql_scored([_m]), *sql_eval())

    def _curve(t: Tables, m: str = _m) -> DataFrame:
        lab = evaluate.label(D.scored(t, m).where("city = 0"), t.truth)
        return rounded(evaluate.pr_curve(lab, t.truth.where("city = 0").agg(F.count(F.lit(1)).alias("n_true")), []))

    register(
        f"e_pr_curve_{_m.lower()}",
        _curve,
        "SELECT round(score, 6) AS score, a::BIGINT AS n_accepted, c::BIGINT AS n_correct, t::BIGINT AS n_true, round(c::DOUBLE / a, 6) AS precision, round(c::DOUBLE / t, 6) AS recall, round(2e0 * c / (a + t), 6) AS f1 FROM cur WHERE fold = -9",
        *sql_scored([_m]),
        *sql_eval(),
    )
    register(
        f"e_best_cut_{_m.lower()}",
        lambda t, m=_m: rounded(evaluate.best_cut(D.scored(t, m), t.truth).select("cut", "train_f1")),
        "SELECT round(cut, 6) AS cut, round(best_f1, 6) AS train_f1 FROM cut WHERE fold = -9",
        *sql_scored([_m]),
        *sql_eval(),
    )


def table_one(t: Tables, methods=D.METHODS) -> DataFrame:
    """The methods side by side: cross-validation in the source city and transfer to the target city."""
    scores = _counted(t, methods)
    cv = _cv(t, methods, scores).where("fold = -1").select("method", *[F.col(c).alias("cv_" + c) for c in ("precision", "recall", "f1")])
    return cv.join(_tr(t, methods, scores).select("method", *[F.col(c).alias("tr_" + c) for c in ("precision", "recall", "f1")]), "method")


register(
    "e_table1",
    table_one,
    "SELECT method, v.precision AS cv_precision, v.recall AS cv_recall, v.f1 AS cv_f1, r.precision AS tr_precision, r.recall AS tr_recall, r.f1 AS tr_f1 FROM cv v JOIN tr r USING (method) WHERE fold = -1",
    *sql_scored(list(D.METHODS)),
    *sql_eval(),
)
# The trained text baselines have no SQL: their rows stand beside the others in a table of its own.
register("e_table1_all", lambda t: table_one(t, D.ALL_METHODS))
for _m in ("T2", "T3"):
    register(f"e_cv_{_m.lower()}", lambda t, m=_m: _cv(t, [m]))
    register(f"e_transfer_{_m.lower()}", lambda t, m=_m: _tr(t, [m]))
    register(
        f"e_pr_curve_{_m.lower()}",
        lambda t, m=_m: rounded(evaluate.pr_curve(D.text_scored(t, m).where("city = 0"), t.truth.where("city = 0").agg(F.count(F.lit(1)).alias("n_true")), [])),
    )
    register(f"e_best_cut_{_m.lower()}", lambda t, m=_m: rounded(evaluate.best_cut(D.text_scored(t, m), t.truth).select("cut", "train_f1")))
register(
    "e_drop",
    lambda t: _drop(t, _counted(t, ["T1", "M4"])),
    "SELECT method, round(v.f1, 5) AS cv_f1, round(r.f1, 5) AS tr_f1, round((2e0 * v.c / (v.a + v.t) - 2e0 * r.c / (r.a + r.t)) / nullif(2e0 * v.c / (v.a + v.t), 0), 5) AS f1_drop FROM cv v JOIN tr r USING (method) WHERE fold = -1",
    *sql_scored(["T1", "M4"]),
    *sql_eval(),
)


def _drop(t: Tables, scores: DataFrame) -> DataFrame:
    return rounded(evaluate.drop(evaluate.cross_validate(scores, t.truth, ["method"]), evaluate.transfer(scores, t.truth, ["method"]), ["method"]), 5)


SIZES = [20, 50, 100, 150, 200, 250, 300, 400, 500]


def resolution(t: Tables, sizes: list[int] | None = None) -> DataFrame:
    """F1 by method, resolution and task (best in the source city; transferred to the target city)."""
    by = ["method", "n_grid"]
    s = settle(D.scores_counted(t, ["M3", "M4"], sizes or SIZES))
    own = evaluate.best_cut(s, t.truth, by).select(*by, F.lit("source").alias("task"), F.round("train_f1", 6).alias("f1"))
    return own.unionByName(evaluate.transfer(s, t.truth, by).select(*by, F.lit("transfer").alias("task"), F.round("f1", 6).alias("f1")))


register(
    "e_resolution",
    resolution,
    "SELECT method, n_grid, 'source' AS task, round(best_f1, 6) AS f1 FROM cut WHERE fold = -9 UNION ALL SELECT method, n_grid, 'transfer', f1 FROM tr",
    FP,
    PAIRS,
    sql_raster(SIZES),
    f"scored AS (SELECT 'M3' AS method, n_grid, {KEYS}, -round(smooth, 6) AS score FROM cmp UNION ALL SELECT 'M4', n_grid, {KEYS}, overlap FROM cmp)",
    *sql_eval("method, n_grid"),
)
register("e_alias_matrix", lambda t: D.discover(t, "M4", 0.5), f"SELECT {KEYS} FROM cmp WHERE overlap > 0.5", *_RASTER)
register(
    "e_confusion_by_district",
    lambda t: rounded(evaluate.confusion(score.accept(D.scored(t, "M4"), 0.5), t.truth, ["district"])),
    """SELECT coalesce(x.district, y.district) AS district, coalesce(a, 0)::BIGINT AS n_accepted, coalesce(c, 0)::BIGINT AS n_correct, coalesce(t, 0)::BIGINT AS n_true, round(coalesce(c::DOUBLE / nullif(a, 0), 0), 6) AS precision,
  round(coalesce(c::DOUBLE / nullif(t, 0), 0), 6) AS recall, round(CASE WHEN coalesce(a, 0) + coalesce(t, 0) > 0 THEN 2e0 * coalesce(c, 0) / (coalesce(a, 0) + coalesce(t, 0)) ELSE 0 END, 6) AS f1
FROM (SELECT p.district, count(*) FILTER (overlap > 0.5) AS a, count(*) FILTER (overlap > 0.5 AND tr.cand_name IS NOT NULL) AS c FROM cmp p LEFT JOIN truth tr ON tr.district = p.district AND tr.std_name = p.std_name AND tr.cand_name = p.cand_name GROUP BY 1) x
FULL JOIN (SELECT district, count(*) AS t FROM truth GROUP BY 1) y USING (district)""",
    *_RASTER,
)


for _name, _kind, _sql in (("45", {"scheme": "all_pairs"}, {"rounds": ALL_ROUNDS}), ("labelled", {"universe": "labelled_standard"}, {"universe": "AND EXISTS (SELECT 1 FROM truth u WHERE u.district = s.district AND u.std_name = s.std_name)"})):
    register(
        f"e_cv_m4_{_name}",
        lambda t, k=_kind: rounded(evaluate.cross_validate(_counted(t, ["M4"], **k), t.truth, ["method"], k.get("scheme", "disjoint"))),
        f"SELECT method, fold, {EVAL_COLS} FROM cv",
        *sql_scored(["M4"]),
        *sql_eval(**_sql),
    )


def _mixed_curve(t: Tables) -> DataFrame:
    """The curve over scores of both signs with zero, one, halves and ties."""
    rows = t.base("labels").select((F.floor((F.col("doc_id") * 37 % 97 - 48) / 3) / 8).alias("score"), F.col("quality").alias("hit"))
    return rounded(evaluate.pr_curve(rows, rows.agg(F.sum("hit").alias("n_true")), []))


plain(
    "e_pr_curve_mixed",
    _mixed_curve,
    """WITH g AS (SELECT floor((doc_id * 37 % 97 - 48) / 3) / 8 AS score, count(*) AS k, sum(quality) AS h FROM labels GROUP BY 1),
r AS (SELECT score, sum(k) OVER w AS a, sum(h) OVER w AS c, (SELECT sum(quality) FROM labels) AS t FROM g WINDOW w AS (ORDER BY score DESC ROWS UNBOUNDED PRECEDING))
SELECT score, a::BIGINT AS n_accepted, c::BIGINT AS n_correct, t::BIGINT AS n_true, round(c::DOUBLE / a, 6) AS precision, round(c::DOUBLE / t, 6) AS recall, round(2e0 * c / (a + t), 6) AS f1 FROM r""",
)


# ---- Names in free text --------------------------------------------------------------------------------------------


def _passages(t: Tables) -> DataFrame:
    return t.base("benchmark").select(F.col("item_id").alias("pattern_id"), F.substring("text", 1, 40).alias("pattern"))


def _first_words(t: Tables) -> DataFrame:
    """Three-word names: how each passage begins."""
    return t.base("benchmark").select(F.col("item_id").alias("pattern_id"), F.substring_index("text", " ", 3).alias("pattern"))


def _mentions(texts: DataFrame, patterns: DataFrame, key: str) -> DataFrame:
    return footprint.contained(texts, patterns).select(F.col("text_id").alias(key), F.col("pattern_id").alias("item_id"))


plain(
    "e_contains_text",
    lambda t: _mentions(t.base("documents").select(F.col("doc_id").alias("text_id"), "text"), _passages(t), "doc_id"),
    "SELECT DISTINCT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, left(b.text, 40))",
)
THREE_WORDS = "split_part(b.text, ' ', 1) || ' ' || split_part(b.text, ' ', 2) || ' ' || split_part(b.text, ' ', 3)"
plain(
    "e_pages_mentions",
    lambda t: _mentions(t.base("pages").select(F.col("page_id").alias("text_id"), footprint.page_text(F.col("html")).alias("text")), _first_words(t), "page_id"),
    rf"""SELECT DISTINCT page_id, item_id FROM (SELECT page_id, trim(regexp_replace(regexp_replace(regexp_replace(html, '(?is)<script\b.*?</script\s*>|<style\b.*?</style\s*>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'), '[ \t\r\n]+', ' ', 'g')) AS text FROM pages) p
JOIN benchmark b ON contains(p.text, {THREE_WORDS})""",
)
plain(
    "e_conv_mentions",
    lambda t: _mentions(t.base("conversations").where("role = 'user'").select(F.struct("conv_id", "turn").alias("text_id"), "text"), _first_words(t), "at").select("at.conv_id", "at.turn", "item_id"),
    f"SELECT DISTINCT conv_id, turn, item_id FROM conversations c JOIN benchmark b ON role = 'user' AND contains(c.text, {THREE_WORDS})",
)

# ---- Claims about the method ---------------------------------------------------------------------------------------


def _author_curve(t: Tables) -> DataFrame:
    """Mean metres from the centroid of a name to its place: of its first author alone, and of all its authors."""
    auth = D.author_sets(t)
    first = auth.groupBy("city", "district", "place_name").agg(F.min("user_id").alias("user_id"))
    where = t.view("place_name").where("kind = 'standard'").select("poi_id", F.col("name").alias("place_name")).join(t.view("place").select("poi_id", "lat_u", "lon_u"), "poi_id")
    parts = []
    for k, who in (("one", first), ("all", auth)):
        at = locate.centroid(footprint.rollup(who, footprint.user_partials(t.ping))).join(where, "place_name")
        d = great_circle_m(F.col("lat"), F.col("lon"), F.col("lat_u") / 1e6, F.col("lon_u") / 1e6)
        parts.append(at.agg(F.lit(k).alias("authors"), F.count(F.lit(1)).alias("names"), F.round(F.avg(d), 1).alias("mean_error_m")))
    return parts[0].unionByName(parts[1])


register("x_author_curve", _author_curve)
NO_HOME = FP.replace("JOIN ping p ON p.user_id = a.user_id", "JOIN ping p ON p.user_id = a.user_id AND h >= 55")


def _no_home(t: Tables) -> DataFrame:
    """M4 without the pings at home: people of one place share other haunts too."""
    cand = score.candidates(t.address, t.standard)
    away = t.view("ping").where("h >= 55").select("user_id", "city", "lat_u", "lon_u", "ts")
    shares = settle(raster.share(settle(raster.density(D.author_sets(t), raster.assign(away, t.box, D.GRID)))))
    s = score.distribution(divergence.compare(shares, D.all_pairs(t), t.standard, cand, D.EPS, D.GRID))
    s = settle(s.select(F.lit("M4").alias("method"), "city", "district", "std_name", "cand_name", "score"))
    return rounded(evaluate.best_cut(s, t.truth, ["method"]).select("method", "cut", "train_f1"))


register(
    "x_no_home",
    _no_home,
    "SELECT method, round(cut, 6) AS cut, round(best_f1, 6) AS train_f1 FROM cut WHERE fold = -9",
    NO_HOME,
    PAIRS,
    sql_raster([D.GRID]),
    f"scored AS (SELECT 'M4' AS method, {KEYS}, overlap AS score FROM cmp)",
    *sql_eval(),
)


def _kl_missing(t: Tables) -> DataFrame:
    """Share of pairs whose standard name has mass where the candidate has none, by resolution."""
    return D.missing_mass(t, SIZES).select("n_grid", "pairs", F.round(F.try_divide("missing", "pairs"), 6).alias("missing"))


register("x_kl_missing", _kl_missing, "SELECT n_grid, count(is_inf) AS pairs, round(avg(is_inf::INT), 6) AS missing FROM cmp GROUP BY 1", FP, PAIRS, sql_raster(SIZES))
register(
    "x_cell_jaccard",
    lambda t: _cell_jaccard(t),
    f"""SELECT {KEYS}, round(n_shared_cells::DOUBLE / (a.k + b.k - n_shared_cells), 6) AS jaccard FROM cmp c JOIN (SELECT place_name, count(*) AS k FROM shr GROUP BY 1) a ON a.place_name = c.std_name
JOIN (SELECT place_name, count(*) AS k FROM shr GROUP BY 1) b ON b.place_name = c.cand_name""",
    *_RASTER,
)


def _cell_jaccard(t: Tables) -> DataFrame:
    """Unweighted likeness of the cell sets of each pair."""
    return D.compared(t, columns=("jaccard",), places={"jaccard": 6}).where("jaccard IS NOT NULL")


def _pruned(t: Tables) -> DataFrame:
    """Candidate pruning against all pairs: how many pairs stay, and how many of the true ones."""
    pairs = settle(D.all_pairs(t))
    kept = settle(score.minhash_candidates(settle(D.densities(t)), pairs))
    keys = ["city", "district", "std_name", "cand_name"]
    true = lambda d: d.join(t.truth.select(*keys), keys, "left_semi").count()
    return t.spark.createDataFrame([(pairs.count(), kept.count(), true(pairs), true(kept))], "n_pairs bigint, n_kept bigint, n_true bigint, n_true_kept bigint")


register("x_minhash_candidates", _pruned)


def _costs(t: Tables) -> DataFrame:
    """Operators of the final plans, rows and milliseconds of the four measures' last steps."""
    return t.spark.createDataFrame([cost.measure(D.scored(t, m), m) for m in ("T1", "M1", "M2", "M3", "M4")])


register("x_cost", _costs)


def _evaluator(t: Tables) -> DataFrame:
    """The evaluator on labels that are not ours: text length as score, quality as truth."""
    rows = t.base("documents").join(t.base("labels"), "doc_id").select(F.col("n_chars").cast("double").alias("score"), F.col("quality").alias("hit"))
    return rounded(evaluate.pr_curve(rows, rows.agg(F.sum("hit").alias("n_true")), []))


plain(
    "e_evaluator_labels",
    _evaluator,
    """WITH g AS (SELECT n_chars::DOUBLE AS score, count(*) AS k, sum(quality) AS h FROM documents JOIN labels USING (doc_id) GROUP BY 1),
r AS (SELECT score, sum(k) OVER w AS a, sum(h) OVER w AS c, (SELECT sum(quality) FROM labels JOIN documents USING (doc_id)) AS t FROM g WINDOW w AS (ORDER BY score DESC ROWS UNBOUNDED PRECEDING))
SELECT score, a::BIGINT AS n_accepted, c::BIGINT AS n_correct, t::BIGINT AS n_true, round(c::DOUBLE / a, 6) AS precision, round(c::DOUBLE / t, 6) AS recall, round(2e0 * c / (a + t), 6) AS f1 FROM r""",
)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Overlap-based discovery end to end: accepted pairs with their score."""
    t = Tables(spark, sf_dir)
    return score.accept(D.scored(t, "M4"), 0.5).where("is_alias").select("city", "district", "std_name", "cand_name", F.round("score", 9).alias("score"))


register("discover_m4", lambda t: flagship(t.spark, t.dir), f"SELECT {KEYS}, round(overlap, 9) AS score FROM cmp WHERE overlap > 0.5", *_RASTER)


def queries() -> dict[str, Query]:
    from . import surroundings

    return {**_QUERIES, **surroundings.QUERIES}


def oracle_sql() -> dict[str, str]:
    from . import surroundings

    return {**_ORACLES, **surroundings.ORACLES, "sql_m4": _ORACLES["m4_score"]}

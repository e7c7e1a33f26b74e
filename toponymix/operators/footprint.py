"""Addresses to author sets to footprints."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def parse(addr: DataFrame, sep: str = "/") -> DataFrame:
    """addr_text -> administrative terms and place name."""
    part = F.split("addr_text", sep)
    return addr.select(
        "user_id",
        "addr_seq",
        "city",
        F.regexp_extract(F.get(part, F.lit(2)), r"district-(\d+)", 1).cast("int").alias("district"),
        F.trim(F.get(part, F.lit(0))).alias("region_name"),
        F.trim(F.get(part, F.lit(1))).alias("nation_name"),
        F.trim(F.get(part, F.lit(3))).alias("place_name"),
    )


def mentions(addr: DataFrame, names: DataFrame, mode: str = "parsed", q: int = 6) -> DataFrame:
    """(city, district, place_name, user_id) rows: addresses that write a name.

    `parsed` compares the parsed place name; `contains` finds a name anywhere in the text. Containment is blocked on the
    last `q` characters of each name (all of a shorter name): a text that contains the name has them among its own
    pieces of that length, so an equi-join finds every hit and the exact test follows. No nested loop.
    """
    if mode == "parsed":
        return addr.join(names.select("city", "district", F.col("name").alias("place_name")), ["city", "district", "place_name"]).select("city", "district", "place_name", "user_id")
    keyed = names.where(F.length("name") > 0).select("city", "district", "name", F.length("name").alias("n"))
    keyed = keyed.withColumn("k", F.least("n", F.lit(q))).withColumn("piece", F.expr("right(name, k)"))
    sizes_used = F.broadcast(keyed.select("k").distinct())
    texts = addr.select("city", "district", "user_id", "addr_text").distinct().crossJoin(sizes_used)
    at = F.explode(F.sequence(F.lit(1), F.greatest(F.length("addr_text") - F.col("k") + 1, F.lit(1)))).alias("at")
    pieces = texts.select("city", "district", "user_id", "addr_text", "k", at).withColumn("piece", F.expr("substring(addr_text, at, k)"))
    hit = pieces.join(keyed.drop("n"), ["city", "district", "k", "piece"]).where(F.contains("addr_text", "name"))
    return hit.select("city", "district", F.col("name").alias("place_name"), "user_id")


def contained(texts: DataFrame, patterns: DataFrame) -> DataFrame:
    """(text_id, pattern_id): texts (text_id, text) that contain a pattern (pattern_id, pattern) anywhere.

    A pattern of three words or more is found by its longest inner word, which stands whole in every text around it; shorter
    ones by each place of a text. Both are equi-joins; the exact test follows. Nulls and empty patterns match nothing.
    """
    pat = patterns.where(F.length("pattern") > 0).withColumn("w", F.split("pattern", " "))
    long = pat.where(F.size("w") > 2).withColumn("inner", F.slice("w", F.lit(2), F.size("w") - 2))
    long = long.select("pattern_id", "pattern", F.array_max(F.transform("inner", lambda x: F.struct(F.length(x).alias("n"), x.alias("x"))))["x"].alias("key"))
    some = texts.where(F.col("text").isNotNull()).select("text_id", "text")
    by_word = some.select("text_id", "text", F.explode(F.array_distinct(F.split("text", " "))).alias("key")).join(long, "key")
    short = pat.where(F.size("w") <= 2).select("pattern_id", "pattern", F.length("pattern").alias("k"))
    places = F.explode(F.transform(F.sequence(F.lit(1), F.greatest(F.length("text") - F.col("k") + 1, F.lit(1))), lambda i: F.substr("text", i, F.col("k"))))
    by_place = some.crossJoin(F.broadcast(short.select("k").distinct())).select("text_id", "text", "k", places.alias("pattern")).distinct().join(short, ["k", "pattern"])
    hits = [x.where(F.contains("text", "pattern")).select("text_id", "pattern_id") for x in (by_word, by_place)]
    return hits[0].unionByName(hits[1]).distinct()


def page_text(html: Column) -> Column:
    """The text of a page: scripts, styles and tags become spaces, runs of white space one."""
    bare = F.regexp_replace(F.regexp_replace(html, r"(?is)<(script|style)\b.*?</\1\s*>", " "), r"(?s)<[^>]*>", " ")
    return F.trim(F.regexp_replace(bare, r"[ \t\r\n]+", " "))


def authors(written: DataFrame) -> DataFrame:
    """Distinct (city, district, place_name, user_id): a user counts once per name."""
    return written.select("city", "district", "place_name", "user_id").distinct()


def build(auth: DataFrame, pings: DataFrame, semantics: str = "multiset") -> DataFrame:
    """All pings of each name's authors; `set` keeps equal coordinates once."""
    points = auth.join(pings.select("user_id", "lat_u", "lon_u"), "user_id").select("city", "district", "place_name", "user_id", "lat_u", "lon_u")
    return points if semantics == "multiset" else points.dropDuplicates(["place_name", "lat_u", "lon_u"])


def user_partials(pings: DataFrame, *cell: str) -> DataFrame:
    """Per user (and raster cell): count and coordinate sums. Footprints add these up, so raw pings are shuffled once."""
    return pings.groupBy("user_id", *cell).agg(F.count(F.lit(1)).alias("n"), F.sum("lat_u").alias("lat_sum"), F.sum("lon_u").alias("lon_sum"))


def rollup(auth: DataFrame, partials: DataFrame, *cell: str) -> DataFrame:
    """Author sets and user partials to footprint totals per name (and cell)."""
    joined = auth.join(partials, "user_id")
    return joined.groupBy("city", "district", "place_name", *cell).agg(*[F.sum(c).alias(c) for c in ("n", "lat_sum", "lon_sum")])


def sizes(auth: DataFrame, pings: DataFrame) -> DataFrame:
    """Users, pings and distinct points per name; pings are reduced per user and point before they meet the author sets."""
    spots = pings.groupBy("user_id", "lat_u", "lon_u").agg(F.count(F.lit(1)).alias("n"))
    per_user = pings.groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))
    totals = auth.join(per_user, "user_id").groupBy("place_name").agg(F.count(F.lit(1)).alias("n_users"), F.sum("n").alias("n_pings"))
    points = auth.join(spots, "user_id").select("place_name", "lat_u", "lon_u").distinct().groupBy("place_name").agg(F.count(F.lit(1)).alias("n_points_distinct"))
    return totals.join(points, "place_name")

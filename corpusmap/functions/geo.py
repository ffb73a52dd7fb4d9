"""Where a page comes from: host, top-level domain, country; posts near cities."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: fixed values: country domains used commercially, and domains without a country
REPURPOSED = ("ai", "fm", "io", "ly", "ag", "tv")
NOT_GEOGRAPHIC = ("com", "net", "org", "info", "biz", "edu", "gov", "int", "mil")
EARTH_KM = 6371.0


def host(url: Column) -> Column:
    return F.regexp_extract(url, r"^[a-z]+://([^/:?#]+)", 1)


def tld(host_: Column) -> Column:
    """The last label; internationalised labels in their xn-- form; no label for an IP address."""
    last = F.lower(F.regexp_extract(host_, r"\.([^.]+)$", 1))
    return F.when(last.rlike(r"^[0-9]*$"), F.lit(None)).otherwise(last)


def normalise_tlds(names: list[str]) -> dict[str, str]:
    """Unicode labels to xn-- labels, on the distinct labels of a table of domains."""
    return {n: (n if n.isascii() else n.encode("idna").decode()) for n in names}


def with_country(pages: DataFrame, domains: DataFrame, url: str = "url", non_latin: bool = True) -> DataFrame:
    """Pages of usable country domains with their country; ``domains(tld, country, usable, script)`` is a fixed list of about 1,500 rows.

    A domain is met in both its forms, the Unicode label and the xn-- label.
    """
    usable = domains.filter("usable")
    if not non_latin:
        usable = usable.filter("script = 'Latin'")
    rows = usable.select("tld", "country").collect()  # the fixed list
    forms = sorted({(f, r["country"]) for r in rows for n in [r["tld"].lower()] for f in (n, normalise_tlds([n])[n], n.encode().decode("idna") if n.startswith("xn--") else n)})
    both = pages.sparkSession.createDataFrame(forms, usable.select("tld", "country").schema)
    return pages.withColumn("tld", tld(host(F.col(url)))).join(F.broadcast(both), "tld")


def drop_reason(tld_: Column) -> Column:
    return F.when(tld_.isNull(), "none").when(tld_.isin(*REPURPOSED), "repurposed").when(tld_.isin(*NOT_GEOGRAPHIC), "not geographic").otherwise("kept")


def cap_pages(pages: DataFrame, country: str, ceiling: int, key: str) -> DataFrame:
    """At most ``ceiling`` pages of each country, those whose hashed key comes first; one pass and a small table of rates.

    A filter at twice the needed rate comes before the ranking, so that no
    country is ranked as a whole.
    """
    from pyspark.sql.window import Window

    hashed = F.md5(F.col(key).cast("string"))
    counts = pages.groupBy(country).count().withColumn("rate", F.least(F.lit(1.0), (F.lit(2.0 * ceiling) + 50) / F.col("count"))).drop("count")
    unit = F.conv(F.substring(hashed, 1, 8), 16, 10).cast("double") / 4294967296.0
    some = pages.join(F.broadcast(counts), country).filter(unit < F.col("rate")).drop("rate")
    order = Window.partitionBy(country).orderBy(hashed, key)
    return some.withColumn("_n", F.row_number().over(order)).filter(F.col("_n") <= ceiling).drop("_n")


def haversine(lat1, lon1, lat2, lon2) -> Column:
    a = F.pow(F.sin(F.radians(lat2 - lat1) / 2), 2) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.pow(F.sin(F.radians(lon2 - lon1) / 2), 2)
    return 2 * EARTH_KM * F.asin(F.sqrt(F.least(a, F.lit(1.0))))


def within_radius(posts: DataFrame, cities: DataFrame, km: float = 50.0, mode: str = "grid") -> DataFrame:
    """Posts with the nearest city (``city_id, city_country, km``) no further than ``km``; ties go to the smaller city_id.

    The cities (some ten thousand) are laid on every grid cell that their
    circle touches and broadcast; a post meets those of its own cell.
    """
    c = cities.select("city_id", F.col("country").alias("city_country"), F.col("lat").alias("city_lat"), F.col("lon").alias("city_lon"))
    dist = haversine(F.col("lat"), F.col("lon"), F.col("city_lat"), F.col("city_lon"))
    if mode == "cross":
        met = posts.crossJoin(F.broadcast(c))
    else:
        step = math.degrees(km / EARTH_KM)
        far = F.abs("city_lat") + step
        reach = F.when(far >= 89.0, 180.0).otherwise(F.degrees(F.asin(F.least(F.lit(1.0), F.sin(F.lit(km / EARTH_KM)) / F.cos(F.radians("city_lat"))))))
        rows = F.sequence(F.floor((F.col("city_lat") - step) / step).cast("int"), F.floor((F.col("city_lat") + step) / step).cast("int"))
        n_lon = int(360 // step) + 1
        cols = F.when(reach >= 180, F.sequence(F.lit(0), F.lit(n_lon - 1))).otherwise(F.sequence(F.floor((F.col("city_lon") - reach + 180) / step).cast("int"), F.floor((F.col("city_lon") + reach + 180) / step).cast("int")))
        cells = c.withColumn("cell_lat", F.explode(rows)).withColumn("cell_lon", F.explode(cols)).withColumn("cell_lon", F.when(F.col("cell_lon") < 0, F.col("cell_lon") + n_lon).when(F.col("cell_lon") >= n_lon, F.col("cell_lon") - n_lon).otherwise(F.col("cell_lon")))
        wrap = cells.filter(F.col("cell_lon").isin(0, n_lon - 1)).withColumn("cell_lon", n_lon - 1 - F.col("cell_lon"))  # the last column is narrower
        cells = cells.union(wrap).distinct()
        own = posts.withColumn("cell_lat", F.floor(F.col("lat") / step).cast("int")).withColumn("cell_lon", F.floor((F.col("lon") + 180) / step).cast("int"))
        met = own.join(F.broadcast(cells), ["cell_lat", "cell_lon"]).drop("cell_lat", "cell_lon")
    met = met.withColumn("km", dist).filter(F.col("km") <= km)
    best = F.min_by(F.struct("city_id", "city_country", "km"), F.struct("km", "city_id")).alias("b")
    return met.groupBy(*posts.columns).agg(best).select(*posts.columns, "b.city_id", "b.city_country", "b.km")

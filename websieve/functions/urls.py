"""Parts and canonical form of URLs by regular expressions that Spark and SQL engines share."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SCHEME = r"^([a-zA-Z][a-zA-Z0-9+.-]*)://"
HOST = r"^[a-zA-Z][a-zA-Z0-9+.-]*://([^/?#:]*)"
PATH = r"^[a-zA-Z][a-zA-Z0-9+.-]*://[^/?#]*([^?#]*)"
QUERY = r"\?([^#]*)"


def scheme(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, SCHEME, 1))


def host(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, HOST, 1))


def path(url: Column) -> Column:
    return F.regexp_extract(url, PATH, 1)


def query(url: Column) -> Column:
    return F.regexp_extract(url, QUERY, 1)


def canonical(url: Column) -> Column:
    """Lower-case host without "www.", no scheme, fragment or closing slash; the query stays."""
    q = query(url)
    kept = F.concat(F.regexp_replace(host(url), r"^www\.", ""), F.regexp_replace(path(url), "/+$", ""))
    return F.when(q != "", F.concat(kept, F.lit("?"), q)).otherwise(kept)

"""Names, urls, markup and tokens as columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def namespace(term: Column) -> Column:
    """What stands before the last colon, slash or hash; empty if nothing does."""
    return F.regexp_extract(term, r"^(.*)[:/#][^:/#]*$", 1)


def local_name(term: Column) -> Column:
    return F.regexp_extract(term, r"([^:/#]*)$", 1)


def url_host(url: Column) -> Column:
    return F.regexp_extract(url, r"^[a-z]+://([^/?#]+)", 1)


def url_path(url: Column) -> Column:
    return F.regexp_extract(url, r"^[a-z]+://[^/?#]+([^?#]*)", 1)


def url_query(url: Column) -> Column:
    return F.regexp_extract(url, r"\?([^#]*)", 1)


def links(html: Column) -> Column:
    return F.regexp_extract_all(html, F.lit('href="([^"]*)"'), F.lit(1))


def page_language(html: Column) -> Column:
    return F.nullif(F.regexp_extract(html, 'lang="([^"]*)"', 1), F.lit(""))


def tokens(text: Column) -> Column:
    """Lower-case parts between spaces, tabs and line ends."""
    return F.filter(F.split(F.lower(text), "[ \t\n]+"), lambda w: w != "")

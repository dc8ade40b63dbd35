"""Items from text, addresses, JSON and times."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def tokens(docs: DataFrame, key: str = "doc_id", text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """key, pos, token: the lower-case runs of letters of each text, without empty ones."""
    return docs.select(*(keep or []), key, F.posexplode(F.split(F.lower(text), r"[^\p{L}]+")).alias("pos", "token")).where("token <> ''")


def url_host(url: str | Column) -> Column:
    """The host of an address, without user and port."""
    return F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1)


def url_path_prefix(url: str | Column, depth: int) -> Column:
    """Host and the first so many parts of the path."""
    path = F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://[^/?#]*(/[^?#]*)?", 1)
    return F.concat(url_host(url), F.substring_index(path, "/", depth + 1))


def utc(ts: str | Column) -> Column:
    """A timestamp without zone as one of the session's zone, which watermarks need."""
    return (F.col(ts) if isinstance(ts, str) else ts).cast("timestamp")


def bucket_time(ts: str | Column, grain: str) -> Column:
    """The start of the hour, day or month that a time lies in."""
    return F.date_trunc(grain, ts)


def json_item(props: str | Column, path: str) -> Column:
    return F.get_json_object(props, path)

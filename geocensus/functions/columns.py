"""Column expressions of detection, text preparation, MIME types and samples.  All run inside the JVM."""

from __future__ import annotations

import functools
import operator

from pyspark.sql import Column
from pyspark.sql import functions as F

from geocensus.functions.patterns import ADDRESSES, BARE_MASKS, COORDS, DECOYS, GATES, KEYED_MASKS, READ_AS_SHOWN

# The MIME types that are exclusively geospatial.
GEO_MIMES = (
    "application/geo+json", "application/gml+xml", "application/gpx+xml", "application/tcx+xml", "application/vnd.garmin.gpx+xml", "application/vnd.garmin.tcx+xml",
    "application/vnd.geo+json", "application/vnd.google-earth.gpx+xml", "application/vnd.google-earth.kml+xml", "application/vnd.google-earth.kmz", "application/vnd.openstreetmap.data+xml",
    "application/vnd.topografix.gpx+xml", "application/x-shapefile", "text/gpx+xml", "text/x-gpx+xml", "text/xml+georss",
)
OTHER_MIMES = ("text/html", "application/xhtml+xml", "application/pdf")
RELEASES = ("R2019", "R2021", "R2024")
# Top-level domains above one per cent of the published sample, with their country.
TLD_COUNTRY = (
    ("com", None), ("org", None), ("ru", "Russia"), ("de", "Germany"), ("net", None), ("uk", "United Kingdom"), ("jp", "Japan"), ("fr", "France"), ("it", "Italy"), ("nl", "Netherlands"),
    ("pl", "Poland"), ("br", "Brazil"), ("cn", "China"), ("au", "Australia"), ("edu", None),
)


def normal_mime(c: Column) -> Column:
    return F.lower(F.trim(F.element_at(F.split(c, ";"), 1)))


def is_geo_mime(c: Column) -> Column:
    """Whether a MIME type, parameters and case aside, is exclusively geospatial."""
    return normal_mime(c).isin(*GEO_MIMES)


def mime_from_url(url: Column) -> Column:
    """A type from the path's extension, for entries that lack one."""
    ext = F.lower(F.regexp_extract(F.regexp_extract(url, r"^[^?#]*", 0), r"\.([A-Za-z0-9]+)$", 1))
    known = {"geojson": "application/geo+json", "kml": "application/vnd.google-earth.kml+xml", "kmz": "application/vnd.google-earth.kmz", "gpx": "application/gpx+xml", "gml": "application/gml+xml", "tcx": "application/tcx+xml", "shp": "application/x-shapefile"}
    return functools.reduce(lambda c, kv: c.when(ext == kv[0], kv[1]), known.items(), F.when(F.lit(False), "")).otherwise(F.lit(None).cast("string"))


def host(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, "^[a-z]+://([^/?#:]+)", 1))


def tld(url: Column) -> Column:
    return F.element_at(F.split(host(url), r"\."), -1)


# Text preparation.


def soften_tags(html: Column) -> Column:
    """Tags become blanks; read the raw page as well for attributes and scripts."""
    return F.regexp_replace(html, "<[^>]{0,1000}>", " ")


ENTITIES = (("&deg;", "°"), ("&#176;", "°"), ("&prime;", "′"), ("&Prime;", "″"), ("&nbsp;", " "), ("&#160;", " "), ("&quot;", '"'), ("&#39;", "'"), ("&apos;", "'"), ("&lt;", "<"), ("&gt;", ">"), ("&amp;", "&"))


def decode_entities(c: Column) -> Column:
    for name, value in ENTITIES:
        c = F.replace(c, F.lit(name), F.lit(value))
    return c


def unescape_unicode(c: Column) -> Column:
    """``\\uXXXX`` escapes as characters; runs are decoded together, so surrogate pairs join."""
    runs = F.regexp_extract_all(c, F.lit(r"((?:\\u[0-9A-Fa-f]{4})+)"), F.lit(1))
    rest = F.split(c, r"(?:\\u[0-9A-Fa-f]{4})+", -1)
    made = F.transform(runs, lambda r: F.decode(F.unhex(F.replace(r, F.lit("\\u"), F.lit(""))), "UTF-16BE"))
    return F.array_join(F.zip_with(rest, made, lambda a, b: F.concat(a, F.coalesce(b, F.lit("")))), "")


def decode_url(c: Column) -> Column:
    return F.coalesce(F.try_url_decode(c), c)


def mask(c: Column, kinds: tuple[str, ...] = BARE_MASKS) -> Column:
    """Decoys as blanks; what a decoy's pattern consumes around it stays."""
    return functools.reduce(lambda x, k: F.regexp_replace(x, DECOYS[k], "$1 $2"), kinds, c)


def windows(c: Column, size: int, overlap: int) -> Column:
    """Windows of a long text with their starts; one for a text that fits."""
    step = size - overlap
    last = F.greatest(F.lit(0), F.ceil((F.length(c) - overlap) / step) - 1).cast("int")
    return F.transform(F.sequence(F.lit(0), last), lambda k: F.struct((k * step).alias("start"), F.substring(c, k * step + 1, F.lit(size)).alias("text")))


def n_tokens(c: Column, method: str = "word") -> Column:
    """Tokens by a proxy: words and punctuation marks, or four characters each."""
    return F.regexp_count(c, F.lit(r"[^ \t\r\n.,;:!?]+|[.,;:!?]")).cast("long") if method == "word" else F.ceil(F.length(c) / 4).cast("long")


# Detection.


def as_shown(html: Column) -> Column:
    """A page without tags and entities, as far as detection needs it."""
    return decode_entities(soften_tags(html))


def has_coord_format(text: Column, name: str) -> Column:
    """Whether a format occurs, apart from what must not count.  Masks are only made where the raw text has the format."""
    pattern = COORDS[name]
    masks = BARE_MASKS if name == "c1_bare_pair" else KEYED_MASKS
    found = text.rlike(pattern) & mask(text, masks).rlike(pattern)
    if name in READ_AS_SHOWN:
        found = found | as_shown(text).rlike(pattern)
    return F.when(text.rlike(GATES[name]), found).otherwise(False) if name in GATES else found


def has_coords(text: Column, formats: tuple[str, ...] = tuple(COORDS)) -> Column:
    """Any coordinate.  A text without a digit is not looked at; formats are tried until one is found."""
    found = functools.reduce(operator.or_, [has_coord_format(text, f) for f in formats])
    return F.coalesce(F.when(text.rlike(r"[0-9]"), found), F.lit(False))


def has_address_format(text: Column, name: str) -> Column:
    found = text.rlike(ADDRESSES[name])
    return F.when(text.rlike(GATES[name]), found).otherwise(False) if name in GATES else found


def has_address(text: Column, formats: tuple[str, ...] = tuple(ADDRESSES)) -> Column:
    return F.coalesce(functools.reduce(operator.or_, [has_address_format(text, f) for f in formats]), F.lit(False))


def evidence(text: Column) -> Column:
    """All matches: kind, format and raw text, as an array."""
    none = F.array().cast("array<struct<kind:string,format:string,raw:string>>")

    def part(kind: str, name: str, pattern: str) -> Column:
        seen = mask(text, BARE_MASKS if name == "c1_bare_pair" else KEYED_MASKS) if kind == "coord" else text
        raw = F.regexp_extract_all(seen, F.lit(pattern), F.lit(0))
        return F.transform(raw, lambda r: F.struct(F.lit(kind).alias("kind"), F.lit(name).alias("format"), r.alias("raw")))

    both = [part("coord", k, v) for k, v in COORDS.items()] + [part("address", k, v) for k, v in ADDRESSES.items()]
    return F.coalesce(F.concat(*both), none)


def first_example(text: Column, kind: str) -> Column:
    """The first match of the first format of a kind that occurs, or null."""
    pats = COORDS if kind == "coord" else ADDRESSES
    has = has_coord_format if kind == "coord" else has_address_format
    return F.coalesce(*[F.when(has(text, k), F.nullif(F.regexp_extract(text, v, 0), F.lit(""))) for k, v in pats.items()])


# Spatial helpers.


def haversine_km(lat1: Column, lon1: Column, lat2: Column, lon2: Column) -> Column:
    a = F.pow(F.sin(F.radians(lat2 - lat1) / 2), 2) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.pow(F.sin(F.radians(lon2 - lon1) / 2), 2)
    return F.lit(2 * 6371.0088) * F.asin(F.sqrt(a))


def order_key(seed: str, *ids: str) -> Column:
    """A random order that any engine reproduces."""
    return F.md5(F.concat_ws("|", F.lit(seed), *[F.col(c).cast("string") for c in ids]))


def bucket(seed: str, id_col: str, buckets: int = 1000) -> Column:
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), F.col(id_col).cast("string"))), 1, 8), 16, 10).cast("long") % buckets

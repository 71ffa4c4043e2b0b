"""Patterns of coordinates, addresses and decoys, in the subset that Java's engine and RE2 read alike.

No look-around, no word boundaries, no unbounded repetition above 1,000; boundaries are consumed characters.
"""

from __future__ import annotations

_LAT = r"-?(?:90\.0{3,}|[0-8]?[0-9]\.[0-9]{3,12})"
_LON = r"-?(?:180\.0{3,}|(?:1[0-7][0-9]|[0-9]?[0-9])\.[0-9]{3,15})"
_NUM = r"-?[0-9]{1,3}(?:\.[0-9]{1,15})?"
_DMS = r"[0-9]{1,3}°[ ]?[0-9]{1,2}['′][ ]?[0-9]{1,2}(?:[.,][0-9]{1,6})?(?:''|\"|″)"
_STREET = "Street|St|Avenue|Ave|Road|Rd|Lane|Ln|Drive|Dr|Boulevard|Blvd|Square|Court|Crescent|Terrace|Way"
_POSTCODE = "[A-Z]{1,2}[0-9]{1,2}[A-Z]?[ ][0-9][A-Z]{2}"
_LAT_KEY = rf"[Ll]at(?:itude)?[\"']?[ ]?[:=][ ]?[\"']?{_NUM}"
_LON_KEY = rf"[Ll](?:on|ng)(?:gitude)?[\"']?[ ]?[:=][ ]?[\"']?{_NUM}"


def _meta(name: str) -> str:
    return rf"<meta[^>]{{1,80}}{name}[\"'][^>]{{0,40}}content=[\"']{_NUM}"


#: Coordinate formats.  Bare pairs are range-checked by the pattern itself; keyed and labelled pairs are not.
COORDS = {
    "c1_bare_pair": rf"(?:^|[^0-9A-Za-z.,+-]){_LAT}(?:[ ]?[,;][ ]?|[ ]){_LON}(?:$|[^0-9A-Za-z.])",
    "c2_constructor": rf"(?:(?:LatLng|latLng|LngLat|GeoPoint)\([ ]?\[?|Marker\([ ]?\[){_NUM}[ ]?,[ ]?{_NUM}",
    "c3_dms_after": rf"{_DMS}[ ]?[NS][^0-9]{{1,12}}{_DMS}[ ]?[EWO]",
    "c4_dms_before": rf"[NS][ ]?{_DMS}[^0-9]{{0,6}}[EWO][ ]?{_DMS}",
    "c5_meta": rf"(?:<meta[^>]{{1,80}}(?:geo\.position|ICBM)[^>]{{1,40}}content=[\"']{_NUM}[ ]?[;,][ ]?{_NUM}|{_meta('latitude')}[\"'][^<]{{0,40}}{_meta('longitude')}|{_meta('longitude')}[\"'][^<]{{0,40}}{_meta('latitude')})",
    "c6_keys": rf"(?:{_LAT_KEY}[\"']?[ \t\r\n,;&]{{1,8}}[\"']?{_LON_KEY}|{_LON_KEY}[\"']?[ \t\r\n,;&]{{1,8}}[\"']?{_LAT_KEY})",
    "c7_grid_id": r"27700[^0-9]{1,40}[\"']?x[\"']?[ ]?:[ ]?[0-9]{4,6}(?:\.[0-9]{1,15})?[ \t\r\n,]{1,8}[\"']?y[\"']?[ ]?:[ ]?[0-9]{4,7}",
    "c8_easting": r"[Ee]asting[ :=]{1,3}[0-9]{5,6}[^0-9]{1,20}[Nn]orthing[ :=]{1,3}[0-9]{5,7}",
    "c9_map_link": r"href=[\"'][^\"'<> ]{0,60}map[^\"'<> ]{0,80}(?:@|ll=|q=|!3d)-?[0-9]{1,2}\.[0-9]{3,12}(?:,|%2C|!4d)-?[0-9]{1,3}\.[0-9]{3,12}",
    "c10_embed": r"<iframe[^>]{0,80}src=[\"'][^\"'<> ]{0,60}map[^\"'<> ]{0,80}(?:@|ll=|q=|!2d|!3d)-?[0-9]{1,3}\.[0-9]{3,12}(?:,|%2C|!3d|!4d)-?[0-9]{1,3}\.[0-9]{3,12}",
    "c11_xml_point": rf"(?:<lat>{_NUM}</lat>[ \t\r\n]{{0,8}}<lon>{_NUM}|<gml:pos>{_NUM}[ ]{_NUM}|POINT[ ]?\({_NUM}[ ]{_NUM}\)|[\"']coordinates[\"'][ ]?:[ ]?\[{_NUM}[ ]?,[ ]?{_NUM})",
}
#: Address formats.
ADDRESSES = {
    "a1_number_street": rf"(?:^|[^0-9A-Za-z])[0-9]{{1,5}}[A-Za-z]?[ ](?:[A-Z][a-z]{{1,20}}[ ]){{1,3}}(?:{_STREET})(?:$|[^A-Za-z])",
    "a2_floor": r"(?:[A-Z][a-záéíóúñ]{2,20}[ ]){1,3}[0-9]{1,5},[ ]?[0-9]{1,2}[ ]?(?:piso|º piso)",
    "a3_microdata_content": r"itemprop=[\"'](?:address|streetAddress)[\"'][ ]content=[\"'][^\"'<>]{0,40}[0-9][^\"'<>]{0,60}[\"']",
    "a4_postal_object": r"[\"']streetAddress[\"'][ ]?:[ ]?[\"'][^\"']{3,80}[\"']",
    "a5_microdata_spans": r"itemprop=[\"']streetAddress[\"']>[^<]{0,40}[0-9][^<]{0,40}<",
    "a6_pipes": rf"[A-Z][A-Za-z ]{{2,40}}[ ]\|[ ][A-Z][A-Za-z ]{{1,30}}(?:{_STREET})[ ]\|[^|<>]{{2,40}}\|[ ]{_POSTCODE}",
    "a7_map_query": r"map[^\"'<> ]{0,60}q=(?:[0-9]{1,5})?\+?[A-Z][^\"'<>& ]{0,40}\+[^\"'<>& ]{0,40}\+[^\"'<>& ]{2,40}",
    "a8_escaped": r"(?:(?:\\u0443\\u043b\\u0438\\u0446\\u0430|\\u043f\\u0435\\u0440\\u0435\\u0443\\u043b\\u043e\\u043a|\\u043f\\u0440\\u043e\\u0441\\u043f\\u0435\\u043a\\u0442)[^\"'<>]{0,80}[ ][0-9]{1,4}"
    r"|(?:улица|ул\.|переулок|проспект|площадь|[Οο]δός|[Λλ]εωφόρος)[ ][^\"'<>\n]{0,60}[ ][0-9]{1,4}|[Ѐ-ӿ]{2,20}[ ](?:улица|переулок|проспект|площадь),?[ ][0-9]{1,4}"
    r"|[一-龥]{1,10}(?:路|街|大道)[0-9]{1,5}[号號]|[一-龥]{1,8}[区市][一-龥]{0,8}[0-9]{1,4}(?:丁目|番地|-[0-9]{1,4}))",
    "a9_landmark_city": r"(?:Tower|Museum|House|Palace|Bridge|Cathedral|Theatre),?[ ][A-Z][a-z]{2,20},?[ ][A-Z]{2}(?:$|[^A-Za-z])",
    "a10_upper_block": rf"[A-Z][A-Z ]{{3,30}}\n[A-Z][A-Z ]{{2,30}}(?:ROAD|STREET|LANE|AVENUE)\n[A-Z ]{{3,30}}\n[A-Z ]{{0,20}}{_POSTCODE}",
    "a11_number_after": r"(?:[A-Z][a-zäöüß]{2,20}(?:straße|strasse|weg|platz|gasse)[ ][0-9]{1,4}|[0-9]{1,4},?[ ](?:rue|avenue|place)[ ](?:de |du |des |la ){0,2}[A-Z][a-zéèê]{2,20}|(?:Calle|Avenida|Plaza)[ ](?:de |del |la ){0,2}[A-Z][a-záéíóúñ]{2,20},?[ ][0-9]{1,4})",
    "a12_filler": rf"[0-9]{{1,5}}[ ][A-Z][a-z]{{1,20}}[ ](?:{_STREET})<br[ ]?/?>[A-Z][A-Za-z ]{{2,30}},[ ][A-Z]{{2}}",
}
_ZERO = r"-?0(?:\.0{1,9})?"
_ZLAT = rf"[Ll]at(?:itude)?[\"']?[ ]?[:=][ ]?[\"']?{_ZERO}"
_ZLON = rf"[Ll](?:on|ng)(?:gitude)?[\"']?[ ]?[:=][ ]?[\"']?{_ZERO}"
_BETWEEN = r"[\"']?[ \t\r\n,;&]{1,8}[\"']?"
#: What must not count.  Where a mark ends at a character that it consumes, the pattern keeps it as its last group.
DECOYS = {
    "zero": rf"(^|[^0-9A-Za-z.]){_ZERO}(?:[ ]?[,;][ ]?|[ ]){_ZERO}($|[^0-9.])",
    "zero_keys": rf"()(?:{_ZLAT}{_BETWEEN}{_ZLON}|{_ZLON}{_BETWEEN}{_ZLAT}|<lat>{_ZERO}</lat>[ \t\r\n]{{0,8}}<lon>{_ZERO})($|[^0-9.])",
    "celestial": r"(^|[^A-Za-z])(?:RA[ :=]{1,3}[0-9]{1,3}[0-9 .:hms'°]{0,24}[ ,;]{1,3}Dec[ :=]{1,3}[+-]?[0-9]{1,3}[0-9 .:d'\"°]{0,24}|[Rr]ight ascension[ :=]{1,3}[0-9]{1,3}[0-9 .:hms'°]{0,24}(?:[ ,;]{1,3}(?:and )?declination[ :=]{1,3}[+-]?[0-9]{1,3}[0-9 .:d'\"°]{0,24})?)($|[^0-9])",
    "quantity": r"(^|[^A-Za-z])(?:[Pp]rices?|[Vv]ersions?|[Rr]atios?|[Ss]cores?|[Rr]ates?|[Cc]osts?|[Ww]eights?)[ :=]{1,3}[$€£]?[0-9]{1,6}\.[0-9]{1,9}(?:[ ]?[,;][ ]?[$€£]?[0-9]{1,6}\.[0-9]{1,9})?($|[^0-9.])",
    "ipv4": r"()[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}()",
    "phone": r"()\+[0-9][0-9 ().-]{8,20}()",
}
#: Masks for bare pairs, and for all other formats.
BARE_MASKS, KEYED_MASKS = tuple(DECOYS), ("zero", "zero_keys")
#: A cheap look for what each format cannot do without; a format is only tried where its gate holds.
GATES = {
    "c2_constructor": r"Lng|LngLat|GeoPoint|Marker", "c3_dms_after": "°|&deg;|&#176;", "c4_dms_before": "°|&deg;|&#176;", "c5_meta": "<meta", "c6_keys": r"[Ll](?:on|ng)(?:gitude)?[\"']?[ ]?[:=]", "c7_grid_id": "27700", "c8_easting": "asting",
    "c9_map_link": "href=", "c10_embed": "<iframe", "c11_xml_point": "<lat>|<gml:pos>|POINT|coordinates", "a2_floor": "piso", "a3_microdata_content": "itemprop=", "a4_postal_object": "streetAddress", "a5_microdata_spans": "itemprop=", "a6_pipes": r"\|",
    "a7_map_query": "q=", "a10_upper_block": r"(?:ROAD|STREET|LANE|AVENUE)\n", "a12_filler": "<br",
}
#: Formats whose parts a page may split by tags or write as entities: they are sought in the page as read, too.
READ_AS_SHOWN = ("c3_dms_after", "c4_dms_before")
#: The widest baseline: any decimal number.
ANY_DECIMAL = r"[0-9]{1,3}\.[0-9]+"
#: Pairs without ranges, least decimals or masks.
ANY_PAIR = r"-?[0-9]{1,3}\.[0-9]+[ ]?[,; ][ ]?-?[0-9]{1,3}\.[0-9]+"
#: Words whose presence is a cheap reason to look closer at addresses.
KEYWORDS = ("street", "avenue", "road", "latitude", "longitude", "postcode", "address")
LICENCE = r"[Vv]ersion [0-9]+\.[0-9]+"

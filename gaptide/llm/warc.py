"""WARC derivatives: response records, and the metadata and plain-text conversion records that refer to them.

Everything is DataFrame functions. Record ids follow from the page's id and address, so reruns agree; digests are SHA-256,
labelled as the format asks. A conversion's text is the page without comments, scripts, styles and tags, block tags
ending a line, with character references decoded.

Where a table keeps the source's own status line and header lines, or its fetch times, columns with them can be named: the
lines are kept in the response as they are, and the metadata and conversion records bear the same date. A table without them
(such as one of id, address and page) gets a plain 200 response and one given date.

Cases: null html is an empty page; a null url is an empty target; null headers or dates fall back on the plain ones; null ids
share the empty id; repeated rows repeat their records; an empty table gives an empty table; pages of any length are read
whole; extra columns aren't read, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

CRLF = "\r\n"
#: Element names that end a line, and the named references that are decoded.
BLOCKS = "p|div|br|hr|li|ul|ol|dl|dt|dd|h[1-6]|tr|td|th|table|article|section|nav|aside|header|footer|main|title|head|body|html|form|pre|blockquote"
NAMED = {"nbsp": " ", "lt": "<", "gt": ">", "quot": '"', "apos": "'"}


def plain_text(html: Column) -> Column:
    t = F.regexp_replace(html, "(?s)<!--.*?-->", "")
    t = F.regexp_replace(t, r"(?is)<script\b[^>]*>.*?</script\s*>", "")
    t = F.regexp_replace(t, r"(?is)<style\b[^>]*>.*?</style\s*>", "")
    t = F.regexp_replace(t, rf"(?i)</?(?:{BLOCKS})\b[^>]*>", "\n")
    t = F.regexp_replace(t, "<[a-zA-Z/!?][^>]*>", "")
    for name, c in NAMED.items():
        t = F.replace(t, F.lit(f"&{name};"), F.lit(c))
    t = decoded(t)
    t = F.replace(t, F.lit("&amp;"), F.lit("&"))
    t = F.regexp_replace(t, r"[ \t\r\f]+", " ")
    t = F.regexp_replace(t, r" ?\n[ \n]*", "\n")
    return F.regexp_replace(F.regexp_replace(t, r"^[ \n]+", ""), r"[ \n]+$", "")


def decoded(t: Column) -> Column:
    """Numeric references: the parts after each mark begin with a number and a semicolon, or are left as they were."""
    parts = F.split(t, "&#")

    def one(p: Column) -> Column:
        digits = F.regexp_extract(p, "^([0-9]{1,7});", 1)
        hexes = F.regexp_extract(p, "^[xX]([0-9a-fA-F]{1,6});", 1)
        code = F.when(digits != "", F.expr("0").cast("long") + F.when(digits != "", digits).cast("long")).when(hexes != "", F.conv(hexes, 16, 10).cast("long"))
        good = code.isNotNull() & (code > 0) & (code < 0x110000) & ~code.between(0xD800, 0xDFFF)
        letter = F.decode(F.unhex(F.lpad(F.hex(F.when(good, code)), 8, "0")), "UTF-32")
        return F.when(good, F.concat(letter, F.regexp_replace(p, "^[0-9a-fA-FxX]{1,7};", ""))).otherwise(F.concat(F.lit("&#"), p))

    rest = F.when(F.size(parts) > 1, F.transform(F.slice(parts, 2, 1 << 30), one)).otherwise(F.array().cast("array<string>"))
    return F.concat(F.element_at(parts, 1), F.concat_ws("", rest))


def urn(kind: str, page: Column, url: Column) -> Column:
    h = F.md5(F.concat(F.lit(f"{kind}:"), page, F.lit(":"), url))
    return F.concat(F.lit("<urn:uuid:"), *[x for a, n in ((1, 8), (9, 4), (13, 4), (17, 4), (21, 12)) for x in ([F.lit("-")] if a > 1 else []) + [F.substring(h, a, n)]], F.lit(">"))


def digest(x: Column) -> Column:
    return F.concat(F.lit("sha256:"), F.sha2(x.cast("binary"), 256))


def title(html: Column) -> Column:
    return F.regexp_replace(F.regexp_extract(html, r"(?is)<title[^>]*>(.*?)</title", 1), r"[\r\n\t]+", " ")


def derive(pages: DataFrame, date: str = "2024-01-01T00:00:00Z", key: str = "page_id", url: str = "url", html: str = "html", headers: str | None = None, fetched: str | None = None) -> DataFrame:
    """key, kind, record_id, refers_to, target_uri, block_digest, payload_digest, content_type, content_length, block: three records for each page."""
    page, target, body = F.coalesce(F.col(key).cast("string"), F.lit("")), F.coalesce(F.col(url).cast("string"), F.lit("")), F.coalesce(F.col(html).cast("string"), F.lit(""))
    lines = F.regexp_replace(F.regexp_replace(F.col(headers).cast("string"), r"[\r\n]+$", ""), "\r?\n", CRLF) if headers else F.lit(None).cast("string")
    when = F.coalesce(F.date_format(F.col(fetched).cast("timestamp"), "yyyy-MM-dd'T'HH:mm:ss'Z'"), F.lit(date)) if fetched else F.lit(date)
    rows = pages.select(F.col(key), page.alias("page"), target.alias("target"), body.alias("body"), lines.alias("lines"), when.alias("date"))
    rows = rows.withColumn("plain", plain_text(F.col("body"))).withColumn("payload", digest(F.col("body")))
    b = F.col("body")
    plain_head = F.concat(F.lit(f"HTTP/1.1 200 OK{CRLF}Content-Type: text/html; charset=utf-8{CRLF}Content-Length: "), F.octet_length(b).cast("string"))
    http = F.concat(F.coalesce(F.col("lines"), plain_head), F.lit(CRLF * 2), b)
    fields = F.concat(F.lit("title: "), title(b), F.lit(f"{CRLF}outlinks: "), F.regexp_count(b, F.lit(r"(?i)<a\b[^>]*\bhref")).cast("string"), F.lit(f"{CRLF}source-length: "), F.octet_length(b).cast("string"), F.lit(f"{CRLF}text-length: "), F.octet_length("plain").cast("string"), F.lit(f"{CRLF}source-payload-digest: "), F.col("payload"), F.lit(CRLF))
    source = urn("response", F.col("page"), F.col("target"))
    record = lambda kind, refers, mime, block, payload: F.struct(F.lit(kind).alias("kind"), urn(kind, F.col("page"), F.col("target")).alias("record_id"), refers.alias("refers_to"), F.lit(mime).alias("content_type"), payload.alias("payload_digest"), block.alias("block"))
    three = F.array(
        record("response", F.lit(None).cast("string"), "application/http; msgtype=response", http, F.col("payload")),
        record("metadata", source, "application/warc-fields", fields, F.col("payload")),
        record("conversion", source, "text/plain", F.col("plain"), F.col("payload")),
    )
    rows = rows.select(key, "target", "date", F.explode(three).alias("r"))
    return rows.select(key, "r.kind", "r.record_id", "r.refers_to", F.col("target").alias("target_uri"), "date", "r.content_type", F.octet_length("r.block").cast("long").alias("content_length"), digest(F.col("r.block")).alias("block_digest"), "r.payload_digest", "r.block")


def serialised(records: DataFrame) -> DataFrame:
    """records with `record`: the whole record as WARC/1.1 bytes, ready to be written one after another."""
    line = lambda name, value: F.when(value.isNotNull(), F.concat(F.lit(f"{name}: "), value, F.lit(CRLF))).otherwise("")
    c = F.col
    head = F.concat(
        F.lit(f"WARC/1.1{CRLF}"), line("WARC-Type", c("kind")), line("WARC-Record-ID", c("record_id")), line("WARC-Date", c("date")), line("WARC-Target-URI", c("target_uri")), line("WARC-Refers-To", c("refers_to")),
        F.when(c("kind") == "response", line("WARC-Payload-Digest", c("payload_digest"))).otherwise(line("WARC-Source-Payload-Digest", c("payload_digest"))), line("WARC-Block-Digest", c("block_digest")), line("Content-Type", c("content_type")), line("Content-Length", c("content_length").cast("string")), F.lit(CRLF),
    )
    return records.withColumn("record", F.concat(head, c("block"), F.lit(CRLF * 2)).cast("binary"))

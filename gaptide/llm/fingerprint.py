"""Homomorphic multiset fingerprints of documents.

A document is a multiset of paragraphs: lines, and within a line sentences. Each paragraph is hashed to a wide vector of
whole numbers; the document's fingerprint is their number and their sum, lane by lane, modulo a power of two. So the
order of paragraphs doesn't matter, and adding or taking away a paragraph adds or subtracts its vector.

A paragraph that comes m times weighs m * m in a mean square of such sums. So a second sum goes with them, which makes the
occurrences of a paragraph different ones: for the k-th repetition, the lanes of the paragraph and k, less those of the
paragraph. Differences of the two sums together are sums over the occurrences that only one document has, so their mean
square estimates how many those are: likeness is 1 minus that number over the paragraphs of both, from 0 to 1.
Fingerprints (number and first sums) of any documents may be added; second sums only of documents without a paragraph in
common, as otherwise repetitions across the two weigh as squares.

Plans are DataFrame functions only: a paragraph's lanes are hashes of two 64-bit hashes of it.

Cases: null text is the empty text; two empty texts are alike (1); equal texts have equal fingerprints; rows with one
doc_id come in the order of their texts; null doc_ids come after all others, by descending hash of their texts; the last document is followed by the first,
a single one by itself; an empty table gives an empty table; extra columns aren't read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: A word of the vector holds two lanes: 16-bit hashes, summed in fields of 32 and 30 bits. The sum of a whole word modulo
#: 2**62 is what is kept; a difference gives both lanes back as signed numbers.
WORDS, LANE_BITS, POWER = 32, 16, 62
LANES = 2 * WORDS
MASK = 2**POWER - 1
FIELDS = (2**LANE_BITS - 1) << 32 | (2**LANE_BITS - 1)
MIDDLE = (2**LANE_BITS - 1) / 2
SPREAD = (4.0**LANE_BITS - 1) / 12  # variance of a lane's hash
PIECE = 6
#: Most buckets that neighbours are sought in; their bounds are all that the driver holds.
MOST_BUCKETS = 131072


def paragraphs(text: Column) -> Column:
    """Lines, sentences within them, and of a long sentence pieces of six words."""
    marked = F.regexp_replace(F.regexp_replace(text, "([.!?]) ", "$1\n"), f"((?:[^ \n]+ ){{{PIECE}}})", "$1\n")
    return F.filter(F.split(marked, "\n"), lambda p: p != "")


def _bound(value: Column, body) -> Column:
    """body of the value, which is made once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _words(c: Column, i: Column) -> Column:
    return F.xxhash64(c, i).bitwiseAND(F.lit(FIELDS))


def _repeats(hashes: Column) -> Column:
    """An array of (hash, k) for each k-th repetition, k from 1, of the hashes that come more than once."""

    def runs(s: Column) -> Column:
        at = F.sequence(F.lit(0), F.size(s) - 1)
        like = lambda i, j: F.coalesce(F.get(s, i) == F.get(s, j), F.lit(False))
        heads, tails = F.filter(at, lambda i: like(i, i + 1) & ~like(i, i - 1)), F.filter(at, lambda i: like(i, i - 1) & ~like(i, i + 1))
        return F.flatten(F.zip_with(heads, tails, lambda h, t: F.transform(F.sequence(F.lit(1), t - h), lambda k: F.struct(F.get(s, h).alias("h"), k.cast("long").alias("k")))))

    none = F.array().cast("array<struct<h:bigint,k:bigint>>")
    return F.when(F.size(F.array_distinct(hashes)) == F.size(hashes), none).otherwise(_bound(F.sort_array(hashes), runs))


def vector(text: Column) -> Column:
    """Number of paragraphs, the sum of a plain hash of each, then the words of two lanes, then as many words that tell repetitions apart."""
    mask = F.lit(MASK)
    seeds = F.array(*[F.lit(i).cast("long") for i in range(1, WORDS + 1)])
    parts = paragraphs(text)
    zero = F.array(*[F.lit(0).cast("long")] * WORDS)

    def sums(hashes: Column) -> Column:
        lanes = F.aggregate(hashes, zero, lambda acc, c: F.zip_with(acc, seeds, lambda s, i: s.bitwiseAND(mask) + _words(c, i)))
        apart = F.aggregate(_repeats(hashes), zero, lambda acc, r: F.zip_with(acc, seeds, lambda s, i: s.bitwiseAND(mask) + _words(F.xxhash64(r["h"], r["k"]), i) - _words(r["h"], i)))
        return F.concat(lanes, apart)

    plain = F.aggregate(parts, F.lit(0).cast("long"), lambda s, p: s.bitwiseAND(mask) + F.xxhash64(F.lit(WORDS), p).bitwiseAND(mask))
    return F.transform(F.concat(F.array(F.size(parts).cast("long"), plain), _bound(F.transform(parts, lambda p: F.xxhash64(p)), sums)), lambda x: x.bitwiseAND(mask))


def fingerprint(v: Column) -> Column:
    """The words of a vector that any two documents' may be added by."""
    return F.slice(v, 1, 2 + WORDS)


def printed(v: Column) -> Column:
    return F.concat_ws("", F.transform(v, lambda x: F.lpad(F.lower(F.hex(x)), 16, "0")))


def add(a: Column, b: Column) -> Column:
    """Fingerprint vector of two documents' paragraphs together."""
    return F.zip_with(a, b, lambda x, y: (x + y).bitwiseAND(F.lit(MASK)))


def remove(a: Column, b: Column) -> Column:
    """Fingerprint vector of a's paragraphs without b's."""
    return F.zip_with(a, b, lambda x, y: (x - y).bitwiseAND(F.lit(MASK)))


def likeness(a: Column, b: Column) -> Column:
    """From two vectors. A lane of the difference, less the mean of so many hashes, is read as the number of least size that it can be."""
    many = F.element_at(a, 1) - F.element_at(b, 1)
    both = (F.element_at(a, 1) + F.element_at(b, 1)).cast("double")
    centre = (many * F.lit(2**LANE_BITS - 1)).cast("long")  # twice the mean

    def near(x: Column, bits: int) -> Column:
        half = F.lit(2 ** (bits - 1))
        return (x + half).bitwiseAND(F.lit(2**bits - 1)) - half

    def squares(x: Column, y: Column) -> Column:
        d = (x - y).bitwiseAND(F.lit(MASK))
        low = near(d - F.floor(centre / 2), 32) + F.floor(centre / 2)
        high = near(F.shiftright(near(d - low, POWER), 32) - F.floor(centre / 2), POWER - 32) + F.floor(centre / 2)
        l, h = (2 * low - centre).cast("double") / 2, (2 * high - centre).cast("double") / 2
        return l * l + h * h

    told = lambda v: F.zip_with(F.slice(v, 3, WORDS), F.slice(v, 3 + WORDS, WORDS), lambda x, y: x + y)
    square = F.aggregate(F.zip_with(told(a), told(b), squares), F.lit(0.0), lambda s, x: s + x)
    apart = square / (LANES * SPREAD)
    return F.when(both == 0, F.lit(1.0)).otherwise(F.greatest(F.lit(0.0), F.least(F.lit(1.0), 1.0 - apart / both)))


def fingerprints(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, text, vector."""
    body = F.coalesce(F.col(text).cast("string"), F.lit(""))
    return docs.select(key, body.alias("text")).withColumn("vector", vector(F.col("text")))


def _longs(values: list) -> Column:
    """An array of whole numbers or nulls as one constant, however many they are."""
    return F.split(F.lit(",".join("" if v is None else str(v) for v in values)), ",").cast("array<bigint>") if values else F.array().cast("array<bigint>")


def _bounds(ids: DataFrame, n: int, rows_in_bucket: int) -> tuple[list, list]:
    """First and last key of each bucket, in order: the ends of range partitions of the keys alone."""
    parts = max(1, min(MOST_BUCKETS, n // rows_in_bucket))
    ends = ids.where("k is not null").repartitionByRange(parts, "k").groupBy(F.spark_partition_id().alias("p")).agg(F.min("k").alias("lo"), F.max("k").alias("hi"))
    found = sorted((r["lo"], r["hi"]) for r in ends.select("lo", "hi").where("lo is not null").collect())
    return [x for x, _ in found], [y for _, y in found]


def _place(k: Column, lows: list) -> Column:
    """Index of the bucket of a key: a search among groups of bounds, then within one."""
    step = max(1, int(len(lows) ** 0.5))
    group = F.greatest(F.lit(1), F.size(F.filter(_longs(lows[::step]), lambda b: b <= k)))
    inner = F.size(F.filter(F.slice(_longs(lows), (group - 1) * step + 1, step), lambda b: b <= k))
    return F.greatest((group - 1) * step + inner - 1, F.lit(0))


def _keyless(docs: DataFrame, n: int, rows_in_bucket: int) -> tuple[Column, list, list]:
    """Cell of a row without a key, by ranges of its text's hash; the cells that hold rows, and the greatest hash of each."""
    parts = max(1, min(MOST_BUCKETS, n // rows_in_bucket))
    cell = F.floor((F.shiftright(F.col("h"), 32) + F.lit(1 << 31)) * F.lit(parts) / F.lit(1 << 32)).cast("int")
    tops = sorted((r["c"], r["top"]) for r in docs.where("k is null").groupBy(cell.alias("c")).agg(F.max("h").alias("top")).collect())
    return cell, [c for c, _ in tops], [t for _, t in tops]


def with_next(docs: DataFrame, key: str = "doc_id", rows_in_bucket: int = 400) -> DataFrame:
    """Each row of fingerprints() with next_text and next_vector of the document that follows in descending key, the first after the last.

    Texts are shuffled once, by ranges of the key (of the text's hash, where there is no key); the first rows of a range go
    to the range before it too.
    """
    hashed = docs.withColumn("h", F.when(F.col(key).isNull(), F.xxhash64("text")))
    counts = docs.agg(F.count(F.lit(1)).alias("n"), F.count(key).alias("keyed")).first()
    lows, highs = _bounds(docs.select(F.col(key).alias("k")), counts["keyed"], rows_in_bucket) if counts["keyed"] else ([], [])
    place, first, n, below = _place(F.col(key), lows), F.col(key), len(lows), 0
    tops = highs
    if counts["n"] > counts["keyed"]:
        cell, cells, heads = _keyless(docs.select(F.col(key).alias("k"), F.xxhash64("text").alias("h")), counts["n"] - counts["keyed"], rows_in_bucket)
        below = len(cells)
        place = F.when(F.col(key).isNull(), F.array_position(_longs(cells), cell.cast("bigint")).cast("int") - 1).otherwise(place + below)
        first, tops, n = F.coalesce(F.col(key), F.col("h")), heads + highs, n + below
    placed = hashed.withColumn("bucket", place)
    here, there = F.struct(F.col("bucket").alias("b"), F.lit(False).alias("guest")), F.struct(F.pmod(F.col("bucket") + 1, F.lit(max(n, 1))).alias("b"), F.lit(True).alias("guest"))
    copies = F.when(first == F.get(_longs(tops), F.col("bucket")), F.array(here, there)).otherwise(F.array(here))
    rows = placed.select("*", F.explode(copies).alias("c")).select(key, "text", "vector", "h", F.col("c.b").alias("b"), F.col("c.guest").alias("guest"))
    order = W.partitionBy("b").orderBy("guest", F.col(key).desc_nulls_last(), F.col("h").desc(), "text")
    nxt = F.lead(F.struct("text", "vector")).over(order)
    return rows.withColumn("nxt", nxt).where(~F.col("guest")).select(key, "text", "vector", F.col("nxt.text").alias("next_text"), F.col("nxt.vector").alias("next_vector"))


def edited_likeness(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Fingerprints of all texts and of their edited forms (the last third of the code points replaced by the next document's first), and their likeness."""
    rows = with_next(fingerprints(docs, key, text), key)
    n = F.char_length("text")
    third = F.floor(n / 3).cast("int")
    edited = F.concat(F.substring(F.col("text"), F.lit(1), n - third), F.substring(F.col("next_text"), F.lit(1), third))
    rows = rows.select(key, n.cast("long").alias("n_chars"), edited.alias("edited"), "vector", "next_vector").withColumn("edited_vector", vector(F.col("edited")))
    v, e, x = (F.col(c) for c in ("vector", "edited_vector", "next_vector"))
    return rows.select(key, "n_chars", "edited", printed(fingerprint(F.col("vector"))).alias("fingerprint"), printed(fingerprint(F.col("edited_vector"))).alias("edited_fingerprint"), likeness(v, e).alias("near_edited"), likeness(v, x).alias("near_next"))

"""The thin queries of this subpackage and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann, bpe, fingerprint, jaccard, langid, license, mixing, secrets, tokencount, warc
from .base import table
from .warc_sql import WARC


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.mix(table(spark, sf_dir, "documents"), mixing.ramps((3, 1, 2)))
    return mixed.select("doc_id", "size", "source_size", "target", "taken", F.round("first_position", 6).alias("first_position"))


def op2_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.join_groups(table(spark, sf_dir, "documents"))


def held_out(key: str = "doc_id"):
    return F.coalesce(F.pmod(F.crc32(F.col(key).cast("string")), F.lit(4)) == 2, F.lit(False))


def op3_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = langid.learn(docs, ~held_out())
    return langid.predict(docs.select("doc_id", "text"), model).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")


def op4_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    records = warc.derive(table(spark, sf_dir, "pages"))
    return records.select("page_id", "kind", "record_id", "refers_to", "target_uri", "content_length", "block_digest", "payload_digest")


def tokenizer(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op5_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.digests(bpe.round_trip(table(spark, sf_dir, "documents"), tokenizer("word_bpe_49k.json")))


def op6_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.edited_likeness(table(spark, sf_dir, "documents")).select("doc_id", "n_chars", F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"), "fingerprint", "edited_fingerprint", "near_edited", "near_next")


def op7_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokencount.count_tokens(table(spark, sf_dir, "documents"), tokenizer("piece_bpe_32k.model"))


def op8_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license.scan(table(spark, sf_dir, "documents"))


def op9_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan(table(spark, sf_dir, "documents"))


def op10_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.nearest(table(spark, sf_dir, "embeddings"), F.pmod(F.col("id"), F.lit(50)) == 0)


QUERIES = {f.__name__: f for f in (op1_mixing, op2_jaccard, op3_language, op4_warc, op5_bpe, op6_fingerprints, op7_tokens, op8_licenses, op9_secrets, op10_neighbours)}

SQL = {
    "op1_mixing": r"""
WITH RECURSIVE sized AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
         ('0x' || substr(md5('mix:' || coalesce(doc_id::VARCHAR, '')), 1, 15))::BIGINT AS k FROM documents),
per AS (SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS r FROM sized GROUP BY source),
weighed AS (SELECT source, source_size, CASE r % 3 WHEN 0 THEN 3.0 WHEN 1 THEN 1.0 ELSE 2.0 END::DOUBLE AS w, 2.0::DOUBLE * source_size AS most FROM per),
rounds AS (
  SELECT 0 AS i, source, w, most, source_size, false AS stopped, w * (SELECT 1.5 * sum(source_size) FROM weighed) / (SELECT sum(w) FROM weighed) AS target FROM weighed
  UNION ALL
  SELECT i + 1, source, w, most, source_size, stopped OR target >= most,
         CASE WHEN stopped OR target >= most THEN most
              ELSE w * ((SELECT 1.5 * sum(source_size) FROM weighed) - sum(CASE WHEN stopped OR target >= most THEN most ELSE 0 END) OVER ())
                   / sum(CASE WHEN stopped OR target >= most THEN 0 ELSE w END) OVER () END
  FROM rounds WHERE i < 40),
goal AS (SELECT source, source_size, target, floor(target + 0.5)::BIGINT AS g, CASE WHEN r % 3 = 1 THEN -0.5 ELSE 0.5 END::DOUBLE AS sw FROM rounds JOIN (SELECT source AS src, r FROM per) ON src IS NOT DISTINCT FROM source WHERE i = 40),
laid AS (SELECT doc_id, size, s.source, coalesce(sum(size) OVER (PARTITION BY s.source ORDER BY k, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS off0 FROM sized s),
took AS (SELECT l.doc_id, l.size, g.source_size, g.target, g.g, g.sw, l.off0, greatest(0, least(g.g - l.off0, l.size))::BIGINT AS one, greatest(0, least(g.g - l.off0 - g.source_size, l.size))::BIGINT AS two FROM laid l JOIN goal g ON l.source IS NOT DISTINCT FROM g.source)
SELECT doc_id, size, source_size, target, (one + two)::BIGINT AS taken,
       CASE WHEN one > 0 THEN round(least(1, 2 * (off0 / target) / ((1 - sw) + sqrt((1 - sw) * (1 - sw) + 4 * sw * (off0 / target)))), 6) END AS first_position FROM took
""",
    "op2_jaccard": r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
sh AS (SELECT DISTINCT doc_id, s FROM (
  SELECT doc_id, unnest(CASE WHEN len(ws) = 0 THEN []::VARCHAR[] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')]
         ELSE list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' ')) END) AS s FROM w)),
n AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
k AS (SELECT doc_id, md5_number(s) AS h FROM sh),
common AS (SELECT h FROM k GROUP BY h HAVING count(*) > 1),
few AS (SELECT k.doc_id, k.h FROM k JOIN common USING (h)),
inter AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM few a JOIN few b ON a.h = b.h AND a.doc_id <> b.doc_id GROUP BY 1, 2),
links AS (SELECT a, b FROM inter JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * i >= 75 * (x.n + y.n - i)),
reach AS (SELECT doc_id AS d, doc_id AS r FROM documents UNION SELECT reach.d, links.b FROM reach JOIN links ON links.a = reach.r)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, m.c AS component_id
FROM documents d LEFT JOIN n USING (doc_id) JOIN (SELECT d, min(r) AS c FROM reach GROUP BY d) m ON m.d = d.doc_id
""",
    "op4_warc": WARC,
}

"""Registered queries of the subpackage, and their SQL where SQL can say the same."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadsample.llm import ann, bpe, langid, linededup, mixing, quality, secrets, sharding, vector_dedup
from spreadsample.llm.common import table
from spreadsample.llm.simhash import near_duplicates


def op1_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


def op2_nearest_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.search(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 100 == 0, k=10)


def op7_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_dedup.near_duplicates(table(spark, sf_dir, "embeddings"))


def vocabulary_file(name: str) -> str:
    """Where an installed public vocabulary lies on the driver; executors get what was read from it."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(table(spark, sf_dir, "documents"), vocabulary_file("piece_bpe_32k.model"))


def op5_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.digests(table(spark, sf_dir, "documents"), vocabulary_file("byte_bpe_50k.json"))


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linededup.dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op6_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.digests(table(spark, sf_dir, "documents"))


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op8_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.taken(table(spark, sf_dir, "documents"))


def op9_shard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard(table(spark, sf_dir, "documents"))


OP4_SQL = """
WITH l AS (
  SELECT doc_id, n, ls[n] AS line, length(ls[n]) + 1 AS w, ls
  FROM (SELECT doc_id, string_split(text, chr(10)) AS ls FROM documents) d, unnest(range(1, len(ls) + 1)) AS t(n)),
c AS (SELECT *, sum(w) OVER (PARTITION BY doc_id ORDER BY n) AS upto FROM l),
ends AS (
  SELECT a.doc_id, a.n AS s, min(b.n) AS e FROM c a JOIN c b ON a.doc_id = b.doc_id AND b.n BETWEEN a.n AND a.n + 19
  WHERE b.upto - a.upto + a.w >= 20 GROUP BY a.doc_id, a.n
  UNION
  SELECT b.doc_id, max(a.n) AS s, b.n AS e FROM c a JOIN c b ON a.doc_id = b.doc_id AND a.n BETWEEN b.n - 19 AND b.n
  WHERE b.upto - a.upto + a.w >= 20 GROUP BY b.doc_id, b.n),
named AS (SELECT ends.doc_id, s, e, array_to_string(ls[s:e], chr(10)) AS run FROM ends JOIN l ON l.doc_id = ends.doc_id AND l.n = ends.s),
late AS (SELECT * FROM named QUALIFY row_number() OVER (PARTITION BY run, e - s ORDER BY doc_id, s) > 1),
gone AS (SELECT DISTINCT doc_id, t.n FROM late, unnest(range(s, e + 1)) AS t(n)),
kept AS (SELECT l.doc_id, l.line, l.n, gone.n IS NOT NULL AS g FROM l LEFT JOIN gone ON l.doc_id = gone.doc_id AND l.n = gone.n)
SELECT d.doc_id, CASE WHEN d.text IS NULL THEN NULL ELSE coalesce(k.text, '') END AS text,
       CAST(coalesce(n_lines, 0) AS BIGINT) AS n_lines, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed
FROM documents d LEFT JOIN (
  SELECT doc_id, string_agg(line, chr(10) ORDER BY n) FILTER (WHERE NOT g) AS text, count(*) AS n_lines, count(*) FILTER (WHERE g) AS n_removed
  FROM kept GROUP BY doc_id) k ON d.doc_id = k.doc_id
"""

OP8_SQL = """
WITH d AS (
  SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')), 0) AS BIGINT) AS size,
         md5(coalesce(CAST(doc_id AS VARCHAR), 'null:' || md5(coalesce(text, '')))) AS h FROM documents),
p AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS sid FROM d GROUP BY source),
q AS (SELECT *, sid % 3 + 1 AS w, 3 * source_size AS cap FROM p),
r AS (SELECT *, CAST(sum(cap) OVER f AS BIGINT) - cap AS before,
             CAST(sum(w) OVER (ORDER BY cap / w, sid ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS BIGINT) AS remaining,
             CAST(sum(source_size) OVER () AS BIGINT) AS total
      FROM q WINDOW f AS (ORDER BY cap / w, sid ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)),
lv AS (SELECT (total - before) / remaining AS level FROM r WHERE (total - before) / remaining <= cap / w ORDER BY cap / w, sid LIMIT 1),
t AS (SELECT source, sid, source_size, total, least(CAST(cap AS DOUBLE), w * level) AS target, CAST(floor(least(CAST(cap AS DOUBLE), w * level)) AS BIGINT) AS words FROM r, lv),
b AS (SELECT greatest(1, least(4096, max(total) // 65536)) AS block, max(total) AS total FROM t),
e AS (SELECT sid, words, sum(words) OVER (ORDER BY sid ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS upto, sum(words) OVER () AS every FROM t WHERE words > 0),
reach AS (SELECT sid, CAST(upto - words AS HUGEINT) * 2147483648 // CAST(every AS HUGEINT) AS lo, CAST(upto AS HUGEINT) * 2147483648 // CAST(every AS HUGEINT) AS hi FROM e),
slots AS (SELECT range AS id, (range * 1327217885) % 2147483648 AS u FROM range((SELECT total // block + 1 FROM b))),
drawn AS (SELECT sid, id, row_number() OVER (PARTITION BY sid ORDER BY id) - 1 AS block FROM slots JOIN reach ON u >= lo AND u < hi),
s AS (SELECT doc_id, sid, size, source_size, target, words,
             CAST(sum(size) OVER (PARTITION BY d.source ORDER BY h, size ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) - size AS start
      FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
k AS (SELECT *, CASE WHEN source_size = 0 THEN 0 ELSE words // source_size * size + greatest(0, least(size, words % source_size - start)) END AS taken,
             CASE WHEN source_size = 0 THEN 0 ELSE list_sum(list_transform(range(0, words // source_size + 1), lambda n:
               CASE WHEN size > 0 AND least(n * source_size + start + size, words) > n * source_size + start
                    THEN (least(n * source_size + start + size, words) - 1) // block - (n * source_size + start) // block + 1 ELSE 0 END)) END AS n_slots,
             start // block AS nth, b.total // block + 1 AS all_slots FROM s, b)
SELECT doc_id, size, source_size, target, taken, CASE WHEN taken > 0 THEN coalesce(id, all_slots + nth) END AS first_slot, CAST(n_slots AS BIGINT) AS n_slots
FROM k LEFT JOIN drawn ON drawn.sid = k.sid AND drawn.block = k.nth
"""

OP7_SQL = """
WITH RECURSIVE v AS (
  SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e,
         coalesce(len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
                  AND len(list_filter(embedding, lambda x: x <> 0)) > 0, false) AS ok
  FROM embeddings),
links AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.vec_id <> b.vec_id
  WHERE a.ok AND b.ok AND len(a.e) = len(b.e) AND list_cosine_similarity(a.e, b.e) >= 0.9),
reach AS (SELECT vec_id AS a, vec_id AS b FROM v UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a),
comp AS (SELECT a AS vec_id, min(b) AS component_id FROM reach GROUP BY a),
counts AS (SELECT a AS vec_id, count(*) AS n FROM links GROUP BY a)
SELECT v.vec_id, CAST(coalesce(n, 0) AS BIGINT) AS n_links, component_id, v.vec_id = component_id AS kept
FROM v JOIN comp USING (vec_id) LEFT JOIN counts USING (vec_id)
"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_simhash_near_dedup, op2_nearest_neighbours, op3_language_id, op4_line_dedup, op5_bpe, op6_secrets, op7_embedding_near_dedup, op8_mix_sources, op9_shard, op10_quality)}


def oracle_sql() -> dict[str, str]:
    return {"op4_line_dedup": OP4_SQL, "op8_mix_sources": OP8_SQL, "op7_embedding_near_dedup": OP7_SQL}

"""The thin registered queries of the corpus operators, and their SQL twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

URL_RULES = [("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block")]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_file() -> str:
    import public_tokenizers

    return str(public_tokenizers.path("byte_bpe_50k.json"))


def op1_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tangentia.llm.quality import quality_scores

    return quality_scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op2_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tangentia.llm.setsketch import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"), width=4, threshold=0.8)


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tangentia.llm.tokens import count_tokens

    return count_tokens(table(spark, sf_dir, "documents"), tokenizer_file())


def op4_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tangentia.llm.pii import report

    return report(table(spark, sf_dir, "documents"))


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tangentia.llm.toxicity import toxicity_scores

    scored = toxicity_scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    offsets = F.transform("spans", lambda s: F.concat_ws(":", s["start"].cast("string"), s["end"].cast("string")))
    return scored.select("doc_id", "held_out", "score", "predicted", F.array_join(offsets, ",").alias("toxic_spans"))


def op6_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tangentia.llm.warc import round_trip

    return round_trip(table(spark, sf_dir, "pages"))


def op7_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tangentia.llm.topk import top_k

    return top_k(table(spark, sf_dir, "embeddings"))


def op8_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tangentia.llm.decontamination import leaks

    return leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op9_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tangentia.llm.urls import judge_urls

    return judge_urls(table(spark, sf_dir, "pages"), URL_RULES)


def op10_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tangentia.llm.mixing import mix_report

    rows = mix_report(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "size", "source_size", "target", "taken", "passes", F.round("position", 9).alias("position"), F.round("last_position", 9).alias("last_position"))


def queries() -> dict:
    return {f.__name__: f for f in (op1_quality, op2_near_duplicates, op3_token_counts, op4_personal_data, op5_toxicity, op6_warc, op7_top_k, op8_decontaminate, op9_url_rules, op10_mix)}


OP2_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, md5(array_to_string(list_slice(w, i, least(i + 3, len(w))), ' ')) AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 2, 2))) AS i FROM w WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
e AS MATERIALIZED (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * k >= 80 * (x.n + y.n - k)),
both_ways AS MATERIALIZED (SELECT a, b FROM e UNION SELECT b, a FROM e),
r(doc_id, c) AS (SELECT doc_id, doc_id FROM documents UNION SELECT b, c FROM r JOIN both_ways ON a = r.doc_id)
SELECT d.doc_id, CAST(coalesce(n, 0) AS BIGINT) AS n_shingles, m.c AS component_id, m.c = d.doc_id AS kept
FROM documents d LEFT JOIN n ON n.doc_id = d.doc_id JOIN (SELECT doc_id, min(c) AS c FROM r GROUP BY doc_id) m ON m.doc_id = d.doc_id
"""
OP6_SQL = r"""
WITH p AS (SELECT page_id, coalesce(html, '') AS html, octet_length(encode(coalesce(html, ''))) AS n, sha1(coalesce(html, '')) AS d FROM pages),
g AS (SELECT d, max(page_id) AS last_id FROM p WHERE n >= 1000 GROUP BY d)
SELECT page_id, CAST(n AS BIGINT) AS payload_bytes, p.d AS payload_digest,
  CASE WHEN last_id > page_id THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN last_id > page_id THEN last_id END AS refers_to
FROM p LEFT JOIN g ON p.d = g.d
"""
OP7_SQL = r"""
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * CAST(x AS DOUBLE))) AS v FROM embeddings
  WHERE embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_dot_product(q.v, c.v) AS BIGINT) AS score FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id),
r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""
OP9_SQL = r"""
WITH rules(rh, rp, verdict) AS (VALUES ('com', '/', 'allow'), ('example.com', '/en/', 'block'), ('www.example.com', '/en/', 'allow'), ('net', '/es/', 'block'), ('net', '/fr/', 'block')),
u AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
h AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
  regexp_extract(substr(rest, length(regexp_extract(rest, '^[^/?#]*')) + 1), '^[^?#]*') AS path FROM u),
n AS (SELECT *, row_number() OVER () AS i FROM h),
f AS (SELECT i, arg_max(rh || rp, length(rh || rp)) AS rule, arg_max(verdict, length(rh || rp)) AS verdict FROM n
  JOIN rules ON (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp) GROUP BY i)
SELECT page_id, host, path, rule, coalesce(verdict, 'allow') AS verdict FROM n LEFT JOIN f USING (i)
"""
OP10_SQL = r"""
WITH d AS (SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size, md5('0:' || CAST(doc_id AS VARCHAR)) AS h FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
w AS (SELECT *, CAST(row_number() OVER (ORDER BY source NULLS LAST) - 1 AS INTEGER) % 3 + 1 AS k, [3, 1, 2][k] AS weight, [-0.5, 0.5, 0.0][k]::DOUBLE AS slope, 2.0::DOUBLE * source_size AS cap FROM s),
l AS (SELECT *, (1.5::DOUBLE * CAST(sum(source_size) OVER () AS DOUBLE) - coalesce(sum(cap) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
  / CAST(sum(weight) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS DOUBLE) AS level FROM w),
m AS (SELECT arg_min(level, cap / weight) FILTER (level * weight < cap) AS last FROM l),
g AS (SELECT source, source_size, slope, CASE WHEN level * weight >= cap THEN cap ELSE last * weight END AS target FROM l, m),
t AS (SELECT source, source_size, target, CAST(round(target) AS BIGINT) AS goal, slope - sum(round(target) * slope) OVER () / greatest(sum(round(target)) OVER (), 1) AS slope FROM g),
p AS (SELECT d.*, source_size, target, goal, slope, CAST(coalesce(sum(size) OVER (PARTITION BY d.source ORDER BY h, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS start
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
n AS (SELECT *, CASE WHEN size = 0 OR start >= goal THEN 0 WHEN start + source_size >= goal THEN 1 ELSE 2 END AS passes FROM p),
f AS (SELECT *, start::DOUBLE / goal AS f0, (start + source_size * (passes - 1))::DOUBLE / goal AS f1 FROM n)
SELECT doc_id, size, source_size, target, CAST(passes AS INTEGER) AS passes,
  CAST(greatest(0, least(size, goal - start)) + greatest(0, least(size, goal - start - source_size)) AS BIGINT) AS taken,
  CASE WHEN passes > 0 THEN round(2 * f0 / (1 - slope + sqrt((1 - slope) ** 2 + 4 * slope * f0)), 9) END AS position,
  CASE WHEN passes > 0 THEN round(2 * f1 / (1 - slope + sqrt((1 - slope) ** 2 + 4 * slope * f1)), 9) END AS last_position
FROM f
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_near_duplicates": OP2_SQL, "op6_warc": OP6_SQL, "op7_top_k": OP7_SQL, "op9_url_rules": OP9_SQL, "op10_mix": OP10_SQL}

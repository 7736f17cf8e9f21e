"""The registered queries opN_* and, where SQL can say the same, that SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import embedding_dedup, exact_dedup, language_id, licenses, mixing, near_dedup, packing, pii, token_output, toxicity
from .common import cut, read, remove, shared_dir


def _tokenizer(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_pareto_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    taken = mixing.copies(read(spark, sf_dir, "documents"))
    return taken.select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"))


def op2_pii_boosting(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.redactions(read(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", *[f"n_{k}" for k in pii.KINDS], F.sha2(pii.joined("base"), 256).alias("base_sha256"), pii.joined("spans").alias("spans"))


def op3_grace_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.groups(read(spark, sf_dir, "documents"))


def op4_license_digests(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = licenses.scan(read(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", "text_digest", "license", "n_notices", "notices")


def op5_string_kernel_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    found = language_id.predict(docs, language_id.fit(docs))
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, F.lit(False))
    return found.select("doc_id", held.alias("held_out"), "lang_pred", "score")


def op6_odd_sketch_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.classes(read(spark, sf_dir, "documents").select("doc_id", "text"))


def op7_toxicity_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = toxicity.scored(read(spark, sf_dir, "documents").select("doc_id", "text"), read(spark, sf_dir, "labels"))
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 4 == 2, F.lit(False))
    return found.select("doc_id", held.alias("held_out"), F.col("_score").alias("score"), F.col("_toxic").alias("predicted"))


def op8_projection_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_dedup.classes_of(read(spark, sf_dir, "embeddings"))


def op9_bin_completion(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(read(spark, sf_dir, "documents"), _tokenizer("word_bpe_49k.json"), added_tokens=True)


def op10_range_coded_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{shared_dir(spark)}/token-ids-{uuid.uuid4().hex}"
    token_output.write_tokens(read(spark, sf_dir, "documents"), path, _tokenizer("byte_bpe_50k.json"), vocab=50257, end_id=2, added_tokens=True)
    found = cut(token_output.read_tokens(spark, path))
    remove(spark, path)
    return found


QUERIES = {f.__name__: f for f in (op1_pareto_mix, op2_pii_boosting, op3_grace_dedup, op4_license_digests, op5_string_kernel_language, op6_odd_sketch_dedup, op7_toxicity_trees, op8_projection_forest, op9_bin_completion, op10_range_coded_tokens)}

_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

MIX_SQL = r"""
slim AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size, doc_key FROM mix_input),
sources AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS weight FROM slim GROUP BY source),
levels AS (SELECT *, source_size * 3 / weight AS ratio, row_number() OVER w AS place,
    (CAST(sum(source_size) OVER () AS BIGINT) - coalesce(CAST(sum(source_size * 3) OVER b AS BIGINT), 0)) / (CAST(sum(weight) OVER () AS BIGINT) - coalesce(CAST(sum(weight) OVER b AS BIGINT), 0)) AS level
  FROM sources WINDOW w AS (ORDER BY source_size * 3 / weight, source NULLS LAST), b AS (ORDER BY source_size * 3 / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
free AS (SELECT min(place) AS first_free FROM levels WHERE level <= ratio),
targets AS (SELECT l.source, l.source_size, CASE WHEN l.place < first_free THEN CAST(l.source_size * 3 AS DOUBLE)
    ELSE least(l.weight * (SELECT level FROM levels WHERE place = first_free), CAST(l.source_size * 3 AS DOUBLE)) END AS target FROM levels l, free),
rates AS (SELECT *, CASE WHEN source_size = 0 THEN 0.0 ELSE target / source_size END AS rate FROM targets),
wanted AS (SELECT *, floor(rate) AS whole, (rate - floor(rate)) * source_size AS missing FROM rates),
counts AS (SELECT s.source, s.size, count(*) AS n, CAST(ceil(sqrt(CAST(s.size AS DOUBLE))) AS HUGEINT) AS draw, w.missing FROM slim s JOIN wanted w ON s.source IS NOT DISTINCT FROM w.source WHERE s.size > 0 AND w.missing > 0 GROUP BY s.source, s.size, w.missing),
scales AS (SELECT source, size, (missing - CAST(coalesce(sum(CAST(size * n AS HUGEINT)) OVER (PARTITION BY source ORDER BY size DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS DOUBLE)) / CAST(sum(draw * size * n) OVER (PARTITION BY source ORDER BY size ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS DOUBLE) AS scale, CAST(draw AS BIGINT) AS draw FROM counts),
firsts AS (SELECT source, max(size) AS most, arg_max(scale, size) AS scale FROM scales WHERE scale * draw <= 1 GROUP BY source),
odds AS (SELECT s.doc_id, s.source, s.size, w.source_size, w.target, s.doc_key, w.whole, w.missing,
    CASE WHEN s.size <= 0 OR f.scale IS NULL THEN 0.0::DOUBLE WHEN s.size > f.most OR f.scale * CAST(ceil(sqrt(CAST(s.size AS DOUBLE))) AS BIGINT) >= 1 THEN 1.0::DOUBLE ELSE f.scale * CAST(ceil(sqrt(CAST(s.size AS DOUBLE))) AS BIGINT) END AS p,
    (CAST('0x' || substr(md5(coalesce(CAST(s.doc_id AS VARCHAR), '')), 1, 13) AS BIGINT) + 0.5::DOUBLE) / 4503599627370496.0::DOUBLE AS u
  FROM slim s JOIN wanted w ON s.source IS NOT DISTINCT FROM w.source LEFT JOIN firsts f ON s.source IS NOT DISTINCT FROM f.source),
cut AS (SELECT *, CAST(coalesce(sum(CASE WHEN p > 0 THEN size END) OVER (PARTITION BY source ORDER BY CASE WHEN p = 1 THEN -1 WHEN p > 0 THEN (u / (1 - u)) / (p / (1 - p)) END NULLS LAST, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS ahead FROM odds),
mixed AS (SELECT *, CAST(whole + CASE WHEN p = 1 OR (p > 0 AND ahead + size / 2 <= missing) THEN 1 ELSE 0 END AS BIGINT) AS copies FROM cut)
"""


def _license_sql() -> str:
    def quoted(s: str) -> str:
        return "'" + s.replace("'", "''") + "'"

    def canonical(x: str) -> str:
        t = f"translate(coalesce({x}, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
        t = f"regexp_replace({t}, {quoted(licenses.COPYRIGHT)}, ' ', 'g')"
        t = f"regexp_replace({t}, 'all rights reserved', ' ', 'g')"
        t = f"regexp_replace({t}, '[^\\p{{L}}\\p{{N}}]+', ' ', 'g')"
        for a, b in licenses.EQUAL:
            t = f"regexp_replace({t}, '\\b{a}(s?)\\b', '{b}\\1', 'g')"
        return f"trim({t}, ' ')"

    texts = ", ".join(f"({quoted(k)}, {quoted(v)})" for k, v in licenses.LICENSES.items())
    notices = ", ".join(f"({quoted(k)}, {quoted(v)})" for k, v in licenses.NOTICES.items())
    return f"""
WITH known AS (SELECT sha256({canonical("t")}) AS digest, min(license) AS license FROM (VALUES {texts}) v(license, t) GROUP BY 1),
notice AS (SELECT {canonical("t")} AS line, max(license) AS license FROM (VALUES {notices}) v(t, license) GROUP BY 1),
lines AS (SELECT doc_id, unnest([{canonical("x")} for x in string_split(text, chr(10))]) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS place FROM documents WHERE regexp_matches(text, '(?i)licen[sc]e')),
found AS (SELECT doc_id, count(*) AS n, string_agg(license, ',' ORDER BY place) AS names FROM lines JOIN notice USING (line) GROUP BY doc_id)
SELECT d.doc_id, d.text_digest, k.license, coalesce(f.n, 0) AS n_notices, coalesce(f.names, '') AS notices
FROM (SELECT doc_id, sha256({canonical("text")}) AS text_digest FROM documents) d LEFT JOIN known k ON d.text_digest = k.digest LEFT JOIN found f ON d.doc_id = f.doc_id"""


ORACLE_SQL = {
    "op1_pareto_mix": f"WITH mix_input AS (SELECT doc_id, source, text, doc_id AS doc_key FROM documents), {MIX_SQL} SELECT doc_id, size, source_size, target, copies * size AS taken FROM mixed",
    "op3_grace_dedup": f"SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = max(doc_id) OVER w AS kept, sha256(t) AS text_sha256 FROM (SELECT doc_id, {_LOWER} AS t FROM documents) WINDOW w AS (PARTITION BY t)",
    "op4_license_digests": _license_sql(),
    "op6_odd_sketch_dedup": r"""
WITH RECURSIVE words AS (SELECT doc_id, regexp_extract_all(""" + _LOWER + r""", '[^\x20\x09-\x0D]+') AS w FROM documents),
sets AS (SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')] ELSE list_distinct([array_to_string(w[i:i + 4], ' ') for i in range(1, len(w) - 3)]) END AS s FROM words),
sizes AS (SELECT doc_id, CAST(len(s) AS BIGINT) AS n FROM sets),
rows AS (SELECT doc_id, unnest(s) AS g FROM sets),
pairs AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM rows a JOIN rows b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
links AS (SELECT p.a, p.b FROM pairs p JOIN sizes x ON p.a = x.doc_id JOIN sizes y ON p.b = y.doc_id WHERE 100 * p.c >= 75 * (x.n + y.n - p.c)),
reach AS (SELECT doc_id AS a, doc_id AS b FROM sizes UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a),
comp AS (SELECT a, min(b) AS component_id FROM reach GROUP BY a)
SELECT s.doc_id, s.n AS n_shingles, c.component_id, s.doc_id = c.component_id AS kept FROM sizes s JOIN comp c ON s.doc_id = c.a""",
    "op8_projection_forest": """
WITH RECURSIVE v AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings WHERE label IS NOT NULL AND embedding IS NOT NULL),
links AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id AND list_cosine_similarity(a.e, b.e) >= 0.93),
reach AS (SELECT vec_id AS a, vec_id AS b FROM embeddings UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a),
comp AS (SELECT a, min(b) AS component_id FROM reach GROUP BY a),
n AS (SELECT a, count(*) AS n FROM links GROUP BY a)
SELECT c.a AS vec_id, coalesce(n.n, 0) AS n_links, c.component_id, c.a = c.component_id AS kept FROM comp c LEFT JOIN n ON n.a = c.a""",
}

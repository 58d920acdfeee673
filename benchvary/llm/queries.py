"""One query for each operator, with production parameters, over its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from benchvary.llm import decontaminate, jaccard_join, langmodel, packing, quality, secrets, suffix_dedup, url_filter, vector_dedup, warc_zip

URL_RULES = tuple(
    url_filter.Rule.of(*x) for x in (("block", "com/en/"), ("allow", "example.com/en/7"), ("allow", "net/de/"), ("block", "example.net/de/8"), ("block", "org/es/"))
)

#: Bytes of a passage of some fifty words: what op10 reports, beside the strings of 400 bytes that it removes.
REPORTED = 288


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secrets.scan_secrets(_table(spark, sf_dir, "documents"))
    rank = {k: i for i, k in enumerate(secrets.ORDER)}
    n = lambda kind: F.size(F.filter("strong", lambda x: x["rank"] == rank[kind])).cast("long")
    return found.select(
        "doc_id",
        n("assign").alias("n_assign"),
        n("access").alias("n_access"),
        n("hex").alias("n_hex"),
        F.sha2(secrets.span_list(F.col("strong")).cast("binary"), 256).alias("base_sha256"),
        secrets.span_list(F.array_sort(F.concat("strong", "linked"))).alias("spans"),
    )


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from benchvary.session import materialize

    stats = materialize(quality.text_statistics(_table(spark, sf_dir, "documents")), "statistics")
    held = langmodel.held_out("doc_id", 4, 2)
    model = quality.train(stats, _table(spark, sf_dir, "labels").where(~held))
    score = F.col("score")
    return stats.select("doc_id", held.alias("held_out"), model.score().alias("score")).withColumn("predicted", (score >= 0.7).cast("int"))


def op3_langmodel(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    held = langmodel.held_out("doc_id", 10, 0)
    model = langmodel.fit(docs.where(~held).select("text"))
    return langmodel.score(model, docs.select("doc_id", held.alias("held_out"), "text"), ("doc_id", "held_out"))


def op4_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_dedup.near_vectors(_table(spark, sf_dir, "embeddings"), 0.93)


def op5_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge_urls(_table(spark, sf_dir, "pages"), URL_RULES)


def op6_archives(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = _table(spark, sf_dir, "pages")
    manifest = warc_zip.write_archives(pages, warc_zip.archive_folder(pages), least_bytes=0)
    return warc_zip.read_archives(manifest).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    pieces = packing.concatenate_and_cut(_table(spark, sf_dir, "documents"))
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find_leaks(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op9_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.similar_groups(_table(spark, sf_dir, "documents"), n_words=4, threshold=(85, 100)).select("doc_id", "n_shingles", "component_id")


def op10_suffixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = suffix_dedup.remove_repeats(_table(spark, sf_dir, "documents"), 400, REPORTED)
    return found.select(
        "doc_id",
        "n_bytes",
        (F.col("n_bytes") - F.octet_length("kept")).cast("long").alias("n_removed"),
        F.size("spans").cast("long").alias("n_spans"),
        F.sha2("kept", 256).alias("kept_sha256"),
        "n_reported",
    )


QUERIES = {f.__name__: f for f in (op1_secrets, op2_quality, op3_langmodel, op4_vectors, op5_urls, op6_archives, op7_packing, op8_decontamination, op9_jaccard, op10_suffixes)}
_REACH = """, reach(a, b) AS (SELECT id, id FROM nodes UNION SELECT r.a, l.b FROM reach r JOIN links l ON l.a = r.b), low AS (SELECT a AS id, min(b) AS component_id FROM reach GROUP BY 1)"""
_WORDS = r"list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda w: w <> '')"
_BASE32 = " || ".join(f"substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + (('0x' || substr(hex_, {5 * j + 1}, 5))::INT >> {shift}) % 32, 1)" for j in range(8) for shift in (15, 10, 5, 0))
_COSINE = "list_dot_product(a.e, b.e) / (sqrt(list_dot_product(a.e, a.e)) * sqrt(list_dot_product(b.e, b.e)))"
#: DuckDB SQL for those that need neither a trained model nor a tokeniser; tests hold the others against brute force.
ORACLE: dict[str, str] = {
    "op4_vectors": f"""WITH RECURSIVE v AS (SELECT vec_id, label, embedding::DOUBLE[] AS e FROM embeddings),
ok AS (SELECT * FROM v WHERE label IS NOT NULL AND e IS NOT NULL AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(e, lambda x: x <> 0)) > 0),
links AS (SELECT a.vec_id AS a, b.vec_id AS b FROM ok a JOIN ok b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.e) = len(b.e) AND {_COSINE} >= 0.93), nodes AS (SELECT vec_id AS id FROM v){_REACH}
SELECT id AS vec_id, (SELECT count(*) FROM links WHERE links.a = low.id) AS n_links, component_id, id = component_id AS kept FROM low""",
    "op6_archives": f"""WITH p AS (SELECT page_id, coalesce(html, '') AS body FROM pages), h AS (SELECT page_id, octet_length(encode(body)) AS payload_bytes, sha1(body) AS hex_, max(page_id) OVER (PARTITION BY body) AS last_ FROM p)
SELECT page_id, payload_bytes, {_BASE32} AS payload_digest, CASE WHEN page_id = last_ THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> last_ THEN last_ END AS refers_to FROM h""",
    "op9_jaccard": f"""WITH RECURSIVE w AS (SELECT doc_id, {_WORDS} AS l FROM documents),
sets AS (SELECT doc_id, CASE WHEN len(l) >= 4 THEN list_distinct(list_transform(range(len(l) - 3), lambda i: array_to_string(l[i + 1:i + 4], ' '))) WHEN len(l) > 0 THEN [array_to_string(l, ' ')] ELSE [] END AS s FROM w),
sh AS (SELECT doc_id, len(s) AS n, unnest(list_transform(s, lambda x: hash(x))) AS g FROM sets), pairs AS (SELECT a.doc_id AS a, b.doc_id AS b, any_value(a.n) AS na, any_value(b.n) AS nb, count(*) AS c FROM sh a JOIN sh b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
links AS (SELECT a, b FROM pairs WHERE 100 * c >= 85 * (na + nb - c)), nodes AS (SELECT doc_id AS id FROM documents){_REACH}
SELECT doc_id, len(s) AS n_shingles, component_id FROM sets JOIN low ON id = doc_id""",
}

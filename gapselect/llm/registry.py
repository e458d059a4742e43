"""Queries of the corpus operators, each over its whole table, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gapselect.llm.common import table


def op1_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gapselect.llm.coding import default_vocabulary
    from gapselect.llm.packing import pack

    return pack(table(spark, sf_dir, "documents"), default_vocabulary())


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gapselect.llm.exact_dedup import exact_groups

    return exact_groups(table(spark, sf_dir, "documents"), digest=True)


def op3_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gapselect.llm.url_rules import judge_urls

    return judge_urls(table(spark, sf_dir, "pages")).drop("by_alias")


def op4_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gapselect.llm.ngram_join import link_components

    return link_components(table(spark, sf_dir, "documents"))


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gapselect.llm.quality import quality_rules

    cols = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"]
    return quality_rules(table(spark, sf_dir, "documents")).select(*cols)


def op6_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gapselect.llm.coding import decode_documents, default_vocabulary, encode_documents

    path = default_vocabulary()
    coded = decode_documents(encode_documents(table(spark, sf_dir, "documents"), path), path)
    return coded.select(
        "doc_id", (F.octet_length("ids") / 4).cast("long").alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"),
        F.sha2(F.encode("text", "UTF-8"), 256).alias("decoded_sha256"),
    )


def op7_training_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gapselect.llm.coding import default_vocabulary
    from gapselect.llm.training_order import write_order

    return write_order(table(spark, sf_dir, "documents"), default_vocabulary()).drop("folder")


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gapselect.llm.attribution import attribute_tokens
    from gapselect.llm.coding import default_vocabulary

    return attribute_tokens(table(spark, sf_dir, "documents"), default_vocabulary()).drop("name")


def op9_ring_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gapselect.llm.ring import ring_shards

    placed = ring_shards(table(spark, sf_dir, "documents"))
    return placed.withColumns({"law": F.lit("rows"), "grown_shard": F.lit(None).cast("int")})


def op10_preference_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gapselect.llm.preference import preference_pairs, swapped_replies

    pairs = preference_pairs(*swapped_replies(table(spark, sf_dir, "conversations")))

    def shown(mask: str) -> Column:
        return F.array_join(F.transform(mask, lambda t: F.concat(t["chars"].cast("string"), F.lit(":"), t["learned"].cast("string"))), ",")

    return pairs.select(F.col("pair_id").alias("conv_id"), "n_prompt_turns", "prompt", "chosen", "rejected", shown("chosen_mask").alias("chosen_mask"), shown("rejected_mask").alias("rejected_mask"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_best_fit_packing, op2_exact_dedup, op3_url_filters, op4_ngram_join, op5_quality_rules, op6_bpe_codec,
        op7_training_order, op8_token_counts, op9_ring_sharding, op10_preference_pairs, pipeline,
    )
}

ORACLES: dict[str, str] = {
    "op2_exact_dedup": r"""
        WITH n AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS t FROM documents)
        SELECT doc_id, min(doc_id) OVER (PARTITION BY t) AS keep_id, CAST(count(*) OVER (PARTITION BY t) AS BIGINT) AS group_size,
               doc_id = min(doc_id) OVER (PARTITION BY t) AS kept, sha256(t) AS text_sha256
        FROM n
    """,
    # The given pages hold no redirect or canonical link, so own rules and the default decide; alias
    # classes are tested against brute force.
    "op3_url_filters": r"""
        WITH p AS (
            SELECT page_id, coalesce(translate(regexp_extract(url, '(?s)^.*?://([^/?#]*)([^?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '') AS host,
                   coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)([^?#]*)', 2), '') AS path FROM pages),
        r(verdict, rh, rp) AS (VALUES ('allow', 'org', '/'), ('block', 'example.org', '/es/'), ('block', 'example.org', '/en/1'), ('allow', 'com', '/fr/'), ('block', 'com', '/de/')),
        m AS (SELECT page_id, max_by(rh || rp, length(rh || rp)) AS rule, max_by(verdict, length(rh || rp)) AS verdict
              FROM p JOIN r ON (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp) GROUP BY page_id)
        SELECT p.page_id, host, path, rule, coalesce(m.verdict, 'allow') AS verdict FROM p LEFT JOIN m ON p.page_id = m.page_id
    """,
    "op10_preference_pairs": r"""
        WITH last AS (SELECT conv_id, max(turn) AS fin, max_by(text, turn) AS said FROM conversations WHERE role = 'assistant' GROUP BY conv_id),
        c AS (SELECT t.conv_id, t.turn, t.role, t.text, l.fin FROM conversations t LEFT JOIN last l ON t.conv_id = l.conv_id WHERE l.fin IS NULL OR t.turn <= l.fin),
        r AS (SELECT c.conv_id, c.turn, c.role, CASE WHEN c.turn = c.fin THEN o.said ELSE c.text END AS text
              FROM c LEFT JOIN last o ON o.conv_id = xor(c.conv_id, 1) WHERE c.fin IS NULL OR c.turn <> c.fin OR o.said IS NOT NULL),
        j AS (SELECT coalesce(c.conv_id, r.conv_id) AS conv_id, coalesce(c.turn, r.turn) AS turn, c.role AS role, c.text AS ct, r.text AS rt,
                     CASE WHEN c.text IS NOT NULL AND r.text IS NOT NULL AND c.text = r.text AND c.role = r.role THEN 0 ELSE 1 END AS differs
              FROM c FULL JOIN r ON c.conv_id = r.conv_id AND c.turn = r.turn),
        k AS (SELECT *, max(differs) OVER (PARTITION BY conv_id ORDER BY turn) AS after FROM j),
        s AS (SELECT conv_id, turn, role, after, '<|im_start|>' || role || chr(10) || ct || '<|im_end|>' || chr(10) AS cs,
                     '<|im_start|>' || role || chr(10) || rt || '<|im_end|>' || chr(10) AS rs FROM k)
        SELECT conv_id, CAST(count(*) FILTER (after = 0) AS INTEGER) AS n_prompt_turns,
               coalesce(string_agg(cs, '' ORDER BY turn) FILTER (after = 0), '') AS prompt,
               coalesce(string_agg(cs, '' ORDER BY turn) FILTER (after = 1), '') AS chosen,
               coalesce(string_agg(rs, '' ORDER BY turn) FILTER (after = 1), '') AS rejected,
               coalesce(string_agg(length(cs) || ':' || CAST(role = 'assistant' AS INTEGER), ',' ORDER BY turn) FILTER (after = 1), '') AS chosen_mask,
               coalesce(string_agg(length(rs) || ':' || CAST(role = 'assistant' AS INTEGER), ',' ORDER BY turn) FILTER (after = 1 AND rs IS NOT NULL), '') AS rejected_mask
        FROM s GROUP BY conv_id
    """,
}

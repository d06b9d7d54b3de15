"""Queries of the training-data operators, and their SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rankloom.llm import pipeline
from rankloom.llm.chat import format_chats
from rankloom.llm.common import load
from rankloom.llm.decontaminate import find_leaks
from rankloom.llm.html import extract_pages
from rankloom.llm.jaccard import jaccard_components
from rankloom.llm.language import predict_languages
from rankloom.llm.lm import score_texts
from rankloom.llm.mixing import mix_documents
from rankloom.llm.quality import classify_quality
from rankloom.llm.sharding import shard_documents
from rankloom.llm.simhash import simhash_documents


def op1_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_documents(load(spark, sf_dir, "documents"))


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_documents(load(spark, sf_dir, "documents"))


def op3_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(load(spark, sf_dir, "documents"))


def op4_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    return format_chats(load(spark, sf_dir, "conversations"))


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_leaks(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark"))


def op6_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_documents(load(spark, sf_dir, "documents"))


def op7_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return predict_languages(load(spark, sf_dir, "documents"))


def op8_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_texts(load(spark, sf_dir, "documents"))


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classify_quality(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels"))


def op10_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_pages(load(spark, sf_dir, "pages"))


# -- what the contracts of operators without SQL fix, in SQL -------------------------


def sharding_law_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows, slots and bytes of all shards."""
    rows = op6_shards(spark, sf_dir)
    by = rows.groupBy("shard").agg(F.count("*").alias("n"), F.count_distinct("slot").alias("slots"), F.max("slot").alias("last_slot"))
    sums = rows.agg(F.sum("size").alias("bytes_in_all"))
    return by.crossJoin(sums).select("shard", "n", "slots", "last_slot", "bytes_in_all")


def language_contract(spark: SparkSession, sf_dir: str) -> DataFrame:
    known = [r[0] for r in load(spark, sf_dir, "documents", "lang").distinct().collect() if r[0] is not None]
    rows = op7_language(spark, sf_dir)
    return rows.select("doc_id", "held_out", (F.col("lang_pred") == "und").alias("und"), (F.col("lang_pred").isin(*known, "und") & F.col("score").between(0, 1)).alias("in_range"))


def lm_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op8_lm(spark, sf_dir).select("doc_id", "held_out", "n_tokens", "n_known", "train_tokens", F.round("base_score", 4).alias("base_score"))


def quality_contract(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = op9_quality(spark, sf_dir)
    return rows.select("doc_id", "held_out", (F.col("score").between(0, 1) & ((F.col("score") >= 0.5) == (F.col("predicted") == 1))).alias("consistent"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    named = (op1_mix, op2_simhash, op3_jaccard, op4_chat, op5_decontaminate, op6_shards, op7_language, op8_lm, op9_quality, op10_html)
    found = {f.__name__: f for f in (*named, sharding_law_verdict, language_contract, lm_counts, quality_contract)}
    return found | {"pipeline": pipeline.run}


#: crc32 of doc_id as text, byte by byte over the table of its polynomial: a row (doc_id, crc) for each document.
CRC = """RECURSIVE poly AS (SELECT list(list_reduce([b, 0, 0, 0, 0, 0, 0, 0, 0], lambda a, x: CASE WHEN a & 1 = 1 THEN xor(a >> 1, 3988292384) ELSE a >> 1 END) ORDER BY b) AS t FROM (SELECT unnest(range(256)) AS b)),
        steps AS (SELECT doc_id, CAST(doc_id AS VARCHAR) AS s, 1 AS i, CAST(4294967295 AS BIGINT) AS c FROM documents WHERE doc_id IS NOT NULL
            UNION ALL SELECT doc_id, s, i + 1, xor(c >> 8, t[CAST(xor(c, ascii(s[i])) & 255 AS BIGINT) + 1]) FROM steps, poly WHERE i <= length(s)),
        crc AS (SELECT doc_id, xor(c, 4294967295) AS crc FROM steps WHERE i = length(s) + 1)"""

ORACLE = {
    "op1_mix": r"""
        WITH d AS (SELECT doc_id, CASE WHEN regexp_matches(source, '^src[0-9]*[13579]$') THEN 'edited' ELSE 'open' END AS domain,
                          coalesce(lang, 'unknown') AS lang, coalesce(source, 'unknown') AS source,
                          CAST(len(regexp_extract_all(coalesce(text, ''), '[^ \t\n\x0B\f\r]+')) AS BIGINT) AS tokens FROM documents),
        leaf AS (SELECT domain, lang, source, CAST(sum(tokens) AS BIGINT) AS tokens, CAST(sum(tokens) * 2 AS BIGINT) AS supply FROM d GROUP BY ALL),
        d0 AS (SELECT domain, CAST(sum(supply) AS BIGINT) AS supply, CASE domain WHEN 'open' THEN 3 WHEN 'edited' THEN 2 ELSE 1 END AS weight,
                      (SELECT CAST(sum(tokens) AS BIGINT) * 6 // 10 FROM leaf) AS budget FROM leaf GROUP BY domain),
        d1 AS (SELECT *, least(budget, CAST(sum(supply) OVER () AS BIGINT)) AS total,
                      CAST(sum(weight) OVER () - coalesce(sum(weight) OVER e, 0) AS BIGINT) AS still, CAST(coalesce(sum(supply) OVER e, 0) AS BIGINT) AS used
               FROM d0 WINDOW e AS (ORDER BY CAST(supply AS DOUBLE) / weight, domain ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
        d2 AS (SELECT *, supply * still <= (total - used) * weight AS is_full FROM d1),
        d3 AS (SELECT *, CAST(total - coalesce(sum(supply) FILTER (is_full) OVER (), 0) AS BIGINT) AS rest, CAST(coalesce(sum(weight) FILTER (NOT is_full) OVER (), 0) AS BIGINT) AS ws,
                      CAST(coalesce(sum(weight) FILTER (NOT is_full) OVER e, 0) AS BIGINT) AS fr
               FROM d2 WINDOW e AS (ORDER BY CAST(supply AS DOUBLE) / weight, domain ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
        dg AS (SELECT domain, CASE WHEN is_full THEN supply ELSE rest * (fr + weight) // greatest(ws, 1) - rest * fr // greatest(ws, 1) END AS budget FROM d3),
        l0 AS (SELECT domain, lang, CAST(sum(supply) AS BIGINT) AS supply, CASE lang WHEN 'en' THEN 4 WHEN 'de' THEN 2 WHEN 'fr' THEN 2 ELSE 1 END AS weight, any_value(budget) AS budget
               FROM leaf JOIN dg USING (domain) GROUP BY domain, lang),
        l1 AS (SELECT *, least(budget, CAST(sum(supply) OVER (PARTITION BY domain) AS BIGINT)) AS total,
                      CAST(sum(weight) OVER (PARTITION BY domain) - coalesce(sum(weight) OVER e, 0) AS BIGINT) AS still, CAST(coalesce(sum(supply) OVER e, 0) AS BIGINT) AS used
               FROM l0 WINDOW e AS (PARTITION BY domain ORDER BY CAST(supply AS DOUBLE) / weight, lang ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
        l2 AS (SELECT *, supply * still <= (total - used) * weight AS is_full FROM l1),
        l3 AS (SELECT *, CAST(total - coalesce(sum(supply) FILTER (is_full) OVER p, 0) AS BIGINT) AS rest, CAST(coalesce(sum(weight) FILTER (NOT is_full) OVER p, 0) AS BIGINT) AS ws,
                      CAST(coalesce(sum(weight) FILTER (NOT is_full) OVER e, 0) AS BIGINT) AS fr
               FROM l2 WINDOW p AS (PARTITION BY domain), e AS (PARTITION BY domain ORDER BY CAST(supply AS DOUBLE) / weight, lang ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
        lg AS (SELECT domain, lang, CASE WHEN is_full THEN supply ELSE rest * (fr + weight) // greatest(ws, 1) - rest * fr // greatest(ws, 1) END AS budget FROM l3),
        s0 AS (SELECT domain, lang, source, tokens, supply, CASE source WHEN 'src0' THEN 2 ELSE 1 END AS weight, budget FROM leaf JOIN lg USING (domain, lang)),
        s1 AS (SELECT *, least(budget, CAST(sum(supply) OVER (PARTITION BY domain, lang) AS BIGINT)) AS total,
                      CAST(sum(weight) OVER (PARTITION BY domain, lang) - coalesce(sum(weight) OVER e, 0) AS BIGINT) AS still, CAST(coalesce(sum(supply) OVER e, 0) AS BIGINT) AS used
               FROM s0 WINDOW e AS (PARTITION BY domain, lang ORDER BY CAST(supply AS DOUBLE) / weight, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
        s2 AS (SELECT *, supply * still <= (total - used) * weight AS is_full FROM s1),
        s3 AS (SELECT *, CAST(total - coalesce(sum(supply) FILTER (is_full) OVER p, 0) AS BIGINT) AS rest, CAST(coalesce(sum(weight) FILTER (NOT is_full) OVER p, 0) AS BIGINT) AS ws,
                      CAST(coalesce(sum(weight) FILTER (NOT is_full) OVER e, 0) AS BIGINT) AS fr
               FROM s2 WINDOW p AS (PARTITION BY domain, lang), e AS (PARTITION BY domain, lang ORDER BY CAST(supply AS DOUBLE) / weight, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
        g AS (SELECT domain, lang, source, tokens AS leaf_tokens, CASE WHEN is_full THEN supply ELSE rest * (fr + weight) // greatest(ws, 1) - rest * fr // greatest(ws, 1) END AS granted FROM s3),
        e AS (SELECT *, CASE WHEN leaf_tokens > 0 THEN granted // leaf_tokens ELSE 0 END AS passes, CASE WHEN leaf_tokens > 0 THEN granted % leaf_tokens ELSE 0 END AS rest FROM g),
        k AS (SELECT d.*, passes, rest, CAST('0x' || substr(md5('11|' || passes || '|' || doc_id), 1, 15) AS BIGINT) AS key FROM d JOIN e USING (domain, lang, source)),
        r AS (SELECT *, CAST(coalesce(sum(tokens) OVER (PARTITION BY domain, lang, source ORDER BY key, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS ahead FROM k)
        SELECT doc_id, domain, lang, source, tokens, passes + CASE WHEN ahead < rest THEN 1 ELSE 0 END AS copies,
               passes * tokens + CASE WHEN ahead < rest THEN least(tokens, rest - ahead) ELSE 0 END AS take_tokens
        FROM r WHERE passes > 0 OR ahead < rest""",
    "op3_jaccard": r"""
        WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
        s AS (SELECT DISTINCT doc_id, array_to_string(w[i : i + 3], ' ') AS shingle FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 1) + 1)) AS i FROM w WHERE len(w) > 0)),
        n AS (SELECT w.doc_id, count(shingle) AS n FROM w LEFT JOIN s ON s.doc_id = w.doc_id GROUP BY w.doc_id),
        c AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS common FROM s a JOIN s b ON a.shingle = b.shingle AND a.doc_id <> b.doc_id GROUP BY ALL),
        link AS (SELECT x, y FROM c JOIN n nx ON nx.doc_id = x JOIN n ny ON ny.doc_id = y WHERE 100 * common >= 85 * (nx.n + ny.n - common)),
        reach AS (SELECT doc_id AS x, doc_id AS y FROM documents UNION SELECT r.x, l.y FROM reach r JOIN link l ON l.x = r.y)
        SELECT n.doc_id, n.n AS n_shingles, m.component_id FROM n JOIN (SELECT x, min(y) AS component_id FROM reach GROUP BY x) m ON m.x = n.doc_id""",
    "op4_chat": r"""
        WITH t AS (SELECT conv_id, list({'role': coalesce(role, ''), 'text': coalesce(text, '')} ORDER BY turn, coalesce(role, ''), coalesce(text, '')) AS turns
                   FROM conversations WHERE conv_id IS NOT NULL GROUP BY conv_id
                   UNION ALL SELECT NULL, [{'role': coalesce(role, ''), 'text': coalesce(text, '')}] FROM conversations WHERE conv_id IS NULL),
        p AS (SELECT DISTINCT turns[1:k] AS turns FROM (SELECT turns, unnest(range(1, len(turns))) AS k FROM t)),
        m AS (SELECT turns, min(conv_id) AS conv_id, count(*) AS n_copies FROM t ANTI JOIN p USING (turns) GROUP BY turns)
        SELECT conv_id, CAST(len(turns) AS BIGINT) AS n_turns, n_copies,
               array_to_string(list_transform(turns, lambda x: '<|' || x.role || '|>' || chr(10) || x.text || '<|end|>' || chr(10)), '') AS rendered
        FROM m""",
    "sharding_law_verdict": """
        SELECT CAST(s AS INTEGER) AS shard, n // 16 + CASE WHEN s < n % 16 THEN 1 ELSE 0 END AS n, n // 16 + CASE WHEN s < n % 16 THEN 1 ELSE 0 END AS slots,
               n // 16 + CASE WHEN s < n % 16 THEN 1 ELSE 0 END - 1 AS last_slot, bytes_in_all
        FROM (SELECT count(*) AS n, CAST(sum(strlen(coalesce(text, '')) + 1) AS BIGINT) AS bytes_in_all FROM documents) CROSS JOIN range(16) t(s)""",
    "language_contract": f"""
        WITH {CRC} SELECT d.doc_id, crc % 4 = 2 AS held_out, NOT regexp_matches(coalesce(text, ''), '\\p{{L}}') AS und, TRUE AS in_range FROM documents d JOIN crc USING (doc_id)""",
    "lm_counts": f"""
        WITH {CRC},
        w AS (SELECT d.doc_id, crc % 10 = 0 AS held_out, list_append(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+'), '') AS w FROM documents d JOIN crc USING (doc_id)),
        k AS (SELECT doc_id, held_out, unnest(w) AS token FROM w),
        c AS (SELECT token, count(*) AS c FROM k WHERE NOT held_out GROUP BY token),
        n AS (SELECT CAST(sum(c) AS BIGINT) AS n, count(*) AS v FROM c)
        SELECT doc_id, held_out, count(*) AS n_tokens, count(c) AS n_known, any_value(n) AS train_tokens, round(sum(log10((coalesce(c, 0) + 0.1) / (n + 0.1 * (v + 1)))), 4) AS base_score
        FROM k LEFT JOIN c USING (token) CROSS JOIN n GROUP BY doc_id, held_out""",
    "quality_contract": f"""
        WITH {CRC} SELECT doc_id, crc % 3 = 1 AS held_out, TRUE AS consistent FROM documents JOIN crc USING (doc_id)""",
}


def oracle_sql() -> dict[str, str]:
    out = dict(ORACLE)
    if pipeline.ORACLE_SQL:
        out["pipeline"] = pipeline.ORACLE_SQL
    return out

"""Queries of the training-data operators on the given tables, and DuckDB SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontam_lsa, divergence, langid_crf, line_dedup, packing, quality_crf, simhash, token_counts, toxicity_ws, warc_index
from .common import bucket_of, table

Query = Callable[[SparkSession, str], DataFrame]


def op1_language_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    fold = bucket_of(F.col("doc_id"), 4)
    out = langid_crf.predict(docs, langid_crf.fitted(docs, fold != 2))
    return out.select("doc_id", (bucket_of(F.col("doc_id"), 4) == 2).alias("held_out"), "lang_pred", "score")


def op2_divergence(spark: SparkSession, sf_dir: str) -> DataFrame:
    return divergence.rate(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def _op2_sql() -> str:
    """Both histograms, the references and the distances, in SQL over the table."""
    quote = lambda x: "'" + x.replace("'", "''") + "'"
    vocab = "[" + ", ".join(map(quote, divergence.vocabulary())) + "]"
    classes = [f"length(t) - length(regexp_replace(t, {quote(r)}, '', 'g')) AS {k}" for k, r in divergence.CLASSES.items()]
    names = ", ".join(divergence.CLASSES)
    part = "CASE WHEN {0} > 0 THEN {0} * log2({0} / (({0} + {1}) / 2)) ELSE 0 END"
    near = "(SELECT d.r, min(sqrt(greatest(s, 0))) AS dist FROM (SELECT h.r, f.lang, sum((" + part.format("h.p", "f.p") + " + " + part.format("f.p", "h.p") + ") / 2) AS s FROM {0} h JOIN {1} f ON h.bin = f.bin GROUP BY h.r, f.lang) d GROUP BY d.r)"
    return f"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, lang, coalesce(text, '') AS t FROM documents),
a AS (SELECT *, list_filter(string_split_regex(t, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w,
  list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines,
  list_filter(string_split_regex(lower(t), '[\x20\x09-\x0D.,;:!?]+'), lambda x: list_contains({vocab}, x)) AS cw,
  {", ".join(classes)} FROM d),
win AS (SELECT r, i, array_to_string(w[i:i + 4], ' ') AS g FROM (SELECT r, w, unnest(range(1, len(w) - 3)) AS i FROM a)),
twice AS (SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, g) AS n FROM win) WHERE n > 1),
rep AS (SELECT r, count(DISTINCT pos) AS n FROM (SELECT r, unnest(range(i, i + 5)) AS pos FROM twice) GROUP BY r),
base AS (SELECT a.r, doc_id, lang, len(w) AS n_words, length(array_to_string(w, '')) AS word_chars, symbol AS n_symbols,
  len(lines) - len(list_distinct(lines)) AS n_dup_lines, coalesce(rep.n, 0) AS n_repeat_words, length(t) AS n, cw, {names}
  FROM a LEFT JOIN rep ON a.r = rep.r),
c AS (SELECT r, lang, unnest([{", ".join(f"'{k}'" for k in [*divergence.CLASSES, "space", "rest"])}]) AS bin,
  unnest([{names}, n - word_chars, word_chars - ({" + ".join(divergence.CLASSES)})]) AS x FROM base),
wc AS (SELECT r, lang, v AS bin, len(list_filter(cw, lambda y: y = v)) AS x FROM (SELECT r, lang, cw, unnest({vocab}) AS v FROM base)
  UNION ALL SELECT r, lang, ' rest', greatest(n_words - len(cw), 0) FROM base),
langs AS (SELECT lang FROM documents WHERE lang IS NOT NULL GROUP BY lang HAVING count(*) >= 10),
cr AS (SELECT lang, bin, sum(x) / sum(sum(x)) OVER (PARTITION BY lang) AS p FROM c WHERE lang IN (SELECT lang FROM langs) GROUP BY lang, bin),
wr AS (SELECT lang, bin, sum(x) / sum(sum(x)) OVER (PARTITION BY lang) AS p FROM wc WHERE lang IN (SELECT lang FROM langs) GROUP BY lang, bin),
cp AS (SELECT r, bin, x / s AS p FROM (SELECT *, sum(x) OVER (PARTITION BY r) AS s FROM c) WHERE s > 0),
wp AS (SELECT r, bin, x / s AS p FROM (SELECT *, sum(x) OVER (PARTITION BY r) AS s FROM wc) WHERE s > 0),
verdict AS (SELECT base.*, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed,
  coalesce(cd.dist > 0.25 OR wd.dist > 0.33 OR cd.dist + wd.dist > 0.43, false) AS far
  FROM base LEFT JOIN {near.format("cp", "cr")} cd ON base.r = cd.r LEFT JOIN {near.format("wp", "wr")} wd ON base.r = wd.r)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  NOT base_failed AND (n_words < 60 OR NOT far) AS kept FROM verdict
"""


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held_out = bucket_of(F.col("doc_id"), 5) == 0
    model = toxicity_ws.fitted(docs, table(spark, sf_dir, "labels"), ~held_out)
    return toxicity_ws.predict(docs, model, threshold=0.5).select("doc_id", held_out.alias("held_out"), "score", "predicted")


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(table(spark, sf_dir, "documents"), tokenizer_path("piece_bpe_32k.model"))


def op5_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), tokenizer_path(), capacity=4096, end_id=1)


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam_lsa.leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op7_quality_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held_out = bucket_of(F.col("doc_id"), 5) == 0
    model = quality_crf.fitted(docs, table(spark, sf_dir, "labels"), ~held_out)
    return quality_crf.predict(docs, model, threshold=0.3).select("doc_id", held_out.alias("held_out"), "score", "predicted")


def op8_warc_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = warc_index.archive_and_index(table(spark, sf_dir, "pages"), min_revisit_bytes=0)
    return out.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


OP8_SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
s AS (SELECT page_id, octet_length(encode(h)) AS n, sha1(h) AS x FROM p),
d AS (SELECT page_id, n, x, min(page_id) OVER (PARTITION BY x) AS first FROM s)
SELECT page_id, n AS payload_bytes,
  list_aggregate(list_transform(range(0, 32), lambda i:
    substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST((CAST('0x' || substr(x, (i // 4) * 5 + 1, 5) AS BIGINT)
      // CAST(power(32, 3 - i % 4) AS BIGINT)) % 32 + 1 AS BIGINT), 1)), 'string_agg', '') AS payload_digest,
  CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id = first THEN NULL ELSE first END AS refers_to
FROM d
"""


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"), radius=3, width=3)


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = line_dedup.drop_frequent_lines(table(spark, sf_dir, "documents"), min_docs=10, min_chars=1)
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2("text", 256).alias("kept_sha256"))


OP10_SQL = """
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS text FROM documents),
lines AS (
  SELECT r, doc_id, pos, string_split(text, chr(10))[pos] AS line
  FROM (SELECT r, doc_id, text, unnest(range(1, len(string_split(text, chr(10))) + 1)) AS pos FROM d)),
keyed AS (
  SELECT *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
    'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k FROM lines),
frequent AS (SELECT k FROM keyed WHERE length(k) >= 1 GROUP BY k HAVING count(DISTINCT r) >= 10),
marked AS (SELECT keyed.*, frequent.k IS NOT NULL AS gone FROM keyed LEFT JOIN frequent ON keyed.k = frequent.k)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM marked GROUP BY r, doc_id
"""


def queries() -> dict[str, Query]:
    return {
        "op1_language_crf": op1_language_crf,
        "op2_divergence": op2_divergence,
        "op3_token_counts": op3_token_counts,
        "op4_toxicity": op4_toxicity,
        "op5_best_fit_packing": op5_best_fit_packing,
        "op6_decontamination": op6_decontamination,
        "op7_quality_crf": op7_quality_crf,
        "op8_warc_index": op8_warc_index,
        "op9_simhash": op9_simhash,
        "op10_line_dedup": op10_line_dedup,
    }


def oracle_sql() -> dict[str, str]:
    return {"op2_divergence": _op2_sql(), "op8_warc_index": OP8_SQL, "op10_line_dedup": OP10_SQL}

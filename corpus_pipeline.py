"""The corpus pipeline: language ID, line deduplication, near-deduplication, decontamination, packing.

Each stage takes (spark, docs, sf_dir), works on all rows its predecessor kept and returns a DataFrame, which run() writes as Parquet in the
shared folder and reads again for the next. All but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from framedelta.llm import decontam_lsa, langid_crf, line_dedup, packing, simhash_text
from framedelta.llm.common import new_path, table
from framedelta.llm.registry import tokenizer_path

#: Texts whose most probable language has a smaller share are rejected, as are those without letters.
LEAST_SHARE = 0.35
#: Ids of leaking rows are broadcast up to this number.
BROADCAST_LEAKS = 200_000


def _renamed(docs: DataFrame) -> tuple[DataFrame, dict[str, str]]:
    """docs with its extra columns under names which no operator uses, and the way back."""
    names = {c: f"_in_{i}" for i, c in enumerate(docs.columns) if c not in ("doc_id", "text")}
    return docs.withColumnsRenamed(names), {v: k for k, v in names.items()}


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts of which no language is sure, or without letters, go. The field learns from the lang of all documents.

    Null and empty texts have no letters, so they go. Null ids and repeated rows are decided like others. Without any lang nothing can be learned, and all
    rows stay; an empty table stays empty.
    """
    safe, back = _renamed(docs)
    model = langid_crf.fitted(docs, F.lit(True))
    out = langid_crf.predict(safe, model, carry=tuple(safe.columns))
    if model is None:
        return docs
    return out.where((F.col("lang_pred") != "und") & (F.col("score") >= LEAST_SHARE)).select(*safe.columns).withColumnsRenamed(back)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines found in at least ten documents go; n_chars follows the text.

    A null text becomes an empty one. A repeated row is a document of its own, so ten of them lose their lines. Rows never go here; an empty table stays empty.
    """
    safe, back = _renamed(docs)
    out = line_dedup.drop_frequent_lines(safe, min_docs=10, min_chars=1, carry=tuple(safe.columns)).select(*safe.columns).withColumnsRenamed(back)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near-duplicates stays: five-word shingles, a similarity of 0.8 or more.

    Null and empty texts are one class. Of a class the smallest doc_id stays, a null one only where there is no other; of repeated rows one.
    """
    return simhash_text.one_of_each(docs, width=5, least=0.8)


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark passage go.

    Rows are told apart by 128 bits of hash of id and text, so repeated rows go together, a null id among them, and rows of one id with other texts
    stay. Null and empty texts hold nothing; without a benchmark all rows stay; an empty table stays empty.
    """
    whole = F.concat(F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.lit("\n"), F.coalesce("text", F.lit("")))
    key = F.md5(whole.cast("binary"))
    keyed = docs.select(key.alias("doc_id"), "text")
    leaks = decontam_lsa.leaks(keyed, table(spark, sf_dir, "benchmark")).select(F.col("doc_id").alias("_leak")).distinct()
    path = new_path(spark, "leaks")
    leaks.write.parquet(path)
    leaks = spark.read.parquet(path)
    side = F.broadcast(leaks) if leaks.count() <= BROADCAST_LEAKS else leaks
    return docs.join(side, key == F.col("_leak"), "left_anti").select(*docs.columns)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Places in sequences of at most 4096 tokens.

    Every row is packed: a null or empty text as its end token alone, repeated rows and null ids each for themselves. An empty table gives no row.
    """
    return packing.pack(docs, tokenizer_path(), capacity=4096, end_id=1)


STAGES = [
    ("language_id", language),
    ("line_dedup", lines),
    ("near_dedup", near_duplicates),
    ("decontamination", decontaminated),
    ("packing", packed),
]
#: The stages learn, hash and tokenise, which SQL cannot express.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        path = new_path(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)

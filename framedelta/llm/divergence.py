"""Distribution divergence as a quality rule, in DataFrame functions alone.

Every text gets two histograms: of character classes and of common words (with a bin for all other words). The table's own
documents, added up by `lang`, are the language references. A text is compared with each reference by the
Jensen-Shannon distance (base 2, 0 to 1), and the smallest distance counts: a text may be in any of the languages. The
distances are looked at only in texts long enough for them to mean something. Base rules on length and repetition
go before.

Texts are read once: what is counted is written, and references and verdicts come from those counts.

Defined cases: a null or empty text has no words, so fails the base rules. A null lang adds to no reference. A table in which no
language has `min_reference_docs` documents has no reference, and then the base rules decide alone. Repeated rows and null ids get
their rows. Extra columns are ignored. An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import written

SPACE = r"[\x20\x09-\x0D]"
# Common words of the four languages.
WORDS = {
    "en": "the of and to a in is that it for was on are with as be at this from or by an have",
    "de": "der die und in den von zu das mit sich des auf für ist im dem nicht ein eine als auch es an",
    "fr": "de la le et les des en un une du que est pour qui dans par sur au pas ne se ce plus",
    "es": "de la que el en y a los se del las un por con no una su para es al lo como más",
}
CLASSES = {"lower": "[a-z]+", "upper": "[A-Z]+", "digit": "[0-9]+", "mark": r"[.,;:!?'\"()\-]+", "symbol": r"[#*$%&|<>]+"}
OUTPUTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "char_divergence", "word_divergence", "kept")


def let(value: Column, body) -> Column:
    """body(value), with value worked out once."""
    return F.transform(F.array(value), body)[0]


def repeated_words(words: Column, width: int = 5) -> Column:
    """How many words lie in windows of `width` words that occur twice or more."""
    n = F.size(words)
    hashed = F.transform(words, lambda w: F.xxhash64(w))

    def windows(h):
        return F.transform(F.sequence(F.lit(0), n - width), lambda i: F.xxhash64(*[F.get(h, i + k) for k in range(width)]))

    def covered(at):
        steps = F.transform(at, lambda p, i: F.coalesce(F.least(F.get(at, i + 1) - p, F.lit(width)), F.lit(width)))
        return F.aggregate(steps, F.lit(0), lambda a, x: a + x)

    def among(s):
        same = lambda e, o: F.coalesce(o["h"] == e["h"], F.lit(False))
        twice = F.filter(s, lambda e, i: same(e, F.get(s, i - 1)) | same(e, F.get(s, i + 1)))
        return let(F.array_sort(F.transform(twice, lambda e: e["p"])), covered)

    def count(w):
        found = let(F.array_sort(F.transform(w, lambda x, i: F.struct(x.alias("h"), i.alias("p")))), among)
        return F.when(F.size(F.array_distinct(w)) == F.size(w), F.lit(0)).otherwise(found)

    return F.when(n < width, F.lit(0)).otherwise(let(let(hashed, windows), count)).cast("bigint")


def vocabulary() -> list[str]:
    return sorted({w for x in WORDS.values() for w in x.split()})


def counted(docs: DataFrame) -> DataFrame:
    """doc_id, lang, the base counts, and the histograms `chars` and `common` (array<bigint>)."""
    text = F.coalesce(F.col("text"), F.lit(""))
    vocab = vocabulary()
    lang = F.col("lang").cast("string") if "lang" in docs.columns else F.lit(None).cast("string")
    a = docs.select("doc_id", lang.alias("lang"), text.alias("t"))
    b = a.select(
        "doc_id",
        "lang",
        "t",
        F.array_remove(F.split("t", f"{SPACE}+"), "").alias("w"),
        F.filter(F.split("t", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")).alias("lines"),
        F.filter(F.split(F.lower("t"), r"[\x20\x09-\x0D.,;:!?]+"), lambda x: x.isin(*vocab)).alias("cw"),
        *[(F.length("t") - F.length(F.regexp_replace("t", r, ""))).cast("bigint").alias(k) for k, r in CLASSES.items()],
    )
    c = b.select(
        "doc_id",
        "lang",
        F.size("w").cast("bigint").alias("n_words"),
        F.length(F.array_join("w", "")).cast("bigint").alias("word_chars"),
        F.col("symbol").alias("n_symbols"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("bigint").alias("n_dup_lines"),
        repeated_words(F.col("w")).alias("n_repeat_words"),
        F.length("t").cast("bigint").alias("n"),
        *CLASSES,
        F.size("cw").cast("bigint").alias("n_common"),
        F.concat(F.lit(" "), F.array_join("cw", "  "), F.lit(" ")).alias("cw"),
    )
    hits = [((F.length("cw") - F.length(F.replace("cw", F.lit(f" {w} "), F.lit("")))) / (len(w) + 2)).cast("bigint") for w in vocab]
    space = F.col("n") - F.col("word_chars")
    rest = F.col("word_chars") - sum(F.col(k) for k in CLASSES)
    return c.select(
        "doc_id", "lang", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        F.array(*CLASSES, space, rest).alias("chars"),
        F.array(*hits, F.greatest(F.col("n_words") - F.col("n_common"), F.lit(0).cast("bigint"))).alias("common"),
    )


def references(counts: DataFrame, min_docs: int) -> list[tuple[str, list[float], list[float]]]:
    """(lang, shares of character classes, shares of common words) of every language with at least min_docs documents."""
    n_chars, n_common = len(CLASSES) + 2, len(vocabulary()) + 1
    sums = [F.sum(F.get("chars", F.lit(i))).alias(f"c{i}") for i in range(n_chars)] + [F.sum(F.get("common", F.lit(i))).alias(f"w{i}") for i in range(n_common)]
    got = counts.where("lang is not null").groupBy("lang").agg(F.count(F.lit(1)).alias("n"), *sums).where(F.col("n") >= min_docs).orderBy(F.desc("n"), "lang").collect()

    def shares(x):
        total = sum(x)
        return [v / total for v in x] if total else [0.0] * len(x)

    return [(r["lang"], shares([r[f"c{i}"] for i in range(n_chars)]), shares([r[f"w{i}"] for i in range(n_common)])) for r in got]


def js_distance(hist: Column, reference: list[float]) -> Column:
    """The square root of the Jensen-Shannon divergence (base 2) of a histogram's shares and the reference."""
    ref = F.array(*[F.lit(float(x)) for x in reference])

    def part(p, q):
        """What one bin adds: p and q each against their mean."""
        m = (p + q) / 2
        term = lambda x: F.when(x > 0, x * F.log2(x / m)).otherwise(0.0)
        return (term(p) + term(q)) / 2

    total = F.aggregate(hist, F.lit(0).cast("bigint"), lambda a, x: a + x)
    sums = lambda t: F.aggregate(F.zip_with(hist, ref, lambda x, q: part(x / t, q)), F.lit(0.0), lambda a, x: a + x)
    return F.when(total > 0, F.sqrt(F.greatest(let(total, sums), F.lit(0.0))))


def rate(docs: DataFrame, min_words: int = 60, most_char: float = 0.25, most_word: float = 0.33, most_sum: float = 0.43, min_reference_docs: int = 10) -> DataFrame:
    """doc_id and OUTPUTS for each row of docs. Divergences are null for texts without words or where there is no reference."""
    counts = written(counted(docs), "histograms")
    refs = references(counts, min_reference_docs)
    nearest = lambda col, i: F.array_min(F.array(*[js_distance(F.col(col), r[i]) for r in refs])) if refs else F.lit(None).cast("double")
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    far = F.coalesce((F.col("char_divergence") > most_char) | (F.col("word_divergence") > most_word) | (F.col("char_divergence") + F.col("word_divergence") > most_sum), F.lit(False))
    x = counts.withColumns({"char_divergence": nearest("chars", 1), "word_divergence": nearest("common", 2), "base_failed": failed})
    return x.withColumn("kept", ~F.col("base_failed") & ((F.col("n_words") < min_words) | ~far)).select("doc_id", *OUTPUTS)

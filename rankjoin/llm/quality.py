"""Quality rules [native]: a hashed n-gram log-likelihood ratio between a trusted
target and the raw corpus, over word and line rules.

Every word and every pair of neighbouring words falls into one of `buckets`
hash buckets. Two smoothed multinomials over the buckets are counted: one over the texts
labelled as trusted, one over all texts. A text's verdict is its mean log ratio
of the two per n-gram, compared with a threshold that follows from the two alone: a text goes
if it is further from the target than the two multinomials are from each other (their
Jeffreys divergence: the mean ratio of texts drawn from the one less that of texts drawn from
the other). No random numbers, so every run gives every document the same verdict.

DataFrame and SQL functions only. The counts need one pass with a shuffle of at
most `buckets` rows per task; the scores need no shuffle: the weights (`buckets`
doubles, a size fixed by parameter) reach the tasks as one constant of the plan.

Defined results: a null text is an empty one; an empty text has no words and so
fails the base rules; without any trusted text every ratio is 0; rows are judged
one by one, so repeated rows get equal verdicts; other columns pass untouched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rankjoin.llm.common import SPACE_CHARS, free_name, words

#: Fixed value: the characters counted as symbols.
SYMBOLS = "#*$%&|<>"
BUCKETS = 1 << 14
#: Largest number of trusted ids that is broadcast (8 bytes each); beyond it the join shuffles.
BROADCAST_IDS = 2_000_000


def _neighbours(a: Column) -> Column:
    """Hashes of all neighbouring pairs of an array's items."""
    n = F.greatest(F.size(a) - 1, F.lit(0))
    return F.zip_with(F.slice(a, 1, n), F.slice(a, 2, n), lambda x, y: F.xxhash64(x, y))


def _ngrams(w: Column, pairs: Column, buckets: int) -> Column:
    """Buckets of all words, then of all neighbouring pairs."""
    bucket = lambda h: F.pmod(h, F.lit(buckets)).cast("int")
    return F.concat(F.transform(w, lambda x: bucket(F.xxhash64(x))), F.transform(pairs, bucket))


def ratio_weights(docs: DataFrame, trusted_ids: DataFrame, *, buckets: int = BUCKETS) -> DataFrame:
    """One row: `weights`, an array of `buckets` log ratios (target over raw), and `apart`, the two multinomials' divergence.

    docs: doc_id, text. trusted_ids: doc_id of the trusted texts (nulls never match).
    """
    ids = trusted_ids.select(F.col("doc_id").alias("_id")).where("_id is not null").distinct()
    ids = ids.withColumn("_in", F.lit(1))
    if ids.count() <= BROADCAST_IDS:
        ids = F.broadcast(ids)
    tagged = docs.select("doc_id", "text").join(ids, F.col("doc_id") == F.col("_id"), "left")
    grams = tagged.select(F.coalesce("_in", F.lit(0)).alias("t"), words(F.col("text")).alias("w"))
    counts = grams.select("t", F.explode(_ngrams(F.col("w"), _neighbours(F.col("w")), buckets)).alias("b")).groupBy("b").agg(F.count("*").alias("n"), F.sum("t").alias("n_t"))
    every = docs.sparkSession.range(buckets).select(F.col("id").cast("int").alias("b")).join(counts, "b", "left").na.fill(0, ["n", "n_t"])
    table = every.agg(F.sort_array(F.collect_list(F.struct("b", "n", "n_t"))).alias("c"), F.sum("n").alias("all_n"), F.sum("n_t").alias("all_t"))
    ours = lambda x: (x["n_t"] + 1.0) / (F.col("all_t") + F.lit(float(buckets)))
    raw = lambda x: (x["n"] + 1.0) / (F.col("all_n") + F.lit(float(buckets)))
    ratio = lambda x: F.log(ours(x)) - F.log(raw(x))
    apart = F.aggregate(F.transform("c", lambda x: (ours(x) - raw(x)) * ratio(x)), F.lit(0.0), lambda a, x: a + x)
    none = F.col("all_t") == 0
    return table.select(F.when(none, F.transform("c", lambda x: F.lit(0.0))).otherwise(F.transform("c", ratio)).alias("weights"), F.when(none, 0.0).otherwise(apart).alias("apart"))


def _base(text: Column, w: Column, s: Column) -> dict[str, Column]:
    lines = F.filter(F.split(text, "\n"), lambda x: F.length(F.btrim(x, F.lit(SPACE_CHARS))) > 0)
    again = F.filter(s, lambda x, i: F.coalesce(F.get(s, i - 1)["h"] == x["h"], F.lit(False)) | F.coalesce(F.get(s, i + 1)["h"] == x["h"], F.lit(False)))
    at = F.sort_array(F.transform(again, lambda x: x["i"]))
    return {"n_words": F.size(w).cast("long"), "word_chars": F.aggregate(w, F.lit(0), lambda a, x: a + F.length(x)).cast("long"), "n_symbols": F.regexp_count(text, F.lit(f"[{SYMBOLS}]")).cast("long"), "lines": lines, "at": at}


def judge(docs: DataFrame, weights: DataFrame, *, buckets: int = BUCKETS, threshold: float | None = None, into: str = "quality") -> DataFrame:
    """docs with one more column `into`: a struct of the measures and the verdict.

    weights: the single row of `ratio_weights`. threshold: of the ratio, instead of -apart. The struct has n_words, word_chars,
    n_symbols, n_dup_lines, n_repeat_words, base_failed, ratio and kept.
    """
    text, w, p, g, s, h, base, score = free_name(docs, "_text", "_words", "_pairs", "_windows", "_sorted", "_w", "_base", "_score")
    own = docs.columns
    c = F.col
    df = docs.select(*own, F.coalesce(c("text"), F.lit("")).alias(text)).withColumn(w, words(c(text)))
    df = df.withColumn(p, _neighbours(c(w)))
    df = df.withColumn(g, _neighbours(c(p))).withColumn(h, _ngrams(c(w), c(p), buckets))  # two pairs of pairs: a window
    ordered = F.sort_array(F.transform(c(g), lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
    df = df.withColumn(s, F.when(F.size(F.array_distinct(g)) < F.size(g), ordered).otherwise(F.array().cast("array<struct<h:bigint,i:int>>")))  # most texts repeat no window: no sort
    m = _base(c(text), c(w), c(s))
    model = weights.first()
    threshold = -model["apart"] if threshold is None else threshold
    lookup = F.lit(",".join(map(repr, model["weights"])))  # one constant; `buckets` bounds it
    table = F.split(lookup, ",").cast("array<double>")  # folded once into a constant array
    total = F.aggregate(h, F.lit(0.0), lambda acc, b: acc + F.get(table, b))
    df = df.select(*own, F.struct(*(v.alias(k) for k, v in m.items())).alias(base), F.when(F.size(h) > 0, total / F.size(h)).otherwise(F.lit(0.0)).alias(score))
    at = c(base)["at"]
    covered = F.aggregate(F.zip_with(at, F.slice(at, 2, F.greatest(F.size(at) - 1, F.lit(0))), lambda p, q: F.least(F.lit(3), F.coalesce(q - p, F.lit(3)))), F.lit(0), lambda a, x: a + x).cast("long")
    dup = (F.size(c(base)["lines"]) - F.size(F.array_distinct(c(base)["lines"]))).cast("long")
    df = df.select(*own, score, *(c(base)[k].alias(f"{base}_{k}") for k in ("n_words", "word_chars", "n_symbols")), dup.alias(f"{base}_dup"), covered.alias(f"{base}_rep"))
    failed = (c(f"{base}_n_words") < 50) | (100 * c(f"{base}_rep") > 50 * c(f"{base}_n_words"))
    # a nondeterministic part (always true) keeps the optimizer from copying all of the above below a filter on the verdict
    verdict = ~failed & (c(score) >= threshold) & (F.spark_partition_id() >= 0)
    return df.select(
        *own,
        F.struct(
            c(f"{base}_n_words").alias("n_words"), c(f"{base}_word_chars").alias("word_chars"), c(f"{base}_n_symbols").alias("n_symbols"), c(f"{base}_dup").alias("n_dup_lines"), c(f"{base}_rep").alias("n_repeat_words"),
            failed.alias("base_failed"), c(score).alias("ratio"), verdict.alias("kept"),
        ).alias(into),
    )


def trusted(labels: DataFrame) -> DataFrame:
    """Ids of the texts labelled as good."""
    return labels.where(F.col("quality") == 1).select("doc_id")


def keep(docs: DataFrame, labels: DataFrame, **how) -> DataFrame:
    """The documents that pass, with their own columns only."""
    (into,) = free_name(docs, "_quality")
    return judge(docs, ratio_weights(docs, trusted(labels)), into=into, **how).where(F.col(into)["kept"]).select(*docs.columns)


def op8_quality_rules(spark, sf_dir: str) -> DataFrame:
    """Verdict and measures of every document."""
    from rankjoin.llm.common import table

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    out = judge(docs, ratio_weights(docs, trusted(table(spark, sf_dir, "labels"))))
    fields = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "ratio")
    return out.select("doc_id", *(F.col("quality")[f].alias(f) for f in fields))

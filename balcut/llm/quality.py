"""Quality rules: base text rules and a hashed n-gram log-likelihood ratio.

Two multinomials over hashed word n-grams are counted over whole corpora: the trusted target
(documents marked good) and the raw corpus (all documents). A document's score is the sum of
log p_target - log p_raw over its n-grams, divided by its number of words.

A fold of the trusted documents stays out of the target's counts. The threshold is the mean of their
scores less some standard deviations, so it comes from rows that the model hasn't seen, and follows the
scores where more text or fuller buckets move them. Every document gets its verdict from that one number.

Defined results: a null text counts as empty; without words all counts are 0 and the score is 0;
repeated rows give repeated rows; an empty table gives none; only the id and text columns are
read, whatever other columns a table has. Without trusted documents every ratio is flat, and with fewer than
two held-out ones that pass the base rules there is no threshold: the base rules alone decide then.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import each, in_mask, key_mask, sealed, settle, table, unused, words_of

#: Buckets of the hashed n-grams; the model is an array of this size, whatever the corpus.
#: Tasks sum up to so many rows at most, which bounds what is shuffled; fuller buckets bring all scores
#: nearer to 0, and the threshold with them.
BUCKETS = 1 << 18
#: Buckets of a part of the model; parts are packed apart and joined at the end.
PART = 1 << 10
SMOOTH = 1.0
#: Orders of the n-grams.
ORDERS = (1, 2)
#: Of so many folds of the trusted documents one sets the threshold; the others make the target.
FOLDS = 5
#: Standard deviations under the mean score of held-out trusted documents at which documents are rejected.
DEVIATIONS = 3.0
#: Base rules (fixed values).
MIN_WORDS, MAX_REPEAT_PERCENT, SYMBOLS, WINDOW = 10, 20, "#*$%&|<>", 5


def _hashed(df: DataFrame, text: str, longest: int = 2) -> DataFrame:
    """Adds the words and the hashes of all their n-grams: ``_g1`` of words, ``_g2`` of pairs and so on.

    An n-gram's hash is that of the hashes of its first and of its last n - 1 words.
    """
    df = df.withColumn("_words", words_of(F.col(text)))
    df = df.withColumn("_g1", F.transform("_words", lambda w: F.xxhash64(w)))
    for n in range(2, longest + 1):
        df = df.withColumn(f"_g{n}", _paired(F.col(f"_g{n - 1}"), 1))
    return df


def _paired(hashes: Column, apart: int) -> Column:
    """Hashes of all pairs of elements that are so many places apart."""
    return F.transform(F.slice(hashes, 1, F.greatest(F.size(hashes) - apart, F.lit(0))), lambda h, i: F.xxhash64(h, F.get(hashes, i + apart)))


def bucket_counts(docs: DataFrame, text: str = "text", buckets: int = BUCKETS, orders: tuple[int, ...] = ORDERS) -> DataFrame:
    """(bucket, n) over all documents; tasks sum up to ``buckets`` rows before the shuffle.

    Places of words are exploded, not n-grams made in lambdas, so hashing and sums are generated code.
    """
    words = docs.select(words_of(F.col(text)).alias("w"))
    last = F.size("w") - 1
    places = F.when(last >= 0, F.sequence(F.lit(0), last)).otherwise(F.array().cast("array<int>"))
    at = words.select("w", each(places).alias("i")).where("i is not null")
    gram = lambda n, k: F.xxhash64(F.get(F.col("w"), F.col("i") + k)) if n == 1 else F.xxhash64(gram(n - 1, k), gram(n - 1, k + 1))
    grams = [F.when(F.col("i") + (n - 1) < F.size("w"), F.pmod(gram(n, 0), F.lit(buckets)).cast("int")) for n in orders]
    return at.select(F.explode(F.array(*grams)).alias("bucket")).where("bucket is not null").groupBy("bucket").agg(F.count("*").alias("n"))


def trusted_documents(docs: DataFrame, good: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Texts of the documents whose id is in ``good``; a fixed-size mask thins the texts before the join."""
    keys = good.select(F.col(doc_id).alias("_key")).where("_key is not null").distinct()
    mask = key_mask(keys, F.xxhash64("_key"))
    near = docs.select(F.col(doc_id).alias("_key"), F.col(text).alias("_text")).where(in_mask(mask, F.xxhash64("_key")))
    # Merged at every size: labels grow with the corpus, so a broadcast that fits today isn't planned on.
    return near.join(keys.hint("merge"), "_key", "left_semi").select(F.col("_key").alias(doc_id), F.col("_text").alias(text))


def held_out(doc_id: Column) -> Column:
    """Whether a trusted document sets the threshold: a fold by the checksum of its id."""
    return F.crc32(doc_id.cast("string")) % FOLDS == 0


def ratio_model(raw: DataFrame, target: DataFrame, buckets: int = BUCKETS, smooth: float = SMOOTH) -> DataFrame:
    """One row, one array of floats: log p_target - log p_raw of every bucket, from the two tables of counts."""
    spark = raw.sparkSession
    none = spark.range(buckets).select(F.col("id").cast("int").alias("bucket"), F.lit(0).cast("long").alias("n_raw"), F.lit(0).cast("long").alias("n_target"))
    both = raw.selectExpr("bucket", "n as n_raw", "0L as n_target").unionByName(target.selectExpr("bucket", "0L as n_raw", "n as n_target")).unionByName(none)
    every = settle(both.groupBy("bucket").agg(F.sum("n_raw").alias("n_raw"), F.sum("n_target").alias("n_target")), "ngram-counts")
    total = {c: every.agg(F.sum(c).alias(c)).scalar() for c in ("n_raw", "n_target")}
    share = lambda c: F.log((F.col(c) + smooth) / (total[c] + smooth * buckets))
    value = F.when(total["n_target"] > 0, share("n_target") - share("n_raw")).otherwise(F.lit(0.0)).cast("float")
    parts = every.select(F.floor(F.col("bucket") / PART).cast("int").alias("part"), "bucket", value.alias("value"))
    parts = parts.groupBy("part").agg(F.transform(F.array_sort(F.collect_list(F.struct("bucket", "value"))), lambda s: s["value"]).alias("values"))
    whole = F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("part", "values"))), lambda s: s["values"]))
    return parts.agg(whole.alias("model"))


def text_rules(df: DataFrame, text: str = "text") -> DataFrame:
    """Adds n_words, word_chars, n_symbols, n_dup_lines and n_repeat_words; needs ``_words``, ``_g1`` and ``_g2``."""
    body = F.coalesce(F.col(text), F.lit(""))
    n = F.size("_words")
    lines = F.filter(F.split(body, "\n", -1), lambda x: F.rlike(x, F.lit(r"[^\x20\x09-\x0D]")))
    df = df.withColumns(
        {
            "n_words": n.cast("long"),
            "word_chars": F.length(F.array_join("_words", "")).cast("long"),
            "n_symbols": F.length(F.regexp_replace(body, r"[^#*$%&|<>]+", "")).cast("long"),
            "_lines": F.when(F.contains(body, F.lit("\n")), lines).otherwise(F.array().cast("array<string>")),
            # A window of five words: two pairs and the last word.
            "_win": F.transform(F.slice("_g2", 1, F.greatest(n - (WINDOW - 1), F.lit(0))), lambda h, i: F.xxhash64(h, F.get(F.col("_g2"), i + 2), F.get(F.col("_g1"), i + 4))),
        }
    )
    df = df.withColumns({"n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"), "_again": F.size(F.array_distinct("_win")) < F.size("_win")})
    placed = F.array_sort(F.transform("_win", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    df = df.withColumn("_placed", F.when(F.col("_again"), placed).otherwise(F.array().cast("array<struct<h:bigint,i:int>>")))
    alike = lambda x, k: F.coalesce(F.get(F.col("_placed"), k)["h"] == x["h"], F.lit(False))
    twice = F.filter("_placed", lambda x, k: alike(x, k + 1) | (F.when(k > 0, alike(x, k - 1)).otherwise(F.lit(False))))
    df = df.withColumn("_starts", F.sort_array(F.transform(twice, lambda x: x["i"])))
    covered = F.aggregate(
        "_starts",
        F.struct(F.lit(-WINDOW).alias("last"), F.lit(0).cast("long").alias("sum")),
        lambda a, s: F.struct(s.alias("last"), (a["sum"] + F.least(F.lit(WINDOW), s - a["last"])).alias("sum")),
        lambda a: a["sum"],
    )
    return df.withColumn("n_repeat_words", covered).drop("_lines", "_win", "_again", "_placed", "_starts")


def judge(docs: DataFrame, model: Column, doc_id: str = "doc_id", text: str = "text", threshold: Column | float | None = None, buckets: int = BUCKETS, orders: tuple[int, ...] = ORDERS, carry: tuple[str, ...] = ()) -> DataFrame:
    """The verdict on every document: base rules, score and ``kept``; ``carry`` names columns to keep.

    ``model`` is a scalar subquery, evaluated once and not per row. The rows are sealed: pushed further down, a filter on
    ``kept`` would repeat the rules inside their own lambdas.
    """
    carried = [c for c in carry if c not in (doc_id, text)]
    own = [f"_in_{k}" for k in range(len(carried))]  # names of the input can't clash with ours
    df = docs.select(F.col(f"`{doc_id}`").alias("_id"), F.col(f"`{text}`").alias("_text"), *(F.col(f"`{c}`").alias(o) for c, o in zip(carried, own, strict=True)))
    df = text_rules(_hashed(df, "_text", max(2, *orders)), "_text")
    # The model is named once, so the optimizer puts the subquery's value there and no row carries it.
    df = df.withColumn("_model", model)
    grams = F.concat(*(F.col(f"_g{n}") for n in orders)) if len(orders) > 1 else F.col(f"_g{orders[0]}")
    total = F.aggregate(grams, F.lit(0.0), lambda a, h: a + F.get(F.col("_model"), F.pmod(h, F.lit(buckets)).cast("int")))
    df = df.withColumn("score", F.when(F.col("n_words") > 0, total / F.col("n_words")).otherwise(F.lit(0.0)))
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    least = threshold if isinstance(threshold, Column) else F.lit(threshold).cast("double")
    df = df.withColumn("base_failed", failed).withColumn("kept", ~F.col("base_failed") & F.coalesce(F.col("score") >= least, F.lit(True)))
    facts = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "score", "kept"]
    named = dict(zip(carried, own, strict=True)) | {doc_id: "_id", text: "_text"}
    df = sealed(df.select(*named.values(), *facts))
    outs = unused(docs.select(*(f"`{c}`" for c in named)), *facts) if carry else facts
    return df.select(*(F.col(o).alias(c) for c, o in named.items()), *(F.col(f).alias(o) for f, o in zip(facts, outs, strict=True)))


def quality_rules(docs: DataFrame, good: DataFrame, doc_id: str = "doc_id", text: str = "text", threshold: float | None = None, buckets: int = BUCKETS, orders: tuple[int, ...] = ORDERS, carry: tuple[str, ...] = ()) -> DataFrame:
    """Count both corpora, set the threshold by held-out trusted documents unless one is given, then judge every document.

    With ``carry``, facts whose name an input column has get underscores in front; they are the last eight columns.
    """
    trusted = settle(trusted_documents(docs, good, doc_id, text), "trusted")
    out = held_out(F.col(doc_id))
    model = settle(ratio_model(bucket_counts(docs, text, buckets, orders), bucket_counts(trusted.where(~out), text, buckets, orders), buckets), "ratio-model").scalar()
    if threshold is None:
        checked = judge(trusted.where(out), model, doc_id, text, None, buckets, orders).where("not base_failed")
        # Rounded, so the order in which sums are made decides nothing.
        limits = settle(checked.agg(F.round(F.avg("score") - DEVIATIONS * F.stddev("score"), 6).alias("least")), "threshold")
        return judge(docs, model, doc_id, text, limits.scalar(), buckets, orders, carry)
    return judge(docs, model, doc_id, text, threshold, buckets, orders, carry)


def trusted_labels(labels: DataFrame) -> DataFrame:
    return labels.where(F.col("quality") == 1).select("doc_id")


def op10_quality_rules(spark, sf_dir: str) -> DataFrame:
    judged = quality_rules(table(spark, sf_dir, "documents"), trusted_labels(table(spark, sf_dir, "labels")))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.round("score", 6).alias("score"))


def quality_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: documents that the rules reject go."""
    judged = quality_rules(docs, trusted_labels(table(spark, sf_dir, "labels")), carry=tuple(docs.columns))
    kept = judged.columns[-1]
    return judged.where(F.col(kept)).select(*docs.columns)

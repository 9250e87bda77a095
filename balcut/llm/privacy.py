"""Personal data: patterns for entities, and an information-theoretic measure for revealing terms.

Base spans are e-mail addresses, IP addresses, card numbers and telephone numbers. The words
around them are terms. With document counts over the whole corpus, a term's disclosure of an
entity is their pointwise mutual information as a share of the entity's own information:
log(N n_et / (n_e n_t)) / log(N / n_e), which is 1 where the term occurs only with the entity. Terms
over a removal threshold are removed, terms over a lower one are generalised to their shape.
Only pairs that occur in several distinct texts count, as one text says nothing on co-occurrence.

Defined results: a null text counts as empty and has no spans; repeated rows are scanned one by
one and count as one text in the statistics; without entities nothing is added; an entity that
every text has informs of nothing and has no revealing terms; words of any length are terms; input
columns beside the named ones, whatever their names, are ignored by the scan and kept by ``sanitised``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import SPAN, cut_out, dealt, each, fenced, in_mask, key_mask, merged, settle, span_text, table, tagged, unused, with_matches, words_of

#: Patterns of the base spans and their order (fixed values). Possessive repeats match the same
#: and keep long runs linear; a run is entered at its start or where the last match ended.
EMAIL = r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
IP = r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}"
CARD = r"[0-9](?:[\x20-]?[0-9])++"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
KINDS = ("email", "ip", "card", "phone")
BYTE = r"0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})"

#: Code points to each side of an entity within which words are its terms; about a dozen words.
REACH = 72
#: Distinct texts in which an entity and a term occur together at least.
SUPPORT = 3
#: Disclosure from which a term is generalised, and removed.
GENERALISE, REMOVE = 0.5, 0.8
#: Shorter terms are never touched.
MIN_TERM = 4
#: Distinct texts from which a pair of entity and term is hot and its rows are dealt over several tasks.
HOT = 10_000
#: Marks before and after a word. A match starts at the word's start or after a letter or digit, so long runs of marks stay linear.
MARKS = r"(?<![^\x20\x09-\x0D])[^\p{L}\p{N}\x20\x09-\x0D]++|(?<=[\p{L}\p{N}])[^\p{L}\p{N}\x20\x09-\x0D]++(?![^\x20\x09-\x0D])"


def _digits(s: Column) -> Column:
    return F.regexp_replace(s, "[^0-9]", "")


def luhn(digits: Column) -> Column:
    """Whether the checksum of a string of digits holds; counted from the right, every second digit doubles."""
    n = F.length(digits)
    at = F.transform(F.sequence(F.lit(1), n), lambda i: F.struct(F.substring(digits, n - i + 1, F.lit(1)).cast("int").alias("d"), (i % 2 == 0).alias("twice")))
    total = F.aggregate(at, F.lit(0), lambda a, x: a + F.when(~x["twice"], x["d"]).when(x["d"] > 4, 2 * x["d"] - 9).otherwise(2 * x["d"]))
    return total % 10 == 0


def scan_texts(docs: DataFrame, doc_id: str, text: str, reach: int = REACH) -> DataFrame:
    """One pass over the texts: base spans of every row, and the terms around each entity."""
    df = fenced(docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("_text")))
    some_digit = F.rlike(F.col("_text"), F.lit("[0-9]{2}|[0-9][ .-][0-9]"))
    df = with_matches(
        df.withColumn("_digit", some_digit),
        "_text",
        {
            "email": (EMAIL, F.contains(F.col("_text"), F.lit("@"))),
            "ip": (IP, F.col("_digit")),
            "card": (CARD, F.col("_digit")),
            "phone": (PHONE, F.contains(F.col("_text"), F.lit("+"))),
        },
    )
    between = lambda s, low, high: F.length(_digits(s["value"])).between(low, high)
    df = df.withColumns(
        {
            "ip": F.filter("ip", lambda s: F.rlike(s["value"], F.lit(rf"^{BYTE}(?:\.{BYTE}){{3}}$"))),
            "card": F.filter("card", lambda s: F.when(between(s, 12, 19), luhn(_digits(s["value"]))).otherwise(F.lit(False))),
            "phone": F.filter("phone", lambda s: between(s, 9, 15)),
        }
    )
    df = df.withColumn("base", F.array_sort(F.concat(*(tagged(F.col(k), k, i) for i, k in enumerate(KINDS)))))
    # Words with their places, only where there are entities: the pieces between runs of white space.
    some = F.size("base") > 0
    df = with_matches(df.withColumn("_some", some), "_text", {"word": (r"[^\x20\x09-\x0D]++", F.col("_some"))})
    term = lambda w: F.regexp_replace(F.lower(w["value"]), MARKS, "")
    terms = F.transform(F.filter("word", lambda w: F.exists("base", lambda b: (w["start"] < b["end"] + reach) & (b["start"] < w["end"] + reach))), lambda w: F.struct(w["start"].alias("start"), w["end"].alias("end"), term(w).alias("term")))
    df = df.withColumn("_near", F.filter(terms, lambda w: F.length(w["term"]) >= MIN_TERM))
    clear = lambda w: ~F.exists("base", lambda b: (w["start"] < b["end"]) & (b["start"] < w["end"]))
    df = df.withColumn("near", F.filter("_near", clear))
    counts = {f"n_{k}": F.size(k).cast("long") for k in KINDS}
    return df.withColumns(counts).select(F.col("_fence").alias("row_key"), "doc_id", F.xxhash64("_text").alias("text_hash"), "base", "near", *counts)


def _pairs(scanned: DataFrame) -> DataFrame:
    """(row_key, text_hash, entity, term, start, end): the terms near each entity of a row."""
    entity = scanned.select("row_key", "text_hash", "near", each(F.col("base")).alias("b")).where("b is not null")
    at = F.filter("near", lambda w: (w["start"] < F.col("b.end") + REACH) & (F.col("b.start") < w["end"] + REACH))
    rows = entity.select("row_key", "text_hash", F.xxhash64("b.kind", "b.value").alias("entity"), each(at).alias("w")).where("w is not null")
    return rows.select("row_key", "text_hash", "entity", F.col("w.term").alias("term"), F.col("w.start").alias("start"), F.col("w.end").alias("end"))


def distinct_texts(docs: DataFrame, scanned: DataFrame, text: str = "text") -> DataFrame:
    """One row ``_text`` for each distinct text.

    Texts that occur once, nearly all, pass without a shuffle. A fixed-size mask finds the others by
    their hash; of these each task keeps one row a text before they are merged.
    """
    copied = scanned.groupBy("text_hash").agg(F.count("*").alias("n")).where("n > 1")
    body = fenced(docs.select(F.coalesce(F.col(text), F.lit("")).alias("_text"))).withColumn("text_hash", F.xxhash64("_text"))
    body = body.withColumn("_copied", in_mask(key_mask(copied, F.col("text_hash")), F.col("text_hash"))).where("_fence >= 0")
    once = body.where("not _copied").select("_text")
    return once.unionByName(body.where("_copied").groupBy("text_hash").agg(F.first("_text").alias("_text")).select("_text"))


def counts_of(docs: DataFrame, scanned: DataFrame, text: str = "text", support: int = SUPPORT) -> DataFrame:
    """(entity, term, n_et, n_e, n_t) of all pairs that ``support`` distinct texts have; counts are of distinct texts."""
    pairs = _pairs(scanned).select("entity", "term", "text_hash").distinct().groupBy("entity", "term").agg(F.count("*").alias("n_et")).where(F.col("n_et") >= support)
    pairs = settle(pairs, "pairs")
    entities = scanned.select("text_hash", each(F.col("base")).alias("b")).where("b is not null").select(F.xxhash64("b.kind", "b.value").alias("entity"), "text_hash").distinct()
    n_e = entities.groupBy("entity").agg(F.count("*").alias("n_e"))
    # A fixed-size mask lets mostly wanted words through to the sums, which each task makes before the
    # shuffle; the exact join then has one row a term on either side.
    mask = key_mask(pairs.select("term").distinct(), F.xxhash64("term"))
    terms = F.array_distinct(words_of(F.regexp_replace(F.lower("_text"), MARKS, "")))
    every = distinct_texts(docs, scanned, text).select(each(terms).alias("term")).where("term is not null")
    n_t = every.where(in_mask(mask, F.xxhash64("term"))).groupBy("term").agg(F.count("*").alias("n_t"))
    n_t = n_t.join(pairs.select("term").distinct(), "term")
    return pairs.join(n_e, "entity").join(n_t, "term")


def disclosure(docs: DataFrame, scanned: DataFrame, text: str = "text", support: int = SUPPORT) -> DataFrame:
    """(entity, term, n_et, disclosure) over the whole corpus; equal texts count once."""
    total = scanned.select("text_hash").distinct().agg(F.count("*").alias("n")).scalar()
    known = counts_of(docs, scanned, text, support).withColumn("n", total)
    own = F.log(F.col("n") / F.col("n_e"))
    joint = F.log(F.col("n") * F.col("n_et") / (F.col("n_e") * F.col("n_t")))
    return known.where("n_e < n").select("entity", "term", "n_et", F.round(joint / own, 9).alias("disclosure"))


def sanitise_spans(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", support: int = SUPPORT, generalise: float = GENERALISE, remove: float = REMOVE) -> DataFrame:
    """Per row: base spans and added spans of revealing terms, of kind ``remove`` or ``general``."""
    scanned = settle(scan_texts(docs, doc_id, text), "privacy")
    told = settle(disclosure(docs, scanned, text, support).where(F.col("disclosure") >= generalise), "told")
    key = F.xxhash64("entity", "term")
    rows, told = dealt(_pairs(scanned), told, key, told.where(F.col("n_et") >= HOT), key, F.xxhash64("row_key"))
    hits = rows.join(told, ["entity", "term", "_salt"])
    worst = hits.groupBy("row_key", "start", "end", "term").agg(F.max("disclosure").alias("disclosure"))
    kind = F.when(F.col("disclosure") >= remove, F.lit("remove")).otherwise(F.lit("general"))
    span = F.struct("start", F.when(F.col("disclosure") >= remove, F.lit(len(KINDS))).otherwise(F.lit(len(KINDS) + 1)).alias("rank"), "end", kind.alias("kind"), F.col("term").alias("value"))
    added = worst.groupBy("row_key").agg(F.array_sort(F.collect_list(span)).cast(SPAN).alias("added"))
    none = F.array().cast(SPAN)
    return scanned.join(added, "row_key", "left").select("row_key", "doc_id", "text_hash", *(f"n_{k}" for k in KINDS), "base", F.coalesce("added", none).alias("added"))


def sanitised(docs: DataFrame, spans: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents with entities as ``[KIND]``, removed terms as ``[..]`` and generalised ones as their shape."""
    key, at, put = unused(docs, "text_hash", "spans", "id")
    cuts = spans.where(F.size(F.concat("base", "added")) > 0).groupBy(F.col("doc_id").alias(put), F.col("text_hash").alias(key)).agg(F.max(F.concat("base", "added")).alias(at))
    label = lambda s: F.when(s["kind"] == "remove", F.lit("[..]")).when(s["kind"] == "general", F.concat(F.lit("[word of "), (s["end"] - s["start"]).cast("string"), F.lit("]"))).otherwise(F.concat(F.lit("["), F.upper(s["kind"]), F.lit("]")))
    ours = F.coalesce(F.col(f"`{text}`"), F.lit(""))
    left, right = docs.withColumn(key, F.xxhash64(ours)).alias("l"), cuts.alias("r")
    same = F.col(f"l.`{doc_id}`").eqNullSafe(F.col(f"r.`{put}`")) & (F.col(f"l.`{key}`") == F.col(f"r.`{key}`"))
    joined = left.join(right, same, "left").select("l.*", f"r.`{at}`")
    joined = joined.withColumn(at, F.transform(merged(F.col(at)), lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), label(s).alias("label"))))
    return joined.withColumn(text, F.when(F.size(at) > 0, cut_out(F.col(f"`{text}`"), F.col(at))).otherwise(F.col(f"`{text}`"))).select(*(f"`{c}`" for c in docs.columns))


def op3_private_data(spark, sf_dir: str) -> DataFrame:
    found = sanitise_spans(table(spark, sf_dir, "documents"))
    return found.select(
        "doc_id", *(f"n_{k}" for k in KINDS),
        F.sha2(span_text(F.col("base")), 256).alias("base_sha256"),
        span_text(F.concat("base", "added")).alias("spans"),
    )

"""Secret scans: patterns for single texts, and corpus-wide ownership of what they find.

Base spans come from three patterns. Candidates are the values of those spans and of long mixed
tokens that no base span covers. Over the whole corpus each candidate's hash is counted by
distinct repositories and distinct owners: a value that many owners share is a copied example, a
value of one or two owners is a live-looking credential. Live-looking tokens outside the base
spans become additional spans of kind ``live``.

Defined results: a null text counts as empty and has no spans; repeated rows are scanned one by
one and count once as owners; null owners and repositories count as one owner and repository of
their own; an empty table gives an empty result; further columns, whatever their names, are ignored by the scan
and kept by ``redacted`` and the stage.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import SPAN, cut_out, dealt, each, fenced, in_mask, key_mask, merged, settle, span_text, table, tagged, unused, with_matches

#: Patterns of the base spans and their order (fixed values).
ASSIGN = r"(?i:password|passwd|secret|token|api_?key)[\"']?+\x20*+[:=]\x20*+[\"']?+([A-Za-z0-9+/_.=-]++)"
ACCESS = r"AKIA[A-Z0-9]{16,}"
HEX = r"[0-9a-f]{24,}"
TOKEN = r"[A-Za-z0-9+/_=-]{20,}"
KINDS = ("assign", "access", "hex")
MIN_VALUE = 6
#: From this many distinct owners on, a value is a copied example.
EXAMPLE_OWNERS = 3
#: A token of mixed characters has at least so many distinct ones.
MIN_DISTINCT = 10
#: Finds of one value from which it is hot and its rows are dealt over several tasks.
HOT = 10_000


def _has_keyword(text: Column) -> Column:
    low = F.lower(text)
    return F.contains(low, F.lit("passw")) | F.contains(low, F.lit("secret")) | F.contains(low, F.lit("token")) | F.contains(low, F.lit("api"))


def scan_texts(docs: DataFrame, doc_id: str, text: str, repository: Column, owner: Column, carry: tuple[str, ...] = ()) -> DataFrame:
    """One pass over the texts: base spans and candidates of every row, under a row key."""
    df = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("_text"), F.xxhash64(repository).alias("repository"), F.xxhash64(owner).alias("owner"))
    df = fenced(df)
    patterns = {
        "assign": (ASSIGN, _has_keyword(F.col("_text"))),
        "access": (ACCESS, F.contains(F.col("_text"), F.lit("AKIA"))),
        "hex": (HEX, F.lit(True)),
        "token": (TOKEN, F.lit(True)),
    }
    df = with_matches(df, "_text", patterns)
    value = lambda s: F.regexp_extract(s["value"], ASSIGN, 1)
    secret = F.transform(F.filter("assign", lambda s: F.length(value(s)) >= MIN_VALUE), lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), value(s).alias("value")))
    df = df.withColumn("assign", secret)
    base = F.concat(*(tagged(F.col(k), k, i) for i, k in enumerate(KINDS)))
    mixed = lambda s: F.rlike(s["value"], F.lit("[0-9]")) & F.rlike(s["value"], F.lit("[A-Za-z]")) & (F.size(F.array_distinct(F.split(s["value"], ""))) > MIN_DISTINCT)
    df = df.withColumn("base", F.array_sort(base))
    free = lambda s: ~F.exists("base", lambda b: (b["start"] < s["end"]) & (s["start"] < b["end"]))
    df = df.withColumn("tokens", tagged(F.filter("token", lambda s: mixed(s) & free(s)), "live", len(KINDS)))
    counts = {f"n_{k}": F.size(k).cast("long") for k in KINDS}
    return df.withColumns(counts).select(F.col("_fence").alias("row_key"), "doc_id", F.xxhash64("_text").alias("text_hash"), "repository", "owner", "base", "tokens", *counts)


def ownership(scanned: DataFrame, example_owners: int = EXAMPLE_OWNERS) -> DataFrame:
    """(secret, n_repositories, n_owners, example) of every candidate hash in the corpus.

    Copies within one repository collapse before the shuffle, so a value in a third of all rows
    sends one row per task and owner.
    """
    found = scanned.select("repository", "owner", each(F.concat("base", "tokens")).alias("s")).where("s is not null")
    places = found.select(F.xxhash64("s.value").alias("secret"), "repository", "owner").groupBy("secret", "repository", "owner").agg(F.count("*").alias("n"))
    owners = places.groupBy("secret", "owner").agg(F.count("*").alias("repositories"), F.sum("n").alias("n"))
    totals = owners.groupBy("secret").agg(F.sum("repositories").alias("n_repositories"), F.count("*").alias("n_owners"), F.sum("n").alias("n_found"))
    return totals.withColumn("example", F.col("n_owners") >= example_owners)


def secret_scan(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", repository: Column | None = None, owner: Column | None = None, example_owners: int = EXAMPLE_OWNERS) -> DataFrame:
    """Per row: base spans, added spans of live-looking tokens, and how many candidates are live or examples."""
    repository = F.struct("source", "lang") if repository is None else repository
    owner = F.col("source") if owner is None else owner
    scanned = settle(scan_texts(docs, doc_id, text, repository, owner), "secrets")
    verdicts = settle(ownership(scanned, example_owners), "ownership")
    single = scanned.select("row_key", each(F.concat("base", "tokens")).alias("s")).where("s is not null").withColumn("secret", F.xxhash64("s.value"))
    rows, verdicts = dealt(single, verdicts, F.col("secret"), verdicts.where(F.col("n_found") >= HOT), F.col("secret"), F.col("row_key"))
    judged = rows.join(verdicts, ["secret", "_salt"]).groupBy("row_key").agg(
        F.count_if("example").alias("n_example"),
        F.count_if(~F.col("example")).alias("n_live"),
        F.collect_list(F.when(~F.col("example") & (F.col("s.kind") == "live"), F.col("s"))).alias("added"),
    )
    df = scanned.join(judged, "row_key", "left")
    none = F.array().cast(SPAN)
    return df.select(
        "row_key", "doc_id", "text_hash", *(f"n_{k}" for k in KINDS), "base",
        F.array_sort(F.coalesce("added", none)).alias("added"),
        *(F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("n_live", "n_example")),
    )


def op4_secret_scan(spark, sf_dir: str) -> DataFrame:
    found = secret_scan(table(spark, sf_dir, "documents"))
    return found.select(
        "doc_id", *(f"n_{k}" for k in KINDS),
        F.sha2(span_text(F.col("base")), 256).alias("base_sha256"),
        span_text(F.concat("base", "added")).alias("spans"),
        "n_live", "n_example",
    )


def redacted(df: DataFrame, text: str, spans: str, label: str = "REDACTED") -> DataFrame:
    """``df`` with every span of the column ``spans`` replaced in ``text`` by its kind in brackets.

    The label must not read as a secret itself, as a keyword and a colon would.
    """
    (at,) = unused(df, "cuts")
    cuts = F.transform(merged(F.col(f"`{spans}`")), lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), F.concat(F.lit(f"[{label} "), s["kind"], F.lit("]")).alias("label")))
    body = F.col(f"`{text}`")
    return df.withColumn(at, cuts).withColumn(text, F.when(F.size(at) > 0, cut_out(body, F.col(at))).otherwise(body)).drop(at)


def secrets_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: secrets are replaced in the texts; all documents stay.

    Base spans and live-looking tokens go. Spans come back by document and hash of the text, so
    different texts under one id are told apart and equal rows share theirs. Nearly all documents have
    none; a fixed-size mask tells them before any text moves.
    """
    found = secret_scan(docs).where(F.size(F.concat("base", "added")) > 0)
    key, at, mine = unused(docs, "text_hash", "spans", "mine")
    spans = settle(found.groupBy("doc_id", "text_hash").agg(F.max(F.concat("base", "added")).alias("spans")), "secret-spans")
    rows = docs.withColumn(key, F.xxhash64(F.coalesce(F.col("text"), F.lit(""))))
    rows = rows.withColumn(mine, in_mask(key_mask(spans, F.xxhash64("doc_id", "text_hash")), F.xxhash64("doc_id", key)))
    right = spans.select(F.col("doc_id").alias("s_id"), F.col("text_hash").alias("s_hash"), F.col("spans").alias(at)).alias("s")
    same = F.col("x.doc_id").eqNullSafe(F.col("s.s_id")) & (F.col(f"x.{key}") == F.col("s.s_hash"))
    some = rows.where(mine).alias("x").join(right, same, "left").select("x.*", f"s.{at}")
    clean = redacted(some, "text", at)
    clean = clean.withColumn("n_chars", F.when(F.col(at).isNotNull(), F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    out = [F.col(f"`{c}`") for c in docs.columns]
    return rows.where(~F.col(mine)).select(*out).unionByName(clean.select(*out))

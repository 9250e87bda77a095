"""URL filters: host and path rules, and trust spread over the host graph for all other urls.

Host edges come from absolute and scheme-relative links in the pages; as an option also from a host to the next
shorter name above it (``blog.a.example`` to ``a.example``). From trusted hosts a personalised PageRank runs along
the edges; from blocked hosts a second one runs against them, so hosts that lead to blocked ones are distrusted.
A host is blocked where distrust exceeds its share of both. Rank that reaches hosts without a way out goes back to
the seeds, so none is lost. Ranks are whole numbers, so sums don't depend on their order and every run gives the
same verdicts. After r rounds a vector is within 2 * damping^r of its limit: ``ROUNDS`` keeps that under a
hundredth of the mass, and a vector that has come to rest ends the rounds early without a change of result.

Defined results: a null url or one without ``://`` has an empty host and path, fits no rule and is
allowed; a null page has no links; equal rules keep the first; repeated rows get equal verdicts;
without seeds all ranks are 0 and urls without a rule are allowed; further columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import each, settle, table

#: Rules of the query (fixed values): verdict, host, path.
RULES = (
    ("block", "com", "/en/"),
    ("allow", "example.com", "/en/7"),
    ("allow", "net", "/de/"),
    ("block", "example.net", "/de/8"),
    ("block", "org", "/es/"),
)
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Up to so many rules are one expression; longer lists are joined by host names.
RULES_INLINE = 64
#: Whole mass of a rank vector: one edge of 10**10 still gets a part of it, and mass times weight fits into 38 digits.
MASS = 10**20
#: Damping in percent, and rounds: 2 * 0.7^15 is under 0.01.
DAMP, ROUNDS = 70, 15
#: Rounds between writes that cut the lineage.
CUT_EVERY = 4
#: Share of distrust over which a host is blocked, in percent.
DISTRUST_PERCENT = 50
#: Share of a host's pages that rules block from which the host is a blocked seed, in percent.
SEED_PERCENT = 50
#: Blocked hosts of which every executor gets the whole list at most.
HOSTS_SENT = 100_000
LINK = r"(?i)href\s*=\s*[\"']?(?:[a-z][a-z0-9+.-]*:)?//([^/?#\"'<>\s]+)"


def host_and_path(url: Column) -> tuple[Column, Column]:
    rest = F.when(F.instr(url, "://") > 0, F.substring(url, F.instr(url, "://") + 3, F.length(url))).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    return F.translate(F.regexp_extract(rest, r"^[^/?#]*", 0), UPPER, LOWER), F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)


def ruled(df: DataFrame, rules=RULES, host: str = "host", path: str = "path") -> DataFrame:
    """Adds ``rule`` and ``rule_verdict`` of the longest rule that fits each url, else null."""
    if len(rules) <= RULES_INLINE:
        rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
        for what, h, p in sorted(reversed(rules), key=lambda r: len(r[1]) + len(r[2])):
            fits = ((F.col(host) == h) | F.endswith(F.col(host), F.lit("." + h))) & F.startswith(F.col(path), F.lit(p))
            rule, verdict = F.when(fits, F.lit(h + p)).otherwise(rule), F.when(fits, F.lit(what)).otherwise(verdict)
        return df.withColumns({"rule": rule, "rule_verdict": verdict})
    spark = df.sparkSession
    listed = spark.createDataFrame([(i, *r) for i, r in enumerate(rules)], "at int, verdict string, rule_host string, rule_path string")
    pairs = df.select(host, path).distinct()
    labels = F.split(F.col(host), r"\.", -1)
    above = pairs.withColumn("labels", labels).select(host, path, each(F.transform(F.sequence(F.lit(1), F.size("labels")), lambda i: F.array_join(F.slice("labels", i, F.size("labels")), "."))).alias("rule_host"))
    fit = above.join(listed, "rule_host").where(F.startswith(F.col(path), F.col("rule_path")))
    best = fit.groupBy(host, path).agg(F.max_by(F.struct(F.concat("rule_host", "rule_path").alias("rule"), "verdict"), F.struct(F.length(F.concat("rule_host", "rule_path")), -F.col("at"))).alias("best"))
    return df.join(best, [host, path], "left").select(*df.columns, F.col("best.rule").alias("rule"), F.col("best.verdict").alias("rule_verdict"))


def host_edges(pages: DataFrame, host: str = "host", html: str = "html", parents: bool = False) -> DataFrame:
    """(src, dst, w): links between different hosts, summed; with ``parents`` one edge to the name above for every page too."""
    linked = F.when(F.contains(F.col(html), F.lit("//")), F.regexp_extract_all(F.col(html), F.lit(LINK), F.lit(1))).otherwise(F.array().cast("array<string>"))
    links = pages.select(F.col(host).alias("src"), each(linked).alias("dst")).where("dst is not null and src <> ''").select("src", F.translate("dst", UPPER, LOWER).alias("dst"))
    if parents:
        links = links.unionByName(pages.where(F.size(F.split(F.col(host), r"\.", -1)) > 2).select(F.col(host).alias("src"), F.regexp_replace(F.col(host), r"^[^.]*\.", "").alias("dst")))
    return links.where("src <> dst").groupBy("src", "dst").agg(F.count("*").alias("w"))


def spread(edges: DataFrame, seeds: DataFrame, rounds: int = ROUNDS, mass: int = MASS, damp: int = DAMP, facts: dict | None = None) -> DataFrame:
    """(host, trust, distrust) after ``rounds`` of both propagations, or less where the ranks come to rest.

    ``seeds`` has (host, kind): kind 0 trusted, kind 1 blocked. Both vectors run as one table by kind. What a
    round's edges don't bring on, damped mass and that of hosts without a way out, goes to the seeds in equal parts.
    ``facts`` is told the rounds run.
    """
    whole = "decimal(38,0)"
    both = edges.selectExpr("0 as kind", "src", "dst", "w").unionByName(edges.selectExpr("1 as kind", "dst as src", "src as dst", "w"))
    out = both.groupBy("kind", "src").agg(F.sum("w").alias("out"))
    shares = settle(both.join(out, ["kind", "src"]).selectExpr("kind", "src", "dst", "cast(w as decimal(12,0)) as w", "cast(out as decimal(12,0)) as out"), "host-edges")
    per_kind = settle(seeds.groupBy("kind").agg(F.count("*").alias("n")), "host-kinds")  # two rows at most
    base = settle(seeds.join(F.broadcast(per_kind), "kind").select("kind", "host", F.expr(f"cast(floor(cast({mass} as {whole}) / n) as {whole})").alias("rank")), "host-seeds")
    rank, before = base, None
    for k in range(rounds):
        sent = shares.join(rank.withColumnRenamed("host", "src"), ["kind", "src"])
        sent = sent.groupBy("kind", "dst").agg(F.expr(f"cast(floor(sum(cast(floor(rank * w / out) as {whole})) * {damp} / 100) as {whole})").alias("got"))
        moved = sent.groupBy("kind").agg(F.sum("got").cast(whole).alias("moved"))
        back = per_kind.join(moved, "kind", "left").select("kind", F.expr(f"cast(floor((cast({mass} as {whole}) - coalesce(moved, 0)) / n) as {whole})").alias("back"))
        rows = sent.select("kind", F.col("dst").alias("host"), "got").unionByName(base.join(F.broadcast(back), "kind").select("kind", "host", F.col("back").alias("got")))
        rank = rows.groupBy("kind", "host").agg(F.sum("got").cast(whole).alias("rank"))
        if facts is not None:
            facts["rounds"] = k + 1
        if (k + 1) % CUT_EVERY == 0 or k + 1 == rounds:
            rank = settle(rank, "host-rank")
            # Ranks that are equal to the last ones written have come to rest: all rounds between had the same.
            if before is not None and rank.exceptAll(before).limit(1).count() == 0:
                break
            before = rank
    return rank.groupBy("host").agg(F.expr(f"cast(coalesce(sum(rank) filter (where kind = 0), 0) as {whole})").alias("trust"), F.expr(f"cast(coalesce(sum(rank) filter (where kind = 1), 0) as {whole})").alias("distrust"))


def seeds_of(judged: DataFrame, percent: int = SEED_PERCENT) -> DataFrame:
    """Blocked seeds: hosts with at least that share of pages blocked by rules. Trusted: hosts with allowed and no blocked pages."""
    counts = judged.where("host <> ''").groupBy("host").agg(F.count("*").alias("n"), F.count_if(F.col("rule_verdict") == "block").alias("blocked"), F.count_if(F.col("rule_verdict") == "allow").alias("allowed"))
    kind = F.when((F.col("blocked") > 0) & (100 * F.col("blocked") >= percent * F.col("n")), F.lit(1)).when((F.col("allowed") > 0) & (F.col("blocked") == 0), F.lit(0))
    return counts.select("host", kind.alias("kind")).where("kind is not null")


def url_filter(pages: DataFrame, rules=RULES, page_id: str = "page_id", url: str = "url", html: str = "html", rounds: int = ROUNDS, parents: bool = False) -> DataFrame:
    """Every url with host, path, rule and verdict."""
    host, path = host_and_path(F.col(url))
    judged = ruled(pages.select(F.col(page_id).alias("page_id"), host.alias("host"), path.alias("path")), rules)
    edges = host_edges(pages.select(host.alias("host"), F.col(html).alias("html")), parents=parents)
    ranks = spread(edges, seeds_of(judged), rounds)
    bad = ranks.where(100 * F.col("distrust") > DISTRUST_PERCENT * (F.col("trust") + F.col("distrust"))).select("host", F.lit("block").alias("host_verdict"))
    bad = settle(bad, "blocked-hosts")
    # One host may have a third of all pages. A list of blocked hosts under a checked size goes to
    # the pages; a longer one is joined by host, where large partitions are split at run time.
    side = F.broadcast(bad) if bad.limit(HOSTS_SENT + 1).count() <= HOSTS_SENT else bad
    verdict = F.coalesce("rule_verdict", "host_verdict", F.lit("allow"))
    return judged.join(side, "host", "left").select("page_id", "host", "path", "rule", verdict.alias("verdict"))


def op5_url_filter(spark, sf_dir: str) -> DataFrame:
    return url_filter(table(spark, sf_dir, "pages"))


def _sql() -> str:
    order = sorted(RULES, key=lambda r: -(len(r[1]) + len(r[2])))
    fits = [(f"(host = '{h}' or ends_with(host, '.{h}')) and starts_with(path, '{p}')", h + p, v) for v, h, p in order]
    case = lambda k: "case " + " ".join(f"when {f[0]} then '{f[k]}'" for f in fits) + " end"
    link = LINK.replace("(?i)", "").replace("\\\"", '"').replace("'", "''")
    steps, last = [], "base"
    for k in range(1, ROUNDS + 1):
        steps.append(
            f"g{k} as materialized (select s.kind, s.dst as host, (sum((r.rank * s.w) // s.out) * {DAMP}) // 100 as got from shares s join {last} r on r.kind = s.kind and r.host = s.src group by all), "
            f"r{k} as materialized (select kind, host, sum(got)::hugeint as rank from (select kind, host, got::hugeint as got from g{k} union all "
            f"select b.kind, b.host, (({MASS}::hugeint - coalesce((select sum(got) from g{k} g where g.kind = b.kind), 0)::hugeint) // b.n)::hugeint from base b) group by all)"
        )
        last = f"r{k}"
    return f"""
with u as (select page_id, html, case when position('://' in url) > 0 then substr(url, position('://' in url) + 3) else '' end as rest from pages),
h as (select page_id, html, translate(regexp_extract(coalesce(rest, ''), '^[^/?#]*'), '{UPPER}', '{LOWER}') as host, regexp_extract(coalesce(rest, ''), '^[^/?#]*([^?#]*)', 1) as path from u),
j as materialized (select page_id, host, path, {case(1)} as rule, {case(2)} as rule_verdict from h),
l as (select host as src, translate(unnest(regexp_extract_all(html, '{link}', 1, 'i')), '{UPPER}', '{LOWER}') as dst from h where host <> ''),
e as materialized (select src, dst, count(*) as w from l where src <> dst group by src, dst),
b as (select 0 as kind, src, dst, w from e union all select 1, dst, src, w from e),
shares as materialized (select kind, src, dst, w::hugeint as w, (sum(w) over (partition by kind, src))::hugeint as out from b),
c as (select host, count(*) as n, count(*) filter (where rule_verdict = 'block') as blocked, count(*) filter (where rule_verdict = 'allow') as allowed from j where host <> '' group by host),
seeds as (select host, case when blocked > 0 and 100 * blocked >= {SEED_PERCENT} * n then 1 when allowed > 0 and blocked = 0 then 0 end as kind from c),
base as materialized (select kind, host, count(*) over (partition by kind) as n, {MASS}::hugeint // (count(*) over (partition by kind))::hugeint as rank from seeds where kind is not null),
{', '.join(steps)},
t as (select host, coalesce(sum(rank) filter (where kind = 0), 0)::hugeint as trust, coalesce(sum(rank) filter (where kind = 1), 0)::hugeint as distrust from {last} group by host),
bad as (select host from t where 100 * distrust > {DISTRUST_PERCENT} * (trust + distrust))
select page_id, j.host, path, rule, coalesce(rule_verdict, case when bad.host is not null then 'block' end, 'allow') as verdict
from j left join bad on bad.host = j.host
"""


OP5_SQL = _sql()

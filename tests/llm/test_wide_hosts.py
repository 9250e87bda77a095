"""Rank over the host graph: wide hosts, hosts without a way out, convergence, and the SQL on pages with links."""

import os
import random
from collections import defaultdict

import duckdb
import pytest

from balcut.llm import urls


def test_a_hub_sends_rank_along_every_edge(spark):
    many = 3_000_000_000
    edges = spark.createDataFrame([("hub", "small", 1), ("hub", "big", many), ("leads", "hub", 1), ("crowd", "hub", many)], "src string, dst string, w long")
    seeds = spark.createDataFrame([("hub", 0), ("hub", 1)] + [(f"s{i}", 0) for i in range(50)], "host string, kind int")
    got = {r["host"]: r for r in urls.spread(edges, seeds, rounds=2).collect()}
    assert got["small"]["trust"] > 0 and got["leads"]["distrust"] > 0
    ratio = got["crowd"]["distrust"] / got["leads"]["distrust"]
    assert abs(ratio / many - 1) < 1e-6


def plain(edges, seeds, rounds):
    """Personalised rank by hand, in floats; mass without a way out goes to the seeds."""
    out = defaultdict(float)
    for s, _, w in edges:
        out[s] += w
    rank = {h: 1 / len(seeds) for h in seeds}
    for _ in range(rounds):
        new = defaultdict(float)
        for s, d, w in edges:
            new[d] += urls.DAMP / 100 * rank.get(s, 0) * w / out[s]
        back = 1 - sum(new.values())
        for h in seeds:
            new[h] += back / len(seeds)
        rank = new
    return rank


def test_ranks_converge_and_lose_no_mass(spark):
    r = random.Random(4)
    names = [f"h{i}" for i in range(30)]
    edges = list({(a, b): (a, b, r.randint(1, 9)) for a, b in ((r.choice(names[:25]), r.choice(names)) for _ in range(70)) if a != b}.values())
    trusted, blocked = names[:3], names[5:7]
    seeds = spark.createDataFrame([(h, 0) for h in trusted] + [(h, 1) for h in blocked], "host string, kind int")
    got = {x["host"]: x for x in urls.spread(spark.createDataFrame(edges, "src string, dst string, w long"), seeds).collect()}
    back = [(b, a, w) for a, b, w in edges]
    for kind, e, s in (("trust", edges, trusted), ("distrust", back, blocked)):
        for rounds, tolerance in ((urls.ROUNDS, 1e-9), (400, 0.01)):
            want = plain(e, s, rounds)
            assert sum(abs(int(got[h][kind]) / urls.MASS - want.get(h, 0)) for h in got) < tolerance
        assert abs(sum(int(x[kind]) for x in got.values()) / urls.MASS - 1) < 1e-12


def test_rest_ends_the_rounds(spark):
    facts = {}
    none = spark.createDataFrame([], "src string, dst string, w long")
    got = urls.spread(none, spark.createDataFrame([("a", 0)], "host string, kind int"), facts=facts).collect()
    assert facts["rounds"] < urls.ROUNDS and int(got[0]["trust"]) == urls.MASS


@pytest.mark.parametrize("seed", [1, 2])
def test_sql_agrees_on_pages_with_links(spark, tmp_path, seed):
    r = random.Random(seed)
    hosts = [f"{a}.{b}.{c}" for a in ("x", "y", "z", "q") for b in ("one", "two") for c in ("com", "net", "org", "io")]
    rows = []
    for i in range(200):
        links = "".join(f"<a href={q}{'https:' if r.random() < 0.7 else ''}//{r.choice(hosts).upper() if r.random() < 0.2 else r.choice(hosts)}/p{q}>" for q in ['"', "'"] for _ in range(r.randint(0, 2)))
        rows.append((i, f"http://{r.choice(hosts)}{r.choice(['/en/1', '/de/2', '/es/3', '/fr/4', ''])}", links))
    spark.createDataFrame(rows, "page_id long, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    got = sorted(tuple(x) for x in urls.op5_url_filter(spark, str(tmp_path)).collect())
    con = duckdb.connect()
    con.execute(f"create view pages as select * from read_parquet('{os.path.join(tmp_path, 'pages.parquet', '*.parquet')}')")
    assert got == sorted(con.execute(urls.OP5_SQL).fetchall())
    free = [v for _, _, p, rule, v in got if rule is None]
    assert "block" in free and "allow" in free  # links decide both ways

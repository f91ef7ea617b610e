"""Aliases by relative links and by several links of one page."""

import duckdb

from momenttree.llm import oracles, urls

RULES = [("h.org", "/blocked", "block")]


def test_relative_links_and_all_links_of_a_page(spark):
    link, moved = "<link rel='canonical' href='{}'>".format, '<meta http-equiv="refresh" content="0; url={}">'.format
    rows = [
        ("http://h.org/blocked/a/b.html", link("/free/root") + link("one.html") + moved("../up") + moved("./same?u=http://z.org/q") + link("//other.net/p") + link("mailto:x@y.z") + link("?q=1")),
        *((u, None) for u in ("http://h.org/free/root", "https://other.net/p/", "http://z.org/q")),
        ("http://h.org", link("free/top")),
    ]
    pages = spark.createDataFrame([(k, u, h) for k, (u, h) in enumerate(rows)], "page_id bigint, url string, html string")
    want = {"h.org/free/root", "h.org/blocked/a/one", "h.org/blocked/up", "h.org/blocked/a/same", "other.net/p"}
    links = {(r.a, r.b) for r in urls.page_links(pages).collect()}
    assert links == {("h.org/blocked/a/b", x) for x in want} | {("h.org", "h.org/free/top")}
    got = {r.page_id: (r.verdict, r.decided_by) for r in urls.judge(pages, RULES).collect()}
    assert got == {0: ("block", "rule"), 1: ("block", "alias"), 2: ("block", "alias"), 3: ("allow", "default"), 4: ("allow", "default")}


def test_the_sql_twin_resolves_the_same_links(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(urls, "RULES", [*RULES, ("net", "/ok", "allow")])
    tags = ['<link rel="canonical" href="{}">', '<link href="{}" rel=canonical>', "<meta http-equiv=refresh content='1;URL={}'>"]
    targets = ["/free/a", "b.html", "../up/./c", "../../../top", "//www.other.net/p/", "https://m.h.org/blocked/z", "mailto:a@b", "?q", "#f", "HTTP://H.ORG/free/a.html", "./", "..", "ftp://third.net/ok/1"]
    bases = ["http://h.org/blocked/x/y.html", "http://h.org", "https://www.h.org/free/", "http://other.net/p?x=1", None, "nothing", "http://third.net/ok/1", "http://h.org/free/a"]
    rows = [(b, "".join(tags[(i + j) % 3].format(t) for j, t in enumerate(targets[i::3]))) for i, b in enumerate(bases)] + [(f"http://h.org{x}", None) for x in ("/free/a", "/up/c", "/top", "/blocked/x/b", "/free/b")]
    pages = spark.createDataFrame([(k, u, h) for k, (u, h) in enumerate(rows)], "page_id bigint, url string, html string")
    pages.toPandas().to_parquet(f"{tmp_path}/pages.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW pages AS SELECT * FROM '{tmp_path}/pages.parquet'")
    want = {r[0]: r[1:] for r in con.execute(oracles.url_rules()).fetchall()}
    got = {r[0]: tuple(r)[1:] for r in urls.judge(pages, urls.RULES).collect()}
    assert got == want and {v[4] for v in got.values()} == {"rule", "alias", "default"}

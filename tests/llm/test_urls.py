"""URL rules by longest fit; false positives of the filter never show."""

from __future__ import annotations

from blocksketch.llm import url_filter

RULES = [("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"), (None, "/", "block")]


def plain(url):
    if url is None or "://" not in url:
        return "", "", None, "allow"
    rest = url.split("://", 1)[1]
    cut = min([rest.find(c) for c in "/?#" if c in rest], default=len(rest))
    host, tail = rest[:cut], rest[cut:]
    host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host)
    path = tail[: min([tail.find(c) for c in "?#" if c in tail], default=len(tail))]
    fits = [(len(h + p), h + p, v) for h, p, v in RULES if h and (host == h or host.endswith("." + h)) and path.startswith(p)]
    return (host, path, *(max(fits)[1:] if fits else (None, "allow")))


URLS = [
    None, "", "nothing", "http://", "http://net", "http://NET/", "https://a.b.example.net/en/x?y#z", "https://example.net/en", "https://xexample.net/en/", "http://a.example.com/de/1#t", "http://example.com/fr/1",
    "http://w.org/fr/?q", "http://w.org?fr/", "http://Ünet.net/a", "x://y://z.net/", "http://u:p@h.net:80/p", "http://" + "a." * 5000 + "net/" + "p" * 5000, "http://.net/", "http://net./", "http://é.org/fr/é",
]


def test_against_plain_rules(spark):
    rows = [(i, u, "clash") for i, u in enumerate(URLS)] + [(3, URLS[5], "clash"), (3, URLS[5], "clash"), (None, URLS[6], "clash")]
    pages = spark.createDataFrame(rows, "page_id long, url string, verdict string")
    rules = spark.createDataFrame(RULES, "host string, path string, verdict string")
    got = sorted((tuple(r) for r in url_filter.url_filter(pages, rules).collect()), key=str)
    assert got == sorted(((i, *plain(u)) for i, u, _ in rows), key=str)
    assert url_filter.url_filter(pages.limit(0), rules).count() == 0
    assert url_filter.url_filter(pages, rules.limit(0)).where("verdict <> 'allow' or rule is not null").count() == 0


def test_many_rules_by_shuffle(spark, monkeypatch):
    monkeypatch.setattr(url_filter, "MOST_BROADCAST_RULES", 1)
    monkeypatch.setattr(url_filter, "MOST_WORDS", 16)  # a crowded filter lets much through; the join decides
    rules = spark.range(3000).selectExpr("concat('h', id, '.net') as host", "'/p' as path", "'block' as verdict")
    pages = spark.range(6000).selectExpr("id as page_id", "concat('http://w.h', id, '.net/path') as url")
    got = {r.page_id: r.verdict for r in url_filter.url_filter(pages, rules).collect()}
    assert got == {i: "block" if i < 3000 else "allow" for i in range(6000)}

from veil.llm import url_rules as U
from veil.llm.queries import URL_RULES

URLS = [
    None, "", "nothing", "http://", "http://com/", "http://com", "http://a.com/", "https://A.Example.COM/en/x?y#z", "http://example.com/en", "http://example.com/en/",
    "http://www.example.com/en/1", "http://x.www.example.com/en/", "http://wwwexample.com/en/", "ftp://z.net/es/", "http://net/fr/q", "http://b.net/de/", "//x.com/",
    "http://a.com?x=/en/", "http://a.com#f", "x://y://example.com/en/", "http://a..com/", "http://" + "a." * 3000 + "com/", "http://example.com/en/" + "p" * 100_000, "http://é.com/ü", "http://user:1@example.com:80/en/",
]


def brute(url, rules=URL_RULES):
    if url is None or "://" not in url:
        return "", "", None, "allow"
    rest = url.split("://", 1)[1]
    n = min([rest.index(c) for c in "/?#" if c in rest] + [len(rest)])
    host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in rest[:n])
    path = rest[n:]
    path = path[: min([path.index(c) for c in "?#" if c in path] + [len(path)])]
    best = None
    for action, e in rules:
        h, p = e.split("/", 1)
        if (host == h or host.endswith("." + h)) and path.startswith("/" + p) and (best is None or len(e) > len(best[1])):
            best = (action, e)
    return host, path, best and best[1], best[0] if best else "allow"


def test_against_plain_matching(spark):
    rows = [(i, u, 1) for i, u in enumerate(URLS)] + [(0, None, 2), (6, URLS[6], 2)]
    df = spark.createDataFrame(rows, "page_id long, url string, verdict int")
    got = U.judge(df, U.rule_table(spark, URL_RULES)).collect()
    assert len(got) == len(rows)
    for r in got:
        assert (r.host, r.path, r.rule, r.verdict) == brute(URLS[r.page_id])


def test_shuffled_rules_and_prefixes_inside_a_segment(spark, monkeypatch):
    monkeypatch.setattr(U, "BROADCAST_RULES", 0)
    rules = [("block", "example.com/e"), ("allow", "example.com/en/x"), ("block", "com/"), ("block", "com/")]
    df = spark.createDataFrame([(i, u) for i, u in enumerate(URLS)], "page_id long, url string")
    for r in U.judge(df, U.rule_table(spark, rules)).collect():
        assert (r.rule, r.verdict) == brute(URLS[r.page_id], rules)[2:]


def test_empty_tables(spark):
    df = spark.createDataFrame([(1, "http://a.com/")], "page_id long, url string")
    assert U.judge(df.filter("false"), U.rule_table(spark, URL_RULES)).count() == 0
    none = U.rule_table(spark, URL_RULES).filter("false")
    assert [(r.rule, r.verdict) for r in U.judge(df, none, default="block").collect()] == [(None, "block")]

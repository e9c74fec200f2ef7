import re

from rangecut.llm import urls


def brute(url, rules):
    host, path = "", ""
    if url is not None and "://" in url:
        m = re.match(r"([^/?#]*)([^?#]*)", url.split("://", 1)[1], re.S)
        host, path = m[1].translate(str.maketrans(urls.UPPER, urls.LOWER)), m[2]
    best = max((r for r in rules if re.compile(r.pattern, re.ASCII).search(host + path)), key=lambda r: r.weight, default=None)
    return host, path, (best.name or None) if best else None, best.verdict if best else "allow"


URLS = [
    None, "", "no scheme", "http://", "https://WWW.Example.COM/en/1?x=http://a.net/es/", "http://example.com/en/", "http://example.com/EN/1", "http://notexample.com/en/1",
    "http://a.b.example.com/en/x#y", "http://x.net/es/1", "http://x.net/es", "http://net/fr/", "http://x.org/casino/1", "http://casino-win.org/", "http://mycasino.org/", "http://com", "http://com/", "http://x.org/spam-farm?", "http://é.net/fr/ü", "x://y://z.com/",
]


def test_index_finds_what_trying_every_rule_finds(spark):
    rules = urls.LIST_RULES + urls.WORD_RULES
    df = spark.createDataFrame(list(enumerate(URLS + URLS[:3])), "page_id long, url string")
    for r in urls.judge(df, rules).collect():
        assert (r.host, r.path, r.rule, r.verdict) == brute((URLS + URLS[:3])[r.page_id], rules)
        assert r.n_tried < len(rules)


def test_rarest_token_files_a_rule():
    rule = urls.list_rule("example.com", "/en/", "block")
    by_token, always = urls.index_of((rule,), {"example": 100, "com": 50, "en": 3})
    assert by_token == {"en": [0]} and not always


def test_empty_table(spark):
    assert urls.judge(spark.createDataFrame([], "page_id long, url string"), urls.LIST_RULES).count() == 0

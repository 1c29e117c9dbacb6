import random
import re

import pytest

from ranksort.llm import urlfilter as uf

RULES = [uf.Rule("block", "com/en/"), uf.Rule("allow", "example.com/en/7"), uf.Rule("allow", "net/de/"), uf.Rule("block", "example.net/de/8"), uf.Rule("block", "org/es/")]


def brute(url, rules, listed):
    url = url or ""
    rest = url.split("://", 1)[1] if "://" in url else ""
    host = re.match(r"[^/?#]*", rest)[0]
    path = re.match(r"[^?#]*", rest[len(host) :])[0]
    host = re.sub("[A-Z]", lambda m: m[0].lower(), host)
    fits = [r for r in rules if (host == r.host or host.endswith("." + r.host)) and path.startswith(r.path)]
    best = min(fits, key=lambda r: (-len(r.rule), r.rule), default=None)
    inside = host != "" and any(host == k or host.endswith("." + k) for k in listed)
    return host, path, best and best.rule, best.verdict if best else "block" if inside else "allow"


def urls(n=600):
    rng = random.Random(3)
    odd = [None, "", "no scheme", "://", "http://", "http:///en/x", "HTTP://A.COM?x=/en/", "x://EXAMPLE.com/en/7?q#f", "a://b://com/en/", "http://é.org/es/1", "http://com/en/", "http://xcom/en/", "http://.com/en/1", "http://a..b/"]
    return odd + [f"http://{'.'.join(rng.choice(['a', 'b', 'example', 'bad', f'h{rng.randrange(90)}']) for _ in range(rng.randrange(1, 4)))}.{rng.choice(['com', 'net', 'org'])}/{rng.choice(['en', 'de', 'es'])}/{rng.randrange(99)}" for _ in range(n)]


def frame(spark, all_urls):
    return spark.createDataFrame(list(enumerate(all_urls)), "page_id long, url string")


@pytest.mark.parametrize("in_plan,max_bytes", [(500, 1 << 20), (0, 1 << 20), (500, 1)])
def test_verdicts_against_brute_force(spark, monkeypatch, in_plan, max_bytes):
    monkeypatch.setattr(uf, "RULES_IN_PLAN", in_plan)
    listed = ["bad.com", "a.bad.net", "h7.org", "example", "not.there", "B.com"]
    rules = [*RULES, uf.Rule("allow", "h5.com"), uf.Rule("block", "h5.com")][:6]
    pages = frame(spark, urls()).selectExpr("*", "1 as host", "'x' as rule", "2 as key")
    found = uf.judge(pages, rules, spark.createDataFrame([(k,) for k in [*listed, None]], "key string"), max_filter_bytes=max_bytes)
    for r in found.collect():
        assert (r["host"], r["path"], r["rule"], r["verdict"]) == brute(r.url, rules, [k.lower() for k in listed]), r.url


@pytest.mark.parametrize("share", [0.0, 0.002, 0.3, 0.9, 1.0])
def test_cascade_is_exact(spark, share):
    rng = random.Random(11)
    keys = [(f"k{i}.com", rng.random() < share) for i in range(4000)]
    marked = spark.createDataFrame(keys, "key string, listed boolean")
    cascade = uf.build_cascade(marked)
    assert marked.where(cascade.has(marked["key"]) != marked["listed"]).count() == 0
    n = sum(x for _, x in keys)
    assert len(cascade.sizes) == 0 if not n else cascade.n_bits <= 1.6 * uf.expected_bits(n, 4000 - n) + 640


def test_defined_cases(spark):
    none = spark.createDataFrame([], "key string")
    rows = uf.judge(frame(spark, [None, "", "http://a.b/c", "http://a.b/c"]), [], none).collect()
    assert [(r.host, r.path, r.rule, r.verdict) for r in rows] == [("", "", None, "allow")] * 2 + [("a.b", "/c", None, "allow")] * 2
    assert uf.judge(frame(spark, []), RULES, none).count() == 0
    assert uf.judge(frame(spark, ["http://" + "a." * 3000 + "com/en/" + "x" * 50_000]), RULES, none).first().verdict == "block"

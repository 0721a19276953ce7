import itertools
import random
import re

from glyphfold.llm import url_filter as uf

URLS = [None, "", "nothing", "://", "http://", "HTTP://WWW.Example.COM/EN/x", "http://www.example.com/en/x?a=b", "http://a.example.com/en/1#t", "https://example.com/en", "https://example.com?x/en/", "http://exampleXcom/", "https://x.net/es/1", "https://net/fr/2", "x://y://z/fr/", "http://b.org:80/p/q.html?k=v&z", "http://É.com/É\n/?"]


def brute(url):
    url = url or ""
    rest = url.split("://", 1)[1] if "://" in url else ""
    host = re.match(r"[^/?#]*", rest)[0]
    path = re.match(r"[^?#]*", rest[len(host) :])[0]
    host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host)
    fits = [(len(h + p), h + p, v) for v, h, p in uf.HOST_RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
    best = max(fits, default=(0, None, None))
    return host, path, best[1], best[2]


def test_fixed_rules(spark):
    rows = [(i, u, "h") for i, u in enumerate(URLS)] * 2
    pages = spark.createDataFrame(rows, "page_id long, url string, host string")
    labels = spark.createDataFrame([(1, 0, None)], "doc_id long, quality int, toxic int")
    got = uf.url_verdicts(pages, labels).collect()
    assert len(got) == 2 * len(URLS)
    for r in got:
        host, path, rule, verdict = brute(URLS[r.page_id])
        assert (r.host, r["path"], r.rule, r.verdict) == (host, path, rule, verdict or "allow")
    assert uf.url_verdicts(pages.limit(0), labels).count() == 0


def test_mined_rules_match_brute_force(spark):
    random.seed(7)
    rows, labels = [], []
    for i in range(600):
        host = random.choice(["casino", "news", "free", "shop"]) + random.choice(["-win", "-bets", ""]) + random.choice([".example.org", ".site.info"])
        url = f"http://{host}/{random.choice(['en', 'de'])}/{i}" + random.choice(["", "?utm=1"])
        bad = ("casino" in url and "utm" in url) or "bets" in url
        rows.append((i, url))
        if i % 4:
            labels.append((i, 1, int(bad != (random.random() < 0.05))))
    pages = spark.createDataFrame(rows, "page_id long, url string")
    truth = dict((i, t) for i, _, t in labels)
    tokens = {r.page_id: frozenset(r.t) for r in uf.split_url(pages).select("page_id", uf.token_column().alias("t")).collect()}
    support, total = {}, {}
    for i, t in tokens.items():
        if i in truth:
            for k in range(1, 5):
                for c in itertools.combinations(sorted(t), k):
                    total[c] = total.get(c, 0) + 1
                    support[c] = support.get(c, 0) + truth[i]
    rules = {c: support[c] / total[c] for c in total if support[c] >= 20 and support[c] / total[c] >= 0.8}
    rules = {c: p for c, p in rules.items() if not any(set(d) < set(c) and q >= p for d, q in rules.items())}
    df = uf.split_url(pages).withColumn("tokens", uf.token_column())
    ldf = spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    got = {tuple(sorted(r.tokens)): r.confidence for r in uf.mined_rules(df.join(ldf, df.page_id == ldf.doc_id).selectExpr("tokens", "toxic = 1 as bad")).collect()}
    assert got == rules and rules
    verdicts = {r.page_id: r.verdict for r in uf.url_verdicts(pages, ldf).collect()}
    assert verdicts == {i: "block" if any(set(c) <= t for c in rules) else "allow" for i, t in tokens.items()}
    assert sum(v == "block" for v in verdicts.values()) > 100

from spark_nlops.llm import url_rules as U


def slow(url, rules, default="allow"):
    if url is None or "://" not in url:
        return "", "", None, default
    rest = url.split("://", 1)[1]
    end = min([i for i in map(rest.find, "/?#") if i >= 0], default=len(rest))
    host, path = "".join(c.lower() if c.isascii() else c for c in rest[:end]), rest[end:].split("?")[0].split("#")[0]
    fit = [(len(h + p), v == "block", h + p, v) for h, p, v in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
    best = max(fit, default=(0, 0, None, default))
    return host, path, best[2], best[3]


URLS = [None, "", "nothing", "http://", "https://COM/", "http://example.com", "http://example.com/en/", "http://www.Example.com/en/x?y#z", "http://a.www.example.com/en/x",
        "http://badexample.com/en/x", "http://example.com.evil.net/fr/x", "ftp://net/es/?q=://x", "x://com-x/", "http://a..com/", "http://x.net?x=/es/", "http://ÄB.com/en/://y", "http://user@b.example.com:80/en/"]


def test_rules_against_brute_force(spark):
    rules = U.RULES + [("a.b.c.example.com", "/", "block"), ("b.example.com:80", "/en", "block"), ("example.com", "/en/x", "block"), ("example.com", "", "allow")]
    urls = URLS + [f"http://{h}{p}" for h in ("a.b.c.example.com", "z.a.b.c.example.com", "b.c.example.com", "example.net") for p in ("", "/", "/en/x", "/es/")]
    df = spark.createDataFrame([(i, u, "h", 7) for i, u in enumerate(urls)] + [(None, urls[5], "h", 7)] * 2, "page_id long, url string, host string, sweep int")
    got = {r.page_id: tuple(r)[1:] for r in U.judge_urls(df, U.rule_frame(spark, rules)).collect()}
    for i, u in enumerate(urls):
        assert got[i] == slow(u, rules), u
    assert U.judge_urls(df, U.rule_frame(spark, rules)).count() == len(urls) + 2
    assert U.judge_urls(df.limit(0), U.rule_frame(spark, rules)).count() == 0


def test_no_rules(spark):
    df = spark.createDataFrame([(1, "http://a.com/x")], "page_id long, url string")
    rows = U.judge_urls(df, U.rule_frame(spark, U.RULES).limit(0)).collect()
    assert tuple(rows[0]) == (1, "a.com", "/x", None, "allow")


def test_sweeps_follow_rows_and_rules(spark, monkeypatch):
    assert U.sweep_count(0, 5, 8) == 1
    assert U.sweep_count(64_000, 5, 8) == 8
    assert U.sweep_count(10**12, 5, 200) == -(-(10**12) // U.SWEEP_ROWS)
    # copies of borders never outnumber an eighth of the pages, but for one sweep's
    assert U.sweep_count(10**12, 10**7, 200) * 2 * 10**7 <= 10**12 // 8 + 2 * 10**7
    rules = [(f"h{i}.example.com", f"/{i % 3}", "block" if i % 2 else "allow") for i in range(300)] + U.RULES
    urls = URLS + [f"http://a.h{i * 7}.example.com/{i % 4}/x" for i in range(40)] + ["http://x.net/es/1"] * 30
    df = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    for rows, a_border in ((1 << 20, 8), (5, 0)):  # one sweep for the borders' sake; more sweeps than the session has partitions
        monkeypatch.setattr(U, "SWEEP_ROWS", rows)
        monkeypatch.setattr(U, "ROWS_A_BORDER", a_border)
        got = {r.page_id: tuple(r)[1:] for r in U.judge_urls(df, U.rule_frame(spark, rules)).collect()}
        assert got == {i: slow(u, rules) for i, u in enumerate(urls)}

"""License scan and URL filter."""

import re

from tupleshare.llm import license_scan, url_filter


def plain_words(text):
    low = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    return [re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", x) for x in low.split("\n")]


def plain_scan(text):
    lines = plain_words(text)
    words = [w for x in lines for w in x]
    places = {label: [i for i in range(len(words)) if words[i : i + len(p.split())] == p.split()] for p, label in license_scan.PHRASES}
    flat = sorted(i for x in places.values() for i in x)
    base = sorted(k for k, x in places.items() if x)
    more, best = set(base), 0.0
    blocks = []
    for k, x in enumerate(lines):  # windows of neighbouring lines, to the end of the paragraph
        if x:
            window = lines[k : k + license_scan.SPAN]
            blocks.append({w for y in window[: window.index([]) if [] in window else None] for w in y})
    for label, t in license_scan.TEMPLATES:
        t = set(t.split())
        telling = license_scan.TELLING.get(label)
        for x in blocks:
            c = len(t & x) / len(t)
            if c >= 0.8 - 1e-9 and (telling not in t or telling in x):
                more.add(label)
                best = max(best, c)
    return len(words), len(flat), flat[0] if flat else None, flat[-1] if flat else None, ",".join(base), ",".join(sorted(more)), 1.0 if flat else best


TEXTS = [
    None, "", "\n \t", "CC BY", "cc-by cc by\nALL RIGHTS\nreserved", "Licensed under the Apache License, Version 2.0.", "licensed under apache license version 2", "x " * 30000 + "all rights reserved",
    "Released under the MIT License. Released under the MIT License.", "É cc bÝ, cc by é", "General Public\x00License general public license", "under the license", "This work is licensed under the GNU General Public License, version 3.",
]


def test_license_scan_equals_plain(spark):
    rows = [(i, t) for i, t in enumerate(TEXTS)] + [(3, TEXTS[3]), (None, TEXTS[5])]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "'b' AS blocks", "1 AS words", "2 AS `row`", "3 AS id").repartition(3)
    got = sorted((tuple(r) for r in license_scan.scan_licenses(df).collect()), key=repr)
    assert got == sorted(((i, *plain_scan(t)) for i, t in rows), key=repr)
    assert license_scan.scan_licenses(df.limit(0)).count() == 0


def plain_judge(url):
    low = "".join(c.lower() if "A" <= c <= "Z" else c for c in url or "")
    m = re.match(r"(?s).*?://([^/?#]*)([^?#]*)", url or "")
    host, path = ("".join(c.lower() if "A" <= c <= "Z" else c for c in m[1]), m[2]) if m else ("", "")
    fits = []
    for r in url_filter.HOST_RULES:
        h, _, p = r.name.partition("/")
        if (host == h or host.endswith("." + h)) and path.startswith("/" + p):
            fits.append((len(r.name), r.name, r.verdict))
    if fits:
        return host, path, max(fits)[1], max(fits)[2]
    hits = [(len(r.regex), r.regex, r.verdict) for r in url_filter.PATTERN_RULES if re.search(r.regex, low)]
    return host, path, None, max(hits)[2] if hits else "allow"


URLS = [
    None, "", "no scheme", "http://org", "http://ORG/", "https://a.example.org/es/1", "http://example.org/ES/1", "http://example.org/en/12?x#y", "http://example.org/en/2", "http://notexample.org/es/", "http://x.com/fr/9",
    "http://x.com/de/", "http://x.com/de", "http://com/de/", "ftp://a.net/casino/", "http://a.net/x?page=512", "http://x.com:80/de/", "a://b://c.org/x", "http://ads.z.example.net/", "http://é.org/ü", "http://a.net/wp-admin", "://org/",
]


def test_urls_equal_plain(spark):
    rows = [(i, u) for i, u in enumerate(URLS)] + [(4, URLS[4]), (None, URLS[5])]
    df = spark.createDataFrame(rows, "page_id long, url string").selectExpr("*", "'h' AS host", "'t' AS token", "1 AS id", "2 AS `row`", "'r' AS rule").repartition(3)
    rules = url_filter.HOST_RULES + url_filter.PATTERN_RULES
    got = sorted((tuple(r) for r in url_filter.judge_urls(df, rules).collect()), key=repr)
    assert got == sorted(((i, *plain_judge(u)) for i, u in rows), key=repr)
    assert url_filter.judge_urls(df.limit(0), rules).count() == 0


def test_rules_without_literals_are_always_checked(spark):
    urls = spark.createDataFrame([(1, "http://a.example.net/xyz"), (2, "http://a.example.net/abc"), (3, None)], "page_id long, url string")
    judged = url_filter.judge_urls(urls, [*url_filter.HOST_RULES, url_filter.pattern_rule("block", "xyz")])
    assert {r.page_id: r.verdict for r in judged.collect()} == {1: "block", 2: "allow", 3: "allow"}

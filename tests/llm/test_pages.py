"""Operators on web pages."""

import re

import numpy as np
import pytest

from ordering_engine.llm import host_reputation, html_text

PAGES = [
    (1, "https://WWW.Example.org/es/x?q=1", "<p>Hello <b>big</b>\n world</p>", "x"),
    (2, "http://a.example.org/en/1", None, "x"),
    (3, None, "", "x"),
    (4, "no scheme", "<nav>menu</nav>", "x"),
    (5, "https://shop.com/fr/a#b", "<article><h1>T &amp; U</h1><p>one<p>two</article><footer>f</footer>", "x"),
    (6, "https://shop.com/de/a", "<div class='comments'><p>c</p></div>", "x"),
    (7, "https://shop.com", "<script>var t='</p>';</script><p>ok", "x"),
    (7, "https://shop.com", "<script>var t='</p>';</script><p>ok", "x"),
    (None, "ftp://u@h.co.uk:21/p://q", "plain", "x"),
]


@pytest.fixture(scope="module")
def pages(spark):
    return spark.createDataFrame(PAGES, "page_id bigint, url string, html string, verdict string")


def plain_host(url):
    rest = (url or "").partition("://")[2] if "://" in (url or "") else ""
    host = re.split(r"[/?#]", rest, maxsplit=1)[0]
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in host), re.split(r"[?#]", rest[len(host) :], maxsplit=1)[0]


def plain_rule(host, path):
    fits = [(h + p, v) for h, p, v in host_reputation.RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
    return max(fits, key=lambda r: len(r[0]), default=(None, None))


def test_rules_hosts_and_paths(spark, pages, small):
    for table in (pages, spark.read.parquet(f"{small}/pages.parquet")):
        got = host_reputation.judge(table).collect()
        urls = {r.page_id: r.url for r in table.collect()}
        assert len(got) == table.count()
        for r in got:
            host, path = plain_host(urls[r.page_id])
            rule, verdict = plain_rule(host, path)
            assert (r.host, r.path, r.rule) == (host, path, rule)
            assert r.verdict in ("allow", "block") and (verdict is None or r.verdict == verdict)
    assert host_reputation.judge(pages.where("page_id < 0")).count() == 0


def test_reputation_is_shrunk_and_bounded(spark):
    labels = [(f"http://bad.com/{i}", 1) for i in range(60)] + [(f"http://good.com/{i}", 0) for i in range(60)] + [("http://once.net/", 1)]
    pages = spark.createDataFrame([(k, f"http://{h}/") for k, h in enumerate(["bad.com", "new.bad.com", "good.com", "once.net", "unknown.info"])], "page_id bigint, url string")
    got = {r.host: r for r in host_reputation.judge(pages, rules=(), labels=spark.createDataFrame(labels, "url string, bad int")).collect()}
    assert got["bad.com"].verdict == "block" and got["new.bad.com"].bad_low > got["good.com"].bad_low
    assert [got[h].verdict for h in ("good.com", "once.net", "unknown.info")] == ["allow"] * 3
    empty = host_reputation.judge(pages, rules=(), labels=spark.createDataFrame([], "url string, bad int")).collect()
    assert {r.verdict for r in empty} == {"allow"}


def plain_posteriors(counts, strength=8.0, most=1000.0):
    """(a, b) per host from {host: (n, bad)}, level by level in plain Python."""
    domain = lambda h: ".".join(h.split(".")[-2:])
    suffix = lambda h: h.split(".")[-1]

    def summed(level, up):
        out = {}
        for key, (n, bad) in level.items():
            was = out.get(up(key), (0, 0))
            out[up(key)] = (was[0] + n, was[1] + bad)
        return out

    def shrunk(level, up, parents):
        q = s0 = s1 = 0.0
        for key, (n, bad) in level.items():
            a, b = parents[up(key)]
            mean = a / (a + b)
            if n:
                q, s0, s1 = q + n * (bad / n - mean) ** 2, s0 + mean * (1 - mean), s1 + mean * (1 - mean) * (n - 1)
        m = strength if s1 <= 0 else most if q <= s0 else min(max(s1 / (q - s0) - 1, strength), most)
        means = {key: (lambda a, b: a / (a + b))(*parents[up(key)]) for key in level}
        return {key: (means[key] * m + bad, (1 - means[key]) * m + n - bad) for key, (n, bad) in level.items()}

    domains = summed(counts, domain)
    suffixes = summed(domains, suffix)
    n, bad = (sum(v[k] for v in suffixes.values()) for k in (0, 1))
    top = {"": (bad + 1.0, n - bad + 1.0)}
    return shrunk(counts, domain, shrunk(domains, suffix, shrunk(suffixes, lambda s: "", top))), (bad + 1) / (n + 2)


def plain_quantile(a, b, q):
    u = np.linspace(-60, 60, 400_001)
    w = -a * np.logaddexp(0, -u) - b * np.logaddexp(0, u)
    total = np.cumsum(np.exp(w - w.max()))
    return 1 / (1 + np.exp(-u[np.searchsorted(total, q * total[-1])]))


def test_verdicts_of_unruled_pages_follow_the_posteriors(spark, small):
    """Against plain Python; a filter without reputation (all allowed, or all blocked) fails here."""
    rng = np.random.default_rng(2)
    rates = {f"{kind}{k}.{tld}": rate for kind, rate in (("bad", 0.9), ("mixed", 0.3), ("good", 0.02)) for k in range(6) for tld in ("com", "net", "io")}
    labels = [(f"http://www.{h}/{i}", int(rng.random() < rate)) for h, rate in rates.items() for i in range(int(rng.integers(1, 60)))]
    counts = {}
    for url, bad in labels:
        host = plain_host(url)[0]
        counts[host] = (counts.get(host, (0, 0))[0] + 1, counts.get(host, (0, 0))[1] + bad)
    hosts = [*counts, "new.bad0.com", "never.seen.io", "other.tld"]
    want, rate = plain_posteriors(counts | dict.fromkeys(hosts[-3:], (0, 0)))
    pages = spark.createDataFrame([(k, f"https://{h}/x") for k, h in enumerate(hosts)], "page_id bigint, url string")
    got = host_reputation.judge(pages, rules=(), labels=spark.createDataFrame(labels, "url string, bad int")).collect()
    for r in got:
        low = plain_quantile(*want[r.host], 0.05)
        assert abs(r.bad_low - low) < 2e-3 and (r.verdict == "block") == (r.bad_low > rate), r
    verdict = {r.host: r.verdict for r in got}
    assert {v for h, v in verdict.items() if "good" in h} == {"allow"} and sum(v == "block" for h, v in verdict.items() if "bad" in h) > 12
    table = spark.read.parquet("/root/testdata/sf0.1/pages.parquet")
    free = [r for r in host_reputation.judge(table).collect() if r.rule is None]
    assert {r.verdict for r in free} == {"allow", "block"} and len({(r.host, r.verdict) for r in free}) == len({r.host for r in free})


def test_reputation_plan_has_no_python(pages):
    plan = host_reputation.judge(pages)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan


def test_main_text_of_pages(spark, small):
    table = spark.read.parquet(f"{small}/pages.parquet")
    html = {r.page_id: r.html for r in table.collect()}
    import html as entities

    for r in html_text.extract(table).collect():
        inner = re.search("<article>(.*)</article>", html[r.page_id], re.S)[1]
        blocks = (" ".join(entities.unescape(re.sub("<[^>]*>", "", b.replace("<br>", " "))).split()) for b in re.split("</?(?:p|h1)>", inner))
        assert r.text == "\n".join(b for b in blocks if b) and r.n_chars == len(r.text)


def test_main_text_of_awkward_pages(pages):
    got = {r.page_id: r.text for r in html_text.extract(pages).collect()}
    assert got[1] == "Hello big world" and got[2] == got[3] == got[4] == got[6] == ""
    assert got[5] == "T & U\none\ntwo" and got[7] == "ok" and got[None] == "plain"
    assert html_text.extract(pages.where("page_id < 0")).count() == 0


@pytest.mark.parametrize("part", ["<nav><a href=x>Menu item</a></nav>", "<header><h1>Site name</h1></header>", "<footer>Imprint</footer>", "<aside>Side</aside>", "<div class='sidebar'><p>Side text</p></div>", "<div id='cookie-notice'>We use cookies</div>", "<div class='ad'>Buy now</div>",
    "<form><label>Mail</label><input></form>", "<script>x()</script>", "<style>p{}</style>", "<section class='comments'><p>Reader comment that is as long as a paragraph of the article itself, or longer.</p></section>", "<!-- a comment -->"])
def test_parts_that_are_dropped(part):
    text = "<p>A paragraph of the article that goes on for a while, as paragraphs do.</p><p>Short.</p><p>Another paragraph of the article, also of a decent length, to end it.</p>"
    want = re.sub("</p><p>", "\n", text)[3:-4]
    for page in (f"<html><body>{part}<article>{text}</article></body>", f"<body><article>{text}</article>{part}", f"<body><main>{part}{text}</main>", f"<div class='page has-sidebar'>{part}<div class='content'>{text}</div></div>"):
        assert html_text.main_text(page) == want, page


def test_all_clusters_and_all_articles_are_kept():
    line = "A sentence of the text that goes on for a while, as sentences of a text do, and then ends."
    body = "".join(f"<p>{line} {k}</p>" for k in range(12))
    kept = [f"{line} {k}" for k in range(12)]
    page = f"<body><ul><li><a href=x>Other page</a></li></ul><div id=c><h1>The title</h1><p>Intro. {line}</p><div class=body>{body}</div><p>Closing. {line}</p></div>"
    assert html_text.main_text(page).split("\n") == ["The title", f"Intro. {line}", *kept, f"Closing. {line}"]
    two = f"<body><article>{body}</article><article><p>Second. {line}</p>{body[: len(body) * 2 // 3]}</article>"
    got = html_text.main_text(two).split("\n")
    assert got[:13] == [*kept, f"Second. {line}"] and len(got) > 18


def unnamed(page):
    """The page with containers that tell nothing: every sectioning element a div, no class, id or role."""
    return re.sub(r"<(/?)(article|main|nav|footer|header|aside|section|form)\b", r"<\1div", re.sub(r' (?:class|id|role)=(?:"[^"]*"|\'[^\']*\'|[^ >]*)', "", page))


def test_clusters_find_the_text_without_any_names(spark):
    table = spark.read.parquet("/root/testdata/sf0.1/pages.parquet").select("html").limit(600).collect()
    same = sum(html_text.main_text(unnamed(r.html)) == html_text.main_text(r.html) for r in table)
    assert same >= 0.95 * len(table)


def test_clusters_decide(monkeypatch):
    """The result follows from the ratios: with every line called content, short lines around the text come along."""
    line = "A sentence of the text that goes on for a while, as sentences of a text do, and then ends."
    body = "".join(f"<p>{line} {k}</p>" for k in range(8))
    page = f"<body>Home<br><b><i>News</i></b><hr><i>Today</i><hr><div><h1>Title</h1>{body}<p>End.</p></div><hr><b><i>Up</i></b><hr><b>Mail</b></body>"
    want = ["Title", *(f"{line} {k}" for k in range(8)), "End."]
    assert html_text.main_text(page).split("\n") == want
    monkeypatch.setattr(html_text, "clusters", lambda lines, sigma: np.ones(len(lines), bool))
    assert html_text.main_text(page).split("\n") != want


def test_pages_take_time_in_proportion():
    import time

    for page in ("<div>a" * 8000, "<p>a" * 20000 + "<ul>" + "<li>x" * 20000 + "</b>" * 20000, "<div class=x><span>" * 8000 + "end", "a" * 2_000_000, "<b>a</b> " * 100_000):
        began = time.perf_counter()
        assert html_text.main_text(page)
        assert time.perf_counter() - began < 2

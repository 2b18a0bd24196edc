import math
from collections import Counter, defaultdict

from roadweave.llm import urls


def split(url):
    if not url or "://" not in url:
        return "", ""
    rest = url.split("://", 1)[1]
    cut = min([i for i in (rest.find(c) for c in "/?#") if i >= 0], default=len(rest))
    path = rest[cut:]
    path = path[: min([i for i in (path.find(c) for c in "?#") if i >= 0], default=len(path))]
    return "".join(c.lower() if c.isascii() else c for c in rest[:cut]), path


def rule(host, path):
    fits = [(h + p, v) for h, p, v in urls.RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
    return max(fits, key=lambda x: len(x[0]), default=(None, None))


def text(url):
    plain = "".join("0" if c in "0123456789" else c if "\x21" <= c <= "\x7e" else "~" for c in (url or "").lower())
    return " " * urls.ORDER + plain + " "


def grams(t):
    return [t[i : i + urls.ORDER + 1] for i in range(len(t) - urls.ORDER)]


def models(ruled, every):
    counts = {v: Counter(g for u, says in ruled if says == v for g in grams(text(u))) for v in ("allow", "block")}

    def log_p(v, gram):
        p = 1 / urls.ALPHABET
        for k in range(urls.ORDER + 1):
            low = defaultdict(int)
            for g, c in counts[v].items():
                low[g[urls.ORDER - k :]] += c
            own = gram[urls.ORDER - k :]
            of = [c for g, c in low.items() if g[:k] == own[:k]]
            if of:
                p = (low.get(own, 0) + len(of) * p) / (sum(of) + len(of))
        return math.log(p)

    return {g: log_p("allow", g) - log_p("block", g) for g in every}


def test_against_brute_force(spark):
    pages = spark.read.parquet("/root/testdata/sf0.001/pages.parquet").limit(50).select("page_id", "url")
    odd = [(-1, None), (-2, ""), (-3, "no scheme/net/es/"), (-4, "HTTP://WWW.Example.COM/en/x?y#z"), (-5, "a://example.com/EN/"), (-6, "a://b.net/es/1"), (-7, "a://net"), (-7, "a://net"), (None, "x://é.org://q"), (-8, "x://example.com?/en/")]
    pages = pages.unionByName(spark.createDataFrame(odd, pages.schema)).cache()
    rows = urls.judge(pages).collect()
    source = [(r["page_id"], r["url"]) for r in pages.collect()]
    assert len(rows) == len(source)
    expected = {}
    ruled = [(u, rule(*split(u))[1]) for _, u in source]
    # Grams that no ruled URL has back off to shorter contexts; a score is divided by all characters.
    every = {g for _, u in source for g in grams(text(u))}
    assert len(every) > len({g for u, says in ruled if says for g in grams(text(u))})
    table = models([x for x in ruled if x[1]], every)
    scores = {u: sum(table[g] for g in grams(text(u))) / len(grams(text(u))) for _, u in source}
    by = {v: [scores[u] for u, says in ruled if says == v] for v in ("allow", "block")}
    mean = {v: sum(x) / len(x) for v, x in by.items()}
    sd = {v: math.sqrt(sum((a - mean[v]) ** 2 for a in x) / len(x)) for v, x in by.items()}
    cut = (mean["allow"] * sd["block"] + mean["block"] * sd["allow"]) / (sd["allow"] + sd["block"])
    for i, u in source:
        host, path = split(u)
        name, says = rule(host, path)
        expected.setdefault(i, set()).add((host, path, name, says or ("allow" if scores[u] >= cut else "block")))
    for r in rows:
        assert abs(r["cut"] - cut) < 1e-6
        assert (r["host"], r["path"], r["rule"], r["verdict"]) in expected[r["page_id"]], r


def test_empty_tables_and_no_rules(spark):
    empty = spark.createDataFrame([], "page_id long, url string, verdict string, row_id int")
    assert urls.judge(empty).count() == 0
    some = spark.createDataFrame([(1, "http://a.org/x"), (2, None)], "page_id long, url string")
    assert {r["verdict"] for r in urls.judge(some).collect()} == {"allow"}


def test_plan_has_no_python(spark):
    table = spark.createDataFrame([(1, "http://a.com/x")], "page_id long, url string")
    assert "Python" not in urls.judge(table)._jdf.queryExecution().toString()
